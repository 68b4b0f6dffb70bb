"""Streaming queries: ``events`` replayed as a stream of files; each equals its batch form in SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..models import LinearModel
from ..optim.rules import Sgd, constant
from ..sources.sinks import scratch_path
from ..sources.tables import read_table, stream_files
from ..streaming import servers as sv
from ..timing import asynchronous as asy
from ..timing import trace as tr
from .common import events, rounded, trace, trace_sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None, digits: int = 8):
    def put(f):
        QUERIES[name] = lambda spark, sf_dir: rounded(f(spark, sf_dir), digits)
        if sql:
            ORACLES[name] = sql
        return f

    return put


def replayed(spark: SparkSession, df: DataFrame, order: str, files: int = 4, per_trigger: int = 2) -> DataFrame:
    """``df`` written as files of consecutive ``order``, one after another, and read again as a stream in that order."""
    path = scratch_path(spark, "stream-in")
    cuts = df.approxQuantile(order, [i / files for i in range(1, files)], 0.001)
    for low, high in zip([None, *cuts], [*cuts, None], strict=True):
        part = df if low is None else df.where(F.col(order) > low)
        part = part if high is None else part.where(F.col(order) <= high)
        part.coalesce(1).write.mode("append").parquet(path)
    return stream_files(spark, path, df.schema, per_trigger)


def event_stream(spark, sf_dir, again: bool = False) -> DataFrame:
    """Events with a session-zone timestamp and the value in micro-units; ``again`` sends a third of them twice."""
    e = read_table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type", "value"])
    e = e.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", F.round(F.col("value") * 1e6).cast("long").alias("micro"))
    return replayed(spark, e.union(e.where("event_id % 3 = 0")) if again else e, "event_id")


def _rocks(spark):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", sv.ROCKSDB)


@query("stream_quorum", f"WITH {trace_sql()} SELECT iteration, round(max(arrival) FILTER (k <= 94), 8) AS step_time, 94::INTEGER AS n_used, count(*) FILTER (k > 94)::INTEGER AS n_dropped FROM tk GROUP BY iteration")
def _(spark, sf_dir):
    """Files are cut by arrival, so the stream sees gradients in the order of time."""
    _rocks(spark)
    stream = replayed(spark, trace(spark, sf_dir), "arrival")
    rows = sv.run_to_table(spark, sv.streaming_quorum(stream, 94), scratch_path(spark, "stream"), "update")
    return rows.groupBy("iteration").agg(F.max("step_time").alias("step_time"), F.max("n_used").alias("n_used"), F.max("n_dropped").alias("n_dropped"))


@query("stream_async", """WITH w0 AS (SELECT (event_id % 8)::INTEGER AS worker, event_id // 8 AS seq, CAST(value AS DECIMAL(18, 6)) AS d FROM events), w AS (SELECT * FROM w0 QUALIFY count(*) OVER (PARTITION BY seq) = 8),
c AS (SELECT *, sum(d) OVER (PARTITION BY worker ORDER BY seq ROWS UNBOUNDED PRECEDING) AS f FROM w), u AS (SELECT *, row_number() OVER (ORDER BY f, worker, seq) - 1 AS u FROM c)
SELECT shard::INTEGER AS shard, u::BIGINT AS update, worker, seq::BIGINT AS seq, coalesce(lag(u) OVER w + 1, 0)::BIGINT AS read_version, (u - coalesce(lag(u) OVER w + 1, 0))::BIGINT AS lag FROM u, range(4) AS s(shard) WINDOW w AS (PARTITION BY shard, worker ORDER BY seq)""")
def _(spark, sf_dir):
    """Every gradient goes to four servers, each a key of its own with its own versions."""
    _rocks(spark)
    shard, path = F.explode(F.sequence(F.lit(0), F.lit(3))).alias("shard"), scratch_path(spark, "clocks")
    asy.worker_clocks(asy.work_trace(events(spark, sf_dir), 8, tr.raw)).select("worker", "seq", "finish").write.parquet(path)
    gradients = replayed(spark, spark.read.parquet(path), "finish", per_trigger=1).select(shard, "worker", "seq", "finish")
    return sv.run_to_table(spark, sv.streaming_async(gradients), scratch_path(spark, "stream"))


_MICRO = "round(value * 1e6)::BIGINT"


@query("stream_deadline", f"WITH e AS (SELECT (epoch_us(ts) // 3600000000) * 3600000000 AS start_us, {_MICRO} AS micro FROM events) SELECT start_us::BIGINT AS start_us, count(*)::BIGINT AS n_used, sum(micro)::BIGINT AS sum_micro FROM e GROUP BY 1")
def _(spark, sf_dir):
    """Steps of an hour; complete output, so that no step waits for the watermark."""
    return sv.run_to_table(spark, sv.deadline_windows(event_stream(spark, sf_dir)), scratch_path(spark, "stream"), "complete")


_LATE = f"""WITH e AS (SELECT event_id % 20 = 0 AS late, event_id % 20 < 19 AS early, epoch_us(ts) AS us, (epoch_us(ts) // 3600000000) * 3600000000 AS start_us, {_MICRO} AS micro FROM events),
m AS (SELECT max(us) FILTER (early AND NOT late) - 1800000000 AS first, max(us) - 1800000000 AS last FROM e)
SELECT start_us::BIGINT AS start_us, count(*)::BIGINT AS n_used, sum(micro)::BIGINT AS sum_micro FROM e, m WHERE NOT late OR start_us + 3600000000 > first GROUP BY start_us, last HAVING start_us + 3600000000 <= last"""


@query("stream_deadline_late", _LATE)
def _(spark, sf_dir):
    """Append output: a step is final once the watermark has passed it.

    Every twentieth gradient comes after all others and is dropped where its step was closed by the batch before; the
    batch between lets the first one's watermark take effect.
    """
    e = read_table(spark, sf_dir, "events", ["event_id", "ts", "value"])
    e = e.select("event_id", F.col("ts").cast("timestamp").alias("ts"), F.round(F.col("value") * 1e6).cast("long").alias("micro"))
    path = scratch_path(spark, "stream-in")
    rest = F.col("event_id") % 20
    for part in ((rest > 0) & (rest < 19), rest == 19, rest == 0):
        e.where(part).coalesce(1).write.mode("append").parquet(path)
    return sv.run_to_table(spark, sv.deadline_windows(stream_files(spark, path, e.schema, 1)), scratch_path(spark, "stream"))


def _window_sql(width: int, slide: int) -> str:
    n = width // slide
    return f"""WITH e AS (SELECT epoch_us(ts) AS us, event_type, {_MICRO} AS micro FROM events), s AS (SELECT ((us // {slide}) - i) * {slide} AS start_us, event_type, micro FROM e, range({n}) r(i))
SELECT start_us::BIGINT AS start_us, (start_us + {width})::BIGINT AS end_us, event_type, count(*)::BIGINT AS n, sum(micro)::BIGINT AS sum_micro, max(micro) AS max_micro FROM s GROUP BY ALL"""


@query("stream_tumbling", _window_sql(3_600_000_000, 3_600_000_000))
def _(spark, sf_dir):
    return sv.run_to_table(spark, sv.monitor(event_stream(spark, sf_dir), F.window("ts", "1 hour")), scratch_path(spark, "stream"), "complete")


@query("stream_sliding", _window_sql(7_200_000_000, 1_800_000_000))
def _(spark, sf_dir):
    return sv.run_to_table(spark, sv.monitor(event_stream(spark, sf_dir), F.window("ts", "2 hours", "30 minutes")), scratch_path(spark, "stream"), "complete")


@query("stream_session", f"""WITH e AS (SELECT epoch_us(ts) AS us, event_type, {_MICRO} AS micro FROM events), g AS (SELECT *, CASE WHEN us - lag(us) OVER w < 7200000000 THEN 0 ELSE 1 END AS fresh FROM e WINDOW w AS (PARTITION BY event_type ORDER BY us)),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY event_type ORDER BY us ROWS UNBOUNDED PRECEDING) AS n FROM g) SELECT min(us)::BIGINT AS start_us, (max(us) + 7200000000)::BIGINT AS end_us, event_type, count(*)::BIGINT AS n, sum(micro)::BIGINT AS sum_micro, max(micro) AS max_micro FROM s GROUP BY event_type, s.n""")
def _(spark, sf_dir):
    return sv.run_to_table(spark, sv.monitor(event_stream(spark, sf_dir), F.session_window("ts", "2 hours")), scratch_path(spark, "stream"), "complete")


@query("stream_dedup", f"SELECT event_id, {_MICRO} AS micro FROM events")
def _(spark, sf_dir):
    return sv.run_to_table(spark, sv.deduplicated(event_stream(spark, sf_dir, again=True)).select("event_id", "micro"), scratch_path(spark, "stream"))


@query("stream_join", "SELECT r.event_id AS read_id, a.event_id AS apply_id FROM events r JOIN events a ON a.user_id = r.user_id AND a.ts > r.ts AND a.ts <= r.ts + INTERVAL 1 HOUR AND r.event_id % 2 = 0 AND a.event_id % 2 = 1")
def _(spark, sf_dir):
    """Even events are reads, odd ones applies; order of files is order of time, so the watermark drops none."""
    stream = event_stream(spark, sf_dir)
    other = event_stream(spark, sf_dir)
    joined = sv.read_with_apply(stream.where("event_id % 2 = 0"), other.where("event_id % 2 = 1"))
    return sv.run_to_table(spark, joined, scratch_path(spark, "stream"))


@query("stream_static_join", "SELECT event_id, CASE WHEN event_type < 'm' THEN 'first' ELSE 'second' END AS host FROM events")
def _(spark, sf_dir):
    kinds = read_table(spark, sf_dir, "events", ["event_type"]).distinct().withColumn("host", F.when(F.col("event_type") < "m", "first").otherwise("second"))
    return sv.run_to_table(spark, sv.with_hosts(event_stream(spark, sf_dir), kinds).select("event_id", "host"), scratch_path(spark, "stream"))


@query("stream_online_training")
def _(spark, sf_dir):
    """A micro-batch is an iteration: value from hour of day, one step each."""
    stream = event_stream(spark, sf_dir).select(F.array(F.lit(1.0), F.hour("ts") / 24).alias("x"), (F.col("micro") / 1e8).alias("y"))
    path = scratch_path(spark, "stream")
    trainer = sv.OnlineTrainer(LinearModel(2), lambda: Sgd(constant(0.3)), np.zeros(2), f"{path}-states")
    stream.writeStream.option("checkpointLocation", path).trigger(availableNow=True).foreachBatch(trainer).start().awaitTermination()
    return spark.createDataFrame([(k, float(t[0]), float(t[1])) for k, t in trainer.history(spark)], "batch int, theta0 double, theta1 double")
