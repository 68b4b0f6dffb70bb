"""The parameter server as a stream: gradients arrive as rows, state closes iterations.

State is keyed and bounded: an open iteration holds at most its quorum, a closed one a flag until its time to live
ends.  The provider of ``transformWithState`` is RocksDB, a setting that a session takes at run time.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import fields

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..sources.sinks import checkpoint_run, load_run, versions
from ..train.gradient import quorum_gradient

ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


class QuorumServer(StatefulProcessor):
    """Per iteration: the first N gradients in order of arrival are used, later ones are dropped by their tag and counted."""

    def __init__(self, quorum: int, ttl_ms: int | None = None):
        self.quorum, self.ttl_ms = quorum, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        schema = "n int, dropped int, step_time double"
        self.count = handle.getValueState("count", schema, self.ttl_ms) if self.ttl_ms else handle.getValueState("count", schema)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        n, dropped, step_time = self.count.get() if self.count.exists() else (0, 0, 0.0)
        pdf = pd.concat(list(rows)).sort_values(["arrival", "worker"])
        used = pdf.iloc[: max(0, self.quorum - n)]
        n, dropped = n + len(used), dropped + len(pdf) - len(used)
        if len(used):
            step_time = float(used["arrival"].iloc[-1])
        self.count.update((n, dropped, step_time))
        if n >= self.quorum:  # closed now, or a late gradient more
            yield pd.DataFrame({"iteration": [int(key[0])], "step_time": [step_time], "n_used": [n], "n_dropped": [dropped]})

    def close(self) -> None:
        pass


def streaming_quorum(gradients: DataFrame, quorum: int, ttl_ms: int | None = None) -> DataFrame:
    """(iteration, step_time, n_used, n_dropped) as iterations close, and again for each batch with late gradients of one,
    from a stream of (iteration, worker, arrival).  The row of the most dropped gradients is an iteration's last.

    With ``ttl_ms`` closed iterations leave the state after that time; the clock then keeps the stream alive, so a
    stream that should end with its input (``availableNow``) goes without.
    """
    mode = "ProcessingTime" if ttl_ms else "None"
    return gradients.groupBy("iteration").transformWithStateInPandas(QuorumServer(quorum, ttl_ms), "iteration int, step_time double, n_used int, n_dropped int", outputMode="Update", timeMode=mode)


class ApplyCounter(StatefulProcessor):
    """Per server: version after each gradient and the lag of its worker."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.version = handle.getValueState("version", "v long")
        self.read = handle.getMapState("read", "worker int", "v long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        v = self.version.get()[0] if self.version.exists() else 0
        pdf = pd.concat(list(rows)).sort_values(["finish", "worker", "seq"], ignore_index=True)
        pdf["update"] = np.arange(v, v + len(pdf))
        # State is read and written once for each worker of a batch; in between, a worker's last update is in the batch.
        seen = {w: self.read.getValue((int(w),))[0] if self.read.containsKey((int(w),)) else 0 for w in pdf["worker"].unique()}
        before = pdf.groupby("worker")["update"].shift() + 1
        read = before.fillna(pdf["worker"].map(seen)).astype("int64")
        for worker, update in pdf.groupby("worker")["update"].max().items():
            self.read.updateValue((int(worker),), (int(update) + 1,))
        self.version.update((v + len(pdf),))
        yield pd.DataFrame({"shard": np.int32(key[0]), "update": pdf["update"], "worker": pdf["worker"], "seq": pdf["seq"], "read_version": read, "lag": pdf["update"] - read})

    def close(self) -> None:
        pass


def streaming_async(gradients: DataFrame) -> DataFrame:
    """(shard, update, worker, seq, read_version, lag) from a stream of (shard, worker, seq, finish) in order of finish."""
    return gradients.groupBy("shard").transformWithStateInPandas(ApplyCounter(), "shard int, update long, worker int, seq long, read_version long, lag long", outputMode="Append", timeMode="None")


def deadline_windows(stream: DataFrame, width: str = "1 hour", late: str = "30 minutes") -> DataFrame:
    """Steps that close by event time: gradients later than the watermark are dropped (in append mode; complete output
    keeps every window open)."""
    rows = stream.withWatermark("ts", late).groupBy(F.window("ts", width))
    return rows.agg(F.count("*").alias("n_used"), F.sum("micro").alias("sum_micro")).select(F.unix_micros("window.start").alias("start_us"), "n_used", "sum_micro")


def monitor(stream: DataFrame, window, late: str = "30 minutes") -> DataFrame:
    """Arrivals per worker group and window: count, total and slowest, in micro-units so that sums are exact."""
    rows = stream.withWatermark("ts", late).groupBy(window.alias("w"), "event_type")
    return rows.agg(F.count("*").alias("n"), F.sum("micro").alias("sum_micro"), F.max("micro").alias("max_micro")).select(F.unix_micros("w.start").alias("start_us"), F.unix_micros("w.end").alias("end_us"), "event_type", "n", "sum_micro", "max_micro")


def deduplicated(stream: DataFrame, late: str = "1 day") -> DataFrame:
    """Gradients that were sent again, within the watermark, count once."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_hosts(stream: DataFrame, hosts: DataFrame) -> DataFrame:
    """Stream-static join."""
    return stream.join(hosts, "event_type")


def read_with_apply(reads: DataFrame, applies: DataFrame, within: str = "1 hour", late: str = "30 minutes") -> DataFrame:
    """Stream-stream join: each read with the applies of its user in the time after it."""
    r, a = reads.withWatermark("ts", late).alias("r"), applies.withWatermark("ts", late).alias("a")
    near = F.expr(f"a.user_id = r.user_id AND a.ts > r.ts AND a.ts <= r.ts + INTERVAL {within}")
    return r.join(a, near).select(F.col("r.event_id").alias("read_id"), F.col("a.event_id").alias("apply_id"))


def run_to_table(spark: SparkSession, stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and return its output; append mode writes Parquet, others the last state.

    Complete and update outputs go through ``foreachBatch`` into one folder per batch: idempotent when a batch is run again.
    """
    writer = stream.writeStream.option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).outputMode(mode)
    if mode == "append":
        query = writer.format("parquet").option("path", f"{path}/out").start()
    else:
        query = writer.foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{path}/out/batch={n:09d}")).start()
    query.awaitTermination()
    out = spark.read.schema(stream.schema).parquet(f"{path}/out").select(*stream.columns)
    if mode == "complete":
        last = spark.read.parquet(f"{path}/out").agg(F.max("batch")).first()[0]
        out = spark.read.schema(stream.schema).parquet(f"{path}/out/batch={last:09d}")
    return out


class OnlineTrainer:
    """Training in ``foreachBatch``: a micro-batch is an iteration.

    Parameters, rule and step are written to ``path`` after each batch under the batch's number, so a batch that is run
    again after a failure, by this driver or by the next one, starts from what the one before it left.
    """

    def __init__(self, model, rule_maker, theta, path: str):
        self.model, self.rule_maker, self.start, self.path = model, rule_maker, theta, path

    def __call__(self, batch: DataFrame, number: int) -> None:
        spark, rule, theta = batch.sparkSession, self.rule_maker(), self.start
        done = [v for v in versions(spark, self.path) if v <= number]
        if done:
            state = load_run(spark, self.path, done[-1])[1]
            theta = state.pop("theta")
            for name, value in state.items():
                setattr(rule, name, int(value) if name == "t" else value)
        rows = batch.select(F.lit(0).alias("iteration"), F.lit(0).alias("worker"), "x", "y")
        g, _, n = quorum_gradient(rows, self.model, 0, theta)
        theta = rule.step(theta, g) if n else theta
        kept = {f.name: getattr(rule, f.name) for f in fields(rule) if f.name != "rate"}
        checkpoint_run(spark, self.path, number + 1, {"theta": theta, **kept})

    def history(self, spark: SparkSession) -> list[tuple[int, np.ndarray]]:
        """(batch, parameters after it) of all batches."""
        return [(v - 1, load_run(spark, self.path, v)[1]["theta"]) for v in versions(spark, self.path)]
