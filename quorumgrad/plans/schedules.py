"""Schedule, staleness and trade-off queries with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..timing import asynchronous as asy
from ..timing import busy, tradeoff
from ..timing import trace as tr
from .common import SHAPED_SQL, events, rounded, trace, trace_sql

FLEET, QUORUM, SERVERS, TAU = 100, 94, 19, 2.0
KS = (1, 50, 90, 97, 98, 99, 100)
GRIDS = {"shaped": tuple(1.4 + 0.2 * i for i in range(16)), "raw": tuple(20.0 * i for i in range(1, 21))}
SPARES, HOSTS = tuple(range(13)), (1, 2, 4, 8)
OWN_KNOTS = ((50, 170.0), (70, 125.0), (80, 110.0), (90, 95.0), (100, 85.0))
LAYERS, NETWORK = 18, 0.3

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None, digits: int = 8):
    """Register a query, rounded at its end, and its SQL."""
    def put(f):
        QUERIES[name] = lambda spark, sf_dir: rounded(f(spark, sf_dir), digits)
        if sql:
            ORACLES[name] = sql
        return f

    return put


@query("arrival_trace", f"WITH {trace_sql()} SELECT iteration, worker, round(arrival, 8) AS arrival FROM t")
def _(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trace(spark, sf_dir)


@query("kth_arrival", f"WITH {trace_sql()} SELECT iteration, k, worker, round(arrival, 8) AS arrival FROM tk")
def _(spark, sf_dir):
    return tr.kth_arrival(trace(spark, sf_dir))


def _cdf_sql(shape: str) -> str:
    grid = ", ".join(f"({t!r}::DOUBLE)" for t in GRIDS[shape])
    return f"WITH {trace_sql(shape=shape)} SELECT k, t AS t, round(avg(CASE WHEN arrival <= t THEN 1.0 ELSE 0.0 END), 8) AS share FROM (SELECT iteration, k, arrival FROM tk WHERE k IN {KS}) CROSS JOIN (VALUES {grid}) AS g(t) GROUP BY k, t".replace("t AS t,", "round(t, 8) AS t,")


@query("arrival_cdf", _cdf_sql("shaped"))
def _(spark, sf_dir):
    return tr.arrival_cdf(trace(spark, sf_dir), KS, GRIDS["shaped"])


@query("arrival_cdf_raw", _cdf_sql("raw"))
def _(spark, sf_dir):
    return tr.arrival_cdf(trace(spark, sf_dir, shape="raw"), KS, GRIDS["raw"])


@query("arrival_profile", f"WITH {trace_sql()} SELECT k, round(avg(arrival), 8) AS mean_s, round(median(arrival), 8) AS median_s, round(max(arrival), 8) AS max_s FROM tk GROUP BY k")
def _(spark, sf_dir):
    return tr.arrival_profile(trace(spark, sf_dir))


_COPIES = f"""WITH {trace_sql()}, m AS (SELECT *, median(arrival) OVER (PARTITION BY iteration) AS mid, lead(arrival) OVER (PARTITION BY worker ORDER BY iteration) AS again FROM tk),
e AS (SELECT *, arrival > 1.5 * mid AND again IS NOT NULL AS slow, CASE WHEN arrival > 1.5 * mid AND again IS NOT NULL THEN least(arrival, 1.5 * mid + again) ELSE arrival END AS eff FROM m)
SELECT iteration, round(max(arrival), 8) AS full_s, round(max(eff), 8) AS speculation_s, round(max(arrival) FILTER (k <= {QUORUM}), 8) AS spares_s, count(*) FILTER (slow)::BIGINT AS copies FROM e GROUP BY 1"""


@query("speculation", _COPIES)
def _(spark, sf_dir):
    """Step times of waiting for all, of second copies for slow workers, and of spares."""
    return tr.speculation_steps(trace(spark, sf_dir), QUORUM)


@query("arrival_profile_sketch")
def _(spark, sf_dir):
    return tr.arrival_profile_sketch(trace(spark, sf_dir))


def _sync_sql(quorum: int) -> str:
    return f"""WITH {trace_sql()}, s AS (SELECT iteration, count(*) FILTER (k <= {quorum})::BIGINT AS n_used, count(*) FILTER (k > {quorum})::BIGINT AS n_dropped, max(arrival) FILTER (k <= {quorum}) AS step_time FROM tk GROUP BY iteration)
SELECT iteration, n_used, n_dropped, round(step_time, 8) AS step_time, round(sum(step_time) OVER (ORDER BY iteration), 8) AS clock FROM s"""


@query("sync_full", _sync_sql(FLEET))
def _(spark, sf_dir):
    return tr.sync_steps(trace(spark, sf_dir), FLEET)


@query("sync_spares", _sync_sql(QUORUM))
def _(spark, sf_dir):
    return tr.sync_steps(trace(spark, sf_dir), QUORUM)


_SHARDED = f"""WITH {trace_sql()}, j AS (SELECT iteration, worker, shard, arrival * (1 + ((worker * 31 + shard * 17 + iteration * 7) % 10) / 100) AS arrival FROM t CROSS JOIN range({SERVERS}) AS r(shard)),
q AS (SELECT iteration, shard, max(arrival) AS s FROM (SELECT *, row_number() OVER (PARTITION BY iteration, shard ORDER BY arrival, worker) AS k FROM j) WHERE k <= {QUORUM} GROUP BY iteration, shard),
m AS (SELECT iteration, max(s) AS step_time FROM q GROUP BY iteration) SELECT iteration, round(step_time, 8) AS step_time, round(sum(step_time) OVER (ORDER BY iteration), 8) AS clock FROM m"""


@query("sync_shard_quorum", _SHARDED)
def _(spark, sf_dir):
    return tr.shard_clock(trace(spark, sf_dir), QUORUM, SERVERS)


def _deadline_sql(target: int) -> str:
    return f"""WITH {trace_sql()}, u AS (SELECT *, k = 1 OR (arrival <= {TAU} AND k <= {target}) AS used FROM tk),
s AS (SELECT iteration, count(*) FILTER (used)::BIGINT AS n_used, CASE WHEN min(arrival) > {TAU} THEN min(arrival) WHEN count(*) FILTER (used) >= {target} THEN max(arrival) FILTER (used) ELSE {TAU}::DOUBLE END AS step_time FROM u GROUP BY iteration)
SELECT iteration, n_used, round(step_time, 8) AS step_time, round(sum(step_time) OVER (ORDER BY iteration), 8) AS clock FROM s"""


@query("deadline_schedule", _deadline_sql(FLEET))
def _(spark, sf_dir):
    return tr.deadline_steps(trace(spark, sf_dir), TAU)


@query("either_schedule", _deadline_sql(QUORUM))
def _(spark, sf_dir):
    return tr.deadline_steps(trace(spark, sf_dir), TAU, QUORUM)


@query("spares_ablation", f"WITH {trace_sql()} SELECT ({FLEET} - k)::INTEGER AS spares, round(avg(arrival), 8) AS mean_step_s, round(sum(arrival), 8) AS total_s FROM tk WHERE k >= {FLEET - 12} GROUP BY k")
def _(spark, sf_dir):
    return tr.spares_ablation(trace(spark, sf_dir), FLEET, SPARES)


@query("waste_report", f"""WITH {trace_sql()}, m AS (SELECT iteration, max(arrival) AS last, max(arrival) FILTER (k <= {QUORUM}) AS closed FROM tk GROUP BY iteration)
SELECT iteration, round(sum(last - arrival), 8) AS idle_s, round(max(last) - max(closed), 8) AS saved_s, round(avg(CASE WHEN k > {QUORUM} THEN 1.0 ELSE 0.0 END), 8) AS dropped_share FROM tk JOIN m USING (iteration) GROUP BY iteration""")
def _(spark, sf_dir):
    return tr.waste(trace(spark, sf_dir), QUORUM)


@query("merge_messages", f"""WITH {trace_sql()}, h AS (SELECT h::INTEGER AS workers_per_host, iteration, worker // h AS host, max(arrival) AS sent FROM t CROSS JOIN (VALUES (1), (2), (4), (8)) AS v(h) GROUP BY ALL)
SELECT workers_per_host, count(*)::BIGINT AS messages, round(avg(sent), 8) AS mean_sent_s FROM h GROUP BY workers_per_host""")
def _(spark, sf_dir):
    return tr.messages(trace(spark, sf_dir), HOSTS)


@query("busy_stragglers")
def _(spark, sf_dir):
    return busy.busy_schedule(trace(spark, sf_dir), [QUORUM, 96, FLEET])


# ---- asynchronous ----------------------------------------------------------------------------------------------

def _work_sql(workers: int, shape: str = "raw") -> str:
    value = SHAPED_SQL if shape == "shaped" else "value"
    return f"""w0 AS (SELECT (event_id % {workers})::INTEGER AS worker, event_id // {workers} AS seq, CAST({value} AS DECIMAL(18, 6)) AS duration FROM events),
w AS (SELECT * FROM w0 QUALIFY count(*) OVER (PARTITION BY seq) = {workers}),
c AS (SELECT *, sum(duration) OVER (PARTITION BY worker ORDER BY seq ROWS UNBOUNDED PRECEDING) AS finish FROM w),
u AS (SELECT worker, seq, duration::DOUBLE AS duration, finish::DOUBLE AS finish, (finish - duration)::DOUBLE AS start, row_number() OVER (ORDER BY finish, worker, seq) - 1 AS u FROM c),
a AS (SELECT *, coalesce(lag(u) OVER (PARTITION BY worker ORDER BY seq) + 1, 0) AS read_version FROM u)"""


LAG_SQL = "min(lag)::BIGINT AS min_lag, round(avg(lag), 8) AS mean_lag, round(quantile_cont(lag, 0.5)::DOUBLE, 8) AS median_lag, max(lag)::BIGINT AS max_lag, round(stddev_samp(lag), 8) AS sd_lag, count(*)::BIGINT AS n"


def _work(spark, sf_dir, workers, shape="raw"):
    return asy.work_trace(events(spark, sf_dir), workers, tr.SHAPES[shape])


@query("async_schedule", f"WITH {_work_sql(40)} SELECT u::BIGINT AS update, worker, seq::BIGINT AS seq, round(start, 8) AS start, round(finish, 8) AS finish, read_version::BIGINT AS read_version, (u - read_version)::BIGINT AS lag FROM a")
def _(spark, sf_dir):
    return asy.async_schedule(_work(spark, sf_dir, 40))


for _w in (8, 16, 40):

    @query(f"staleness_flat_{_w}", f"WITH {_work_sql(_w)}, l AS (SELECT u - read_version AS lag FROM a) SELECT {LAG_SQL} FROM l")
    def _(spark, sf_dir, workers=_w):
        return asy.lag_summary(asy.async_schedule(_work(spark, sf_dir, workers)))


def layer_table(spark: SparkSession, layers: int = LAYERS) -> DataFrame:
    """A stack of equal layers whose backward pass costs twice the forward one."""
    return spark.range(layers).select(F.col("id").cast("int").alias("layer"), F.lit(1.0).alias("fwd"), F.lit(2.0).alias("bwd"))


_LAYERED = f"""WITH {_work_sql(40, "shaped")}, o AS (SELECT i::INTEGER AS layer, {1 - NETWORK} * (i / {3.0 * LAYERS}) AS read_at, {1 - NETWORK} * (({LAYERS} + 2.0 * ({LAYERS} - i)) / {3.0 * LAYERS}) + {NETWORK} AS send_at FROM range({LAYERS}) AS r(i)),
e AS (SELECT min(last) AS until FROM (SELECT max(finish) AS last FROM u GROUP BY worker)),
p AS (SELECT layer, worker, seq, start + read_at * duration AS read, start + send_at * duration AS sent FROM u CROSS JOIN o CROSS JOIN e WHERE start + send_at * duration <= until),
n AS (SELECT *, row_number() OVER (PARTITION BY layer ORDER BY sent, worker, seq) AS place FROM p),
b AS (SELECT layer, sent, max(place) AS place FROM n GROUP BY layer, sent),
v AS (SELECT n.layer, n.place - 1 - coalesce(b.place, 0) AS lag FROM n ASOF LEFT JOIN b ON n.layer = b.layer AND n.read >= b.sent)
SELECT layer, {LAG_SQL} FROM v GROUP BY layer"""


@query("staleness_by_layer", _LAYERED)
def _(spark, sf_dir):
    return asy.lag_summary(asy.layered_lag(_work(spark, sf_dir, 40, "shaped"), asy.layer_offsets(layer_table(spark), NETWORK)), ["layer"])


@query("read_versions_per_shard", f"""WITH {_work_sql(16)}, r AS (SELECT worker, seq, s::INTEGER AS shard, start + s * 0.01 * duration AS tm FROM u CROSS JOIN range(4) AS x(s)),
f AS (SELECT tm, max(n) AS n FROM (SELECT finish AS tm, row_number() OVER (ORDER BY finish) AS n FROM u) GROUP BY tm)
SELECT r.worker, r.seq::BIGINT AS seq, r.shard, coalesce(f.n, 0)::BIGINT AS read_version FROM r ASOF LEFT JOIN f ON r.tm >= f.tm""")
def _(spark, sf_dir):
    return asy.shard_versions(_work(spark, sf_dir, 16), 4).select("worker", "seq", "shard", F.coalesce("read_version", F.lit(0)).cast("long").alias("read_version"))


@query("wave_plan")
def _(spark, sf_dir):
    """One row per wave.  The plan is made where the replay runs, from (update, version) pairs of one run."""
    pairs = asy.async_schedule(_work(spark, sf_dir, 40)).select("update", "read_version")

    def plan(pdf):
        pdf = pdf.sort_values("update")
        return pdf.assign(wave=asy.waves(pdf["read_version"].tolist()))[["wave", "update"]]

    waves = pairs.groupBy(F.lit(0).alias("run")).applyInPandas(lambda pdf: plan(pdf), "wave long, update long")
    return waves.groupBy("wave").agg(F.count("*").alias("updates"), F.min("update").alias("first_update"))


# ---- trade-off -------------------------------------------------------------------------------------------------

def _interp_sql(knots) -> str:
    values = ", ".join(f"({n}, {i}::DOUBLE)" for n, i in knots)
    return f"""kn AS (SELECT n AS a, i AS ia, lead(n) OVER (ORDER BY n) AS b, lead(i) OVER (ORDER BY n) AS ib FROM (VALUES {values}) AS v(n, i)),
ip AS (SELECT x::INTEGER AS n, ia + (ib - ia) * (x - a) / (b - a) AS iterations FROM range(50, 101) AS r(x) JOIN kn ON x >= a AND (x < b OR (x = b AND x = 100)) WHERE b IS NOT NULL)"""


def _estimate_sql(knots, shape="shaped") -> str:
    return f"""WITH {trace_sql(shape=shape)}, {_interp_sql(knots)}, m AS (SELECT k, avg(arrival) AS mean_s FROM tk GROUP BY k),
e AS (SELECT n, (100 - n)::INTEGER AS spares, iterations, mean_s, iterations * mean_s AS estimate_s FROM ip JOIN m ON n = k)"""


def _est(digits: int = 4) -> str:
    return f"SELECT n, spares, round(iterations, 8) AS iterations, round(mean_s, 8) AS mean_s, round(estimate_s, {digits}) AS estimate_s FROM e"


def _estimates(spark, sf_dir, knots, shape="shaped"):
    return tradeoff.time_to_converge(trace(spark, sf_dir, shape=shape), tradeoff.knots_frame(spark, knots), 50, FLEET)


@query("interp_iters", f"WITH {_interp_sql(OWN_KNOTS)} SELECT event_id, n, round(iterations, 8) AS iterations FROM events JOIN ip ON 50 + event_id % 51 = n")
def _(spark, sf_dir):
    """Iterations to converge at each event's quorum."""
    lines = tradeoff.interpolate(tradeoff.knots_frame(spark, OWN_KNOTS), 50, FLEET)
    return events(spark, sf_dir).join(F.broadcast(lines), F.col("event_id") % 51 + 50 == F.col("n")).select("event_id", "n", "iterations")


def _seconds(df, digits: int = 4):
    """Estimates rounded where no product of a mean and a knot ends in a five."""
    return df.withColumn("estimate_s", F.round("estimate_s", digits))


@query("time_estimate_pub", _estimate_sql(tradeoff.PUBLISHED_KNOTS) + _est())
def _(spark, sf_dir):
    return _seconds(_estimates(spark, sf_dir, tradeoff.PUBLISHED_KNOTS))


@query("time_estimate_own", _estimate_sql(OWN_KNOTS) + _est(3))
def _(spark, sf_dir):
    return _seconds(_estimates(spark, sf_dir, OWN_KNOTS), 3)


@query("best_split", _estimate_sql(tradeoff.PUBLISHED_KNOTS) + _est() + " ORDER BY e.estimate_s, n DESC LIMIT 1")
def _(spark, sf_dir):
    return _seconds(tradeoff.best_split(_estimates(spark, sf_dir, tradeoff.PUBLISHED_KNOTS)))


@query("best_split_raw", _estimate_sql(tradeoff.PUBLISHED_KNOTS, "raw") + _est() + " ORDER BY e.estimate_s, n DESC LIMIT 1")
def _(spark, sf_dir):
    return _seconds(tradeoff.best_split(_estimates(spark, sf_dir, tradeoff.PUBLISHED_KNOTS, "raw")))
