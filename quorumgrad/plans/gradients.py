"""Losses, gradients, sampling and few-step training, with SQL that repeats the arithmetic step by step."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import FleetConfig, TrainConfig
from ..functions.hashing import bernoulli, draws, slot_layout, split_name
from ..models import LinearModel
from ..models import expressions as ex
from ..models.exact import normal_sums
from ..optim.rules import AdaGrad, Adam, Momentum, RmsProp, Rule, Sgd, constant, exponential
from ..optim.wide import touched, wide_step
from ..sources.tables import read_table
from ..timing import asynchronous as asy
from ..timing import trace as tr
from ..train import distributed as td
from .common import events, rounded, trace, trace_sql

FEATURES, THETA = ("x1", "x2", "x3"), (0.5, -0.25, 0.125)
WORKERS, QUORUM, STEPS, RATE, DECAY, EMA = 10, 8, 5, 0.3, 0.9, 0.9

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None, digits: int = 6):
    def put(f):
        QUERIES[name] = lambda spark, sf_dir: rounded(f(spark, sf_dir), digits)
        if sql:
            ORACLES[name] = sql
        return f

    return put


def net_task(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Net price from price, discount and tax: near linear, so the optimum is known.  Slots make 5 iterations of 10 workers."""
    rows = wide_slots(spark, sf_dir, STEPS * WORKERS)
    return rows.select(F.expr(f"CAST(slot DIV {WORKERS} AS INT)").alias("iteration"), (F.col("slot") % WORKERS).cast("int").alias("worker"), *FEATURES, "y")


NET_SQL = f"""s AS (SELECT (l_orderkey * 31 + l_partkey * 17 + l_suppkey * 7 + l_linenumber) % {STEPS * WORKERS} AS slot, l_extendedprice / 50000 AS x1, l_discount * 10 AS x2, l_tax * 10 AS x3,
l_extendedprice * (1 - l_discount) * (1 + l_tax) / 50000 AS y FROM lineitem), b AS (SELECT (slot // {WORKERS})::INTEGER AS iteration, (slot % {WORKERS})::INTEGER AS worker, x1, x2, x3, y FROM s)"""
_ERR = " + ".join(f"({t}::DOUBLE) * {f}" for f, t in zip(FEATURES, THETA, strict=True)) + " - y"
_Z = " + ".join(f"({t}::DOUBLE) * {f}" for f, t in zip(FEATURES, THETA, strict=True))
_LABEL = "CASE WHEN y > 0.5 THEN 1 ELSE 0 END"


@query("loss_linear", f"WITH {NET_SQL} SELECT round(avg(0.5 * pow({_ERR}, 2)), 6) AS loss FROM b")
def _(spark, sf_dir):
    return net_task(spark, sf_dir).agg(ex.linear_loss(FEATURES, THETA, "y").alias("loss"))


@query("loss_logistic", f"WITH {NET_SQL}, z AS (SELECT {_Z} AS z, {_LABEL} AS l FROM b) SELECT round(avg(greatest(z, 0) + ln(1 + exp(-abs(z))) - l * z), 6) AS loss FROM z")
def _(spark, sf_dir):
    df = net_task(spark, sf_dir).withColumn("l", (F.col("y") > 0.5).cast("int"))
    return df.agg(ex.logistic_loss(FEATURES, THETA, "l").alias("loss"))


THETAS3 = ((0.5, -0.25, 0.125), (-0.5, 0.25, 0.0), (0.25, 0.0, -0.125))


@query("loss_softmax", f"WITH {NET_SQL}, z AS (SELECT " + ", ".join(" + ".join(f"({t}::DOUBLE) * {f}" for f, t in zip(FEATURES, th, strict=True)) + f" AS z{i}" for i, th in enumerate(THETAS3)) + ", CASE WHEN y > 1 THEN 2 WHEN y > 0.5 THEN 1 ELSE 0 END AS l FROM b) SELECT round(avg(ln(exp(z0) + exp(z1) + exp(z2)) - CASE l WHEN 0 THEN z0 WHEN 1 THEN z1 ELSE z2 END), 6) AS loss FROM z")
def _(spark, sf_dir):
    df = net_task(spark, sf_dir).withColumn("l", F.when(F.col("y") > 1, 2).when(F.col("y") > 0.5, 1).otherwise(0))
    return df.agg(ex.softmax_loss(FEATURES, THETAS3, "l").alias("loss"))


@query("grad_linear", f"WITH {NET_SQL}, e AS (SELECT *, {_ERR} AS e FROM b) SELECT round(avg(e * x1), 6) AS g0, round(avg(e * x2), 6) AS g1, round(avg(e * x3), 6) AS g2 FROM e")
def _(spark, sf_dir):
    return net_task(spark, sf_dir).agg(*ex.linear_gradient(FEATURES, THETA, "y"))


@query("grad_logistic", f"WITH {NET_SQL}, e AS (SELECT *, 1 / (1 + exp(-({_Z}))) - {_LABEL} AS e FROM b) SELECT round(avg(e * x1), 6) AS g0, round(avg(e * x2), 6) AS g1, round(avg(e * x3), 6) AS g2 FROM e")
def _(spark, sf_dir):
    df = net_task(spark, sf_dir).withColumn("l", (F.col("y") > 0.5).cast("int"))
    return df.agg(*ex.logistic_gradient(FEATURES, THETA, "l"))


def folded_sql(n: int, name: str = "f") -> str:
    return f"{name} AS (SELECT event_id % {n} AS event_id, CAST(sum(CAST(value AS DECIMAL(18, 6))) AS DOUBLE) / count(*) AS value FROM events GROUP BY 1)"


def folded(spark, sf_dir, n: int) -> DataFrame:
    """The whole event table as ``n`` events: each stands for all whose id leaves it as the rest, with their mean value.

    Slots hold many rounds of work each when a run has few steps, so the time of a slot's gradient is that of all its
    rounds; their sum in fixed point does not hang on its order.
    """
    rows = events(spark, sf_dir).groupBy((F.col("event_id") % n).alias("event_id"))
    return rows.agg((F.sum(F.col("value").cast("decimal(18,6)")).cast("double") / F.count("*")).alias("value"))


_TRACE10 = f"{folded_sql(STEPS * WORKERS)}, k AS (SELECT (event_id // {WORKERS})::INTEGER AS iteration, (event_id % {WORKERS})::INTEGER AS worker, value AS arrival, row_number() OVER (PARTITION BY event_id // {WORKERS} ORDER BY value, event_id) AS k FROM f)"


def raw_trace(spark, sf_dir) -> DataFrame:
    """Arrivals of the few steps, from the whole event table."""
    return tr.arrival_trace(folded(spark, sf_dir, STEPS * WORKERS), WORKERS, "raw")


@query("quorum_gradient", f"WITH {NET_SQL}, {_TRACE10}, e AS (SELECT *, {_ERR} AS e FROM b JOIN k USING (iteration, worker) WHERE k <= {QUORUM}), w AS (SELECT iteration, worker, avg(e * x1) AS g0, avg(e * x2) AS g1, avg(e * x3) AS g2 FROM e GROUP BY ALL) SELECT iteration, round(avg(g0), 6) AS g0, round(avg(g1), 6) AS g1, round(avg(g2), 6) AS g2, count(*)::BIGINT AS n_workers FROM w GROUP BY iteration")
def _(spark, sf_dir):
    used = net_task(spark, sf_dir).join(tr.winners(raw_trace(spark, sf_dir), QUORUM), ["iteration", "worker"], "left_semi")
    return ex.two_level(used, ["iteration"], "worker", ex.linear_gradient(FEATURES, THETA, "y"))


@query("grad_variance", f"WITH {NET_SQL}, e AS (SELECT *, {_ERR} AS e FROM b), w AS (SELECT iteration, worker, avg(e * x1) AS g FROM e GROUP BY ALL), n AS (SELECT unnest([1, 2, 5, 10]) AS n), q AS (SELECT n, iteration, worker // n AS grp, avg(g) AS g FROM w CROSS JOIN n GROUP BY ALL) SELECT n::INTEGER AS n, round(var_samp(g) * 1000, 6) AS var_x1000 FROM q GROUP BY n", 6)
def _(spark, sf_dir):
    """Variance of the mean of n workers' gradients: falls as n grows."""
    per = net_task(spark, sf_dir).groupBy("iteration", "worker").agg(F.avg(ex.linear_error(FEATURES, THETA, "y") * F.col("x1")).alias("g"))
    groups = per.withColumn("n", F.explode(F.array(*map(F.lit, (1, 2, 5, 10))))).groupBy("n", "iteration", F.floor(F.col("worker") / F.col("n"))).agg(F.avg("g").alias("g"))
    return groups.groupBy("n").agg((F.var_samp("g") * 1000).alias("var_x1000"))


@query("normal_equations", f"WITH {NET_SQL} SELECT " + ", ".join(f"round(sum(x{i + 1} * x{j + 1}), 4) AS xx_{i}_{j}" for i in range(3) for j in range(i, 3)) + ", " + ", ".join(f"round(sum(x{i + 1} * y), 4) AS xy_{i}" for i in range(3)) + ", count(*)::BIGINT AS n FROM b", 4)
def _(spark, sf_dir):
    return normal_sums(net_task(spark, sf_dir), list(FEATURES), "y")


# ---- sampling --------------------------------------------------------------------------------------------------

_H = "('0x' || substr(md5({}), 1, 8))::BIGINT"


@query("split_counts", f"WITH h AS (SELECT {_H.format('doc_id::VARCHAR')} / 4294967296.0 AS h FROM documents) SELECT CASE WHEN h < 0.7 THEN 'train' WHEN h < 0.85 THEN 'validation' ELSE 'test' END AS split, count(*)::BIGINT AS n FROM h GROUP BY 1")
def _(spark, sf_dir):
    docs = read_table(spark, sf_dir, "documents", ["doc_id"])
    return docs.groupBy(split_name(F.col("doc_id")).alias("split")).agg(F.count("*").alias("n"))


_DRAWS = _H.format("concat_ws(':', 7, event_id // 80, event_id // 8 % 10, event_id % 8)")


@query("draws", f"SELECT (event_id // 80)::INTEGER AS iteration, (event_id // 8 % 10)::INTEGER AS worker, (event_id % 8)::INTEGER AS pos, {_DRAWS} % 500 AS row_index FROM events")
def _(spark, sf_dir):
    """Events number the draws: 8 of each of 10 workers in an iteration."""
    return draws(read_table(spark, sf_dir, "events", ["event_id"]), "event_id", 10, 8, 500, seed=7)


_SLOT = _H.format("concat_ws(':', 3, vec_id)") + " % 16"


@query("slot_layout", f"SELECT vec_id, ({_SLOT})::INTEGER AS slot FROM embeddings")
def _(spark, sf_dir):
    return slot_layout(read_table(spark, sf_dir, "embeddings", ["vec_id"]), "vec_id", 16, epoch=3)


@query("batch_histogram", f"SELECT ({_SLOT})::INTEGER AS slot, count(*)::BIGINT AS n FROM embeddings GROUP BY 1")
def _(spark, sf_dir):
    return slot_layout(read_table(spark, sf_dir, "embeddings", ["vec_id"]), "vec_id", 16, epoch=3).groupBy("slot").agg(F.count("*").alias("n"))


_BERNOULLI = _H.format("concat_ws(':', 5, t, vec_id)") + " < 85899345"


@query("bernoulli_batches", f"SELECT t::INTEGER AS iteration, count(*)::BIGINT AS n, sum(vec_id)::BIGINT AS ids FROM embeddings, range(20) AS s(t) WHERE {_BERNOULLI} GROUP BY 1")
def _(spark, sf_dir):
    """Batches in which every row is with probability 0.02, whatever the other rows: their sizes vary."""
    rows = bernoulli(read_table(spark, sf_dir, "embeddings", ["vec_id"]), "vec_id", 20, 0.02, seed=5)
    return rows.groupBy("iteration").agg(F.count("*").alias("n"), F.sum("vec_id").alias("ids"))


# ---- few-step training -----------------------------------------------------------------------------------------

def vectors(df: DataFrame) -> DataFrame:
    return df.select("iteration", "worker", F.array(*FEATURES).alias("x"), "y")


def steps_frame(spark: SparkSession, run: td.Trained, averages: bool = True) -> DataFrame:
    """(step, coord, theta, theta_avg): parameters after each step, the average as it was fed before that step."""
    rows = []
    for t, theta in enumerate(run.history[1:], 1):
        avg = run.averages[t] if averages and run.averages else theta
        rows += [(t, i, float(v), float(a)) for i, (v, a) in enumerate(zip(theta, avg, strict=True))]
    return spark.createDataFrame(rows, "step int, coord int, theta double, theta_avg double")


def _fmt(x: float) -> str:
    return f"({x!r}::DOUBLE)"


def unrolled_sql(rows: str, steps: int, rule: str = "sgd", rate: float = RATE, decay: float = DECAY, read=None, ema: float = EMA, averaged: bool = True) -> str:
    """Training as chained table expressions over ``rows`` (iteration, worker, x1, x2, x3, y): per step the mean over
    workers of each worker's mean, then the rule.  ``read[t]`` is the version that step t's gradient is computed at."""
    d, parts = range(3), [NET_SQL, rows]
    slot = {"sgd": "", "momentum": "v", "adagrad": "s", "rmsprop": "s", "adam": "mv"}[rule]
    start = [f"0::DOUBLE AS {n}{i}" for n in "ta" + slot for i in d]
    parts.append("p0 AS (SELECT " + ", ".join(start) + ")")
    for t in range(steps):
        v = t if read is None else read[t]
        err = " + ".join(f"q.t{i} * x{i + 1}" for i in d) + " - y"
        parts.append(f"g{t} AS (SELECT " + ", ".join(f"avg(w{i}) AS g{i}" for i in d) + " FROM (SELECT worker, " + ", ".join(f"avg(({err}) * x{i + 1}) AS w{i}" for i in d) + f" FROM r, p{v} q WHERE iteration = {t} GROUP BY worker))")
        lr, cols = _fmt(rate * decay**t), []
        for i in d:
            g = f"g{i}"
            if rule == "sgd":
                move = g
            elif rule == "momentum":
                move = f"(0.9::DOUBLE * v{i} + {g})"
                cols.append(f"{move} AS v{i}")
            elif rule == "adagrad":
                cols.append(f"s{i} + {g} * {g} AS s{i}")
                move = f"{g} / (sqrt(s{i} + {g} * {g}) + 1e-8)"
            elif rule == "rmsprop":
                s = f"(0.9::DOUBLE * s{i} + {_fmt(1 - 0.9)} * {g} * {g})"
                cols.append(f"{s} AS s{i}")
                move = f"{g} / (sqrt({s}) + 1e-8)"
            else:
                m, s = f"(0.9::DOUBLE * m{i} + {_fmt(1 - 0.9)} * {g})", f"(0.999::DOUBLE * v{i} + {_fmt(1 - 0.999)} * {g} * {g})"
                cols += [f"{m} AS m{i}", f"{s} AS v{i}"]
                move = f"({m} / {_fmt(1 - 0.9 ** (t + 1))}) / (sqrt({s} / {_fmt(1 - 0.999 ** (t + 1))}) + 1e-8)"
            cols.append(f"t{i} - {lr} * ({move}) AS t{i}")
            cols.append(f"t{i} AS a{i}" if t == 0 else f"{_fmt(ema)} * a{i} + {_fmt(1 - ema)} * t{i} AS a{i}")
        parts.append(f"p{t + 1} AS (SELECT " + ", ".join(cols) + f" FROM p{t}, g{t})")
    a = "a" if averaged else "t"
    out = " UNION ALL ".join(f"SELECT {t}::INTEGER AS step, {i}::INTEGER AS coord, round(t{i}, 6) AS theta, round({a}{i}, 6) AS theta_avg FROM p{t}" for t in range(1, steps + 1) for i in d)
    return "WITH " + ",\n".join(parts) + "\n" + out


_ALL = "r AS (SELECT * FROM b)"
_ONE = "r AS (SELECT iteration, 0 AS worker, x1, x2, x3, y FROM b)"
_USED = f"{_TRACE10}, r AS (SELECT b.* FROM b JOIN k USING (iteration, worker) WHERE k <= {QUORUM})"
_TIMED = f"{_TRACE10}, r AS (SELECT b.* FROM b JOIN k USING (iteration, worker) WHERE k = 1 OR arrival <= (SELECT avg(arrival) FROM k))"


def _run(spark, sf_dir, rule, winners=None, one=False, ema: float = EMA) -> DataFrame:
    rows = net_task(spark, sf_dir)
    rows = vectors(rows.withColumn("worker", F.lit(0)) if one else rows)
    return steps_frame(spark, td.train_sync(rows, winners, LinearModel(3), rule, STEPS, ema=ema))


def _fleet(spark, sf_dir, rule, averages: bool = True, shards: int = 1, **settings) -> DataFrame:
    """Five steps of the ten workers, closed as the settings say."""
    config = TrainConfig(FleetConfig(QUORUM, WORKERS - QUORUM, shards), STEPS, **{"ema_decay": EMA} | settings)
    return steps_frame(spark, td.train_fleet(config, vectors(net_task(spark, sf_dir)), raw_trace(spark, sf_dir), LinearModel(3), rule), averages)


def _rate():
    return exponential(RATE, DECAY)


@query("serial_sgd_5", unrolled_sql(_ONE, STEPS))
def _(spark, sf_dir):
    return _run(spark, sf_dir, Sgd(_rate()), one=True)


@query("minibatch_sgd_5", unrolled_sql("r AS (SELECT iteration, 0 AS worker, x1, x2, x3, y FROM b WHERE worker = 0)", STEPS))
def _(spark, sf_dir):
    """One worker of the fleet alone: mini-batches of its own slot."""
    only_first = raw_trace(spark, sf_dir).where("worker = 0").select("iteration", "worker")
    return _run(spark, sf_dir, Sgd(_rate()), winners=only_first)


@query("sync_sgd_5", unrolled_sql(_ALL, STEPS))
def _(spark, sf_dir):
    return _run(spark, sf_dir, Sgd(_rate()))


@query("sync_spares_sgd_5", unrolled_sql(_USED, STEPS))
def _(spark, sf_dir):
    return _fleet(spark, sf_dir, lambda: Sgd(_rate()))


@query("deadline_sgd_5", unrolled_sql(_TIMED, STEPS))
def _(spark, sf_dir):
    """Steps close at the mean arrival."""
    tau = raw_trace(spark, sf_dir).agg(F.avg("arrival")).first()[0]
    return _fleet(spark, sf_dir, lambda: Sgd(_rate()), close="deadline", deadline=tau)


@query("busy_sgd_5")
def _(spark, sf_dir):
    """Stragglers stay busy with the step they missed; what they send for it is dropped by its tag."""
    return _fleet(spark, sf_dir, lambda: Sgd(_rate()), straggler="busy")


@query("local_merge_sgd_5", unrolled_sql(_USED, STEPS))
def _(spark, sf_dir):
    return _fleet(spark, sf_dir, lambda: Sgd(_rate()), merge_hosts=4)


@query("ema_5", unrolled_sql(_USED, STEPS, ema=0.5))
def _(spark, sf_dir):
    return _fleet(spark, sf_dir, lambda: Sgd(_rate()), ema_decay=0.5)


for _name, _rule, _lr in (("momentum", Momentum, 0.1), ("adagrad", AdaGrad, 0.3), ("rmsprop", RmsProp, 0.1), ("adam", Adam, 0.1)):

    @query(f"{_name}_5", unrolled_sql(_USED, STEPS, _name, _lr))
    def _(spark, sf_dir, rule=_rule, lr=_lr):
        return _fleet(spark, sf_dir, lambda: rule(exponential(lr, DECAY)))


UPDATES = 6


def updates_task(spark, sf_dir) -> DataFrame:
    """Every row in the slot of one of the updates."""
    rows = net_task(spark, sf_dir).withColumn("iteration", (F.col("iteration") * WORKERS + F.col("worker")) % UPDATES)
    return vectors(rows.withColumn("worker", F.lit(0)))


_SLOTS = f"r AS (SELECT (iteration * {WORKERS} + worker) % {UPDATES} AS iteration, 0 AS worker, x1, x2, x3, y FROM b)"


@query("stale_sgd_6", unrolled_sql(_SLOTS, UPDATES, read=[max(0, t - 2) for t in range(UPDATES)], averaged=False))
def _(spark, sf_dir):
    run = td.train_async(updates_task(spark, sf_dir), td.stale_schedule(UPDATES, lambda u: 2), LinearModel(3), Sgd(_rate()), EMA)
    return steps_frame(spark, run, averages=False)


def _async_sql() -> str:
    """The version of each update depends on the arrivals: all versions are candidates, the right one is picked by a join."""
    d, n = range(3), UPDATES
    parts = [NET_SQL, _SLOTS, folded_sql(18), "w AS (SELECT event_id % 3 AS worker, event_id // 3 AS seq, CAST(value AS DECIMAL(18, 6)) AS d FROM f)", "c AS (SELECT *, sum(d) OVER (PARTITION BY worker ORDER BY seq ROWS UNBOUNDED PRECEDING) AS f FROM w)", "u AS (SELECT *, row_number() OVER (ORDER BY f, worker, seq) - 1 AS u FROM c)", "a AS (SELECT u, coalesce(lag(u) OVER (PARTITION BY worker ORDER BY seq) + 1, 0) AS v FROM u)", "h0 AS (SELECT 0 AS v, 0::DOUBLE AS t0, 0::DOUBLE AS t1, 0::DOUBLE AS t2)"]
    for t in range(n):
        err = " + ".join(f"q.t{i} * x{i + 1}" for i in d) + " - y"
        parts.append(f"g{t} AS (SELECT " + ", ".join(f"avg(({err}) * x{i + 1}) AS g{i}" for i in d) + f" FROM r, (SELECT h.* FROM h{t} h JOIN a ON a.v = h.v WHERE a.u = {t}) q WHERE iteration = {t})")
        parts.append(f"h{t + 1} AS (SELECT * FROM h{t} UNION ALL SELECT {t + 1}, " + ", ".join(f"h.t{i} - {_fmt(RATE * DECAY**t)} * g{i}" for i in d) + f" FROM h{t} h, g{t} WHERE h.v = {t})")
    out = " UNION ALL ".join(f"SELECT v::INTEGER AS step, {i}::INTEGER AS coord, round(t{i}, 6) AS theta, round(t{i}, 6) AS theta_avg FROM h{n} WHERE v > 0" for i in d)
    return "WITH " + ",\n".join(parts) + "\n" + out


@query("async_sgd_6", _async_sql())
def _(spark, sf_dir):
    work = asy.work_trace(folded(spark, sf_dir, 18), 3, tr.raw)
    plan = asy.async_schedule(work).where(F.col("update") < UPDATES).select("update", "read_version").orderBy("update").collect()
    run = td.train_async(updates_task(spark, sf_dir), [(r[0], r[0], r[1]) for r in plan], LinearModel(3), Sgd(_rate()), EMA)
    return steps_frame(spark, run, averages=False)


@query("async_waves_sgd")
def _(spark, sf_dir):
    """Two hundred asynchronous updates of 40 workers over all rows, a job per wave: loss over all rows at every 20th."""
    return async_waves(spark, sf_dir)


def async_waves(spark: SparkSession, sf_dir: str, workers: int = 40, updates: int = 200, every: int = 20, rate: float = 0.01) -> DataFrame:
    """(update, clock, lag, loss): the whole event table as the trace, the whole item table dealt into a slot per update."""
    work = asy.work_trace(folded(spark, sf_dir, updates), workers, tr.raw)
    plan = asy.async_schedule(work).select("update", "read_version", "finish").orderBy("update").collect()
    rows = vectors(wide_slots(spark, sf_dir, updates).select(F.col("slot").alias("iteration"), F.lit(0).alias("worker"), *FEATURES, "y"))
    run = td.train_async(rows, [(r[0], r[0], r[1]) for r in plan], LinearModel(3), Sgd(constant(rate)), EMA)
    marks = [0, *range(every, len(plan) + 1, every)]
    losses = losses_at(rows, [run.history[m] for m in marks])
    data = [(m, plan[m - 1].finish if m else 0.0, int(plan[m - 1][0] - plan[m - 1][1]) if m else 0, float(x)) for m, x in zip(marks, losses, strict=True)]
    return spark.createDataFrame(data, "update int, clock double, lag int, loss double")


def wide_slots(spark, sf_dir, n: int) -> DataFrame:
    """The net-price task with a slot in 0..n-1 for every row."""
    li = read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice", "l_discount", "l_tax"])
    slot = F.pmod(F.col("l_orderkey") * 31 + F.col("l_partkey") * 17 + F.col("l_suppkey") * 7 + F.col("l_linenumber"), F.lit(n)).cast("int")
    net = F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))
    return li.select(slot.alias("slot"), (F.col("l_extendedprice") / 50000).alias("x1"), (F.col("l_discount") * 10).alias("x2"), (F.col("l_tax") * 10).alias("x3"), (net / 50000).alias("y"))


def losses_at(rows: DataFrame, thetas: list) -> list[float]:
    """Mean squared-error loss over all rows at each of some parameter vectors, in one pass."""
    error = lambda th: sum((F.lit(float(v)) * F.col("x")[i] for i, v in enumerate(th)), F.lit(0.0)) - F.col("y")
    return list(rows.agg(*[F.avg(0.5 * F.pow(error(th), F.lit(2.0))).alias(f"l{k}") for k, th in enumerate(thetas)]).first())


@query("async_mixed_sgd_6")
def _(spark, sf_dir):
    """Asynchronous updates whose two slices are read at different versions."""
    work = asy.work_trace(folded(spark, sf_dir, 18), 3, tr.raw)
    order = asy.async_schedule(work).where(F.col("update") < UPDATES).select("worker", "seq", "update")
    reads = asy.shard_versions(work, 2, step=0.5).join(order, ["worker", "seq"]).groupBy("update").agg(F.array_sort(F.collect_list(F.struct("shard", F.coalesce("read_version", F.lit(0)).alias("v")))).alias("v")).orderBy("update").collect()
    plan = [(r.update, r.update, tuple(min(int(x.v), r.update) for x in r.v)) for r in reads]
    run = td.train_async(updates_task(spark, sf_dir), plan, LinearModel(3), Sgd(_rate()), EMA, slices=[slice(0, 2), slice(2, 3)])
    return steps_frame(spark, run, averages=False)


@query("async_layered_sgd_6")
def _(spark, sf_dir):
    """Asynchronous updates of a two-layer model: the top layer is read later and sent sooner than the bottom one."""
    from ..models import MlpModel

    model = MlpModel((3, 4), 2)
    work = asy.work_trace(folded(spark, sf_dir, 18), 3, tr.raw)
    layers = spark.createDataFrame([(0, 1.0, 2.0), (1, 1.0, 2.0)], "layer int, fwd double, bwd double")
    order = asy.async_schedule(work).select("worker", "seq", "update")
    lags = asy.layered_lag(work, asy.layer_offsets(layers, 0.1)).join(order, ["worker", "seq"]).where(F.col("update") < UPDATES)
    rows = lags.groupBy("update").agg(F.array_sort(F.collect_list(F.struct("layer", "lag"))).alias("v")).orderBy("update").collect()
    # Updates past the end of the first trace have no lag; they read the newest version.
    known = {r.update: [int(x.lag) for x in r.v] for r in rows if len(r.v) == 2}
    plan = [(u, u, tuple(max(0, u - lag) for lag in known.get(u, [0, 0]))) for u in range(UPDATES)]
    task = updates_task(spark, sf_dir).withColumn("y", (F.col("y") > 0.5).cast("double"))
    return steps_frame(spark, td.train_async(task, plan, model, Sgd(_rate()), EMA, slices=model.layers()), averages=False)


def _shard_sql() -> str:
    """A server's slice is one coordinate here: each moves by the mean over its own quorum of the workers' whole gradients."""
    d, parts = range(3), [NET_SQL, _TRACE10, f"j AS (SELECT iteration, worker, s AS shard, row_number() OVER (PARTITION BY iteration, s ORDER BY arrival * (1 + ((worker * 31 + s * 17 + iteration * 7) % 10) / 100), worker) AS k FROM k, range(3) AS x(s))", "p0 AS (SELECT 0::DOUBLE AS t0, 0::DOUBLE AS t1, 0::DOUBLE AS t2)"]
    for t in range(STEPS):
        err = " + ".join(f"q.t{i} * x{i + 1}" for i in d) + " - y"
        parts.append(f"w{t} AS (SELECT worker, " + ", ".join(f"avg(({err}) * x{i + 1}) AS g{i}" for i in d) + f" FROM b, p{t} q WHERE iteration = {t} GROUP BY worker)")
        move = ", ".join(f"(SELECT avg(g{i}) FROM w{t} JOIN j USING (worker) WHERE j.iteration = {t} AND shard = {i} AND k <= {QUORUM}) AS m{i}" for i in d)
        parts.append(f"p{t + 1} AS (SELECT " + ", ".join(f"t{i} - {_fmt(RATE * DECAY**t)} * coalesce(m{i}, 0) AS t{i}" for i in d) + f" FROM p{t}, (SELECT {move}))")
    out = " UNION ALL ".join(f"SELECT {t}::INTEGER AS step, {i}::INTEGER AS coord, round(t{i}, 6) AS theta, round(t{i}, 6) AS theta_avg FROM p{t}" for t in range(1, STEPS + 1) for i in d)
    return "WITH " + ",\n".join(parts) + "\n" + out


@query("sync_shard_sgd_5", _shard_sql())
def _(spark, sf_dir):
    """Every parameter server closes its own quorum."""
    return _fleet(spark, sf_dir, lambda: Sgd(_rate()), averages=False, shards=3, quorum_scope="shard")


_PRICE = "y AS (SELECT l_partkey AS coord, avg(l_extendedprice / 50000) AS y FROM lineitem GROUP BY 1)"


@query("wide_adagrad_2", f"""WITH {_PRICE}, a AS (SELECT *, -y AS g1, y * y AS s1, 0.3::DOUBLE * y / (abs(y) + 1e-8) AS v1 FROM y), b AS (SELECT *, v1 - y AS g2 FROM a)
SELECT (coord % 4)::INTEGER AS shard, coord, round(v1 - 0.3::DOUBLE * g2 / (sqrt(s1 + g2 * g2) + 1e-8), 6) AS value, round(s1 + g2 * g2, 6) AS slot FROM b""")
def _(spark, sf_dir):
    """Two steps of parameters that stay in tables: a price per part, over four servers, by joins alone."""
    items = read_table(spark, sf_dir, "lineitem", ["l_partkey", "l_extendedprice"]).select(F.col("l_partkey").alias("coord"), (F.col("l_extendedprice") / 50000).alias("y"))
    theta = items.select("coord").distinct().select((F.col("coord") % 4).cast("int").alias("shard"), "coord", F.lit(0.0).alias("value"), F.lit(0.0).alias("slot"))
    for _step in range(2):
        errors = touched(theta, items).join(items, "coord").groupBy("shard", "coord").agg(F.avg(F.col("value") - F.col("y")).alias("g"))
        theta = wide_step(theta, errors, 0.3, "adagrad")
    return theta


FLEET, FLEET_QUORUM, FLEET_STEPS = 100, 94, 8


def _curve_sql() -> str:
    """The flagship's steps unrolled: winners by the shaped trace, then per step the workers' mean loss and gradient."""
    d, n = range(3), FLEET * FLEET_STEPS
    rows = NET_SQL.replace(f"% {STEPS * WORKERS} AS slot", f"% {n} AS slot").replace(f"slot // {WORKERS}", f"slot // {FLEET}").replace(f"slot % {WORKERS}", f"slot % {FLEET}")
    parts = [rows, trace_sql(FLEET), f"r AS (SELECT b.* FROM b JOIN tk USING (iteration, worker) WHERE k <= {FLEET_QUORUM})", "p0 AS (SELECT 0::DOUBLE AS t0, 0::DOUBLE AS t1, 0::DOUBLE AS t2)"]
    for t in range(FLEET_STEPS):
        err = " + ".join(f"q.t{i} * x{i + 1}" for i in d) + " - y"
        worker = ", ".join(f"avg(({err}) * x{i + 1}) AS w{i}" for i in d)
        parts.append(f"g{t} AS (SELECT avg(l) AS loss, " + ", ".join(f"avg(w{i}) AS g{i}" for i in d) + f" FROM (SELECT worker, avg(0.5 * pow({err}, 2)) AS l, {worker} FROM r, p{t} q WHERE iteration = {t} GROUP BY worker))")
        parts.append(f"p{t + 1} AS (SELECT " + ", ".join(f"t{i} - {_fmt(RATE * DECAY**t)} * g{i} AS t{i}" for i in d) + f" FROM p{t}, g{t})")
    losses = " UNION ALL ".join(f"SELECT {t} AS iteration, loss FROM g{t}" for t in range(FLEET_STEPS))
    steps = f"SELECT iteration, count(*) FILTER (k <= {FLEET_QUORUM})::BIGINT AS n_used, count(*) FILTER (k > {FLEET_QUORUM})::BIGINT AS n_dropped, max(arrival) FILTER (k <= {FLEET_QUORUM}) AS step_time FROM tk GROUP BY iteration"
    parts += [f"l AS ({losses})", f"st AS ({steps})", "c AS (SELECT *, sum(step_time) OVER (ORDER BY iteration) AS clock FROM st)"]
    return "WITH " + ",\n".join(parts) + "\nSELECT c.iteration, n_used, n_dropped, round(step_time, 6) AS step_time, round(clock, 6) AS clock, round(loss, 6) AS loss FROM c JOIN l USING (iteration)"


@query("sync_spares_curve", _curve_sql())
def _(spark, sf_dir):
    """The flagship: net-price regression with 94 of 100 workers on the shaped trace, loss and clock after each step."""
    return flagship(spark, sf_dir)


def flagship(spark: SparkSession, sf_dir: str, workers: int = FLEET, quorum: int = FLEET_QUORUM, steps: int = FLEET_STEPS) -> DataFrame:
    """(iteration, n_used, step_time, clock, loss) of synchronous training with spares: the clock runs over the whole
    trace, all rows are dealt over the steps, and the winners' rows alone are read."""
    slot = F.col("slot")
    rows = wide_slots(spark, sf_dir, steps * workers).withColumns({"iteration": F.expr(f"CAST(slot DIV {workers} AS INT)"), "worker": (slot % workers).cast("int")})
    arrivals = trace(spark, sf_dir, workers)
    config = TrainConfig(FleetConfig(quorum, workers - quorum), steps)
    run = td.train_fleet(config, vectors(rows), arrivals, LinearModel(3), lambda: Sgd(exponential(RATE, DECAY)))
    losses = spark.createDataFrame([(t, float(x)) for t, x in enumerate(run.losses)], "iteration int, loss double")
    return tr.sync_steps(arrivals, quorum).join(losses, "iteration")
