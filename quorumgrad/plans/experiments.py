"""The experiment workloads: staleness, quorum size, rate sweep, synchronous against asynchronous, likelihood, extensions.

Long runs replay in numpy, a task per configuration, on rows whose size is checked (``train.replay``).  What the
reference leaves open (batch sizes, decay constants, convergence tolerance) is set here and named in the rows.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..metrics import curves as mc
from ..models import BigramModel, LogisticModel, MlpModel, SoftmaxModel, SparseEmbeddingModel
from ..models.base import log_softmax
from ..models.exact import conditional_entropy, majority_share, newton
from ..operators.ordering import numbered
from ..optim.rules import AdaGrad, Momentum, RmsProp, Sgd, constant, exponential, stale_safe
from ..sources import features
from ..timing import asynchronous as asy
from ..timing import trace as tr
from ..train import replay as rp
from ..train import sized as sz
from ..train.gradient import full_loss, worker_gradients
from ..train.live import LiveQuorum
from .common import SHAPED_SQL, events, rounded, trace, trace_sql

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None, digits: int = 6):
    def put(f):
        QUERIES[name] = lambda spark, sf_dir: rounded(f(spark, sf_dir), digits)
        if sql:
            ORACLES[name] = sql
        return f

    return put


def rounds(updates: int, workers: int) -> int:
    """Iterations of the trace that a plan of so many asynchronous updates goes through."""
    return -(-updates // workers) * 2 + 2


def arrays(spark: SparkSession, sf_dir: str, workers: int, most: int) -> np.ndarray:
    """Arrival times (iterations x workers) of the trace that a replay repeats in turn: its first ``most`` iterations.

    Executors find the whole trace's complete iterations and order them; a replay of up to ``most`` iterations never
    looks past these, so that no more come to the driver however long the trace is.
    """
    head = trace(spark, sf_dir, workers).orderBy("iteration", "worker").limit(most * workers).select("arrival")
    return head.toArrow().column(0).to_numpy().reshape(-1, workers)


def step_times(times: np.ndarray, quorum: int, steps: int) -> np.ndarray:
    return np.resize(np.sort(times, axis=1)[:, quorum - 1], steps)


def async_plan(times: np.ndarray, updates: int) -> tuple[np.ndarray, np.ndarray]:
    """(versions read, clock) of asynchronous updates when each worker repeats its column of times."""
    finish = np.cumsum(np.resize(times, (rounds(updates, times.shape[1]), times.shape[1])), axis=0)
    order = np.argsort(finish.ravel(), kind="stable")[:updates]
    workers, reads, last = order % times.shape[1], np.empty(updates, int), np.zeros(times.shape[1], int)
    for u, w in enumerate(workers):
        reads[u], last[w] = last[w], u + 1
    return reads, finish.ravel()[order]


# ---- simulated staleness ---------------------------------------------------------------------------------------

LAGS, UPDATES, BATCH, RATE = (0, 5, 10, 15, 20, 30, 40, 50), 600, 32, 2.0


CLASSES = {"languages": 4, "planted": 2}


def _stale_plan(s: dict, widths: dict[str, int]) -> sz.Plan:
    """One try of a run, as ``rp.replay_stale`` does it."""
    schedule = stale_safe(constant(s["rate"]), s["lag"], s.get("factor", 1.0))
    seed, updates = 10 * s["try"] + 1, s["updates"]
    law = rp.LagLaw(s.get("law", "fixed"), s["lag"], round(s.get("ramp_epochs", 0) * s["epoch"]))
    reads = np.arange(updates) - law.draw(updates, seed + 1)
    model = SoftmaxModel(widths[s["task"]], CLASSES[s["task"]])
    return sz.Plan(model, Momentum(schedule, mu=s.get("mu", 0.0)), reads, np.arange(1, updates + 1, dtype=float), max(30, updates // 20), seed, stops=True)


def _errors(found: list[sz.Evaluation]) -> tuple[list[tuple], float]:
    """Curve rows up to an explosion, and the last validation precision (of parameters that are finite)."""
    rows, score = [], -np.inf
    for e in found:
        error = {f"{s}_error": 1 - e.share[s] for s in ("test", "train", "validation")}
        rows += [(e.iteration, e.clock, k, None if np.isnan(v) else v) for k, v in error.items()]
        score = e.share["validation"] if e.finite else -np.inf
        if not e.finite or rp.diverged(np.zeros(1), error["train_error"]):
            rows.append((e.iteration, e.clock, "exploded", 1.0))
            break
    return rows, score


def stale_curves(spark, tables: dict[str, sz.Table], runs: dict[str, dict]) -> DataFrame:
    """Curves of runs by name; of a run with several tries the one best on validation."""
    groups: dict[tuple, sz.Group] = {}
    for name, s in runs.items():
        epoch = -(-tables[s["task"]].counts["train"] // BATCH)
        updates = max(UPDATES, s.get("epochs", 0) * epoch)
        for k in range(s.get("tries", 1)):
            own = groups.setdefault((s["task"], k, updates), sz.Group(s["task"], 10 * k + 1, updates, BATCH, {}))
            own.runs[f"{name}#{k}"] = s | {"try": k, "updates": updates, "epoch": epoch}
    widths = {t: own.width for t, own in tables.items()}
    found = sz.evaluated(spark, list(groups.values()), tables, {t: SoftmaxModel(w, CLASSES[t]) for t, w in widths.items()}, _stale_plan, widths)
    out = []
    for name, s in runs.items():
        rows, score = _errors(found[f"{name}#0"])
        for k in range(1, s.get("tries", 1)):
            other, value = _errors(found[f"{name}#{k}"])
            if value > score:
                rows, score = other, value
        out += [(name, *r) for r in rows]
    return spark.createDataFrame(out, rp.CURVE)


def _stale(spark, sf_dir, variants: dict[str, dict], tasks: tuple[str, ...] = ("languages", "planted")) -> DataFrame:
    """(task, variant, lag, test error over the second half of the evaluations: mean, spread, worst; mean training and
    validation error; exploded_at, the update at which a run stopped, null where none did): one lucky point decides
    nothing."""
    makers = {"languages": features.languages, "planted": features.planted}
    tables = {t: sz.table(makers[t](spark, sf_dir)) for t in tasks}
    runs = {f"{t}/{v}/{lag}": {"rate": RATE * 4, "lag": lag, "task": t} | settings for t in tasks for v, settings in variants.items() for lag in LAGS}
    out = stale_curves(spark, tables, runs)
    last = F.max("iteration").over(W.partitionBy("run_id"))
    late = lambda metric: F.when((F.col("metric") == metric) & (F.col("iteration") > F.col("last") / 2), F.col("value"))
    part = F.split("run_id", "/")
    return out.withColumn("last", last).groupBy(part[0].alias("task"), part[1].alias("variant"), part[2].cast("int").alias("lag")).agg(
        F.avg(late("test_error")).alias("mean_error"), F.coalesce(F.stddev_samp(late("test_error")), F.lit(0.0)).alias("spread"), F.max(late("test_error")).alias("worst"),
        F.avg(late("train_error")).alias("train_error"), F.avg(late("validation_error")).alias("validation_error"), F.max(F.when(F.col("metric") == "exploded", F.col("iteration"))).alias("exploded_at"),
    )


@query("stale_sweep")
def _(spark, sf_dir):
    return _stale(spark, sf_dir, {"fixed": {}, "uniform": {"law": "uniform"}, "geometric": {"law": "geometric"}, "momentum": {"mu": 0.9, "rate": RATE}})


@query("stale_ramp")
def _(spark, sf_dir):
    """The lag grows over three passes over the rows; every run takes six."""
    return _stale(spark, sf_dir, {"plain": {"mu": 0.9, "rate": RATE, "epochs": 6}, "ramp": {"mu": 0.9, "rate": RATE, "epochs": 6, "ramp_epochs": 3}})


@query("stale_lowlr")
def _(spark, sf_dir):
    return _stale(spark, sf_dir, {"plain": {"mu": 0.9, "rate": RATE}, "low_rate_from_20": {"mu": 0.9, "rate": RATE, "factor": 0.1}})


@query("stale_restart")
def _(spark, sf_dir):
    return _stale(spark, sf_dir, {"plain": {"mu": 0.9, "rate": RATE}, "best_of_3": {"mu": 0.9, "rate": RATE, "tries": 3}})


# ---- iterations against quorum size ----------------------------------------------------------------------------

L2, QUORUMS = 1e-3, (50, 70, 80, 90, 100)


def noisy_planted(spark, sf_dir) -> tuple[rp.Rows, LogisticModel, float]:
    """Rows, model and least loss of the planted task with a tenth of its labels turned; all rows train."""
    rows = rp.bounded_rows(features.planted(spark, sf_dir, flips=1))
    x, y = np.concatenate([rows.x, rows.x_val, rows.x_test]), np.concatenate([rows.y, rows.y_val, rows.y_test])
    model = LogisticModel(64, L2)
    return rp.Rows(x, y, rows.x_val, rows.y_val, rows.x_test, rows.y_test), model, model.loss(newton(x, y, L2), x, y)


def _regret(model, rows, best):
    return lambda th: {"regret": model.loss(th, rows.x, rows.y) - best, "precision": rp.accuracy(model, th, rows.x_test, rows.y_test)}


def _quorum_run(s: dict, shared) -> rp.Curve:
    rows, model, best = shared
    return rp.replay_sync(model, rows, Sgd(constant(0.02 * s["n"])), np.ones(400), s["n"], 1, 5, s["seed"], _regret(model, rows, best), lambda m: m["regret"] <= 0.05)[0]


@query("iters_vs_n")
def _(spark, sf_dir):
    """(n, iterations): median over seeds of steps to a regret of 0.05; the rate is proportional to N by choice."""
    runs = {f"{n}/{k}": {"n": n, "seed": k} for n in QUORUMS for k in range(5)}
    reached = mc.first_reach(rp.sweep(spark, runs, noisy_planted(spark, sf_dir), _quorum_run).where("metric = 'regret'"), 0.05)
    return reached.groupBy(F.split("run_id", "/")[0].cast("int").alias("n")).agg(F.expr("percentile(iteration, 0.5)").alias("iterations"), F.count("iteration").alias("reached"))


# ---- initial rate ----------------------------------------------------------------------------------------------

RATES = (1.125, 2.25, 4.5, 9.0)


def _rate_run(s: dict, shared) -> rp.Curve:
    rows, model, best = shared
    return rp.replay_sync(model, rows, Sgd(exponential(s["rate"], 0.99)), np.ones(600), 100, 1, 5, 3, _regret(model, rows, best))[0]


def _rates(spark, sf_dir) -> DataFrame:
    """(run_id, iteration, clock, metric, value, epoch): a step draws 100 rows, an epoch has as many draws as rows."""
    shared = noisy_planted(spark, sf_dir)
    return rp.sweep(spark, {f"{r}": {"rate": r} for r in RATES}, shared, _rate_run).withColumn("epoch", F.col("iteration") * 100 / F.lit(len(shared[0].y)))


@query("lr_sweep")
def _(spark, sf_dir):
    """(rate, best_regret, iteration, epoch, precision): when a run comes within a hundredth of its own best regret, and
    the share of test rows that it has right then."""
    rows = _rates(spark, sf_dir)
    done = mc.converged_at(rows.where("metric = 'regret'"), 0.01).select("run_id", F.col("best").alias("best_regret"), "iteration")
    at = rows.where("metric = 'precision'").select("run_id", "iteration", "epoch", F.col("value").alias("precision"))
    return done.join(at, ["run_id", "iteration"]).select(F.col("run_id").cast("double").alias("rate"), "best_regret", "iteration", "epoch", "precision")


@query("epochs_to_eps")
def _(spark, sf_dir):
    """(rate, eps, iteration, epoch): null where a rate never gets that far."""
    rows = _rates(spark, sf_dir).where("metric = 'regret'").withColumn("eps", F.explode(F.array(*map(F.lit, (0.1, 0.05, 0.02, 0.005)))))
    first = lambda c: F.min(F.when(F.col("value") <= F.col("eps"), F.col(c))).alias(c)
    return rows.groupBy(F.col("run_id").cast("double").alias("rate"), "eps").agg(first("iteration"), first("epoch"))


@query("epochs_to_precision")
def _(spark, sf_dir):
    """(rate, precision, iteration, epoch): the same for test precision."""
    rows = _rates(spark, sf_dir).where("metric = 'precision'").withColumn("precision", F.explode(F.array(*map(F.lit, (0.75, 0.8, 0.82, 0.84)))))
    first = lambda c: F.min(F.when(F.col("value") >= F.col("precision"), F.col(c))).alias(c)
    return rows.groupBy(F.col("run_id").cast("double").alias("rate"), "precision").agg(first("iteration"), first("epoch"))


# ---- synchronous with spares against asynchronous --------------------------------------------------------------

FLEETS = {53: 3, 106: 6, 212: 12}
FLEET_MODELS = {"planted": MlpModel((64, 16), 2), "languages": MlpModel((128, 16), 4)}
GRID = {"sync": (0.125, 0.5, 2.0), "async": (0.005, 0.02, 0.08)}
SEEDS, STEPS, AVERAGE = 5, 200, 0.5


def _fleet_plan(s: dict, times: dict[int, np.ndarray]) -> sz.Plan:
    """One run; both methods are measured on their running average, which forgets half of itself per step of the
    synchronous fleet and per as many asynchronous updates as there are workers."""
    n, model, rule = s["fleet"], FLEET_MODELS[s["task"]], Sgd(constant(s["rate"]))
    if s["method"] == "sync":
        return sz.Plan(model, rule, np.arange(STEPS), np.cumsum(step_times(times[n], n - FLEETS[n], STEPS)), 10, s["seed"], AVERAGE)
    reads, clock = async_plan(times[n], STEPS * n)  # as many epochs as the synchronous runs have steps
    return sz.Plan(model, rule, reads, clock, 10 * n, s["seed"], AVERAGE ** (1 / n), stops=True)


def fleet_runs(spark: SparkSession, tables: dict[str, sz.Table], times: dict[int, np.ndarray], runs: dict[str, dict]) -> list[tuple]:
    """Curve rows (run_id, iteration, clock, metric, value) of runs by name."""
    groups: dict[tuple, sz.Group] = {}
    for name, s in runs.items():
        n = s["fleet"]
        updates, batch = (STEPS, 4 * (n - FLEETS[n])) if s["method"] == "sync" else (STEPS * n, 4)
        own = groups.setdefault((s["task"], s["method"], n, s["seed"]), sz.Group(s["task"], s["seed"], updates, batch, {}))
        own.runs[name] = s
    out = []
    for name, found in sz.evaluated(spark, list(groups.values()), tables, FLEET_MODELS, _fleet_plan, times).items():
        for e in found:
            shares = {"precision": e.share["test"], "validation": e.share["validation"], "train": e.share["train"]}
            out += [(name, e.iteration, e.clock, k, None if np.isnan(v) else v) for k, v in shares.items()]
            if not e.finite and runs[name]["method"] == "async":
                out.append((name, e.iteration, e.clock, "exploded", 1.0))
    return out


def fleet_curves(spark: SparkSession, sf_dir: str, tasks: tuple[str, ...] = ("planted", "languages"), seeds: int = SEEDS) -> DataFrame:
    """(run_id, task, method, fleet, rate, seed, iteration, clock, metric, value) of the rate that is best on validation
    in the first seed's runs, for all seeds; iterations are epochs.

    The curves (84 runs of two tasks, 20 evaluations each) come to the driver, the rows they are measured on do not.
    """
    makers = {"planted": features.planted, "languages": features.languages}
    tables, times = {t: sz.table(makers[t](spark, sf_dir)) for t in tasks}, {f: arrays(spark, sf_dir, f, max(STEPS, rounds(STEPS * f, f))) for f in FLEETS}
    one = lambda t, m, f, r, k: (f"{t}/{m}/{f}/{r}/{k}", {"task": t, "method": m, "fleet": f, "rate": r, "seed": k})
    grid = dict(one(t, m, f, r, 1) for t in tasks for m, rates in GRID.items() for f in FLEETS for r in rates)
    tried = fleet_runs(spark, tables, times, grid)
    last = {name: -1.0 if value is None else value for name, _, _, metric, value in tried if metric == "validation"}
    chosen: dict[tuple, tuple] = {}
    for name, value in last.items():
        s = grid[name]
        own = (s["task"], s["method"], s["fleet"])
        chosen[own] = max(chosen.get(own, (-1.0, float("-inf"))), (value, -s["rate"]))
    best = {own: -rate for own, (_, rate) in chosen.items()}
    rows = [r for r in tried if grid[r[0]]["rate"] == best[tuple(grid[r[0]][c] for c in ("task", "method", "fleet"))]]
    more = dict(one(t, m, f, r, k) for (t, m, f), r in best.items() for k in range(2, seeds + 1))
    if more:
        rows += fleet_runs(spark, tables, times, more)
    p, rows = F.split("run_id", "/"), spark.createDataFrame(rows, rp.CURVE)
    rows = rows.select("run_id", p[0].alias("task"), p[1].alias("method"), p[2].cast("int").alias("fleet"), p[3].cast("double").alias("rate"), p[4].cast("int").alias("seed"), "iteration", "clock", "metric", "value")
    return rows.withColumn("iteration", F.when(F.col("method") == "sync", F.col("iteration")).otherwise(F.floor(F.col("iteration") / F.col("fleet"))))


def _precision(spark, sf_dir) -> DataFrame:
    return fleet_curves(spark, sf_dir).where("metric = 'precision'")


_RUN = ["task", "method", "fleet"]


def _over_seeds(rows: DataFrame, value: str, name: str) -> DataFrame:
    """Mean and spread over seeds, and how many seeds got there."""
    return rows.groupBy(*_RUN).agg(F.avg(value).alias(name), F.stddev_samp(value).alias(f"{name}_sd"), F.count(value).alias("seeds"))


def _named(rows: DataFrame) -> DataFrame:
    p = F.split("run_id", "/")
    return rows.withColumns({"task": p[0], "method": p[1], "fleet": p[2].cast("int")})


@query("sync_vs_async_curve")
def _(spark, sf_dir):
    """Mean test, validation and training precision at each evaluation."""
    rows = fleet_curves(spark, sf_dir).groupBy(*_RUN, "rate", "iteration").agg(
        F.avg(F.when(F.col("metric") == "precision", F.col("clock"))).alias("clock"), *[F.avg(F.when(F.col("metric") == m, F.col("value"))).alias(n) for m, n in (("precision", "precision"), ("validation", "validation"), ("train", "train"))]
    )
    return rows


@query("sync_vs_async_precision")
def _(spark, sf_dir):
    last = _precision(spark, sf_dir).groupBy(*_RUN, "rate", "seed").agg(F.max_by("value", "iteration").alias("value"))
    return _over_seeds(last, "value", "precision").join(last.select(*_RUN, "rate").distinct(), _RUN)


def _converged(spark, sf_dir) -> DataFrame:
    return _named(mc.converged_at(_precision(spark, sf_dir).select("run_id", "iteration", "clock", "value"), 0.01, lower_is_better=False))


@query("sync_vs_async_epochs")
def _(spark, sf_dir):
    return _over_seeds(_converged(spark, sf_dir), "iteration", "epochs")


@query("sync_vs_async_time")
def _(spark, sf_dir):
    return _over_seeds(_converged(spark, sf_dir), "clock", "seconds")


@query("sync_vs_async_epoch_time")
def _(spark, sf_dir):
    rows = _precision(spark, sf_dir).select("run_id", "iteration", "clock", "value")
    return _over_seeds(_named(mc.mean_epoch_time(rows)), "mean_s", "mean_s")


# ---- likelihood of an autoregressive model ---------------------------------------------------------------------

SYMBOL_COUNT = len(features.SYMBOLS) + 1
BIGRAM = BigramModel(4, SYMBOL_COUNT)
NLL_UPDATES = 1600


def _nll_run(s: dict, shared) -> rp.Curve:
    rows, weights, times = shared
    cumulative = np.cumsum(weights) / weights.sum()
    rng = np.random.default_rng(2)
    # Pairs are drawn by their counts, as examples of the corpus would be.
    pick = np.searchsorted(cumulative, rng.uniform(size=1 << 18))
    drawn = rp.Rows(rows.x[pick][:, :2], rows.y[pick], rows.x, rows.y, rows.x, rows.y)
    measure = lambda th: {"nll": BIGRAM.loss(th, rows.x, rows.y)}
    n, batch, total = s["fleet"], 64, NLL_UPDATES
    if s["method"] == "async":
        reads, clock = async_plan(times[n], total)
        return rp.replay_async(BIGRAM, drawn, RmsProp(constant(s["rate"])), reads, clock, batch, 40 * n, 1, measure)[0]
    quorum = max(1, n - 1)
    return rp.replay_sync(BIGRAM, drawn, RmsProp(constant(s["rate"])), step_times(times[n], quorum, total // (1 if n == 1 else 4)), quorum, batch, 20, 1, measure)[0]


def nll_curves(spark, sf_dir) -> DataFrame:
    counts = features.symbol_counts(spark, sf_dir).orderBy("ctx", "prev", "next").toPandas()  # at most 4 x 30 x 30 rows
    x = counts[["ctx", "prev", "n"]].to_numpy(float)
    rows = rp.Rows(x, counts["next"].to_numpy(float), x[:0], x[:0, 0], x[:0], x[:0, 0])
    shared = (rows, counts["n"].to_numpy(float), {n: arrays(spark, sf_dir, n, max(NLL_UPDATES, rounds(NLL_UPDATES, n))) for n in (1, 8, 16)})
    runs = {"serial/1": {"method": "serial", "fleet": 1, "rate": 0.05}} | {f"{m}/{n}": {"method": m, "fleet": n, "rate": 0.05} for m in ("sync", "async") for n in (8, 16)}
    return rp.sweep(spark, runs, shared, _nll_run).drop("metric")


@query("nll_curve")
def _(spark, sf_dir):
    return nll_curves(spark, sf_dir).withColumnRenamed("value", "nll")


@query("nll_best_so_far")
def _(spark, sf_dir):
    return mc.best_so_far(nll_curves(spark, sf_dir))


@query("time_to_nll")
def _(spark, sf_dir):
    """(run_id, eps, seconds) to likelihoods near the optimum; null where never reached."""
    best = conditional_entropy(features.symbol_counts(spark, sf_dir), ["ctx", "prev"]).first()[0]
    rows = nll_curves(spark, sf_dir).withColumn("eps", F.explode(F.array(*[F.lit(best + d) for d in (0.5, 0.2, 0.1)])))
    return rows.groupBy("run_id", "eps").agg(F.min(F.when(F.col("value") <= F.col("eps"), F.col("clock"))).alias("seconds"))


@query("nll_exact", f"""WITH a AS (SELECT CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END AS ctx, list_transform(string_split(lower(text), ''), lambda c: CASE WHEN contains('{features.SYMBOLS}', c) THEN strpos('{features.SYMBOLS}', c) - 1 ELSE {len(features.SYMBOLS)} END) AS c FROM documents),
p AS (SELECT ctx, unnest(list_transform(range(1, len(c)), lambda i: {{'p': c[i], 'n': c[i + 1]}})) AS q FROM a), k AS (SELECT ctx, q.p AS p, q.n AS n, count(*) AS m FROM p GROUP BY ALL), t AS (SELECT *, sum(m) OVER (PARTITION BY ctx, p) AS total FROM k)
SELECT round(-sum(m * ln(m / total)) / sum(m), 6) AS nll FROM t""")
def _(spark, sf_dir):
    return conditional_entropy(features.symbol_counts(spark, sf_dir), ["ctx", "prev"])


# ---- extensions ------------------------------------------------------------------------------------------------

TOKENS, SPARSE_STEPS, SPARSE_BATCH = 4096, 150, 64
SPARSE = "iteration long, clock double, touched double, theta array<double>"


def _triples(tokens: list[list[int]], counts: list[list[float]]) -> np.ndarray:
    """(example, token, count) rows of a few examples, numbered from 0."""
    return np.stack([np.repeat(np.arange(len(tokens)), [len(t) for t in tokens]), np.concatenate(tokens), np.concatenate(counts)], axis=1).astype(float)


def _sparse_examples(spark, sf_dir) -> DataFrame:
    """(at, y, tokens, counts): a row per turn with a word, numbered in the order of row_id, written."""
    rows = features.sparse_roles(spark, sf_dir, TOKENS).groupBy("row_id").agg(F.min(F.struct("token", "y"))["y"].cast("double").alias("y"), F.array_sort(F.collect_list(F.struct("token", "count"))).alias("w"))
    return sz.written(numbered(rows, [F.col("row_id")], "at").select("at", "y", F.col("w.token").alias("tokens"), F.col("w.count").alias("counts")), "examples")


def sparse_curve(spark, examples: DataFrame, rate: float) -> list[tuple]:
    """(run_id, iteration, clock, metric, value): drawn examples stream through the task that trains, and all are measured
    where they are; the driver gets the table of weights at each evaluation."""
    model, n = SparseEmbeddingModel(TOKENS, 2), examples.count()
    size = min(SPARSE_BATCH, n)

    def draw(batches):
        for _ in batches:
            rng = np.random.default_rng(1)
            for t in range(SPARSE_STEPS):
                yield pd.DataFrame({"t": t, "at": np.sort(rng.choice(n, size, replace=False))})

    def train(batches):
        rule, theta, held = AdaGrad(constant(rate)), np.zeros(model.size()), []
        for pdf in batches:
            held += list(pdf[["y", "tokens", "counts", "t"]].itertuples(index=False))
            while len(held) >= size:
                y, tokens, counts, t = zip(*held[:size], strict=True)
                held, batch = held[size:], _triples(tokens, counts)
                theta = rule.step(theta, model.grad(theta, batch, np.array(y)))
                if (t[0] + 1) % 10 == 0:
                    yield pd.DataFrame({"iteration": [t[0] + 1], "clock": [t[0] + 1.0], "touched": [float(len(np.unique(batch[:, 1])))], "theta": [theta]})

    drawn = spark.range(1, numPartitions=1).mapInPandas(draw, "t long, at long")
    steps = examples.join(F.broadcast(drawn), "at").repartition(1).sortWithinPartitions("t", "at").mapInPandas(train, SPARSE)
    steps = sorted(steps.collect())
    sent = spark.sparkContext.broadcast([np.array(r.theta) for r in steps])

    def measure(batches):
        sums = np.zeros((len(sent.value), 2))
        for pdf in batches:
            if len(pdf):
                x, y = _triples(list(pdf["tokens"]), list(pdf["counts"])), pdf["y"].to_numpy()
                for k, theta in enumerate(sent.value):
                    scores = model.scores(theta, x)
                    sums[k] += -log_softmax(scores)[np.arange(len(y)), y.astype(int)].sum(), (scores.argmax(1) == y).sum()
        yield pd.DataFrame({"k": np.arange(len(sums)), "loss": sums[:, 0], "right": sums[:, 1]})

    sums = {r.k: r for r in examples.mapInPandas(measure, "k int, loss double, right double").groupBy("k").agg(F.sum("loss").alias("loss"), F.sum("right").alias("right")).collect()}
    return [("adagrad", r.iteration, r.clock, m, v) for k, r in enumerate(steps) for m, v in (("nll", sums[k].loss / n), ("accuracy", sums[k].right / n), ("touched", r.touched))]


@query("sparse_lm")
def _(spark, sf_dir):
    """A sparse embedding classifier: likelihood, accuracy and how many rows of the table a step touches."""
    return spark.createDataFrame(sparse_curve(spark, _sparse_examples(spark, sf_dir), 0.1), rp.CURVE)


@query("live_quorum")
def _(spark, sf_dir):
    """Spark jobs as workers, four steps: the first 3 of 4 gradients move the parameters, the last job is cancelled.

    Which worker is left out is decided by the race, so losses differ a little between runs; every step lowers them.
    """
    return live_steps(spark, sf_dir)


def live_steps(spark: SparkSession, sf_dir: str, quorum: int = 3, spares: int = 1, steps: int = 4, rate: float = 20.0) -> DataFrame:
    """(step, n_used, loss): the mean loss over all rows after each step of a live quorum on the planted task."""
    model, fleet = LogisticModel(64, L2), quorum + spares
    task = features.planted(spark, sf_dir).select(F.lit(0).alias("iteration"), F.pmod("row_id", F.lit(fleet)).cast("int").alias("worker"), "x", "y").persist()
    live, theta = LiveQuorum(spark, quorum, spares), model.init()
    out = [(0, 0, full_loss(task, model, theta))]
    try:
        for t in range(steps):
            found, _ = live.step(lambda w: worker_gradients(task.where(F.col("worker") == w), model, {0: theta})[(0, w)][2])  # noqa: B023
            theta = theta - rate * np.mean(list(found.values()), axis=0)
            out.append((t + 1, len(found), full_loss(task, model, theta)))
    finally:
        task.unpersist()
    return spark.createDataFrame(out, "step int, n_used int, loss double")


@query("majority", "SELECT round(max(n) / sum(n), 6) AS majority_share FROM (SELECT lang, count(*) AS n FROM documents GROUP BY 1)")
def _(spark, sf_dir):
    return majority_share(features.read_table(spark, sf_dir, "documents", ["lang"]), "lang")


# ---- measures on a curve made by formula -----------------------------------------------------------------------

_CURVE = "c AS (SELECT 'run' || (user_id % 3) AS run_id, row_number() OVER (PARTITION BY user_id % 3 ORDER BY event_id)::BIGINT AS iteration, value FROM events), d AS (SELECT run_id, iteration, iteration * 1.5::DOUBLE AS clock, 100 / (1 + iteration / 50)::DOUBLE + value / 10 AS value FROM c)"


def formula_curve(spark, sf_dir) -> DataFrame:
    e = events(spark, sf_dir).join(features.read_table(spark, sf_dir, "events", ["event_id", "user_id"]), "event_id")
    run = F.concat(F.lit("run"), F.col("user_id") % 3)
    rows = e.withColumn("run_id", run).withColumn("iteration", F.row_number().over(W.partitionBy("run_id").orderBy("event_id")).cast("long"))
    return rows.select("run_id", "iteration", (F.col("iteration") * 1.5).alias("clock"), (100 / (1 + F.col("iteration") / 50) + F.col("value") / 10).alias("value"))


@query("best_so_far", f"WITH {_CURVE} SELECT run_id, iteration, round(clock, 6) AS clock, round(value, 6) AS value, round(min(value) OVER (PARTITION BY run_id ORDER BY iteration), 6) AS best FROM d")
def _(spark, sf_dir):
    return mc.best_so_far(formula_curve(spark, sf_dir))


@query("first_reach", f"WITH {_CURVE} SELECT run_id, min(iteration) FILTER (value <= 12) AS iteration, round(min(clock) FILTER (value <= 12), 6) AS clock FROM d GROUP BY 1")
def _(spark, sf_dir):
    return mc.first_reach(formula_curve(spark, sf_dir), 12.0)


@query("converged_at", f"WITH {_CURVE}, b AS (SELECT *, min(value) OVER (PARTITION BY run_id) AS best FROM d) SELECT run_id, min(iteration) FILTER (abs(value - best) <= 2) AS iteration, round(min(clock) FILTER (abs(value - best) <= 2), 6) AS clock, round(min(best), 6) AS best FROM b GROUP BY 1")
def _(spark, sf_dir):
    return mc.converged_at(formula_curve(spark, sf_dir), 2.0)


@query("epoch_map", f"WITH {_CURVE} SELECT run_id, iteration, iteration // 40 AS epoch FROM d")
def _(spark, sf_dir):
    return formula_curve(spark, sf_dir).select("run_id", "iteration", mc.epoch_of(F.col("iteration"), 40, synchronous=False).alias("epoch"))


@query("mean_epoch_time", f"WITH {_CURVE} SELECT run_id, round(max(clock) / max(iteration), 6) AS mean_s FROM d GROUP BY 1")
def _(spark, sf_dir):
    return mc.mean_epoch_time(formula_curve(spark, sf_dir))


@query("compare_runs", f"WITH {_CURVE} SELECT a.iteration, round(a.value - b.value, 6) AS gap, round(a.value / b.value, 6) AS ratio FROM d a JOIN d b ON a.iteration = b.iteration AND a.run_id = 'run0' AND b.run_id = 'run1'")
def _(spark, sf_dir):
    return mc.compare_runs(formula_curve(spark, sf_dir), "run0", "run1")


_SCORES = "s AS (SELECT l_orderkey, [l_quantity / 50, l_discount * 10, l_tax * 12] AS s, CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS y FROM lineitem), p AS (SELECT y, CASE WHEN s[1] >= s[2] AND s[1] >= s[3] THEN 0 WHEN s[2] >= s[3] THEN 1 ELSE 2 END AS top FROM s)"


def _scored(spark, sf_dir):
    li = features.read_table(spark, sf_dir, "lineitem", ["l_quantity", "l_discount", "l_tax", "l_returnflag"])
    scores = F.array(F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 12)
    return li.select(scores.alias("s"), F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2).alias("y"))


@query("precision_at_1", f"WITH {_SCORES} SELECT round(avg((top = y)::INTEGER), 6) AS precision FROM p")
def _(spark, sf_dir):
    return _scored(spark, sf_dir).agg(mc.precision_at_k(F.col("s"), F.col("y")).alias("precision"))


@query("precision_at_2", f"WITH {_SCORES}, r AS (SELECT y, s, s[y + 1] AS own FROM s) SELECT round(avg((len(list_filter(range(1, 4), lambda i: s[i] > own OR (s[i] = own AND i < y + 1))) < 2)::INTEGER), 6) AS precision FROM r")
def _(spark, sf_dir):
    return _scored(spark, sf_dir).agg(mc.precision_at_k(F.col("s"), F.col("y"), 2).alias("precision"))


@query("error_rate", f"WITH {_SCORES} SELECT round(1 - avg((top = y)::INTEGER), 6) AS error FROM p")
def _(spark, sf_dir):
    return _scored(spark, sf_dir).agg((1 - mc.precision_at_k(F.col("s"), F.col("y"))).alias("error"))


@query("updates_per_second", f"WITH {trace_sql(40)}, a AS (SELECT worker, sum(CAST({SHAPED_SQL} AS DECIMAL(18, 6))) AS s, count(*) AS n FROM (SELECT event_id % 40 AS worker, value FROM events WHERE event_id < (SELECT count(*) // 40 * 40 FROM events)) GROUP BY 1) SELECT round(sum(n) / max(s)::DOUBLE, 6) AS async_per_s, round((SELECT count(*) / sum(m) FROM (SELECT max(arrival) AS m FROM t GROUP BY iteration)), 6) AS sync_per_s FROM a")
def _(spark, sf_dir):
    """Updates a second that the asynchronous fleet applies, and steps a second of the fully synchronous one."""
    clocks = asy.worker_clocks(asy.work_trace(events(spark, sf_dir), 40, tr.shaped)).agg((F.count("*") / F.max("finish")).alias("async_per_s"))
    steps = tr.sync_steps(trace(spark, sf_dir, 40), 40).agg((F.count("*") / F.sum("step_time")).alias("sync_per_s"))
    return clocks.crossJoin(steps)
