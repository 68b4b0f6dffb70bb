"""Invariants, second implementations and plans of the optimization engine."""

import functools
import itertools

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from quorumgrad.config import FleetConfig, TrainConfig
from quorumgrad.metrics import curves as mc
from quorumgrad.models import BigramModel, LinearModel, LogisticModel, MlpModel, SoftmaxModel, SparseEmbeddingModel
from quorumgrad.models.exact import conditional_entropy, newton, solve_normal
from quorumgrad.optim.rules import RULES, AdaGrad, Adam, Ema, Momentum, RmsProp, Sgd, ShardPlan, constant, exponential, listed, stale_safe
from quorumgrad.optim.wide import touched, wide_step
from quorumgrad.plans import experiments, gradients, relational, schedules, streams
from quorumgrad.sources import features, sinks
from quorumgrad.sources.tables import read_table, read_with_schema, validate
from quorumgrad.streaming import servers
from quorumgrad.timing import asynchronous as asy
from quorumgrad.timing import busy, tradeoff
from quorumgrad.timing import trace as tr
from quorumgrad.train import distributed as td
from quorumgrad.train import replay as rp
from quorumgrad.train import sized as sz
from quorumgrad.train.gradient import full_loss, host_sums, merged_gradient, point_gradient, quorum_gradient, worker_sums
from quorumgrad.train.live import LiveQuorum

SF, SF2 = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def events(spark):
    return read_table(spark, SF2, "events", ["event_id", "value"])


@pytest.fixture(scope="module")
def trace(events):
    return tr.arrival_trace(events, 100)


@pytest.fixture(scope="module")
def batches(spark):
    rng = np.random.default_rng(0)
    rows = [(t, w, rng.normal(size=3).tolist(), float(rng.normal())) for t in range(4) for w in range(6) for _ in range(1 + (w + t) % 4)]
    return spark.createDataFrame(rows, "iteration int, worker int, x array<double>, y double").repartition(3)


def literal(spark, rows):
    return spark.createDataFrame(rows, "iteration int, worker int, arrival double")


# ---- models ----------------------------------------------------------------------------------------------------

RNG = np.random.default_rng(7)
CASES = [
    (LinearModel(4), RNG.normal(size=(9, 4)), RNG.normal(size=9)),
    (LogisticModel(4, 0.1), RNG.normal(size=(9, 4)), RNG.integers(0, 2, 9).astype(float)),
    (SoftmaxModel(4, 3, 0.1), RNG.normal(size=(9, 4)), RNG.integers(0, 3, 9)),
    (MlpModel((4, 5, 3), 3), RNG.normal(size=(9, 4)), RNG.integers(0, 3, 9)),
    (BigramModel(2, 4), np.stack([RNG.integers(0, 2, 9), RNG.integers(0, 4, 9), RNG.integers(1, 5, 9)], axis=1).astype(float), RNG.integers(0, 4, 9)),
    (SparseEmbeddingModel(6, 2), np.array([[0, 1, 2], [0, 3, 1], [1, 0, 1], [2, 5, 3]], float), np.array([0, 1, 1])),
]


@pytest.mark.parametrize(("model", "x", "y"), CASES, ids=lambda v: type(v).__name__)
def test_gradient_matches_central_differences(model, x, y):
    theta = np.random.default_rng(1).normal(size=model.size()) * 0.5
    g = model.grad(theta, x, y)
    eye = np.eye(model.size()) * 1e-6
    numeric = np.array([(model.loss(theta + e, x, y) - model.loss(theta - e, x, y)) / 2e-6 for e in eye])
    assert np.abs(g - numeric).max() < 1e-5


def test_layers_cover_the_parameters():
    model = MlpModel((4, 5), 3)
    assert sum(s.stop - s.start for s in model.layers()) == model.size() == len(model.init(1))


def test_exact_optima(spark):
    df = gradients.net_task(spark, SF)
    theta = solve_normal(df, ["x1", "x2", "x3"], "y")
    x = np.array(df.select("x1", "x2", "x3").collect())
    y = np.array(df.select("y").collect())[:, 0]
    assert np.abs(LinearModel(3).grad(theta, x, y)).max() < 1e-8
    lx, ly = RNG.normal(size=(200, 3)), RNG.integers(0, 2, 200).astype(float)
    assert np.abs(LogisticModel(3, 1e-2).grad(newton(lx, ly, 1e-2), lx, ly)).max() < 1e-10
    counts = spark.createDataFrame([(0, 0, 3), (0, 1, 1), (1, 0, 2)], "prev int, next int, n long")
    want = -(3 * np.log(0.75) + np.log(0.25)) / 6
    assert conditional_entropy(counts, ["prev"]).first()[0] == pytest.approx(want)


# ---- rules -----------------------------------------------------------------------------------------------------

def test_rules_against_plain_loops():
    gs, theta = RNG.normal(size=(4, 3)), np.ones(3)
    sgd, mom, ada, rms, adam = Sgd(constant(0.1)), Momentum(constant(0.1)), AdaGrad(constant(0.1)), RmsProp(constant(0.1)), Adam(constant(0.1))
    t = [theta.copy() for _ in range(5)]
    v, s, r, m1, m2 = (np.zeros(3) for _ in range(5))
    for k, g in enumerate(gs, 1):
        v, s, r = 0.9 * v + g, s + g * g, 0.9 * r + 0.1 * g * g
        m1, m2 = 0.9 * m1 + 0.1 * g, 0.999 * m2 + 0.001 * g * g
        want = [t[0] - 0.1 * g, t[1] - 0.1 * v, t[2] - 0.1 * g / (np.sqrt(s) + 1e-8), t[3] - 0.1 * g / (np.sqrt(r) + 1e-8), t[4] - 0.1 * (m1 / (1 - 0.9**k)) / (np.sqrt(m2 / (1 - 0.999**k)) + 1e-8)]
        t = [rule.step(x, g) for rule, x in zip((sgd, mom, ada, rms, adam), t, strict=True)]
        assert np.allclose(t, want)
    assert set(RULES) == {"sgd", "momentum", "adagrad", "rmsprop", "adam"}


def test_schedules_and_average():
    assert [listed([3, 2, 1])(t) for t in range(5)] == [3, 2, 1, 1, 1]
    assert exponential(1, 0.5, 10)(5) == pytest.approx(0.5**0.5) and exponential(1, 0.5, 10, staircase=True)(19) == 0.5
    assert stale_safe(constant(1.0), 20)(3) == 0.1 and stale_safe(constant(1.0), 19)(3) == 1
    ema = Ema(0.9)
    assert (ema.feed(np.ones(2)) == 1).all() and np.allclose(ema.feed(np.full(2, 2.0)), 1.1)
    zero = Ema(0.0)
    assert [float(zero.feed(np.array([x]))[0]) for x in (3.0, 5.0)] == [3, 5]


def test_shards_and_wide_steps(spark):
    plan = ShardPlan(10, 3)
    assert [s.stop - s.start for s in plan.slices()] == [3, 4, 3] and list(np.bincount(plan.shard_of())) == [3, 4, 3]
    theta = spark.createDataFrame([(int(plan.shard_of()[i]), i, 1.0, 0.0) for i in range(10)], "shard int, coord long, value double, slot double")
    g = spark.createDataFrame([(int(plan.shard_of()[i]), i, float(i)) for i in (2, 5)], "shard int, coord long, g double")
    for rule in ("sgd", "momentum", "adagrad", "rmsprop"):
        got = {r.coord: r.value for r in wide_step(theta, g, 0.1, rule).collect()}
        dense = np.zeros(10)
        dense[[2, 5]] = [2, 5]
        want = RULES[rule](constant(0.1)).step(np.ones(10), dense)
        assert np.allclose([got[i] for i in range(10)], want)
    assert touched(theta, g).count() == 2


# ---- schedules -------------------------------------------------------------------------------------------------

def test_quorum_partition_and_order(trace):
    rows = tr.sync_schedule(trace, 94)
    per = rows.groupBy("iteration").agg(F.count_if("used").alias("u"), F.count_if(~F.col("used")).alias("d"), F.countDistinct("worker").alias("w")).collect()
    assert {(r.u, r.d, r.w) for r in per} == {(94, 6, 100)}
    means = [r.mean_s for r in tr.arrival_profile(trace).orderBy("k").collect()]
    assert means == sorted(means)
    won = {(r.iteration, r.worker) for r in tr.winners(trace, 94).collect()}
    assert won == {(r.iteration, r.worker) for r in rows.where("used").collect()}


def test_clocks_are_ordered(trace):
    last = lambda df: df.agg(F.max("clock")).first()[0]
    fresh, full = last(tr.sync_steps(trace, 96)), last(tr.sync_steps(trace, 100))
    held = last(busy.busy_schedule(trace, [96]))
    assert fresh <= held + 1e-9 <= full and full == pytest.approx(last(busy.busy_schedule(trace, [100])))
    assert last(tr.shard_clock(trace, 94, 1)) >= last(tr.sync_steps(trace, 94)) - 1e-9
    assert last(tr.deadline_steps(trace, 1e9)) == pytest.approx(full)


def test_ties_nulls_and_partial_iterations(spark):
    t = literal(spark, [(0, 2, 1.0), (0, 1, 1.0), (0, 0, 1.0), (0, 3, None)])
    assert [(r.k, r.worker) for r in tr.kth_arrival(t).orderBy("k").collect()] == [(1, 0), (2, 1), (3, 2), (4, 3)]
    assert {r.worker for r in tr.sync_schedule(t, 4).where("used").collect()} == {0, 1, 2}
    e = spark.createDataFrame([(i, float(i)) for i in range(7)], "event_id long, value double")
    assert tr.arrival_trace(e, 3, "raw").count() == 6
    none = tr.deadline_steps(literal(spark, [(0, 0, 5.0), (0, 1, 6.0)]), 1.0).first()
    assert (none.n_used, none.step_time) == (1, 5.0)


def test_busy_clock_small_case():
    times = np.array([[1.0, 5.0], [1.0, 1.0], [1.0, 1.0]])
    assert busy.busy_clock(times, 1).tolist() == [1.0, 2.0, 3.0]
    assert busy.busy_clock(times, 2).tolist() == [5.0, 6.0, 7.0]


def test_async_schedule_against_a_loop(events):
    work = asy.work_trace(events, 8, tr.raw)
    got = {(r.worker, r.seq): (r.update, r.read_version, r.lag) for r in asy.async_schedule(work).collect()}
    durations = {}
    for r in work.collect():
        durations.setdefault(r.worker, {})[r.seq] = round(r.duration * 1e6)
    marks = sorted((sum(d[k] for k in range(s + 1)) if s < 3 else None, w, s) for w, d in durations.items() for s in range(3))
    clock = {w: list(itertools.accumulate(d[s] for s in sorted(d))) for w, d in durations.items()}
    order = sorted((c, w, s) for w, cs in clock.items() for s, c in enumerate(cs))
    read = dict.fromkeys(durations, 0)
    for u, (_, w, s) in enumerate(order):
        assert got[(w, s)] == (u, read[w], u - read[w])
        read[w] = u + 1
    assert len(marks) == 24
    one = asy.async_schedule(asy.work_trace(events, 1, tr.raw)).agg(F.max("lag")).first()[0]
    assert one == 0


def test_lag_tends_to_workers_less_one(events):
    for workers, least in ((8, 6.5), (40, 36.5)):
        mean = asy.lag_summary(asy.async_schedule(asy.work_trace(events, workers, tr.raw))).first().mean_lag
        assert least < mean < workers


def test_layers_read_and_send(spark, events):
    off = {r.layer: (r.read_at, r.send_at) for r in asy.layer_offsets(schedules.layer_table(spark, 3)).collect()}
    assert off[0] == pytest.approx((0, 1)) and off[2] == pytest.approx((2 / 9, 5 / 9))
    lags = {r.layer: r.mean_lag for r in schedules.QUERIES["staleness_by_layer"](spark, SF2).collect()}
    assert [lags[i] for i in range(18)] == sorted(lags.values(), reverse=True)
    assert lags[0] == pytest.approx(38.97, abs=0.5) and lags[17] == pytest.approx(13.3, abs=0.5)


def test_waves_cover_updates():
    assert asy.waves([0, 0, 1, 1, 4]) == [0, 0, 1, 1, 2]
    assert asy.waves([]) == []


def test_best_split(spark, events):
    for shape, best in (("shaped", 93), ("raw", 50)):
        est = tradeoff.time_to_converge(tr.arrival_trace(events, 100, shape), tradeoff.knots_frame(spark, tradeoff.PUBLISHED_KNOTS), 50, 100)
        assert tradeoff.best_split(est).first().n == best


def test_published_knots_are_endpoints(spark):
    rows = {r.n: r.iterations for r in tradeoff.interpolate(tradeoff.knots_frame(spark, tradeoff.PUBLISHED_KNOTS), 50, 100).collect()}
    assert len(rows) == 51 and rows[50] == 137.5e3 and rows[100] == pytest.approx(76.2e3)


# ---- training --------------------------------------------------------------------------------------------------

def numpy_rows(batches):
    out = {}
    for r in batches.collect():
        out.setdefault((r.iteration, r.worker), []).append((r.x, r.y))
    return {k: (np.array([a for a, _ in v]), np.array([b for _, b in v])) for k, v in out.items()}


def test_sync_is_the_mean_of_means(batches, spark):
    model, rows = LinearModel(3), numpy_rows(batches)
    chosen = {(t, w) for t in range(4) for w in (0, 2, 3, 5)}
    won = spark.createDataFrame(sorted(chosen), "iteration int, worker int")
    run = td.train_sync(batches, won, model, Sgd(constant(0.1)), 4)
    theta = np.zeros(3)
    for t in range(4):
        theta = theta - 0.1 * np.mean([model.grad(theta, *rows[(t, w)]) for w in (0, 2, 3, 5)], axis=0)
    assert np.allclose(run.theta, theta, atol=1e-12) and run.jobs == 4
    flat = np.zeros(3)
    for t in range(4):
        x, y = (np.concatenate(p) for p in zip(*[rows[(t, w)] for w in (0, 2, 3, 5)], strict=True))
        flat = flat - 0.1 * model.grad(flat, x, y)
    assert not np.allclose(flat, run.theta)
    merged = td.train_sync(batches, won, model, Sgd(constant(0.1)), 4, workers_per_host=3)
    assert np.allclose(merged.theta, run.theta)
    g, loss, n, sent = merged_gradient(batches.where("iteration = 0"), model, 0, np.zeros(3), 3)
    plain = quorum_gradient(batches.where("iteration = 0"), model, 0, np.zeros(3))
    assert sent == 2 and n == plain[2] and loss == pytest.approx(plain[1]) and np.allclose(g, plain[0])
    assert merged.messages == [2] * 4 or max(merged.messages) <= 2


def test_no_spares_is_full_sync_and_sharded_agrees(batches, spark):
    model = LinearModel(3)
    everyone = spark.createDataFrame([(t, w) for t in range(4) for w in range(6)], "iteration int, worker int")
    a = td.train_sync(batches, None, model, Sgd(constant(0.1)), 4).theta
    b = td.train_sync(batches, everyone, model, Sgd(constant(0.1)), 4).theta
    shards = everyone.crossJoin(spark.range(3).select(F.col("id").cast("int").alias("shard")))
    c = td.train_sync_sharded(batches, shards, model, [Sgd(constant(0.1)) for _ in range(3)], ShardPlan(3, 3), 4).theta
    assert np.allclose(a, b) and np.allclose(a, c)


def test_partitions_do_not_change_the_result(batches):
    model = LinearModel(3)
    runs = [td.train_sync(batches.repartition(n), None, model, Sgd(constant(0.1)), 3).theta for n in (1, 4, 8)]
    assert np.abs(np.diff(runs, axis=0)).max() < 1e-9


def test_empty_step_keeps_the_parameters(batches, spark):
    none = spark.createDataFrame([], "iteration int, worker int")
    assert (td.train_sync(batches, none, LinearModel(3), Sgd(constant(0.1)), 2).theta == 0).all()


def test_async_waves_equal_a_naive_loop(batches):
    model = LinearModel(3)
    flat = batches.withColumn("iteration", F.col("iteration") * 6 + F.col("worker")).withColumn("worker", F.lit(0))
    rows = numpy_rows(flat)
    reads = [0, 0, 1, 1, 3, 4, 4, 6, 7, 7, 8, 11]
    run = td.train_async(flat, [(u, u, v) for u, v in enumerate(reads)], model, Momentum(constant(0.05)))
    rule, versions = Momentum(constant(0.05)), [np.zeros(3)]
    for u, v in enumerate(reads):
        versions.append(rule.step(versions[-1], model.grad(versions[v], *rows[(u, 0)])))
    assert np.allclose(run.history, versions, atol=1e-12) and run.jobs < len(reads)
    fresh = td.train_async(flat, td.stale_schedule(8, lambda u: 0), model, Sgd(constant(0.05))).theta
    serial = td.train_sync(flat, None, model, Sgd(constant(0.05)), 8).theta
    assert np.allclose(fresh, serial, atol=1e-12)


def test_mixed_reads_assemble_slices(batches):
    model, slices = LinearModel(3), [slice(0, 1), slice(1, 3)]
    flat = batches.withColumn("iteration", F.col("iteration") * 6 + F.col("worker")).withColumn("worker", F.lit(0))
    rows, reads = numpy_rows(flat), [(0, 0), (0, 1), (1, 2), (1, 3), (4, 2), (5, 4)]
    run = td.train_async(flat, [(u, u, v) for u, v in enumerate(reads)], model, Sgd(constant(0.05)), slices=slices)
    versions = [np.zeros(3)]
    for u, v in enumerate(reads):
        seen = np.concatenate([versions[k][s] for k, s in zip(v, slices, strict=True)])
        versions.append(versions[-1] - 0.05 * model.grad(seen, *rows[(u, 0)]))
    assert np.allclose(run.history, versions, atol=1e-12)
    same = td.train_async(flat, [(u, u, (max(0, u - 2),) * 2) for u in range(6)], model, Sgd(constant(0.05)), slices=slices).theta
    assert np.allclose(same, td.train_async(flat, td.stale_schedule(6, lambda u: 2), model, Sgd(constant(0.05))).theta)


def test_losses_and_points(batches):
    model = LinearModel(3)
    x, y = (np.concatenate(p) for p in zip(*numpy_rows(batches).values(), strict=True))
    assert full_loss(batches, model, np.ones(3)) == pytest.approx(model.loss(np.ones(3), x, y))
    named = batches.sparkSession.createDataFrame([(i, [float(i), 1.0, -1.0], 0.5) for i in range(5)], "row_id long, x array<double>, y double")
    assert np.allclose(point_gradient(named, model, np.ones(3), 3), model.grad(np.ones(3), np.array([[3.0, 1.0, -1.0]]), np.array([0.5])))
    assert quorum_gradient(batches.where("iteration = 99"), model, 99, np.zeros(3))[2] == 0


def test_replay_lag_zero_is_serial_and_guards():
    x, y = RNG.normal(size=(50, 3)), RNG.normal(size=50)
    rows, model, none = rp.Rows(x, y, x, y, x, y), LinearModel(3), lambda th: {"loss": float(th.sum())}
    a = rp.replay_stale(model, rows, Sgd(constant(0.1)), rp.LagLaw("fixed", 0), 30, 4, 30, 5, none)[1]
    b = rp.replay_sync(model, rows, Sgd(constant(0.1)), np.ones(30), 1, 4, 30, 5, none)[1]
    assert np.allclose(a, b)
    for kind in ("fixed", "uniform", "geometric"):
        lag = rp.LagLaw(kind, 10).draw(4000, 1)
        assert abs(lag[200:].mean() - 10) < 1 and (lag <= np.arange(4000)).all()
    assert rp.LagLaw("fixed", 10, ramp=100).draw(200, 1)[50] <= 5
    assert rp.diverged(np.array([np.nan]), 0.1) and rp.diverged(np.zeros(1), 0.9) and not rp.diverged(np.zeros(1), 0.5)
    curve, theta, k = rp.with_restarts(lambda k: (rp.Curve(), np.array([float(k)])), 3, lambda th: -abs(th[0] - 1))
    assert k == 1


def test_bounded_rows_refuses_what_does_not_fit(spark):
    df = spark.createDataFrame([(i, [1.0] * 10, 1.0, "train") for i in range(10)], "row_id long, x array<double>, y double, split string")
    assert rp.bounded_rows(df).x.shape == (10, 10)
    with pytest.raises(ValueError, match="exceed"):
        rp.bounded_rows(df, most=100)


def test_steps_read_their_own_slots_and_drivers_get_a_row_a_worker(batches, spark):
    won = tr.winners(spark.createDataFrame([(t, w, float((w * 3 + t) % 6)) for t in range(4) for w in range(6)], "iteration int, worker int, arrival double"), 4)
    with td.slots(batches, won) as used:
        step = used.where(F.col("iteration") == 2)
        text = step._jdf.queryExecution().toString()
        assert "PartitionFilters: [isnotnull(iteration" in text and "Window" not in text
        assert len(used.inputFiles()) <= 4 * 8 and "LocalTableScan" not in text
        expected = {tuple(r) for r in won.where("iteration = 2").collect()}
        assert {tuple(r) for r in step.select("iteration", "worker").distinct().collect()} == expected
        for parts in (1, 7, 40):
            rows = worker_sums(step.repartition(parts), LinearModel(3), {2: np.ones(3)}).collect()
            assert len(rows) == len(expected)
            assert len(host_sums(step.repartition(parts), LinearModel(3), {2: np.ones(3)}, 3).collect()) <= 2


def test_runs_go_on_from_checkpoints(batches, spark):
    path = sinks.scratch_path(spark, "resume")
    for k, rule in enumerate((Sgd, Momentum, AdaGrad, Adam)):
        whole = td.train_sync(batches, None, LinearModel(3), rule(constant(0.05)), 4)
        td.train_sync(batches, None, LinearModel(3), rule(constant(0.05)), 2, checkpoint=f"{path}{k}")
        rest = td.train_sync(batches, None, LinearModel(3), rule(constant(0.05)), 4, checkpoint=f"{path}{k}")
        assert rest.jobs == 2 and np.allclose(rest.theta, whole.theta) and np.allclose(rest.averaged, whole.averaged)


def test_async_waves_over_the_whole_tables_are_the_numpy_loop(spark):
    """Forty workers, two hundred updates, every event and item: the query's losses against a loop that keeps all versions."""
    got = {r.update: r for r in gradients.QUERIES["async_waves_sgd"](spark, SF).collect()}
    plan = asy.async_schedule(asy.work_trace(gradients.folded(spark, SF, 200), 40, tr.raw)).orderBy("update").collect()
    rows = gradients.wide_slots(spark, SF, 200).toPandas()
    x, y, slot = rows[["x1", "x2", "x3"]].to_numpy(), rows["y"].to_numpy(), rows["slot"].to_numpy()
    model, versions = LinearModel(3), [np.zeros(3)]
    for r in plan:
        own = slot == r.update
        versions.append(versions[-1] - 0.01 * model.grad(versions[r.read_version], x[own], y[own]) if own.any() else versions[-1])
    assert len(plan) == 200 and max(r.lag for r in plan) > 30
    for u, r in got.items():
        assert r.loss == pytest.approx(float(0.5 * np.mean((x @ versions[u] - y) ** 2)), abs=1e-5)
    assert got[200].loss < got[0].loss / 3


def test_shared_folder_is_not_made_up_on_a_cluster():
    class Conf:
        def get(self, *a):
            return None

    class Context:
        master = "spark://host:7077"

        def getConf(self):
            return Conf()

        def getCheckpointDir(self):
            return None

    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        sinks.shared_dir(type("Session", (), {"conf": Conf(), "sparkContext": Context()})())


def test_busy_training_is_the_loop(spark):
    """Steps close with the first gradients of workers that were free in time; the parameters follow a numpy loop."""
    times = np.zeros((5, 10))
    for r in gradients.raw_trace(spark, SF).collect():
        times[r.iteration, r.worker] = r.arrival
    clock, counted = busy.busy_steps(times, 8)
    assert (counted.sum(1) == 8).all() and (np.diff(clock) > 0).all()
    rows = numpy_rows(gradients.vectors(gradients.net_task(spark, SF)))
    theta, model = np.zeros(3), LinearModel(3)
    for t in range(5):
        theta = theta - 0.3 * 0.9**t * np.mean([model.grad(theta, *rows[(t, w)]) for w in np.flatnonzero(counted[t]) if (t, w) in rows], axis=0)
    got = {r.coord: r.theta for r in gradients.QUERIES["busy_sgd_5"](spark, SF).where("step = 5").collect()}
    assert [got[i] for i in range(3)] == pytest.approx(theta.tolist(), abs=2e-6)


def test_live_steps_lower_the_loss(spark):
    loss = [r.loss for r in sorted(experiments.QUERIES["live_quorum"](spark, SF).collect())]
    assert len(loss) == 5 and all(b < a for a, b in zip(loss, loss[1:])) and loss[-1] < 0.95 * loss[0]


def test_a_run_that_blows_up_stops_and_says_so():
    x, y = RNG.normal(size=(50, 3)), RNG.normal(size=50)
    rows, model = rp.Rows(x, y, x, y, x, y), LinearModel(3)
    curve, theta = rp.replay_stale(model, rows, Sgd(constant(50.0)), rp.LagLaw("fixed", 5), 3000, 4, 30, 5, lambda th: {"test_error": 0.1})
    assert ("exploded", 1.0) in {(m, v) for _, _, m, v in curve.rows} and max(u for u, *_ in curve.rows) < 3000 and not np.isfinite(theta).all()


def test_live_quorum(spark):
    done, _ = LiveQuorum(spark, 2, 1).step(lambda w: spark.range(10).where(F.col("id") > w).count())
    assert len(done) == 2 and all(v == 9 - w for w, v in done.items())
    with pytest.raises(RuntimeError):
        LiveQuorum(spark, 1, 0).step(lambda w: 1 / 0)


def test_configured_fleets_close_as_they_say(batches, spark):
    arrivals = spark.createDataFrame([(t, w, float((w * 5 + t * 2) % 7)) for t in range(4) for w in range(6)], "iteration int, worker int, arrival double")
    fleet, model, rule = FleetConfig(4, 2, 3), LinearModel(3), lambda: Sgd(constant(0.1))
    direct = {
        "quorum": tr.winners(arrivals, 4), "deadline": tr.deadline_schedule(arrivals, 3.0).where("used").select("iteration", "worker"),
        "either": tr.deadline_schedule(arrivals, 3.0, 4).where("used").select("iteration", "worker"),
    }
    thetas = []
    for close, won in direct.items():
        config = TrainConfig(fleet, 4, close=close, deadline=3.0)
        thetas.append(td.train_fleet(config, batches, arrivals, model, rule).theta)
        assert np.allclose(thetas[-1], td.train_sync(batches, won, model, rule(), 4).theta)
    busy_run = td.train_fleet(TrainConfig(fleet, 4, straggler="busy"), batches, arrivals, model, rule).theta
    assert np.allclose(busy_run, td.train_sync(batches, busy.busy_winners(arrivals, 4), model, rule(), 4).theta)
    per_shard = td.train_fleet(TrainConfig(fleet, 4, quorum_scope="shard"), batches, arrivals, model, rule).theta
    won = td.closing(TrainConfig(fleet, 4, quorum_scope="shard"), arrivals)
    assert won.groupBy("iteration", "shard").count().where("count <> 4").isEmpty() and won.select("shard").distinct().count() == 3
    assert np.allclose(per_shard, td.train_sync_sharded(batches, won, model, [rule() for _ in range(3)], ShardPlan(3, 3), 4).theta)
    assert np.allclose(td.train_fleet(TrainConfig(fleet, 4, merge_hosts=3), batches, arrivals, model, rule).theta, thetas[0])


def test_configurations():
    with pytest.raises(ValueError):
        FleetConfig(2, -1)
    with pytest.raises(ValueError):
        TrainConfig(FleetConfig(2, 1), close="deadline")
    assert FleetConfig(94, 6).workers == 100


# ---- behaviour that the reference reports ----------------------------------------------------------------------

def test_staleness_hurts_beyond_the_knee(spark):
    rows = {(r.variant, r.lag): r for r in experiments.QUERIES["stale_sweep"](spark, SF2).collect()}
    assert rows[("momentum", 50)].mean_error > 3 * rows[("momentum", 0)].mean_error
    assert rows[("fixed", 50)].mean_error > rows[("fixed", 0)].mean_error


STALE = {
    "stale_sweep": {"geometric": {"law": "geometric", "lag": 20}},
    "stale_ramp": {"ramp": {"mu": 0.9, "rate": 2.0, "epochs": 6, "ramp_epochs": 3, "lag": 30}},
    "stale_lowlr": {"low": {"mu": 0.9, "rate": 2.0, "factor": 0.1, "lag": 20}, "high": {"mu": 0.9, "rate": 1e308, "lag": 20}},
    "stale_restart": {"best": {"mu": 0.9, "rate": 2.0, "tries": 3, "lag": 30}},
}


@pytest.mark.parametrize("name", STALE)
def test_stale_runs_on_rows_that_stay_with_executors(spark, monkeypatch, name):
    """The very curves of the replay on matrices, with no table at the driver (which was refused over 256 MiB)."""
    rows, runs = rp.bounded_rows(features.planted(spark, SF2)), {f"planted/{v}": {"task": "planted", "rate": 8.0} | s for v, s in STALE[name].items()}
    monkeypatch.setattr(rp, "bounded_rows", None)
    got: dict[str, list] = {}
    for r in experiments.stale_curves(spark, {"planted": sz.table(features.planted(spark, SF2))}, runs).collect():
        got.setdefault(r.run_id, []).append(tuple(r)[1:])
    for v, s in runs.items():
        epoch = -(-len(rows.y) // 32)
        updates, model = max(600, s.get("epochs", 0) * epoch), SoftmaxModel(64, 2)
        measure = lambda th: {"test_error": 1 - rp.accuracy(model, th, rows.x_test, rows.y_test), "train_error": 1 - rp.accuracy(model, th, rows.x, rows.y), "validation_error": 1 - rp.accuracy(model, th, rows.x_val, rows.y_val)}
        law = rp.LagLaw(s.get("law", "fixed"), s["lag"], round(s.get("ramp_epochs", 0) * epoch))
        train = lambda k: rp.replay_stale(model, rows, Momentum(stale_safe(constant(s["rate"]), s["lag"], s.get("factor", 1.0)), mu=s.get("mu", 0.0)), law, updates, 32, max(30, updates // 20), 10 * k + 1, measure)  # noqa: B023, E731
        want = rp.with_restarts(train, s.get("tries", 1), lambda th: rp.accuracy(model, th, rows.x_val, rows.y_val))[0].rows
        assert [r[:3] for r in got[v]] == [r[:3] for r in want] and np.allclose([r[3] for r in got[v]], [r[3] for r in want])
    assert name != "stale_lowlr" or got["planted/high"][-1][2] == "exploded"


@pytest.mark.parametrize("method", ["sync", "async"])
def test_fleets_on_rows_that_stay_with_executors(spark, method):
    """The very curves of the replay on matrices."""
    rows, n, model = rp.bounded_rows(features.planted(spark, SF2)), 53, experiments.FLEET_MODELS["planted"]
    times = {n: experiments.arrays(spark, SF2, n, 402)}
    run = {"planted/x": {"task": "planted", "method": method, "fleet": n, "rate": 0.08, "seed": 2}}
    got = [r[1:] for r in experiments.fleet_runs(spark, {"planted": sz.table(features.planted(spark, SF2))}, times, run)]
    measure = lambda th: {"precision": rp.accuracy(model, th, rows.x_test, rows.y_test), "validation": rp.accuracy(model, th, rows.x_val, rows.y_val), "train": rp.accuracy(model, th, rows.x, rows.y)}
    if method == "sync":
        want = rp.replay_sync(model, rows, Sgd(constant(0.08)), experiments.step_times(times[n], n - 3, 200), n - 3, 4, 10, 2, measure, ema=0.5)[0].rows
    else:
        reads, clock = experiments.async_plan(times[n], 200 * n)
        want = rp.replay_async(model, rows, Sgd(constant(0.08)), reads, clock, 4, 10 * n, 2, measure, ema=0.5 ** (1 / n))[0].rows
    assert len(got) == 60 and [r[:3] for r in got] == [r[:3] for r in want] and np.allclose([r[3] for r in got], [r[3] for r in want])


def test_restarts_measured_on_rows_that_stay_with_executors(spark, monkeypatch):
    """The whole query on one task is what the replay on matrices gives; no table comes to the driver."""
    rows, model = rp.bounded_rows(features.planted(spark, SF2)), SoftmaxModel(64, 2)
    monkeypatch.setattr(rp, "bounded_rows", None)
    monkeypatch.setattr(experiments, "LAGS", (0, 30))
    monkeypatch.setattr(experiments, "_stale", functools.partial(experiments._stale, tasks=("planted",)))
    got = {(r.variant, r.lag): r for r in experiments.QUERIES["stale_restart"](spark, SF2).collect()}
    measure = lambda th: {"test_error": 1 - rp.accuracy(model, th, rows.x_test, rows.y_test), "train_error": 1 - rp.accuracy(model, th, rows.x, rows.y)}
    for variant, tries in (("plain", 1), ("best_of_3", 3)):
        for lag in (0, 30):
            train = lambda k: rp.replay_stale(model, rows, Momentum(constant(2.0), mu=0.9), rp.LagLaw("fixed", lag), 600, 32, 30, 10 * k + 1, measure)  # noqa: B023, E731
            late = [v for u, _, m, v in rp.with_restarts(train, tries, lambda th: rp.accuracy(model, th, rows.x_val, rows.y_val))[0].rows if m == "test_error" and u > 300]
            r = got.pop((variant, lag))
            assert [r.mean_error, r.spread, r.worst] == pytest.approx([np.mean(late), np.std(late, ddof=1), max(late)], abs=2e-6) and r.exploded_at is None
    assert not got


@pytest.mark.parametrize("name", ["sync_vs_async_epoch_time", "sync_vs_async_epochs", "sync_vs_async_time"])
def test_fleets_measured_on_rows_that_stay_with_executors(spark, monkeypatch, name):
    """The whole query on one task and fleet is what the replay on matrices gives; no table comes to the driver."""
    rows, n, model = rp.bounded_rows(features.planted(spark, SF2)), 53, experiments.FLEET_MODELS["planted"]
    monkeypatch.setattr(rp, "bounded_rows", None)
    monkeypatch.setattr(experiments, "FLEETS", {n: 3})
    monkeypatch.setattr(experiments, "GRID", {"sync": (0.125, 0.5), "async": (0.02,)})
    monkeypatch.setattr(experiments, "fleet_curves", functools.partial(experiments.fleet_curves, tasks=("planted",), seeds=2))
    got = {r.method: r for r in experiments.QUERIES[name](spark, SF2).collect()}
    times = experiments.arrays(spark, SF2, n, 402)
    reads, clock = experiments.async_plan(times, 200 * n)
    measure = lambda th: {"precision": rp.accuracy(model, th, rows.x_test, rows.y_test), "validation": rp.accuracy(model, th, rows.x_val, rows.y_val)}
    train = {
        "sync": lambda rate, seed: rp.replay_sync(model, rows, Sgd(constant(rate)), experiments.step_times(times, n - 3, 200), n - 3, 4, 10, seed, measure, ema=0.5)[0].rows,
        "async": lambda rate, seed: rp.replay_async(model, rows, Sgd(constant(rate)), reads, clock, 4, 10 * n, seed, measure, ema=0.5 ** (1 / n))[0].rows,
    }
    assert set(got) == set(train)
    for method, run in train.items():
        rate = max(experiments.GRID[method], key=lambda r: ([v for _, _, m, v in run(r, 1) if m == "validation"][-1], -r))  # noqa: B023
        found = []
        for seed in (1, 2):
            curve = [(u if method == "sync" else u // n, c, v) for u, c, m, v in run(rate, seed) if m == "precision"]
            near = [p for p in curve if abs(p[2] - max(v for *_, v in curve)) <= 0.01]
            found.append({"epochs": near[0][0], "seconds": near[0][1], "mean_s": curve[-1][1] / curve[-1][0]})
        column = {"sync_vs_async_epoch_time": "mean_s", "sync_vs_async_epochs": "epochs", "sync_vs_async_time": "seconds"}[name]
        values = [f[column] for f in found]
        assert got[method].seeds == 2 and [got[method][column], got[method][f"{column}_sd"]] == pytest.approx([np.mean(values), np.std(values, ddof=1)], abs=2e-6)


def test_a_server_keeps_state_once_a_batch():
    """Two batches of one server: state calls follow the workers, not the gradients."""
    import pandas as pd

    calls, kept = [], {}

    class Value:
        def exists(self):
            return "v" in kept

        def get(self):
            return kept["v"]

        def update(self, v):
            kept["v"] = v

    class Map:
        def containsKey(self, k):
            return k in kept

        def getValue(self, k):
            return kept[k]

        def updateValue(self, k, v):
            calls.append(k)
            kept[k] = v

    server, out = servers.ApplyCounter(), []
    server.version, server.read = Value(), Map()
    frame = pd.DataFrame({"shard": 1, "worker": np.arange(4000) % 7 % 3, "seq": np.arange(4000), "finish": np.arange(4000.0)})
    for half in (frame[:1500], frame[1500:]):
        out += [*server.handleInputRows((1,), iter([half.sample(frac=1, random_state=1)]), None)]
    got, last = pd.concat(out), {}
    for u, (worker, seq) in enumerate(zip(frame["worker"], frame["seq"])):
        assert tuple(got.iloc[u]) == (1, u, worker, seq, last.get(worker, 0), u - last.get(worker, 0))
        last[worker] = u + 1
    assert len(calls) <= 6


def test_more_gradients_need_fewer_iterations(spark):
    rows = {r.n: r.iterations for r in experiments.QUERIES["iters_vs_n"](spark, SF2).collect()}
    assert rows[50] > rows[80] > rows[100] and 1.5 < rows[50] / rows[100] < 2.5


def test_small_rates_never_reach_tight_thresholds(spark):
    rows = {(r.rate, r.eps): r.iteration for r in experiments.QUERIES["epochs_to_eps"](spark, SF2).collect()}
    assert rows[(1.125, 0.005)] is None and rows[(9.0, 0.02)] is not None


def test_gradient_variance_falls_with_workers(spark):
    rows = {r.n: r.var_x1000 for r in gradients.QUERIES["grad_variance"](spark, SF2).collect()}
    assert rows[1] > rows[2] > rows[5] > rows[10] and 3 < rows[1] / rows[10] < 30


def test_a_replay_takes_the_head_of_a_trace_of_any_length(spark, monkeypatch):
    """Nine million arrivals were refused once, and all of a shorter trace's rows came to the driver."""
    long = spark.range(9_000_000).select(F.expr("CAST(id DIV 8 AS INT)").alias("iteration"), F.expr("CAST(id % 8 AS INT)").alias("worker"), (F.col("id") * 0.5).alias("arrival"))
    monkeypatch.setattr(experiments, "trace", lambda spark, sf_dir, workers: long)
    assert (experiments.arrays(spark, "", 8, 402) == np.arange(402 * 8).reshape(402, 8) * 0.5).all()


@pytest.mark.parametrize("name", ["nll_curve", "time_to_nll", "nll_best_so_far"])
def test_likelihood_curves_hang_on_the_trace_a_replay_goes_through(spark, monkeypatch, name):
    """The same rows as with the whole trace at the driver, where no more than its own iterations come to it."""
    real, sent = experiments.arrays, []

    def whole(spark, sf_dir, workers, most):
        pdf = experiments.trace(spark, sf_dir, workers).toPandas().sort_values(["iteration", "worker"])
        sent.append((real(spark, sf_dir, workers, most).shape[0], most))
        return pdf["arrival"].to_numpy().reshape(-1, workers)

    got = sorted(map(str, experiments.QUERIES[name](spark, SF2).collect()))
    monkeypatch.setattr(experiments, "arrays", whole)
    assert got == sorted(map(str, experiments.QUERIES[name](spark, SF2).collect()))
    assert len(sent) == 3 and all(n <= most for n, most in sent)


def test_likelihood_nears_the_entropy(spark):
    best = experiments.QUERIES["nll_exact"](spark, SF2).first().nll
    serial = experiments.QUERIES["nll_best_so_far"](spark, SF2).where("run_id = 'serial/1'").agg(F.min("best")).first()[0]
    assert best < serial < best + 0.3


# ---- measures, sources, plans ----------------------------------------------------------------------------------

def test_first_reach_is_null_when_never(spark):
    c = spark.createDataFrame([("a", 1, 1.0, 5.0), ("a", 2, 2.0, 3.0)], "run_id string, iteration long, clock double, value double")
    assert mc.first_reach(c, 1.0).first().iteration is None and mc.first_reach(c, 4.0).first().iteration == 2


def test_checkpoints_and_schemas(spark):
    path = sinks.scratch_path(spark, "theta")
    assert sinks.versions(spark, path) == []
    for v in (1, 2):
        sinks.checkpoint_theta(spark, path, v, np.array([v, 2.0]))
    assert sinks.versions(spark, path) == [1, 2] and sinks.load_theta(spark, path)[1].tolist() == [2.0, 2.0]
    with pytest.raises(ValueError, match="l_tax"):
        validate(read_table(spark, SF, "lineitem").drop("l_tax"), read_table(spark, SF, "lineitem").schema, "lineitem")
    with pytest.raises(ValueError):
        read_with_schema(spark, path, "xml", read_table(spark, SF, "nation").schema)


def test_word_vectors_agree(spark):
    docs = read_table(spark, SF, "documents", ["doc_id", "text"]).where("doc_id < 12")
    a = {r.doc_id: r.x for r in features.word_vectors(docs, "doc_id", 32).collect()}
    b = {r.doc_id: r.x for r in docs.select("doc_id", features.hashed_words(F.col("text"), 32).alias("x")).collect()}
    assert all(np.allclose(a[k], b[k]) for k in a)


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans_prune_and_limit(spark, events):
    text = plan(tr.winners(tr.arrival_trace(events, 100), 94))
    assert "WindowGroupLimit" in text and "ReadSchema: struct<event_id:bigint,value:double>" in text
    raw = plan(gradients.raw_trace(spark, SF))
    assert "PushedFilters: []" in raw and "partial_sum" in raw  # the whole trace, summed before it is shuffled
    docs = plan(relational.QUERIES["filter_split"](spark, SF))
    assert "ReadSchema: struct<doc_id:bigint,lang:string>" in docs


SMALL = [n for m in (schedules, gradients, relational) for n in m.ORACLES]


@pytest.mark.parametrize("name", SMALL)
def test_queries_equal_their_sql(spark, name):
    con = duckdb.connect()
    for t in ("region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations").split():
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF2}/{t}.parquet'")
    df = entry.queries()[name](spark, SF2)
    want = con.sql(entry.oracle_sql()[name])
    assert sorted(df.columns) == sorted(want.columns)
    order = sorted(df.columns)
    key = lambda rows: sorted(tuple(str(v) for v in r) for r in rows)
    got = key([tuple(r[c] for c in order) for r in df.collect()])
    assert got == key(want.project(", ".join(f'"{c}"' for c in order)).fetchall())


def test_streams_equal_batches(spark):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW events AS SELECT * FROM '{SF}/events.parquet'")
    for name in ("stream_quorum", "stream_deadline", "stream_deadline_late", "stream_session", "stream_dedup"):
        df = streams.QUERIES[name](spark, SF)
        order = sorted(df.columns)
        want = con.sql(streams.ORACLES[name]).project(", ".join(order)).fetchall()
        assert sorted(str(tuple(r[c] for c in order)) for r in df.collect()) == sorted(str(tuple(r)) for r in want), name


def test_online_training_goes_on_after_a_failure(spark):
    """A batch run again, and a new driver, start from what the batch before left; momentum is kept too."""
    batch = lambda k: spark.createDataFrame([([1.0, k + i / 10], 1.0 + k) for i in range(5)], "x array<double>, y double")
    runs = []
    for again in (False, True):
        path = sinks.scratch_path(spark, "online")
        make = lambda: servers.OnlineTrainer(LinearModel(2), lambda: Momentum(constant(0.1)), np.zeros(2), path)  # noqa: B023, E731
        trainer = make()
        for k in range(3):
            trainer(batch(k), k)
            if again:
                trainer = make()
                trainer(batch(k), k)
        runs.append(trainer.history(spark))
    assert [k for k, _ in runs[0]] == [0, 1, 2]
    assert all(np.allclose(a, b) for (_, a), (_, b) in zip(*runs, strict=True))


def test_entry_runs(spark):
    rows = entry.entry(spark).collect()
    assert rows and rows[-1].loss < rows[0].loss
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["decay_recursive", "draws", "interp_iters", "join_cross_grid", "join_range_knots", "udtf_replay"])
def test_queries_that_read_a_table(spark, name):
    assert any(entry.queries()[name](spark, SF).inputFiles())


def test_a_sparse_model_leaves_its_examples_with_executors(spark, monkeypatch):
    monkeypatch.setattr(type(spark.range(1)), "toPandas", lambda df: pytest.fail("a table at the driver"))
    rows = experiments.QUERIES["sparse_lm"](spark, SF).collect()
    assert len(rows) == 45 and {r.metric for r in rows} == {"nll", "accuracy", "touched"}


def test_language_vectors_in_parts_are_the_words_counted(spark, monkeypatch):
    """A worker holds few rows' vectors and few words' buckets; what it forgets and looks up again changes no vector."""
    docs = features.read_table(spark, SF, "documents", ["doc_id", "text"])
    want = {r.doc_id: r.x for r in features.word_vectors(docs, "doc_id").collect()}
    monkeypatch.setattr(features, "PART", 3)
    monkeypatch.setattr(features, "HELD", 5)
    got = {r.row_id: r.x for r in features.languages(spark, SF).collect()}
    assert got and all(np.allclose(x, want[i], atol=1e-12) for i, x in got.items())
