"""Training with one Spark job per step (synchronous) or per wave (asynchronous, stale).

Timing is decided first: a schedule says which worker's gradient counts in which step and at which version it was
computed.  Rows of gradients that count are then written once, a folder per step (``slots``), so that every job reads
its own step's files alone and no job works out winners again.  What comes back is one vector per worker or host.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field, fields

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..config import TrainConfig
from ..models import Model
from ..optim.rules import Ema, Rule, ShardPlan
from ..sources.sinks import checkpoint_run, drop_path, load_run, scratch_path
from ..timing import busy
from ..timing import trace as tr
from ..timing.asynchronous import waves
from .gradient import merged_gradient, quorum_gradient, worker_gradients


@dataclass
class Trained:
    """Parameters after the run, their average, and all versions kept."""

    theta: np.ndarray
    averaged: np.ndarray
    history: list[np.ndarray] = field(default_factory=list)
    averages: list[np.ndarray] = field(default_factory=list)
    losses: list[float] = field(default_factory=list)
    messages: list[int] = field(default_factory=list)
    jobs: int = 0


@contextmanager
def slots(batches: DataFrame, winners: DataFrame | None = None, spread: int = 8) -> Iterator[DataFrame]:
    """``batches`` (iteration, worker, x, y), the winners' rows alone, written by iteration for the length of a run.

    An iteration has ``spread`` files at most; a scan for it is pruned to them.
    """
    spark, path = batches.sparkSession, scratch_path(batches.sparkSession, "slots")
    rows = batches.select("iteration", "worker", "x", "y")
    used = rows.join(winners, ["iteration", "worker"], "left_semi") if winners is not None else rows
    try:
        used.repartition("iteration", F.pmod(F.col("worker"), F.lit(spread))).write.partitionBy("iteration").parquet(path)
        yield spark.read.schema(rows.schema).parquet(path).select("iteration", "worker", "x", "y")
    finally:
        drop_path(spark, path)


def _state(rule: Rule, theta: np.ndarray, average: Ema, averaged: np.ndarray) -> dict:
    kept = {f.name: getattr(rule, f.name) for f in fields(rule) if f.name != "rate"}
    return {"theta": theta, "averaged": averaged, **({} if average.value is None else {"ema": average.value}), **{f"rule.{k}": v for k, v in kept.items()}}


def _restore(state: dict, rule: Rule, average: Ema) -> tuple[np.ndarray, np.ndarray]:
    for k, v in state.items():
        if k.startswith("rule."):
            setattr(rule, k[5:], int(v) if k == "rule.t" else v)
    average.value = state.get("ema")
    return state["theta"], state["averaged"]


def train_sync(
    batches: DataFrame, winners: DataFrame | None, model: Model, rule: Rule, steps: int, theta: np.ndarray | None = None, ema: float = 0.9, workers_per_host: int = 1,
    guard: Callable[[np.ndarray, float], bool] | None = None, checkpoint: str | None = None, every: int = 1,
) -> Trained:
    """Steps over ``batches`` (iteration, worker, x, y).

    ``winners`` (iteration, worker) are the gradients that close each step (none: all workers).  Serial training is
    one worker, full synchronous training has all as winners, spares and deadlines differ in the winners alone.
    A step without any gradient leaves the parameters as they are.

    With ``checkpoint`` the run's whole state is written to that folder after each ``every`` steps, and a run that
    finds some there goes on from the newest; ``history`` then begins with what was loaded.
    """
    spark = batches.sparkSession
    average, first = Ema(ema), 0
    theta = model.init() if theta is None else theta
    averaged = theta.copy()
    if checkpoint and (found := load_run(spark, checkpoint)):
        first, state = found
        theta, averaged = _restore(state, rule, average)
    out = Trained(theta, averaged, [theta.copy()], [averaged.copy()])
    with slots(batches, winners) as used:
        for t in range(first, steps):
            rows = used.where(F.col("iteration") == t)
            if workers_per_host > 1:
                g, loss, n, sent = merged_gradient(rows, model, t, theta, workers_per_host)
            else:
                g, loss, n = quorum_gradient(rows, model, t, theta)
                sent = n
            out.jobs += 1
            out.averaged = average.feed(theta).copy()
            if n:
                theta = rule.step(theta, g)
            out.losses.append(loss)
            out.messages.append(sent)
            out.history.append(theta.copy())
            out.averages.append(out.averaged)
            if checkpoint and ((t + 1) % every == 0 or t + 1 == steps):
                checkpoint_run(spark, checkpoint, t + 1, _state(rule, theta, average, out.averaged))
            if guard and guard(theta, loss):
                break
    out.theta = theta
    return out


def train_sync_sharded(batches: DataFrame, shard_winners: DataFrame, model: Model, rules: list[Rule], plan: ShardPlan, steps: int) -> Trained:
    """Every server moves its slice by its own quorum (iteration, shard, worker); a worker's gradient is computed once,
    and only if some server uses it."""
    theta = model.init()
    out = Trained(theta, theta.copy(), [theta.copy()])
    chosen: dict[int, dict[int, set[int]]] = {}
    shard_winners = shard_winners.where(F.col("iteration") < steps)
    for r in shard_winners.collect():  # steps x shards x quorum
        chosen.setdefault(r.iteration, {}).setdefault(r.shard, set()).add(r.worker)
    with slots(batches, shard_winners.select("iteration", "worker").distinct()) as used:
        for t in range(steps):
            found = worker_gradients(used.where(F.col("iteration") == t), model, {t: theta})
            theta = theta.copy()
            for j, (part, rule) in enumerate(zip(plan.slices(), rules, strict=True)):
                own = [g[part] for (_, w), (_, _, g) in found.items() if w in chosen[t][j]]
                if own:
                    theta[part] = rule.step(theta[part], np.mean(own, axis=0))
            out.history.append(theta)
            out.jobs += 1
    out.theta = theta
    return out


def closing(config: TrainConfig, arrivals: DataFrame) -> DataFrame:
    """(iteration, worker) of the gradients that close each step, as a configuration says; with a quorum per shard
    (iteration, shard, worker)."""
    quorum = config.fleet.quorum
    arrivals = arrivals.where(F.col("iteration") < config.steps)
    if config.quorum_scope == "shard":
        order = W.partitionBy("iteration", "shard").orderBy("arrival", "worker")
        ranked = tr.shard_trace(arrivals, config.fleet.shards).withColumn("rank", F.row_number().over(order))
        return ranked.where(F.col("rank") <= quorum).select("iteration", "shard", "worker")
    if config.straggler == "busy":
        return busy.busy_winners(arrivals, quorum)
    if config.close == "quorum":
        return tr.winners(arrivals, quorum)
    timed = tr.deadline_schedule(arrivals, config.deadline, quorum if config.close == "either" else None)
    return timed.where("used").select("iteration", "worker")


def train_fleet(config: TrainConfig, batches: DataFrame, arrivals: DataFrame, model: Model, rule: Callable[[], Rule], checkpoint: str | None = None) -> Trained:
    """A synchronous run of a configured fleet over ``batches`` (iteration, worker, x, y) and ``arrivals``; ``rule`` makes
    a fresh rule (one per shard with a quorum per shard)."""
    won = closing(config, arrivals)
    if config.quorum_scope == "shard":
        plan = ShardPlan(len(model.init()), config.fleet.shards)
        return train_sync_sharded(batches, won, model, [rule() for _ in range(config.fleet.shards)], plan, config.steps)
    return train_sync(batches, won, model, rule(), config.steps, ema=config.ema_decay, workers_per_host=config.merge_hosts, checkpoint=checkpoint, every=config.eval_every)


def train_async(batches: DataFrame, schedule: list[tuple[int, int, int | tuple[int, ...]]], model: Model, rule: Rule, ema: float = 0.9, slices: list[slice] | None = None, history: bool = True) -> Trained:
    """Updates in order of ``schedule``: (update, iteration key of its rows, version read).

    Updates whose versions exist already run as one job, each at its own version; the driver keeps versions from the
    oldest that is still to be read, and all of them only with ``history``.  Rows of ``batches`` are keyed by
    (iteration, worker) with iteration = update.  With ``slices`` (parameter servers or layers) a version is a tuple,
    one per slice: a gradient then mixes versions, as reads that are not consistent do.
    """
    theta = model.init()
    average = Ema(ema)
    out = Trained(theta, theta.copy(), [theta.copy()])
    versions = {0: theta}
    reads = [v if isinstance(v, tuple) else (v,) for _, _, v in schedule]
    oldest = [min(v) for v in reads]
    later = np.minimum.accumulate(np.array(oldest[::-1], dtype=int))[::-1] if reads else np.empty(0, int)
    number = waves([max(v) for v in reads])

    def seen(v: tuple[int, ...]) -> np.ndarray:
        if slices is None:
            return versions[v[0]]
        mixed = np.empty_like(theta)
        for k, part in zip(v, slices, strict=True):
            mixed[part] = versions[k][part]
        return mixed

    at = 0
    with slots(batches) as used:
        while at < len(schedule):
            to = at
            while to < len(schedule) and number[to] == number[at]:
                to += 1
            wave = [(schedule[i][0], reads[i]) for i in range(at, to)]
            rows = used.where(F.col("iteration").isin([u for u, _ in wave]))
            found = worker_gradients(rows, model, {u: seen(v) for u, v in wave})
            grads: dict[int, list[np.ndarray]] = {}
            for (u, _), (_, _, g) in found.items():
                grads.setdefault(u, []).append(g)
            out.jobs += 1
            for u, _ in wave:
                out.averaged = average.feed(theta).copy()
                if u in grads:
                    theta = rule.step(theta, np.mean(grads[u], axis=0))
                versions[u + 1] = theta
                if history:
                    out.history.append(theta)
            low = int(later[to]) if to < len(schedule) else to
            versions = {k: v for k, v in versions.items() if k >= low}
            at = to
    out.theta = theta
    return out


def stale_schedule(updates: int, lag: Callable[[int], int]) -> list[tuple[int, int, int]]:
    """A schedule in which update ``u`` uses parameters ``lag(u)`` updates old (as old as there are)."""
    return [(u, u, max(0, u - lag(u))) for u in range(updates)]
