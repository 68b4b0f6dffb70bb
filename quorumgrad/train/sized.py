"""The runs of ``train.replay`` on any number of rows, which stay with the executors.

A run looks at the rows that its draws name.  Draws are joined to the rows and stream, in the order of updates, through
the task that trains; what is kept is one vector of parameters per evaluation.  All of these are then measured on all
rows in one pass.  Neither the driver nor a task holds a table.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..models import Model
from ..operators.ordering import numbered
from ..optim.rules import Ema, Rule
from ..sources.sinks import scratch_path
from .gradient import matrix, vectors_column

SPLITS = ("train", "validation", "test")


def written(df: DataFrame, name: str) -> DataFrame:
    path = scratch_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@dataclass
class Table:
    """Rows (at, x, y, split), where training rows have the numbers from 0 in the order of row_id; rows of each split; width."""

    rows: DataFrame
    counts: dict[str, int]
    width: int


def table(df: DataFrame) -> Table:
    """(row_id, x, y, split) written in order."""
    rows = written(df.select("row_id", F.col("x").cast("array<double>"), F.col("y").cast("double"), "split"), "rows")
    at = written(numbered(rows, [F.col("split") != "train", F.col("row_id"), F.xxhash64("x")], "at").select("at", "x", "y", "split"), "rows")
    counts = {s: 0 for s in SPLITS} | {r.split: r.n for r in at.groupBy("split").agg(F.count("*").alias("n")).collect()}
    return Table(at, counts, at.agg(F.max(F.size("x"))).first()[0] or 0)


@dataclass
class Group:
    """Runs (by name, with their settings) of one task that draw the same rows: ``batch`` in each of ``updates`` updates."""

    task: str
    seed: int
    updates: int
    batch: int
    runs: dict[str, dict]


@dataclass
class Plan:
    """What a run does with its rows: the version each gradient is computed at, the clock, and when it is evaluated."""

    model: Model
    rule: Rule
    reads: np.ndarray
    clock: np.ndarray
    every: int
    seed: int
    ema: float | None = None
    stops: bool = False  # at the first evaluation with parameters that are not finite


class Live:
    """A run under way; ``feed`` takes an update's rows and gives its evaluation, where there is one."""

    def __init__(self, plan: Plan):
        self.plan, self.theta, self.u, self.done = plan, plan.model.init(plan.seed), 0, False
        self.average = Ema(plan.ema) if plan.ema is not None else None
        self.versions = [self.theta] * (int((np.arange(len(plan.reads)) - plan.reads).max(initial=0)) + 2)

    def feed(self, x: np.ndarray, y: np.ndarray) -> tuple[int, float, bool, np.ndarray] | None:
        p, u, ring = self.plan, self.u, len(self.versions)
        if self.done:
            return None
        self.versions[u % ring] = self.theta
        if self.average:
            self.average.feed(self.theta)
        self.theta = p.rule.step(self.theta, p.model.grad(self.versions[p.reads[u] % ring], x, y))
        self.u = u + 1
        self.done = self.u == len(p.reads)
        if self.u % p.every and not self.done:
            return None
        finite = bool(np.isfinite(self.theta).all())
        self.done |= p.stops and not finite
        return self.u, float(p.clock[u]), finite, self.average.value if self.average else self.theta


def draws(spark: SparkSession, groups: list[Group], tables: dict[str, Table]) -> DataFrame:
    """(task, slot, nth, at): the training rows that each group draws, one after another, as a replay does."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pa.RecordBatch]:
        for pdf in batches:
            for task, slot, seed, rows, updates, batch in pdf.itertuples(index=False):
                rng, step = np.random.default_rng(seed), max(1, (1 << 16) // batch)
                for u in range(0, updates, step):
                    at = np.concatenate([rng.integers(0, rows, batch) for _ in range(u, min(u + step, updates))])
                    yield pd.DataFrame({"task": task, "slot": np.int32(slot), "nth": np.arange(len(at)) + u * batch, "at": at})

    named = spark.createDataFrame([(g.task, i, g.seed, tables[g.task].counts["train"], g.updates, g.batch) for i, g in enumerate(groups)], "task string, slot int, seed long, n long, updates long, batch long")
    return named.repartitionById(len(groups), "slot").mapInPandas(run, "task string, slot int, nth long, at long")


TRAINED = "run_id string, iteration long, clock double, finite boolean, theta array<double>"


def trained(spark: SparkSession, groups: list[Group], tables: dict[str, Table], plan: Callable[[dict, object], Plan], shared: object) -> DataFrame:
    """Parameters at each evaluation of each run; a task per group, which holds an update's rows and its runs' versions."""
    drawn = written(draws(spark, groups, tables), "draws")
    parts = [drawn.where(F.col("task") == t).join(own.rows.where("split = 'train'").select("at", "x", "y"), "at").select("slot", "nth", "x", "y") for t, own in tables.items()]
    rows = parts[0]
    for p in parts[1:]:
        rows = rows.union(p)
    sent = spark.sparkContext.broadcast(([(g.batch, g.runs) for g in groups], shared))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slot = None
        for b in batches:
            slots, xs, ys, out = np.asarray(b.column(0)), matrix(b.column(2)), np.asarray(b.column(3)), []
            cuts = [0, *(np.flatnonzero(np.diff(slots)) + 1).tolist(), len(slots)]
            for lo, hi in zip(cuts, cuts[1:]):
                x, y = xs[lo:hi], ys[lo:hi]
                if slots[lo] != slot:
                    slot = slots[lo]
                    batch, runs = sent.value[0][slot]
                    live = {name: Live(plan(s, sent.value[1])) for name, s in runs.items()}
                else:
                    x, y = np.concatenate([rest_x, x]), np.concatenate([rest_y, y])  # noqa: F821
                whole = len(y) // batch * batch
                for at in range(0, whole, batch):
                    for name, one in live.items():
                        found = one.feed(x[at : at + batch], y[at : at + batch])
                        if found:
                            out.append((name, *found))
                rest_x, rest_y = x[whole:].copy(), y[whole:].copy()
            for name in dict.fromkeys(o[0] for o in out):
                _, u, c, f, theta = zip(*(o for o in out if o[0] == name), strict=True)
                arrays = [pa.array([name] * len(u)), pa.array(u, pa.int64()), pa.array(c, pa.float64()), pa.array(f), vectors_column(theta)]
                yield pa.RecordBatch.from_arrays(arrays, names=["run_id", "iteration", "clock", "finite", "theta"])

    ordered = rows.repartitionById(len(groups), "slot").sortWithinPartitions("slot", "nth")
    return written(ordered.mapInArrow(run, TRAINED), "trained")


def right(rows: DataFrame, model: Model, thetas: np.ndarray) -> np.ndarray:
    """(parameters x splits): rows of each split that each vector of parameters has right, in one pass over the rows."""
    sent = rows.sparkSession.sparkContext.broadcast(thetas)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((len(sent.value), len(SPLITS)), np.int64)
        for b in batches:
            x, y, split = matrix(b.column(0)), np.asarray(b.column(1)), np.array([SPLITS.index(s) for s in b.column(2).to_pylist()], np.int64)
            hits = model.predict_all(sent.value, x) == y
            for s in range(len(SPLITS)):
                sums[:, s] += hits[:, split == s].sum(axis=1)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(sums.size)), pa.array(sums.ravel())], names=["place", "n"])

    table = rows.select("x", "y", "split").mapInArrow(run, "place long, n long").groupBy("place").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(len(thetas) * len(SPLITS), np.int64)
    out[table.column(0).to_numpy()] = table.column(1).to_numpy()
    return out.reshape(-1, len(SPLITS))


@dataclass
class Evaluation:
    """An evaluation of a run: its update, clock, whether its parameters were finite, and the share of each split it has right."""

    iteration: int
    clock: float
    finite: bool
    share: dict[str, float]


def evaluated(spark: SparkSession, groups: list[Group], tables: dict[str, Table], models: dict[str, Model], plan: Callable[[dict, object], Plan], shared: object = None) -> dict[str, list[Evaluation]]:
    """The evaluations of every run in order.

    The driver gets the parameters of each evaluation (their number and size are the runs' settings, not the rows').
    """
    found = trained(spark, groups, tables, plan, shared).orderBy("run_id", "iteration").toArrow()
    names, steps, clocks, finite = (found.column(i).to_pylist() for i in range(4))
    task = {name: g.task for g in groups for name in g.runs}
    out: dict[str, list[Evaluation]] = {name: [] for g in groups for name in g.runs}
    for t, own in tables.items():
        at = [i for i, name in enumerate(names) if task[name] == t]
        if not at:
            continue
        hits = right(own.rows, models[t], np.stack([matrix(found.column(4).slice(i, 1))[0] for i in at]))
        for i, hit in zip(at, hits.tolist(), strict=True):
            share = {s: h / own.counts[s] if own.counts[s] else float("nan") for s, h in zip(SPLITS, hit, strict=True)}
            out[names[i]].append(Evaluation(steps[i], clocks[i], finite[i], share))
    return out
