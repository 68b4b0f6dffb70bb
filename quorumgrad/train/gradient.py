"""Gradients of a step as one Spark job.

Arrow batches become numpy partial sums, one row per partition and worker; these are dealt by worker (or by host) and
added up by executors, so the driver gets one vector per worker (or per host), never one per partition.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..models import Model

PARTIAL = "iteration int, worker int, n double, loss double, g array<double>"
HOSTS = "iteration int, host int, n double, loss double, g array<double>"


def matrix(column: pa.Array) -> np.ndarray:
    """A list column of equal lengths as a matrix, without Python lists."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = np.asarray(column.flatten(), float)
    return flat.reshape(len(column), -1) if len(column) else np.empty((0, 0))


def vectors_column(rows: list[np.ndarray]) -> pa.Array:
    """Vectors of one length as a list column."""
    flat = np.concatenate(rows) if rows else np.empty(0)
    return pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1, dtype=np.int32) * (len(flat) // max(len(rows), 1)), pa.int32()), pa.array(flat))


def partial_sums(batch: DataFrame, model: Model, thetas: dict[int, np.ndarray]) -> DataFrame:
    """Sums per partition, iteration and worker over (iteration, worker, x, y); ``thetas`` holds one vector per
    iteration (a wave has several).  A partition emits one row per worker it holds, not one per example."""
    sent = batch.sparkSession.sparkContext.broadcast(thetas)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple[int, int], list] = {}
        for b in batches:
            its, workers, x, y = np.asarray(b.column(0)), np.asarray(b.column(1)), matrix(b.column(2)), np.asarray(b.column(3), float)
            for t, w in set(zip(its.tolist(), workers.tolist(), strict=True)):
                own = (its == t) & (workers == w)
                loss, g = model.loss_and_grad(sent.value[t], x[own], y[own])
                n = int(own.sum())
                at = sums.setdefault((t, w), [0.0, 0.0, np.zeros(len(g))])
                at[0], at[1], at[2] = at[0] + n, at[1] + n * loss, at[2] + n * g
        yield from summed_batch(sums, ("iteration", "worker"))

    return batch.select("iteration", "worker", "x", "y").mapInArrow(run, PARTIAL)


def summed_batch(sums: dict[tuple[int, int], list], names: tuple[str, str]) -> Iterator[pa.RecordBatch]:
    """One batch of (keys, n, loss, g) rows."""
    if sums:
        keys, rows = zip(*sums.items(), strict=True)
        arrays = [*(pa.array([k[i] for k in keys], pa.int32()) for i in (0, 1)), pa.array([float(r[0]) for r in rows]), pa.array([float(r[1]) for r in rows]), vectors_column([r[2] for r in rows])]
        yield pa.RecordBatch.from_arrays(arrays, names=[*names, "n", "loss", "g"])


def _added(batches: Iterator[pa.RecordBatch]) -> dict[tuple[int, int], list]:
    """Partial rows added up by (iteration, worker): one vector per key is held, whatever the number of partitions."""
    sums: dict[tuple[int, int], list] = {}
    for b in batches:
        for t, w, n, loss, g in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist(), matrix(b.column(4)), strict=True):
            at = sums.setdefault((t, w), [0.0, 0.0, np.zeros(len(g))])
            at[0], at[1], at[2] = at[0] + n, at[1] + loss, at[2] + g
    return sums


def worker_sums(batch: DataFrame, model: Model, thetas: dict[int, np.ndarray]) -> DataFrame:
    """(iteration, worker, n, loss, g) with sums, one row per worker and iteration: added up by executors."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from summed_batch(_added(batches), ("iteration", "worker"))

    return partial_sums(batch, model, thetas).repartition("iteration", "worker").mapInArrow(add, PARTIAL)


def host_sums(batch: DataFrame, model: Model, thetas: dict[int, np.ndarray], workers_per_host: int) -> DataFrame:
    """(iteration, host, n, loss, g): each host adds up its workers' means and sends one message (sum, count)."""

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hosts: dict[tuple[int, int], list] = {}
        for (t, w), (n, loss, g) in _added(b.select(["iteration", "worker", "n", "loss", "g"]) for b in batches).items():
            at = hosts.setdefault((t, w // workers_per_host), [0.0, 0.0, np.zeros(len(g))])
            at[0], at[1], at[2] = at[0] + 1, at[1] + loss / n, at[2] + g / n
        yield from summed_batch(hosts, ("iteration", "host"))

    partials = partial_sums(batch, model, thetas)
    host = F.expr(f"worker DIV {workers_per_host}")
    return partials.repartition("iteration", host).mapInArrow(merge, HOSTS)


def _collected(rows: DataFrame) -> Iterator[tuple[int, int, float, float, np.ndarray]]:
    table = rows.toArrow()
    return zip(*(table.column(i).to_pylist() for i in range(4)), matrix(table.column(4)), strict=True)


def worker_gradients(batch: DataFrame, model: Model, thetas: dict[int, np.ndarray]) -> dict[tuple[int, int], tuple[float, float, np.ndarray]]:
    """(n, mean loss, mean gradient) of each (iteration, worker): what the workers send, one vector each."""
    return {(t, w): (n, loss / n, g / n) for t, w, n, loss, g in _collected(worker_sums(batch, model, thetas))}


def quorum_gradient(batch: DataFrame, model: Model, iteration: int, theta: np.ndarray) -> tuple[np.ndarray, float, int]:
    """Mean over workers of their means, mean loss, and how many workers had rows."""
    found = worker_gradients(batch, model, {iteration: theta})
    if not found:
        return np.zeros_like(theta), float("nan"), 0
    return np.mean([g for _, _, g in found.values()], axis=0), float(np.mean([x for _, x, _ in found.values()])), len(found)


def merged_gradient(batch: DataFrame, model: Model, iteration: int, theta: np.ndarray, workers_per_host: int) -> tuple[np.ndarray, float, int, int]:
    """The same mean and loss when hosts merge first, the number of workers, and the messages sent (one per host)."""
    rows = list(_collected(host_sums(batch, model, {iteration: theta}, workers_per_host)))
    workers = sum(n for _, _, n, _, _ in rows)
    if not workers:
        return np.zeros_like(theta), float("nan"), 0, 0
    return sum(g for *_, g in rows) / workers, sum(loss for *_, loss, _ in rows) / workers, int(workers), len(rows)


def full_loss(df: DataFrame, model: Model, theta: np.ndarray) -> float:
    """Mean loss over all rows of (x, y): the empirical loss."""
    rows = df.select(F.lit(0).alias("iteration"), F.lit(0).alias("worker"), "x", "y")
    found = worker_gradients(rows, model, {0: theta})
    return found[(0, 0)][1] if found else float("nan")


def point_gradient(df: DataFrame, model: Model, theta: np.ndarray, row_id: int) -> np.ndarray:
    """The gradient of one example, read by its id."""
    rows = df.where(F.col("row_id") == row_id).select(F.lit(0).alias("iteration"), F.lit(0).alias("worker"), "x", "y")
    return worker_gradients(rows, model, {0: theta})[(0, 0)][2]
