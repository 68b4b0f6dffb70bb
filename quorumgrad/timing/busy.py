"""Busy stragglers: a worker that misses a step finishes its old gradient, which is dropped by its tag, and joins the
step that is then open."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def busy_steps(times: np.ndarray, quorum: int) -> tuple[np.ndarray, np.ndarray]:
    """(close times of all steps, which workers' gradients close each); ``times[t, w]`` is how long worker ``w``'s
    ``t``-th gradient takes.

    A worker still computing when a step opens starts on it as soon as it is free.
    """
    steps, workers = times.shape
    free, used, now = np.zeros(workers), np.zeros(workers, int), 0.0
    out, counted = np.empty(steps), np.zeros((steps, workers), bool)
    for t in range(steps):
        begin = np.maximum(free, now)
        done = begin + times[np.minimum(used, steps - 1), np.arange(workers)]
        first = np.argsort(done, kind="stable")[:quorum]
        counted[t, first] = True
        now = done[first[-1]]
        started = begin < now
        free = np.where(started, done, free)
        used += started
        out[t] = now
    return out, counted


def busy_clock(times: np.ndarray, quorum: int) -> np.ndarray:
    return busy_steps(times, quorum)[0]


def busy_winners(trace: DataFrame, quorum: int) -> DataFrame:
    """(iteration, worker) of the gradients that close each step when stragglers stay busy."""
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        times = pdf.pivot(index="iteration", columns="worker", values="arrival").sort_index().to_numpy()
        t, w = np.nonzero(busy_steps(times, quorum)[1])
        return pd.DataFrame({"iteration": t.astype("int32"), "worker": w.astype("int32")})

    # A run is sequential: its trace, steps x workers numbers, goes to one task.
    return trace.groupBy(F.lit("run")).applyInPandas(run, "iteration int, worker int")


def busy_schedule(trace: DataFrame, quorums: list[int]) -> DataFrame:
    """(quorum, iteration, clock) for several quorums, each a group of its own.

    A step depends on the one before, so a run is sequential; its trace (steps x workers numbers) goes to one task.
    """
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        times = pdf.pivot(index="iteration", columns="worker", values="arrival").sort_index().to_numpy()
        clock = busy_clock(times, int(pdf["quorum"].iloc[0]))
        return pd.DataFrame({"quorum": int(pdf["quorum"].iloc[0]), "iteration": np.arange(len(clock)), "clock": clock})

    per = trace.withColumn("quorum", F.explode(F.array(*[F.lit(q) for q in quorums])))
    return per.groupBy("quorum").applyInPandas(run, "quorum int, iteration int, clock double")
