"""A live quorum: real Spark jobs are the workers, the first N to end win, the rest is cancelled by its tag."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from concurrent.futures import FIRST_COMPLETED, ThreadPoolExecutor, wait
from typing import Any

from pyspark.sql import SparkSession


class LiveQuorum:
    """``step`` runs ``work(worker)`` for N + b workers as concurrent jobs and returns the first N results.

    Spark's own remedy for slow tasks, speculation, runs a second copy instead of dropping the first; it is a setting
    of the session and independent of this class.
    """

    def __init__(self, spark: SparkSession, quorum: int, spares: int):
        if quorum < 1 or spares < 0:
            raise ValueError("a quorum of 1 at least and no negative spares")
        self.spark, self.quorum, self.spares = spark, quorum, spares

    def step(self, work: Callable[[int], Any]) -> tuple[dict[int, Any], float]:
        """(results by worker, seconds).  A worker that fails counts as one that never answers."""
        tag, sc = f"step-{uuid.uuid4().hex}", self.spark.sparkContext

        def one(worker: int) -> Any:
            sc.addJobTag(tag)
            try:
                return work(worker)
            finally:
                sc.removeJobTag(tag)

        began, done = time.monotonic(), {}
        pool = ThreadPoolExecutor(self.quorum + self.spares)
        try:
            open_ = {pool.submit(one, w): w for w in range(self.quorum + self.spares)}
            while open_ and len(done) < self.quorum:
                ended, _ = wait(open_, return_when=FIRST_COMPLETED)
                for f in ended:
                    worker = open_.pop(f)
                    if f.exception() is None and len(done) < self.quorum:
                        done[worker] = f.result()
            seconds = time.monotonic() - began
            if open_:
                sc.cancelJobsWithTag(tag)
        finally:
            pool.shutdown(wait=True)
        if len(done) < self.quorum:
            raise RuntimeError(f"only {len(done)} of {self.quorum} gradients came in")
        return done, seconds
