"""Run logs and parameter checkpoints in a shared folder."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder in ``spark.checkpoint.dir``.

    Where it is unset and Spark runs in this one process (tests, benches), a temporary folder is made; on a cluster that
    is an error, since executors would not see it.
    """
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if named is None:
        if not re.fullmatch(r"local(\[[^,\]]*(,[0-9]+)?\])?", sc.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        sc.setCheckpointDir(f"file://{tempfile.mkdtemp(prefix='quorumgrad-')}")
        named = sc.getCheckpointDir()
    return named


_SCOPES: list[list[str]] = []


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new folder name in the shared folder; inside a ``scratch_scope`` the folder goes when the scope ends."""
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    if _SCOPES:
        _SCOPES[-1].append(path)
    return path


@contextmanager
def scratch_scope(spark: SparkSession) -> Iterator[None]:
    """Delete the scratch folders made in the block when it ends.

    Frames built on them must have been written elsewhere by then.
    """
    _SCOPES.append([])
    try:
        yield
    finally:
        for path in _SCOPES.pop():
            drop_path(spark, path)


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a folder that a run wrote for itself."""
    fs, target = _marker(spark, path)
    fs.delete(target, True)


def write_run_log(curve: DataFrame, path: str) -> None:
    """Curves (run_id, iteration, ...) by run; writing a run again replaces that run alone."""
    curve.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run_id").parquet(path)


def read_run_log(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def _marker(spark: SparkSession, path: str):
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), target


def checkpoint_theta(spark: SparkSession, path: str, version: int, theta: np.ndarray, averaged: np.ndarray | None = None) -> None:
    """Parameters of one version; the writer's marker comes last, so a version without it does not count."""
    pair = averaged if averaged is not None else theta
    rows = [(i, float(t), float(a)) for i, (t, a) in enumerate(zip(theta, pair, strict=True))]
    spark.createDataFrame(rows, "coord long, value double, averaged double").coalesce(1).write.mode("overwrite").parquet(f"{path}/v={version:012d}")


def versions(spark: SparkSession, path: str) -> list[int]:
    """Complete versions under a path."""
    fs, root = _marker(spark, path)
    if not fs.exists(root):
        return []
    done = []
    for status in fs.listStatus(root):
        name = status.getPath().getName()
        ok = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(status.getPath(), "_SUCCESS")
        if name.startswith("v=") and fs.exists(ok):
            done.append(int(name[2:]))
    return sorted(done)


def load_theta(spark: SparkSession, path: str, version: int | None = None) -> tuple[int, np.ndarray, np.ndarray]:
    """(version, parameters, averaged parameters) of a version, the newest by default."""
    found = versions(spark, path)
    if not found or version is not None and version not in found:
        raise ValueError("no such version")
    version = found[-1] if version is None else version
    rows = spark.read.parquet(f"{path}/v={version:012d}").orderBy("coord").collect()
    return version, np.array([r.value for r in rows]), np.array([r.averaged for r in rows])


def checkpoint_run(spark: SparkSession, path: str, version: int, state: dict[str, np.ndarray | float]) -> None:
    """Everything a run needs to go on from ``version``: named vectors and numbers, complete once the marker is there."""
    rows = [(k, np.ndim(v), [float(x) for x in np.atleast_1d(v)]) for k, v in state.items()]
    spark.createDataFrame(rows, "name string, dims int, value array<double>").coalesce(1).write.mode("overwrite").parquet(f"{path}/v={version:012d}")


def load_run(spark: SparkSession, path: str, version: int | None = None) -> tuple[int, dict[str, np.ndarray | float]] | None:
    """A complete version under a path (the newest by default) and its state; none if there is none."""
    found = versions(spark, path) if version is None else [version]
    if not found:
        return None
    rows = spark.read.parquet(f"{path}/v={found[-1]:012d}").collect()
    return found[-1], {r.name: np.array(r.value) if r.dims else r.value[0] for r in rows}


def distinct_runs(spark: SparkSession, path: str) -> DataFrame:
    return read_run_log(spark, path).select(F.col("run_id")).distinct()
