"""Helpers shared by the training-data operators."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.sinks import scratch_path

__all__ = ["WORD_PATTERN", "as_row", "batch_texts", "load", "map_rows", "materialized", "n_words", "only", "rows_with", "scratch_path", "slices", "text_or_empty"]

#: Fixed value: the white space that separates words in every contract of this subpackage.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of the input folder, by Spark's reader alone (the folder may be remote)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def materialized(spark: SparkSession, df: DataFrame, name: str, few: bool = False) -> DataFrame:
    """Write to the shared folder and read back: lineage ends there and survives lost executors.

    ``few`` is for narrow tables (ids, counts, pairs): one file for each core of the cluster at most, however many
    partitions they come from, instead of thousands of files of a few rows.
    """
    path = scratch_path(spark, name)
    (df.coalesce(max(1, spark.sparkContext.defaultParallelism)) if few else df).write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def text_or_empty(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))


def n_words(column: str = "text") -> Column:
    """Words of the whole text; null counts 0."""
    return F.regexp_count(text_or_empty(column), F.lit(WORD_PATTERN)).cast("long")


def batch_texts(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bytes, starts, ends) of a string column without copying the values; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "")
    n = len(column)
    _, offsets, data = column.buffers()
    if not n or offsets is None:
        return np.empty(0, np.uint8), np.zeros(n, np.int64), np.zeros(n, np.int64)
    bounds = np.frombuffer(offsets, np.int64)[column.offset : column.offset + n + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.empty(0, np.uint8)
    return raw, bounds[:-1], bounds[1:]


def rows_with(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, marked: np.ndarray) -> np.ndarray:
    """Which rows hold a byte of those marked (256 booleans).  One vector pass over the batch."""
    hits = np.concatenate([[0], np.cumsum(marked[raw], dtype=np.int64)])
    return hits[ends] > hits[starts]


def slices(n_rows: int, sizes: np.ndarray, budget: int) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``budget`` bytes; one row that is larger stands alone."""
    at = 0
    total = np.concatenate([[0], np.cumsum(sizes)])
    while at < n_rows:
        to = max(at + 1, int(np.searchsorted(total, total[at] + budget, side="right")) - 1)
        yield at, to
        at = to


def as_row(df: DataFrame) -> Column:
    """All columns of a row as one struct, so that helper columns beside it clash with none; ``select("row.*")`` undoes it."""
    return F.struct(*[df[f"`{c}`"].alias(c) for c in df.columns]).alias("row")


def map_rows(df: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> DataFrame:
    """``df`` through ``run``, which takes and gives batches of its columns by place; any names will do."""
    plain = df.toDF(*[f"c{i}" for i in range(len(df.columns))])
    return plain.mapInArrow(run, plain.schema).toDF(*df.columns)


def only(df: DataFrame, *columns: str) -> DataFrame:
    """The named columns; further columns, whatever their names, play no part."""
    return df.select(*[df[c] for c in columns])
