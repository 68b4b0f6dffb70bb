"""What the query modules share."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.tables import read_table
from ..timing import trace as tr


def rounded(df: DataFrame, digits: int = 6, **special: int) -> DataFrame:
    """Doubles rounded, as the last projection."""
    return df.select(*[F.round(c.name, special.get(c.name, digits)).alias(c.name) if isinstance(c.dataType, T.DoubleType) else F.col(c.name) for c in df.schema])


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "events", ["event_id", "value"])


def trace(spark: SparkSession, sf_dir: str, workers: int = 100, shape: str = "shaped") -> DataFrame:
    return tr.arrival_trace(events(spark, sf_dir), workers, shape)


SHAPED_SQL = "1.4::DOUBLE + value / 250 + CASE WHEN value > 190 THEN (value - 190) / 8 ELSE 0 END"


def trace_sql(workers: int = 100, shape: str = "shaped", name: str = "t") -> str:
    """The trace as common table expressions for DuckDB: ``t`` (iteration, worker, arrival) and ``k`` ranked."""
    value = SHAPED_SQL if shape == "shaped" else "value"
    return f"""{name}0 AS (SELECT (event_id // {workers})::INTEGER AS iteration, (event_id % {workers})::INTEGER AS worker, {value} AS arrival FROM events),
{name} AS (SELECT * FROM {name}0 QUALIFY count(*) OVER (PARTITION BY iteration) = {workers}),
{name}k AS (SELECT *, row_number() OVER (PARTITION BY iteration ORDER BY arrival, worker)::INTEGER AS k FROM {name})"""
