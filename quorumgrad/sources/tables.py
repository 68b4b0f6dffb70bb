"""Readers: validated Parquet, and text formats with an explicit schema."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from ..schemas import TABLES


def validate(df: DataFrame, expected: T.StructType, name: str) -> DataFrame:
    """``df`` with the expected columns; a missing or mistyped one is named in the error."""
    have = {f.name: f.dataType for f in df.schema}
    for want in expected:
        if want.name not in have:
            raise ValueError(f"{name}: column {want.name} is missing")
        got, need = have[want.name], want.dataType
        if got != need and not {type(got), type(need)} <= {T.TimestampNTZType, T.TimestampType} and not (isinstance(got, T.ArrayType) and isinstance(need, T.ArrayType) and got.elementType == need.elementType):
            raise ValueError(f"{name}: column {want.name} is {got.simpleString()}, not {need.simpleString()}")
    return df


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """One of the input tables.  Columns are pruned by the scan when the plan needs fewer."""
    df = validate(spark.read.parquet(f"{sf_dir}/{name}.parquet"), TABLES[name], name)
    return df.select(*columns) if columns else df


def read_all(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    return {name: read_table(spark, sf_dir, name) for name in TABLES}


def read_with_schema(spark: SparkSession, path: str, fmt: str, schema: T.StructType, **options: str) -> DataFrame:
    """CSV, JSON, ORC or text with an explicit schema; malformed records fail instead of turning null."""
    if fmt not in ("csv", "json", "orc", "text", "parquet"):
        raise ValueError(f"unknown format {fmt}")
    reader = spark.read.schema(schema).options(**options)
    return (reader.option("mode", "FAILFAST") if fmt in ("csv", "json") else reader).format(fmt).load(path)


def stream_files(spark: SparkSession, path: str, schema: T.StructType, files_per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
