"""Operators that Spark lacks: global numbers, running sums and as-of versions, without one task that sees all rows.

Rows are range-partitioned in the wanted order and written with their partition, so that what is computed inside a
partition and what is added from the partitions before come from the same ranges.  Only one row per partition (and key)
is ordered in a single task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..sources.sinks import scratch_path


def _dealt(df: DataFrame, order: list[Column]) -> DataFrame:
    spark = df.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    path = scratch_path(spark, "ordered")
    df.repartitionByRange(parts, *order).withColumn("_part", F.spark_partition_id()).write.parquet(path)
    return spark.read.parquet(path)


def _earlier(total: str, *keys: str) -> Column:
    """The sum over the partitions before, per key."""
    return F.coalesce(F.sum(total).over(W.partitionBy(*keys).orderBy("_part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))


def numbered(df: DataFrame, order: list[Column], name: str) -> DataFrame:
    """Adds a global number from 0 in the given order."""
    dealt = _dealt(df, order)
    placed = dealt.withColumn("_at", F.row_number().over(W.partitionBy("_part").orderBy(*order)))
    counts = dealt.groupBy("_part").agg(F.count("*").alias("_n")).select("_part", _earlier("_n").alias("_before"))
    return placed.join(counts, "_part").withColumn(name, F.col("_before") + F.col("_at") - 1).drop("_part", "_at", "_before")


def running_sum(df: DataFrame, keys: list[str], order: list[Column], value: Column, name: str) -> DataFrame:
    """Adds the sum of ``value`` over a key's rows up to each row, in the given order; a key may hold all rows.

    Keys are not null.  Rows that are equal in the order stay together, in no particular order among themselves.
    """
    dealt = _dealt(df.withColumn("_value", value), [*map(F.col, keys), *order])
    run = W.partitionBy("_part", *keys).orderBy(*order).rowsBetween(W.unboundedPreceding, W.currentRow)
    totals = dealt.groupBy("_part", *keys).agg(F.sum("_value").alias("_n")).select("_part", *keys, _earlier("_n", *keys).alias("_before"))
    placed = dealt.withColumn("_own", F.sum("_value").over(run))
    return placed.join(totals, ["_part", *keys]).withColumn(name, F.col("_before") + F.col("_own")).drop("_part", "_own", "_before", "_value")


def versions_at(reads: DataFrame, applies: DataFrame, keys: list[str]) -> DataFrame:
    """``reads`` (keys, at, ...) with ``version``: updates of the same key applied at or before that time.

    One order of the union instead of a quadratic join; an update at the very time of a read counts.
    """
    extra = [c for c in reads.columns if c not in (*keys, "at")]
    marks = applies.select(*keys, "at", *[F.lit(None).cast(reads.schema[c].dataType).alias(c) for c in extra], F.lit(1).alias("_is"))
    union = marks.unionByName(reads.select(*keys, "at", *extra, F.lit(0).alias("_is")))
    return running_sum(union, keys, [F.col("at"), F.col("_is").desc()], F.col("_is"), "version").where("_is = 0").drop("_is")
