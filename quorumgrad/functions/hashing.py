"""Hash draws that Spark and other SQL engines compute alike (md5 prefixes), and splits built on them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def hash32(*parts: Column | int | str) -> Column:
    """The first 32 bits of the md5 of the parts joined by colons, as a long."""
    cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[c.cast("string") for c in cols])), 1, 8), 16, 10).cast("long")


def hash01(*parts: Column | int | str) -> Column:
    """Uniform in [0, 1)."""
    return hash32(*parts) / F.lit(4294967296.0)


def split_name(key: Column, train: float = 0.7, validation: float = 0.15) -> Column:
    h = hash01(key)
    return F.when(h < train, "train").when(h < train + validation, "validation").otherwise("test")


def draws(df: DataFrame, number: str, workers: int, batch: int, rows: int, seed: int) -> DataFrame:
    """(iteration, worker, pos, row_index): every worker draws ``batch`` rows with replacement in every step; the column
    ``number`` counts the draws from 0."""
    grid = df.select(
        F.expr(f"CAST({number} DIV {workers * batch} AS INT)").alias("iteration"), F.expr(f"CAST(({number} DIV {batch}) % {workers} AS INT)").alias("worker"), F.expr(f"CAST({number} % {batch} AS INT)").alias("pos")
    )
    return grid.withColumn("row_index", F.pmod(hash32(F.lit(seed), F.col("iteration"), F.col("worker"), F.col("pos")), F.lit(rows)))


def bernoulli(df: DataFrame, key: str, steps: int, share: float, seed: int) -> DataFrame:
    """``df`` with ``iteration``: each row is in the batch of each step with probability ``share``, independently."""
    step = F.explode(F.sequence(F.lit(0), F.lit(steps - 1)))
    return df.withColumn("iteration", step).where(hash32(F.lit(seed), F.col("iteration"), F.col(key)) < F.lit(int(share * 2**32)))


def slot_layout(df: DataFrame, key: str, slots: int, epoch: int = 0) -> DataFrame:
    """Each row's slot in an epoch; a step reads whole slots, without replacement within the epoch."""
    return df.withColumn("slot", F.pmod(hash32(F.lit(epoch), F.col(key)), F.lit(slots)).cast("int"))

