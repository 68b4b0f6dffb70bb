"""Parameters too wide for the driver: (shard, coord, value, slot) rows, updated by a join on (shard, coord)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def wide_step(theta: DataFrame, gradient: DataFrame, rate: float, rule: str = "sgd", mu: float = 0.9, rho: float = 0.9, eps: float = 1e-8) -> DataFrame:
    """One step of (shard, coord, value, slot) by (shard, coord, g); coordinates without a gradient stay.

    Both sides are dealt by (shard, coord); where they are stored bucketed by it, nothing moves.
    """
    rows = theta.join(gradient, ["shard", "coord"], "left").withColumn("g", F.coalesce("g", F.lit(0.0)))
    if rule == "sgd":
        slot, move = F.col("slot"), F.col("g")
    elif rule == "momentum":
        slot = mu * F.col("slot") + F.col("g")
        move = slot
    elif rule == "adagrad":
        slot = F.col("slot") + F.col("g") * F.col("g")
        move = F.col("g") / (F.sqrt(slot) + eps)
    elif rule == "rmsprop":
        slot = rho * F.col("slot") + (1 - rho) * F.col("g") * F.col("g")
        move = F.col("g") / (F.sqrt(slot) + eps)
    else:
        raise ValueError(f"unknown rule {rule}")
    return rows.select("shard", "coord", (F.col("value") - rate * move).alias("value"), slot.alias("slot"))


def touched(theta: DataFrame, batch: DataFrame, key: str = "coord") -> DataFrame:
    """Only the rows of sparse parameters that a batch needs."""
    return theta.join(batch.select(key).distinct(), key, "left_semi")
