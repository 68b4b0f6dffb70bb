"""How many spares a fixed fleet should have: iterations to converge times mean time of the quorum's last gradient."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .trace import kth_arrival

#: The published iteration counts at 50 and 100 gradients.
PUBLISHED_KNOTS = ((50, 137.5e3), (100, 76.2e3))


def knots_frame(spark: SparkSession, knots: Sequence[tuple[int, float]]) -> DataFrame:
    return spark.createDataFrame([(int(n), float(i)) for n, i in knots], "n int, iterations double")


def interpolate(knots: DataFrame, low: int, high: int) -> DataFrame:
    """(n, iterations) for every n from low to high by straight lines between neighbouring knots.

    Knots are few (one row per measured N) and are broadcast into a range join.
    """
    nxt = W.orderBy("n")
    pairs = knots.select(F.col("n").alias("a"), F.col("iterations").alias("ia"), F.lead("n").over(nxt).alias("b"), F.lead("iterations").over(nxt).alias("ib")).where("b is not null")
    xs = knots.sparkSession.range(low, high + 1).select(F.col("id").cast("int").alias("n"))
    last = F.lit(high)
    inside = (F.col("n") >= F.col("a")) & ((F.col("n") < F.col("b")) | (F.col("n") == F.col("b")) & (F.col("n") == last))
    line = F.col("ia") + (F.col("ib") - F.col("ia")) * (F.col("n") - F.col("a")) / (F.col("b") - F.col("a"))
    return xs.join(F.broadcast(pairs), inside).select("n", line.alias("iterations"))


def time_to_converge(trace: DataFrame, knots: DataFrame, low: int, high: int) -> DataFrame:
    """(n, spares, iterations, mean_s, estimate_s) for a fleet of ``high`` workers."""
    mean = kth_arrival(trace).groupBy("k").agg(F.avg("arrival").alias("mean_s"))
    rows = interpolate(knots, low, high).join(mean, F.col("n") == F.col("k"))
    return rows.select("n", (F.lit(high) - F.col("n")).alias("spares"), "iterations", "mean_s", (F.col("iterations") * F.col("mean_s")).alias("estimate_s"))


def best_split(estimates: DataFrame) -> DataFrame:
    """The fastest row; of equal estimates the larger quorum."""
    return estimates.orderBy("estimate_s", F.desc("n")).limit(1)
