"""Measures over evaluation curves (run_id, iteration, clock, value) and over predictions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def each_run():
    return W.partitionBy("run_id")


def best_so_far(curve: DataFrame, lower_is_better: bool = True) -> DataFrame:
    run = each_run().orderBy("iteration").rowsBetween(W.unboundedPreceding, W.currentRow)
    return curve.withColumn("best", (F.min if lower_is_better else F.max)("value").over(run))


def first_reach(curve: DataFrame, eps: float, lower_is_better: bool = True, epoch: Column | None = None) -> DataFrame:
    """(run_id, iteration, clock) of the first evaluation as good as ``eps``; null where a run never is."""
    hit = F.col("value") <= eps if lower_is_better else F.col("value") >= eps
    rows = curve if epoch is None else curve.withColumn("iteration", epoch)
    return rows.groupBy("run_id").agg(F.min(F.when(hit, F.col("iteration"))).alias("iteration"), F.min(F.when(hit, F.col("clock"))).alias("clock"))


def converged_at(curve: DataFrame, tolerance: float, lower_is_better: bool = True) -> DataFrame:
    """(run_id, iteration, clock, best): the first evaluation within ``tolerance`` of the run's best value."""
    best = (F.min if lower_is_better else F.max)("value").over(each_run())
    near = F.abs(F.col("value") - F.col("best")) <= tolerance
    rows = curve.withColumn("best", best)
    return rows.groupBy("run_id").agg(F.min(F.when(near, F.col("iteration"))).alias("iteration"), F.min(F.when(near, F.col("clock"))).alias("clock"), F.first("best").alias("best"))


def epoch_of(update: Column, workers: int, synchronous: bool) -> Column:
    """Epochs that compare both ways: a synchronous step is one, as are as many asynchronous updates as workers."""
    return update if synchronous else F.floor(update / workers).cast("long")


def mean_epoch_time(curve: DataFrame) -> DataFrame:
    """(run_id, mean_s): clock per iteration."""
    return curve.groupBy("run_id").agg((F.max("clock") / F.max("iteration")).alias("mean_s"))


def compare_runs(curve: DataFrame, a: str, b: str) -> DataFrame:
    """(iteration, gap, ratio) of two runs where both were evaluated."""
    left = curve.where(F.col("run_id") == a).select("iteration", F.col("value").alias("va"))
    right = curve.where(F.col("run_id") == b).select("iteration", F.col("value").alias("vb"))
    return left.join(right, "iteration").select("iteration", (F.col("va") - F.col("vb")).alias("gap"), F.try_divide(F.col("va"), F.col("vb")).alias("ratio"))


def precision_at_k(scores: Column, label: Column, k: int = 1) -> Column:
    """Share of rows whose label is among the k best classes; of equal scores the lower class comes first."""
    order = F.array_sort(F.transform(scores, lambda s, i: F.struct((-s).alias("s"), i.alias("i"))))
    top = F.transform(F.slice(order, 1, k), lambda e: e["i"])
    return F.avg(F.array_contains(top, label.cast("int")).cast("double"))


def nll(probability: Column) -> Column:
    return F.avg(-F.log(probability))
