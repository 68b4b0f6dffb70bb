"""Arrival traces, order statistics, and what closes a synchronous step.

A trace has one row per gradient: (iteration, worker, arrival) in seconds since the iteration began.  All statistics
are windows over one iteration, so one shuffle by iteration serves them all.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def each():
    """All gradients of an iteration."""
    return W.partitionBy("iteration")


def in_order():
    """The gradients of an iteration as they arrive; of equal arrivals the lower worker id comes first."""
    return each().orderBy(F.col("arrival").asc_nulls_last(), "worker")



def raw(value: Column) -> Column:
    return value


def shaped(value: Column) -> Column:
    """A tight body with a heavy tail, in seconds."""
    return F.lit(1.4) + value / 250 + F.when(value > 190, (value - 190) / 8).otherwise(0.0)


SHAPES = {"raw": raw, "shaped": shaped}


def arrival_trace(events: DataFrame, workers: int, shape: str = "shaped") -> DataFrame:
    """Consecutive events are the gradients of consecutive iterations; an incomplete last iteration is dropped."""
    rows = events.select(F.expr(f"CAST(event_id DIV {workers} AS INT)").alias("iteration"), F.expr(f"CAST(event_id % {workers} AS INT)").alias("worker"), SHAPES[shape](F.col("value")).alias("arrival"))
    return rows.withColumn("_n", F.count("*").over(each())).where(F.col("_n") == workers).drop("_n")


def with_hosts(trace: DataFrame, workers_per_host: int) -> DataFrame:
    return trace.withColumn("host", F.expr(f"CAST(worker DIV {workers_per_host} AS INT)"))


def shard_trace(trace: DataFrame, shards: int) -> DataFrame:
    """The same gradients as they reach each parameter server, with a deterministic jitter of up to 9 %."""
    per = trace.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))))
    jitter = 1 + F.pmod(F.col("worker") * 31 + F.col("shard") * 17 + F.col("iteration") * 7, F.lit(10)) / 100
    return per.withColumn("arrival", F.col("arrival") * jitter).select("iteration", "worker", "shard", "arrival")


def kth_arrival(trace: DataFrame) -> DataFrame:
    """(iteration, k, worker, arrival): of equal arrivals the lower worker id comes first; a null never answers."""
    return trace.select("iteration", F.row_number().over(in_order()).alias("k"), "worker", "arrival")


def clocked(steps: DataFrame) -> DataFrame:
    """Adds the running clock to one row per iteration.  The window spans iterations (run length), not gradients."""
    return steps.withColumn("clock", F.sum("step_time").over(W.orderBy("iteration").rowsBetween(W.unboundedPreceding, W.currentRow)))


def sync_schedule(trace: DataFrame, quorum: int) -> DataFrame:
    """(iteration, worker, rank, used, step_time): the first ``quorum`` gradients close the step, later ones go."""
    ranked = trace.withColumn("rank", F.row_number().over(in_order()))
    ranked = ranked.withColumn("used", (F.col("rank") <= quorum) & F.col("arrival").isNotNull())
    return ranked.withColumn("step_time", F.max(F.when(F.col("used"), F.col("arrival"))).over(each())).select("iteration", "worker", "arrival", "rank", "used", "step_time")


def winners(trace: DataFrame, quorum: int) -> DataFrame:
    """(iteration, worker) of the used gradients alone; the rank filter sits on the window, so Spark limits per group."""
    return trace.where("arrival is not null").withColumn("rank", F.row_number().over(in_order())).where(F.col("rank") <= quorum).select("iteration", "worker")


def sync_steps(trace: DataFrame, quorum: int) -> DataFrame:
    """(iteration, n_used, n_dropped, step_time, clock)."""
    rows = sync_schedule(trace, quorum).groupBy("iteration").agg(
        F.sum(F.col("used").cast("long")).alias("n_used"), F.sum((~F.col("used")).cast("long")).alias("n_dropped"), F.max("step_time").alias("step_time")
    )
    return clocked(rows)


def shard_steps(trace: DataFrame, quorum: int, shards: int) -> DataFrame:
    """(iteration, shard, step_time, n_used): every server closes its own quorum."""
    order = W.partitionBy("iteration", "shard").orderBy("arrival", "worker")
    ranked = shard_trace(trace, shards).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= quorum)
    return ranked.groupBy("iteration", "shard").agg(F.max("arrival").alias("step_time"), F.count("*").alias("n_used"))


def shard_clock(trace: DataFrame, quorum: int, shards: int) -> DataFrame:
    """A worker waits for all slices, so the slowest server sets the step."""
    return clocked(shard_steps(trace, quorum, shards).groupBy("iteration").agg(F.max("step_time").alias("step_time")))


def deadline_schedule(trace: DataFrame, tau: float, quorum: int | None = None) -> DataFrame:
    """(iteration, worker, arrival, used, step_time): the step closes at ``tau``, with one gradient at least, or
    sooner when all are in or, with ``quorum``, when that many are."""
    target = F.lit(quorum) if quorum else F.count("*").over(each())
    rows = trace.withColumn("rank", F.row_number().over(in_order()))
    rows = rows.withColumn("used", (F.col("rank") == 1) | (F.col("arrival") <= tau) & (F.col("rank") <= target))
    n, last, first = F.sum(F.col("used").cast("int")).over(each()), F.max(F.when(F.col("used"), F.col("arrival"))).over(each()), F.min("arrival").over(each())
    return rows.withColumn("step_time", F.when(first > tau, first).when(n >= target, last).otherwise(F.lit(float(tau)))).select("iteration", "worker", "arrival", "used", "step_time")


def deadline_steps(trace: DataFrame, tau: float, quorum: int | None = None) -> DataFrame:
    rows = deadline_schedule(trace, tau, quorum).groupBy("iteration").agg(F.sum(F.col("used").cast("long")).alias("n_used"), F.max("step_time").alias("step_time"))
    return clocked(rows)


def speculation_steps(trace: DataFrame, quorum: int, slow: float = 1.5) -> DataFrame:
    """(iteration, full_s, speculation_s, spares_s, copies): the contrast to dropping stragglers.

    A worker later than ``slow`` times its iteration's median gets a second copy at that time, which takes as long as
    the worker's next gradient; the sooner of both counts, and the step still waits for all.
    """
    again = F.lead("arrival").over(W.partitionBy("worker").orderBy("iteration"))
    rows = trace.withColumn("again", again).withColumn("k", F.row_number().over(in_order())).withColumn("limit", slow * F.expr("percentile(arrival, 0.5)").over(each()))
    late = (F.col("arrival") > F.col("limit")) & F.col("again").isNotNull()
    rows = rows.withColumn("late", late).withColumn("eff", F.when(late, F.least("arrival", F.col("limit") + F.col("again"))).otherwise(F.col("arrival")))
    return rows.groupBy("iteration").agg(
        F.max("arrival").alias("full_s"), F.max("eff").alias("speculation_s"), F.max(F.when(F.col("k") <= quorum, F.col("arrival"))).alias("spares_s"), F.sum(F.col("late").cast("long")).alias("copies")
    )


def arrival_cdf(trace: DataFrame, ks: Sequence[int], grid: Sequence[float]) -> DataFrame:
    """(k, t, share): share of iterations whose k-th gradient is in by t.

    The grid is a literal array; counting by conditional sums keeps one row per (k, t) and task in the shuffle.
    """
    ranked = kth_arrival(trace).where(F.col("k").isin(list(ks)))
    per = ranked.select("k", "arrival", F.explode(F.array(*[F.lit(float(t)) for t in grid])).alias("t"))
    return per.groupBy("k", "t").agg(F.avg((F.col("arrival") <= F.col("t")).cast("double")).alias("share"))


def arrival_profile(trace: DataFrame) -> DataFrame:
    """(k, mean_s, median_s, max_s)."""
    return kth_arrival(trace).groupBy("k").agg(F.avg("arrival").alias("mean_s"), F.expr("percentile(arrival, 0.5)").alias("median_s"), F.max("arrival").alias("max_s"))


def arrival_profile_sketch(trace: DataFrame) -> DataFrame:
    """The same from mergeable quantile sketches, for traces too long for exact percentiles."""
    rows = kth_arrival(trace).groupBy("k").agg(F.avg("arrival").alias("mean_s"), F.expr("kll_sketch_agg_double(arrival)").alias("s"))
    return rows.select("k", "mean_s", F.expr("kll_sketch_get_quantile_double(s, 0.5D)").alias("median_s"))


def waste(trace: DataFrame, quorum: int) -> DataFrame:
    """(iteration, idle_s, saved_s, dropped_share): seconds that workers wait for the slowest, seconds that closing at
    the quorum saves, share of gradients dropped."""
    last = F.max("arrival").over(each())
    rows = sync_schedule(trace, quorum).withColumn("last", last)
    return rows.groupBy("iteration").agg(
        F.sum(F.col("last") - F.col("arrival")).alias("idle_s"), (F.max("last") - F.max("step_time")).alias("saved_s"), F.avg((~F.col("used")).cast("double")).alias("dropped_share")
    )


def spares_ablation(trace: DataFrame, workers: int, spares: Sequence[int]) -> DataFrame:
    """(spares, mean_step_s, total_s): step time at each number of spares out of a fixed fleet."""
    k = kth_arrival(trace).withColumn("spares", F.lit(workers) - F.col("k")).where(F.col("spares").isin(list(spares)))
    return k.groupBy("spares").agg(F.avg("arrival").alias("mean_step_s"), F.sum("arrival").alias("total_s"))


def messages(trace: DataFrame, workers_per_host: Sequence[int]) -> DataFrame:
    """(workers_per_host, messages, seconds): gradients merged on their host before they are sent; a host's message
    leaves with its last worker."""
    per = trace.withColumn("workers_per_host", F.explode(F.array(*[F.lit(h) for h in workers_per_host])))
    hosts = per.groupBy("workers_per_host", "iteration", F.floor(F.col("worker") / F.col("workers_per_host")).alias("host")).agg(F.max("arrival").alias("sent"))
    return hosts.groupBy("workers_per_host").agg(F.count("*").alias("messages"), F.avg("sent").alias("mean_sent_s"))
