"""Asynchronous schedules: worker clocks, the global order of updates, the version each gradient was computed at."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..operators.ordering import numbered, running_sum, versions_at


def work_trace(events: DataFrame, workers: int, shape) -> DataFrame:
    """(worker, seq, duration): the gradients that each worker computes one after another; a partial last round goes."""
    rows = events.select(F.expr(f"CAST(event_id % {workers} AS INT)").alias("worker"), F.expr(f"event_id DIV {workers}").alias("seq"), shape(F.col("value")).alias("duration"))
    return rows.withColumn("_n", F.count("*").over(W.partitionBy("seq"))).where(F.col("_n") == workers).drop("_n")


def worker_clocks(work: DataFrame) -> DataFrame:
    """Adds start and finish: a worker begins its next gradient when it has sent the last one.

    Durations add up in microseconds of fixed point, so the order of updates does not hang on the order of additions.
    """
    run = W.partitionBy("worker").orderBy("seq").rowsBetween(W.unboundedPreceding, W.currentRow)
    exact = work.withColumn("_d", F.col("duration").cast("decimal(18,6)"))
    exact = exact.withColumn("_f", F.sum("_d").over(run))
    return exact.withColumn("finish", F.col("_f").cast("double")).withColumn("start", (F.col("_f") - F.col("_d")).cast("double")).withColumn("duration", F.col("_d").cast("double")).drop("_d", "_f")


def async_schedule(work: DataFrame) -> DataFrame:
    """(update, worker, seq, start, finish, read_version, lag) where a worker reads as soon as it has sent.

    A gradient is computed at the version that its worker's previous update made, so the lag is the number of updates
    in between.
    """
    rows = numbered(worker_clocks(work), [F.col("finish"), F.col("worker"), F.col("seq")], "update")
    before = F.coalesce(F.lag("update").over(W.partitionBy("worker").orderBy("seq")) + 1, F.lit(0))
    rows = rows.withColumn("read_version", before)
    return rows.select("update", "worker", "seq", "start", "finish", "read_version", (F.col("update") - F.col("read_version")).alias("lag"))


def layer_offsets(layers: DataFrame, network: float = 0.0) -> DataFrame:
    """(layer, read_at, send_at) as shares of a cycle.

    A layer is read when the forward pass reaches it from below and sent when the backward pass has come down to it;
    ``network`` is the share of the cycle that a gradient spends on its way.
    """
    up = W.orderBy("layer").rowsBetween(W.unboundedPreceding, -1)
    down = W.orderBy(F.desc("layer")).rowsBetween(W.unboundedPreceding, W.currentRow)
    everything = W.partitionBy(F.lit(1))
    forward, total = F.sum("fwd").over(everything), F.sum(F.col("fwd") + F.col("bwd")).over(everything)
    read = F.coalesce(F.sum("fwd").over(up), F.lit(0.0)) / total
    send = (forward + F.sum("bwd").over(down)) / total
    return layers.select("layer", ((1 - network) * read).alias("read_at"), ((1 - network) * send + network).alias("send_at"))


def layered_lag(work: DataFrame, offsets: DataFrame) -> DataFrame:
    """(layer, worker, seq, lag): updates of a layer between its read and its own update.

    What comes after the first worker's trace ends is dropped, else the fleet would seem smaller.  ``offsets`` has one
    row per layer and is broadcast.
    """
    clocks = worker_clocks(work)
    end = clocks.groupBy("worker").agg(F.max("finish").alias("last")).agg(F.min("last").alias("until"))
    per = clocks.crossJoin(F.broadcast(offsets)).select(
        "layer", "worker", "seq", (F.col("start") + F.col("read_at") * F.col("duration")).alias("read"), (F.col("start") + F.col("send_at") * F.col("duration")).alias("sent")
    )
    per = per.crossJoin(F.broadcast(end)).where("sent <= until").drop("until")
    order = [F.col("sent"), F.col("worker"), F.col("seq")]
    applied = running_sum(per, ["layer"], order, F.lit(1), "place").withColumn("place", F.col("place") - 1)
    reads = applied.select("layer", F.col("read").alias("at"), "worker", "seq", "place")
    applies = applied.select("layer", F.col("sent").alias("at"))
    return versions_at(reads, applies, ["layer"]).select("layer", "worker", "seq", (F.col("place") - F.col("version")).alias("lag"))


def shard_versions(work: DataFrame, shards: int, step: float = 0.01) -> DataFrame:
    """(worker, seq, shard, read_version): slices are read one after another, ``step`` of a cycle apart, and updates
    reach them all at once; so one gradient can mix versions."""
    clocks = worker_clocks(work)
    shard = F.explode(F.sequence(F.lit(0), F.lit(shards - 1)))
    reads = clocks.select(shard.alias("shard"), "worker", "seq", "start", "duration").select("shard", (F.col("start") + F.col("shard") * step * F.col("duration")).alias("at"), "worker", "seq")
    applies = clocks.select(shard.alias("shard"), F.col("finish").alias("at"))
    return versions_at(reads, applies, ["shard"]).select("worker", "seq", "shard", F.col("version").alias("read_version"))


def lag_summary(rows: DataFrame, by: list[str] | None = None) -> DataFrame:
    """min, mean, median, max, standard deviation and count of ``lag``, per key or over all."""
    return rows.groupBy(*(by or [])).agg(
        F.min("lag").cast("long").alias("min_lag"), F.avg("lag").alias("mean_lag"), F.expr("CAST(percentile(lag, 0.5) AS DOUBLE)").alias("median_lag"),
        F.max("lag").cast("long").alias("max_lag"), F.stddev_samp("lag").alias("sd_lag"), F.count("lag").alias("n"),
    )


def waves(read_versions: list[int]) -> list[int]:
    """Wave of each update, given the version it reads: updates whose versions are all applied already run as one job."""
    out, wave, applied = [], 0, 0
    for update, version in enumerate(read_versions):
        if version > applied:
            wave, applied = wave + 1, update
        out.append(wave)
    return out
