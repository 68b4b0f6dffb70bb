"""Mixing sources to target weights by balanced sampling with the cube method.

A source whose target is ``r`` times its size takes every document ``floor(r)`` times and once more with probability
``r - floor(r)``.  Those fractional probabilities are rounded together: the flight phase moves them along the null
space of the balancing constraints (a source's document total and its token total stay as they are) until all but two
are 0 or 1.  Documents of a source are dealt into blocks of bounded size, each block flies alone, and what every block
leaves, two documents at most, flies again in the next level, until one block per source is left.  The last block keeps a dozen documents of all sizes for the landing, which tries every rounding
of them and of the two that the flight left, and takes the one whose totals are nearest.

Only (row key, size) travels, never text.  Random numbers are hashes of the seed and the row, so reruns agree.

Defined results: null text counts 0 words; a null source is one source, the last; repeated rows are told apart by a
number within equal keys; an empty table gives an empty result; further columns are ignored (``mixed`` keeps them).
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import as_row, materialized, n_words, only

WEIGHTS, SHARE, MOST = (3, 1, 2), 1.5, 2.0
#: Documents of a source that the landing decides, besides what the flight leaves.
LANDING = 12


def source_targets(sizes: DataFrame, weights: Sequence[int] = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """source, source_size, target from (source, source_size): weights repeat over the sources by code point, null last.

    ``share`` of all sizes goes to the sources by weight; a target stops at ``most`` times its source's size and the
    excess goes to the others by weight.  Filling in the order of ``most * size / weight``, a source is full when the
    level that the rest could reach lies at or over its own.  One row per source: windows over these rows alone.
    """
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    rank = F.row_number().over(W.orderBy(F.col("source").asc_nulls_last()))
    rows = sizes.withColumn("weight", F.element_at(cycle, (F.pmod(rank - 1, F.lit(len(weights))) + 1).cast("int"))).withColumn("cap", most * F.col("source_size"))
    everything = W.partitionBy(F.lit(1))
    by_level = W.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last()).rowsBetween(W.unboundedPreceding, -1)
    rows = rows.withColumn("all", share * F.sum("source_size").over(everything)).withColumn("weights", F.sum("weight").over(everything))
    rest = (F.col("all") - F.coalesce(F.sum("cap").over(by_level), F.lit(0.0))) / (F.col("weights") - F.coalesce(F.sum("weight").over(by_level), F.lit(0.0)))
    rows = rows.withColumn("rest", rest).withColumn("full", rest >= F.col("cap") / F.col("weight"))
    level = F.max(F.when(~F.col("full"), F.col("rest"))).over(everything)  # the first that is not full sets it
    return rows.withColumn("level", level).select("source", "source_size", F.when(F.col("full"), F.col("cap")).otherwise(F.col("level") * F.col("weight")).alias("target"))


def flight(pi: np.ndarray, x: np.ndarray, draws: np.ndarray) -> np.ndarray:
    """Round ``pi`` so that the sums of ``x`` (units x constraints) stay: at most that many entries remain fractional.

    Units enter in order.  ``active`` always holds one more than there are constraints; a vector of the null space of
    their constraint matrix is followed either way, at odds that keep every mean, until one of them is 0 or 1.
    """
    pi, p, tiny = pi.copy(), x.shape[1], 1e-9
    active: list[int] = []
    d = 0
    for i in np.flatnonzero((pi > tiny) & (pi < 1 - tiny)):
        active.append(int(i))
        while len(active) > p:
            u = _null_vector(x[active[: p + 1]])
            own = np.array(active[: p + 1])
            up, down = _reach(pi[own], u), _reach(pi[own], -u)
            step = up if draws[d % len(draws)] * (up + down) < down else -down
            d += 1
            pi[own] = np.clip(pi[own] + step * u, 0.0, 1.0)
            pi[own[pi[own] < tiny]], pi[own[pi[own] > 1 - tiny]] = 0.0, 1.0
            active = [k for k in active if tiny < pi[k] < 1 - tiny]
    pi[pi < tiny], pi[pi > 1 - tiny] = 0.0, 1.0
    return pi


def _null_vector(rows: np.ndarray) -> np.ndarray:
    """A vector ``u`` with ``u @ rows == 0`` for one more row than columns."""
    if rows.shape[1] == 2:
        (a, d), (b, e), (c, f) = rows
        u = np.array([b * f - c * e, c * d - a * f, a * e - b * d])
        if not np.abs(u).max() > 1e-12:  # rank 1: two rows alone do
            return np.array([b, -a, 0.0]) if abs(a) + abs(b) > 0 and abs(b * d - a * e) < 1e-12 else np.array([e, -d, 0.0])
        return u / np.abs(u).max()
    a, b = rows[:, 0]
    return np.array([b, -a]) / max(abs(a), abs(b)) if max(abs(a), abs(b)) > 0 else np.array([1.0, 0.0])


def _reach(pi: np.ndarray, u: np.ndarray) -> float:
    with np.errstate(divide="ignore", invalid="ignore"):
        far = np.where(u > 0, (1 - pi) / u, np.where(u < 0, -pi / u, np.inf))
    return float(far.min())


def land(pi: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Settle the few units that are left (LANDING and two at most): of all ways to round them the one whose totals come
    nearest, a document counting as a fiftieth of the mean size."""
    pi = pi.copy()
    left = np.flatnonzero((pi > 0) & (pi < 1))
    ways = (np.arange(1 << len(left))[:, None] >> np.arange(len(left))) & 1
    tokens, count = np.abs((ways - pi[left]) @ size[left]), np.abs((ways - pi[left]).sum(axis=1))
    pi[left] = ways[np.argmin(tokens + 0.02 * size.mean() * count)] if len(left) else 0
    return pi


def _block(pdf: pd.DataFrame, last: bool) -> pd.DataFrame:
    """Fly one block: rows (key, source, size, pi); ``pi`` comes back rounded but for two, or wholly if ``last``."""
    pdf = pdf.sort_values(["size", "draw", "key"], ascending=[False, True, True], kind="stable").reset_index(drop=True)
    x = np.stack([np.ones(len(pdf)), pdf["size"].to_numpy(float) / max(pdf["size"].max(), 1)], axis=1)
    pi, fly = pdf["pi"].to_numpy().copy(), np.ones(len(pdf), bool)
    if last:  # of every size some stay for the landing
        fly[np.unique(np.linspace(0, len(pdf) - 1, LANDING).round().astype(int))] = False
    pi[fly] = flight(pi[fly], x[fly], pdf["draw"].to_numpy())
    return pdf.assign(pi=land(pi, pdf["size"].to_numpy(float)) if last else pi)


def balanced_sample(spark: SparkSession, units: DataFrame, block: int = 4096) -> DataFrame:
    """(key, picked) from (key, source, size, pi, draw): each source's document and token totals balanced.

    ``block`` bounds the rows of a group; the number of blocks of a source follows its row count, so a source with a
    third of all rows is split like any other.
    """
    schema = "key string, source string, size long, pi double, draw double, groups long"
    done, rest = None, units
    while True:
        counts = rest.groupBy("source").agg(F.count("*").alias("n")).select("source", F.ceil(F.col("n") / block).alias("groups"))
        counts = materialized(spark, counts, "block-counts", few=True)
        most = counts.agg(F.max("groups")).first()[0] or 1
        # Source names are few and short; the join is left to the planner, which knows the written table's size.
        dealt = rest.alias("r").join(counts.alias("c"), F.col("r.source").eqNullSafe(F.col("c.source"))).select("r.*", "c.groups")
        dealt = dealt.withColumn("part", F.pmod(F.xxhash64("key"), F.col("groups")))

        def fly(pdf: pd.DataFrame) -> pd.DataFrame:
            return _block(pdf, last=bool(pdf["groups"].iloc[0] == 1))[["key", "source", "size", "pi", "draw", "groups"]]

        flown = materialized(spark, dealt.groupBy("source", "part").applyInPandas(lambda pdf: fly(pdf.drop(columns="part")), schema), "flown", few=True)
        settled = flown.where("pi = 0 or pi = 1").select("key", F.col("pi").cast("long").alias("picked"))
        done = settled if done is None else done.union(settled)
        if most <= 1:
            return done
        rest = flown.where("pi > 0 and pi < 1").drop("groups")


def mix(spark: SparkSession, docs: DataFrame, seed: int = 7, weights: Sequence[int] = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """doc_id, size, source_size, target, taken, times, key of each row of ``docs`` (doc_id, source, text)."""
    rows = only(docs, "doc_id", "source", "text").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), n_words().alias("size"), F.xxhash64("text").alias("of"))
    # Equal rows are interchangeable; their number within the equal rows tells them apart.
    copy = F.row_number().over(W.partitionBy("doc_id", "source", "of").orderBy("size"))
    rows = rows.withColumn("key", F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("-")), F.hex("of"), copy, F.coalesce("source", F.lit("\0"))))
    rows = materialized(spark, rows.drop("of"), "sizes", few=True)
    totals = rows.groupBy("source").agg(F.sum("size").alias("source_size"))
    targets = materialized(spark, source_targets(totals, weights, share, most).withColumnRenamed("source", "of"), "targets", few=True)
    rows = rows.join(targets, F.col("source").eqNullSafe(F.col("of"))).drop("of")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    rows = rows.withColumn("whole", F.floor(rate + 1e-12)).withColumn("pi", F.greatest(rate - F.col("whole"), F.lit(0.0)))
    draw = (F.pmod(F.xxhash64("key", F.lit(seed)), F.lit(1 << 40)) + 0.5) / float(1 << 40)
    units = rows.where("pi > 0").select("key", "source", "size", "pi", draw.alias("draw"))
    picked = balanced_sample(spark, units)
    out = rows.join(picked, "key", "left").withColumn("times", F.col("whole") + F.coalesce("picked", F.lit(0)))
    return out.select("doc_id", "size", "source_size", "target", (F.col("times") * F.col("size")).alias("taken"), "times", "key")


def mixed(spark: SparkSession, docs: DataFrame, seed: int = 7) -> DataFrame:
    """``docs`` with each row as often as the mix takes it, columns as they are; rows without a word stay once."""
    own = docs.select(docs["doc_id"].cast("long").alias("id"), F.hex(F.xxhash64(docs["text"])).alias("of"), as_row(docs))
    plan = mix(spark, docs, seed).select(F.col("doc_id").alias("plan_id"), F.split("key", ":")[1].alias("plan_of"), "times", "size")
    plan = plan.groupBy("plan_id", "plan_of").agg(F.sum(F.when(F.col("size") > 0, F.col("times")).otherwise(1)).alias("times"), F.count("*").alias("rows"))
    plan = materialized(spark, plan, "mix", few=True)
    rows = own.join(plan, F.col("id").eqNullSafe(F.col("plan_id")) & (F.col("of") == F.col("plan_of")))
    single = rows.where("rows = 1").select("row", "times")
    # Copies of one row share their takes: the quotient each, and one more for the first of them.
    number = F.row_number().over(W.partitionBy("id", "of").orderBy(F.lit(1)))
    repeated = rows.where("rows > 1").select("row", (F.floor(F.col("times") / F.col("rows")) + (number <= F.col("times") % F.col("rows")).cast("long")).alias("times"))
    return _repeat(single.unionByName(repeated))


def _repeat(rows: DataFrame) -> DataFrame:
    return rows.where("times > 0").withColumn("copy", F.explode(F.array_repeat(F.lit(1), F.col("times").cast("int")))).select("row.*")
