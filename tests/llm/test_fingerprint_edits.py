"""Likeness of versions whatever the length, the place of the edit and the script."""

import random

import pytest
from pyspark.sql import functions as F

from quorumgrad.llm import fingerprints as fp

WORDS = "the of land water move given seven away big table over very good work voice kind page world give small been make move some five".split()


def text(n, seed, line=10**9):
    pick = random.Random(seed)
    out = []
    while sum(map(len, out)) + len(out) < n:
        out.append("".join(pick.choice("bcdfgklmnrstvw") + pick.choice("aeiouy") for _ in range(pick.randint(1, 4))) if pick.random() < 0.7 else pick.choice(WORDS))
        if len(out) % line == line - 1:
            out.append("\n")
    return " ".join(out)[:n]


@pytest.fixture(scope="module")
def likeness(spark):
    def of(pairs):
        df = spark.createDataFrame([(i, *p) for i, p in enumerate(pairs)], "i int, x string, y string")
        df = df.withColumns({"a": fp.digests(F.col("x")), "b": fp.digests(F.col("y"))}).withColumns({f"{c}_cells": fp.cells_of(c) for c in "ab"})
        df = df.withColumn("d", fp.difference("a", "b", "a_cells", "b_cells"))
        exact = F.size(F.array_except("a", "b")) + F.size(F.array_except("b", "a"))
        rows = df.select("i", fp.likeness("a", "b", F.size("d")).alias("near"), F.size("d").alias("n"), exact.alias("exact"), F.size(F.array_distinct("d")).alias("different"), F.expr("forall(d, z -> IF(z.n = 1, array_contains(a, z.d), array_contains(b, z.d)))").alias("sides")).orderBy("i").collect()
        assert all(r["n"] == r["exact"] == r["different"] and r["sides"] for r in rows)
        return [r["near"] for r in rows]

    return of


def test_prefixes_across_lengths(likeness):
    pairs = [(t, t[:cut]) for n, cut in ((2000, 1334), (1510, 1490), (1600, 1400), (60000, 40000), (210000, 190000), (900, 700)) for t in (text(n, n),)]
    near = likeness(pairs)
    for (t, cut), x in zip(pairs, near, strict=True):
        assert abs(x - len(cut) / len(t)) < 0.2
    assert near[1] > 0.8


def test_text_in_front_moves_nothing(likeness):
    t = text(27000, 1)
    for front in ("abc", "a whole line\n", text(300, 2)):
        (near,) = likeness([(t, front + t)])
        assert near > 0.95


def test_scripts_and_lines(likeness):
    pick = random.Random(3)
    cyrillic = " ".join("".join(chr(pick.randint(0x430, 0x44F)) for _ in range(6)) for _ in range(600))
    chinese = "".join(chr(pick.randint(0x4E00, 0x9FA0)) for _ in range(4000))
    blob = "".join(pick.choice("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/") for _ in range(6000))
    pairs = [(t, t[: len(t) // 3] + "new" + t[len(t) // 3 :]) for t in (cyrillic, chinese, blob, text(6000, 4), text(6000, 5, line=12))]
    assert min(likeness(pairs)) > 0.9
    assert likeness([("", ""), ("x" * 5000, "x" * 5000), ("x" * 5000, ""), ("a\nb\n", "a\nb\n")]) == [1.0, 1.0, 0.0, 1.0]


def test_wholly_different_long_texts(likeness):
    near = likeness([(text(120000, 6), text(120000, 7)), (text(3000, 8), text(90000, 9))])
    assert max(near) < 0.05
