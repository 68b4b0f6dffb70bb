"""Pipeline stages on odd tables: equal ids, clashing column names, nulls everywhere, no rows, repeated rows."""

from collections import Counter

import pytest

import corpus_pipeline as cp
from quorumgrad.llm import simhash

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
CLASH = "_keep string, _of string, _n string, _copy string, row string, id string, of string, node string, times string, rows string, copy string, root string, `a.b` string"


def text(seed, n=120):
    return " ".join(f"{WORDS[(seed * 7 + i * (seed + 3)) % len(WORDS)]}{(seed * 31 + i * i) % 97}" for i in range(n))


def frame(spark, rows, clash=False):
    rows = [(i, t, "en", s, len(t) if t is not None else None, *(["x"] * 13 if clash else [])) for i, t, s in rows]
    return spark.createDataFrame(rows, f"{SCHEMA}, {CLASH}" if clash else SCHEMA).repartition(3)


def test_equal_ids_of_different_texts_stay(spark):
    a, b, c = text(1), text(2), text(3)
    rows = [(1, a, "s"), (1, b, "s"), (2, c, "s"), (2, c, "s"), (None, text(4), "s"), (None, text(5), "s"), (3, a, "s"), (None, a, "s")]
    for stage in (lambda d: cp.near_duplicates(spark, d, ""), lambda d: simhash.deduplicated(spark, d)):
        got = Counter((r.doc_id, r.text) for r in stage(frame(spark, rows)).collect())
        assert got == Counter([(1, a), (1, b), (2, c), (None, text(4)), (None, text(5))])


def test_texts_equal_but_for_case_and_spaces_are_one(spark):
    rows = [(5, text(1), "s"), (5, text(1).upper().replace(" ", "  "), "s"), (5, None, "s"), (6, "", "s"), (7, " \n", "s")]
    got = cp.near_duplicates(spark, frame(spark, rows), "").collect()
    assert Counter(r.doc_id for r in got) == Counter({5: 2})


@pytest.mark.parametrize("clash", [False, True])
def test_every_stage_on_odd_tables(spark, clash):
    mixed = [(1, text(1), "a"), (1, text(1), "a"), (2, None, None), (3, "", "b"), (4, "short text", "b"), (None, text(6), None), (5, "x" * 200_000, "a"), (6, text(7, 3000), "c")]
    for rows in (mixed, [], [(None, None, None)] * 3):
        df = frame(spark, rows, clash)
        for name, stage in cp.STAGES:
            out = stage(spark, df, "")
            got = out.collect()
            if name != "packing":
                assert out.schema.names == df.schema.names and [f.dataType for f in out.schema] == [f.dataType for f in df.schema]
                assert {(r.doc_id, r.source) for r in got} <= {(i, s) for i, _, s in rows}
            if name in ("personal_data", "packing"):
                assert Counter(r.doc_id for r in got if name != "packing" or r.start == 0) == Counter(i for i, _, _ in rows)


def test_repeated_rows_and_empty_texts_mix(spark):
    rows = [(i % 7, text(i % 7), f"s{i % 3}") for i in range(60)] + [(None, None, None)] * 4
    got = Counter(r.doc_id for r in cp.source_mix(spark, frame(spark, rows, True), "").collect())
    assert got[None] == 4 and sum(got.values()) > 60
    sizes = Counter(i % 7 for i in range(60))
    assert all(n <= 2 * sizes[i] for i, n in got.items() if i is not None)
