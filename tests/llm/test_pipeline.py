"""The pipeline stage by stage on a small table, and as a whole."""

from collections import Counter

import corpus_pipeline as cp
from quorumgrad.llm import mixing, pii
from quorumgrad.llm.common import materialized

from .test_brute_force import SF, both, brute_pii, brute_quality, whole_ids


def test_stages_and_run(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    after, cur = {}, docs
    for name, stage in cp.STAGES:
        cur = materialized(spark, stage(spark, cur, SF), f"test-{name}")
        after[name] = cur
        assert name == "packing" or cur.schema == docs.schema
    assert Counter(both(after["quality_rules"])) == Counter((i, t) for i, t in both(docs) if brute_quality(t)["kept"])

    kept = both(after["near_duplicates"])
    assert len({t for _, t in kept}) == len(kept) and set(kept) <= set(both(after["quality_rules"]))

    masked = dict(both(after["personal_data"]))
    for i, text in kept:
        spans = brute_pii(text)
        assert (masked[i] == text) == (not spans) and not brute_pii(masked[i])
        assert Counter(k for k, _, _ in spans) == Counter({k: masked[i].count(f"[{k.upper()}]") for k in pii.KINDS if f"[{k.upper()}]" in masked[i]})

    plan = {r.doc_id: r.times for r in mixing.mix(spark, after["personal_data"]).collect()}
    assert Counter(both(after["source_mix"])) == Counter({(i, t): plan[i] for i, t in masked.items() if plan[i]})

    pieces = after["packing"].collect()
    texts = [t for _, t in both(after["source_mix"])]
    assert sum(p.length for p in pieces) == sum(map(len, whole_ids(texts, 1)))
    whole = cp.run(spark, SF).collect()
    # Tails are packed per partition, so the cuts may differ; the documents and their tokens may not.
    size = lambda rows: Counter({d: sum(p.length for p in rows if p.doc_id == d) for d in {p.doc_id for p in rows}})
    assert size(whole) == size(pieces)
