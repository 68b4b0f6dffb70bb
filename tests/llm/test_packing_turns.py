"""Instruction data: every limit of a sequence binds, and no id is lost."""

import zlib
from collections import defaultdict

import numpy as np
import pytest
from tokenizers import Tokenizer

from quorumgrad.llm import packing
from quorumgrad.llm.queries import vocabulary

SF = "/root/testdata/sf0.01"


def examples(turns):
    """(ids, whether each bears loss) of each conversation."""
    t = Tokenizer.from_file(vocabulary())
    out = defaultdict(lambda: ([], []))
    for r in sorted(turns.collect(), key=lambda r: (r["conv_id"], r["turn"], r["role"], r["text"])):
        ids = t.encode(r["text"] or "", add_special_tokens=False).ids + [1]
        out[r["conv_id"]][0].extend(ids)
        out[r["conv_id"]][1].extend([r["role"] == "assistant"] * len(ids))
    return out


@pytest.mark.parametrize("limits", [packing.Limits(tokens=512, segments=4, loss_tokens=200), packing.Limits(tokens=2048, segments=3, loss_tokens=2047), packing.Limits(tokens=128, segments=64, loss_tokens=40, block=32)])
def test_conversations(spark, limits):
    turns = spark.read.parquet(f"{SF}/conversations.parquet").dropDuplicates(["conv_id", "turn", "role", "text"])
    want = examples(turns)
    bins, covered = defaultdict(list), defaultdict(list)
    for r in packing.packed_turns(turns, vocabulary(), 1, limits=limits, partitions=2).collect():
        ids, bears = want[r["doc_id"]]
        a, b = r["start"], r["start"] + r["length"]
        assert r["doc_tokens"] == len(ids) and r["loss_tokens"] == sum(bears[a:b])
        assert r["ids_crc32"] == zlib.crc32(np.array(ids[a:b], "<u4").tobytes())
        covered[r["doc_id"]].append((a, b))
        bins[r["sequence_id"]].append(r)
    assert covered.keys() == want.keys()
    for k, spans in covered.items():
        spans.sort()
        assert spans[0][0] == 0 and spans[-1][1] == len(want[k][0]) and all(x[1] == y[0] for x, y in zip(spans, spans[1:]))
    full = np.array([[sum(r["length"] for r in b), len(b), sum(r["loss_tokens"] for r in b)] for b in bins.values()])
    assert (full <= limits.vector).all()
    short = np.isin(full[:, 0], [1 << k for k in range(12)]) & (full[:, 0] < limits.tokens)  # a partition's rest
    tight = full[~short] >= 0.98 * limits.vector
    assert tight.any(axis=1).mean() > 0.9  # nearly every sequence is closed by a limit
    assert tight[:, 1].any() or tight[:, 2].any()
    for b in bins.values():
        at = 0
        for r in sorted(b, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]


def test_edges(spark):
    rows = [(1, 0, "user", "a b c"), (1, 1, "assistant", None), (1, 1, "assistant", None), (None, 0, None, "x"), (2, 0, "assistant", "w " * 5000)]
    turns = spark.createDataFrame([(*r, "clash") for r in rows], "conv_id long, turn int, role string, text string, data string")
    got = packing.packed_turns(turns, vocabulary(), 1, limits=packing.Limits(tokens=64, segments=2, loss_tokens=10)).collect()
    assert sum(r["length"] for r in got) == sum({r["doc_id"]: r["doc_tokens"] for r in got}.values()) and {r["doc_id"] for r in got} == {1, 2, None}
    assert packing.packed_turns(turns.limit(0), vocabulary(), 1).count() == 0
    with pytest.raises(ValueError):
        packing.Limits(tokens=0)
