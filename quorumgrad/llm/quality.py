"""Quality rules by suffix-array repetition.

Words of a batch of texts become integers, a suffix array over them is built by prefix doubling in numpy (later rounds
touch only positions whose prefix is not yet unique), and longest common prefixes of neighbouring suffixes come from
the kept rank levels.  A position whose prefix of ``l`` words occurs elsewhere in its text starts a repeated span of
``l`` words; the spans' union is the repeated part.

Defined results: null or empty text has zero counts and fails the base rule (under 50 words); repeated rows are scored
one by one; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .common import batch_texts, map_rows, only, slices

SCHEMA = (
    "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, "
    "base_failed boolean, kept boolean, n_covered_words long, longest_repeat long"
)
SYMBOLS = np.isin(np.arange(256), np.frombuffer(b"#*$%&|<>", np.uint8))
SPACES = np.isin(np.arange(256), [0x20, *range(0x09, 0x0E)])
#: Bytes that begin a code point in UTF-8.
LEADS = (np.arange(256) & 0xC0) != 0x80


@dataclass(frozen=True)
class RepetitionRules:
    """Limits of the verdict.  A span counts when at least ``min_repeat`` words long."""

    min_words: int = 50
    max_window_percent: int = 50
    min_repeat: int = 8
    max_covered_fraction: float = 0.4
    max_longest_repeat: int = 50


def suffix_levels(first: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    """Suffix array of integer sequences that share no symbol across sequences, and its rank levels.

    ``ends[i]`` is where the sequence of position ``i`` ends.  Level ``k`` ranks prefixes of ``2**k`` symbols; equal
    ranks mean equal prefixes wholly inside the sequence.
    """
    n = len(first)
    order = np.argsort(first, kind="stable")
    rank = np.empty(n, np.int64)
    heads = np.flatnonzero(np.concatenate([[True], first[order][1:] != first[order][:-1]])) if n else np.empty(0, np.int64)
    rank[order] = np.repeat(heads, np.diff(np.append(heads, n)))
    levels, width = [rank.copy()], 1
    sizes = np.diff(np.append(heads, n))
    slots = np.flatnonzero(np.repeat(sizes, sizes) > 1)  # places in ``order`` that are not settled
    while len(slots):
        at = order[slots]
        ahead = at + width
        after = np.where(ahead < ends[at], rank[np.minimum(ahead, n - 1)], -1)
        by = np.lexsort((after, rank[at]))
        at, after, group = at[by], after[by], rank[at][by]
        order[slots] = at
        new = np.concatenate([[True], (group[1:] != group[:-1]) | (after[1:] != after[:-1])])
        head = slots[np.flatnonzero(new)]
        sizes = np.diff(np.append(np.flatnonzero(new), len(slots)))
        rank[at] = np.repeat(head, sizes)
        slots = slots[np.repeat(sizes, sizes) > 1]
        width *= 2
        levels.append(rank.copy())
    return order, levels


def neighbour_prefixes(order: np.ndarray, levels: list[np.ndarray], ends: np.ndarray) -> np.ndarray:
    """For every position the longest prefix it shares with a neighbour in the suffix array."""
    n = len(order)
    best = np.zeros(n, np.int64)
    if n < 2:
        return best
    pairs = np.flatnonzero(levels[0][order[1:]] == levels[0][order[:-1]])
    a, b = order[pairs], order[pairs + 1]
    shared = np.zeros(len(pairs), np.int64)
    for k in range(len(levels) - 1, -1, -1):
        i, j = a + shared, b + shared
        inside = (i < ends[a]) & (j < ends[b])
        same = inside & (levels[k][np.minimum(i, n - 1)] == levels[k][np.minimum(j, n - 1)])
        shared[same] += 1 << k
    np.maximum.at(best, a, shared)
    np.maximum.at(best, b, shared)
    return best


def covered_by(length: np.ndarray, at_least: int, cut: int | None = None) -> np.ndarray:
    """Positions inside the union of spans ``[i, i + length[i])`` that are ``at_least`` long (or their first ``cut``)."""
    steps = np.zeros(len(length) + 1, np.int64)
    starts = np.flatnonzero(length >= at_least)
    np.add.at(steps, starts, 1)
    np.add.at(steps, starts + (length[starts] if cut is None else cut), -1)
    return np.cumsum(steps[:-1]) > 0


def _per_row(flags: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(flags, dtype=np.int64)])
    return total[last] - total[first]


def score_texts(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, rules: RepetitionRules) -> dict[str, np.ndarray]:
    """Counts of a batch; ``raw`` holds the rows' bytes one after another."""
    lo, hi = (int(starts[0]), int(ends[-1])) if len(starts) else (0, 0)
    part, starts, ends = raw[lo:hi], starts - lo, ends - lo
    space = SPACES[part]
    before = np.concatenate([[True], space])[: len(part)]
    before[starts[starts < len(part)]] = True
    after = np.concatenate([space[1:], [True]])[: len(part)]
    after[ends[ends > 0] - 1] = True
    word_at, word_to = np.flatnonzero(~space & before), np.flatnonzero(~space & after) + 1
    first, last = np.searchsorted(word_at, starts), np.searchsorted(word_at, ends)
    n = last - first
    blob = part.tobytes()
    words = [blob[a:b] for a, b in zip(word_at.tolist(), word_to.tolist(), strict=True)]
    codes = pd.factorize(np.array(words, dtype=object))[0].astype(np.int64) if words else np.empty(0, np.int64)
    row = np.repeat(np.arange(len(starts)), n)
    limit = np.repeat(last, n)
    order, levels = suffix_levels(row * (codes.max(initial=0) + 1) + codes, limit)
    shared = neighbour_prefixes(order, levels, limit)
    windows, spans = covered_by(shared, 3, 3), covered_by(shared, rules.min_repeat)
    longest = np.zeros(len(starts), np.int64)
    np.maximum.at(longest, row, shared)
    dup = np.zeros(len(starts), np.int64)
    for i in np.flatnonzero(_per_row(part == 10, starts, ends) > 0):
        lines = [x for x in blob[starts[i] : ends[i]].split(b"\n") if x.strip(b" \t\n\x0b\x0c\r")]
        dup[i] = len(lines) - len(set(lines))
    repeat = _per_row(windows, first, last)
    failed = (n < rules.min_words) | (100 * repeat > rules.max_window_percent * n)
    covered = _per_row(spans, first, last)
    kept = ~failed & (covered <= rules.max_covered_fraction * n) & (longest <= rules.max_longest_repeat)
    return {
        "n_words": n, "word_chars": _per_row(LEADS[part] & ~space, starts, ends), "n_symbols": _per_row(SYMBOLS[part], starts, ends),
        "n_dup_lines": dup, "n_repeat_words": repeat, "base_failed": failed, "kept": kept, "n_covered_words": covered, "longest_repeat": longest,
    }


def score_batch(column: pa.Array | pa.ChunkedArray, rules: RepetitionRules, budget: int = 2 << 20) -> dict[str, np.ndarray]:
    raw, starts, ends = batch_texts(column)
    parts = [score_texts(raw, starts[a:b], ends[a:b], rules) for a, b in slices(len(starts), ends - starts, budget)]
    return {k: np.concatenate([x[k] for x in parts]) for k in parts[0]} if parts else {}


def quality_report(docs: DataFrame, rules: RepetitionRules = RepetitionRules()) -> DataFrame:
    """Counts and verdict per row of ``docs`` (doc_id, text).  Narrow: no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                found = score_batch(batch.column(1), rules)
                yield pa.RecordBatch.from_arrays([pc.cast(batch.column(0), pa.int64()), *map(pa.array, found.values())], names=["doc_id", *found])

    cols = [c.strip().split()[0] for c in SCHEMA.split(",")]
    return only(docs, "doc_id", "text").mapInArrow(run, SCHEMA).select(*cols)


def kept_documents(docs: DataFrame, rules: RepetitionRules = RepetitionRules()) -> DataFrame:
    """``docs`` without the rejected rows, columns as they are; filtered batch by batch, so no join is needed."""
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield batch.filter(pa.array(score_batch(batch.column(at), rules)["kept"]))

    return map_rows(docs, run)
