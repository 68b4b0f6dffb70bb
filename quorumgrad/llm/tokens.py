"""Token ids of whole texts, shared by the token-store and packing operators.

White space never enters a token and never joins its neighbours, so a text's ids are those of its white-space chunks
in order.  Texts pass in groups of some MB: numpy finds the chunks of a group, Arrow tells the distinct ones, only those
are looked up or encoded in Python, and one gather lays out the ids of the group.

Ids of chunks are kept in a table per worker, bounded in entries and in bytes a chunk, and dropped when a task ends
(``released``), so that later stages in the same worker do not carry it.

Defined results: an empty text has only the end id; a null is for the caller to make empty; texts of any length are
encoded whole; equal texts have equal ids; no texts, no result.
"""

from __future__ import annotations

import os
import sys
from array import array
from collections.abc import Iterable, Iterator
from contextlib import contextmanager
from functools import cache
from itertools import repeat

import numpy as np
import pyarrow as pa
from tokenizers import Tokenizer, normalizers, pre_tokenizers

ID_BYTES = 4
#: Fixed value: the ASCII characters that are neither letters, digits nor white space.
MARKS = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
if array("I").itemsize != ID_BYTES or sys.byteorder != "little":
    raise ImportError("ids are written as little-endian 32-bit integers; this machine's are not")

BYTE = np.arange(256)
IS_SPACE = np.isin(BYTE, [0x20, *range(0x09, 0x0E)])
IS_MARK = np.isin(BYTE, np.frombuffer(MARKS, np.uint8))
IS_ALNUM = np.array([bytes([b]).isalnum() for b in range(256)])
LOWER = np.frombuffer(bytes(range(256)).lower(), np.uint8)
#: Bytes of lower-case letters of Latin-1, which are letters to the vocabulary's own pattern, already composed and in
#: lower case: those of ASCII, and what may follow LATIN, the first byte of the others.
IS_LETTER = (BYTE >= ord("a")) & (BYTE <= ord("z"))
LATIN, IS_SECOND = 0xC3, np.isin(BYTE, [0x9F, *range(0xA0, 0xB7), *range(0xB8, 0xC0)])


def gathered(flat: np.ndarray, starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The runs ``flat[start : start + count]`` one after another."""
    ends = np.cumsum(counts)
    at = np.repeat(starts - (ends - counts), counts)
    at += np.arange(len(at))
    return flat[at]


def _values(column: pa.Array) -> tuple[list[bytes], np.ndarray, np.ndarray]:
    """The values of a large binary column without nulls or empty values, their lengths, and which are words of plain
    lower-case letters."""
    edges = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2].to_pybytes()
    raw = np.frombuffer(data, np.uint8)[: edges[-1]]
    first = raw == LATIN
    pair = first[:-1] & IS_SECOND[raw[1:]]
    plain = IS_LETTER[raw]
    plain[:-1] |= pair
    plain[1:] |= pair
    odd = np.concatenate([[0], np.cumsum(~plain)])
    cuts = edges.tolist()
    return [data[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)], np.diff(edges), odd[edges[1:]] == odd[edges[:-1]]


class ChunkIds:
    """A table from chunks of UTF-8 bytes to their ids, over one vocabulary."""

    def __init__(self, path: str, entries: int = 300_000, longest: int = 48):
        # One core per task: the library's own threads would only contend.
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        self.tokenizer, self.entries, self.longest = Tokenizer.from_file(path), entries, longest
        self.whole = (self.tokenizer.normalizer, self.tokenizer.pre_tokenizer)
        # The same vocabulary and merges for parts that need no normalizing: white space splits, bytes become symbols.
        self.lean = (normalizers.Sequence([]), pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)]))
        names = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(names.values()) + 1, bool)
        self.ends[[i for name, i in names.items() if name.endswith("</w>")]] = True
        self.clear()

    def clear(self) -> None:
        #: Chunk -> start in ``flat`` and number of ids, as start << 32 | number.
        self.places: dict[bytes, int] = {}
        self.flat, self.used = np.empty(1 << 12, np.uint32), 0

    def _add(self, ids: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Append runs of ids; their places."""
        if self.used + len(ids) > len(self.flat):
            grown = np.empty(2 * (self.used + len(ids)), np.uint32)
            grown[: self.used] = self.flat[: self.used]
            self.flat = grown
        self.flat[self.used : self.used + len(ids)] = ids
        starts = self.used + np.cumsum(counts) - counts
        self.used += len(ids)
        return (starts << 32) | counts

    def _as(self, form: tuple) -> Tokenizer:
        self.tokenizer.normalizer, self.tokenizer.pre_tokenizer = form
        return self.tokenizer

    def _words(self, words: list[bytes]) -> np.ndarray:
        """Places of words of plain lower-case letters: one token of each, the last, ends a word."""
        texts = [b" ".join(words[at : at + 256]).decode() for at in range(0, len(words), 256)]
        found = self._as(self.lean).encode_batch_fast(texts, add_special_tokens=False)
        ids = np.concatenate([np.array(x.ids, np.uint32) for x in found])
        last = np.flatnonzero(self.ends[ids])
        return self._add(ids, np.diff(last, prepend=-1))

    def _parts(self, parts: list[bytes]) -> np.ndarray:
        """Places of any parts, some at a time as one text: a token belongs to the part that its first character lies in."""
        tokenizer, ids, counts = self._as(self.whole), [], []
        for at in range(0, len(parts), 256):
            texts = [p.decode("utf-8", "replace") for p in parts[at : at + 256]]
            found = tokenizer.encode(" ".join(texts), add_special_tokens=False)
            edges = np.cumsum([0, *(len(t) + 1 for t in texts)])
            begins = np.fromiter((o[0] for o in found.offsets), np.int64, len(found.offsets))
            counts.append(np.diff(np.searchsorted(begins, edges)))
            ids.append(np.array(found.ids, np.uint32))
        return self._add(np.concatenate(ids), np.concatenate(counts))

    def _alone(self, chunk: bytes) -> np.ndarray:
        ids = np.array(self._as(self.whole).encode(chunk.decode("utf-8", "replace"), add_special_tokens=False).ids, np.uint32)
        return self._add(ids, np.array([len(ids)]))

    def of(self, chunks: list[bytes], lengths: np.ndarray, plain: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(starts, counts) in ``flat`` of distinct chunks; valid until the next call.

        Chunks over ``longest`` bytes are encoded each time and not kept.  A table over ``entries`` is cut down to the
        chunks asked for now.
        """
        places = np.fromiter(map(self.places.get, chunks, repeat(-1)), np.int64, len(chunks))
        new, short = places < 0, lengths <= self.longest
        for own, encode in ((new & short & plain, self._words), (new & short & ~plain, self._parts)):
            at = np.flatnonzero(own)
            if len(at):
                names = [chunks[i] for i in at.tolist()]
                places[at] = encode(names)
                self.places.update(zip(names, places[at].tolist(), strict=True))
        kept = self.used
        for i in np.flatnonzero(new & ~short).tolist():
            places[i] = self._alone(chunks[i])[0]
        self.used = kept  # what was added last is still there, and the next call writes over it
        starts, counts = places >> 32, places & 0xFFFFFFFF
        if len(self.places) > self.entries:
            ids = gathered(self.flat, starts, counts)
            self.clear()
            places = self._add(ids, counts)
            self.places = {chunks[i]: x for i, x in zip(np.flatnonzero(short).tolist(), places[short].tolist(), strict=True)}
            starts = places >> 32
        return starts, counts

    def encoded(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids, bounds) of texts: those of the i-th are ``ids[bounds[i] : bounds[i + 1]]``.

        A closing run of ASCII marks after an ASCII letter or digit is a token group of its own, and the vocabulary is
        of lower case: chunks share their ids with and without marks, in either case of ASCII, unless the chunk may
        hold a special token's name.
        """
        blob = b"\n".join(texts)
        text_ends = np.cumsum([len(t) + 1 for t in texts]) - 1
        raw = np.frombuffer(blob, np.uint8)
        space = IS_SPACE[raw]
        edges = np.flatnonzero(np.diff(np.concatenate([[True], space, [True]]).view(np.int8)))
        start, end = edges[::2], edges[1::2]
        if not len(start):
            return np.empty(0, np.uint32), np.zeros(len(texts) + 1, np.int64)
        low, mark = LOWER[raw], IS_MARK[raw]
        places = np.int32 if len(raw) < 1 << 31 else np.int64
        stem = np.maximum.accumulate(np.where(mark, places(-1), np.arange(len(raw), dtype=places)))[end - 1]
        cut = (stem >= start) & (stem < end - 1) & IS_ALNUM[raw[stem]]
        at = blob.find(b"<|")
        while at >= 0:
            i = int(np.searchsorted(start, at, side="right")) - 1
            cut[i] = False
            low[start[i] : end[i]] = raw[start[i] : end[i]]
            at = blob.find(b"<|", int(end[i]))
        first = np.cumsum(1 + cut) - (1 + cut)
        part_start, part_end = np.empty(len(start) + int(cut.sum()), np.int64), np.empty(len(start) + int(cut.sum()), np.int64)
        part_start[first], part_end[first] = start, np.where(cut, stem + 1, end)
        part_start[first[cut] + 1], part_end[first[cut] + 1] = stem[cut] + 1, end[cut]
        offsets = np.concatenate([[0], np.cumsum(part_end - part_start)])
        parts = pa.Array.from_buffers(pa.large_binary(), len(part_start), [None, pa.py_buffer(offsets), pa.py_buffer(low[~space])]).dictionary_encode()
        starts, counts = self.of(*_values(parts.dictionary))
        index = parts.indices.to_numpy()
        counts = counts[index]
        ids = gathered(self.flat, starts[index], counts)
        before = np.concatenate([[0], np.cumsum(counts)])
        return ids, np.concatenate([[0], before[np.searchsorted(part_start, text_ends)]])


@cache
def chunk_ids(path: str) -> ChunkIds:
    """One table per worker process and vocabulary file."""
    return ChunkIds(path)


@contextmanager
def released(path: str) -> Iterator[ChunkIds]:
    """The worker's table for the length of a task; only the vocabulary stays in the worker."""
    table = chunk_ids(path)
    try:
        yield table
    finally:
        table.clear()
        pa.default_memory_pool().release_unused()


def ids_of(texts: Iterable[bytes], table: ChunkIds, end: int, group_bytes: int = 4 << 20) -> Iterator[bytes]:
    """The ids of each text (split as bytes: at ASCII white space) and the end id; texts pass in groups of some MB."""
    last, group, size = array("I", [end]).tobytes(), [], 0

    def flush() -> Iterator[bytes]:
        ids, bounds = table.encoded(group)
        cuts = bounds.tolist()
        return (ids[a:b].tobytes() + last for a, b in zip(cuts[:-1], cuts[1:], strict=True))

    for text in texts:
        group.append(text)
        size += len(text)
        if size > group_bytes:
            yield from flush()
            group, size = [], 0
    if group:
        yield from flush()
