"""Packing by vector bin packing with the dot-product heuristic.

An example is a vector (tokens, segments, loss-bearing tokens) and a sequence a bin with a limit on each.  Examples
are cut into full sequences; their tails are packed in blocks: the open bin takes the tail with the largest weighted
dot product of its demands and the bin's free room among those that fit.  Where none fits whole and the bin still has
room in every dimension, the best tail is cut to fill it.  What is left at the end of a partition goes into sequences
whose lengths are powers of two, which need no padding.

``packed`` takes documents, whose every token but a segment's first bears loss.  ``packed_turns`` takes conversations:
one example each, of which only the answering role's tokens bear loss, so that all three limits can bind.

Every partition packs its own rows: a lost task packs the same rows the same way again.  A task holds the ids of one
block of tails, each shorter than a sequence, whatever the texts' lengths.

Defined results: a null text is empty (its only id is the end id); repeated rows are packed each; a null doc_id stays
null; an empty table gives no piece; further columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_texts, only
from .tokens import ID_BYTES, ids_of, released

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, loss_tokens long"
NAMES = [c.strip().split()[0] for c in SCHEMA.split(",")]


@dataclass(frozen=True)
class Limits:
    """Limits of a sequence.  The first token of a segment bears no loss, so a sequence has at least one that doesn't."""

    tokens: int = 2048
    segments: int = 512
    loss_tokens: int = 2047
    block: int = 1024

    def __post_init__(self):
        if min(self.tokens, self.segments, self.block) < 1 or self.loss_tokens < 0:
            raise ValueError("a sequence needs room for a token, a segment and no negative loss")

    @property
    def vector(self) -> np.ndarray:
        return np.array([self.tokens, self.segments, self.loss_tokens], float)


@dataclass
class Tail:
    """Ids of an example from ``start`` on that are still to be placed.

    ``data`` are these ids, ``total`` the whole example's number of ids.  ``loss`` counts loss-bearing ids before each
    place of ``data`` (one more entry than ids); without it every id but a piece's first bears loss.
    """

    doc: int | None
    start: int
    data: bytes
    total: int
    loss: np.ndarray | None = None

    def __len__(self) -> int:
        return len(self.data) // ID_BYTES

    def losses(self, length: int | None = None) -> int:
        """Loss-bearing ids among the first ``length``."""
        n = len(self) if length is None else length
        return max(n - 1, 0) if self.loss is None else int(self.loss[n] - self.loss[0])

    def most(self, tokens: int, losses: int) -> int:
        """How many ids fit from the first on."""
        n = min(len(self), tokens)
        if self.loss is None:
            return min(n, losses + 1)
        return min(n, int(np.searchsorted(self.loss, self.loss[0] + losses, side="right")) - 1)

    def split(self, length: int) -> tuple[Tail, Tail]:
        a, b = self.data[: length * ID_BYTES], self.data[length * ID_BYTES :]
        left, right = (None, None) if self.loss is None else (self.loss[: length + 1], self.loss[length:])
        return Tail(self.doc, self.start, a, self.total, left), Tail(self.doc, self.start + length, b, self.total, right)


def pack_block(tails: list[Tail], limits: Limits) -> tuple[list[list[Tail]], list[Tail]]:
    """Bins (lists of pieces) that are full or closed, and the pieces of the last, unfilled bin."""
    tails = list(tails)
    need = np.array([(len(t), 1, t.losses()) for t in tails], float).reshape(-1, 3)
    alive = np.ones(len(tails), bool)
    scale = 1.0 / np.maximum(limits.vector, 1.0)  # demands and room count as fractions of the limits
    weight = need.sum(axis=0) * scale
    weight = weight / max(weight.sum(), 1e-9) * scale  # a scarce dimension weighs more
    parts = need * weight
    bins, own = [], []
    room = limits.vector.copy()
    while alive.any():
        score = parts @ (room * scale)
        fits = alive & (need <= room + 1e-9).all(axis=1)
        if fits.any():
            i = int(np.where(fits, score, -1.0).argmax())
            take = len(tails[i])
        else:
            i = int(np.where(alive, score, -1.0).argmax())
            take = tails[i].most(int(room[0]), int(room[2])) if room[1] >= 1 else 0
        if take <= 0:
            if not own:
                raise ValueError("no sequence can hold the next token: the limit on loss-bearing tokens is too small")
            bins.append(own)
            own, room = [], limits.vector.copy()
            continue
        piece, rest = tails[i].split(take)
        own.append(piece)
        room -= (take, 1, piece.losses())
        tails[i], alive[i] = rest, len(rest) > 0
        need[i] = len(rest), 1, rest.losses()
        parts[i] = need[i] * weight
        if room[0] < 1:
            bins.append(own)
            own, room = [], limits.vector.copy()
    return bins, own


def power_of_two_bins(pieces: list[Tail], limits: Limits) -> list[list[Tail]]:
    """Sequences of power-of-two lengths that hold all pieces; they are those of one bin, so no limit is passed."""
    rest, out = list(pieces), []
    while left := sum(map(len, rest)):
        size = min(1 << (left.bit_length() - 1), 1 << (limits.tokens.bit_length() - 1))
        own, free = [], size
        while free:
            piece, after = rest[0].split(min(free, len(rest[0])))
            own.append(piece)
            free -= len(piece)
            rest[:1] = [after] if len(after) else []
        out.append(own)
    return out


def bins_of(examples: Iterable[Tail], limits: Limits) -> Iterator[list[Tail]]:
    """Sequences (lists of pieces) of all examples, as soon as they are closed."""
    tails: list[Tail] = []
    for rest in examples:
        while len(rest) and (len(rest) >= limits.tokens or rest.losses() > limits.loss_tokens):
            take = rest.most(limits.tokens, limits.loss_tokens)
            if take <= 0:
                raise ValueError("no sequence can hold the next token: the limit on loss-bearing tokens is too small")
            piece, rest = rest.split(take)
            if take == limits.tokens:
                yield [piece]
            else:
                tails.append(piece)
        if len(rest):
            tails.append(rest)
        while len(tails) >= limits.block:
            bins, tails = pack_block(tails, limits)
            yield from bins
            if not bins:
                break
    if tails:
        bins, tails = pack_block(tails, limits)
        yield from bins
    yield from power_of_two_bins(tails, limits)


def written(bins: Iterable[list[Tail]], base: int, rows: int = 8192) -> Iterator[pa.RecordBatch]:
    """Batches of pieces; sequences are numbered from ``base`` on."""
    out: list[tuple] = []

    def batch() -> pa.RecordBatch:
        columns = zip(*out, strict=True) if out else [[]] * len(NAMES)
        made = pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=NAMES)
        out.clear()
        return made

    for sequence, pieces in enumerate(bins, base):
        offset = 0
        for p in pieces:
            out.append((p.doc, p.start, len(p), zlib.crc32(p.data), p.total, sequence, offset, p.losses()))
            offset += len(p)
        if len(out) >= rows:
            yield batch()
    yield batch()


def packed(docs: DataFrame, tokenizer: str, end: int, limits: Limits = Limits()) -> DataFrame:
    """Pieces of all documents (doc_id, text) with their sequence and offset.  Narrow: no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with released(tokenizer) as table:

            def examples() -> Iterator[Tail]:
                for batch in batches:
                    raw, starts, ends = batch_texts(batch.column(1))
                    texts = (raw[a:b].tobytes() for a, b in zip(starts, ends, strict=True))
                    for doc_id, data in zip(batch.column(0).to_pylist(), ids_of(texts, table, end), strict=True):
                        yield Tail(doc_id, 0, data, len(data) // ID_BYTES)

            yield from written(bins_of(examples(), limits), TaskContext.get().partitionId() << 40)

    own = only(docs, "doc_id", "text")
    return own.withColumn("doc_id", own["doc_id"].cast("long")).mapInArrow(run, SCHEMA)


def packed_turns(turns: DataFrame, tokenizer: str, end: int, roles: tuple[str, ...] = ("assistant",), limits: Limits = Limits(), partitions: int | None = None) -> DataFrame:
    """Pieces of all conversations (conv_id, turn, role, text); ``doc_id`` is the conversation's id.

    A conversation is its turns in order (ties by role, then text), each with the end id; ids of turns by one of
    ``roles`` bear loss.  Turns are dealt by conversation and sorted, and pass as a stream: a conversation is held
    as ids, never its turns' rows.  Null text is empty, a null role bears no loss, rows of a null conv_id are one
    conversation.
    """
    own = only(turns, "conv_id", "turn", "role", "text").select(F.col("conv_id").cast("long").alias("conv_id"), "turn", F.col("role").isin(*roles).alias("bears"), "role", "text")
    dealt = own.repartition(*([partitions] if partitions else []), "conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with released(tokenizer) as table:

            def turns_of() -> Iterator[tuple[int | None, bool, bytes]]:
                for batch in batches:
                    raw, starts, ends = batch_texts(batch.column(2))
                    texts = (raw[a:b].tobytes() for a, b in zip(starts, ends, strict=True))
                    yield from zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), ids_of(texts, table, end), strict=True)

            def examples() -> Iterator[Tail]:
                last, data, flags = None, [], []

                def whole() -> Tail:
                    ids = b"".join(data)
                    return Tail(last, 0, ids, len(ids) // ID_BYTES, np.concatenate([[0], np.cumsum(np.concatenate(flags))]))

                for conv_id, bears, ids in turns_of():
                    if data and conv_id != last:
                        yield whole()
                        data, flags = [], []
                    last = conv_id
                    data.append(ids)
                    flags.append(np.full(len(ids) // ID_BYTES, bool(bears), np.int64))
                if data:
                    yield whole()

            yield from written(bins_of(examples(), limits), TaskContext.get().partitionId() << 40)

    return dealt.select("conv_id", "bears", "text").mapInArrow(run, SCHEMA)
