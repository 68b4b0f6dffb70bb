"""Feature frames (row_id, x, y, split) of the learning tasks."""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import vectors
from ..functions.hashing import hash32, split_name
from .tables import read_table

LANGS = ("de", "en", "es", "fr")


def planted(spark: SparkSession, sf_dir: str, flips: int = 0) -> DataFrame:
    """Which side of a planted plane an embedding lies on; ``flips`` of 10 labels are turned by a fixed rule."""
    e = read_table(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    x = F.transform("embedding", lambda v: v.cast("double"))
    y = (vectors.dot(x, vectors.planted(64)) > 0).cast("int")
    turned = F.pmod(F.col("vec_id") * 7919, F.lit(100)) < 10 * flips
    return e.select(F.col("vec_id").alias("row_id"), x.alias("x"), F.when(turned, 1 - y).otherwise(y).alias("y"), split_name(F.col("vec_id")).alias("split"))


def hashed_words(text: Column, width: int = 128) -> Column:
    """Unit vector of word counts by md5 bucket; null text is the zero vector.

    A histogram over the words' buckets: one pass over the words for the buckets, one comparison per word and bucket.
    """
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"\s+"), lambda w: w != "")
    buckets = F.transform(words, lambda w: (F.pmod(hash32(w), F.lit(width))).cast("int"))
    counts = F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.size(F.filter(buckets, lambda b: b == i)).cast("double"))
    norm = F.sqrt(F.aggregate(counts, F.lit(0.0), lambda s, c: s + c * c))
    return F.transform(counts, lambda c: c / F.greatest(norm, F.lit(1.0)))


def word_vectors(df: DataFrame, key: str, width: int = 128) -> DataFrame:
    """(key, x): the same vectors by explode and partial sums, which stay linear in words for long texts."""
    words = df.select(key, F.explode(F.split(F.lower("text"), r"\s+")).alias("w")).where("w <> ''")
    counts = words.groupBy(key, F.pmod(hash32(F.col("w")), F.lit(width)).cast("int").alias("b")).agg(F.count("*").cast("double").alias("n"))
    wide = counts.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct("b", "n"))).alias("m"), F.sqrt(F.sum(F.col("n") * F.col("n"))).alias("norm"))
    return wide.select(key, F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.coalesce(F.element_at("m", i), F.lit(0.0)) / F.col("norm")).alias("x"))


#: Rows that a worker turns into vectors at once, and words whose buckets it holds before it forgets them all.
PART, HELD = 512, 1 << 17


class Buckets(dict):
    """The md5 bucket of each word (bytes) asked for."""

    def __init__(self, width: int):
        super().__init__()
        self.width = width

    def __missing__(self, word: bytes) -> int:
        self[word] = found = int(md5(word).hexdigest()[:8], 16) % self.width
        return found


def languages(spark: SparkSession, sf_dir: str, width: int = 128) -> DataFrame:
    """Language of a document from hashed words: the main task with several classes.

    The vectors of ``word_vectors``, counted row by row in parts of Arrow batches: nothing is shuffled, and a worker holds
    the vectors of few texts and the buckets of few words at once.  Texts without a word have no row.
    """
    label = F.array_position(F.array(*map(F.lit, LANGS)), F.col("lang")).cast("int") - 1
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "text", "lang"]).select("doc_id", F.lower("text").cast("binary").alias("text"), label.alias("y")).where("y >= 0")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bucket = Buckets(width)
        for batch in (b.slice(at, PART) for b in batches for at in range(0, b.num_rows, PART)):
            kept, rows = [], []
            for i, text in enumerate(batch.column(1).to_pylist()):
                words = text.split() if text else ()  # bytes: ASCII white space only, as in the pattern
                if words:
                    if len(bucket) > HELD:
                        bucket.clear()
                    n = np.bincount(np.fromiter(map(bucket.__getitem__, words), np.int64, len(words)), minlength=width)
                    kept.append(i)
                    rows.append(n / np.sqrt((n * n).sum()))
            flat = pa.array(np.concatenate(rows) if rows else np.empty(0))
            x = pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1, dtype=np.int32) * width), flat)
            at = pa.array(kept, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(at), x, batch.column(2).take(at)], names=["row_id", "x", "y"])

    return docs.mapInArrow(run, "row_id long, x array<double>, y int").select("row_id", "x", "y", split_name(F.col("row_id")).alias("split"))


def labelled(spark: SparkSession, sf_dir: str, label: str = "quality", width: int = 128) -> DataFrame:
    """Documents with a quality or toxicity label."""
    labels = read_table(spark, sf_dir, "labels", ["doc_id", label]).where(F.col(label).isNotNull())
    docs = read_table(spark, sf_dir, "documents", ["doc_id", "text"]).join(labels, "doc_id")
    return word_vectors(docs, "doc_id", width).join(labels, "doc_id").select(F.col("doc_id").alias("row_id"), "x", F.col(label).alias("y"), split_name(F.col("doc_id")).alias("split"))


SYMBOLS = "abcdefghijklmnopqrstuvwxyz .,"


def symbol_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(ctx, prev, next, n): counts of neighbouring characters by language; other characters fold into one symbol.

    Each Arrow batch is counted in numpy and leaves at most languages x symbols squared rows, so little is shuffled.
    """
    docs = read_table(spark, sf_dir, "documents", ["text", "lang"]).where(F.col("lang").isin(*LANGS) & F.col("text").isNotNull())
    k = len(SYMBOLS) + 1
    code = np.full(256, k - 1)
    for i, c in enumerate(SYMBOLS):
        code[[ord(c), ord(c.upper())]] = i

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            total = np.zeros(len(LANGS) * k * k, np.int64)
            for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
                c = code[np.minimum(points, 255)]
                total += np.bincount((LANGS.index(lang) * k + c[:-1]) * k + c[1:], minlength=len(total))
            at = np.flatnonzero(total)
            columns = [at // (k * k), at // k % k, at % k]
            yield pa.RecordBatch.from_arrays([*[pa.array(x.astype(np.int32)) for x in columns], pa.array(total[at])], names=["ctx", "prev", "next", "n"])

    return docs.mapInArrow(run, "ctx int, prev int, next int, n long").groupBy("ctx", "prev", "next").agg(F.sum("n").alias("n"))


def sparse_roles(spark: SparkSession, sf_dir: str, tokens: int = 4096) -> DataFrame:
    """(row_id, token, count, y): who speaks, from hashed words of a turn; long form for sparse models."""
    conv = read_table(spark, sf_dir, "conversations", ["conv_id", "turn", "role", "text"])
    rows = conv.select((F.col("conv_id") * 1000 + F.col("turn")).alias("row_id"), (F.col("role") == "user").cast("int").alias("y"), F.explode(F.split(F.lower("text"), r"\s+")).alias("w")).where("w <> ''")
    return rows.groupBy("row_id", "y", F.pmod(hash32(F.col("w")), F.lit(tokens)).alias("token")).agg(F.count("*").cast("double").alias("count"))
