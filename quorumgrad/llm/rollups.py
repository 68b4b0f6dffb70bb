"""Token counts kept by delta: signed changes update additive totals by source, language and tokenizer version.

A batch is a set of signed rows (source, lang, tokenizer, docs, tokens): an insert counts +1, a delete -1, and a revised
count is the old one taken back and the new one added.  A batch is summed before it is stored, lands in a folder that
bears its number, and is committed by the marker that Spark's writer puts there last.  Committing the same number again
replaces or skips the same folder, so a replay after a lost driver or executor changes nothing.  Totals are the sum of
all committed batches; ``compact`` folds them into one, which keeps their numbers in a row of its own, so that a
replay into the compacted store changes nothing either.

Tokens are counted by a version's pattern (``VERSIONS``), or, where the version is the path of a vocabulary file, by
that tokenizer over whole texts.

Defined results: null source, language or text form groups or counts of their own (null text has 0 tokens); repeated
rows count each; groups whose documents are all deleted go; an empty batch changes nothing; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import batch_texts, only, text_or_empty
from .tokens import ID_BYTES, ids_of, released

KEYS = ("source", "lang", "tokenizer")
#: Tokenizer versions that need no vocabulary: words between white space, and words or single marks.
VERSIONS = {"words-1": r"[^\x20\x09-\x0D]+", "marks-2": r"[A-Za-z0-9]+|[^A-Za-z0-9\x20\x09-\x0D]"}
STORED = "source string, lang string, tokenizer string, docs long, tokens long, folded array<long>"


def count_tokens(version: str) -> Column:
    return F.regexp_count(text_or_empty(), F.lit(VERSIONS[version])).cast("long")


def by_vocabulary(docs: DataFrame, path: str) -> DataFrame:
    """(source, lang, tokens) of each row, by the tokenizer of a vocabulary file.  Narrow."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with released(path) as table:
            for batch in batches:
                raw, starts, ends = batch_texts(batch.column(2))
                texts = (raw[a:b].tobytes() for a, b in zip(starts, ends, strict=True))
                counts = np.fromiter((len(x) // ID_BYTES - 1 for x in ids_of(texts, table, 0)), np.int64, batch.num_rows)
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(counts)], names=["source", "lang", "tokens"])

    own = only(docs, "source", "lang", "text").select(F.col("source").cast("string"), F.col("lang").cast("string"), "text")
    return own.mapInArrow(run, "source string, lang string, tokens long")


def inserts(docs: DataFrame, version: str, name: str | None = None) -> DataFrame:
    """Signed rows of documents that come in.  ``version`` is one of ``VERSIONS`` or a vocabulary file, ``name`` what it
    is stored as (the version itself by default)."""
    if version in VERSIONS:
        counted = only(docs, "source", "lang", "text").withColumn("tokens", count_tokens(version))
    else:
        counted = by_vocabulary(docs, version)
    return counted.select("source", "lang", F.lit(name or version).alias("tokenizer"), F.lit(1).cast("long").alias("docs"), "tokens")


def deletes(docs: DataFrame, version: str, name: str | None = None) -> DataFrame:
    return inserts(docs, version, name).withColumns({"docs": -F.col("docs"), "tokens": -F.col("tokens")})


def revisions(docs: DataFrame, old: str, new: str) -> DataFrame:
    return deletes(docs, old).unionByName(inserts(docs, new))


class Rollup:
    """Totals in a folder of the shared file system."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def _folder(self, batch: int) -> str:
        return f"{self.path}/batch={batch:012d}"

    def _rows(self) -> DataFrame:
        schema = f"{STORED}, batch long"
        try:
            return self.spark.read.schema(schema).option("basePath", self.path).parquet(self.path)
        except AnalysisException:  # nothing has been committed yet
            return self.spark.createDataFrame([], schema)

    def committed(self, batch: int) -> bool:
        """Whether the batch's marker is there, or its number among those that a compacted batch holds."""
        jvm = self.spark.sparkContext._jvm
        marker = jvm.org.apache.hadoop.fs.Path(f"{self._folder(batch)}/_SUCCESS")
        if marker.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(marker):
            return True
        return not self._rows().where(F.array_contains("folded", F.lit(batch).cast("long"))).isEmpty()

    def _store(self, batch: int, deltas: DataFrame, folded: DataFrame | None = None) -> bool:
        if self.committed(batch):
            return False
        summed = deltas.groupBy(*KEYS).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        rows = summed.withColumn("folded", F.lit(None).cast("array<long>"))
        (rows if folded is None else rows.unionByName(folded)).write.mode("overwrite").parquet(self._folder(batch))
        return True

    def commit(self, batch: int, deltas: DataFrame) -> bool:
        """Store a batch of signed rows unless it is there; False if it was."""
        return self._store(batch, deltas)

    def totals(self, upto: int | None = None) -> DataFrame:
        """source, lang, tokenizer, docs, tokens over the committed batches (up to a number)."""
        rows = self._rows() if upto is None else self._rows().where(F.col("batch") <= upto)
        return rows.groupBy(*KEYS).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens")).where("docs <> 0 or tokens <> 0")

    def numbers(self, upto: int) -> DataFrame:
        """The numbers up to ``upto`` that are committed here, those of compacted batches included."""
        rows = self._rows().where(F.col("batch") <= upto)
        # A batch without a row has a folder all the same, so folders are asked, not rows.
        jvm, conf = self.spark.sparkContext._jvm, self.spark.sparkContext._jsc.hadoopConfiguration()
        root = jvm.org.apache.hadoop.fs.Path(self.path)
        fs = root.getFileSystem(conf)
        names = [s.getPath().getName() for s in fs.listStatus(root)] if fs.exists(root) else []
        done = [int(n[6:]) for n in names if n.startswith("batch=") and fs.exists(jvm.org.apache.hadoop.fs.Path(f"{self.path}/{n}/_SUCCESS"))]
        own = self.spark.createDataFrame([(n,) for n in done if n <= upto], "n long")
        return own.union(rows.select(F.explode("folded").alias("n"))).distinct()

    def compact(self, other: Rollup, upto: int) -> None:
        """Fold batches up to a number into one batch of another store; rows and numbers are committed together."""
        held = self.numbers(upto).agg(F.array_sort(F.collect_set("n")).alias("folded"))
        none = F.lit(None).cast("string")
        mark = held.select(*[none.alias(k) for k in KEYS], F.lit(0).cast("long").alias("docs"), F.lit(0).cast("long").alias("tokens"), "folded")
        other._store(upto, self.totals(upto), mark)
