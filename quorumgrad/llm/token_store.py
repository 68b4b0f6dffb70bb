"""Token ids on disk: each document compressed alone, with one shared zstandard dictionary.

File format: a folder of two Parquet tables, written and read by Spark alone so that any file system will do.
``dictionary``: one row (dict_hash, dictionary).  ``shards``: one row per shard with its number, the hash of the
dictionary it needs, the documents' ids, the offset index (binary, little-endian unsigned 64-bit, one more than
documents), the token counts and the payload, in which each document is a zstandard frame of its ids as little-endian
unsigned 32-bit integers.  A short document is read by its two offsets, without its neighbours.

The dictionary is trained on the serialized ids of a bounded sample: the ``sample_docs`` documents of the smallest hash
of doc_id.  Documents are range-partitioned by doc_id before encoding, so a shard's number is its place in the order.

Defined results: a null text is empty (its only id is the end id); a null doc_id comes first; repeated rows are stored
each; an empty table makes a store with no shard; further columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import batch_texts, materialized, only, slices
from .tokens import ID_BYTES, chunk_ids, ids_of, released

SHARDS = "part long, seq long, dict_hash string, doc_ids array<bigint>, counts array<bigint>, offsets binary, payload binary"


def train_dictionary(docs: DataFrame, tokenizer: str, end: int, sample_docs: int = 256, sample_bytes: int = 1 << 16, dict_bytes: int = 64 << 10) -> bytes:
    """A dictionary from the ids of ``sample_docs`` documents, at most ``sample_bytes`` of ids of each."""
    own = only(docs, "doc_id", "text").withColumn("h", F.xxhash64("doc_id"))
    # The hashes alone are ordered; texts are read only at or under the largest that is taken.
    last = own.select("h").orderBy("h").limit(sample_docs).agg(F.max("h")).first()[0]
    rows = own.where(F.col("h") <= last).limit(sample_docs).select(F.substring("text", 1, sample_bytes)).collect() if last is not None else []
    table = chunk_ids(tokenizer)
    samples = [x[:sample_bytes] for x in ids_of(((r[0] or "").encode("utf-8", "surrogatepass") for r in rows), table, end)]
    samples = [s[i : i + 2048] for s in samples for i in range(0, len(s), 2048)]
    try:
        return zstandard.train_dictionary(dict_bytes, samples).as_bytes()
    except zstandard.ZstdError:  # too little to learn from: plain content serves as a dictionary
        return b"".join(samples)[-dict_bytes:] or b"\0" * 8


def dictionary_hash(data: bytes) -> str:
    return hashlib.sha256(data).hexdigest()


def write_store(docs: DataFrame, path: str, tokenizer: str, end: int, shard_bytes: int = 8 << 20, level: int = 3, partitions: int | None = None) -> None:
    """Encode every whole text, append ``end``, and write the store."""
    spark = docs.sparkSession
    data = train_dictionary(docs, tokenizer, end)
    digest = dictionary_hash(data)
    spark.createDataFrame([(digest, bytearray(data))], "dict_hash string, dictionary binary").coalesce(1).write.parquet(f"{path}/dictionary")

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pack = zstandard.ZstdCompressor(level=level, dict_data=zstandard.ZstdCompressionDict(data), write_content_size=True, write_checksum=False)
        part, seq, ids, counts, frames, size = TaskContext.get().partitionId(), 0, [], [], [], 0

        def shard() -> pa.RecordBatch:
            offsets = np.concatenate([[0], np.cumsum([len(f) for f in frames])]).astype("<u8").tobytes()
            row = [[part], [seq], [digest], [ids], [counts], [offsets], [b"".join(frames)]]
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary(), pa.binary()]
            return pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(row, kinds, strict=True)], names=[c.strip().split()[0] for c in SHARDS.split(",")])

        with released(tokenizer) as table:
            for batch in batches:
                raw, starts, ends = batch_texts(batch.column(1))
                texts = (raw[a:b].tobytes() for a, b in zip(starts, ends, strict=True))
                for doc_id, data_ids in zip(batch.column(0).to_pylist(), ids_of(texts, table, end), strict=True):
                    frame = pack.compress(data_ids)
                    ids.append(doc_id)
                    counts.append(len(data_ids) // ID_BYTES)
                    frames.append(frame)
                    size += len(frame)
                    if size >= shard_bytes:
                        yield shard()
                        seq, ids, counts, frames, size = seq + 1, [], [], [], 0
        if ids:
            yield shard()

    own = only(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("long"))
    n = partitions or max(own.rdd.getNumPartitions(), 1)
    ordered = own.repartitionByRange(n, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    ordered.mapInArrow(encode, SHARDS).write.option("compression", "uncompressed").parquet(f"{path}/shards")


def read_dictionary(spark: SparkSession, path: str) -> tuple[str, bytes]:
    row = spark.read.parquet(f"{path}/dictionary").first()
    if dictionary_hash(bytes(row[1])) != row[0]:
        raise ValueError("the dictionary does not have the hash that it is stored under")
    return row[0], bytes(row[1])


def read_store(spark: SparkSession, path: str, batch_bytes: int = 4 << 20) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, ids (binary) of each document, from the files.

    Documents are handed on in batches of ``batch_bytes`` of ids (one longer document alone).
    """
    digest, data = read_dictionary(spark, path)
    # Shards are numbered within their part; parts, one row for each task that wrote, in one task.
    index = spark.read.parquet(f"{path}/shards").select("part", "seq", F.aggregate("counts", F.lit(0).cast("long"), lambda a, b: a + b).alias("total"))
    earlier = lambda w: F.coalesce(F.sum("total").over(w.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    parts = index.groupBy("part").agg(F.sum("total").alias("total"))
    parts = parts.select("part", earlier(W.orderBy("part")).alias("start"))
    index = index.withColumn("within", earlier(W.partitionBy("part").orderBy("seq"))).join(parts, "part")
    index = index.select("part", "seq", (F.col("start") + F.col("within")).alias("base"))
    # Written, so that the planner knows its size and sends it out rather than moving the payloads.
    index = materialized(spark, index, "shard-index", few=True)
    shards = spark.read.parquet(f"{path}/shards").join(index, ["part", "seq"]).select("base", "dict_hash", "doc_ids", "counts", "offsets", "payload")

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(data))
        for batch in batches:
            for i in range(batch.num_rows):
                base, used, doc_ids, counts, offsets, payload = (c[i] for c in batch.columns)
                if used.as_py() != digest:
                    raise ValueError("a shard needs another dictionary")
                at, body = np.frombuffer(offsets.as_buffer(), "<u8").tolist(), payload.as_buffer()
                n = np.array(counts.as_py(), np.int64)
                starts = base.as_py() + np.concatenate([[0], np.cumsum(n)[:-1]])
                rows = doc_ids.as_py()
                for lo, hi in slices(len(rows), n * ID_BYTES, batch_bytes):
                    ids = [unpack.decompress(body[at[k] : at[k + 1]]) for k in range(lo, hi)]
                    yield pa.RecordBatch.from_arrays([pa.array(rows[lo:hi], pa.int64()), pa.array(starts[lo:hi]), pa.array(n[lo:hi]), pa.array(ids, pa.binary())], names=["doc_id", "start", "n_tokens", "ids"])

    return shards.mapInArrow(decode, "doc_id long, start long, n_tokens long, ids binary")


def digests(store: DataFrame) -> DataFrame:
    """The ids of each document as their unsigned crc32."""
    return store.select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))


def one_document(shard: dict, place: int, dictionary: bytes) -> np.ndarray:
    """Short access: the ids of the ``place``-th document of a shard row by its two offsets."""
    at = np.frombuffer(shard["offsets"], "<u8")
    frame = bytes(shard["payload"][int(at[place]) : int(at[place + 1])])
    ids = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(dictionary)).decompress(frame)
    return np.frombuffer(ids, "<u4")
