"""A corpus through five stages: quality rules, near-duplicates, personal data, mixing, packing.

Each stage takes (spark, docs, sf_dir) and reads all its predecessor kept, as Parquet.  All but the last return the
columns of ``documents``, whatever their names and however many there are.

Defined results: a null text is an empty one (too short, so the quality rules reject it; later stages, each taken by
itself, keep it); null ids, languages and sources are values like others, but that no two rows are one document for
having no id; of repeated rows one stays; rows of one id and different texts are different documents; an empty table
gives an empty result in every stage; texts of any length are read whole.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from quorumgrad.llm import mixing, packing, pii, quality, simhash
from quorumgrad.llm.common import load
from quorumgrad.llm.queries import vocabulary
from quorumgrad.sources.sinks import drop_path, scratch_path, scratch_scope


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.kept_documents(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.deduplicated_similar(spark, docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pii.masked(docs)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed(spark, docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.packed(docs, vocabulary(), end=1)


STAGES = [("quality_rules", quality_rules), ("near_duplicates", near_duplicates), ("personal_data", personal_data), ("source_mix", source_mix), ("packing", pack)]

#: Suffix arrays, fingerprints and balanced sampling are beyond SQL; the tests compare each stage with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what each keeps is written to the shared folder and read again.

    A stage's working tables are deleted when its result is written, and its input when the next one's is.  The last
    stage reads the table that the fourth one left.
    """
    docs, before = load(spark, sf_dir, "documents"), None
    for name, stage in STAGES[:-1]:
        path = scratch_path(spark, f"stage-{name}")
        with scratch_scope(spark):
            kept = stage(spark, docs, sf_dir)
            kept.write.parquet(path)
        docs = spark.read.schema(kept.schema).parquet(path)
        if before:
            drop_path(spark, before)
        before = path
    return STAGES[-1][1](spark, docs, sf_dir)
