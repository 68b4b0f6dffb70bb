"""The thin queries of the ten operators and of the pipeline, with SQL where SQL can say it."""

from __future__ import annotations

from functools import cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import fingerprints, html_text, mixing, packing, pii, quality, rollups, secrets, simhash, token_store
from .common import load, scratch_path


@cache
def vocabulary(name: str = "word_bpe_49k.json") -> str:
    """A public tokenizer's file, as the installed package places it."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pii_spans(load(spark, sf_dir, "documents"))


def op2_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(spark, load(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "times")


def op3_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.main_text(spark, load(spark, sf_dir, "pages"))


def op4_repetition(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_report(load(spark, sf_dir, "documents")).drop("longest_repeat")


def op5_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch_path(spark, "token-store")
    token_store.write_store(load(spark, sf_dir, "documents"), path, vocabulary(), end=2)
    return token_store.digests(token_store.read_store(spark, path))


def op6_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.fingerprint_report(load(spark, sf_dir, "documents"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(load(spark, sf_dir, "documents"), vocabulary(), end=1)


def op8_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents come in, those with an id divisible by 5 get a new tokenizer version, those of 7 go; each batch twice."""
    docs = load(spark, sf_dir, "documents")
    store = rollups.Rollup(spark, scratch_path(spark, "rollup"))
    fifth, seventh = docs.where("doc_id % 5 = 0"), docs.where("doc_id % 7 = 0")
    batches = {
        1: rollups.inserts(docs, "words-1"),
        2: rollups.revisions(fifth, "words-1", "marks-2"),
        3: rollups.deletes(seventh.where("doc_id % 5 <> 0"), "words-1").unionByName(rollups.deletes(seventh.where("doc_id % 5 = 0"), "marks-2")),
    }
    for number, deltas in [*batches.items(), *batches.items()]:
        store.commit(number, deltas)
    return store.totals().select("source", "lang", "tokenizer", F.col("docs").alias("n_docs"), F.col("tokens").alias("n_tokens"))


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(spark, load(spark, sf_dir, "documents"))


def op10_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_spans(load(spark, sf_dir, "documents"))


OP4_SQL = r"""
WITH d AS (SELECT doc_id, COALESCE(text, '') AS t FROM documents),
tok AS (SELECT doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d),
pos AS (SELECT doc_id, unnest(range(1, len(w) + 1)) AS i, w, len(w) AS n FROM tok),
win AS (SELECT doc_id, i, n, CASE WHEN i + 2 <= n THEN hash(list_slice(w, i, i + 2)) END AS h3, CASE WHEN i + 7 <= n THEN hash(list_slice(w, i, i + 7)) END AS h8,
  CASE WHEN i + 50 <= n THEN hash(list_slice(w, i, i + 50)) END AS h51 FROM pos),
seen AS (SELECT doc_id, i,
  h3 IS NOT NULL AND count(*) OVER (PARTITION BY doc_id, h3) > 1 AS r3, h8 IS NOT NULL AND count(*) OVER (PARTITION BY doc_id, h8) > 1 AS r8,
  h51 IS NOT NULL AND count(*) OVER (PARTITION BY doc_id, h51) > 1 AS r51 FROM win),
cover AS (SELECT doc_id, r51, max(r3) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS c3,
  max(r8) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 7 PRECEDING AND CURRENT ROW) AS c8 FROM seen),
agg AS (SELECT doc_id, count(*) FILTER (c3) AS n3, count(*) FILTER (c8) AS n8, bool_or(r51) AS long FROM cover GROUP BY doc_id),
base AS (SELECT tok.doc_id, len(w)::BIGINT AS n_words, COALESCE(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
  length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines,
  COALESCE(n3, 0)::BIGINT AS n_repeat_words, COALESCE(n8, 0)::BIGINT AS n_covered_words, COALESCE(long, false) AS long FROM tok LEFT JOIN agg USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed,
  NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND n_covered_words <= 0.4 * n_words AND NOT long AS kept, n_covered_words FROM base
"""

OP8_SQL = r"""
WITH d AS (SELECT doc_id, source, lang, COALESCE(text, '') AS t FROM documents WHERE doc_id % 7 <> 0),
c AS (SELECT source, lang, CASE WHEN doc_id % 5 = 0 THEN 'marks-2' ELSE 'words-1' END AS tokenizer,
  CASE WHEN doc_id % 5 = 0 THEN len(regexp_extract_all(t, '[A-Za-z0-9]+|[^A-Za-z0-9\x20\x09-\x0D]')) ELSE len(regexp_extract_all(t, '[^\x20\x09-\x0D]+')) END AS n FROM d)
SELECT source, lang, tokenizer, count(*)::BIGINT AS n_docs, sum(n)::BIGINT AS n_tokens FROM c GROUP BY ALL
"""

QUERIES = {
    "op1_pii": op1_pii, "op2_mixing": op2_mixing, "op3_html_text": op3_html_text, "op4_repetition": op4_repetition, "op5_token_store": op5_token_store,
    "op6_fingerprints": op6_fingerprints, "op7_packing": op7_packing, "op8_token_rollup": op8_token_rollup, "op9_simhash": op9_simhash, "op10_secrets": op10_secrets,
}
ORACLES = {"op4_repetition": OP4_SQL, "op8_token_rollup": OP8_SQL}
