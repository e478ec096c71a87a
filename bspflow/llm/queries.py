"""The digest queries of the operators, each over its whole table with production parameters, and their SQL."""

from __future__ import annotations

import os
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import pii
from .ann import nearest
from .bitslice import exact_top_k
from .common import materialize, shared_path, word_count
from .langid import identify
from .mixing import mix_sources
from .rollup import Ledger, signed_changes
from .simhash import near_duplicate_components
from .spiece import sample_segmentations
from .substring import substring_dedup
from .tokens_out import byte_tokens, read_slots, write_training_order

#: Segmentations sampled for each document.
SAMPLES = 2


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = substring_dedup(_docs(spark, sf_dir), window=50)
    return cut.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mix_sources(_docs(spark, sf_dir), weights=(5, 2, 1), max_epochs=3, seed=17)
    return mixed.select("doc_id", "size", "source_size", "target", "taken")


def _every_20th(vectors: DataFrame) -> DataFrame:
    """The stated query set of the searches."""
    return vectors.where(F.col("vec_id") % 20 == 0)


def op3_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return nearest(vectors, _every_20th(vectors), k=20)


def op4_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicate_components(_docs(spark, sf_dir), most_bits=4)
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def piece_model() -> str:
    """Path of the public piece vocabulary; ``BSPFLOW_PIECES`` names another."""
    if said := os.environ.get("BSPFLOW_PIECES"):
        return said
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def op5_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    sampled = sample_segmentations(_docs(spark, sf_dir), piece_model(), k=SAMPLES, seed=11)
    return sampled.select("doc_id", "sample", "n_tokens", "log_prob", "inclusion", F.sha2("ids", 256).alias("ids_sha256"), "round_trip")


def op6_training_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sequences of 2,048 byte tokens in training order, read back from the binary shards.

    ``piece_tokens`` gives piece numbers instead; encoding them takes more than this query's budget (README).
    """
    path = shared_path(spark, "order")
    write_training_order(_docs(spark, sf_dir), path, byte_tokens(F.col("text")), length=2048, shard_rows=2048, key=20)
    return read_slots(spark, path).select("slot", "shard", "seq", F.octet_length("tokens").cast("long").alias("n_tokens"), F.sha2("tokens", 256).alias("tokens_sha256"))


def op7_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.summary(pii.find(_docs(spark, sf_dir).select("doc_id", "text")))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three batches over the corpus: insert all counts of two tokenizers; delete documents under 10 words; revise
    the byte counts to texts without outer spaces.  The second batch is sent twice, as a retry would."""
    docs = _docs(spark, sf_dir)
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long")
    bare = F.coalesce(F.octet_length(F.trim("text")), F.lit(0)).cast("long")
    sized = materialize(docs.select("doc_id", "source", "lang", word_count(F.col("text")).alias("words"), size.alias("bytes"), bare.alias("bare")), "counts")

    def counts(rows: DataFrame, **kinds: str) -> DataFrame:
        pairs = F.explode(F.array(*[F.struct(F.lit(k).alias("tokenizer"), F.col(c).alias("tokens")) for k, c in kinds.items()]))
        return rows.select("doc_id", "source", "lang", pairs.alias("x")).select("doc_id", "source", "lang", "x.tokenizer", "x.tokens")

    both = {"words_v1": "words", "bytes_v1": "bytes"}
    ledger = Ledger(spark, shared_path(spark, "ledger"))
    kept = sized.where("words >= 10")
    removal = signed_changes(counts(sized.where("words < 10"), **both), None)
    ledger.commit("insert-all", signed_changes(None, counts(sized, **both)))
    ledger.commit("delete-short", removal)
    ledger.commit("delete-short", removal)
    ledger.compact()
    ledger.commit("revise-bytes", signed_changes(counts(kept, bytes_v1="bytes"), counts(kept, bytes_v1="bare")))
    return ledger.totals()


def op9_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return exact_top_k(vectors, _every_20th(vectors), k=20, scale=64.0)


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(_docs(spark, sf_dir))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_substring_dedup": op1_substring_dedup,
    "op2_mix_sources": op2_mix_sources,
    "op3_nearest": op3_nearest,
    "op4_simhash_dedup": op4_simhash_dedup,
    "op5_sentencepiece": op5_sentencepiece,
    "op6_training_order": op6_training_order,
    "op7_pii": op7_pii,
    "op8_token_counts": op8_token_counts,
    "op9_exact_top_k": op9_exact_top_k,
    "op10_language_id": op10_language_id,
}

_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

SQL: dict[str, str] = {
    "op1_substring_dedup": f"""
WITH w AS (SELECT doc_id, {_WORDS} AS ws FROM documents),
t AS (SELECT doc_id, ws, unnest(range(1, len(ws) + 1)) AS pos FROM w),
h AS (SELECT doc_id, pos, ws[pos] AS word,
             CASE WHEN pos + 49 <= len(ws) THEN md5(array_to_string(ws[pos:pos + 49], ' ')) END AS h FROM t),
low AS (SELECT h, min(doc_id) AS low FROM h WHERE h IS NOT NULL GROUP BY h),
f AS (SELECT doc_id, pos, word, coalesce(low < doc_id, false) AS hit FROM h LEFT JOIN low USING (h)),
c AS (SELECT doc_id, pos, word, bool_or(hit) OVER (PARTITION BY doc_id ORDER BY pos ROWS 49 PRECEDING) AS gone FROM f),
k AS (SELECT doc_id, count(*) FILTER (gone) AS n_removed, string_agg(word, ' ' ORDER BY pos) FILTER (NOT gone) AS kept FROM c GROUP BY doc_id)
SELECT w.doc_id, len(ws)::BIGINT AS n_words, coalesce(n_removed, 0)::BIGINT AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM w LEFT JOIN k USING (doc_id)""",
    "op2_mix_sources": f"""
WITH d AS (SELECT doc_id, source, len({_WORDS})::BIGINT AS size,
                  ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null') || ':17'), 1, 15))::BIGINT AS key FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source::BLOB ASC NULLS LAST) - 1 AS turn FROM d GROUP BY source),
q AS (SELECT *, CASE turn % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS weight, 3 * source_size AS cap,
             sum(source_size) OVER () AS total FROM s),
r AS (SELECT *, total - coalesce(sum(cap) OVER o, 0) AS left_size, sum(weight) OVER () - coalesce(sum(weight) OVER o, 0) AS left_weight
      FROM q WINDOW o AS (ORDER BY cap * (10 // weight), turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
h AS (SELECT *, cap * left_weight <= weight * left_size AS held FROM r),
g AS (SELECT *, total - coalesce(sum(cap) FILTER (held) OVER (), 0) AS rest, sum(weight) FILTER (NOT held) OVER () AS rest_weight FROM h),
b AS (SELECT source, source_size, CASE WHEN held THEN cap::DOUBLE ELSE (weight * rest)::DOUBLE / rest_weight::DOUBLE END AS target,
             CASE WHEN held THEN cap ELSE (weight * rest) // rest_weight END AS budget FROM g),
p AS (SELECT d.doc_id, size, source_size, target, CASE WHEN source_size > 0 THEN budget // source_size ELSE 0 END AS epochs, budget,
             coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
      FROM d JOIN b ON d.source IS NOT DISTINCT FROM b.source)
SELECT doc_id, size, source_size, target,
       (epochs * size + least(greatest(budget - epochs * source_size - before, 0), size))::BIGINT AS taken FROM p""",
    "op8_token_counts": f"""
WITH d AS (SELECT source, lang, len({_WORDS})::BIGINT AS words, strlen(trim(text, ' '))::BIGINT AS bare FROM documents),
t AS (SELECT source, lang, 'words_v1' AS tokenizer, words AS tokens FROM d WHERE words >= 10
      UNION ALL SELECT source, lang, 'bytes_v1', bare FROM d WHERE words >= 10)
SELECT source, lang, tokenizer, count(*)::BIGINT AS docs, sum(tokens)::BIGINT AS tokens FROM t GROUP BY ALL""",
    "op9_exact_top_k": """
WITH z AS (SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)::BIGINT) AS z FROM embeddings WHERE embedding IS NOT NULL),
s AS (SELECT q.vec_id AS query_id, v.vec_id, list_sum(list_transform(list_zip(q.z, v.z), lambda p: p[1] * p[2]))::BIGINT AS score
      FROM z q JOIN z v ON q.vec_id % 20 = 0 AND q.vec_id <> v.vec_id),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20""",
}
