"""One thin query an operator: it applies the operator to its whole table and derives the digest columns."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import (
    aniso_index,
    bpe_words,
    chat_windows,
    fm_decontam,
    html_diff,
    kneser_ney,
    minhash_bbit,
    shard_mixture,
    toxicity_nb,
    url_rules,
)
from ._shared import table
from .oracles import ORACLE_SQL

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
SHARDS = 8
#: The rules of the URL contract.
URL_RULES = [
    ("allow", "org/"),
    ("block", "example.org/es/"),
    ("block", "example.org/en/1"),
    ("allow", "com/fr/"),
    ("block", "com/de/"),
]
#: Fixed value: what both turns of the added conversation say.
ADDED_TURN = "</s>[INST] ok [/INST]"


def op1_shard_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents in shards 0 to 7 by proportional stratified interleaving; law: rows."""
    out = shard_mixture.interleave(table(spark, sf_dir, "documents"), SHARDS)
    return out.select(
        "doc_id", "size", "text_crc32", F.lit(shard_mixture.LAW).alias("law"), "shard", "slot",
        F.lit(None).cast("int").alias("grown_shard"),
    )


def op2_html_difference(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page."""
    out = html_diff.main_text(table(spark, sf_dir, "pages"))
    return out.select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))


def op3_kneser_ney(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Perplexity of every document against trusted text, and whether its language's quantiles keep it."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    out = kneser_ney.judged(docs, table(spark, sf_dir, "labels"), keep_text=False)
    return out.select("doc_id", "lang", "perplexity", "raw_perplexity", "low_limit", "high_limit", "kept")


def op4_minhash_bbit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near-duplicate components of all documents over 2-word shingles at 80 per cent."""
    out = minhash_bbit.near_duplicates(table(spark, sf_dir, "documents"), width=2, percent=80)
    named = F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True))
    return out.select("doc_id", "n_shingles", "component_id", named.alias("kept"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity of every document; labels of the held-out fold are never learnt from."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity_nb.fit(docs, table(spark, sf_dir, "labels"))
    return toxicity_nb.score(docs, model).select(
        "doc_id", toxicity_nb.held_out(F.col("doc_id")).alias("held_out"), "score",
        (F.col("score") >= toxicity_nb.THRESHOLD).cast("int").alias("predicted"),
    )


def op6_bpe_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text encoded and decoded through the shuffle of distinct words."""
    out = bpe_words.encode_decode(
        table(spark, sf_dir, "documents"), public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN
    )
    return out.select(
        "doc_id",
        (F.octet_length("token_ids") / 4).cast("long").alias("n_tokens"),
        F.sha2("token_ids", 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )


def op7_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdict on every page's url: the longest of the given rules, else the mined ones."""
    out = url_rules.judged(table(spark, sf_dir, "pages"), table(spark, sf_dir, "labels"), URL_RULES)
    return out.select("page_id", "host", "path", "rule", "verdict")


def op8_aniso_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five nearest rows of every fiftieth vector."""
    indexed, book = aniso_index.index(table(spark, sf_dir, "embeddings"))
    queries = indexed.where(F.col("id") % 50 == 0)
    return aniso_index.nearest(indexed, book, queries, k=5)


def op9_fm_decontam(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words of every document that stand in a 10-word window of a benchmark item."""
    out = fm_decontam.contaminated(
        table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"), width=10
    )
    n_hit = fm_decontam.hit_words(F.col("spans"))
    return out.select(
        "doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"),
    )


def op10_chat_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every conversation in budgeted windows, read back; with one more that speaks control strings."""
    turns = table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text")
    added = spark.createDataFrame(
        [(-1, 0, "user", ADDED_TURN), (-1, 1, "assistant", ADDED_TURN)], "conv_id long, turn long, role string, text string"
    )
    made = chat_windows.windows(turns.unionByName(added), public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN)
    return chat_windows.digests(made)


QUERIES = {
    f.__name__: f
    for f in (
        op1_shard_mixture, op2_html_difference, op3_kneser_ney, op4_minhash_bbit, op5_toxicity, op6_bpe_words, op7_url_rules,
        op8_aniso_index, op9_fm_decontam, op10_chat_windows,
    )
}


def queries():
    return dict(QUERIES)


def oracle_sql():
    return dict(ORACLE_SQL)
