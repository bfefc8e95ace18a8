"""Documents made ready for training: five stages, each of which works on all that the one before kept.

Each stage takes (spark, docs, sf_dir); run() writes its result as Parquet in the shared
folder and reads it again as the next one's docs. All but the last return the columns of
documents, and any other column that docs has, whatever its name.

Edge cases of every stage: null, empty and wordless texts are kept (they are neither toxic nor
of odd perplexity, nor copies of each other) and have no ids; a null or repeated doc_id is a row
like any other; a text of any length is one row, whole; an empty table gives no rows.
"""

from __future__ import annotations

import functools
import weakref

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prunedknn.llm import bpe_words, fm_decontam, kneser_ney, minhash_bbit, toxicity_nb
from prunedknn.llm._shared import fresh, noting, release, table, written
from prunedknn.llm.registry import VOCABULARY

#: Scratch tables that stages left, each list with the result that reads them.
_LEFT: list[tuple[weakref.ref, list[str]]] = []


def _stage(function):
    """Note the scratch tables of a stage. When a later one begins, those go whose result nobody holds any more
    and which its docs don't read; the rest go with the application."""

    @functools.wraps(function)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        idle = [left for left in _LEFT if left[0]() is None]
        read = docs.inputFiles() if idle else []
        for left in idle:
            if not any(path.rsplit("/", 1)[1] in file for path in left[1] for file in read):
                _LEFT.remove(left)
                release(spark, left[1])
        paths: list[str] = []
        with noting(paths):
            out = function(spark, docs, sf_dir)
        if paths:
            _LEFT.append((weakref.ref(out), paths))
        return out

    return run_stage


@_stage
def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier calls toxic go."""
    model = toxicity_nb.fit(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "labels"))
    name = fresh("toxic", docs.columns)
    return toxicity_nb.score(docs, model, out_col=name).where(F.col(name) < toxicity_nb.THRESHOLD).select(*docs.columns)


@_stage
def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose perplexity lies outside of their language's limits go."""
    prefix = "quality_"
    while any(c.lower().startswith(prefix) for c in docs.columns):
        prefix = "_" + prefix
    out = kneser_ney.judged(docs, table(spark, sf_dir, "labels"), prefix=prefix)
    return out.where(F.col(f"{prefix}kept")).select(*docs.columns)


@_stage
def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group at similarity 0.8 over 5-word shingles stays: the one of smallest id.

    Of rows that share the smallest id one stays, as of a group whose ids are all null; a row
    outside of a group stays whatever its id, and so do null, empty and wordless texts.
    """
    return minhash_bbit.without_duplicates(docs, width=5, percent=80)


@_stage
def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of benchmark items are cut out of the texts; n_chars follows."""
    rest = tuple(c for c in docs.columns if c not in ("doc_id", "text"))
    names = tuple(fresh(n, docs.columns) for n in fm_decontam.RESULTS)
    out = fm_decontam.contaminated(docs, table(spark, sf_dir, "benchmark"), extra=rest, clean=True, names=names)
    changed = F.size(names[1]) > 0
    if "n_chars" in docs.columns:
        kind = docs.schema["n_chars"].dataType
        out = out.withColumn("n_chars", F.when(changed, F.char_length("text").cast(kind)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


@_stage
def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text that is left, and digests of them and of what they decode to."""
    out = bpe_words.encode_decode(docs, public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN)
    return out.select(
        "doc_id",
        (F.octet_length("token_ids") / 4).cast("long").alias("n_tokens"),
        F.sha2("token_ids", 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )


STAGES = [
    ("toxicity", toxicity),
    ("quality", quality),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("encoding", encoding),
]
#: SQL can't express the trained stages; tests/llm holds the pipeline against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
