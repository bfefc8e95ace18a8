"""Limits of perplexity stand at one distance from the quantiles, however many texts were held out."""

import random

import pytest
from pyspark.sql import functions as F

from prunedknn.llm import kneser_ney


def test_slack_does_not_hang_on_the_number_of_texts(spark):
    rng = random.Random(9)
    say = lambda: " ".join("".join(rng.choice("abcde") for _ in range(rng.randint(1, 6))) for _ in range(30))
    docs = spark.createDataFrame([(i, say(), "few" if i < 220 else "many") for i in range(900)], "doc_id long, text string, lang string")
    fold = F.pmod(F.xxhash64(F.lit("fold"), F.col("doc_id")), F.lit(kneser_ney.FOLDS)) == 0
    labels = docs.select("doc_id", F.lit(1).alias("quality"))
    rows = kneser_ney.judged(docs, labels, low=0.0, high=1.0).withColumn("held", fold).collect()
    for lang in ("few", "many"):
        held = [r["perplexity"] for r in rows if r["held"] and r["lang"] == lang]
        assert len(held) >= kneser_ney.LEAST_HELD
        limits = next((r["low_limit"], r["high_limit"]) for r in rows if r["lang"] == lang)
        assert limits == pytest.approx((min(held) / kneser_ney.SLACK, max(held) * kneser_ney.SLACK))
