"""What near duplicates sends over the network: texts once a block, bands once, signatures not at all."""

import random

from prunedknn.llm import minhash_bbit
from tests.llm.test_operators import plain_components


def family(n):
    rng = random.Random(5)
    base = [f"w{rng.randint(0, 999)}" for _ in range(100)]
    rows = []
    for i in range(n):
        own = list(base)
        for _ in range(rng.choice([0, 2, 5, 9, 14])):
            own[rng.randrange(len(own))] = f"e{rng.randint(0, 10**9)}"
        rows.append((i, " ".join(own)))
    return rows


def test_texts_in_many_passes_and_one_shuffle_each(spark, monkeypatch):
    monkeypatch.setattr(minhash_bbit, "PLACES", 9)  # a row's places come in several passes
    monkeypatch.setattr(minhash_bbit, "BLOCK", 7)
    plans = {}
    written = minhash_bbit.written

    def noted(df, tag):
        plans[tag] = df._jdf.queryExecution().optimizedPlan().toString()
        return written(df, tag)

    monkeypatch.setattr(minhash_bbit, "written", noted)
    rows = family(60)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((str(r["doc_id"]), r["n_shingles"], str(r["component_id"])) for r in minhash_bbit.near_duplicates(df, 2, 80).collect())
    assert got == plain_components(rows, 2, 80)
    for tag in ("minhash-members", "minhash-stars", "minhash-cross"):
        joins = [line for line in plans[tag].splitlines() if "Join " in line]
        assert all("broadcast" in line for line in joins), tag
    assert "Aggregate" not in plans["minhash-members"]
