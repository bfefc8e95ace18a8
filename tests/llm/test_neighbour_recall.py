"""The registered search over whole tables against brute force."""

from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from prunedknn.llm import registry

FOLDERS = ("sf0.001", "sf0.1")


@pytest.mark.parametrize("folder", FOLDERS)
def test_recall_over_the_whole_table(spark, sf, folder):
    sf_dir = str(Path(sf).parent / folder)
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", F.col("embedding").cast("array<double>")).collect()
    ids, x = np.asarray([r[0] for r in rows]), np.asarray([r[1] for r in rows])
    place = {int(i): n for n, i in enumerate(ids)}
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    found: dict[int, list] = {}
    for r in registry.queries()["op8_aniso_index"](spark, sf_dir).collect():
        found.setdefault(r["query_id"], []).append(r)
    asked = [int(i) for i in ids if i % 50 == 0]
    assert sorted(found) == sorted(asked)
    hits = 0
    for q in asked:
        own = sorted(found[q], key=lambda r: r["rank"])
        assert [r["rank"] for r in own] == [1, 2, 3, 4, 5]
        cosine = unit @ unit[place[q]]
        truth = [int(ids[i]) for i in np.lexsort((ids, -cosine)) if ids[i] != q][:5]
        hits += len(set(truth) & {r["vec_id"] for r in own})
        for r in own:
            assert abs(r["score"] - cosine[place[r["vec_id"]]]) < 1e-12
        assert [(-r["score"], r["vec_id"]) for r in own] == sorted((-r["score"], r["vec_id"]) for r in own)
    assert hits >= 0.9 * 5 * len(asked)
