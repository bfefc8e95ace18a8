"""The pipeline keeps one row of a group, whatever the rows' ids."""

from collections import Counter

import corpus_pipeline as P
from prunedknn.llm._shared import written


def test_one_row_of_each_group_stays(spark):
    copy, near, other = (" ".join(f"{w}{i}" for i in range(80)) for w in "abc")
    rows = [
        (1, copy), (1, copy), (1, copy),  # one id for all copies
        (None, near), (None, near), (None, near + " tail"),  # no id at all
        (5, other), (6, other), (6, "a text like no other in this table"),  # 6 stands for two texts
        (7, None), (7, None), (None, ""),
    ]
    docs = written(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), "test-rows")
    left = [(r["doc_id"], r["text"]) for r in P.near_duplicates(spark, docs, "test").collect()]
    families = Counter((d, (t or "")[:2]) for d, t in left)
    assert families == {(1, "a0"): 1, (None, "b0"): 1, (5, "c0"): 1, (6, "a "): 1, (7, ""): 2, (None, ""): 1}
