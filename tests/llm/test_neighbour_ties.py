"""Vectors that tie, exactly or by their codes, against brute force."""

import numpy as np

from prunedknn.llm import aniso_index


def test_many_equal_vectors_give_the_smallest_ids(spark):
    """A third of the rows equal: far more ties than rows are re-ranked."""
    rng = np.random.default_rng(7)
    x = rng.normal(size=(3000, 8))
    same = rng.permutation(3000)[:1000]
    x[same] = x[same[0]]
    order = rng.permutation(3000)
    df = spark.createDataFrame([(int(i), x[i].tolist()) for i in order], "vec_id long, embedding array<double>").coalesce(1)
    indexed, book = aniso_index.index(df)
    asked = sorted(same.tolist())[:3] + [int(same.max())]
    found = aniso_index.nearest(indexed, book, indexed.where(f"id in {tuple(asked)}"), k=5).collect()
    for q in asked:
        got = [r["vec_id"] for r in sorted((r for r in found if r["query_id"] == q), key=lambda r: r["rank"])]
        assert got == [i for i in sorted(same.tolist()) if i != q][:5]


def test_rows_of_one_code_are_all_ranked(spark):
    """Vectors that differ too little for their codes: the nearest are found among all of them."""
    rng = np.random.default_rng(8)
    x = np.concatenate([rng.normal(size=(600, 8)), np.ones((600, 8)) + rng.normal(size=(600, 8)) * 1e-6])
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").coalesce(1)
    indexed, book = aniso_index.index(df)
    asked = [700, 1100]
    found = aniso_index.nearest(indexed, book, indexed.where(f"id in {tuple(asked)}"), k=5).collect()
    for q in asked:
        s = aniso_index.exact(x, x[q])
        got = [r["vec_id"] for r in sorted((r for r in found if r["query_id"] == q), key=lambda r: r["rank"])]
        assert got == [i for i in np.lexsort((np.arange(len(x)), -s)) if i != q][:5]


def test_first_copies_keep_what_a_result_can_hold():
    x, ids = np.array([[0.0, 1.0]] * 6 + [[-0.0, 1.0], [2.0, 2.0]]), np.array([5, 1, 1, 1, 3, 4, 2, 9])
    assert aniso_index.first_copies(ids, x, 2).tolist() == [1, 2, 4, 6, 7]
