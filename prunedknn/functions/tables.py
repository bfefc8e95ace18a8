"""An aggregate over vectors and a table function for SQL."""

from __future__ import annotations

import heapq

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def vector_mean(vector: Column, dim: int) -> Column:
    """The mean vector of a group: an average a part, with partial sums before any shuffle."""
    wide = vector.cast("array<double>")
    return F.array(*[F.avg(F.get(wide, F.lit(i))) for i in range(dim)])


@F.udtf(returnType="id bigint, dist double")
class KnnTopK:
    """knn_topk(TABLE(SELECT id, vector ...), array(...), k): each partition's k nearest; a LIMIT over an
    ORDER BY of the result makes them the table's."""

    def __init__(self):
        self.heap, self.k = [], 0

    def eval(self, row, q, k):
        self.k = k
        if row[1] is None:
            return
        d = float(np.sqrt(((np.asarray(row[1], dtype=np.float64) - np.asarray(q, dtype=np.float64)) ** 2).sum()))
        item = (-d, -row[0])
        if len(self.heap) < k:
            heapq.heappush(self.heap, item)
        elif k and item > self.heap[0]:
            heapq.heapreplace(self.heap, item)

    def terminate(self):
        for d, i in sorted(self.heap, reverse=True):
            yield -i, -d


def register(spark) -> None:
    spark.udtf.register("knn_topk", KnnTopK)
