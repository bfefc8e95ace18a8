"""What the per-file method is compared with: exact scans, post-filtering, whole-table indexes."""

from __future__ import annotations

import heapq
import time
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .. import ivf
from ..functions.vectors import l2_distance, l2_distance_arrow, literal
from ..manifest import Table
from ..storage import written
from . import search


def brute(df: DataFrame, column: str, q: Sequence[float], k: int, where: str | None = None, keep: Sequence[str] = ("vec_id",), arrow: bool = False) -> DataFrame:
    """Every row's distance, then a top-k; truth for all else. arrow: by the Arrow UDF."""
    df = df.where(where) if where else df
    df = df.where(F.col(column).isNotNull())
    d = l2_distance_arrow(q)(F.col(column)) if arrow else l2_distance(F.col(column), literal(q))
    return df.select(*keep, d.alias("dist")).orderBy("dist", *keep).limit(k)


def brute_batch(df: DataFrame, column: str, queries: DataFrame, k: int, id_col: str) -> DataFrame:
    """(query_id, rank, id, dist) for a block of queries (query_id, qvec) sent to every task; each keeps
    its own k best, so a window sees k rows a query and task."""
    from pyspark.sql.types import LongType, StructField, StructType, DoubleType

    rows = queries.select("query_id", "qvec").orderBy("query_id").collect()
    sent = df.sparkSession.sparkContext.broadcast(([r[0] for r in rows], [np.asarray(r[1], dtype=np.float64) for r in rows]))
    schema = pa.schema([("query_id", pa.int64()), ("id", pa.int64()), ("dist", pa.float64())])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = sent.value
        for batch in batches:
            own = batch.column(0).to_numpy()
            x = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            out: tuple[list, list, list] = ([], [], [])
            for i, v in zip(ids, q, strict=True):
                d = ivf.distances(x, v)
                top = np.lexsort((own, d))[:k]
                for c, values in zip(out, (np.full(len(top), i), own[top], d[top]), strict=True):
                    c.append(values)
            if ids:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in out], schema=schema)

    narrow = df.where(F.col(column).isNotNull()).select(F.col(id_col).cast("long"), F.col(column).cast("array<double>"))
    found = narrow.mapInArrow(scan, StructType([StructField("query_id", LongType()), StructField("id", LongType()), StructField("dist", DoubleType())]))
    order = Window.partitionBy("query_id").orderBy("dist", "id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "id", "dist")


def postfilter(table: Table, q: Sequence[float], k: int, where: str, overfetch: int = 4, **options) -> DataFrame:
    """Search without the filter, then drop what does not satisfy it; may return fewer than k rows."""
    names = [c for c in table.schema().names if c != table.spec().column]
    found = search.knn(table, q, k * overfetch, None, names, **options)
    return found.rows.where(where).limit(k)


CLUSTER_PARTS = 4


@dataclass
class GlobalIvf:
    """One index over the whole table: rows dealt by cluster, with codes where PQ is on."""

    centroids: np.ndarray
    codebook: np.ndarray | None
    postings: DataFrame
    seconds: float

    def search(self, q: Sequence[float], k: int, nprobe: int = 8, rerank: int = 0) -> DataFrame:
        """Clusters nearest to q; distances from looked-up tables (PQ) or exact. rerank: so many of the
        best coded rows are ranked exactly."""
        q = np.asarray(q, dtype=np.float64)
        gaps = ((self.centroids - q) ** 2).sum(axis=1)
        lists = [int(i) for i in np.argsort(gaps, kind="stable")[:nprobe]]
        rows = self.postings.where(F.col("cluster").isin(lists))
        if self.codebook is None:
            return rows.select("id", l2_distance(F.col("vector"), literal(q)).alias("dist")).orderBy("dist", "id").limit(k)
        m, _, width = self.codebook.shape
        tables = {c: ((self.codebook - (q - self.centroids[c]).reshape(m, 1, width)) ** 2).sum(axis=2) for c in lists}
        sent = self.postings.sparkSession.sparkContext.broadcast(tables)
        schema = pa.schema([("id", pa.int64()), ("dist", pa.float64()), ("vector", pa.list_(pa.float32()))])

        def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                clusters = batch.column(0).to_numpy()
                codes = np.frombuffer(b"".join(batch.column(2).to_pylist()), dtype=np.uint8).reshape(batch.num_rows, m)
                d = np.zeros(batch.num_rows)
                for c in np.unique(clusters):
                    own = clusters == c
                    d[own] = sent.value[int(c)][np.arange(m), codes[own]].sum(axis=1)
                yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(np.sqrt(d)), batch.column(3).cast(schema.field(2).type)], schema=schema)

        near = rows.select("cluster", "id", "code", "vector").mapInArrow(scan, "id long, dist double, vector array<float>")
        if rerank:
            near = near.orderBy("dist", "id").limit(rerank).select("id", l2_distance(F.col("vector"), literal(q)).alias("dist"))
        return near.select("id", "dist").orderBy("dist", "id").limit(k)


def build_global(
    df: DataFrame, column: str, id_col: str, n_c: int, pq: int | None = None, algo: str = "lloyd", sample: int = 100_000, iters: int = 8, seed: int = 5
) -> GlobalIvf:
    """Whole-table IVF, flat or with product codes of pq parts. Centroids and codes are trained on at most
    `sample` rows of smallest hashed id on the driver; every row is assigned in one pass and dealt by
    cluster. algo="seed" takes the rows of smallest id as centroids."""
    began, spark = time.time(), df.sparkSession
    rows = df.where(F.col(column).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.col(column).cast("array<float>").alias("vector"))
    order = ["id"] if algo == "seed" else [F.xxhash64("id"), "id"]
    x = np.asarray([r["vector"] for r in rows.orderBy(*order).limit(n_c if algo == "seed" else sample).collect()], dtype=np.float32)
    n_c = min(n_c, len(x))
    centroids = ivf.train(x, n_c, algo, seed, iters).astype(np.float64)
    codebook = None
    if pq:
        residual = x - centroids[ivf.assign(x, centroids)]
        parts = residual.reshape(len(x), pq, -1)
        codebook = np.stack([_codes(parts[:, m], min(256, len(x)), iters, seed) for m in range(pq)])
    sent = spark.sparkContext.broadcast((centroids, codebook))
    schema = pa.schema([("cluster", pa.int32()), ("id", pa.int64()), ("code", pa.binary()), ("vector", pa.list_(pa.float32()))])

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cents, book = sent.value
        for batch in batches:
            v = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1).astype(np.float64)
            own = ivf.assign(v, cents, 1024)
            codes = [b""] * len(v)
            if book is not None:
                parts = (v - cents[own]).reshape(len(v), book.shape[0], -1)
                found = np.stack([ivf.assign(parts[:, m], book[m]) for m in range(book.shape[0])], axis=1).astype(np.uint8)
                codes = [c.tobytes() for c in found]
            yield pa.RecordBatch.from_arrays(
                [pa.array(own.astype(np.int32)), batch.column(0), pa.array(codes, type=pa.binary()), batch.column(1).cast(schema.field(3).type)], schema=schema
            )

    dealt = rows.mapInArrow(deal, "cluster int, id long, code binary, vector array<float>")
    # a folder a cluster, so that a search reads only the lists it probes; a big one is several tasks and files
    dealt = dealt.repartition("cluster", F.pmod(F.xxhash64("id"), F.lit(CLUSTER_PARTS)))
    return GlobalIvf(centroids, codebook, written(dealt, "global-ivf", by="cluster"), time.time() - began)


def _codes(x: np.ndarray, c: int, iters: int, seed: int) -> np.ndarray:
    rng = np.random.default_rng(seed)
    found = ivf.train(x[rng.permutation(len(x))].astype(np.float32), c, "lloyd", seed, iters)
    return np.pad(found, ((0, 256 - len(found)), (0, 0)), constant_values=1e6).astype(np.float64)


class Hnsw:
    """A layered neighbour graph in one process, with filters checked during the walk: the stand-in for a
    separate in-memory service. For the small subsets that such a service is given."""

    LIMIT = 300_000

    def __init__(self, x: np.ndarray, m: int = 16, ef_build: int = 64, seed: int = 9):
        if len(x) > self.LIMIT:
            raise ValueError(f"{len(x)} rows; the graph is kept to {self.LIMIT}")
        self.x, self.m, self.ef_build = x.astype(np.float64), m, ef_build
        rng = np.random.default_rng(seed)
        levels = np.minimum((-np.log(rng.random(len(x)) + 1e-12) / np.log(m)).astype(int), 12)
        self.graph: list[dict[int, list[int]]] = []
        self.entry, self.top = None, -1
        for i, level in enumerate(levels.tolist()):
            self._insert(i, level)

    def _far(self, ids: list[int], q: np.ndarray) -> np.ndarray:
        return ((self.x[ids] - q) ** 2).sum(axis=1)

    def _walk(self, q: np.ndarray, entry: list[int], ef: int, level: int) -> list[tuple[float, int]]:
        seen, start = set(entry), self._far(entry, q).tolist()
        open_, best = [(d, i) for d, i in zip(start, entry, strict=True)], [(-d, i) for d, i in zip(start, entry, strict=True)]
        heapq.heapify(open_)
        heapq.heapify(best)
        while open_:
            d, i = heapq.heappop(open_)
            if d > -best[0][0] and len(best) >= ef:
                break
            fresh = [j for j in self.graph[level].get(i, ()) if j not in seen]
            if not fresh:
                continue
            seen.update(fresh)
            for dj, j in zip(self._far(fresh, q).tolist(), fresh, strict=True):
                if len(best) < ef or dj < -best[0][0]:
                    heapq.heappush(open_, (dj, j))
                    heapq.heappush(best, (-dj, j))
                    if len(best) > ef:
                        heapq.heappop(best)
        return sorted((-d, i) for d, i in best)

    def _insert(self, i: int, level: int) -> None:
        while len(self.graph) <= level:
            self.graph.append({})
        if self.entry is None:
            for g in range(level + 1):
                self.graph[g][i] = []
            self.entry, self.top = i, level
            return
        near = [self.entry]
        for g in range(self.top, level, -1):
            near = [self._walk(self.x[i], near, 1, g)[0][1]]
        for g in range(min(level, self.top), -1, -1):
            found = self._walk(self.x[i], near, self.ef_build, g)
            limit = self.m * 2 if g == 0 else self.m
            self.graph[g][i] = [j for _, j in found[: self.m]]
            for _, j in found[: self.m]:
                links = [*self.graph[g][j], i]
                if len(links) > limit:
                    far = self._far(links, self.x[j])
                    links = [links[t] for t in np.argsort(far, kind="stable")[:limit]]
                self.graph[g][j] = links
            near = [j for _, j in found]
        for g in range(self.top + 1, level + 1):
            self.graph[g][i] = []
        if level > self.top:
            self.entry, self.top = i, level

    def search(self, q: Sequence[float], k: int, ef: int = 64, keep: np.ndarray | None = None) -> list[tuple[float, int]]:
        """(distance, row) of the nearest rows; keep: which rows may be returned (all are walked)."""
        if self.entry is None:
            return []
        q = np.asarray(q, dtype=np.float64)
        near = [self.entry]
        for g in range(self.top, 0, -1):
            near = [self._walk(q, near, 1, g)[0][1]]
        wide = ef if keep is None else round(ef / max(float(keep.mean()), 1e-3))  # as many kept rows as without a filter
        while True:
            found = [(d, i) for d, i in self._walk(q, near, max(wide, k), 0) if keep is None or keep[i]]
            if len(found) >= k or wide >= len(self.x):
                return [(float(np.sqrt(d)), i) for d, i in found[:k]]
            wide *= 2
