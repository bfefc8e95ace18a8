"""Approximate nearest neighbours by score-aware anisotropic quantisation.

Vectors are scaled to length one and split into pairs of dimensions; each pair gets one of
16 centres, so a code is four bits a pair. Codes and centres minimise a loss in which the
part of the error along the vector weighs more than the part across it, since that part
moves the inner products that are looked for. Codes are chosen by coordinate descent and
centres by the closed weighted least-squares solution, on at most SAMPLE rows of smallest
hashed id; every row is then coded.

A search scans the codes of a partition with per-query tables of 16 partial products a pair,
keeps RERANK rows a query and all that tie with the last of them, ranks those by exact cosine
in double precision and passes on the k best; partial results meet per query. Of equal vectors
in a block only the smallest ids are scanned, as many as a result can hold. Queries go out in blocks of at most QUERY_BLOCK.

Edge cases: vectors that are null, zero, or hold null or non-finite parts, or differ in
length from most, take no part; ties go to the smaller id; with fewer candidates than k all
are returned; a table too small to train on is ranked exactly; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ._shared import written

SAMPLE = 8192
CENTRES = 16
THRESHOLD = 0.2
SWEEPS, ROUNDS = 2, 6
RERANK = 128
QUERY_BLOCK = 20_000
CHUNK = 128


def usable(vector: Column) -> Column:
    """Neither null nor zero, and every part a finite number."""
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return vector.isNotNull() & fine & F.exists(vector, lambda x: x != 0)


class Codebook:
    """centres: (parts, 16, width); weight: of parallel against other error."""

    def __init__(self, dim: int, seed: int = 3):
        self.dim, self.width = dim, 2 if dim % 2 == 0 else 1
        self.parts = dim // self.width
        self.weight = max(1.0, (dim - 1) * THRESHOLD**2 / (1 - THRESHOLD**2))
        self.seed = seed

    def _split(self, x: np.ndarray) -> np.ndarray:
        return x.reshape(len(x), self.parts, self.width)

    def fit(self, x: np.ndarray) -> Codebook:
        rng, split = np.random.default_rng(self.seed), self._split(x)
        at = rng.choice(len(x), CENTRES, replace=len(x) < CENTRES)
        self.centres = split[at].transpose(1, 0, 2).copy()
        codes = None
        for turn in range(ROUNDS):
            codes = self.encode(x, SWEEPS if turn else 0)
            self._solve(x, codes)
        return self

    def _solve(self, x: np.ndarray, codes: np.ndarray) -> None:
        """All centres at once: the loss is quadratic in them when the codes are given."""
        n, size = len(x), self.parts * CENTRES * self.width
        normal, right = np.zeros((size, size)), np.zeros(size)
        base = (np.arange(self.parts) * CENTRES + codes) * self.width
        split = self._split(x)
        for i in range(0, n, 1024):
            block = slice(i, min(n, i + 1024))
            rows = np.zeros((block.stop - i, size))
            for w in range(self.width):
                np.put_along_axis(rows, base[block] + w, split[block, :, w], axis=1)
            normal += (self.weight - 1) * (rows.T @ rows)
            right += (self.weight - 1) * rows.sum(axis=0)  # vectors have length one
        for w in range(self.width):
            flat = (base + w).ravel()
            np.add.at(normal, (flat, flat), 1.0)
            np.add.at(right, flat, split[:, :, w].ravel())
        normal[np.diag_indices(size)] += 1e-6
        self.centres = np.linalg.solve(normal, right).reshape(self.parts, CENTRES, self.width)

    def encode(self, x: np.ndarray, sweeps: int = SWEEPS) -> np.ndarray:
        """The code of each part, by turns: whichever centre makes the whole loss least, the others given."""
        split = self._split(x)
        away = split[:, :, None, :] - self.centres[None]
        across = (away**2).sum(axis=3)
        along = (away * split[:, :, None, :]).sum(axis=3)
        codes = across.argmin(axis=2)
        rows, parts = np.arange(len(x))[:, None], np.arange(self.parts)[None]
        total = along[rows, parts, codes].sum(axis=1)
        for _ in range(sweeps):
            for m in range(self.parts):
                rest = total - along[rows[:, 0], m, codes[:, m]]
                loss = across[:, m] + (self.weight - 1) * (rest[:, None] + along[:, m]) ** 2
                codes[:, m] = loss.argmin(axis=1)
                total = rest + along[rows[:, 0], m, codes[:, m]]
        return codes.astype(np.uint8)

    def pack(self, codes: np.ndarray) -> np.ndarray:
        if codes.shape[1] % 2:
            codes = np.pad(codes, ((0, 0), (0, 1)))
        return codes[:, ::2] | (codes[:, 1::2] << 4)

    def scores(self, packed: np.ndarray, queries: np.ndarray) -> np.ndarray:
        """(queries, rows): sums of looked-up partial products; two four-bit look-ups share a byte."""
        tables = np.einsum("qmw,mcw->qmc", self._split(queries), self.centres).astype(np.float32)
        if self.parts % 2:
            tables = np.pad(tables, ((0, 0), (0, 1), (0, 0)))
        both = tables[:, ::2, None, :] + tables[:, 1::2, :, None]
        both = np.ascontiguousarray(both.reshape(len(queries), -1, 256).transpose(1, 2, 0))
        out = np.zeros((len(packed), len(queries)), np.float32)
        for m in range(packed.shape[1]):
            out += both[m][packed[:, m]]
        return out


def exact(vectors: np.ndarray, query: np.ndarray) -> np.ndarray:
    """Cosines in double precision, of the vectors as they are."""
    norms = np.sqrt((vectors * vectors).sum(axis=1)) * np.sqrt((query * query).sum())
    return (vectors * query).sum(axis=1) / norms


def first_copies(ids: np.ndarray, x: np.ndarray, k: int) -> np.ndarray:
    """Positions of the rows that can be among the k nearest of some query: of equal vectors, k rows of
    each of the k + 1 smallest ids, as a query leaves out one id, its own."""
    parts = np.ascontiguousarray(x + 0.0)  # one zero, whatever its sign
    _, group = np.unique(parts.view(np.dtype((np.void, parts.strides[0]))).ravel(), return_inverse=True)
    order = np.lexsort((ids, group))
    group, own = group[order], ids[order]
    rows = np.arange(len(own))
    new_group = np.append(True, group[1:] != group[:-1])
    new_id = new_group | np.append(True, own[1:] != own[:-1])
    copy = rows - np.maximum.accumulate(np.where(new_id, rows, 0))
    numbered = np.cumsum(new_id)
    nth_id = numbered - np.maximum.accumulate(np.where(new_group, numbered, 0))
    return np.sort(order[(copy < k) & (nth_id <= k)])


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _coder(book):
    schema = pa.schema([("id", pa.int64()), ("code", pa.binary()), ("vector", pa.list_(pa.float64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: Codebook = book.value
        for batch in batches:
            for i in range(0, batch.num_rows, 2048):
                part = batch.slice(i, 2048)
                x = part.column(1).flatten().to_numpy(zero_copy_only=False).reshape(part.num_rows, own.dim)
                packed = own.pack(own.encode(_unit(x)))
                codes = pa.array([row.tobytes() for row in packed], type=pa.binary())
                yield pa.RecordBatch.from_arrays([part.column(0), codes, part.column(1).cast(schema.field(2).type)], schema=schema)

    return run


def index(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> tuple[DataFrame, Codebook | None]:
    """Every usable row with its code, as a written table (id, code, vector), and the codebook."""
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("vector"))
    rows = rows.where(usable(F.col("vector")) & F.col("id").isNotNull())
    common = rows.groupBy(F.size("vector").alias("d")).count().orderBy(F.desc("count"), "d").first()
    if common is None:
        return rows.select("id", F.lit(b"").alias("code"), "vector"), None
    dim = common["d"]
    rows = rows.where(F.size("vector") == dim)
    sample = rows.orderBy(F.xxhash64("id"), "id").limit(SAMPLE).collect()
    book = Codebook(dim).fit(_unit(np.asarray([r["vector"] for r in sample], dtype=np.float64)))
    sent = vectors.sparkSession.sparkContext.broadcast(book)
    return written(rows.mapInArrow(_coder(sent), "id long, code binary, vector array<double>"), "aniso-index"), book


def _scanner(book, queries, k: int, rerank: int):
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])

    def best(ids: np.ndarray, packed: np.ndarray, x: np.ndarray, own: Codebook, query_ids, q) -> Iterator[pa.RecordBatch]:
        units = _unit(q)
        for i in range(0, len(q), CHUNK):
            rough = own.scores(packed, units[i : i + CHUNK])
            kept: tuple[list, list, list] = ([], [], [])
            for j in range(rough.shape[1]):
                near = np.arange(len(ids))
                if rerank < len(ids):
                    # all that equal the last one kept: equal codes have equal rough scores
                    near = np.flatnonzero(rough[:, j] >= np.partition(rough[:, j], len(ids) - rerank)[len(ids) - rerank])
                near = near[ids[near] != query_ids[i + j]]
                score = exact(x[near], q[i + j])
                top = np.lexsort((ids[near], -score))[:k]
                kept[0].append(np.full(len(top), query_ids[i + j]))
                kept[1].append(ids[near][top])
                kept[2].append(score[top])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), type=f.type) for c, f in zip(kept, schema, strict=True)], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, (query_ids, q) = book.value, queries.value
        held, size = [], 0

        def flush() -> Iterator[pa.RecordBatch]:
            table = pa.Table.from_batches(held).combine_chunks()
            ids = table.column("id").to_numpy()
            x = table.column("vector").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), own.dim)
            packed = np.frombuffer(b"".join(table.column("code").to_pylist()), dtype=np.uint8).reshape(len(ids), -1)
            few = first_copies(ids, x, k)
            ids, packed, x = ids[few], packed[few], x[few]
            yield from best(ids, packed, x, own, query_ids, q)

        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size >= 32_768:
                yield from flush()
                held, size = [], 0
        if size:
            yield from flush()

    return run


def nearest(indexed: DataFrame, book: Codebook | None, queries: DataFrame, k: int = 5, rerank: int = RERANK) -> DataFrame:
    """(query_id, rank, vec_id, score): the k rows of largest cosine found for each query (id, vector),
    without the row of the query's own id."""
    spark = indexed.sparkSession
    empty = "query_id long, rank int, vec_id long, score double"
    if book is None:
        return spark.createDataFrame([], empty)
    sent = spark.sparkContext.broadcast(book)
    queries = queries.select("id", "vector")
    blocks = int(queries.count() // QUERY_BLOCK) + 1
    found = None
    for block in range(blocks):
        own = queries.where(F.pmod(F.xxhash64("id"), F.lit(blocks)) == block) if blocks > 1 else queries
        rows = own.orderBy("id").collect()  # a block of QUERY_BLOCK rows, give or take
        if not rows:
            continue
        q = spark.sparkContext.broadcast(
            (np.asarray([r["id"] for r in rows]), np.asarray([r["vector"] for r in rows], dtype=np.float64).reshape(len(rows), -1))
        )
        part = indexed.select("id", "code", "vector").mapInArrow(_scanner(sent, q, k, rerank), "query_id long, vec_id long, score double")
        found = part if found is None else found.unionByName(part)
    if found is None:
        return spark.createDataFrame([], empty)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
