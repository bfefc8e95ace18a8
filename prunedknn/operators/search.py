"""Filtered top-k search: prune files, probe and re-score inside the rest, merge, cut.

One task row is a file descriptor. A task reads the vectors and the columns that the filter and
the result need, once, probes the file's index, masks candidates with the filter, ranks them by
exact double-precision distance and returns k * s rows with their projected columns; the driver
side is a TakeOrderedAndProject. Metric rows (ordinal -1) travel with the results.
"""

from __future__ import annotations

import time
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .. import ivf
from ..manifest import Table
from ..plans.pred import TIERS, Pred, parse
from ..plans.prune import PruneReport, plan_survivors, pure_columns, survivors
from ..schema import coerce_query
from ..storage import written
from . import warm as warmth

METRICS = ("candidates", "centroids", "rows_in_file", "fallback", "hits", "load_ms")
QUERIES_PER_TASK = 512


@dataclass
class Options:
    """gate: when the filter is applied inside the search: "rows" (always exact), "pure" (only if
    every column is in the purity set), "none". residual: what a filter that was not pushed does:
    "post" (filter the shortlists), "rescore" (search survivors exhaustively). assemble: "direct"
    (candidates carry their columns), "rescan" (a second read by file and ordinal)."""

    nprobe: int | str = 10
    overfetch: int = 4
    gate: str = "rows"
    residual: str = "post"
    assemble: str = "direct"
    tiers: Sequence[str] = TIERS
    place: str = "hrw"
    slots: int | None = None
    exact: bool = False
    wide: Sequence[str] = ()
    warm: warmth.WarmSet | None = None


@dataclass
class Found:
    """rows: the k nearest. raw: rows and metric rows as they came. The plan says which path ran."""

    rows: DataFrame
    raw: DataFrame | None
    report: PruneReport
    path: str
    reasons: list[str] = field(default_factory=list)

    def metrics(self) -> dict[str, float]:
        if self.raw is None:
            return dict.fromkeys(METRICS, 0.0)
        got = self.raw.where("ord = -1").agg(*[F.sum(F.col("metrics")[i]).alias(m) for i, m in enumerate(METRICS)]).first()
        return {m: float(got[m] or 0.0) for m in METRICS}


def _scan_one(entry: warmth.Entry, q: np.ndarray, p, take: int, pred: Pred | None, push: bool, verdict: str, exact: bool):
    """(ordinals, distances, metrics) of the best `take` rows of a file for one query."""
    x, index = entry.matrix, entry.index
    fallback, centroids = 0, 0
    everything = index is None or exact
    rows = None if everything else index.probe(q, p)
    if everything:
        candidates = np.flatnonzero(np.isfinite(x).all(axis=1)) if len(x) else np.zeros(0, np.int64)
    else:
        candidates, centroids = rows
    if push and verdict != "all":
        keep = entry.mask(pred)
        masked = candidates[keep[candidates]]
        if len(masked) < take and not everything and p != "all":  # too few left: look at the whole file
            whole = np.flatnonzero(keep & np.isfinite(x).all(axis=1))
            fallback, masked = int(len(whole) > len(masked)), whole
        candidates = masked
    if index is not None and index.codes is not None and not exact and p != "all":
        candidates = index.narrow(q, candidates, 4 * take)
    scored = len(candidates)
    d = ivf.distances(x[candidates], q) if scored else np.zeros(0)
    if scored > take:
        near = np.argpartition(d, take - 1)[:take]
        ties = np.flatnonzero(d == d[near].max())  # a tie at the edge must not depend on the partition
        near = np.unique(np.concatenate((near, ties)))
    else:
        near = np.arange(scored)
    order = near[np.lexsort((candidates[near], d[near]))]
    return candidates[order], d[order], [scored, centroids, len(x), fallback, 0, 0]


def _scanner(column: str, dim: int, queries, p, take: int, pred: Pred | None, push: bool, exact: bool, projection: list[str], schema: pa.Schema):
    filters = sorted(pred.columns()) if pred is not None and push else []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = queries.value
        for batch in batches:
            for row in batch.to_pylist():
                began = time.time()
                entry, hit = warmth.load(row, column, dim, [*dict.fromkeys([*filters, *projection])])
                spent = (time.time() - began) * 1000
                for i in range(len(ids)):
                    ordinals, d, metrics = _scan_one(entry, q[i], p, take, pred, push, row["verdict"], exact)
                    metrics[4], metrics[5] = int(hit), spent if i == 0 else 0.0
                    n = len(ordinals)
                    picked = entry.table.select(projection).take(pa.array(ordinals)) if projection else None
                    out = {
                        "query_id": np.full(n + 1, ids[i]), "file": [row["file"]] * (n + 1), "ord": np.append(ordinals, -1),
                        "dist": np.append(d, np.inf), "metrics": [None] * n + [[float(m) for m in metrics]],
                    }
                    arrays = [pa.array(v, type=f.type) for v, f in zip(out.values(), schema, strict=False)]
                    for k, name in enumerate(projection):
                        own = picked.column(name).combine_chunks()
                        own = own if isinstance(own, pa.Array) else pa.concat_arrays(own.chunks)
                        kind = schema.field(5 + k).type
                        arrays.append(pa.concat_arrays([own.cast(kind), pa.nulls(1, type=kind)]))
                    yield pa.RecordBatch.from_arrays(arrays, schema=schema)

    return run


def _raw(table: Table, files: DataFrame, queries: list[tuple[int, list[float]]], k: int, pred: Pred | None, push: bool, projection: list[str], o: Options) -> DataFrame:
    from pyspark.sql.pandas.types import to_arrow_schema

    spec, spark = table.spec(), table.spark
    kinds = table.schema()
    schema = T.StructType(
        [T.StructField("query_id", T.LongType()), T.StructField("file", T.StringType()), T.StructField("ord", T.LongType()),
         T.StructField("dist", T.DoubleType()), T.StructField("metrics", T.ArrayType(T.DoubleType())),
         *(T.StructField(f"c_{c}", kinds[c].dataType) for c in projection)]
    )
    slots = o.slots or spark.sparkContext.defaultParallelism
    placed = warmth.place(files, slots, o.place)
    sent = spark.sparkContext.broadcast((np.asarray([i for i, _ in queries], dtype=np.int64), np.asarray([q for _, q in queries], dtype=np.float64)))
    scan = _scanner(spec.column, spec.dim, sent, o.nprobe, k * o.overfetch, pred, push, o.exact, projection, to_arrow_schema(schema))
    source = o.warm.join(placed, slots) if o.warm is not None else warmth.descriptors(placed, slots)
    return source.mapInArrow(scan, schema)


def _tie_columns(table: Table, tie: str | None) -> str:
    return tie or next((c for c in table.schema().names if c.endswith("id")), "ord")


def knn(
    table: Table, q: Sequence[float], k: int = 10, where: str | Pred | None = None, project: Sequence[str] = (), tie: str | None = None,
    options: Options | None = None, **more,
) -> Found:
    """The k rows nearest to q among those that satisfy where and the table's policy. A filter that the search
    can't evaluate drops rows after it; where that leaves too few, more are looked at, all in the end."""
    found = knn_batch(table, [(0, list(q))], k, where, project, tie, options, **more)
    o = {**(options.__dict__ if options else {}), **more}
    if "predicate_not_pushable" in found.reasons and o.get("residual", "post") == "post" and found.rows.count() < k:
        return escalate(table, q, k, where, project=project, tie=tie, **o)
    return found


def knn_batch(
    table: Table, queries: list[tuple[int, list[float]]], k: int = 10, where: str | Pred | None = None, project: Sequence[str] = (),
    tie: str | None = None, options: Options | None = None, **more,
) -> Found:
    """The same for a block of queries (id, vector) in one pass over the files; at most QUERIES_PER_TASK
    go out together, more make more passes."""
    o = options or Options()
    o = Options(**{**o.__dict__, **more})
    table = table.pinned()
    spec = table.spec()
    queries = [(i, coerce_query(q, spec)) for i, q in queries]
    tie = _tie_columns(table, tie)
    pred = parse(where, table.schema(), table.spark) if isinstance(where, str) else where
    if table.policy:
        policy = parse(table.policy, table.schema(), table.spark)
        pred = policy if pred is None else policy & pred
    files, report = plan_survivors(table, pred, tuple(o.tiers))
    carried = [*dict.fromkeys([*(c for c in (tie,) if c != "ord"), *(c for c in project if c not in o.wide)])]
    reasons: list[str] = []
    if k <= 0 or not queries or report.files_surviving == 0:
        reasons.append("no_survivors" if report.files_surviving == 0 else "nothing_asked")
        return Found(_empty(table, [*carried, *o.wide], len(queries) > 1, project, tie), None, report, "empty", reasons)
    push = pred is not None and pred.pushable()
    if pred is not None and not pred.pushable():
        reasons.append("predicate_not_pushable")
        if len(queries) > 1:
            reasons.append("may_fall_short")
    if push and o.gate == "pure" and not pred.columns() <= pure_columns(table):
        push = False
        reasons.append("not_pure")
    if o.gate == "none":
        push = False
    if pred is not None and not push and o.residual == "rescore":
        o = Options(**{**o.__dict__, "exact": True, "overfetch": 1})
        push = pred.pushable()
        reasons.append("rescored_survivors")
    residual = pred if pred is not None and not push else None
    need = [*dict.fromkeys([*carried, *(sorted(residual.columns()) if residual is not None else ())])]
    inside = need if o.assemble == "direct" else []
    raw = None
    for at in range(0, len(queries), QUERIES_PER_TASK):
        part = _raw(table, files, queries[at : at + QUERIES_PER_TASK], k, pred, push, inside, o)
        raw = part if raw is None else raw.unionByName(part)
    found = raw.where("ord >= 0").drop("metrics")
    if o.assemble == "direct":
        for c in inside:
            found = found.withColumnRenamed(f"c_{c}", c)
    else:  # the contrast: read the candidates' files again
        paths = [r["file"] for r in files.select("file").collect()]
        again = table.spark.read.schema(table.schema()).parquet(*paths).select(
            F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("ord"), *need
        )
        found = again.join(found, ["file", "ord"])
    if residual is not None:
        found = found.where(residual.sql())
    order = [F.col("dist"), *([F.col(tie)] if tie != "ord" else [F.col("file")]), F.col("file"), F.col("ord")]
    if len(queries) == 1:
        top = found.orderBy(*order).limit(k)
    else:
        ranking = Window.partitionBy("query_id").orderBy(*order)
        top = found.withColumn("rank", F.row_number().over(ranking)).where(F.col("rank") <= k)
    if o.wide:
        top = lookup(table, top, list(o.wide))
    names = [*(["query_id", "rank"] if len(queries) > 1 else []), *dict.fromkeys([*([tie] if tie != "ord" else []), *project]), "dist", "file", "ord"]
    rows = top.select(*names)
    if len(queries) == 1:
        rows = rows.orderBy("dist", *([tie] if tie != "ord" else []), "file", "ord")
    return Found(rows, raw, report, "exact" if o.exact else "ivf", reasons)


def lookup(table: Table, winners: DataFrame, columns: list[str]) -> DataFrame:
    """Wide columns of the k winners only: their files are read for these columns, other rows are
    dropped by a join with the k (file, ordinal) keys. The winners are written, so the search runs once."""
    winners = written(winners, "winners")
    keys = winners.select("file", "ord").distinct().collect()  # k rows a query
    if not keys:
        return winners.select("*", *[F.lit(None).cast(table.schema()[c].dataType).alias(c) for c in columns])
    narrow = table.spark.createDataFrame([(r["file"], r["ord"]) for r in keys], "file string, ord long")
    source = table.spark.read.schema(table.schema()).parquet(*sorted({r["file"] for r in keys}))
    wide = source.select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("ord"), *columns)
    return winners.join(wide.join(F.broadcast(narrow), ["file", "ord"]), ["file", "ord"])


def _empty(table: Table, carried: list[str], many: bool, project, tie) -> DataFrame:
    kinds = table.schema()
    names = [*dict.fromkeys([*([tie] if tie != "ord" else []), *project])]
    fields = [*([T.StructField("query_id", T.LongType()), T.StructField("rank", T.IntegerType())] if many else [])]
    fields += [T.StructField(c, kinds[c].dataType) for c in names]
    fields += [T.StructField("dist", T.DoubleType()), T.StructField("file", T.StringType()), T.StructField("ord", T.LongType())]
    return table.spark.createDataFrame([], T.StructType(fields))


def escalate(
    table: Table, q: Sequence[float], k: int, where: str | Pred, rounds: int = 3, project: Sequence[str] = (), tie: str | None = None, **more
) -> Found:
    """When a residual that was not pushed leaves fewer than k rows, over-fetch more, then look at every row."""
    s = more.pop("overfetch", 4)
    for _ in range(rounds):
        found = knn_batch(table, [(0, list(q))], k, where, project, tie, overfetch=s, **more)
        if found.path == "empty" or found.rows.count() >= k:
            return found
        s *= 2
    if "predicate_not_pushable" in found.reasons:  # no search can apply it: the plain plan does
        text = where if isinstance(where, str) else where.sql()
        found = fallback(table, q, k, text, project, f"exact_after_{rounds}", tie)
        none = [F.lit(None).cast("string").alias("file"), F.lit(None).cast("long").alias("ord")]
        return Found(found.rows.select("*", *none), None, found.report, found.path, found.reasons)
    found = knn_batch(table, [(0, list(q))], k, where, project, tie, **{**more, "exact": True, "overfetch": 1, "residual": "rescore"})
    found.reasons.append(f"exact_after_{rounds}")
    return found


def fallback(table: Table, q: Sequence[float], k: int, where: str | None = None, project: Sequence[str] = (), reason: str = "", tie: str | None = None) -> Found:
    """The plain plan: every row, the filter as SQL, exact distances in the JVM."""
    from ..functions.vectors import l2_distance, literal

    spec = table.spec()
    q = coerce_query(q, spec)
    df = table.read()
    df = df.where(where) if where else df
    tie = _tie_columns(table, tie)
    keep = [*dict.fromkeys([tie, *project])] if tie != "ord" else list(project)
    near = df.where(F.col(spec.column).isNotNull()).select(*keep, l2_distance(F.col(spec.column), literal(q)).alias("dist"))
    rows = near.orderBy("dist", *([tie] if tie != "ord" else [])).limit(max(k, 0))
    return Found(rows, None, PruneReport(0, 0, 0, 0), "fallback", [reason] if reason else [])


def by_waves(table: Table, q: Sequence[float], k: int, waves: int = 4, **more) -> Found:
    """Unfiltered search in waves of files by the least distance that their balls allow; it stops when
    no later file can hold a nearer row. Needs indexed files. The table's policy holds as on every path."""
    from ..functions.vectors import l2_distance, literal

    pred = parse(table.policy, table.schema(), table.spark) if table.policy else None
    if pred is not None and not pred.pushable():
        return fallback(table, q, k, reason="policy_not_pushable")
    manifest = survivors(table.manifest(), pred)
    floor = F.coalesce(l2_distance(F.col("ball.centre"), literal(q)) - F.col("ball.radius"), F.lit(-1.0))
    ranked = manifest.select("*", floor.alias("floor")).orderBy("floor", "file").collect()  # metadata, one row a file
    size, best, found = max(1, -(-len(ranked) // waves)), None, None
    for at in range(0, len(ranked), size):
        part = ranked[at : at + size]
        if best is not None and part[0]["floor"] > best:
            break
        own = table.spark.createDataFrame([r[:-1] for r in part], manifest.schema)
        raw = _raw(table, own, [(0, coerce_query(q, table.spec()))], k, pred, pred is not None, [], Options(**more))
        rows = raw.where("ord >= 0").orderBy("dist", "file", "ord").limit(k).select("file", "ord", "dist").collect()
        found = sorted([*(found or []), *rows], key=lambda r: (r["dist"], r["file"], r["ord"]))[:k]
        best = found[-1]["dist"] if len(found) == k else None
    rows = table.spark.createDataFrame(found or [], "file string, ord long, dist double")
    return Found(rows, None, PruneReport(len(ranked), min(len(ranked), at + size) if ranked else 0, 0, 0), "waves")
