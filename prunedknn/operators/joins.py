"""Top-k over vectors with a filter on a joined table: the filter becomes a set of keys on the fact
side, or is laid down in it once."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.vectors import l2_distance, literal
from ..manifest import Table
from ..plans.pred import In, Pred, bloom_positions_column, parse
from ..schema import coerce_query
from ..storage import written
from . import layout, search

MAX_KEYS = 10_000


@dataclass(frozen=True)
class JoinSpec:
    """An inner equi-join of the fact's column `on` with a dimension, filtered by dim_pred.
    how other than inner, and cross_pred (a condition over both sides), can't be reduced."""

    dim: DataFrame
    on: str
    dim_pred: str | None = None
    dim_key: str | None = None
    how: str = "inner"
    cross_pred: str | None = None

    @property
    def key(self) -> str:
        return self.dim_key or self.on


@dataclass
class Joined:
    rows: DataFrame
    path: str
    keys: int | None = None
    found: search.Found | None = None
    reasons: list[str] = field(default_factory=list)


def key_set(spec: JoinSpec) -> DataFrame:
    """Distinct join keys that the dimension filter leaves; null keys never match."""
    dim = spec.dim.where(spec.dim_pred) if spec.dim_pred else spec.dim
    return dim.select(F.col(spec.key).alias("key")).where("key is not null").distinct()


def snowflake(chain: Sequence[tuple[DataFrame, str, str]], last_pred: str) -> DataFrame:
    """Collapse dim1 -> dim2 -> ... into the rows of dim1 that last_pred leaves. chain: (table, own
    key for the next, the next's key), the last table with empty names."""
    table, _, _ = chain[-1]
    kept = table.where(last_pred)
    for own, fk, pk in reversed(chain[:-1]):
        kept = own.join(kept.select(F.col(pk).alias(fk)), fk, "left_semi")
    return kept


def _dimension(spec: JoinSpec) -> DataFrame:
    dim = spec.dim.where(spec.dim_pred) if spec.dim_pred else spec.dim
    return dim.withColumnRenamed(spec.key, spec.on) if spec.key != spec.on else dim


def _exact(table: Table, spec: JoinSpec, q, k: int, where, project, attrs, reason: str, path: str, tie: str, files: DataFrame | None = None) -> Joined:
    """Join, then rank; files: manifest rows, where not all files are to be read."""
    vectors = table.spec()
    df = table.read(None if files is None else [r["file"] for r in files.select("file").orderBy("file").collect()])
    df = df.where(where) if where else df
    joined = df.join(_dimension(spec), spec.on, spec.how)
    joined = joined.where(spec.cross_pred) if spec.cross_pred else joined
    near = joined.where(F.col(vectors.column).isNotNull()).withColumn("dist", l2_distance(F.col(vectors.column), literal(coerce_query(q, vectors))))
    rows = near.select(*dict.fromkeys([tie, *project, *attrs]), "dist").orderBy("dist", tie).limit(k)
    return Joined(rows, path, None, None, [reason, *(["files_reduced"] if files is not None else [])])


def reduce_files(table: Table, keys: DataFrame, column: str) -> DataFrame:
    """Manifest rows that may hold one of the keys, by joins with the presence index or the bloom bits;
    the keys stay a DataFrame of any size."""
    manifest = table.manifest()
    stats = F.col("stats")[column]
    text = keys.select(F.col("key").cast("string").alias("value"))
    listed = manifest.where(stats["present"].isNotNull())
    by_value = listed.select("file", F.explode(stats["present"]).alias("value")).join(text, "value", "left_semi").select("file").distinct()
    bloomed = manifest.where(stats["present"].isNull() & stats["bloom"].isNotNull())
    spans = bloomed.select("file", stats["lo"].alias("lo"), stats["hi"].alias("hi"), stats["bloom"].alias("bloom"))
    numbers = keys.select(F.col("key").cast("double").alias("v"), bloom_positions_column(F.col("key").cast("string")).alias("bits"))
    there = F.expr("forall(bits, b -> (shiftrightunsigned(get(bloom, cast(b div 64 as int)), cast(b % 64 as int)) & 1L) = 1L)")
    # files are metadata and go to the keys; a range test comes first
    by_bloom = numbers.join(F.broadcast(spans), F.coalesce((F.col("v") >= F.col("lo")) & (F.col("v") <= F.col("hi")), F.lit(True)))
    by_bloom = by_bloom.where(there).select("file").distinct()
    unknown = manifest.where(stats["present"].isNull() & stats["bloom"].isNull()).select("file")
    return manifest.join(by_value.unionByName(by_bloom).unionByName(unknown).distinct(), "file", "left_semi")


def knn_join(
    table: Table, spec: JoinSpec, q: Sequence[float], k: int = 10, where: str | None = None, project: Sequence[str] = (),
    attrs: Sequence[str] = (), mode: str = "auto", max_keys: int = MAX_KEYS, tie: str | None = None, allow_ann: bool = False, **options,
) -> Joined:
    """mode: "auto" reduces where that is exact: to rows by a list of keys, beyond max_keys to files; "join" joins, then ranks;
    "sweep" searches without the filter and joins afterwards (may come short of k)."""
    tie = search._tie_columns(table, tie)
    if mode == "join":
        return _exact(table, spec, q, k, where, project, attrs, "asked", "join_then_rank", tie)
    if mode == "sweep":
        found = search.knn(table, q, k * options.pop("join_overfetch", 10), where, [*dict.fromkeys([spec.on, *project])], tie, **options)
        rows = found.rows.join(_dimension(spec), spec.on).select(*dict.fromkeys([tie, *project, *attrs]), "dist").orderBy("dist", tie).limit(k)
        return Joined(rows, "sweep", None, found, [])
    if spec.how != "inner" or spec.cross_pred:
        reason = "outer_join" if spec.how != "inner" else "cross_predicate"
        if allow_ann:
            return knn_join(table, JoinSpec(spec.dim, spec.on, spec.dim_pred, spec.dim_key), q, k, where, project, attrs, "sweep", tie=tie, **options)
        return _exact(table, spec, q, k, where, project, attrs, reason, "exact_join", tie)
    keys = [r["key"] for r in key_set(spec).limit(max_keys + 1).collect()]
    if len(keys) > max_keys:  # they stay a DataFrame: files that can hold none of them are dropped, the rest is joined
        left = reduce_files(table, written(key_set(spec), "keys"), spec.on)
        return _exact(table, spec, q, k, where, project, attrs, "too_many_keys", "join_then_rank", tie, left)
    dim = _dimension(spec)
    if attrs and dim.groupBy(spec.on).count().where("count > 1").limit(1).count():
        return _exact(table, spec, q, k, where, project, attrs, "dimension_keys_repeat", "join_then_rank", tie)
    pred: Pred = In(spec.on, tuple(sorted(keys)))
    if where:
        pred = parse(where, table.schema(), table.spark) & pred
    found = search.knn(table, q, k, pred, [*dict.fromkeys([spec.on, *project])], tie, **options)
    rows = found.rows
    if attrs:
        rows = rows.join(dim.select(spec.on, *attrs), spec.on)
    return Joined(rows.select(*dict.fromkeys([tie, *project, *attrs]), "dist").orderBy("dist", tie), "reduced", len(keys), found, [])


def materialize(fact: DataFrame, spec: JoinSpec, attrs: Sequence[str], path: str, vectors, per_value: int = 1, **layout_options) -> Table:
    """The fact with the dimension's attributes laid down, partitioned by the first of them; a hot value
    is split over per_value files and stays pure."""
    flat = fact.join(spec.dim.select(F.col(spec.key).alias(spec.on), *attrs), spec.on).select(*fact.columns, *attrs)
    return layout.write(written(flat, "materialised"), path, vectors, "partitioned", cols=[attrs[0]], per_value=per_value, **layout_options)


def stale(materialised_with: DataFrame, now: DataFrame, key: str, attrs: Sequence[str]) -> int:
    """How many dimension rows differ from those that a materialised table was made with."""
    a, b = materialised_with.select(key, *attrs), now.select(key, *attrs)
    return a.exceptAll(b).count() + b.exceptAll(a).count()


def refresh(table: Table, fact: DataFrame, spec: JoinSpec, attrs: Sequence[str], made_with: DataFrame, path: str, **layout_options) -> Table:
    """The materialised table as it is while the dimension has not changed, else a new one at path."""
    if not stale(made_with, spec.dim, spec.key, attrs):
        return table
    return materialize(fact, spec, attrs, path, table.spec(), **layout_options)
