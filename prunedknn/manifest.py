"""A table of immutable Parquet files: snapshots, one manifest row a file, optimistic commits."""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import storage
from .plans.pred import BLOOM_BITS, bloom_positions_column
from .schema import VectorSpec

STAT = (
    "struct<lo: double, hi: double, lo_text: string, hi_text: string, nulls: bigint, present: array<string>,"
    " bloom: array<bigint>, partition: boolean>"
)
MANIFEST = (
    f"file string, rows bigint, bytes bigint, indexed boolean, centroids int, stats map<string, {STAT}>,"
    " ball struct<centre: array<double>, radius: double>"
)


class Conflict(RuntimeError):
    """Another writer committed first."""


class RowCountChanged(RuntimeError):
    """A replace commit must keep the number of rows."""


def text_column(c: Column, kind: T.DataType) -> Column:
    return c if isinstance(kind, T.StringType) else c.cast("bigint").cast("string") if isinstance(kind, T.IntegralType) else c.cast("string")


def number_column(c: Column, kind: T.DataType) -> Column:
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.unix_micros(c.cast("timestamp")).cast("double") if isinstance(kind, T.TimestampType) else (
            F.expr("1.0D") * F.timestamp_diff("MICROSECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), c)
        )
    if isinstance(kind, T.DateType):
        return F.unix_date(c).cast("double")
    return F.lit(None).cast("double") if isinstance(kind, T.StringType) else c.cast("double")


def describe(
    spark: SparkSession, paths: list[str], filters: Iterable[str], presence: Iterable[str] = (), bloom: Iterable[str] = (),
    partition: Iterable[str] = (),
) -> DataFrame:
    """Manifest rows of data files: one aggregation by file, and one more for bloom filters.

    presence collects the distinct values of a file, so it is for declared columns of few values.
    """
    df = spark.read.option("recursiveFileLookup", "true").parquet(*paths)
    filters = [*dict.fromkeys([*filters, *presence, *bloom, *partition])]
    file, size = F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_size").alias("bytes")
    narrow = df.select(file, size, *filters)
    aggs = [F.count("*").alias("rows")]
    for c in filters:
        kind, own = df.schema[c].dataType, F.col(c)
        text = isinstance(kind, T.StringType)
        number = number_column(own, kind)
        none = F.lit(None).cast("string")
        aggs.append(
            F.struct(
                F.min(number).alias("lo"), F.max(number).alias("hi"),
                (F.min(own) if text else none).alias("lo_text"), (F.max(own) if text else none).alias("hi_text"),
                F.count_if(own.isNull()).alias("nulls"),
                (F.sort_array(F.collect_set(text_column(own, kind))) if c in presence else F.lit(None).cast("array<string>")).alias("present"),
                F.lit(None).cast("array<bigint>").alias("bloom"), F.lit(c in partition).alias("partition"),
            ).alias(f"s_{c}")
        )
    stats = narrow.groupBy("file", "bytes").agg(*aggs)
    for c in bloom:
        bits = (
            narrow.where(F.col(c).isNotNull())
            .select("file", F.explode(bloom_positions_column(text_column(F.col(c), df.schema[c].dataType))).alias("bit"))
            .groupBy("file", F.floor(F.col("bit") / 64).cast("int").alias("word"))
            .agg(F.bit_or(F.expr("shiftleft(1L, pmod(bit, 64))")).alias("bits"))
            .groupBy("file").agg(F.map_from_entries(F.collect_list(F.struct("word", "bits"))).alias("words"))
        )
        filled = F.transform(F.sequence(F.lit(0), F.lit(BLOOM_BITS // 64 - 1)), lambda w: F.coalesce(F.col("words")[w], F.lit(0).cast("bigint")))
        stats = stats.join(bits, "file", "left").withColumn(f"s_{c}", F.col(f"s_{c}").withField("bloom", filled)).drop("words")
    if filters:
        entries = F.map_from_arrays(F.array(*[F.lit(c) for c in filters]), F.array(*[F.col(f"s_{c}").cast(STAT) for c in filters]))
    else:
        entries = F.expr("map()")
    return stats.select(
        "file", "rows", "bytes", F.lit(False).alias("indexed"), F.lit(0).alias("centroids"), entries.cast(f"map<string, {STAT}>").alias("stats"),
        F.lit(None).cast("struct<centre: array<double>, radius: double>").alias("ball"),
    )


@dataclass(frozen=True)
class Table:
    """path/data/..., path/manifests/..., path/snapshots/v{n}.json; the highest n is the live one."""

    spark: SparkSession
    path: str
    snapshot_id: int | None = None
    policy: str | None = None
    body: str | None = None

    def snapshots(self) -> list[int]:
        return sorted(int(n[1:-5]) for n in storage.names(self.spark, f"{self.path}/snapshots") if n.startswith("v") and n.endswith(".json"))

    def current(self) -> int:
        return self.snapshot_id if self.snapshot_id is not None else self.snapshots()[-1]

    def at(self, snapshot_id: int) -> Table:
        if snapshot_id not in self.snapshots():
            raise KeyError(f"snapshot {snapshot_id} is not kept")
        return replace(self, snapshot_id=snapshot_id, body=None)

    def with_policy(self, condition: str) -> Table:
        """A view on which condition always holds, on every path."""
        return replace(self, policy=f"({self.policy}) AND ({condition})" if self.policy else condition)

    def pinned(self) -> Table:
        """The table as its snapshot stands now, whose file, which never changes, is read once."""
        if self.body is not None:
            return self
        number = self.current()
        return replace(self, snapshot_id=number, body=storage.read(self.spark, f"{self.path}/snapshots/v{number}.json"))

    def meta(self) -> dict:
        return json.loads(self.pinned().body)

    def spec(self) -> VectorSpec:
        return VectorSpec(*self.meta()["spec"])

    def manifest(self) -> DataFrame:
        return self.spark.read.schema(MANIFEST).parquet(f"{self.path}/manifests/{self.meta()['manifest']}")

    def files(self) -> list[str]:
        return [r["file"] for r in self.manifest().select("file").orderBy("file").collect()]

    def schema(self) -> T.StructType:
        return T.StructType.fromJson(json.loads(self.meta()["schema"]))

    def read(self, files: list[str] | None = None) -> DataFrame:
        """All rows of the snapshot, or of some of its files, behind the policy."""
        files = self.files() if files is None else files
        df = self.spark.read.schema(self.schema()).parquet(*files) if files else self.spark.createDataFrame([], self.schema())
        return df.where(self.policy) if self.policy else df

    def commit(self, manifest: DataFrame, parent: int | None, **meta) -> Table:
        name = f"m-{uuid.uuid4().hex}"
        manifest.select("file", "rows", "bytes", "indexed", "centroids", "stats", "ball").write.parquet(f"{self.path}/manifests/{name}")
        number = 0 if parent is None else parent + 1
        total = self.spark.read.schema(MANIFEST).parquet(f"{self.path}/manifests/{name}").agg(F.count("*"), F.coalesce(F.sum("rows"), F.lit(0))).first()
        body = {**meta, "manifest": name, "parent": parent, "n_files": total[0], "n_rows": total[1]}
        if not storage.create(self.spark, f"{self.path}/snapshots/v{number}.json", json.dumps(body)):
            raise Conflict(f"snapshot {number} exists")
        return replace(self, snapshot_id=None, body=None)

    def commit_replace(self, manifest: DataFrame, parent: int) -> Table:
        """Files for files of equal content: the rows of the whole must stay as many."""
        old, new = (m.agg(F.coalesce(F.sum("rows"), F.lit(0))).first()[0] for m in (self.at(parent).manifest(), manifest))
        if old != new:
            raise RowCountChanged(f"{old} rows before, {new} after")
        kept = {k: v for k, v in self.at(parent).meta().items() if k not in ("manifest", "parent")}
        return self.commit(manifest, parent, **kept)

    def append(self, df: DataFrame, tag: str = "append", **more) -> Table:
        """Rows as new files without an index; what was pure stays so only if the new files are. more: what the same
        commit notes in the snapshot."""
        meta, parent = self.meta(), self.current()
        path = f"{self.path}/data/{tag}-{uuid.uuid4().hex[:12]}"
        df.select(*self.schema().names).write.parquet(path)
        new = describe(self.spark, [path], meta["filters"], meta["presence"], meta["bloom"], ())
        pure = [c for c in meta["pure_columns"] if new.where(F.coalesce(F.size(F.col("stats")[c]["present"]), F.lit(2)) > 1).isEmpty()]
        kept = {k: v for k, v in meta.items() if k not in ("manifest", "parent")} | {"pure_columns": pure} | more
        return self.commit(self.manifest().unionByName(new), parent, **kept)

    def expire(self, keep: int = 1) -> int:
        """Drop old snapshots and the files that only they name; returns how many files went."""
        numbers = self.snapshots()
        gone, left = numbers[:-keep], numbers[-keep:]
        if not gone:
            return 0
        files = lambda ns: None if not ns else [self.at(n).manifest().select("file") for n in ns]
        union = lambda dfs: dfs[0] if len(dfs) == 1 else dfs[0].unionByName(union(dfs[1:]))
        orphans = [r["file"] for r in union(files(gone)).distinct().join(union(files(left)), "file", "left_anti").collect()]
        for n in gone:
            storage.delete(self.spark, f"{self.path}/snapshots/v{n}.json")
        for f in orphans:
            storage.delete(self.spark, f)
        return len(orphans)


def open_table(spark: SparkSession, path: str) -> Table:
    return Table(spark, storage.qualified(spark, path))
