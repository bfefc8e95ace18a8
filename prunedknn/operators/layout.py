"""Writers that place rows in files, and how local a column is in what they wrote.

uniform: by a hash, so every file holds every value. value_local and clustered: files hold one
value each; clustered records that, so the column counts as pure. partitioned: the same, as
partition values. derived: by an expression of a column. sorted: ranges of a column.
zorder: ranges of interleaved quantile bits. scattered: like uniform, under a declared index.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .. import storage
from ..manifest import Table, describe
from ..schema import VectorSpec, validate

KINDS = ("uniform", "value_local", "clustered", "partitioned", "derived", "sorted", "zorder", "scattered")


def _below(column: str):
    return lambda edge: edge < F.col(column)


def z_value(df: DataFrame, cols: Sequence[str], bits: int = 8) -> Column:
    """Interleaved bits of each column's quantile bucket; the cuts are 2**bits - 1 numbers a column."""
    cuts = [i / (1 << bits) for i in range(1, 1 << bits)]
    found = df.stat.approxQuantile(list(cols), cuts, 1.0 / (4 << bits))
    out = F.lit(0).cast("bigint")
    for k, (c, edges) in enumerate(zip(cols, found, strict=True)):
        bucket = F.size(F.filter(F.array(*[F.lit(float(e)) for e in sorted(set(edges))]), _below(c)))
        for b in range(bits):
            bit = F.shiftright(bucket, b).bitwiseAND(1).cast("bigint")
            out = out.bitwiseOR(F.shiftleft(bit, b * len(cols) + k))
    return out


def _numbered(df: DataFrame, number: Column, files: int, path: str, sort: Sequence[str] = ()) -> None:
    dealt = df.withColumn("_file", number.cast("int")).repartitionById(files, F.col("_file")).drop("_file")
    (dealt.sortWithinPartitions(*sort) if sort else dealt).write.parquet(path)


def write(
    df: DataFrame, path: str, spec: VectorSpec, kind: str = "uniform", files: int = 8, cols: Sequence[str] = (),
    filters: Sequence[str] = (), presence: Sequence[str] = (), bloom: Sequence[str] = (), key: Sequence[str] = (),
    derive: Column | None = None, file_number: Column | None = None, per_value: int = 1,
) -> Table:
    """Write df as a new table. file_number overrides where rows go; key is what uniform hashes;
    per_value: how many files each value is split over, against hot values."""
    spark = df.sparkSession
    if kind not in KINDS:
        raise ValueError(f"no layout called {kind}")
    df, path = validate(df, spec), storage.qualified(spark, path)
    data = f"{path}/data/base"
    if file_number is not None:
        _numbered(df, file_number, files, data, key)
    elif kind in ("uniform", "scattered"):
        _numbered(df, F.pmod(F.xxhash64(*(key or [c for c in df.columns if c != spec.column])), F.lit(files)), files, data)
    elif kind == "sorted":
        df.repartitionByRange(files, *cols).sortWithinPartitions(*cols).write.parquet(data)
    elif kind == "zorder":
        ordered = df.withColumn("_z", z_value(df, cols))
        ordered.repartitionByRange(files, "_z").sortWithinPartitions("_z").drop("_z").write.parquet(data)
    else:
        value = derive if kind == "derived" else F.struct(*cols)
        valued = df.withColumn("_value", value)
        # one row a value: as many as there are groups of files
        values = [r[0] for r in valued.select("_value").distinct().orderBy("_value").collect()]
        table = spark.createDataFrame([(i, v) for i, v in enumerate(values)], valued.select(F.lit(0).alias("_n"), "_value").schema) if values else None
        if table is None:
            df.write.parquet(data)
        else:
            salt = F.pmod(F.xxhash64(*(key or [c for c in df.columns if c != spec.column])), F.lit(per_value))
            placed = valued.join(F.broadcast(table), valued["_value"].eqNullSafe(table["_value"])).drop("_value")
            number = (F.col("_n") * per_value + salt).cast("int")
            placed = placed.withColumn("_file", number).repartitionById(len(values) * per_value, F.col("_file"))
            placed.select(*df.columns).write.parquet(data)
    filters = [*dict.fromkeys([*filters, *(c for c in cols if c in df.columns)])]
    pure = list(cols) if kind in ("clustered", "partitioned") else []
    presence = [*dict.fromkeys([*presence, *pure])]
    manifest = describe(spark, [data], filters, presence, bloom, cols if kind == "partitioned" else ())
    return Table(spark, path).commit(
        manifest, None, spec=[spec.column, spec.dim, spec.metric], schema=df.select(*df.columns).schema.json(), layout=kind,
        filters=filters, presence=presence, bloom=list(bloom), pure_columns=pure, ordering=list(cols) if kind in ("sorted", "zorder") else [],
    )


def double(table: Table, times: int = 1) -> Table:
    """Insert the table into itself: distributed growth without a client. Not through a policy, which would
    double some of its rows only."""
    if table.policy:
        raise ValueError("a view with a policy can't be doubled")
    for _ in range(times):
        table = table.append(table.read(), "double")
    return table


def ingest_serial(table: Table, rows: DataFrame, batch: int = 1000) -> Table:
    """The contrast: rows pass the client in batches."""
    held = []
    for row in rows.toLocalIterator():
        held.append(row)
        if len(held) == batch:
            table = table.append(table.spark.createDataFrame(held, rows.schema), "serial")
            held = []
    return table.append(table.spark.createDataFrame(held, rows.schema), "serial") if held else table


def locality(table: Table, column: str) -> DataFrame:
    """(value, files_with, files_total, prune_ratio) from the presence index."""
    manifest = table.manifest()
    total = manifest.count()
    return (
        manifest.select(F.explode(F.col("stats")[column]["present"]).alias("value")).groupBy("value").agg(F.count("*").alias("files_with"))
        .select("value", "files_with", F.lit(total).cast("bigint").alias("files_total"), (1 - F.col("files_with") / F.lit(float(max(total, 1)))).alias("prune_ratio"))
    )


def file_bytes_per_row(dim: int) -> int:
    return 4 * dim


def files_for(rows: int, dim: int, target_bytes: int = 512 << 20) -> int:
    """How many files of about target_bytes hold so many vectors."""
    return max(1, math.ceil(rows * file_bytes_per_row(dim) / target_bytes))
