"""Distributed index build: a task a file, new files beside the old, one metadata commit."""

from __future__ import annotations

import threading
import time
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import footer, ivf
from ..manifest import Table
from ..storage import written

REPORT = (
    "file string, target string, status string, error string, rows bigint, bytes bigint, centroids int, seconds double, prefix bigint,"
    " prefix_crc bigint, centre array<double>, radius double"
)


@dataclass
class BuildReport:
    seconds: float
    files: int
    failed: int
    rows: int
    task_seconds: float
    table: Table
    detail: DataFrame


def _build_file(source: str, target: str, column: str, dim: int, c: int | None, training: dict) -> dict:
    began = time.time()
    training = dict(training)
    sidecar = training.pop("sidecar", False)
    out: dict = {"file": source, "target": target, "status": "ok"}
    try:
        x = footer.matrix(footer.read_columns(source, [column]), column, dim)
        # the seed follows the content, so a second attempt makes the same file
        index = ivf.build(x, c, **({"seed": zlib.crc32(x[:64].tobytes())} | training))
        if sidecar:  # the data file stays where and as it is
            blob = ivf.encode(index)
            footer.write_sidecar(source, blob)
            out |= {"target": source, "bytes": len(blob)}
        else:
            out |= footer.embed(source, target, ivf.encode(index))
        there = x[np.isfinite(x).all(axis=1)].astype(np.float64)
        centre = there.mean(axis=0) if len(there) else np.zeros(dim)
        radius = float(np.sqrt(((there - centre) ** 2).sum(axis=1)).max()) if len(there) else 0.0
        out |= {"rows": len(x), "centroids": len(index.centroids), "centre": centre.tolist(), "radius": radius}
    except Exception as e:  # a file that fails stays without an index and is searched whole
        out |= {"target": source, "status": "failed", "error": f"{type(e).__name__}: {e}"[:500]}
    out["seconds"] = time.time() - began
    return out


def _task(column: str, dim: int, c: int | None, training: dict, schema: pa.Schema):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for source, target in zip(*[x.to_pylist() for x in batch.columns], strict=True):
                yield pa.RecordBatch.from_pylist([_build_file(source, target, column, dim, c, training)], schema=schema)

    return run


def _build(table: Table, live: DataFrame, c: int | None, parallelism: int | None, training: dict) -> BuildReport:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    spark, spec, parent, began = table.spark, table.spec(), table.current(), time.time()
    manifest = table.manifest()
    schema = to_arrow_schema(_parse_datatype_string(REPORT))
    run = uuid.uuid4().hex[:12]
    files = live.count()
    plan = live.select("file", F.concat(F.lit(f"{table.path}/data/indexed-{run}/"), F.md5("file"), F.lit(".parquet")).alias("target"))
    plan = plan.repartition(parallelism or max(1, files), "file") if files else plan
    report = written(plan.mapInArrow(_task(spec.column, spec.dim, c, training, schema), REPORT), "build")
    done = report.where("status = 'ok'").select(
        "file", "target", F.col("bytes").alias("new_bytes"), F.col("centroids").alias("new_c"), F.struct("centre", "radius").alias("new_ball")
    )
    new = manifest.join(done, "file", "left").select(
        F.coalesce("target", "file").alias("file"), "rows", F.coalesce("new_bytes", "bytes").alias("bytes"),
        (F.col("indexed") | F.col("target").isNotNull()).alias("indexed"), F.coalesce("new_c", "centroids").alias("centroids"), "stats",
        F.coalesce("new_ball", "ball").alias("ball"),
    )
    table = table.commit_replace(new, parent)
    sums = report.agg(F.count_if(F.col("status") != "ok").alias("failed"), F.sum("rows").alias("rows"), F.sum("seconds").alias("s")).first()
    return BuildReport(time.time() - began, files, sums["failed"], sums["rows"] or 0, sums["s"] or 0.0, table, report)


def create_index(table: Table, c: int | None = None, parallelism: int | None = None, **training) -> BuildReport:
    """Index every file. c: fixed number of centroids (default: by the rule); parallelism=1 is the
    serial contrast; training: algo, iters, batch, seed, pq (parts of product codes), sidecar (blobs in
    files of their own)."""
    return _build(table, table.manifest(), c, parallelism, training)


def fill_gaps(table: Table, **options) -> BuildReport:
    """Index only the files that have none: appended since, or failed before."""
    c, parallelism = options.pop("c", None), options.pop("parallelism", None)
    return _build(table, table.manifest().where(~F.col("indexed")), c, parallelism, options)


class BuildHandle:
    def __init__(self, table: Table, options: dict):
        self.tag, self.outcome, self.error = f"build-{uuid.uuid4().hex[:8]}", None, None
        self._spark = table.spark

        def work() -> None:
            table.spark.addTag(self.tag)
            try:
                self.outcome = create_index(table, **options)
            except Exception as e:
                self.error = e

        self._thread = threading.Thread(target=work, daemon=True)
        self._thread.start()

    def done(self) -> bool:
        return not self._thread.is_alive()

    def cancel(self) -> None:
        self._spark.interruptTag(self.tag)

    def result(self, timeout: float | None = None) -> BuildReport:
        self._thread.join(timeout)
        if self.error:
            raise self.error
        if self.outcome is None:
            raise TimeoutError("the build has not ended")
        return self.outcome


def create_index_async(table: Table, **options) -> BuildHandle:
    return BuildHandle(table, options)
