"""Folders, small files and scratch tables through the session's own file systems."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a temporary folder only where it is unset."""
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if context.getCheckpointDir() is None:
            context.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="prunedknn-"))
        folder = context.getCheckpointDir()
    return folder.rstrip("/")


def scratch(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder; what is written there goes when the application ends."""
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex[:12]}"
    atexit.register(_remove, spark, path)
    return path


def _remove(spark: SparkSession, path: str) -> None:
    try:
        delete(spark, path)
    except Exception:  # the session is gone already
        return


def written(df: DataFrame, tag: str, by: str | None = None) -> DataFrame:
    """df written once and read again: lineage is cut and lost executors cost nothing. by: a column with a
    folder a value, so that a filter on it reads no other."""
    path = scratch(df.sparkSession, tag)
    (df.write.partitionBy(by) if by else df.write).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def numbered(df: DataFrame, key: str, name: str) -> DataFrame:
    """df with each row's place in the order of key, from 0: sorted ranges count their rows, and the counts of the
    ranges before, a row a range, are added; no task sees all rows."""
    kept = written(
        df.repartitionByRange(F.col(key)).sortWithinPartitions(key).select("*", F.spark_partition_id().alias("_part"), F.monotonically_increasing_id().alias("_mono")),
        "numbered",
    )
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    ranges = kept.groupBy("_part").agg(F.count("*").alias("_rows"), F.min("_mono").alias("_first"))
    ranges = ranges.select("_part", "_first", F.coalesce(F.sum("_rows").over(before), F.lit(0)).alias("_offset"))
    return kept.join(F.broadcast(ranges), "_part").select(*df.columns, (F.col("_mono") - F.col("_first") + F.col("_offset")).alias(name))


def _fs(spark: SparkSession, path: str):
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    return hadoop.getFileSystem(spark._jsc.hadoopConfiguration()), hadoop


def qualified(spark: SparkSession, path: str) -> str:
    """The path as Spark names files in it, with its scheme."""
    fs, p = _fs(spark, path)
    return fs.makeQualified(p).toString()


def exists(spark: SparkSession, path: str) -> bool:
    fs, p = _fs(spark, path)
    return fs.exists(p)


def delete(spark: SparkSession, path: str) -> None:
    fs, p = _fs(spark, path)
    fs.delete(p, True)


def create(spark: SparkSession, path: str, text: str) -> bool:
    """Write a small file that must not exist yet; False where another writer was first. It is written aside and
    renamed without overwriting, so no reader sees a part of it. On a store whose rename is not atomic,
    commits need a lock of their own."""
    fs, p = _fs(spark, path)
    if fs.exists(p):
        return False
    hadoop = spark._jvm.org.apache.hadoop.fs
    aside = hadoop.Path(f"{path}.{uuid.uuid4().hex}.tmp")
    out = fs.create(aside, False)
    out.write(bytearray(text.encode()))
    out.close()
    context = hadoop.FileContext.getFileContext(fs.getUri(), spark._jsc.hadoopConfiguration())
    try:
        context.rename(fs.makeQualified(aside), fs.makeQualified(p), spark.sparkContext._gateway.new_array(getattr(hadoop, "Options$Rename"), 0))
    except Exception as e:
        fs.delete(aside, False)
        if fs.exists(p):
            return False
        raise e
    return True


def read(spark: SparkSession, path: str) -> str:
    fs, p = _fs(spark, path)
    stream = fs.open(p)
    try:
        return bytes(spark._jvm.org.apache.commons.io.IOUtils.toByteArray(stream)).decode()
    finally:
        stream.close()


def names(spark: SparkSession, path: str) -> list[str]:
    fs, p = _fs(spark, path)
    return [s.getPath().getName() for s in fs.listStatus(p)] if fs.exists(p) else []
