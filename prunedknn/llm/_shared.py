"""What the text operators share: table reading, scratch tables, rows fetched by number, distributed ranks."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid
from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window


#: Texts may be long: a batch that goes to Python is bounded by its bytes, there and in the JVM. A setting of the
#: running session, read when a query is planned.
BATCH_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; only Spark's own readers touch the path."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fresh(name: str, columns: Iterable[str]) -> str:
    """name, led by as many underscores as make it differ from all columns."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def scratch_dir(spark: SparkSession) -> str:
    """The shared folder of the session (spark.checkpoint.dir). Where that is unset: a temporary folder if
    all runs on this machine, else a folder of the warehouse, which every executor sees."""
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        folder = context.getCheckpointDir()
    if not folder and not context.master.startswith("local-cluster") and context.master.startswith("local"):
        context.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="prunedknn-"))
        folder = context.getCheckpointDir()
    return (folder or spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/prunedknn-scratch").rstrip("/")


def new_path(spark: SparkSession, tag: str) -> str:
    """A path in the shared folder that nothing else uses; what is there goes when the application ends."""
    path = f"{scratch_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    atexit.register(_remove, spark, path)
    if _OPEN:
        _OPEN[-1].append(path)
    return path


def written(df: DataFrame, tag: str) -> DataFrame:
    """Write df once as Parquet in the shared folder and return a reader of it.

    Cuts lineage: what follows survives lost executors and never recomputes df.
    """
    spark = df.sparkSession
    path = new_path(spark, tag)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch = path
    return out


def as_table(df: DataFrame, tag: str) -> DataFrame:
    """df itself if it is a plain read of files, whose rows are numbered alike whenever they are read; else written."""
    plan = df._jdf.queryExecution().optimizedPlan().toString()
    nodes = {line.lstrip(" :+-").split(" ")[0] for line in plan.splitlines() if line.strip()}
    return df if nodes <= {"Project", "Filter", "Relation"} else written(df, tag)


#: Lists, the last of which notes the paths that new_path() gives.
_OPEN: list[list[str]] = []


@contextlib.contextmanager
def noting(paths: list[str]):
    """Paths of the tables written inside go to the list, for release() when nothing reads them any more."""
    _OPEN.append(paths)
    try:
        yield
    finally:
        _OPEN.pop()


@contextlib.contextmanager
def working(spark: SparkSession):
    """Tables written inside go at the end, but for the paths that keep() names: what the result reads."""
    paths: list[str] = []
    kept: set[str] = set()
    with noting(paths):
        yield lambda *some: kept.update(some)
    if _OPEN:
        _OPEN[-1].extend(p for p in paths if p in kept)
    release(spark, [p for p in paths if p not in kept])


def release(spark: SparkSession, paths: list[str]) -> None:
    while paths:
        _remove(spark, paths.pop())


def _remove(spark: SparkSession, path: str) -> None:
    try:
        hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
        hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)
    except Exception:  # the session is gone: nothing is left to clean with
        return


class Shelf:
    """Rows written once, one file a task, each with a number that names its task and its place there.

    match() brings a list of numbers to the rows, never rows to the list: files are visited in
    passes, and a pass broadcasts at most sent_rows of the numbers that lie in its files. So no
    row that is not asked for is shuffled, what is broadcast is bounded whatever the size of the
    list, and all passes together read the table once. The plan is the same at every size.
    """

    SENT_ROWS = 1_000_000
    _TASK = 33  #: monotonically_increasing_id() has the task above this bit

    def __init__(self, df: DataFrame, tag: str, number: str, sent_rows: int | None = None):
        self.spark, self.number, self.path = df.sparkSession, number, new_path(df.sparkSession, tag)
        self.sent_rows = sent_rows or self.SENT_ROWS
        numbered = df.withColumn(number, F.monotonically_increasing_id())
        numbered.write.option("maxRecordsPerFile", 0).parquet(self.path)
        self.schema = numbered.schema

    def rows(self, files: list[str] | None = None) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(*([self.path] if files is None else files))

    def _files(self) -> dict[int, str]:
        """By the task that wrote it."""
        hadoop = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        listed = hadoop.getFileSystem(self.spark._jsc.hadoopConfiguration()).listStatus(hadoop)
        names = [f.getPath().getName() for f in listed]
        return {int(n.split("-")[1]): f"{self.path}/{n}" for n in names if n.startswith("part-")}

    def passes(self, numbers: DataFrame, all_files: bool, sent_rows: int | None = None) -> list[tuple[list[str] | None, list[int] | None, int]]:
        """(files, their tasks, slices): tasks that together hold at most sent_rows of the numbers, or one task
        whose numbers go in slices. One entry a task that wrote the table is on the driver, no row is."""
        most = sent_rows or self.sent_rows
        counts = {
            r["task"]: r["count"] for r in numbers.groupBy(F.shiftright(self.number, self._TASK).cast("int").alias("task")).count().collect()
        }
        if sum(counts.values()) <= most:
            return [(None, None, 1)] if all_files or counts else []
        out, open_, size = [], [], 0
        files = self._files()
        for task in sorted(files if all_files else counts):
            n = counts.get(task, 0)
            if open_ and size + n > most:
                out.append(([files[t] for t in open_], open_, 1))
                open_, size = [], 0
            if n > most:
                out.append(([files[task]], [task], -(-n // most)))
            else:
                open_.append(task)
                size += n
        return out + ([([files[t] for t in open_], open_, 1)] if open_ else [])

    def match(
        self, numbers: DataFrame, how: str, tag: str, columns: list[str | Column] | None = None, sent_rows: int | None = None
    ) -> DataFrame:
        """Rows joined with a written table of numbers: how is left_semi, inner, left or left_anti. A row comes as often as
        an inner or left list has its number. columns: of the rows, those that are wanted. sent_rows: in place of the shelf's."""
        found = []
        of = F.shiftright(self.number, self._TASK).cast("int")
        for files, tasks, slices in self.passes(numbers, how in ("left", "left_anti"), sent_rows):
            for k in range(slices):
                rows, own = self.rows(files), numbers if tasks is None else numbers.where(of.isin(tasks))
                rows = rows if columns is None else rows.select(self.number, *columns)
                if slices > 1:
                    turn = F.pmod(F.xxhash64(self.number), F.lit(slices)) == k
                    rows, own = rows.where(turn), own.where(turn)
                found.append(rows.join(F.broadcast(own), self.number, how))
        if not found:  # nothing is asked for
            return self.rows().select(*(self.schema.names if columns is None else [self.number, *columns])).where("false").join(numbers, self.number, how)
        if len(found) == 1:
            return found[0]
        path = new_path(self.spark, tag)
        for part in found:  # one broadcast at a time
            part.write.mode("append").parquet(path)
        return self.spark.read.schema(found[0].schema).parquet(path)


def ranked(df: DataFrame, keys: list[str], name: str, tag: str) -> DataFrame:
    """Append `name`: the 0-based position of each row in the order of keys over all of df.

    One range shuffle and one written table; no window over a key that may be hot. Each
    sorted partition numbers its rows and the partitions' counts give the offsets, so the
    only broadcast has one row a partition.
    """
    ordered = df.repartitionByRange(*[F.col(k).asc_nulls_first() for k in keys]).sortWithinPartitions(
        *[F.col(k).asc_nulls_first() for k in keys]
    )
    kept = written(
        ordered.select(
            "*", F.spark_partition_id().alias("_part"), F.monotonically_increasing_id().alias("_mono")
        ),
        tag,
    )
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = (
        kept.groupBy("_part")
        .agg(F.count("*").alias("_rows"), F.min("_mono").alias("_first"))
        .select("_part", "_first", F.coalesce(F.sum("_rows").over(before), F.lit(0)).alias("_offset"))
    )
    return kept.join(F.broadcast(offsets), "_part").select(
        *df.columns, (F.col("_mono") - F.col("_first") + F.col("_offset")).alias(name)
    )


def give_back() -> None:
    """Return a worker's freed memory to the system: workers stay for later stages, whose tasks need it."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # where the C library has it
    if trim is not None:
        trim(0)


def press(*parts: bytes) -> bytes:
    """Parts, each compressed, with their sizes in front."""
    import numpy as np
    import pyarrow as pa

    codec = pa.Codec("zstd", compression_level=6)
    raw = [codec.compress(p, asbytes=True) if p else b"" for p in parts]
    sizes = np.asarray([[len(p), len(r)] for p, r in zip(parts, raw, strict=True)], dtype=np.uint64)
    return len(parts).to_bytes(4, "little") + sizes.tobytes() + b"".join(raw)


def spread(blob: bytes) -> list[bytes]:
    import numpy as np
    import pyarrow as pa

    codec, n = pa.Codec("zstd"), int.from_bytes(blob[:4], "little")
    out, at = [], 4 + 16 * n
    for size, taken in np.frombuffer(blob, dtype=np.uint64, count=2 * n, offset=4).reshape(n, 2).tolist():
        out.append(codec.decompress(blob[at : at + taken], decompressed_size=size, asbytes=True) if size else b"")
        at += taken
    return out


def runs(batches, keys: int):
    """Tables of consecutive rows that agree in their first columns, as many as keys; rows come sorted by them."""
    import numpy as np
    import pyarrow as pa

    held, last = [], None
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(keys)]
        change = np.zeros(batch.num_rows, dtype=bool)
        for c in columns:
            change[1:] |= c[1:] != c[:-1]
        starts = [0, *np.flatnonzero(change).tolist()]
        for a, b in zip(starts, [*starts[1:], batch.num_rows], strict=True):
            key = tuple(c[a] for c in columns)
            if held and key != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = key
    if held:
        yield pa.Table.from_batches(held)


def slices(batches, rows: int):
    """Batches of so many rows at most: what Python makes of a batch at once is bounded by that."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def in_parts(batch):
    """A batch in slices of BATCH_BYTES, more or less: what the JVM reads of it at once is bounded."""
    parts = max(1, min(batch.num_rows, -(-batch.nbytes // BATCH_BYTES)))
    step = max(1, -(-batch.num_rows // parts))
    for at in range(0, max(batch.num_rows, 1), step):
        yield batch.slice(at, step)


def tidy(function):
    """A batch function that sends its results in bounded parts and gives memory back when its task ends."""

    def run(batches):
        for batch in function(batches):
            yield from in_parts(batch)
        give_back()

    return run
