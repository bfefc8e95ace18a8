"""Keeping per-file indexes and matrices near the tasks that search them, and placing files on slots.

off: every query reads. block: a persisted DataFrame of decoded files, one partition a slot, so
the block manager keeps them and later queries run where they lie. node: a per-worker cache by
file with a byte budget, least recently used out first. Files never change, so nothing is ever
invalidated.
"""

from __future__ import annotations

import time
from collections import OrderedDict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import footer, ivf
from ..manifest import Table
from ..plans.pred import Pred, row_values


@dataclass
class Entry:
    index: ivf.Index | None
    matrix: np.ndarray
    table: pa.Table

    @property
    def nbytes(self) -> int:
        return self.matrix.nbytes + (self.index.nbytes if self.index else 0) + self.table.nbytes

    def mask(self, pred: Pred) -> np.ndarray:
        return pred.mask(row_values(self.table.select(sorted(pred.columns()))))


class Lru:
    """Entries by file, the least recently used ones dropped beyond a budget of bytes."""

    def __init__(self, budget: int):
        self.budget, self.held, self.bytes = budget, OrderedDict(), 0
        self.hits = self.misses = self.evictions = 0

    def get(self, key, load):
        if key in self.held:
            self.hits += 1
            self.held.move_to_end(key)
            return self.held[key], True
        self.misses += 1
        entry = load()
        self.held[key] = entry
        self.bytes += entry.nbytes
        while self.bytes > self.budget and len(self.held) > 1:
            _, gone = self.held.popitem(last=False)
            self.bytes -= gone.nbytes
            self.evictions += 1
        return entry, False


_NODE: dict[int, Lru] = {}


def read_entry(file: str, column: str, dim: int, columns: list[str], indexed: bool) -> Entry:
    """One file's vectors, its index if it decodes, and the scalar columns that are asked for."""
    table = footer.read_columns(file, [*dict.fromkeys([column, *columns])])
    index = None
    if indexed:
        try:
            blob = footer.read_blob(file)
            index = ivf.decode(blob) if blob else None
            if index is not None and index.rows > table.num_rows:
                index = None
        except ivf.CorruptIndex:
            index = None
    return Entry(index, footer.matrix(table, column, dim), table.select(columns))


def load(row: dict, column: str, dim: int, columns: list[str]) -> tuple[Entry, bool]:
    if row.get("matrix") is not None:  # block mode: the file came decoded
        x = np.frombuffer(row["matrix"], dtype=np.float32).reshape(-1, dim)
        index = ivf.decode(row["blob"]) if row["blob"] else None
        table = pa.ipc.open_stream(row["columns"]).read_all()
        missing = [c for c in columns if c not in table.column_names]
        if missing:
            extra = footer.read_columns(row["file"], missing)
            for c in missing:
                table = table.append_column(c, extra.column(c))
        return Entry(index, x, table), True
    budget = row.get("budget") or 0
    read = lambda: read_entry(row["file"], column, dim, columns, row["indexed"])
    if not budget:
        return read(), False
    return _NODE.setdefault(budget, Lru(budget)).get((row["file"], tuple(columns)), read)


def place(files: DataFrame, slots: int, kind: str = "hrw") -> DataFrame:
    """files with a slot: the one of highest hash of (file, slot), so that one slot more moves only
    1/(slots + 1) of the files; or by turns ("rr"), which moves nearly all."""
    if kind == "rr":
        # files are metadata rows; a deterministic turn by their order
        from pyspark.sql.window import Window

        return files.withColumn("slot", F.pmod(F.row_number().over(Window.orderBy("file")) - 1, F.lit(slots)))
    scores = F.transform(F.sequence(F.lit(0), F.lit(slots - 1)), lambda s: F.struct(F.md5(F.concat_ws(":", F.col("file"), s.cast("string"))).alias("h"), s.alias("s")))
    return files.withColumn("slot", F.array_max(scores)["s"])


def moved_fraction(files: DataFrame, before: int, after: int, kind: str = "hrw") -> float:
    a, b = (place(files.select("file"), n, kind).withColumnRenamed("slot", name) for n, name in ((before, "a"), (after, "b")))
    return float(a.join(b, "file").agg(F.avg((F.col("a") != F.col("b")).cast("double"))).first()[0] or 0.0)


def descriptors(placed: DataFrame, slots: int, budget: int = 0) -> DataFrame:
    """File rows, slot i in partition i."""
    return placed.select("slot", "file", "indexed", "verdict", F.lit(budget).cast("long").alias("budget")).repartitionById(slots, F.col("slot").cast("int")).drop("slot")


def await_executors(spark, n: int, timeout: float = 60.0) -> bool:
    """Wait until n executors have registered, so that placement sees the whole tier."""
    end = time.time() + timeout
    while time.time() < end:
        infos = spark.sparkContext._jsc.sc().statusTracker().getExecutorInfos()
        if len(infos) - 1 >= n or spark.sparkContext.master.startswith("local["):
            return True
        time.sleep(0.2)
    return False


class WarmSet:
    """mode "block": decoded files persisted by slot. columns: scalar columns kept with them; others
    are read when a query first needs them. mode "node": a cache of budget_bytes in each worker."""

    def __init__(self, table: Table, mode: str = "block", columns: tuple[str, ...] = (), slots: int | None = None, kind: str = "hrw", budget_bytes: int = 1 << 30):
        self.table, self.mode, self.budget = table, mode, budget_bytes
        self.slots = slots or table.spark.sparkContext.defaultParallelism
        self.blocks = None
        if mode == "block":
            spec, kept = table.spec(), list(columns)

            def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for batch in batches:
                    for row in batch.to_pylist():
                        e = read_entry(row["file"], spec.column, spec.dim, kept, row["indexed"])
                        sink = pa.BufferOutputStream()
                        with pa.ipc.new_stream(sink, e.table.schema) as w:
                            w.write_table(e.table)
                        yield pa.RecordBatch.from_pylist(
                            [{"slot": row["slot"], "file": row["file"], "blob": ivf.encode(e.index) if e.index else None, "matrix": e.matrix.tobytes(), "columns": sink.getvalue().to_pybytes()}],
                            schema=pa.schema([("slot", pa.int32()), ("file", pa.string()), ("blob", pa.binary()), ("matrix", pa.binary()), ("columns", pa.binary())]),
                        )

            placed = place(table.manifest(), self.slots, kind).select("file", "indexed", F.col("slot").cast("int").alias("slot"))
            dealt = placed.repartitionById(self.slots, F.col("slot"))
            self.blocks = dealt.mapInArrow(decode, "slot int, file string, blob binary, matrix binary, columns binary").persist(StorageLevel.MEMORY_AND_DISK)

    def join(self, placed: DataFrame, slots: int) -> DataFrame:
        if self.blocks is None:
            return descriptors(placed, slots, self.budget)
        # the descriptors are metadata and go to the blocks, which stay where they lie
        wanted = placed.select("file", "indexed", "verdict")
        return self.blocks.join(F.broadcast(wanted), "file").select("file", "indexed", "verdict", "blob", "matrix", "columns")

    def unload(self) -> None:
        if self.blocks is not None:
            self.blocks.unpersist()
