"""Quality by an interpolated modified Kneser-Ney model over character n-grams.

The model is trained on trusted texts and lives in tables: a row an n-gram (its discounted
share) and a row a context (its back-off weight), orders 1 to ORDER. Texts are put into blocks
where they are read. A block's distinct n-grams, not its characters, travel to the hash bucket
of their middle characters, packed as sorted numbers; all blocks' n-grams are made distinct there
and joined with the counts order by order; their log-probabilities go back to the blocks,
where texts, packed, are summed up. What is shuffled follows the corpus, and no part of the
model is broadcast or collected.

Trusted texts of one fold in FOLDS are kept from training; the quantiles of their
perplexity, by language, are the limits. The perplexity held against them is drawn toward the
language's middle by PRIOR characters, so that a text of a few words is not judged by chance;
raw_perplexity is the text's own. A text that the model has learnt from can't be judged by it (it
knows the text's own n-grams); it is trusted, and kept.

N-grams are known by 64-bit hashes of their characters. Rows and blocks are numbered by task, alike
whenever a table is read; what is not a plain read of files is written first. A block that lacks
the answer to one of its n-grams is an error, never a guess.

Edge cases: null and empty texts have perplexity null and are kept; a null language, and one
with fewer than LEAST_HELD held-out texts, takes the limits of all; with no trusted text
every n-gram has the uniform probability and nothing is rejected; repeated rows are each
scored; a text of any length is scored whole, in one block; an empty table gives no rows;
extra columns are carried along, and one that has the name of a result column gives way to it
(prefix gives the results other names).
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._shared import as_table, fresh, give_back, in_parts, press, runs, spread, tidy, working, written

ORDER = 5
BLOCK_BYTES, BLOCK_ROWS = 10_000_000, 16_384
CHUNK_BYTES = 1_000_000
BUCKETS_A_PARTITION = 4
FLAG_BITS = 14
SENT_FLAGS = 65_536
FOLDS = 5
LOW, HIGH = 0.002, 0.995
SLACK = 1.03
PRIOR = 60
LEAST_HELD = 30
SENT_LANGUAGES = 10_000
START = 2
_A, _B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)
_CODE_POINTS = 0x110000

_NAMES = [f"{k}{n}" for n in range(1, ORDER + 1) for k in "gc"]
_HASHES = ", ".join(f"{name} long" for name in _NAMES)


# --- n-grams of packed texts --------------------------------------------------------------------


def _hash(columns: list[np.ndarray], length: int) -> np.ndarray:
    """Hashes of runs of `length` codes, given code by code."""
    seed = np.uint64((length + 1) * int(_B) & 0xFFFFFFFFFFFFFFFF)
    h = np.full(len(columns[0]), seed, np.uint64)
    for c in columns[:length]:
        h = (h ^ c.astype(np.uint64)) * _A
        h = h ^ (h >> np.uint64(31))
    return h


def _chunks(raw: bytes, sizes: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Texts, a bounded run of them at a time: (codes, with ORDER - 1 start marks before each text; which n-grams
    end in a character; the texts' lengths in characters). sizes: bytes of each text."""
    ends = np.cumsum(sizes)
    at = 0
    while at < len(sizes):
        base = int(ends[at - 1]) if at else 0
        stop = min(len(sizes), int(np.searchsorted(ends, base + CHUNK_BYTES)) + 1)
        part = raw[base : int(ends[stop - 1])]
        chars = np.frombuffer(part.decode("utf-8").encode("utf-32-le"), dtype=np.uint32)
        heads = (np.frombuffer(part, dtype=np.uint8) & 0xC0) != 0x80
        before = np.concatenate(([0], np.cumsum(heads)))
        bounds = before[np.concatenate(([0], ends[at:stop] - base))]
        lengths = np.diff(bounds)
        real = np.ones(len(chars) + (ORDER - 1) * len(lengths), dtype=bool)
        marks = bounds[:-1] + (ORDER - 1) * np.arange(len(lengths))
        real[(marks[:, None] + np.arange(ORDER - 1)).ravel()] = False
        codes = np.full(len(real), START, np.uint32)
        codes[real] = chars
        yield codes, real[ORDER - 1 :], lengths
        at = stop


def _windows(values: np.ndarray) -> list[np.ndarray]:
    return [values[k : len(values) - ORDER + 1 + k] for k in range(ORDER)]


def _summed(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct keys, where each stands first in the joined arrays, sums of their counts)."""
    key, n = np.concatenate(keys), np.concatenate(counts)
    order = np.argsort(key, kind="stable")
    key = key[order]
    first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1]))) if len(key) else np.zeros(0, np.int64)
    return key[first], order[first], np.add.reduceat(n[order], first) if len(key) else n


def _radix(letters: np.ndarray) -> bool:
    """Whether ORDER letters of this alphabet make one 64-bit number."""
    return len(letters) ** ORDER < 1 << 64


def distinct_ngrams(raw: bytes, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(codes, counts): a row an n-gram of the highest order, and how often it occurs in the texts."""
    seen = np.zeros(_CODE_POINTS, dtype=bool)
    for codes, _, _ in _chunks(raw, sizes):
        seen[codes] = True
    letters = np.flatnonzero(seen).astype(np.uint32)
    keys, counts, rows = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], [np.zeros((0, ORDER), np.uint32)]
    if _radix(letters):
        place, base = np.zeros(_CODE_POINTS, np.uint64), np.uint64(max(1, len(letters)))
        place[letters] = np.arange(len(letters), dtype=np.uint64)
        for codes, real, _ in _chunks(raw, sizes):
            number = np.zeros(len(real), np.uint64)
            for c in _windows(place[codes]):
                number = number * base + c
            found, n = np.unique(number[real], return_counts=True)
            keys.append(found)
            counts.append(n)
        key, _, n = _summed(keys, counts)
        return _letters_of(key, letters), n
    for codes, real, _ in _chunks(raw, sizes):
        columns = [c[real] for c in _windows(codes)]
        found, at, n = np.unique(_hash(columns, ORDER), return_index=True, return_counts=True)
        keys.append(found)
        counts.append(n)
        rows.append(np.stack([c[at] for c in columns], axis=1))
    _, first, n = _summed(keys, counts)
    return np.concatenate(rows)[first], n


def _letters_of(key: np.ndarray, letters: np.ndarray) -> np.ndarray:
    out, base = np.empty((len(key), ORDER), np.uint32), np.uint64(max(1, len(letters)))
    for k in reversed(range(ORDER)):
        out[:, k] = letters[(key % base).astype(np.int64)] if len(key) else 0
        key = key // base
    return out


def _planes(numbers: np.ndarray) -> bytes:
    """Bytes by significance: high ones are mostly zero and pack to nothing."""
    return np.ascontiguousarray(numbers.view(np.uint8).reshape(len(numbers), -1).T).tobytes()


def _from_planes(raw: bytes, kind) -> np.ndarray:
    size = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(raw, dtype=np.uint8).reshape(size, -1).T).reshape(-1).view(kind)


def pack_ngrams(codes: np.ndarray, counts: np.ndarray) -> bytes:
    """N-grams as the gaps between sorted numbers over their own alphabet, the first character last, as those of
    a bucket agree in the others; where the alphabet is too large, code by code."""
    codes = np.roll(codes, -1, axis=1)
    letters = np.unique(codes)
    if not _radix(letters):
        return press(b"", *[_planes(np.ascontiguousarray(codes[:, k])) for k in range(ORDER)], _planes(counts.astype(np.uint32)))
    key = np.zeros(len(codes), np.uint64)
    for k in range(ORDER):
        key = key * np.uint64(len(letters)) + np.searchsorted(letters, codes[:, k]).astype(np.uint64)
    order = np.argsort(key)
    gaps = np.diff(key[order], prepend=np.uint64(0))
    return press(_planes(letters), _planes(gaps), _planes(counts[order].astype(np.uint32)))


def unpack_ngrams(blob: bytes) -> tuple[np.ndarray, np.ndarray]:
    letters, *parts, counts = spread(blob)
    n = _from_planes(counts, np.uint32).astype(np.int64)
    if len(parts) > 1:
        codes = np.stack([_from_planes(p, np.uint32) for p in parts], axis=1)
    else:
        codes = _letters_of(np.cumsum(_from_planes(parts[0], np.uint64), dtype=np.uint64), _from_planes(letters, np.uint32))
    return np.roll(codes, 1, axis=1), n


def _columns(codes: np.ndarray) -> list[np.ndarray]:
    return [codes[:, k] for k in range(ORDER)]


# --- blocks -------------------------------------------------------------------------------------


def _raw(column: pa.Array) -> tuple[bytes, np.ndarray]:
    """The texts' bytes, one after the other, and the size of each; below zero for null."""
    column = column.cast(pa.large_binary())
    sizes = pc.fill_null(pc.binary_length(column), -1).to_numpy(zero_copy_only=False).astype(np.int64)
    return b"".join(x.as_py() for x in column if x.is_valid), sizes


def _cut(batches: Iterator[pa.RecordBatch], text_at: int) -> Iterator[tuple[int, list[pa.RecordBatch], bytes, np.ndarray]]:
    """Blocks of a task's rows, numbered alike in every pass: (number, rows, texts' bytes, sizes)."""
    from pyspark import TaskContext

    held, size, rows, number = [], 0, 0, TaskContext.get().partitionId() << 32

    def block() -> tuple[int, list[pa.RecordBatch], bytes, np.ndarray]:
        raw, sizes = zip(*[_raw(b.column(text_at)) for b in held], strict=True)
        return number, held, b"".join(raw), np.concatenate(sizes)

    for batch in batches:
        ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(text_at)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while at < batch.num_rows:
            base = int(ends[at - 1]) if at else 0
            full = int(np.searchsorted(ends, base + BLOCK_BYTES - size)) + 1
            stop = max(at + 1, min(batch.num_rows, full, at + BLOCK_ROWS - rows))
            held.append(batch.slice(at, stop - at))
            size, rows, at = size + int(ends[stop - 1]) - base, rows + stop - at, stop
            if size >= BLOCK_BYTES or rows >= BLOCK_ROWS:
                yield block()
                held, size, rows, number = [], 0, 0, number + 1
    if held:
        yield block()


def _pack(text_at: int, schema: pa.Schema):
    """Blocks: the texts packed, the other columns beside them."""
    rest = [i for i in range(len(schema)) if i != text_at]
    kind = pa.struct([schema.field(i) for i in rest])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = pa.Codec("zstd", compression_level=6)
        for number, held, raw, sizes in _cut(batches, text_at):
            rows = pa.StructArray.from_arrays([pa.concat_arrays([b.column(i) for b in held]) for i in rest], fields=list(kind))
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array([number], type=pa.int64()),
                    pa.ListArray.from_arrays(pa.array([0, len(rows)], type=pa.int32()), rows),
                    pa.array([sizes], type=pa.list_(pa.int64())),
                    pa.array([codec.compress(raw, asbytes=True) if raw else b""], type=pa.binary()),
                ],
                names=["block", "rows", "sizes", "texts"],
            )

    return run


def _unpacked(sizes: pa.Scalar, texts: pa.Scalar) -> tuple[bytes, np.ndarray, np.ndarray]:
    """(bytes, size of each text with null as zero, sizes as given)."""
    given = sizes.values.to_numpy(zero_copy_only=False)
    size = np.maximum(given, 0)
    total = int(size.sum())
    return (pa.Codec("zstd").decompress(texts.as_buffer(), decompressed_size=total, asbytes=True) if total else b""), size, given


def _messages(buckets: int, text_at: int):
    """Of texts in blocks: their distinct n-grams, by bucket of the middle characters."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for number, _, raw, sizes in _cut(batches, text_at):
            codes, counts = distinct_ngrams(raw, np.maximum(sizes, 0))
            bucket = (_hash(_columns(codes)[1:], 3) % np.uint64(buckets)).astype(np.int32)
            order = np.argsort(bucket, kind="stable")
            codes, counts, bucket = codes[order], counts[order], bucket[order]
            first = np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1]))) if len(bucket) else np.zeros(0, np.int64)
            packed = [pack_ngrams(codes[a:b], counts[a:b]) for a, b in zip(first.tolist(), [*first[1:].tolist(), len(bucket)], strict=False)]
            yield pa.RecordBatch.from_arrays(
                [pa.array(bucket[first], type=pa.int32()), pa.array(np.full(len(first), number, np.int64)), pa.array(packed, type=pa.binary())],
                names=["bucket", "block", "packed"],
            )

    return run


_MESSAGE = "bucket int, block long, packed binary"


def _buckets(df: DataFrame) -> int:
    return BUCKETS_A_PARTITION * max(2, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Messages, sorted by bucket: each distinct n-gram of a bucket once, with its count, as the hashes of its
    suffixes (g1 to gN) and of their contexts (c1 to cN). What is held is the bucket's distinct n-grams."""
    for own in runs(batches, 1):
        bucket, codes, counts, waiting = own.column(0)[0].as_py(), [np.zeros((0, ORDER), np.uint32)], [np.zeros(0, np.int64)], 0

        def settle(codes=codes, counts=counts) -> None:
            every = np.concatenate(codes)
            _, first, n = _summed([_hash(_columns(every), ORDER)], [np.concatenate(counts)])
            codes[:], counts[:] = [every[first]], [n]

        for packed in own.column(2):
            more, n = unpack_ngrams(packed.as_py())
            codes.append(more)
            counts.append(n)
            waiting += len(n)
            if waiting > 1_000_000 + len(codes[0]):
                settle()
                waiting = 0
        settle()
        c, hashes = _columns(codes[0]), []
        for n in range(1, ORDER + 1):
            hashes.append(_hash(c[ORDER - n :], n).view(np.int64))
            hashes.append(_hash(c[ORDER - n :], n - 1).view(np.int64))
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.full(len(counts[0]), bucket, np.int32)), pa.array(counts[0]), *map(pa.array, hashes)], names=["bucket", "n", *_NAMES]
        )


def _merged(messages: DataFrame) -> DataFrame:
    return messages.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(tidy(_merge), f"bucket int, n long, {_HASHES}")


def _expand(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of n-grams as texts of ORDER characters or fewer: the hashes that _merge gives; null beyond their length."""
    for batch in batches:
        texts = batch.column(0).to_pylist()
        hashes: dict[str, list] = {name: [] for name in _NAMES}
        for t in texts:
            codes = [np.asarray([ord(c)], np.uint32) for c in t]
            for n in range(1, ORDER + 1):
                own = codes[len(codes) - n :] if n <= len(codes) else None
                hashes[f"g{n}"].append(None if own is None else int(_hash(own, n).view(np.int64)[0]))
                hashes[f"c{n}"].append(None if own is None else int(_hash(own, n - 1).view(np.int64)[0]))
        yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(hashes[k], type=pa.int64()) for k in _NAMES]], names=["gram", *_NAMES])


# --- the model ----------------------------------------------------------------------------------


class Model:
    """grams: (order, gram, share); contexts: (order, context, backoff); both written tables."""

    def __init__(self, grams: DataFrame, contexts: DataFrame, alphabet: int):
        self.grams, self.contexts, self.alphabet = grams, contexts, alphabet


def train(trusted: DataFrame, text_col: str = "text") -> Model:
    """A model of the texts of a table."""
    return _model(trusted.select(text_col).mapInArrow(tidy(_messages(_buckets(trusted), 0)), _MESSAGE))


def _model(messages: DataFrame) -> Model:
    """Orders from the highest down: below it, an n-gram counts in how many distinct one-longer n-grams it ends."""
    level = written(_merged(messages).drop("bucket"), "kneser-counts")
    levels = level.select(F.lit(ORDER).alias("order"), F.col(f"g{ORDER}").alias("gram"), F.col(f"c{ORDER}").alias("context"), "n")
    for order in range(ORDER - 1, 0, -1):
        lower = [c for c in _NAMES if int(c[1:]) <= order and c != f"g{order}"]
        level = written(level.groupBy(f"g{order}").agg(*[F.first(c).alias(c) for c in lower], F.count("*").alias("n")), "kneser-counts")
        levels = levels.unionByName(
            level.select(F.lit(order).alias("order"), F.col(f"g{order}").alias("gram"), F.col(f"c{order}").alias("context"), "n")
        )
    levels = written(levels, "kneser-levels")
    seen = {
        (r["order"], r["n"]): r["count"] for r in levels.where("n <= 4").groupBy("order", "n").count().collect()
    }  # at most 4 numbers an order
    discounts = {}
    for order in range(1, ORDER + 1):
        n1, n2, n3, n4 = (seen.get((order, k), 0) for k in range(1, 5))
        y = n1 / (n1 + 2 * n2) if n1 + n2 else 0.5
        found = [k - (k + 1) * y * b / a if a else k / 2 for k, a, b in ((1, n1, n2), (2, n2, n3), (3, n3, n4))]
        discounts[order] = [min(max(d, 0.05), k - 0.05) for k, d in zip((1, 2, 3), found, strict=True)]

    def discount(n: int):
        out = F.lit(0.0)
        for order, d in discounts.items():
            out = F.when(F.col("order") == order, F.lit(float(d[n - 1]))).otherwise(out)
        return out

    of = F.when(F.col("n") == 1, discount(1)).when(F.col("n") == 2, discount(2)).otherwise(discount(3))
    taken = levels.withColumn("taken", of)
    contexts = written(
        taken.groupBy("order", "context").agg(F.sum("n").alias("total"), (F.sum("taken") / F.sum("n")).alias("backoff")),
        "kneser-contexts",
    )
    grams = written(
        taken.join(contexts.select("order", "context", "total"), ["order", "context"])
        .select("order", "gram", ((F.col("n") - F.col("taken")) / F.col("total")).alias("share")),
        "kneser-grams",
    )
    return Model(grams, contexts, levels.where("order = 1").count() + 1)


def _probabilities(model: Model, hashed: DataFrame) -> dict[int, DataFrame]:
    """By order: (gram, p) of the distinct n-grams that the hashes name; of the highest order, with what else hashed
    has. An order is worked out once for each of its own n-grams, from the order below: the lower, the fewer rows."""
    levels, rest = {ORDER: hashed}, [c for c in hashed.columns if c not in _NAMES]
    for order in range(ORDER - 1, 0, -1):
        lower = [c for c in _NAMES if int(c[1:]) <= order and c != f"g{order}"]
        given = levels[order + 1].where(F.col(f"g{order}").isNotNull())
        levels[order] = written(given.groupBy(f"g{order}").agg(*[F.first(c).alias(c) for c in lower]), "kneser-levels")
    out: dict[int, DataFrame] = {}
    for order in range(1, ORDER + 1):
        own = [f"g{order}", f"c{order}", *([f"g{order - 1}"] if order > 1 else []), *(rest if order == ORDER else [])]
        level = levels[order].where(F.col(f"g{order}").isNotNull()).select(*own)
        grams = model.grams.where(F.col("order") == order).select(F.col("gram").alias(f"g{order}"), "share")
        contexts = model.contexts.where(F.col("order") == order).select(F.col("context").alias(f"c{order}"), "backoff")
        if order == 1:  # one context, the empty one
            level = level.join(grams, "g1", "left").join(F.broadcast(contexts.limit(1)), "c1", "left").withColumn("p", F.lit(1.0 / model.alphabet))
        else:
            lower = out[order - 1].withColumnRenamed("gram", f"g{order - 1}")
            level = level.join(lower, f"g{order - 1}").drop(f"g{order - 1}")
            level = level.join(contexts, f"c{order}", "left").drop(f"c{order}").join(grams, f"g{order}", "left")
        p = F.coalesce("share", F.lit(0.0)) + F.coalesce("backoff", F.lit(1.0)) * F.col("p")
        out[order] = written(level.select(F.col(f"g{order}").alias("gram"), p.alias("p"), *(rest if order == ORDER else [])), "kneser-known")
    return out


def log_probabilities(model: Model, ngrams: DataFrame) -> DataFrame:
    """(gram, logp) of distinct n-grams (gram), texts of ORDER characters or fewer."""
    hashed = written(ngrams.select("gram").mapInArrow(_expand, f"gram string, {_HASHES}"), "kneser-asked")
    found = None
    for order, known in _probabilities(model, hashed.drop("gram")).items():
        own = hashed.where(F.char_length("gram") == order).select("gram", F.col(f"g{order}").alias("_g"))
        part = own.join(known.select(F.col("gram").alias("_g"), "p").distinct(), "_g").select("gram", F.ln("p").alias("logp"))
        found = part if found is None else found.unionByName(part)
    return found


# --- scoring ------------------------------------------------------------------------------------


def _found(keys: np.ndarray, values: np.ndarray, asked: np.ndarray) -> np.ndarray:
    """Values by sorted key; every key that is asked for must be there."""
    if not len(asked):
        return np.zeros(0, values.dtype)
    at = np.minimum(np.searchsorted(keys, asked), max(len(keys) - 1, 0))
    if not len(keys) or (keys[at] != asked).any():
        raise ValueError("an n-gram of a block has no answer: the blocks' table is not what the n-grams were read from")
    return values[at]


def _answer(messages: pa.Table, known: pa.Table) -> pa.Table:
    """Messages of a bucket, each with the log-probabilities of its n-grams."""
    keys = known.column("gram").to_numpy().view(np.uint64)
    order = np.argsort(keys)
    keys, logs = keys[order], known.column("logp").to_numpy()[order]
    out = []
    for packed in messages.column("packed"):
        codes, _ = unpack_ngrams(packed.as_py())
        out.append(press(_planes(_found(keys, logs, _hash(_columns(codes), ORDER)).astype(np.float32))))
    return pa.table([messages.column("block"), messages.column("packed"), pa.array(out, type=pa.binary())], names=["block", "packed", "logs"])


def _sum_up(text_at: int, schema: pa.Schema, keep_text: bool):
    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if left.num_rows != 1:
            raise ValueError("answers came for a block that is not there")
        raw, sizes, given = _unpacked(left.column("sizes")[0], left.column("texts")[0])
        keys, values = [np.zeros(0, np.uint64)], [np.zeros(0, np.float32)]
        for packed, logs in zip(right.column("packed"), right.column("logs"), strict=True):
            keys.append(_hash(_columns(unpack_ngrams(packed.as_py())[0]), ORDER))
            values.append(_from_planes(spread(logs.as_py())[0], np.float32))
        key, value = np.concatenate(keys), np.concatenate(values)
        order = np.argsort(key)
        key, value = key[order], value[order]
        sums, counts = [np.zeros(0)], [np.zeros(0, np.int64)]
        for codes, real, lengths in _chunks(raw, sizes):
            found = _found(key, value, _hash(_windows(codes), ORDER)[real])
            running, ends = np.concatenate(([0.0], np.cumsum(found, dtype=np.float64))), np.cumsum(lengths)
            sums.append(running[ends] - running[ends - lengths])
            counts.append(lengths)
        columns = left.column("rows").combine_chunks().flatten().flatten()
        if keep_text:
            offsets = np.concatenate(([0], np.cumsum(sizes)))
            texts = [None if g < 0 else raw[a:b] for g, a, b in zip(given.tolist(), offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
            columns.insert(text_at, pa.array(texts, type=pa.binary()).cast(pa.string()))
        out = pa.Table.from_arrays([*columns, pa.array(np.concatenate(sums)), pa.array(np.concatenate(counts))], schema=schema)
        del raw, left, right
        give_back()
        parts = [part for batch in out.combine_chunks().to_batches() for part in in_parts(batch)]
        return pa.Table.from_batches(parts, schema=schema)

    return run


def _scored(docs: DataFrame, model: Model, text_col: str, keep_text: bool, names: tuple[str, str]) -> DataFrame:
    """docs, with or without the texts, with the log-probability of the whole text and its characters."""
    from pyspark.sql.pandas.types import to_arrow_schema

    buckets = _buckets(docs)
    messages = written(docs.mapInArrow(tidy(_messages(buckets, docs.columns.index(text_col))), _MESSAGE), "kneser-messages")
    hashed = written(_merged(messages).drop("n"), "kneser-asked")
    known = _probabilities(model, hashed)[ORDER].select(F.col("bucket").alias("of"), "gram", F.ln("p").cast("float").alias("logp"))
    answers = messages.groupBy("bucket").cogroup(known.groupBy("of")).applyInArrow(_answer, "block long, packed binary, logs binary")
    rest = T.StructType([f for f in docs.schema.fields if f.name != text_col])
    text_at = docs.columns.index(text_col)
    blocks = docs.mapInArrow(
        tidy(_pack(text_at, to_arrow_schema(docs.schema))),
        T.StructType(
            [T.StructField("block", T.LongType()), T.StructField("rows", T.ArrayType(rest)), T.StructField("sizes", T.ArrayType(T.LongType())),
             T.StructField("texts", T.BinaryType())]
        ),
    )
    out = T.StructType([*(docs.schema if keep_text else rest).fields, T.StructField(names[0], T.DoubleType()), T.StructField(names[1], T.LongType())])
    return blocks.groupBy("block").cogroup(answers.withColumnRenamed("block", "of").groupBy("of")).applyInArrow(
        _sum_up(text_at, to_arrow_schema(out), keep_text), out
    )


def scored(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """docs with log_prob (natural log, of the whole text) and scored_chars."""
    results = ("log_prob", "scored_chars")
    names = tuple(fresh(n, docs.columns) for n in results)
    rows = docs.withColumn(fresh("row", docs.columns), F.lit(0)) if len(docs.columns) == 1 else docs  # a block's rows need a column
    return _settled(_scored(as_table(rows, "kneser-rows"), model, text_col, True, names), docs.columns, dict(zip(results, names, strict=True)))


def marked(docs: DataFrame, id_col: str, ids: DataFrame, name: str) -> DataFrame:
    """docs with a boolean: whether the row's id is among ids (id). Only narrow rows are shuffled; a bit a row goes
    back to the texts, broadcast up to SENT_FLAGS runs of 2 ** FLAG_BITS rows and joined by run beyond that."""
    row, run, bits = (fresh(n, docs.columns) for n in ("row_number", "row_run", "row_bits"))
    numbered = docs.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).alias("id"))
    found = numbered.join(ids, "id", "left_semi").select(
        F.shiftright("row", FLAG_BITS).alias(run), F.expr(f"cast(shiftright(row, 6) & {(1 << FLAG_BITS - 6) - 1} AS int)").alias("word"), "row"
    )
    words = found.groupBy(run, "word").agg(F.bit_or(F.expr("shiftleft(1L, cast(row & 63 AS int))")).alias("w"))
    words = words.groupBy(run).agg(F.map_from_entries(F.collect_list(F.struct("word", "w"))).alias(bits))
    flags = written(words, "flags")
    few = flags.count() <= SENT_FLAGS
    flags = F.broadcast(flags) if few else flags
    own = F.expr(f"coalesce(`{bits}`[cast(shiftright(`{row}`, 6) & {(1 << FLAG_BITS - 6) - 1} AS int)], 0L)")
    bit = F.expr(f"shiftleft(1L, cast(`{row}` & 63 AS int))")
    out = docs.withColumn(row, F.monotonically_increasing_id()).withColumn(run, F.shiftright(row, FLAG_BITS)).join(flags, run, "left")
    out = out.withColumn(name, own.bitwiseAND(bit) != 0).select(*docs.columns, name)
    return out if few else written(out, "flagged")  # a shuffled join gives rows in any order


def _settled(rated: DataFrame, columns: list[str], results: dict) -> DataFrame:
    """The given columns and the results, which take the place of columns of their names."""
    taken = {r.lower() for r in results}
    return rated.select(*[c for c in columns if c.lower() not in taken], *[(F.col(v) if isinstance(v, str) else v).alias(k) for k, v in results.items()])


def judged(
    docs: DataFrame, labels: DataFrame, lang_col: str = "lang", low: float = LOW, high: float = HIGH, text_col: str = "text",
    keep_text: bool = True, id_col: str = "doc_id", prefix: str = "",
) -> DataFrame:
    """docs with perplexity, raw_perplexity, low_limit, high_limit and kept (each name led by prefix); labels:
    (doc_id, quality), 1 marks trusted text. keep_text=False leaves the texts out, so that they are not written again."""
    spark = docs.sparkSession
    own = {k: fresh(k, docs.columns) for k in ("mean", "chars", "log", "learnt", "lang", "q", "own", "drawn")}
    with working(spark) as keep:
        trusted = labels.where("quality = 1 and doc_id is not null").select(F.col("doc_id").alias("id")).distinct()
        fold = F.pmod(F.xxhash64(F.lit("fold"), F.col("id")), F.lit(FOLDS))
        docs_marked = marked(as_table(docs, "kneser-rows"), id_col, trusted.where(fold != 0), own["learnt"])
        model = train(docs_marked.where(own["learnt"]), text_col)
        rated = _scored(docs_marked, model, text_col, keep_text, (own["log"], own["chars"]))
        mean = F.when(F.col(own["chars"]) > 0, -F.col(own["log"]) / F.col(own["chars"]))
        rated = written(rated.withColumn(own["mean"], mean).withColumn(own["lang"], F.coalesce(F.col(lang_col).cast("string"), F.lit("?"))), "kneser-scored")
        keep(rated.scratch)
        held = rated.where(F.col(own["mean"]).isNotNull()).select(
            F.col(id_col).alias("id"), F.col(own["lang"]).alias("lang"), F.col(own["mean"]).alias("mean"), F.col(own["chars"]).alias("chars")
        )
        held = written(held.join(trusted.where(fold == 0), "id", "left_semi"), "kneser-held")

        def drawn(mean: str, chars: str, middle):
            return (F.col(mean) * F.col(chars) + middle * PRIOR) / (F.col(chars) + PRIOR)

        whole = held.agg(F.percentile_approx("mean", 0.5, 10000).alias("m")).first()["m"]
        middle = held.groupBy("lang").agg(F.percentile_approx("mean", 0.5, 10000).alias("own"), F.count("*").alias("held"))
        middle = written(middle.where(F.col("held") >= LEAST_HELD), "kneser-middles")  # a row a language that has LEAST_HELD texts
        few = middle.count() <= SENT_LANGUAGES  # beyond that the limits and the rows are shuffled
        sent = (lambda df: F.broadcast(df)) if few else (lambda df: df)
        whole = math.log(2) if whole is None else float(whole)
        held = held.join(sent(middle.drop("held")), "lang", "left").withColumn("drawn", drawn("mean", "chars", F.coalesce("own", F.lit(whole))))
        cuts = lambda: F.percentile_approx("drawn", [low, high], 10000)
        everywhere = held.agg(cuts().alias("q")).first()["q"] or [-math.inf, math.inf]
        limits = held.groupBy("lang").agg(cuts().alias("q")).join(middle.drop("held"), "lang")
        limits = written(limits.select(F.col("lang").alias(own["lang"]), F.col("q").alias(own["q"]), F.col("own").alias(own["own"])), "kneser-limits")
        keep(limits.scratch)
    slack = math.log(SLACK)
    q = F.col(own["q"])
    out = rated.join(sent(limits), own["lang"], "left").withColumn(
        own["drawn"], F.exp(drawn(own["mean"], own["chars"], F.coalesce(own["own"], F.lit(whole))))
    )
    least, most = F.exp(F.coalesce(q[0], F.lit(everywhere[0])) - slack), F.exp(F.coalesce(q[1], F.lit(everywhere[1])) + slack)
    results = {
        "perplexity": F.col(own["drawn"]), "raw_perplexity": F.exp(own["mean"]), "low_limit": least, "high_limit": most,
        "kept": F.col(own["learnt"]) | F.coalesce(F.col(own["drawn"]).between(least, most), F.lit(True)),
    }
    return _settled(out, [c for c in docs.columns if keep_text or c != text_col], {prefix + k: v for k, v in results.items()})
