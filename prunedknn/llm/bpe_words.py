"""Byte-level BPE by a shuffle of distinct words.

Texts are cut into pre-tokens where they are read. A block of documents keeps its
pre-tokens as a sequence of positions into the block's own word list; the words travel,
packed by hash bucket, to the task that encodes each distinct word of its bucket once; the
ids come back to the block and are put together again by position. Decoding looks every id
up in the token-byte table (as many rows as the vocabulary has, so of a fixed size).

Edge cases: null and empty texts give no ids and an empty decoding; repeated rows and ids
are kept, since a row is known by its block and place; a text of any length is one row of
one block; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import base64
import re
import unicodedata
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._shared import BATCH_BYTES, press, slices, spread, tidy

BLOCK_CHARS = 12_000_000
BLOCK_WORDS = 400_000
READ_ROWS = 512
#: A blank beside other white space, or at either end: there the cut at single blanks does not hold.
_UNEVEN = re.compile(r" \s|\s |^ | $")


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


def _bucket(word: str, buckets: int) -> int:
    return zlib.crc32(word.encode()) % buckets


def newer_letters(ranks: dict[bytes, int], pattern: str) -> str:
    """Code points that the local regex library calls letters or digits and the encoder's own
    older Unicode tables do not; the encoder is asked about each one that Python's tables lack.
    Behind a letter or digit "'s" is a token of its own, behind a sign it is not."""
    import regex
    import tiktoken

    encoding = tiktoken.Encoding("probe", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    word = regex.compile(r"[\p{L}\p{N}]").match
    fresh = [c for c in map(chr, range(0x110000)) if unicodedata.category(c) == "Cn" and word(c)]
    suffix = encoding.encode_ordinary("x's")[1:]
    return "".join(c for c in fresh if encoding.encode_ordinary(c + "'s")[-len(suffix) :] != suffix)


def splitter(pattern: str, odd: str):
    """findall of the pattern, with the code points in odd taken as signs."""
    import regex

    plain = regex.compile(pattern)
    if not odd:
        return plain.findall
    codes = sorted(map(ord, odd))
    breaks = [i for i in range(1, len(codes)) if codes[i] != codes[i - 1] + 1]
    spans = zip([0, *breaks], [*breaks, len(codes)], strict=True)
    ranges = "".join(f"\\U{codes[a]:08x}-\\U{codes[b - 1]:08x}" for a, b in spans)
    strange, as_sign = re.compile(f"[{ranges}]"), dict.fromkeys(codes, "\ue000")

    def findall(text: str) -> list[str]:
        if not strange.search(text):
            return plain.findall(text)
        return [text[m.start() : m.end()] for m in plain.finditer(text.translate(as_sign))]

    return findall


class _Block:
    """Documents gathered until they are long enough; each word gets a number on first sight."""

    def __init__(self, findall, buckets: int):
        self.findall, self.buckets = findall, buckets
        self.numbers: dict[str, int] = {}
        self.chunks: dict[str, tuple[int, ...]] = {}
        self.sequence, self.keys, self.lengths, self.chars = array("I"), [], [], 0

    def number(self, text: str) -> tuple[int, ...]:
        numbers = self.numbers
        return tuple([numbers.setdefault(word, len(numbers)) for word in self.findall(text)])

    def add(self, key, text: str) -> None:
        """A token holds a blank only as its first character, unless blanks adjoin other white
        space. So an even text is the chain of what its blank-led chunks give, and a chunk seen
        before costs one look-up."""
        before, out = len(self.sequence), self.sequence
        if _UNEVEN.search(text):
            out.extend(self.number(text))
        elif text:
            first, *rest = text.split(" ")
            out.extend(self.number(first))
            chunks = self.chunks
            for chunk in rest:
                known = chunks.get(chunk)
                if known is None:
                    known = chunks[chunk] = self.number(" " + chunk)
                out.extend(known)
        self.keys.append(key)
        self.lengths.append(len(out) - before)
        self.chars += len(text)

    def packed(self) -> tuple[bytes, dict[int, bytes]]:
        """(sequence, words by bucket). Words are numbered by falling frequency, so most numbers take one byte."""
        sequence = np.frombuffer(self.sequence, dtype=np.uint32) if len(self.sequence) else np.zeros(0, np.uint32)
        order = np.argsort(-np.bincount(sequence, minlength=len(self.numbers)), kind="stable")
        rank = np.empty(len(order), dtype=np.uint32)
        rank[order] = np.arange(len(order), dtype=np.uint32)
        words = list(self.numbers)
        words = [words[i] for i in order.tolist()]
        where = np.fromiter((_bucket(w, self.buckets) for w in words), dtype=np.uint32, count=len(words))
        by_bucket = {int(b): [words[i].encode() for i in np.flatnonzero(where == b).tolist()] for b in np.unique(where)}
        packed = {
            b: press(_planes(np.asarray([len(w) for w in found], dtype=np.uint32)), b"".join(found))
            for b, found in by_bucket.items()
        }
        return press(_planes(where), *_short(rank[sequence])), packed


def _planes(numbers: np.ndarray) -> bytes:
    """The bytes of unsigned 32-bit numbers by significance: the high ones are mostly zero and pack to nothing."""
    return np.ascontiguousarray(numbers.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes()


def _from_planes(raw: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, dtype=np.uint8).reshape(4, -1).T).view("<u4").reshape(-1)


_ONE_BYTE = 224


def _short(numbers: np.ndarray) -> tuple[bytes, ...]:
    """One byte for numbers below 224, else a byte that holds the top bits and two planes for the rest;
    numbers too large for that go as whole planes."""
    if len(numbers) and int(numbers.max()) >= _ONE_BYTE + (32 << 16):
        return (_planes(numbers),)
    small = numbers < _ONE_BYTE
    rest = numbers[~small] - np.uint32(_ONE_BYTE)
    first = numbers.astype(np.uint8)
    first[~small] = _ONE_BYTE + (rest >> 16).astype(np.uint8)
    return first.tobytes(), (rest & 255).astype(np.uint8).tobytes(), ((rest >> 8) & 255).astype(np.uint8).tobytes()


def _from_short(parts: list[bytes]) -> np.ndarray:
    if len(parts) == 1:
        return _from_planes(parts[0]).astype(np.int64)
    first, low, middle = (np.frombuffer(p, dtype=np.uint8).astype(np.int64) for p in parts)
    large = first >= _ONE_BYTE
    first[large] = _ONE_BYTE + ((first[large] - _ONE_BYTE) << 16 | middle << 8 | low)
    return first


def _cut_words(packed: bytes) -> list[bytes]:
    sizes, raw = spread(packed)
    ends = np.cumsum(_from_planes(sizes), dtype=np.int64).tolist()
    return [raw[a:b] for a, b in zip([0, *ends[:-1]], ends, strict=True)]


def _schema(key_type: pa.DataType) -> pa.Schema:
    """bucket: of words, or below zero for the sequence of a block, which has the keys and lengths too."""
    return pa.schema(
        [("bucket", pa.int32()), ("block", pa.int64()), ("packed", pa.binary()), ("keys", pa.list_(key_type)),
         ("lengths", pa.list_(pa.int64()))]
    )


def _cutter(pattern: str, odd: str, buckets: int, block_chars: int, key_type: pa.DataType):
    schema = _schema(key_type)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        findall = splitter(pattern, odd)
        base, made = TaskContext.get().partitionId() << 32, 0

        def flush(block: _Block) -> pa.RecordBatch:
            number = base + made
            sequence, words = block.packed()
            head = {"bucket": -1 - ((number >> 32) + made) % buckets, "block": number, "packed": sequence, "keys": block.keys, "lengths": block.lengths}
            rest = [{"bucket": b, "block": number, "packed": w} for b, w in words.items()]
            return pa.RecordBatch.from_pylist([head, *rest], schema=schema)

        block = _Block(findall, buckets)
        for batch in slices(batches, READ_ROWS):
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                block.add(key, text or "")
                if block.chars >= block_chars or len(block.numbers) >= BLOCK_WORDS:
                    yield flush(block)
                    made += 1
                    block = _Block(findall, buckets)
        if block.keys:
            yield flush(block)

    return cut


def _encoder(ranks, pattern: str):
    """Rows of one bucket come together: each distinct word is encoded once. Sequences pass by."""

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import tiktoken

        piece = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks.value, special_tokens={})
        piece = piece._core_bpe.encode_single_piece
        current, known = None, {}
        for batch in batches:
            out = []
            for bucket, packed in zip(batch.column(0).to_pylist(), batch.column(2), strict=True):
                if bucket < 0:
                    out.append(packed.as_py())
                    continue
                if bucket != current:
                    current, known = bucket, {}
                sizes, ids = [], array("I")
                for word in _cut_words(packed.as_py()):
                    got = known.get(word)
                    if got is None:
                        got = known[word] = piece(word)
                    sizes.append(len(got))
                    ids.extend(got)
                ids = np.frombuffer(ids, dtype=np.uint32) if len(ids) else np.zeros(0, np.uint32)
                out.append(press(_planes(np.asarray(sizes, dtype=np.uint32)), _planes(ids)))
            columns = [*batch.columns[:2], pa.array(out, type=pa.binary()), *batch.columns[3:]]
            yield pa.RecordBatch.from_arrays(columns, schema=batch.schema)

    return encode


def _ragged(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Indices start, start+1, ... for each (start, size), one after the other."""
    total = int(sizes.sum())
    shift = np.repeat(starts - np.concatenate(([0], np.cumsum(sizes)[:-1])), sizes)
    return shift + np.arange(total, dtype=np.int64)


def _joiner(token_bytes, schema: pa.Schema):
    """A block's rows come together, its sequence first."""

    def put_together(head: dict, parts: list[tuple[int, bytes]], table: list[bytes]) -> Iterator[pa.RecordBatch]:
        where, *short = spread(head["packed"])
        where = _from_planes(where)
        sizes, starts = np.zeros(len(where), np.int64), np.zeros(len(where), np.int64)
        pool, filled = [], 0
        for bucket, packed in parts:
            own, ids = map(_from_planes, spread(packed))
            at = np.flatnonzero(where == bucket)
            if len(at) != len(own):
                raise ValueError(f"bucket {bucket}: {len(own)} words came back for {len(at)}")
            sizes[at] = own
            starts[at] = filled + np.concatenate(([0], np.cumsum(own, dtype=np.int64)[:-1]))
            pool.append(ids)
            filled += len(ids)
        ids_of = np.concatenate(pool) if pool else np.zeros(0, np.uint32)
        sequence = _from_short(short).astype(np.uint32)
        keys, out_ids, out_bytes, at, held = [], [], [], 0, 0

        def made() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip((keys, out_ids, out_bytes), schema, strict=True)], schema=schema)

        for key, length in zip(head["keys"], head["lengths"], strict=True):
            words = sequence[at : at + length]
            at += length
            ids = ids_of[_ragged(starts[words], sizes[words])] if length else np.zeros(0, np.uint32)
            keys.append(key)
            out_ids.append(ids.astype("<u4").tobytes())
            out_bytes.append(b"".join(map(table.__getitem__, ids.tolist())))
            held += len(out_ids[-1]) + len(out_bytes[-1])
            if held >= BATCH_BYTES:
                yield made()
                keys, out_ids, out_bytes, held = [], [], [], 0
        if keys:
            yield made()

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, head, parts = token_bytes.value, None, []
        for batch in batches:
            for k in range(batch.num_rows):
                bucket = batch.column(0)[k].as_py()
                if bucket < 0:
                    if head is not None:
                        yield from put_together(head, parts, table)
                    head, parts = batch.slice(k, 1).to_pylist()[0], []
                else:
                    parts.append((bucket, batch.column(2)[k].as_py()))
        if head is not None:
            yield from put_together(head, parts, table)

    return join


def _dealt(block: str, buckets: int) -> Column:
    """Where a block is put together: blocks of one task, and first blocks of all, go to different places."""
    return F.expr(f"cast((shiftright({block}, 32) + ({block} & 4294967295L)) % {buckets} AS int)")


def encode_decode(
    docs: DataFrame, vocabulary: str, pattern: str, id_col: str = "doc_id", text_col: str = "text",
    buckets: int | None = None, block_chars: int = BLOCK_CHARS,
) -> DataFrame:
    """(id, token_ids, decoded): the ids as little-endian unsigned 32-bit integers, and the
    bytes that they decode to.

    vocabulary: path of a rank file, read on the driver only. buckets: tasks over which the
    distinct words are dealt (default: the session's shuffle partitions). docs should be read
    from a table: a task that is run again must see the same rows.
    """
    from pyspark.sql.pandas.types import to_arrow_schema, to_arrow_type

    spark = docs.sparkSession
    buckets = buckets or max(8, int(spark.conf.get("spark.sql.shuffle.partitions")))
    ranks = load_ranks(vocabulary)
    table_bytes = [b""] * (max(ranks.values()) + 1)
    for token, rank in ranks.items():
        table_bytes[rank] = token
    key = docs.schema[id_col].dataType
    arrow_key = to_arrow_type(key)
    row = T.StructType(
        [T.StructField("bucket", T.IntegerType()), T.StructField("block", T.LongType()), T.StructField("packed", T.BinaryType()),
         T.StructField("keys", T.ArrayType(key)), T.StructField("lengths", T.ArrayType(T.LongType()))]
    )
    out = T.StructType([T.StructField(id_col, key), T.StructField("token_ids", T.BinaryType()), T.StructField("decoded", T.BinaryType())])
    sent, sent_bytes = spark.sparkContext.broadcast(ranks), spark.sparkContext.broadcast(table_bytes)  # as large as the vocabulary
    return (
        docs.select(id_col, text_col).mapInArrow(tidy(_cutter(pattern, newer_letters(ranks, pattern), buckets, block_chars, arrow_key)), row)
        .repartitionById(buckets, F.expr("if(bucket < 0, -1 - bucket, bucket)")).sortWithinPartitions("bucket", "block")
        .mapInArrow(tidy(_encoder(sent, pattern)), row)
        .repartitionById(buckets, _dealt("block", buckets)).sortWithinPartitions("block", "bucket").mapInArrow(tidy(_joiner(sent_bytes, to_arrow_schema(out))), out)
    )
