"""Benchmark decontamination by one FM-index per training shard.

Each task takes its documents in shards of about half a million words, builds a word-level
FM-index of the shard (full suffix order, Burrows-Wheeler transform, wavelet matrix, sampled
suffix positions), and searches all test windows backward at once. Occurrences are located
by walking to the nearest sampled position, and their word spans are merged per document.
Nothing is shuffled, and a task holds one shard at a time.

Test texts are sent to the tasks in blocks of at most BLOCK_BYTES; more of them mean more
passes, each of which adds to the spans of the pass before.

What is cut out leaves its neighbours side by side, and they can make a window that was not
there: cutting goes on until no window is left.

Edge cases: null and empty documents have no words and no hits; null, empty and wordless
test texts have no window; a test text shorter than the window is one window by itself; the
windows of an item whose id is null hit like any other, only its name is missing from the
items; repeated documents and test items are each reported; a document of any length is
searched whole, in one shard; an empty table on either side gives no hits; extra columns are
passed through on request, and one that has the name of a result column gives way to it
(names gives the results other names).
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._shared import slices, tidy, written

BLOCK_BYTES = 32 << 20
SHARD_ROWS = 4096
SHARD_WORDS = 1 << 19
SAMPLE_EVERY = 32

#: A byte to what it counts as: lower-cased letters, digits and all non-ASCII bytes stay, the rest parts words.
_FOLD = bytes(
    b + 32 if 0x41 <= b <= 0x5A else b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 32 for b in range(256)
)
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode().translate(_FOLD).split()


def suffix_order(symbols: np.ndarray) -> np.ndarray:
    """All suffixes of the symbols (integers from 0) in order, by doubling; only groups that
    are still tied are sorted again."""
    n = len(symbols)
    follow = np.zeros(n, np.int64)
    follow[:-1] = symbols[1:].astype(np.int64) + 1
    key = symbols.astype(np.int64) * (int(symbols.max(initial=0)) + 2) + follow
    order = np.argsort(key, kind="stable")
    rank, places, step = np.empty(n + 1, np.int64), np.arange(n), 2
    rank[n] = -1
    tied, keys = order, key[order]
    while True:
        fresh = np.concatenate(([True], keys[1:] != keys[:-1]))
        starts = np.flatnonzero(fresh)
        rank[tied] = np.repeat(places[starts], np.diff(np.append(starts, len(tied))))
        again = ~(fresh & np.append(fresh[1:], True))
        if not again.any():
            return order
        tied, places = tied[again], places[again]
        keys = rank[tied] * (n + 2) + rank[np.minimum(tied + step, n)] + 1
        turn = np.argsort(keys, kind="stable")
        tied, keys = tied[turn], keys[turn]
        order[places] = tied
        step *= 2


class WaveletMatrix:
    """Rank and access over a sequence of symbols, a bit level at a time, on whole arrays of questions."""

    def __init__(self, symbols: np.ndarray, alphabet: int):
        self.levels, self.n = max(1, int(alphabet - 1).bit_length()), len(symbols)
        self.words, self.before, self.zeros = [], [], []
        for level in reversed(range(self.levels)):
            ones = (symbols >> level) & 1 == 1
            raw = np.packbits(ones, bitorder="little")
            padded = np.zeros((self.n // 64 + 1) * 8, np.uint8)
            padded[: len(raw)] = raw
            words = padded.view(np.uint64)
            counts = np.bitwise_count(words).astype(np.int64)
            self.words.append(words)
            self.before.append(np.concatenate(([0], np.cumsum(counts)[:-1])))
            symbols = np.concatenate((symbols[~ones], symbols[ones]))
            self.zeros.append(self.n - int(counts.sum()))
        self.start = self.place(np.arange(alphabet), np.zeros(alphabet, np.int64))

    def _ones(self, k: int, at: np.ndarray) -> np.ndarray:
        block = at >> 6
        mask = (np.uint64(1) << (at & 63).astype(np.uint64)) - np.uint64(1)
        return self.before[k][block] + np.bitwise_count(self.words[k][block] & mask)

    def place(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        for k in range(self.levels):
            ones = self._ones(k, at)
            bit = (symbol >> (self.levels - 1 - k)) & 1 == 1
            at = np.where(bit, self.zeros[k] + ones, at - ones)
        return at

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often symbol stands before place at."""
        return self.place(symbol, at) - self.start[symbol]

    def access(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbol at each place, and its rank there."""
        symbol = np.zeros(len(at), np.int64)
        for k in range(self.levels):
            ones = self._ones(k, at)
            bit = (self.words[k][at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1) == 1
            at = np.where(bit, self.zeros[k] + ones, at - ones)
            symbol = (symbol << 1) | bit
        return symbol, at - self.start[symbol]


class FmIndex:
    """texts: word numbers from 1 (0 parts the documents), each document ended by a 0."""

    def __init__(self, text: np.ndarray, sample_every: int = SAMPLE_EVERY):
        ends = np.flatnonzero(text == 0)
        parted = text.astype(np.int64) + len(ends) - 1
        parted[ends] = np.arange(len(ends))  # each end is a symbol of its own in the order
        order = suffix_order(parted)
        last = text[order - 1].astype(np.int64)  # of position 0: the final 0
        alphabet = int(text.max(initial=0)) + 1
        self.first = np.concatenate(([0], np.cumsum(np.bincount(text, minlength=alphabet))))
        self.wavelet = WaveletMatrix(last, alphabet)
        sampled = (order % sample_every == 0) | (last == 0)
        self.sampled, self.positions = sampled, order[sampled]
        self.sample_number = np.cumsum(sampled) - 1

    def search(self, phrases: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The range of suffixes that begin with each phrase (a row of word numbers)."""
        low, high = np.zeros(len(phrases), np.int64), np.full(len(phrases), self.wavelet.n, np.int64)
        live = np.arange(len(phrases))
        for symbol in phrases.T[::-1]:
            c = symbol[live]
            low[live] = self.first[c] + self.wavelet.rank(c, low[live])
            high[live] = self.first[c] + self.wavelet.rank(c, high[live])
            live = live[high[live] > low[live]]
            if not len(live):
                break
        return low, np.maximum(high, low)

    def locate(self, rows: np.ndarray) -> np.ndarray:
        out, steps, at, todo = np.zeros(len(rows), np.int64), 0, rows.copy(), np.arange(len(rows))
        while len(todo):
            found = self.sampled[at]
            out[todo[found]] = self.positions[self.sample_number[at[found]]] + steps
            todo, at = todo[~found], at[~found]
            symbol, before = self.wavelet.access(at)
            at, steps = self.first[symbol] + before, steps + 1
        return out


class Windows:
    """The distinct windows of a block of test texts, by length, and the items each stands in."""

    def __init__(self, items: list[tuple[str | None, str | None]], width: int):
        self.vocabulary: dict[bytes, int] = {}
        found: dict[tuple[int, ...], set[str]] = defaultdict(set)
        for name, text in items:
            numbers = [self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words_of(text)]
            for i in range(max(1, len(numbers) - width + 1) if numbers else 0):
                found[tuple(numbers[i : i + width])].update([] if name is None else [name])
        self.by_length: dict[int, tuple[np.ndarray, list[list[str]]]] = {}
        for length in {len(w) for w in found}:
            rows = [w for w in found if len(w) == length]
            self.by_length[length] = (np.asarray(rows, dtype=np.int64), [sorted(found[w]) for w in rows])


def _merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def search_shard(texts: list[str | None], windows: Windows) -> list[tuple[int, list[tuple[int, int]], set[str]]]:
    """(number of words, merged word spans, items) of each text of one shard."""
    numbers: dict[bytes, int] = defaultdict(lambda: len(numbers) + 1)
    number = numbers.__getitem__
    flat: list[int] = []
    lengths = []
    for text in texts:
        found = words_of(text)
        flat.extend(map(number, found))
        flat.append(0)
        lengths.append(len(found))
    known = np.asarray([numbers.get(w, 0) for w in windows.vocabulary], dtype=np.int64)
    hits: list[list[tuple[int, int]]] = [[] for _ in texts]
    items: list[set[str]] = [set() for _ in texts]
    index, starts = None, np.concatenate(([0], np.cumsum(np.asarray(lengths) + 1)[:-1]))
    for length, (rows, names) in windows.by_length.items():
        phrases = known[rows]
        present = np.flatnonzero((phrases > 0).all(axis=1))
        if not len(present):
            continue
        if index is None:
            index = FmIndex(np.asarray(flat, dtype=np.int64))
        low, high = index.search(phrases[present])
        sizes = high - low
        which = np.repeat(present, sizes)
        offset = np.arange(len(which)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        at = index.locate(np.repeat(low, sizes) + offset)
        doc = np.searchsorted(starts, at, side="right") - 1
        for d, p, w in zip(doc.tolist(), (at - starts[doc]).tolist(), which.tolist(), strict=True):
            hits[d].append((p, p + length))
            items[d].update(names[w])
    return [(n, _merged(h), i) for n, h, i in zip(lengths, hits, items, strict=True)]


def without(text: str, spans: list[tuple[int, int]]) -> str:
    """The text with the word spans cut out, together with what stands between their words."""
    bounds = [(m.start(), m.end()) for m in _WORD.finditer(text)]
    out, at = [], 0
    for a, b in spans:
        out.append(text[at : bounds[a][0]])
        at = bounds[b - 1][1]
    return "".join(out) + text[at:]


_SPANS = T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))


def _cleaned(texts: list[str | None], spans: list[list[tuple[int, int]]], windows: Windows) -> list[str | None]:
    """Texts without their spans, and without what then stands in a window, until nothing does."""
    out = list(texts)
    while hit := [k for k, s in enumerate(spans) if s]:
        for k in hit:
            out[k] = without(out[k], spans[k])
        again = search_shard([out[k] for k in hit], windows)
        spans = [[] for _ in out]
        for k, (_, more, _) in zip(hit, again, strict=True):
            spans[k] = more
    return out


def _pass(windows, text_at: int, schema: pa.Schema, shard_words: int, clean: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tests: Windows = windows.value
        for batch in slices(batches, SHARD_ROWS):
            texts = batch.column(text_at).to_pylist()
            n = len(batch.schema.names)
            spans, items = batch.column(n - 2).to_pylist(), batch.column(n - 1).to_pylist()
            spans = [[(x["start"], x["end"]) for x in s] for s in spans]
            counts, at = [], 0
            while at < len(texts):
                end, size = at, 0
                while end < len(texts) and (size < 6 * shard_words):
                    size += len(texts[end] or "")
                    end += 1
                for k, (words, hit, names) in enumerate(search_shard(texts[at:end], tests), at):
                    counts.append(words)
                    spans[k] = _merged(hit + spans[k])
                    items[k] = sorted(names | set(items[k]))
                at = end
            listed = [[{"start": a, "end": b} for a, b in s] for s in spans]
            columns = [*batch.columns[: n - 3], counts, listed, items]
            if clean:
                columns[text_at] = pa.array(_cleaned(texts, spans, tests), type=pa.string())
            yield pa.RecordBatch.from_arrays(
                [c if isinstance(c, pa.Array) else pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)], schema=schema
            )

    return run


RESULTS = ("n_words", "spans", "items")


def contaminated(
    docs: DataFrame, tests: DataFrame, width: int = 10, id_col: str = "doc_id", text_col: str = "text",
    item_col: str = "item_id", item_text_col: str = "text", extra: tuple[str, ...] = (), clean: bool = False,
    shard_words: int = SHARD_WORDS, names: tuple[str, str, str] = RESULTS,
) -> DataFrame:
    """(id, text, *extra, n_words, spans, items) of every document.

    spans: merged ranges of word numbers of the given text that occur in a test window. clean: cut
    them from the text. tests may be any size; a count of its bytes decides the number of passes.
    """
    spark = docs.sparkSession
    tests = tests.select(F.col(item_col).cast("string").alias("item"), F.col(item_text_col).alias("text"))
    size = tests.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    passes = int(size // BLOCK_BYTES) + 1
    if passes > 1:
        tests = written(tests.withColumn("part", F.pmod(F.xxhash64("item", "text"), F.lit(passes))), "tests")
    taken = {n.lower() for n in names}
    kept = [c for c in extra if c.lower() not in taken]

    def searched(rows: DataFrame, clean: bool) -> DataFrame:
        from pyspark.sql.pandas.types import to_arrow_schema

        out = rows.select(
            id_col, text_col, *kept, F.lit(0).cast("long").alias(names[0]), F.array().cast(_SPANS).alias(names[1]),
            F.array().cast("array<string>").alias(names[2]),
        )
        schema = T.StructType([T.StructField(f.name, f.dataType) for f in out.schema])
        for k in range(passes):
            items = (tests.where(F.col("part") == k) if passes > 1 else tests).select("item", "text").collect()
            windows = spark.sparkContext.broadcast(Windows([(r[0], r[1]) for r in items], width))
            out = out.mapInArrow(tidy(_pass(windows, 1, to_arrow_schema(schema), shard_words, clean)), schema)
        return out

    if passes == 1 or not clean:
        return searched(docs, clean)
    # the cut of one pass can make a window of another: texts go round until a whole round leaves them alone
    found = searched(docs.select(id_col, text_col, *kept), False).withColumnRenamed(names[0], "_n").withColumnRenamed(names[1], "_s").withColumnRenamed(names[2], "_i")
    kept = [*kept, "_n", "_s", "_i"]
    rows = written(found, "tests-round")
    while True:
        after = written(searched(rows, True), "tests-round")
        rows = after.drop(*names)
        if after.where(F.size(names[1]) > 0).isEmpty():
            return rows.withColumnRenamed("_n", names[0]).withColumnRenamed("_s", names[1]).withColumnRenamed("_i", names[2])


def hit_words(spans) -> F.Column:
    """How many words the merged spans cover."""
    return F.aggregate(spans, F.lit(0).cast("long"), lambda total, s: total + s["end"] - s["start"])
