"""b-bit MinHash near-duplicate classes over word shingles.

1. Texts are written once with a number a row (a shelf), then read once for words, shingle
   hashes, a digest of the shingle set and 128 minima; what is signed holds no text.
2. Documents with equal shingle sets form a class with one representative.
3. Bands of four minima bring representatives together. A bucket's centre is the member that
   shares most buckets with others, so a family of copies has few centres, near its middle.
   Members are estimated against the centre from packed 4-bit minima (equal lanes counted by
   bits, corrected for chance collisions); those above a loose bound form the centre's canopy,
   those above a tight one leave the bucket, and the rest get a next centre.
4. Each member is confirmed against its most similar centre on the full shingle sets. A centre
   meets its members in blocks of bounded size, so its text goes once to a block.
5. Canopies that then still hold several components are searched whole: what is outside of the
   main component meets all members, in blocks of bounded size with an inverted index of the
   block's shingles, and links are kept only as far as they join components.
6. Components: each task joins up the links that it reads, a bounded number at a time; while more are left than
   one task holds, large-star and small-star steps alternate with that, on written tables.

Tables between the steps are written by a task for so many rows, whatever the number of shuffle partitions: most of
them are small, and a file a partition costs more than what is in it.

Only the texts that are compared leave the shelf. The list of their numbers goes to the shelf in
parts of bounded size, each of which visits its own files: one plan, at every size.

No link is lost by canopies: similarity distance is a metric, so what is within 0.2 of a tight
member (0.45 from the centre) is within 0.65 of the centre; the loose bound lies four standard
deviations of the estimate beyond that. A pair at similarity 0.8 shares no band of 32 with
probability 5e-8.

Edge cases: a text with fewer words than a shingle is one shingle; null, empty and wordless
texts have none and stay alone; equal rows are one class; a repeated id joins the classes it
stands in only through its own rows; a null id never becomes a component's id unless all are
null; a very long text is one row of one block, whole; an empty table gives no rows; extra
columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ._shared import Shelf, fresh, runs, slices, tidy, working, written

BANDS, ROWS, BITS = 32, 4, 4
PERMUTATIONS = BANDS * ROWS
LANES = 64 // BITS
MARGIN = 0.16
TIGHT, LOOSE = 0.55, 0.2
LEVELS = 3
BLOCK = 400
BLOCK_SHINGLES = 400_000
SIGNED_ROWS = 256
KNOWN_BYTES = 16 << 20
#: Places in blocks that are broadcast at once.
PLACES = 250_000
#: Rows of a table between two steps that a task writes, and links that a task joins up at once.
TASK_ROWS = 50_000
HELD_LINKS = 1 << 18
_MIX = np.uint64(0xBF58476D1CE4E5B9)


def _fold(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * _MIX
    return h ^ (h >> np.uint64(29))


class Shingler:
    """Distinct shingle hashes of a text; a word is hashed once and remembered, up to a bound on the bytes held."""

    def __init__(self, width: int, remembered: int = KNOWN_BYTES):
        self.width, self.remembered, self.known, self.held = width, remembered, {}, 0

    def __call__(self, text: str | None) -> np.ndarray:
        import xxhash

        words = (text or "").encode().lower().split()
        if not words:
            return np.zeros(0, np.uint64)
        known = self.known
        hashes = np.empty(len(words), np.uint64)
        for i, w in enumerate(words):
            h = known.get(w)
            if h is None:
                h = known[w] = xxhash.xxh3_64_intdigest(w)
                self.held += len(w) + 150  # the entry, the word's and the number's own heads
            hashes[i] = h
        if self.held > self.remembered:
            self.known, self.held = {}, 0
        width = min(self.width, len(words))
        out = np.full(len(words) - width + 1, width, np.uint64)
        for k in range(width):
            out = _fold(out * np.uint64(0x9E3779B97F4A7C15) + hashes[k : len(words) - width + 1 + k])
        return np.unique(out)


def _coefficients() -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20)
    return rng.integers(1, 1 << 63, PERMUTATIONS, dtype=np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(
        0, 1 << 63, PERMUTATIONS, dtype=np.uint64
    )


def minima(shingles: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    best = np.full(PERMUTATIONS, np.uint64(0xFFFFFFFFFFFFFFFF))
    for i in range(0, len(shingles), 512):
        best = np.minimum(best, (shingles[i : i + 512, None] * a + b).min(axis=0))
    return (_fold(best) >> np.uint64(32)).astype(np.uint32)


_SIGNED = pa.schema(
    [("row", pa.int64()), ("id", pa.int64()), ("n_shingles", pa.int64()), ("set_key", pa.binary()), ("bands", pa.list_(pa.int64())),
     ("packed", pa.list_(pa.int64()))]
)
SIGNED_TYPE = "row long, id long, n_shingles long, set_key binary, bands array<long>, packed array<long>"


def _sign(width: int):
    """Of (row, id, text): all but the text, and what is made of it; a slice of a batch at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        shingler, (a, b) = Shingler(width), _coefficients()
        shifts = np.arange(LANES, dtype=np.uint64) * np.uint64(BITS)
        for batch in slices(batches, SIGNED_ROWS):
            columns: list[list] = [[], [], [], []]
            for text in batch.column(2):
                found = shingler(text.as_py())
                columns[0].append(len(found))
                if not len(found):
                    for c in columns[1:]:
                        c.append(None)
                    continue
                columns[1].append(xxhash.xxh3_128_digest(found.tobytes()))
                low = minima(found, a, b)
                banded = low.reshape(BANDS, ROWS).astype(np.uint64)
                key = np.arange(BANDS, dtype=np.uint64)
                for k in range(ROWS):
                    key = _fold(key * np.uint64(0x9E3779B97F4A7C15) + banded[:, k])
                columns[2].append(key.view(np.int64))
                lanes = (low & np.uint32((1 << BITS) - 1)).astype(np.uint64).reshape(-1, LANES)
                columns[3].append(np.bitwise_or.reduce(lanes << shifts, axis=1).view(np.int64))
            made = [pa.array(x, type=f.type) for x, f in zip(columns, list(_SIGNED)[2:], strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *made], schema=_SIGNED)

    return run


def estimate(left: Column, right: Column) -> Column:
    """Similarity from packed b-bit minima: lanes that differ are found by folding their bits
    onto one, equal ones are corrected for the 2**-b that agree by chance."""
    ones = int("1" * LANES, 16)
    signed = ones - (1 << 64) if ones >= 1 << 63 else ones

    def differing(pair: Column) -> Column:
        x = pair["a"].bitwiseXOR(pair["b"])
        folded = reduce(lambda acc, k: acc.bitwiseOR(F.shiftrightunsigned(x, k)), range(1, BITS), x)
        return F.bit_count(folded.bitwiseAND(F.lit(signed)))

    pairs = F.arrays_zip(left.alias("a"), right.alias("b"))
    differ = F.aggregate(pairs, F.lit(0), lambda total, p: total + differing(p).cast("int"))
    chance = 1.0 / (1 << BITS)
    return ((1 - differ / F.lit(float(PERMUTATIONS))) - chance) / (1 - chance)


def gathered(df: DataFrame, rows: int, most: int | None = None) -> DataFrame:
    """df in a task for so many of its rows, of which it reads and has as many as rows at most; nothing is shuffled for that."""
    return df.coalesce(max(1, -(-rows // (most or TASK_ROWS))))


def _least(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of links (u, v): each node but the least of its component, and that least one."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(nodes))
    while True:
        a, b = root[a], root[b]
        apart = a != b
        if not apart.any():
            break
        a, b = a[apart], b[apart]
        np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
        while (root[root] != root).any():
            root = root[root]
    leaf = root != np.arange(len(nodes))
    return nodes[leaf], nodes[root[leaf]]


def _join_up(held: int):
    """Links (u, v) become stars: those of a task, up to so many at a time."""
    schema = pa.schema([("u", pa.int64()), ("v", pa.int64())])

    def stars(links: list[pa.RecordBatch]) -> pa.RecordBatch:
        every = pa.Table.from_batches(links)
        u, v = _least(every.column(0).to_numpy(), every.column(1).to_numpy())
        return pa.RecordBatch.from_arrays([pa.array(u, type=pa.int64()), pa.array(v, type=pa.int64())], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        links, n = [], 0
        for batch in batches:
            if links and n + batch.num_rows > held:
                yield stars(links)
                links, n = [], 0
            links.append(batch)
            n += batch.num_rows
        if links:
            yield stars(links)

    return run


def _joined_up(links: DataFrame, rows: int, tag: str) -> DataFrame:
    return written(gathered(links, rows, HELD_LINKS).mapInArrow(tidy(_join_up(HELD_LINKS)), "u long, v long"), tag)


def components(edges: DataFrame, tag: str) -> DataFrame:
    """(node, component) of the nodes that have an edge (a, b): the smallest node that each reaches.

    Tasks join up their own edges. What one task held whole is done; else large-star and small-star steps go
    on, each of which leaves no more edges than there were, until nothing changes; every round is a written table.
    """
    links = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v")
    rows = edges.count()
    now = _joined_up(links, rows, tag)
    while rows > HELD_LINKS:
        rows = now.count()
        # a star forest: no node is both a leaf and a centre, and each leaf has one centre
        leaves = now.select("u").distinct()
        centred = now.select(F.col("v").alias("u")).join(leaves, "u", "left_semi").limit(1).count()
        if not centred and rows == leaves.count():
            break
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = written(gathered(large.where("u <> v").distinct(), rows), tag)
        small_least = written(gathered(large.groupBy("u").agg(F.min("v").alias("m")), rows), tag)
        small = (
            large.join(small_least, "u").where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .unionByName(small_least.select("u", F.col("m").alias("v")))
            .where("u > v").distinct()
        )
        now = _joined_up(small, rows, tag)
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(
        now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    )


def _canopies(members: DataFrame, packed: DataFrame) -> DataFrame:
    """(a, b, likeness): centre a's canopy holds b. members: (band, row, score), two rows a band at least."""
    rest, parts = members, []
    rows = max(members.count(), packed.count())  # no table of a level has more
    centre = F.max_by("row", F.struct("score", -F.col("row"))).alias("a")
    for _ in range(LEVELS):
        centres = rest.groupBy("band").agg(centre, F.count("*").alias("n")).where("n > 1").drop("n")
        pairs = rest.join(centres, "band").where("row <> a").select("band", "a", F.col("row").alias("b"), "score")
        pairs = written(gathered(pairs, rows), "minhash-centred")
        rated = (
            written(gathered(pairs.select("a", "b").distinct(), rows), "minhash-pairs")
            .join(packed.select(F.col("row").alias("a"), F.col("packed").alias("pa")), "a")
            .join(packed.select(F.col("row").alias("b"), F.col("packed").alias("pb")), "b")
            .select("a", "b", estimate(F.col("pa"), F.col("pb")).alias("likeness"))
        )
        rated = written(gathered(rated, rows), "minhash-rated")
        parts.append(rated.where(F.col("likeness") >= LOOSE))
        left = pairs.join(rated.where(F.col("likeness") >= TIGHT).select("a", "b"), ["a", "b"], "left_anti")
        rest = written(gathered(left.select("band", F.col("b").alias("row"), "score"), rows), "minhash-rest")
        if rest.groupBy("band").count().where("count > 1").isEmpty():
            break
    else:  # what is left in one bucket is looked at whole, as the canopy of one of its rows
        centres = rest.groupBy("band").agg(centre, F.count("*").alias("n")).where("n > 1").drop("n")
        parts.append(rest.join(centres, "band").where("row <> a").select("a", F.col("row").alias("b"), F.lit(float(TIGHT)).alias("likeness")))
    canopies = reduce(DataFrame.unionByName, parts).groupBy("a", "b").agg(F.max("likeness").alias("likeness"))
    return written(gathered(canopies, len(parts) * rows), "minhash-canopies")


def _search_blocks(width: int, percent: int):
    """Rows of a block (a, i, j) come together: rows of one side meet those of the other, and a link is given
    as far as it joins two components."""
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def search(block: pa.Table, shingler: Shingler) -> pa.RecordBatch:
        side, row, comp, text = (block.column(c).to_pylist() for c in ("side", "row", "component", "text"))
        right = sorted({(row[i], comp[i], i) for i in range(len(row)) if side[i]})
        sets = [shingler(text[i]) for _, _, i in right]
        sizes = np.asarray([len(x) for x in sets], dtype=np.int64)
        every = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
        order = np.argsort(every, kind="stable")
        keys, owner = every[order], np.repeat(np.arange(len(sets)), sizes)[order]
        parent: dict[int, int] = {}

        def root(x: int) -> int:
            while parent.get(x, x) != x:
                x = parent[x]
            return x

        out: tuple[list, list] = ([], [])
        for i in (i for i in range(len(row)) if not side[i]):
            own = shingler(text[i])
            low, high = np.searchsorted(keys, own), np.searchsorted(keys, own, side="right")
            n = high - low
            at = np.repeat(low - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            both = np.bincount(owner[at], minlength=len(sets))
            for j in np.flatnonzero((both > 0) & (100 * both >= percent * (len(own) + sizes - both))).tolist():
                x, y = root(comp[i]), root(right[j][1])
                if x != y:
                    parent[max(x, y)] = min(x, y)
                    out[0].append(row[i])
                    out[1].append(right[j][0])
        return pa.RecordBatch.from_arrays([pa.array(c, type=pa.int64()) for c in out], schema=schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(width)
        for block in runs(batches, 3):
            yield search(block, shingler)

    return run


def _blocks(count: str) -> Column:
    """How many blocks hold so many rows and their shingles."""
    return F.ceil(F.greatest(F.col(count) / BLOCK, F.col(f"{count}_shingles") / BLOCK_SHINGLES)).cast("int")


def _linked(dealt: DataFrame, shelf: Shelf, width: int, percent: int, tag: str) -> DataFrame:
    """Links (a, b) found in blocks. dealt: (a, i, j, side, row, component); only its rows' texts are moved, once a block."""
    texts = shelf.match(written(dealt, f"{tag}-dealt"), "inner", f"{tag}-texts")
    return written(
        texts.select("a", "i", "j", "side", "row", "component", "text")
        .repartition("a", "i", "j").sortWithinPartitions("a", "i", "j").mapInArrow(tidy(_search_blocks(width, percent)), "a long, b long"),
        tag,
    )


def _upto(count: str) -> Column:
    return F.sequence(F.lit(0), F.col(count) - 1)


def _one_of(count: str) -> Column:
    return F.pmod(F.xxhash64("row"), F.col(count)).cast("int")


def _starred(canopies: DataFrame, signed: DataFrame, shelf: Shelf, width: int, percent: int) -> DataFrame:
    """Links of each row to the most similar of its centres, confirmed on their full texts."""
    near = canopies.where(F.col("likeness") >= percent / 100 - MARGIN).groupBy("b").agg(
        F.max_by("a", F.struct("likeness", -F.col("a"))).alias("a")
    )
    rows = max(canopies.count(), signed.count())
    near = written(gathered(near.select("a", F.col("b").alias("row")), rows), "minhash-near")
    sizes = near.join(signed.select("row", "n_shingles"), "row").groupBy("a").agg(F.count("*").alias("n"), F.sum("n_shingles").alias("n_shingles"))
    sizes = written(gathered(sizes.select("a", _blocks("n").alias("n")), rows), "minhash-near-sizes")
    right = near.join(sizes, "a").select("a", F.lit(0).alias("i"), _one_of("n").alias("j"), F.lit(True).alias("side"), "row", F.col("row").alias("component"))
    left = sizes.select("a", F.lit(0).alias("i"), F.explode(_upto("n")).alias("j"), F.lit(False).alias("side"), F.col("a").alias("row"), F.col("a").alias("component"))
    return _linked(left.unionByName(right), shelf, width, percent, "minhash-stars")


def _crossed(canopies: DataFrame, comps: DataFrame, signed: DataFrame, shelf: Shelf, width: int, percent: int) -> DataFrame:
    """Links between components inside canopies that hold a tight member and more than one component."""
    rows = max(2 * canopies.count(), signed.count())  # no table below has more
    tight = canopies.where(F.col("likeness") >= TIGHT).select("a").distinct()
    members = canopies.select("a", F.col("b").alias("row")).unionByName(canopies.select("a", F.col("a").alias("row")).distinct())
    # each join is written: it reads tables of known size, whatever the joins before it were
    members = written(gathered(members.join(tight, "a", "left_semi"), rows), "minhash-tight")
    members = members.join(comps.withColumnRenamed("node", "row"), "row", "left").select("a", "row", F.coalesce("component", "row").alias("component"))
    members = written(gathered(members, rows), "minhash-inside")
    mains = written(gathered(members.where("row = a").select("a", F.col("component").alias("main")), rows), "minhash-mains")
    members = members.join(mains, "a").select("a", "row", "component", (F.col("component") != F.col("main")).alias("outside"))
    members = written(gathered(members, rows), "minhash-sides")
    mixed = written(gathered(members.where("outside").select("a").distinct(), rows), "minhash-mixed")
    members = written(gathered(members.join(mixed, "a", "left_semi"), rows), "minhash-mixed-members")
    members = written(gathered(members.join(signed.select("row", "n_shingles"), "row"), rows), "minhash-weighed")
    out = F.col("outside")
    sizes = members.groupBy("a").agg(
        F.count("*").alias("n"), F.sum("n_shingles").alias("n_shingles"), F.count_if(out).alias("m"),
        F.sum(F.when(out, F.col("n_shingles"))).alias("m_shingles"),
    ).select("a", _blocks("n").alias("n"), _blocks("m").alias("m"))
    sizes = written(gathered(sizes, rows), "minhash-sizes")
    members = written(gathered(members.drop("n_shingles").join(sizes, "a"), rows), "minhash-sized")
    left = members.where("outside").select("a", _one_of("m").alias("i"), F.explode(_upto("n")).alias("j"), F.lit(False).alias("side"), "row", "component")
    right = members.select("a", F.explode(_upto("m")).alias("i"), _one_of("n").alias("j"), F.lit(True).alias("side"), "row", "component")
    return _linked(left.unionByName(right), shelf, width, percent, "minhash-cross")


def _classed(signs: Shelf, shelf: Shelf, width: int, percent: int) -> DataFrame:
    """(set_key, component_id, component) of every class of equal shingle sets."""
    signed = signs.rows()
    rows = signed.count()  # no table of classes has more
    classes = signed.where("n_shingles > 0").groupBy("set_key").agg(
        F.min("row").alias("row"), F.min_by(signs.number, "row").alias(signs.number), F.min("id").alias("least_id")
    )
    classes = written(gathered(classes, rows), "minhash-classes")
    reps = signs.match(classes.select(signs.number), "left_semi", "minhash-reps", ["row", "bands"])
    banded = reps.select("row", F.explode("bands").alias("band"))
    # bands go over the network once: a bucket's rows are counted where they meet
    members = banded.select("band", "row", F.count("*").over(Window.partitionBy("band")).alias("n")).where("n > 1")
    members = written(gathered(members, BANDS * rows), "minhash-members")
    scores = members.groupBy("row").agg(F.sum("n").alias("score"))
    members = written(gathered(members.select("band", "row").join(scores, "row"), members.count()), "minhash-scored")
    canopies = _canopies(members, signed.select("row", "packed"))
    links = _starred(canopies, signed, shelf, width, percent)
    comps = written(gathered(components(links, "minhash-round"), 2 * rows), "minhash-first")
    more = _crossed(canopies, comps, signed, shelf, width, percent)
    comps = written(gathered(components(links.unionByName(more), "minhash-round"), 2 * rows), "minhash-components")
    labelled = classes.drop(signs.number).join(comps.withColumnRenamed("node", "row"), "row", "left").select(
        "set_key", "least_id", F.coalesce("component", "row").alias("component")
    )
    labelled = written(gathered(labelled, rows), "minhash-labelled")
    names = written(gathered(labelled.groupBy("component").agg(F.min("least_id").alias("component_id")), rows), "minhash-names")
    return written(gathered(labelled.join(names, "component").select("set_key", "component_id", "component"), rows), "minhash-named")


def duplicates_of(shelf: Shelf, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row, id, n_shingles, component_id, kept) of every row of a shelf, row being its number there: kept is
    true of one row of each component, one that has the component's id. A written table."""
    with working(shelf.spark) as keep:
        texts = shelf.rows().select(F.col(shelf.number).alias("row"), F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
        signs = Shelf(texts.mapInArrow(tidy(_sign(width)), SIGNED_TYPE), "minhash-signed", "sign")
        signed, named = signs.rows(), _classed(signs, _Texts(shelf, text_col), width, percent)
        rows = signed.count()
        found = signed.where("n_shingles > 0").select("row", "id", "n_shingles", "set_key").join(named, "set_key").drop("set_key")
        found = written(gathered(found, rows), "minhash-found")
        firsts = found.where(F.col("id").eqNullSafe(F.col("component_id"))).groupBy("component").agg(F.min("row").alias("row"))
        firsts = written(gathered(firsts.select("row", F.lit(True).alias("first")), rows), "minhash-firsts")
        linked = found.join(firsts, "row", "left").select("row", "id", "n_shingles", "component_id", F.coalesce("first", F.lit(False)).alias("kept"))
        # rows without words are alone; they never meet the others in a join
        alone = signed.where("n_shingles = 0").select("row", "id", "n_shingles", F.col("id").alias("component_id"), F.lit(True).alias("kept"))
        out = written(gathered(linked.unionByName(alone), rows), "minhash-result")
        keep(out.scratch)
    return out


class _Texts:
    """Of a shelf, the number and the text alone."""

    def __init__(self, shelf: Shelf, text_col: str):
        self.shelf, self.text_col = shelf, text_col

    def match(self, numbers: DataFrame, how: str, tag: str) -> DataFrame:
        text = F.col(self.text_col).alias("text")
        found = self.shelf.match(numbers.withColumnRenamed("row", self.shelf.number), how, tag, [text], PLACES)
        return found.withColumnRenamed(self.shelf.number, "row")


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_shingles, component_id, kept) of every row: the smallest id that it reaches over links of
    similarity percent / 100 or more, and whether it is the one row of its component that stays."""
    with working(docs.sparkSession) as keep:
        out = duplicates_of(Shelf(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), "minhash-shelf", "row"), width, percent, "id", "text")
        keep(out.scratch)
    return out.select(F.col("id").alias(id_col), "n_shingles", "component_id", "kept")


def without_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs, with all its columns, less all but one row of each component."""
    shelf = Shelf(docs, "minhash-shelf", fresh("row", docs.columns))
    found = duplicates_of(shelf, width, percent, id_col, text_col)
    gone = written(found.where(~F.col("kept")).select(F.col("row").alias(shelf.number)), "minhash-gone")
    return shelf.match(gone, "left_anti", "minhash-left").select(*docs.columns)
