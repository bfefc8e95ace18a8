"""Toxicity: a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

The n-grams of 3 to 6 characters stand inside one word with its bounds marked; a feature
counts the distinct words of a text that hold the n-gram, so a text's score is a bias plus
the sum of a weight per distinct word, and a word's weight is worked out once a task.
Training takes at most SAMPLE_PER_CLASS labelled texts of each class (those of smallest
hashed id, of the folds that may be learnt from) to the driver as word lists; that bound is
the documented one, scoring covers every text whole.

Edge cases: null, empty and wordless texts get the score of the bias alone; with no labelled
rows of one class the score is the share of the class that is there, smoothed; repeated
labels and documents each count; a text of any length is scored whole; an empty table gives no
rows; extra columns pass through unused, and one that has the name of the result gives way to it.
"""

from __future__ import annotations

import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ._shared import slices, tidy

SAMPLE_PER_CLASS = 2000
FEATURES = 1 << 18
SHORTEST, LONGEST = 3, 6
LEAST_DOCS = 3
RIDGE, STEPS, SMOOTH = 2e-3, 150, 1.0
THRESHOLD = 0.3
KNOWN_BYTES = 32 << 20
SCORED_ROWS = 512

_FOLD = bytes(b + 32 if 0x41 <= b <= 0x5A else b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 32 for b in range(256))


def distinct_words(text: str | None) -> set[bytes]:
    return set((text or "").encode().translate(_FOLD).split())


def ngrams(word: bytes) -> list[int]:
    marked = f"^{word.decode()}$"
    return [
        zlib.crc32(marked[i : i + n].encode()) % FEATURES
        for n in range(SHORTEST, LONGEST + 1)
        for i in range(len(marked) - n + 1)
    ]


class Model:
    """weights: by feature, already times the log-count ratio; bias: at the labelled rate of toxic texts."""

    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias = weights, bias


def train(texts: list[bytes], toxic: np.ndarray, rate: float) -> Model:
    """texts: the distinct words of each, with blanks between. rate: of toxic among all labelled rows;
    the sample may hold the classes otherwise."""
    if not len(texts) or toxic.all() or not toxic.any():
        return Model(np.zeros(FEATURES, np.float32), float(np.log(max(rate, 1e-3) / max(1 - rate, 1e-3))))
    numbers: dict[bytes, int] = {}
    flat, lengths = array("i"), []
    for text in texts:
        own = [numbers.setdefault(w, len(numbers)) for w in text.split()]
        flat.extend(own)
        lengths.append(len(own))
    words, docs = np.frombuffer(flat, dtype=np.int32), np.repeat(np.arange(len(texts), dtype=np.int32), lengths)
    grams, counts = array("i"), array("i")
    for w in numbers:
        own = ngrams(w)
        grams.extend(own)
        counts.append(len(own))
    n_words = len(numbers)
    feature = np.frombuffer(grams, dtype=np.int32)
    owner = np.repeat(np.arange(n_words, dtype=np.int32), np.frombuffer(counts, dtype=np.int32))
    del numbers
    y = toxic.astype(np.float64)

    def to_features(per_word: np.ndarray) -> np.ndarray:
        return np.bincount(feature, weights=per_word[owner], minlength=FEATURES)

    def to_docs(per_feature: np.ndarray) -> np.ndarray:
        per_word = np.bincount(owner, weights=per_feature[feature], minlength=n_words)
        return np.bincount(docs, weights=per_word[words], minlength=len(texts))

    with_word = np.bincount(words, minlength=n_words).astype(np.float64)
    toxic_word = np.bincount(words, weights=y[docs], minlength=n_words)
    seen, p = to_features(with_word), to_features(toxic_word)
    q = seen - p
    p, q = p + SMOOTH, q + SMOOTH
    ratio = np.log((p / p.sum()) / (q / q.sum()))
    ratio[seen < LEAST_DOCS] = 0
    # logistic loss in weights over the scaled features, by Adam on the whole sample
    u, bias = np.zeros(FEATURES), 0.0
    m1, m2, b1, b2 = np.zeros(FEATURES), np.zeros(FEATURES), 0.0, 0.0
    for step in range(1, STEPS + 1):
        error = 1 / (1 + np.exp(-np.clip(to_docs(u * ratio) + bias, -30, 30))) - y
        per_word = np.bincount(words, weights=error[docs], minlength=n_words) / len(texts)
        slope, bias_slope = to_features(per_word) * ratio + RIDGE * u, error.mean()
        m1, m2 = 0.9 * m1 + 0.1 * slope, 0.99 * m2 + 0.01 * slope**2
        b1, b2 = 0.9 * b1 + 0.1 * bias_slope, 0.99 * b2 + 0.01 * bias_slope**2
        pace = 0.05 * np.sqrt(1 - 0.99**step) / (1 - 0.9**step)
        u -= pace * m1 / (np.sqrt(m2) + 1e-8)
        bias -= pace * b1 / (np.sqrt(b2) + 1e-8)
    share = y.mean()
    shift = np.log(rate / (1 - rate)) - np.log(share / (1 - share))
    return Model((u * ratio).astype(np.float32), float(bias + shift))


def _word_lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in slices(batches, SCORED_ROWS):
        words = [b" ".join(sorted(distinct_words(t))) for t in batch.column(0).to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.array(words, type=pa.binary()), batch.column(1)], names=["words", "toxic"])


def held_out(ident: Column) -> Column:
    """Rows that are never learnt from."""
    return F.coalesce(F.crc32(ident.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, sample_per_class: int = SAMPLE_PER_CLASS) -> Model:
    """Two top-n picks over the narrow labels, then one join of the picked ids with the texts."""
    usable = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).where(
        F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))
    )
    counts = {r["toxic"]: r["count"] for r in usable.groupBy("toxic").count().collect()}
    total = sum(counts.values())
    picked = None
    for kind in (0, 1):
        some = usable.where(F.col("toxic") == kind).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_per_class)
        picked = some if picked is None else picked.unionByName(some)
    rows = (
        docs.select("doc_id", "text").join(F.broadcast(picked.distinct()), "doc_id")
        .select("text", "toxic").mapInArrow(_word_lists, "words binary, toxic int").collect()
    )
    rows.sort(key=lambda r: (r["toxic"], r["words"]))  # the same model however the rows arrive
    rate = min(max((counts.get(1, 0) + 0.5) / (total + 1.0), 1e-3), 1 - 1e-3)
    return train([bytes(r["words"]) for r in rows], np.asarray([r["toxic"] for r in rows], dtype=bool), rate)


def _scorer(model, text_at: int, schema: pa.Schema):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights, bias = model.value.weights, model.value.bias
        known: dict[bytes, float] = {}
        held = 0
        for batch in slices(batches, SCORED_ROWS):
            scores = []
            for text in batch.column(text_at):
                total = bias
                for word in sorted(distinct_words(text.as_py())):
                    value = known.get(word)
                    if value is None:
                        value = known[word] = float(weights[ngrams(word)].sum())
                        held += len(word) + 150  # the entry, the word's and the number's own heads
                    total += value
                if held > KNOWN_BYTES:
                    known, held = {}, 0
                scores.append(1 / (1 + np.exp(-min(max(total, -30.0), 30.0))))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores, type=pa.float64())], schema=schema)

    return run


def score(docs: DataFrame, model: Model, text_col: str = "text", out_col: str = "score") -> DataFrame:
    """docs with the probability of being toxic; one pass, nothing shuffled. The model has a fixed size."""
    from pyspark.sql.pandas.types import to_arrow_schema

    docs = docs.select(*[c for c in docs.columns if c.lower() != out_col.lower()])
    schema = T.StructType([*docs.schema.fields, T.StructField(out_col, T.DoubleType())])
    sent = docs.sparkSession.sparkContext.broadcast(model)
    return docs.mapInArrow(tidy(_scorer(sent, docs.columns.index(text_col), to_arrow_schema(schema))), schema)
