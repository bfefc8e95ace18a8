"""The inverted-file index of one data file: training, posting lists, codec, probing, re-scoring."""

from __future__ import annotations

import math
import struct
import zlib
from dataclasses import dataclass

import numpy as np

MAGIC = b"pkiv"
_HEAD = struct.Struct("<4sHHIIQ")


def choose_c(rows: int, mult: int = 4, cap: bool = True, fixed: int | None = None) -> int:
    """Centroids for a file: the next power of two from mult * sqrt(rows); no more than rows."""
    if rows <= 0:
        return 0
    c = fixed or 1 << max(0, math.ceil(math.log2(mult * math.sqrt(rows))))
    return min(c, rows) if cap else c


def squared(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Squared distances by one matrix product; for choosing lists only, never for the final order."""
    return (x * x).sum(axis=1)[:, None] - 2.0 * (x @ c.T) + (c * c).sum(axis=1)[None]


def assign(x: np.ndarray, centroids: np.ndarray, chunk: int = 8192) -> np.ndarray:
    out, wide = np.empty(len(x), dtype=np.int32), centroids.astype(np.float64)
    for i in range(0, len(x), chunk):
        out[i : i + chunk] = squared(x[i : i + chunk].astype(np.float64), wide).argmin(axis=1)
    return out


def train(x: np.ndarray, c: int, algo: str = "minibatch", seed: int = 0, iters: int = 12, batch: int = 4096) -> np.ndarray:
    """Centroids of float32 rows. minibatch: k-means by sampled batches with per-centroid rates;
    lloyd: full passes from the first rows; seed: the first c rows themselves."""
    start = x[:c].astype(np.float64)
    if algo == "seed" or not len(x):
        return start.astype(np.float32)
    if algo == "lloyd":
        for _ in range(iters):
            own = assign(x, start)
            counts = np.bincount(own, minlength=c)
            sums = np.zeros_like(start)
            np.add.at(sums, own, x)
            start = np.where(counts[:, None] > 0, sums / np.maximum(counts, 1)[:, None], start)
        return start.astype(np.float32)
    if algo != "minibatch":
        raise ValueError(f"no training called {algo}")
    rng = np.random.default_rng(seed)
    centroids = x[rng.permutation(len(x))[:c]].astype(np.float64)
    seen = np.zeros(c)
    for _ in range(iters):
        part = x[rng.integers(0, len(x), min(batch, max(len(x), 1)))]
        own = assign(part, centroids)
        counts = np.bincount(own, minlength=c)
        sums = np.zeros_like(centroids)
        np.add.at(sums, own, part)
        seen += counts
        moved = counts > 0
        rate = counts[moved] / seen[moved]
        centroids[moved] += rate[:, None] * (sums[moved] / counts[moved][:, None] - centroids[moved])
    return centroids.astype(np.float32)


def invert(own: np.ndarray, c: int) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, ordinals): the rows of list i are ordinals[offsets[i]:offsets[i + 1]], in file order."""
    offsets = np.concatenate(([0], np.cumsum(np.bincount(own, minlength=c)))).astype(np.uint32)
    return offsets, np.argsort(own, kind="stable").astype(np.uint32)


@dataclass
class Index:
    """codebook and codes, where there are any: product codes of the rows' residuals, in row order, by
    which many candidates are narrowed before exact re-scoring."""

    centroids: np.ndarray
    offsets: np.ndarray
    ordinals: np.ndarray
    codebook: np.ndarray | None = None
    codes: np.ndarray | None = None

    @property
    def rows(self) -> int:
        return int(self.offsets[-1]) if len(self.offsets) else 0

    @property
    def nbytes(self) -> int:
        coded = self.codebook.nbytes + self.codes.nbytes if self.codes is not None else 0
        return self.centroids.nbytes + self.offsets.nbytes + self.ordinals.nbytes + coded

    def lists(self) -> np.ndarray:
        """The list of each row; rows in no list have the last one."""
        own = np.full(len(self.codes), len(self.centroids) - 1, dtype=np.int64)
        own[self.ordinals] = np.repeat(np.arange(len(self.centroids)), np.diff(self.offsets))
        return own

    def narrow(self, q: np.ndarray, candidates: np.ndarray, keep: int) -> np.ndarray:
        """The `keep` candidates of least coded distance."""
        if self.codes is None or len(candidates) <= keep:
            return candidates
        m, _, width = self.codebook.shape
        own, d = self.lists()[candidates], np.empty(len(candidates))
        for c in np.unique(own):
            tables = ((self.codebook - (q - self.centroids[c]).reshape(m, 1, width)) ** 2).sum(axis=2)
            here = own == c
            d[here] = tables[np.arange(m), self.codes[candidates[here]]].sum(axis=1)
        return candidates[np.sort(np.argpartition(d, keep - 1)[:keep])]

    def probe(self, q: np.ndarray, p: int | str) -> tuple[np.ndarray, int]:
        """(row ordinals in the p nearest lists, centroid distances computed). Lists are taken by
        distance, then number, so the lists of a smaller p are among those of a larger."""
        c = len(self.centroids)
        if p == "all" or int(p) >= c:
            return self.ordinals.astype(np.int64), 0
        gaps = ((self.centroids.astype(np.float64) - q) ** 2).sum(axis=1)
        lists = np.lexsort((np.arange(c), gaps))[: int(p)]
        parts = [self.ordinals[self.offsets[i] : self.offsets[i + 1]] for i in lists]
        return (np.concatenate(parts).astype(np.int64) if parts else np.zeros(0, np.int64)), c


def build(x: np.ndarray, c: int | None = None, pq: int | None = None, **training) -> Index:
    """Index of a file's vectors; rows that hold a NaN (null vectors) are in no list. pq: parts of
    product codes to keep beside the lists."""
    there = np.flatnonzero(np.isfinite(x).all(axis=1))
    c = choose_c(len(there)) if c is None else min(c, len(there))
    centroids = train(x[there], c, **training)
    if not c:
        return Index(centroids.reshape(0, x.shape[1]), np.zeros(1, np.uint32), np.zeros(0, np.uint32))
    own = assign(x[there], centroids)
    offsets, order = invert(own, c)
    index = Index(centroids, offsets, there[order].astype(np.uint32))
    if pq:
        parts = (x[there] - centroids[own]).reshape(len(there), pq, -1)
        size = min(256, len(there))
        index.codebook = np.zeros((pq, 256, parts.shape[2]), np.float32)
        index.codes = np.zeros((len(x), pq), np.uint8)
        for m in range(pq):
            index.codebook[m, :size] = train(parts[:, m], size, "lloyd", iters=6)
            index.codes[there, m] = assign(parts[:, m], index.codebook[m, :size])
    return index


def encode(index: Index) -> bytes:
    """Version 1: lists; version 2: lists and product codes."""
    c, d = index.centroids.shape
    body = index.centroids.astype("<f4").tobytes() + index.offsets.astype("<u4").tobytes() + index.ordinals.astype("<u4").tobytes()
    parts = 0
    if index.codes is not None:
        parts = index.codes.shape[1]
        body += index.codebook.astype("<f4").tobytes() + index.codes.tobytes()
    return _HEAD.pack(MAGIC, 2 if parts else 1, parts, d, c, len(index.ordinals)) + body + struct.pack("<I", zlib.crc32(body))


class CorruptIndex(ValueError):
    """The blob does not decode; the file is searched as if it had none."""


def decode(blob: bytes) -> Index:
    try:
        magic, version, parts, d, c, n = _HEAD.unpack_from(blob)
        body = blob[_HEAD.size : -4]
        (crc,) = struct.unpack_from("<I", blob, len(blob) - 4)
    except struct.error as e:
        raise CorruptIndex(str(e)) from e
    size = 4 * (c * d + c + 1 + n)
    if magic != MAGIC or version not in (1, 2) or crc != zlib.crc32(body) or len(body) < size or (version == 1) != (len(body) == size):
        raise CorruptIndex("wrong mark, version, size or checksum")
    flat = np.frombuffer(body, dtype="<u4", count=size // 4)
    index = Index(np.frombuffer(body, dtype="<f4", count=c * d).reshape(c, d), flat[c * d : c * d + c + 1], flat[c * d + c + 1 :])
    if version == 2:
        index.codebook = np.frombuffer(body, dtype="<f4", count=256 * d, offset=size).reshape(parts, 256, d // parts)
        index.codes = np.frombuffer(body, dtype=np.uint8, offset=size + 1024 * d).reshape(-1, parts)
    return index


def distances(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Exact distances, in double precision."""
    return np.sqrt(((x.astype(np.float64) - q) ** 2).sum(axis=1))
