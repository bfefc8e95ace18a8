"""Index, codec, footer and schema, without Spark where none is needed."""

import decimal

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from prunedknn import footer, ivf
from prunedknn.schema import DimensionMismatch, VectorSpec, coerce_query


def rows(n=300, d=8, seed=1):
    return np.random.default_rng(seed).normal(size=(n, d)).astype(np.float32)


@pytest.mark.parametrize("n,c", [(26_000, 1024), (34_000, 1024), (62, 32), (1, 1), (2, 2), (0, 0)])
def test_number_of_centroids(n, c):
    assert ivf.choose_c(n) == c


@pytest.mark.parametrize("algo", ["minibatch", "lloyd", "seed"])
def test_round_trip_and_probe_order(algo):
    x = rows()
    index = ivf.decode(ivf.encode(ivf.build(x, 16, algo=algo)))
    assert sorted(index.ordinals.tolist()) == list(range(len(x)))
    sets = [set(index.probe(x[0].astype(float), p)[0].tolist()) for p in (1, 2, 4, 8, 16)]
    assert all(a <= b for a, b in zip(sets, sets[1:]))
    assert sets[-1] == set(range(len(x)))


def test_null_vectors_are_in_no_list():
    x = rows(50)
    x[7] = np.nan
    assert 7 not in ivf.build(x).ordinals.tolist()


def test_corrupt_blob_is_refused():
    blob = bytearray(ivf.encode(ivf.build(rows())))
    blob[40] ^= 1
    with pytest.raises(ivf.CorruptIndex):
        ivf.decode(bytes(blob))
    with pytest.raises(ivf.CorruptIndex):
        ivf.decode(b"short")


@pytest.mark.parametrize("entries", [0, 1, 14, 15, 40])
def test_footer_keeps_the_table(tmp_path, entries):
    table = pa.table({"id": list(range(100)), "s": [str(i) for i in range(100)]})
    table = table.replace_schema_metadata({f"k{i}": "v" * i for i in range(entries)} or None)
    src, one, two = (str(tmp_path / n) for n in ("a.parquet", "b.parquet", "c.parquet"))
    pq.write_table(table, src)
    footer.embed(src, one, b"first blob")
    out = footer.embed(one, two, b"second")
    assert footer.read_blob(one) == b"first blob" and footer.read_blob(two) == b"second"
    assert pq.read_table(two).equals(table)
    raw, old = open(one, "rb").read(), open(src, "rb").read()
    size = int.from_bytes(old[-8:-4], "little")
    assert raw[: len(old) - 8 - size] == old[: len(old) - 8 - size]
    assert out["bytes"] == len(open(two, "rb").read())
    assert [k for k in pq.read_metadata(two).metadata if k == footer.KEY.encode()] == [footer.KEY.encode()]


def test_query_is_checked():
    spec = VectorSpec("v", 3)
    assert coerce_query([decimal.Decimal("1.5"), 2, 3.0], spec) == [1.5, 2.0, 3.0]
    for bad in ([1, 2], None, [], [1, 2, float("nan")], [1, 2, float("inf")]):
        with pytest.raises(DimensionMismatch):
            coerce_query(bad, spec)


@settings(max_examples=30, deadline=None)
@given(st.integers(1, 60), st.integers(1, 6), st.integers(0, 5))
def test_every_row_is_listed_once(n, d, seed):
    x = np.round(rows(n, d, seed), 1)
    index = ivf.build(x, algo="lloyd", iters=3)
    assert sorted(index.ordinals.tolist()) == list(range(n))
    got, _ = index.probe(x[0].astype(float), "all")
    assert sorted(got.tolist()) == list(range(n))
