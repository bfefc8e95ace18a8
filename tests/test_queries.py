"""Registered queries against DuckDB on the smallest tables."""

import sys
from collections import Counter
from pathlib import Path

import duckdb
import pytest

sys.path.insert(0, str(Path(__file__).parent.parent))
from prunedknn import oracles

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Slower ones are left to the driver's own comparison.
CHOSEN = [n for n in oracles.ORACLE_SQL if n not in ("knn_ablation", "op_stream_ingest", "selectivity_sweep", "recall_at_k")]


def same(rows, columns, other, other_columns):
    order = sorted(columns)
    assert sorted(other_columns) == order
    norm = lambda v: round(v, 9) if isinstance(v, float) else v
    a = Counter(tuple(norm(r[c]) for c in order) for r in rows)
    b = Counter(tuple(norm(r[other_columns.index(c)]) for c in order) for r in other)
    assert a == b


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", CHOSEN)
def test_equals_sql(name, spark, sf, duck):
    df = oracles.QUERIES[name](spark, sf)
    cursor = duck.execute(oracles.ORACLE_SQL[name])
    columns = [c[0] for c in cursor.description]
    same(df.collect(), df.columns, cursor.fetchall(), columns)


def test_recall_rises_with_probes(spark, sf):
    rows = oracles.QUERIES["recall_probe_sweep"](spark, sf).collect()
    means = [r["mean_recall"] for r in rows]
    assert means == sorted(means) and means[-1] == 1.0


def test_warm_workloads(spark, sf):
    from prunedknn import workloads

    own = {r["setting"]: r for r in workloads.warm_latency(spark, sf, count=40, timed=2, repeats=1).collect()}
    assert set(own) == {"ivf", "brute", "brute_cold"} and all(r["queries"] == 40 and r["p50"] <= r["p99"] for r in own.values())
    assert own["brute"]["least_recall"] == 1.0 and own["ivf"]["mean_recall"] >= 0.95 and own["ivf"]["least_recall"] >= 0.9
    steps = {r["setting"]: r for r in workloads.warm_ablation(spark, sf, count=3, repeats=1).collect()}
    assert steps["read"]["files_held"] == 0 and all(steps[s]["files_held"] == 8 for s in ("held", "placed", "stable"))
    assert steps["placed"]["moved_by_one_slot"] < steps["held"]["moved_by_one_slot"]
    assert len({r["mean_recall"] for r in steps.values()}) == 1  # what is held changes no row


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0 and set(e.oracle_sql()) <= set(e.queries())
