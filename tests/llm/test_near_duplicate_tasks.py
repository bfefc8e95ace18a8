"""Near duplicates between its steps: tables are written by a task for so many rows, links are joined up where they are read."""

import random

import pytest

from prunedknn.llm import minhash_bbit
from tests.llm.test_near_duplicate_shuffles import family
from tests.llm.test_operators import plain_components


def test_small_tables_are_written_by_few_tasks(spark, monkeypatch):
    rows, files, rounds = family(60), {}, []
    written = minhash_bbit.written

    def noted(df, tag):
        out = written(df, tag)
        files[tag] = max(files.get(tag, 0), len(out.inputFiles()))
        rounds.append(tag)
        return out

    monkeypatch.setattr(minhash_bbit, "written", noted)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    many = {"spark.sql.shuffle.partitions": "40", "spark.sql.adaptive.coalescePartitions.enabled": "false"}
    before = {k: spark.conf.get(k) for k in many}
    try:
        for k, v in many.items():
            spark.conf.set(k, v)
        got = sorted((str(r["doc_id"]), r["n_shingles"], str(r["component_id"])) for r in minhash_bbit.near_duplicates(df, 2, 80).collect())
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    assert got == plain_components(rows, 2, 80)
    in_blocks = {"minhash-stars", "minhash-cross", "minhash-stars-dealt", "minhash-cross-dealt"}
    assert max(n for tag, n in files.items() if tag not in in_blocks) == 1
    assert rounds.count("minhash-round") == 2  # the links before and after canopies are searched


def plain(links):
    root = {x: x for link in links for x in link}
    changed = True
    while changed:
        changed = False
        for a, b in links:
            m = min(root[a], root[b])
            changed |= root[a] != m or root[b] != m
            root[a] = root[b] = m
    return sorted(x for x in root.items() if any(a != b and x[0] in (a, b) for a, b in links))


@pytest.mark.parametrize("held", [1 << 20, 3, 40])
def test_components_of_links_in_many_tasks(spark, monkeypatch, held):
    rng = random.Random(held)
    monkeypatch.setattr(minhash_bbit, "HELD_LINKS", held)
    chain = [(i, i + 1) for i in range(1000, 1060)]
    star = [(2000 + i, 2500) for i in range(50)]
    loose = [(rng.randint(0, 99), rng.randint(0, 99)) for _ in range(60)] + [(-5, 1 << 60), (7, 7), (3000, 3000)]
    links = chain + star + loose + chain[:5]
    rng.shuffle(links)
    df = spark.createDataFrame(links, "a long, b long").repartition(9)
    got = sorted((r["node"], r["component"]) for r in minhash_bbit.components(minhash_bbit.written(df, "test-links"), "test-round").collect())
    assert got == plain(links)


def test_no_links(spark):
    assert minhash_bbit.components(spark.createDataFrame([], "a long, b long"), "test-round").isEmpty()
