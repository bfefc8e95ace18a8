"""Search against brute force over layouts, gates and predicates; tables, joins, streams."""

import random

import pytest
from pyspark.sql import functions as F

from prunedknn import storage, workloads
from prunedknn.functions.vectors import l2_distance, literal
from prunedknn.manifest import Conflict, RowCountChanged, Table
from prunedknn.operators import build, cost, joins, layout, search, warm
from prunedknn.plans import prune, rewrite
from prunedknn.plans.pred import parse
from prunedknn.schema import DimensionMismatch, VectorSpec

SPEC = workloads.SPEC
PREDICATES = [
    "label = 3", "label <> 3", "lang = 'de' and n_chars > 300", "label in (1, 2) and not lang = 'en'", "n_chars between 100 and 400",
    "lang like 'e%'", "not (label < 5 or lang = 'fr')", "vec_id = 7", "n_chars % 2 = 0", "label is null", "label = 99", "source in ('src0', 'src1')",
]


@pytest.fixture(scope="module")
def fact(spark, sf):
    return storage.written(workloads.docs(spark, sf), "fact")


def truth(fact, q, k, where=None):
    df = fact.where(where) if where else fact
    rows = df.select("vec_id", l2_distance(F.col("embedding"), literal(q)).alias("d")).orderBy("d", "vec_id").limit(k).collect()
    return [(r["vec_id"], round(r["d"], 6)) for r in rows]


def got(found):
    return [(r["vec_id"], round(r["dist"], 6)) for r in found.rows.collect()]


@pytest.fixture(scope="module")
def tables(spark, fact):
    full = dict(filters=["n_chars", "label", "vec_id"], presence=["lang", "label", "source"], bloom=["vec_id"])
    out = {}
    for kind, cols in (("uniform", []), ("clustered", ["label"]), ("sorted", ["lang"]), ("zorder", ["n_chars", "customer_id"])):
        t = layout.write(fact, storage.scratch(spark, kind), SPEC, kind, files=4, cols=cols, **full)
        out[kind] = build.create_index(t).table
    return out


def test_same_rows_for_every_layout_and_predicate(tables, fact, spark, sf):
    q = workloads.query_vector(spark, sf)
    rng = random.Random(3)
    for where in PREDICATES:
        kind = rng.choice(list(tables))
        gate = rng.choice(["rows", "pure"])
        found = search.knn(tables[kind], q, 5, where, nprobe="all", gate=gate, overfetch=200)
        assert got(found) == truth(fact, q, 5, where), (where, kind, gate)


def test_verdicts_are_safe(tables, fact, spark):
    """No file with a match is dropped; a file judged "all" has no row that fails."""
    for kind, t in tables.items():
        for where in PREDICATES:
            pred = parse(where, t.schema(), spark)
            kept = {r["file"]: r["verdict"] for r in prune.survivors(t.manifest(), pred).collect()}
            real = spark.read.parquet(*t.files()).groupBy(F.col("_metadata.file_path").alias("f")).agg(
                F.count_if(F.expr(where)).alias("hit"), F.count("*").alias("n")
            ).collect()
            for r in real:
                assert r["hit"] == 0 or r["f"] in kept, (kind, where)
                assert kept.get(r["f"]) != "all" or r["hit"] == r["n"], (kind, where)


def test_value_local_prunes_and_uniform_does_not(tables, spark):
    pred = parse("label = 3", tables["clustered"].schema(), spark)
    _, local = prune.plan_survivors(tables["clustered"], pred)
    _, even = prune.plan_survivors(tables["uniform"], pred)
    assert local.files_surviving == 1 and even.files_surviving == even.files_total


def test_edges(tables, fact, spark, sf):
    q = workloads.query_vector(spark, sf)
    t = tables["uniform"]
    assert len(got(search.knn(t, q, 10_000, nprobe="all"))) == fact.count()
    assert got(search.knn(t, q, 0)) == []
    assert search.knn(t, q, 3, "label = 99").reasons == ["no_survivors"]
    with pytest.raises(DimensionMismatch):
        search.knn(t, q[:-1], 3)
    found = search.knn(t, q, 5, "vec_id in (1, 2, 3)", nprobe=1)
    assert len(got(found)) == 3 and found.metrics()["fallback"] >= 0


def test_nulls_and_ties(spark):
    rows = [(i, [float(i % 3), 0.0] if i % 5 else None, None if i % 2 else i) for i in range(40)]
    df = spark.createDataFrame(rows, "vec_id long, v array<float>, a int")
    t = build.create_index(layout.write(df, storage.scratch(spark, "nulls"), VectorSpec("v", 2), "uniform", files=3, filters=["a"])).table
    ids = [r["vec_id"] for r in search.knn(t, [0.0, 0.0], 6, "a >= 0", nprobe="all").rows.collect()]
    want = sorted(((float(v[0]), i) for i, v, a in rows if v and a is not None))[:6]
    assert ids == [i for _, i in want]


def test_empty_table(spark):
    df = spark.createDataFrame([], "vec_id long, v array<float>, a int")
    t = build.create_index(layout.write(df, storage.scratch(spark, "empty"), VectorSpec("v", 2), "uniform", files=2, filters=["a"])).table
    assert search.knn(t, [0.0, 0.0], 3).rows.collect() == []


def test_wrong_dimension_in_the_data_is_an_error(spark):
    df = spark.createDataFrame([(1, [1.0, 2.0, 3.0])], "vec_id long, v array<float>")
    with pytest.raises(Exception, match="dimension"):
        layout.write(df, storage.scratch(spark, "dim"), VectorSpec("v", 2))


def test_a_corrupt_file_is_reported_and_searched_whole(spark, fact, sf):
    t = layout.write(fact, storage.scratch(spark, "broken"), SPEC, "uniform", files=3, filters=["vec_id"])
    report = build.create_index(t, algo="none of these")  # every file's task fails, the build does not
    assert report.failed == 3 and report.table.manifest().where("indexed").count() == 0
    q = workloads.query_vector(spark, sf)
    assert got(search.knn(report.table, q, 5)) == truth(fact, q, 5)
    fixed = build.fill_gaps(report.table)
    assert fixed.failed == 0 and fixed.table.manifest().where("not indexed").count() == 0


def test_commits(spark, fact):
    t = layout.write(fact, storage.scratch(spark, "commit"), SPEC, "uniform", files=2, filters=["vec_id"])
    m = t.manifest()
    with pytest.raises(RowCountChanged):
        t.commit_replace(m.limit(1), 0)
    newer = t.commit_replace(m, 0)
    with pytest.raises(Conflict):
        t.commit_replace(m, 0)
    grown = newer.append(fact.limit(5))
    assert grown.read().count() == fact.count() + 5 and grown.at(0).read().count() == fact.count()
    assert grown.expire(1) == 0 and grown.snapshots() == [2]
    assert layout.double(grown).read().count() == 2 * (fact.count() + 5)


def test_policy_holds_on_every_path(tables, spark, sf):
    q = workloads.query_vector(spark, sf)
    view = tables["uniform"].with_policy("lang = 'en'")
    for found in (search.knn(view, q, 20, None, ["lang"]), search.fallback(view, q, 20, None, ["lang"]), search.knn_batch(view, [(1, q), (2, q)], 5, None, ["lang"])):
        assert {r["lang"] for r in found.rows.collect()} == {"en"}
    waves = search.by_waves(view, q, 20, nprobe="all").rows.collect()
    english = search.knn(view, q, 20, None, nprobe="all").rows.collect()
    assert [(r["file"], r["ord"]) for r in waves] == [(r["file"], r["ord"]) for r in english]
    with pytest.raises(ValueError):
        layout.double(view)


def test_a_filter_that_is_not_pushed_still_fills_k(tables, spark, sf):
    q = workloads.query_vector(spark, sf)
    far = search.fallback(tables["uniform"], q, 500, None, ["label"]).rows.collect()[-3:]  # beyond any short list
    where = f"vec_id * 1 in ({', '.join(str(r['vec_id']) for r in far)})"
    found = search.knn(tables["uniform"], q, 3, where, ["label"], overfetch=1, nprobe="all")
    assert {r["vec_id"] for r in found.rows.collect()} == {r["vec_id"] for r in far}


def test_many_keys_reduce_files(tables, spark, sf):
    q = workloads.query_vector(spark, sf)
    spec = joins.JoinSpec(workloads.customers(spark, sf), "customer_id", "region = 'EUROPE'")
    got = [joins.knn_join(tables["uniform"], spec, q, 10, attrs=["region"], nprobe="all", max_keys=m) for m in (10_000, 2)]
    assert [g.path for g in got] == ["reduced", "join_then_rank"] and got[1].reasons == ["too_many_keys", "files_reduced"]
    rows = [[(r["vec_id"], round(r["dist"], 9)) for r in g.rows.collect()] for g in got]
    assert rows[0] == rows[1]


def test_a_streamed_batch_is_one_commit(spark, sf):
    from prunedknn.streaming.ingest import Sink

    e = workloads.table(spark, sf, "embeddings")
    t = layout.write(e.limit(0), storage.scratch(spark, "one-commit"), workloads.SPEC, "uniform", files=1, filters=["vec_id"])
    sink = Sink(t, index_every=100)
    for batch_id in (0, 0, 1):
        sink(e.where(F.col("vec_id") % 2 == batch_id), batch_id)
    assert sink.table.snapshots() == [0, 1, 2] and sink.table.meta()["batches"] == [0, 1] and sink.table.read().count() == e.count()


def test_rewrite_matches_and_refuses(tables, spark, sf):
    q = ", ".join(f"{x:.6f}" for x in workloads.query_vector(spark, sf))
    d = f"l2_distance(embedding, array({q}))"
    views = {"facts": tables["clustered"]}
    run = lambda text: rewrite.sql(spark, text, views)
    assert run(f"SELECT vec_id, {d} AS d FROM facts WHERE label = 3 ORDER BY d LIMIT 4").path == "ivf"
    assert run(f"SELECT vec_id FROM facts ORDER BY {d} LIMIT 4").path == "ivf"
    assert run(f"SELECT vec_id FROM facts ORDER BY {d} DESC LIMIT 4").reason == "descending"
    assert run(f"SELECT vec_id FROM facts ORDER BY {d}").reason == "no_limit"
    assert run("SELECT vec_id FROM facts ORDER BY n_chars LIMIT 4").path == "plain"
    assert run(f"SELECT label, min({d}) AS d FROM facts GROUP BY label ORDER BY d LIMIT 4").path == "plain"
    assert run("SELECT vec_id FROM facts LIMIT 4").reason == "no_order"
    with pytest.raises(DimensionMismatch):
        run("SELECT vec_id FROM facts ORDER BY l2_distance(embedding, array(1.0, 2.0)) LIMIT 4")


def test_joins_agree(tables, fact, spark, sf):
    q, dim = workloads.query_vector(spark, sf), workloads.customers(spark, sf)
    spec = joins.JoinSpec(dim, "customer_id", "region = 'ASIA'")
    key = lambda j: [(r["vec_id"], round(r["dist"], 6)) for r in j.rows.collect()]
    ways = [joins.knn_join(tables["uniform"], spec, q, 5, nprobe="all", **o) for o in ({}, {"mode": "join"}, {"max_keys": 2}, {"mode": "sweep", "join_overfetch": 50})]
    assert len({str(key(w)) for w in ways}) == 1 and [w.path for w in ways] == ["reduced", "join_then_rank", "join_then_rank", "sweep"]
    repeated = joins.JoinSpec(dim.unionByName(dim), "customer_id", "region = 'ASIA'")
    assert joins.knn_join(tables["uniform"], repeated, q, 5, attrs=["region"]).reasons == ["dimension_keys_repeat"]
    assert joins.knn_join(tables["uniform"], joins.JoinSpec(dim, "customer_id", how="left"), q, 5).path == "exact_join"


def test_placement(spark):
    files = spark.range(200).select(F.concat(F.lit("f"), "id").alias("file"))
    assert warm.moved_fraction(files, 11, 12) <= 1.7 / 12 < 0.5 < warm.moved_fraction(files, 11, 12, "rr")


def test_lru():
    class E:
        nbytes = 10

    lru = warm.Lru(25)
    for key in "aba":
        lru.get(key, E)
    assert (lru.hits, lru.misses) == (1, 2)
    lru.get("c", E)
    assert lru.evictions == 1 and "b" not in lru.held and "a" in lru.held


def test_cost_trace():
    c = cost.predict(11_534_160, 444, 1024, 10, 89 / 444)
    assert round(c.files) == 89 and 22_000 < c.candidates < 23_500 and round(c.centroids) == 91_136
    assert 100 < c.reduction_with_centroids < 103


def test_async_build_and_warm_blocks(spark, fact, sf):
    t = layout.write(fact, storage.scratch(spark, "async"), SPEC, "uniform", files=2, filters=["label"])
    t = build.create_index_async(t).result(120).table
    q = workloads.query_vector(spark, sf)
    ws = warm.WarmSet(t, columns=("label",))
    found = search.knn(t, q, 5, "label = 3", ["lang"], warm=ws, nprobe="all")
    assert got(found) == truth(fact, q, 5, "label = 3") and found.metrics()["hits"] == 2
    ws.unload()


def test_open_by_path_is_the_same_table(tables, spark):
    assert Table(spark, tables["uniform"].path).files() == tables["uniform"].files()
