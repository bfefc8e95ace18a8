"""The experiments on the given tables: one query each, with DuckDB SQL beside it where SQL can say it."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import footer, ivf, storage
from .functions import vectors as V
from .manifest import Table
from .operators import baselines, build, cost, joins, layout, measures, search, warm
from .plans.prune import plan_survivors
from .schema import VectorSpec

DIM, K, Q_ID = 64, 10, 7
SPEC = VectorSpec("embedding", DIM)
#: The clustered corpus: rows made of each given vector, and how many centres they lie around.
LATENT_ROWS, LATENT_CENTRES = 8, 40
_TABLES: dict[tuple, Table] = {}


def table(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def customers(spark: SparkSession, sf: str) -> DataFrame:
    """customer_id, segment, nation, region: the dimension, three tables deep."""
    c, n, r = (table(spark, sf, t) for t in ("customer", "nation", "region"))
    return (
        c.join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
        .select(F.col("c_custkey").alias("customer_id"), F.col("c_mktsegment").alias("segment"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))
    )


def docs(spark: SparkSession, sf: str, text: bool = False) -> DataFrame:
    """The fact: vector, scalar columns, a join key."""
    e, d = table(spark, sf, "embeddings"), table(spark, sf, "documents")
    n = table(spark, sf, "customer").count()
    keep = ["vec_id", "embedding", "label", "lang", "source", "n_chars", *(["text"] if text else [])]
    return e.join(d, e.vec_id == d.doc_id).select(*keep).withColumn("customer_id", F.col("vec_id") % n)


def latent(spark: SparkSession, sf: str, n: int, m: int, a: float = 0.8, b: float = 0.4) -> DataFrame:
    """n rows around m centres, made from the given vectors by integer arithmetic and joins."""
    e = table(spark, sf, "embeddings")
    rows = e.count()
    byrank = storage.numbered(e.select("vec_id", F.col("embedding").cast("array<double>").alias("v")), "vec_id", "r").select("r", "v")
    byrank = storage.written(byrank, "latent-base")
    i = F.col("id")
    ids = spark.range(n).select(
        "id", (i % m).alias("r1"), ((i * 7919 + 13) % rows).alias("r2"), ((i * 104729 + 7 + F.floor(i / rows)) % rows).alias("r3")
    )
    for k in (1, 2, 3):
        ids = ids.join(byrank.select(F.col("r").alias(f"r{k}"), F.col("v").alias(f"v{k}")), f"r{k}")
    mixed = F.zip_with(F.zip_with("v1", "v2", lambda x, y: x + F.lit(a) * y), "v3", lambda x, y: x + F.lit(b) * y)
    return ids.select(
        "id", mixed.cast("array<float>").alias("embedding"), F.concat(F.lit("c"), ((i % m) % 5).cast("string")).alias("category"),
    )


def query_vector(spark: SparkSession, sf: str, vec_id: int = Q_ID) -> list[float]:
    return table(spark, sf, "embeddings").where(F.col("vec_id") == vec_id).first()["embedding"]


def indexed(spark: SparkSession, sf: str, name: str) -> Table:
    """The tables that queries share, made once a session."""
    key = (spark.sparkContext.applicationId, sf, name)
    if key in _TABLES:
        return _TABLES[key]
    path = lambda: storage.scratch(spark, f"table-{name}")
    spread = F.col("vec_id") % 8
    full = dict(filters=["n_chars", "vec_id", "label"], presence=["lang", "label", "source"], bloom=["customer_id"])
    if name == "uniform":
        made = layout.write(docs(spark, sf), path(), SPEC, "uniform", file_number=spread, key=["vec_id"], **full)
    elif name == "value_local":
        made = layout.write(docs(spark, sf), path(), SPEC, "clustered", cols=["label"], key=["vec_id"], **full)
    elif name == "sorted":
        made = layout.write(docs(spark, sf), path(), SPEC, "sorted", files=7, cols=["lang", "vec_id"], **full)
    elif name == "by_length":
        made = layout.write(docs(spark, sf), path(), SPEC, "sorted", files=8, cols=["n_chars"], **full)
    elif name == "region":
        spec = joins.JoinSpec(customers(spark, sf), "customer_id")
        made = joins.materialize(docs(spark, sf), spec, ["region"], path(), SPEC, **full)
    elif name == "wide":
        made = layout.write(docs(spark, sf, text=True), path(), SPEC, "uniform", file_number=spread, key=["vec_id"])
    elif name == "scattered":
        many = docs(spark, sf).select("*", F.explode(F.sequence(F.lit(0), F.lit(16))).alias("f"))
        many = many.withColumnRenamed("f", "copy")
        made = layout.write(many, path(), SPEC, "scattered", files=17, file_number=F.col("copy"), presence=["customer_id"], filters=["vec_id"])
    elif name == "seed":
        made = layout.write(table(spark, sf, "embeddings"), path(), SPEC, "uniform", file_number=spread, key=["vec_id"], filters=["vec_id"])
        made = build.create_index(made, c=16, algo="seed").table
    else:
        raise KeyError(name)
    if name not in ("seed", "scattered"):
        made = build.create_index(made).table
    _TABLES[key] = made
    return made


def _out(found, *keep: str) -> DataFrame:
    rows = found.rows if hasattr(found, "rows") else found
    return rows.select(*keep, F.round("dist", 6).alias("dist"))


# --- exact search -------------------------------------------------------------------------------


def knn_brute(spark, sf):
    return _out(baselines.brute(table(spark, sf, "embeddings"), "embedding", query_vector(spark, sf), K), "vec_id")


def knn_brute_arrow(spark, sf):
    return _out(baselines.brute(table(spark, sf, "embeddings"), "embedding", query_vector(spark, sf), K, arrow=True), "vec_id")


def knn_ivf_full_probe(spark, sf):
    return _out(search.knn(indexed(spark, sf, "uniform"), query_vector(spark, sf), K, nprobe="all"), "vec_id")


def knn_ivf_seed_probe(spark, sf):
    return _out(search.knn(indexed(spark, sf, "seed"), query_vector(spark, sf), K, nprobe=4), "vec_id")


def _filtered(name, where, **options):
    def run(spark, sf):
        return _out(search.knn(indexed(spark, sf, name), query_vector(spark, sf), K, where, ["label", "lang"], nprobe="all", **options), "vec_id", "label", "lang")

    return run


def knn_sorted_boundary(spark, sf):
    """A sorted column prunes but is not pure: the gate refuses to push, the result is the same."""
    found = search.escalate(indexed(spark, sf, "sorted"), query_vector(spark, sf), K, "lang = 'fr'", project=["lang"], gate="pure", nprobe="all")
    return _out(found, "vec_id", "lang")


def knn_postfilter(spark, sf):
    rows = baselines.postfilter(indexed(spark, sf, "uniform"), query_vector(spark, sf), K, "label = 3", overfetch=2, nprobe="all")
    return _out(rows, "vec_id", "label")


def knn_policy(spark, sf):
    view = indexed(spark, sf, "uniform").with_policy("lang = 'en'")
    return _out(search.knn(view, query_vector(spark, sf), K, "label = 2", ["lang"], nprobe="all"), "vec_id", "lang")


def knn_mixed_files(spark, sf):
    """A file appended after the build has no index and is searched whole in the same step."""
    base = indexed(spark, sf, "uniform")
    q = query_vector(spark, sf)
    near = docs(spark, sf).where(F.col("vec_id") == Q_ID).withColumn("vec_id", F.lit(-1).cast("bigint"))
    copy = Table(spark, storage.qualified(spark, storage.scratch(spark, "mixed")))
    kept = {k: v for k, v in base.meta().items() if k not in ("manifest", "parent")}
    mixed = copy.commit(base.manifest(), None, **kept).append(near)
    return _out(search.knn(mixed, q, K, None, nprobe="all"), "vec_id")


def knn_wide_lookup(spark, sf):
    found = search.knn(indexed(spark, sf, "wide"), query_vector(spark, sf), K, None, ["text"], wide=["text"], nprobe="all")
    return found.rows.select("vec_id", F.md5("text").alias("text_md5"), F.round("dist", 6).alias("dist"))


def knn_wide_inline(spark, sf):
    """The contrast: the payload rides on the candidate path."""
    found = search.knn(indexed(spark, sf, "wide"), query_vector(spark, sf), K, None, ["text"], nprobe="all")
    return found.rows.select("vec_id", F.md5("text").alias("text_md5"), F.round("dist", 6).alias("dist"))


def _queries(spark, sf):
    rows = table(spark, sf, "embeddings").where("vec_id % 20 = 0").select("vec_id", "embedding").orderBy("vec_id").collect()
    return [(r["vec_id"], r["embedding"]) for r in rows]


def knn_batch_topk(spark, sf):
    found = search.knn_batch(indexed(spark, sf, "uniform"), _queries(spark, sf), 5, nprobe="all")
    return found.rows.select("query_id", F.col("rank").cast("bigint").alias("rank"), "vec_id", F.round("dist", 6).alias("dist"))


def _seed_recalls(spark, sf):
    found = search.knn_batch(indexed(spark, sf, "seed"), _queries(spark, sf), K, nprobe=4).rows
    return measures.recall_at_k(found.withColumnRenamed("vec_id", "id"), _truth(spark, sf), K)


def _truth(spark, sf, where: str = "true"):
    e = table(spark, sf, "embeddings")
    queries = e.where("vec_id % 20 = 0").select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec"))
    return baselines.brute_batch(e.where(where), "embedding", queries, K, "vec_id")


def recall_at_k(spark, sf):
    return _seed_recalls(spark, sf).select("query_id", F.round("recall", 6).alias("recall"))


def recall_bins(spark, sf):
    """How many queries lie in each tenth of recall."""
    return measures.recall_histogram(_seed_recalls(spark, sf))


def _by_selectivity(spark, sf):
    """Searches of 4 lists of 16 a file, k rows a file and no more, under filters that leave a tenth up to all:
    where the lists hold too few, the whole file is masked instead."""
    t, queries = indexed(spark, sf, "seed"), _queries(spark, sf)
    for below in (1, 2, 4, 7, 10):
        yield below, search.knn_batch(t, queries, K, f"label < {below}", ["label"], nprobe=4, overfetch=1)


def recall_by_selectivity(spark, sf):
    out = None
    for below, found in _by_selectivity(spark, sf):
        rows = measures.recall_at_k(found.rows.withColumnRenamed("vec_id", "id"), _truth(spark, sf, f"label < {below}"), K)
        rows = rows.select(F.lit(below).cast("bigint").alias("below"), "query_id", F.round("recall", 6).alias("recall"))
        out = rows if out is None else out.unionByName(rows)
    return out


def work_by_selectivity(spark, sf):
    """Rows scored, centroid distances and files searched whole, over all queries."""
    rows = []
    for below, found in _by_selectivity(spark, sf):
        m = found.metrics()
        rows.append((below, *(int(m[c]) for c in ("candidates", "centroids", "rows_in_file", "fallback"))))
    return spark.createDataFrame(rows, "below long, candidates long, centroids long, rows_in_files long, whole_files long")


def knn_ablation(spark, sf):
    """Every warm-set and assembly setting gives the same rows."""
    t, q, out = indexed(spark, sf, "value_local"), query_vector(spark, sf), None
    settings = {
        "cold": {}, "rr": {"place": "rr"}, "block": {"warm": warm.WarmSet(t, "block", ("label",))}, "node": {"warm": warm.WarmSet(t, "node")},
        "rescan": {"assemble": "rescan"}, "rescore": {"gate": "none", "residual": "rescore"},
    }
    for name, options in settings.items():
        rows = _out(search.knn(t, q, K, "label = 3", nprobe="all", **options), "vec_id").select(F.lit(name).alias("setting"), "vec_id", "dist")
        out = rows if out is None else out.unionByName(rows)
    return out


def knn_sql_rewrite(spark, sf):
    from .plans import rewrite

    q = ", ".join(f"{float(x):.9g}" for x in query_vector(spark, sf))
    text = f"SELECT vec_id, label, l2_distance(embedding, array({q})) AS d FROM facts WHERE label IN (2, 5) ORDER BY d LIMIT {K}"
    got = rewrite.sql(spark, text, {"facts": indexed(spark, sf, "value_local")}, nprobe="all")
    return got.df.select("vec_id", "label", F.round("d", 6).alias("dist"), F.lit(got.path).alias("path"))


def knn_by_waves(spark, sf):
    t, q = indexed(spark, sf, "uniform"), query_vector(spark, sf)
    found = search.by_waves(t, q, K, nprobe="all").rows
    ids = t.spark.read.parquet(*t.files()).select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("ord"), "vec_id")
    return _out(found.join(ids, ["file", "ord"]), "vec_id")


def selectivity_sweep(spark, sf):
    t, q, out = indexed(spark, sf, "by_length"), query_vector(spark, sf), None
    for limit in (200, 500, 1000, 2000, 5000, 100000):
        rows = _out(search.knn(t, q, 5, f"n_chars < {limit}", ["n_chars"], nprobe="all"), "vec_id", "n_chars")
        rows = rows.select(F.lit(limit).cast("bigint").alias("below"), "vec_id", "n_chars", "dist")
        out = rows if out is None else out.unionByName(rows)
    return out


# --- joins --------------------------------------------------------------------------------------


def _join(**how):
    def run(spark, sf):
        spec = joins.JoinSpec(customers(spark, sf), "customer_id", "region = 'EUROPE'")
        got = joins.knn_join(indexed(spark, sf, "uniform"), spec, query_vector(spark, sf), K, attrs=["region"], nprobe="all", **how)
        return _out(got, "vec_id", "region")

    return run


def join_materialized_region(spark, sf):
    found = search.knn(indexed(spark, sf, "region"), query_vector(spark, sf), K, "region = 'EUROPE'", ["region"], nprobe="all")
    return _out(found, "vec_id", "region")


def join_refreshed_region(spark, sf):
    """Half of a region's customers move: the materialised table is stale and is made anew, as it isn't when none move."""
    made_with, spec, attrs = customers(spark, sf), joins.JoinSpec(customers(spark, sf), "customer_id"), ["region"]
    old, facts, path = indexed(spark, sf, "region"), docs(spark, sf), storage.scratch(spark, "refreshed")
    kept = joins.refresh(old, facts, spec, attrs, made_with, path)
    moving = (F.col("region") == "EUROPE") & (F.col("customer_id") % 2 == 0)
    moved = made_with.withColumn("region", F.when(moving, F.lit("NORTH")).otherwise(F.col("region")))
    new = joins.refresh(kept, facts, joins.JoinSpec(moved, "customer_id"), attrs, made_with, path)
    found = search.knn(new, query_vector(spark, sf), K, "region = 'NORTH'", ["region"], nprobe="all")
    return _out(found, "vec_id", "region").withColumn("unchanged_kept", F.lit(kept is old))


def join_key_set(spark, sf):
    return joins.key_set(joins.JoinSpec(customers(spark, sf), "customer_id", "region = 'EUROPE'")).select(F.col("key").alias("customer_id"))


def join_snowflake_keys(spark, sf):
    chain = [(table(spark, sf, "customer"), "c_nationkey", "n_nationkey"), (table(spark, sf, "nation"), "n_regionkey", "r_regionkey"), (table(spark, sf, "region"), "", "")]
    return joins.snowflake(chain, "r_name = 'ASIA'").select("c_custkey")


def join_outer_fallback(spark, sf):
    spec = joins.JoinSpec(customers(spark, sf).where("segment = 'BUILDING'"), "customer_id", how="left")
    got = joins.knn_join(indexed(spark, sf, "uniform"), spec, query_vector(spark, sf), K, attrs=["segment"])
    return _out(got, "vec_id", "segment")


def join_file_reduction(spark, sf):
    """Files that a key set of any size can touch, by joins with presence lists and bloom bits."""
    t = indexed(spark, sf, "uniform")
    keys = spark.createDataFrame([(0,), (8,), (16,)], "key long")
    return joins.reduce_files(t, keys, "customer_id").agg(F.count("*").alias("files"))


# --- pruning, layouts, metadata -----------------------------------------------------------------


def prune_report_layouts(spark, sf):
    rows = []
    for name, where in (("uniform", "label = 3"), ("value_local", "label = 3"), ("region", "region = 'EUROPE'")):
        _, r = plan_survivors(*_pruned(spark, sf, name, where))
        rows.append((name, r.files_total, r.files_surviving, r.rows_total, r.rows_surviving))
    return spark.createDataFrame(rows, "layout string, files_total long, files_surviving long, rows_total long, rows_surviving long")


def _pruned(spark, sf, name, where):
    from .plans.pred import parse

    t = indexed(spark, sf, name)
    return t, parse(where, t.schema(), spark)


def scattered_prunes_nothing(spark, sf):
    _, r = plan_survivors(*_pruned(spark, sf, "scattered", "customer_id = 5"))
    return spark.createDataFrame([(r.files_total, r.files_total - r.files_surviving)], "files_total long, files_pruned long")


def locality_by_column(spark, sf):
    out = None
    for name in ("uniform", "value_local"):
        rows = layout.locality(indexed(spark, sf, name), "label").select(F.lit(name).alias("layout"), "value", "files_with", "files_total", F.round("prune_ratio", 6).alias("prune_ratio"))
        out = rows if out is None else out.unionByName(rows)
    return out


def zone_map_stats(spark, sf):
    s = F.col("stats")["n_chars"]
    return indexed(spark, sf, "uniform").manifest().select(s["lo"].alias("lo"), s["hi"].alias("hi"), s["nulls"].alias("nulls"), "rows")


def presence_index(spark, sf):
    m = indexed(spark, sf, "uniform").manifest()
    return m.select(F.col("stats")["vec_id"]["lo"].cast("bigint").alias("first_id"), F.explode(F.col("stats")["label"]["present"]).alias("value"))


def files_touched(spark, sf):
    from .plans.pred import Cmp

    t, rows = indexed(spark, sf, "by_length"), []
    for limit in (200, 1000, 5000):
        _, r = plan_survivors(t, Cmp("n_chars", "<", limit))
        rows.append((limit, r.files_total, r.files_surviving))
    return spark.createDataFrame(rows, "below long, files_total long, files_surviving long")


def files_touched_uniform(spark, sf):
    """The same where no file is short of any length: few limits prune."""
    from .plans.pred import Cmp

    t, rows = indexed(spark, sf, "uniform"), []
    for limit in (60, 100, 200, 1000):
        _, r = plan_survivors(t, Cmp("n_chars", "<", limit))
        rows.append((limit, r.files_total, r.files_surviving, r.rows_surviving))
    return spark.createDataFrame(rows, "below long, files_total long, files_surviving long, rows_surviving long")


def worked_trace(spark, sf):
    """444 files of about 26 thousand rows, 89 of which hold the value: metadata only."""
    stat = "struct<lo: double, hi: double, lo_text: string, hi_text: string, nulls: bigint, present: array<string>, bloom: array<bigint>, partition: boolean>"
    files = spark.range(444).select(
        F.concat(F.lit("f"), "id").alias("file"), F.lit(25_978).cast("bigint").alias("rows"), F.lit(1024).alias("centroids"),
        F.when(F.col("id") < 89, F.lit("tech")).otherwise(F.concat(F.lit("other"), (F.col("id") % 4).cast("string"))).alias("v"),
    ).select(
        "file", "rows", "centroids",
        F.create_map(F.lit("category"), F.struct(
            F.lit(None).cast("double").alias("lo"), F.lit(None).cast("double").alias("hi"), F.lit(None).cast("string").alias("lo_text"),
            F.lit(None).cast("string").alias("hi_text"), F.lit(0).cast("bigint").alias("nulls"), F.array("v").alias("present"),
            F.lit(None).cast("array<bigint>").alias("bloom"), F.lit(False).alias("partition")).cast(stat)).alias("stats"),
    )
    from .plans.pred import Cmp

    left = files.where(Cmp("category", "=", "tech").might())
    got = left.agg(F.count("*").alias("files"), F.sum("rows").alias("rows"), F.sum("centroids").alias("centroids")).first()
    c = cost.predict(444 * 25_978, 444, 1024, 10, got["files"] / 444)
    return spark.createDataFrame(
        [(444, 444 - got["files"], got["rows"], round(c.candidates), int(got["centroids"]), round(c.reduction, 1), round(c.reduction_with_centroids, 1))],
        "files long, pruned long, rows_left long, candidates long, centroid_distances long, reduction double, honest_reduction double",
    )


def cost_model_grid(spark, sf):
    rows = []
    for sigma in (0.01, 0.05, 0.1, 0.2, 0.5, 1.0):
        for c in (256, 1024, 4096):
            for p in (1, 10, 100):
                x = cost.predict(11_534_160, 444, c, p, sigma)
                rows.append((sigma, c, p, *(math.floor(v * 1e3 + 0.5) / 1e3 for v in (x.candidates, x.centroids, x.reduction, x.reduction_with_centroids))))
    return spark.createDataFrame(rows, "sigma double, c long, p long, candidates double, centroids double, reduction double, honest_reduction double")


def choose_centroids(spark, sf):
    rows = [(n, ivf.choose_c(n)) for n in (1, 2, 10, 62, 500, 1000, 4096, 26_000, 34_000, 125_000, 1_000_000)]
    return spark.createDataFrame(rows, "rows long, c long")


def placement_hrw(spark, sf):
    files = spark.range(444).select(F.concat(F.lit("part-"), F.lpad(F.col("id").cast("string"), 5, "0")).alias("file"))
    return warm.place(files, 11).select("file", F.col("slot").cast("bigint").alias("slot"))


def placement_moved(spark, sf):
    files = spark.range(444).select(F.concat(F.lit("part-"), F.lpad(F.col("id").cast("string"), 5, "0")).alias("file"))
    rows = [(kind, round(warm.moved_fraction(files, 11, 12, kind), 6)) for kind in ("hrw", "rr")]
    return spark.createDataFrame(rows, "kind string, moved double")


def table_doubling(spark, sf):
    t = layout.write(docs(spark, sf).select("vec_id", "embedding", "label"), storage.scratch(spark, "double"), SPEC, "uniform", files=2, filters=["vec_id"])
    return layout.double(t, 2).read().groupBy("label").agg(F.count("*").alias("n"))


def snapshot_replace(spark, sf):
    """The build's commit keeps every row, and the snapshot before it reads as before."""
    t = indexed(spark, sf, "uniform")
    rows = []
    for n in t.snapshots():
        m = t.at(n).manifest().agg(F.sum("rows").alias("rows"), F.count_if("indexed").alias("indexed"), F.count("*").alias("files")).first()
        rows.append((n, m["files"], m["rows"], m["indexed"]))
    return spark.createDataFrame(rows, "snapshot long, files long, rows long, indexed long")


def time_travel_diff(spark, sf):
    t = indexed(spark, sf, "uniform")
    old, new = (t.at(n).read().select("vec_id", "label", "lang", F.md5(F.col("embedding").cast("string")).alias("h")) for n in (0, 1))
    return spark.createDataFrame([(old.exceptAll(new).count(), new.exceptAll(old).count(), new.count())], "only_old long, only_new long, rows long")


def ivf_assignments(spark, sf):
    """Lengths of the posting lists of every file, out of the blobs in the files' tails."""
    t = indexed(spark, sf, "seed")
    files = t.manifest().select(F.col("stats")["vec_id"]["lo"].cast("bigint").alias("n"), "file")

    def lists(batches):
        import pyarrow as pa

        for batch in batches:
            for row in batch.to_pylist():
                index = ivf.decode(footer.read_blob(row["file"]))
                sizes = [int(b) - int(a) for a, b in zip(index.offsets[:-1], index.offsets[1:], strict=True)]
                yield pa.RecordBatch.from_pylist([{"file_no": row["n"], "list": i, "size": s} for i, s in enumerate(sizes)], schema=pa.schema([("file_no", pa.int64()), ("list", pa.int64()), ("size", pa.int64())]))

    return files.mapInArrow(lists, "file_no long, list long, size long")


def kmeans_one_step(spark, sf):
    """One full pass from the first 16 vectors, over the whole table, by joins and averages."""
    e = table(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    seeds = e.orderBy("vec_id").limit(16).select(F.col("vec_id").alias("c"), F.col("v").alias("s"))
    pairs = e.join(F.broadcast(seeds)).select("vec_id", "v", "c", V.l2_squared(F.col("v"), F.col("s")).alias("d"))  # 16 rows by construction
    own = pairs.groupBy("vec_id").agg(F.min_by("c", F.struct("d", "c")).alias("c"), F.first("v").alias("v"))
    return own.select("c", F.posexplode("v").alias("i", "x")).groupBy("c", "i").agg(F.round(F.avg("x"), 6).alias("mean"), F.count("*").alias("n")).withColumn("i", F.col("i").cast("bigint"))


def global_ivf_seed(spark, sf):
    g = baselines.build_global(table(spark, sf, "embeddings"), "embedding", "vec_id", 32, algo="seed")
    return g.search(query_vector(spark, sf), K, nprobe=8).select(F.col("id").alias("vec_id"), F.round("dist", 6).alias("dist"))


# --- approximate behaviour (no SQL) -------------------------------------------------------------


def _latent_table(spark, sf, name="latent", rows_each=LATENT_ROWS):
    key = (spark.sparkContext.applicationId, sf, name, rows_each)
    if key not in _TABLES:
        n, m = rows_each * table(spark, sf, "embeddings").count(), LATENT_CENTRES
        number = F.floor(((F.col("id") * 2654435761) % (1 << 32)) / ((1 << 29) + 1))
        rows = storage.written(latent(spark, sf, n, m), "latent")
        t = layout.write(rows, storage.scratch(spark, name), SPEC, "uniform", files=8, file_number=number, key=["id"], filters=["id"], presence=["category"])
        _TABLES[key] = build.create_index(t, algo="lloyd", iters=5).table
    return _TABLES[key]


def _latent_queries(t: Table, count: int = 200):
    """So many rows, evenly spaced by id, each moved by a tenth of the row that comes (37 j + 5) places after it among them."""
    n = t.manifest().agg(F.sum("rows")).first()[0]
    rows = t.read().where(F.col("id") % max(1, n // count) == 0).select("id", "embedding").orderBy("id").limit(count).collect()
    return [(r["id"], [x + 0.1 * y for x, y in zip(r["embedding"], rows[(37 * j + 5) % len(rows)]["embedding"], strict=True)]) for j, r in enumerate(rows)]


def _recall_over(found, truth) -> dict:
    return measures.recall_distribution(measures.recall_at_k(found.rows, truth, K)).first().asDict()


def warm_latency(spark, sf, count=200, timed=20, repeats=3, rows_each=LATENT_ROWS):
    """Unfiltered top-10 on the clustered corpus with its files held warm: the median of each query's timed runs,
    then percentiles over queries, for ten lists a file and for exact search of every row. Recall is that of all
    queries; so many of them, evenly spaced, are timed one by one (timed=count times all)."""
    t = _latent_table(spark, sf, rows_each=rows_each)
    queries = _latent_queries(t, count)
    truth = storage.written(search.knn_batch(t, queries, K, tie="id", exact=True).rows.select("query_id", "id"), "truth")
    kept = warm.WarmSet(t, "block", ("id",))
    settings = {"ivf": {"nprobe": 10, "warm": kept}, "brute": {"exact": True, "warm": kept}, "brute_cold": {"exact": True}}
    rows = []
    try:
        for name, options in settings.items():
            recall = _recall_over(search.knn_batch(t, queries, K, tie="id", **options), truth)
            runs = [lambda v=v, o=options: search.knn(t, v, K, tie="id", **o).rows.collect() for _, v in queries[:: max(1, len(queries) // timed)]]
            rows.append((name, len(runs), measures.latency(runs, repeats), recall))
    finally:
        kept.unload()
    brute = rows[-1][2]
    return spark.createDataFrame(
        [(n, len(queries), timed, x["p50"], x["p90"], x["p95"], x["p99"], measures.speedup(x, brute), r["mean"], r["least"]) for n, timed, x, r in rows],
        "setting string, queries long, timed long, p50 double, p90 double, p95 double, p99 double, speedup double, mean_recall double, least_recall double",
    )


def warm_ablation(spark, sf, count=10, repeats=3, rows_each=LATENT_ROWS):
    """Each row adds one measure to the row before: files read by every query; held, placed by turns; held, placed by
    highest random weight; and a wait for the whole tier. With the files that a query finds held (the mean over the
    queries), those that a tier of one slot more would have to read again, recall, and the speed against exact
    search that reads. The last two rows differ in time only where executors come and go."""
    t = _latent_table(spark, sf, rows_each=rows_each)
    queries = _latent_queries(t, count)
    truth = storage.written(search.knn_batch(t, queries, K, tie="id", exact=True).rows.select("query_id", "id"), "truth")
    timed = lambda o: measures.latency([lambda v=v: search.knn(t, v, K, tie="id", **o).rows.collect() for _, v in queries], repeats)
    brute, slots = timed({"exact": True}), max(2, t.meta()["n_files"] // 2)
    rows = []
    for name, kind, waits in (("read", None, False), ("held", "rr", False), ("placed", "hrw", False), ("stable", "hrw", True)):
        if waits:
            warm.await_executors(spark, int(spark.conf.get("spark.executor.instances", "1")))
        kept = warm.WarmSet(t, "block", ("id",), slots, kind) if kind else None
        options = {"nprobe": 10, "place": kind or "hrw", "slots": slots, **({"warm": kept} if kept else {})}
        took = timed(options)
        found = search.knn_batch(t, queries, K, tie="id", **options)
        recall, hits = _recall_over(found, truth), found.metrics()["hits"] / len(queries)
        moved = warm.moved_fraction(t.manifest(), slots, slots + 1, kind) if kind else 1.0
        rows.append((name, took["p50"], measures.speedup(took, brute), took["cold_first"], hits, moved, recall["mean"], recall["least"]))
        if kept:
            kept.unload()
    return spark.createDataFrame(
        rows, "setting string, p50 double, speedup double, cold_first double, files_held double, moved_by_one_slot double, mean_recall double, least_recall double"
    )


def recall_probe_sweep(spark, sf):
    """Mean and least recall@10 as more lists are probed; never falls, and is 1 when all are."""
    t = _latent_table(spark, sf)
    queries = _latent_queries(t)
    truth = search.knn_batch(t, queries, K, tie="id", exact=True).rows
    rows = []
    truth = storage.written(truth.select("query_id", "id"), "truth")
    for p in (1, 2, 5, 10, 20, "all"):
        found = search.knn_batch(t, queries, K, tie="id", nprobe=p)
        r = measures.recall_distribution(measures.recall_at_k(found.rows, truth, K)).first()
        m = found.metrics()
        rows.append((str(p), r["mean"], r["least"], m["candidates"] / len(queries), m["centroids"] / len(queries)))
    return spark.createDataFrame(rows, "nprobe string, mean_recall double, least_recall double, candidates double, centroid_distances double")


def global_ivfpq(spark, sf):
    """Whole-table index with product codes, with and without exact re-ranking, against exact search."""
    t = _latent_table(spark, sf)
    queries = _latent_queries(t, 10)
    g = baselines.build_global(t.read(), "embedding", "id", 141, pq=16, iters=4)
    truth = {q: {r["id"] for r in search.knn(t, v, K, tie="id", exact=True).rows.collect()} for q, v in queries}
    rows = []
    for rerank in (0, 100):
        hit = [len(truth[q] & {r["id"] for r in g.search(v, K, 8, rerank).collect()}) / K for q, v in queries]
        rows.append((rerank, sum(hit) / len(hit), min(hit), g.seconds))
    return spark.createDataFrame(rows, "rerank long, mean_recall double, least_recall double, build_seconds double")


def hnsw_service(spark, sf):
    """The in-memory stand-in on a subset, with an attribute filter inside the walk."""
    import time

    import numpy as np

    t = _latent_table(spark, sf)
    began = time.time()
    rows = t.read().orderBy("id").limit(3000).collect()  # the bounded subset that the service is given
    x, cats = np.asarray([r["embedding"] for r in rows], dtype=np.float64), np.asarray([r["category"] for r in rows])
    copied, began = time.time() - began, time.time()
    graph, keep = baselines.Hnsw(x), cats == "c1"
    built, hits = time.time() - began, []
    for i in range(0, len(x), max(1, len(x) // 20)):
        truth = np.flatnonzero(keep)[np.argsort(((x[keep] - x[i]) ** 2).sum(axis=1), kind="stable")[:K]]
        hits.append(len(set(truth.tolist()) & {j for _, j in graph.search(x[i], K, 64, keep)}) / max(1, len(truth)))
    return spark.createDataFrame([(len(x), sum(hits) / len(hits), copied, built)], "rows long, mean_recall double, copy_seconds double, build_seconds double")


def build_over_clustered(spark, sf):
    """The rule's number of centroids and four times as many: seconds and rows kept."""
    base = layout.write(docs(spark, sf).select("vec_id", "embedding"), storage.scratch(spark, "built"), SPEC, "uniform", files=4, filters=["vec_id"])
    rows = []
    for name, options in (("rule", {}), ("four_times", {"c": 4 * ivf.choose_c(base.manifest().agg(F.max("rows")).first()[0])}), ("serial", {"parallelism": 1})):
        r = build.create_index(base.at(0) if name == "rule" else base, **options)
        base = r.table
        rows.append((name, r.files, r.failed, r.rows, r.seconds, r.task_seconds))
    return spark.createDataFrame(rows, "setting string, files long, failed long, rows long, seconds double, task_seconds double")


def cost_choice(spark, sf):
    from .plans.pred import parse

    t, rows = indexed(spark, sf, "value_local"), []
    for where in ("label = 3", "label >= 0", "label = 99"):
        path, c = cost.choose(t, parse(where, t.schema(), spark), K)
        rows.append((where, path, c.files, c.candidates, c.centroids))
    return spark.createDataFrame(rows, "predicate string, path string, files double, candidates double, centroids double")


# --- around the methods -------------------------------------------------------------------------


def op_vector_functions(spark, sf):
    e = table(spark, sf, "embeddings")
    q = V.literal(query_vector(spark, sf))
    c = F.col("embedding")
    return e.select("vec_id", F.round(V.l2_squared(c, q), 6).alias("l2_squared"), F.round(V.inner_product(c, q), 6).alias("inner"), F.round(V.cosine_distance(c, q), 6).alias("cosine"), F.round(V.l2_norm(c), 6).alias("norm"))


def op_cube(spark, sf):
    d = table(spark, sf, "documents")
    return d.cube("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


def op_rollup(spark, sf):
    return table(spark, sf, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("total"))


def op_pivot(spark, sf):
    return table(spark, sf, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).agg(F.count(F.lit(1))).na.fill(0)


def op_asof_join(spark, sf):
    """Each error with the latest click of the same user before it: a union and one window."""
    e = table(spark, sf, "events")
    both = e.where("event_type in ('error', 'click')").select("event_id", "ts", "user_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w)
    return both.withColumn("click_id", last).where("event_type = 'error'").select("event_id", "click_id")


def op_range_join(spark, sf):
    """Events within two minutes after an error of the same user, by bucketed time."""
    e = table(spark, sf, "events")
    step = 120
    sec = F.timestamp_diff("SECOND", F.lit("2024-01-01 00:00:00").cast("timestamp_ntz"), F.col("ts"))
    left = e.where("event_type = 'error'").select(F.col("user_id"), F.col("event_id").alias("error_id"), F.col("ts").alias("t0"), F.explode(F.array(F.floor(sec / step), F.floor(sec / step) + 1)).alias("bucket"))
    right = e.where("event_type <> 'error'").select("user_id", "event_id", "ts", F.floor(sec / step).alias("bucket"))
    near = (F.col("ts") >= F.col("t0")) & (F.col("ts") < F.col("t0") + F.expr("interval 2 minutes"))
    return left.join(right, ["user_id", "bucket"]).where(near).select("error_id", "event_id")


def op_session_window(spark, sf):
    from .streaming.ingest import sessions

    return sessions(table(spark, sf, "events"), "6 hours").groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


def op_tumbling_window(spark, sf):
    from .streaming.ingest import tumbling

    return tumbling(table(spark, sf, "events")).select("start", "event_type", "n", F.round("total", 4).alias("total"))


def op_topk_per_group(spark, sf):
    w = Window.partitionBy("c_mktsegment").orderBy(F.desc("c_acctbal"), "c_custkey")
    return table(spark, sf, "customer").withColumn("r", F.row_number().over(w)).where("r <= 3").select("c_mktsegment", "c_custkey", F.col("r").cast("bigint").alias("r"))


def op_set_operations(spark, sf):
    c, s = table(spark, sf, "customer").select(F.col("c_nationkey").alias("k")), table(spark, sf, "supplier").select(F.col("s_nationkey").alias("k"))
    parts = {"union": c.union(s), "intersect": c.intersect(s), "except": c.exceptAll(s)}
    out = None
    for name, df in parts.items():
        row = df.agg(F.lit(name).alias("op"), F.count("*").alias("n"), F.countDistinct("k").alias("distinct_k"))
        out = row if out is None else out.unionByName(row)
    return out


def op_semi_anti(spark, sf):
    c, o = table(spark, sf, "customer"), table(spark, sf, "orders")
    with_o = c.join(o, c.c_custkey == o.o_custkey, "left_semi").groupBy("c_mktsegment").agg(F.count("*").alias("buyers"))
    without = c.join(o, c.c_custkey == o.o_custkey, "left_anti").groupBy("c_mktsegment").agg(F.count("*").alias("others"))
    return with_o.join(without, "c_mktsegment", "full").select("c_mktsegment", F.coalesce("buyers", F.lit(0)).alias("buyers"), F.coalesce("others", F.lit(0)).alias("others"))


def op_json(spark, sf):
    e = table(spark, sf, "events").select("event_type", F.get_json_object("props", "$.k").cast("int").alias("k"))
    return e.groupBy("event_type").agg(F.sum("k").alias("k_sum"), F.count("k").alias("k_n"))


def op_percentiles(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(*[F.round(F.percentile("l_quantity", p), 6).alias(f"p{int(p * 100)}") for p in (0.5, 0.9, 0.95, 0.99)])


def op_star_revenue(spark, sf):
    """One fact and its dimensions: broadcast by size, pushed filters, partial aggregation."""
    li, o, c, n = (table(spark, sf, t) for t in ("lineitem", "orders", "customer", "nation"))
    j = li.where("l_returnflag = 'R'").join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey)
    price, discount = F.col("l_extendedprice").cast("decimal(18,2)"), F.col("l_discount").cast("decimal(4,2)")
    return j.groupBy("n_name").agg(F.round(F.sum(price * (1 - discount)), 2).cast("double").alias("revenue"), F.count("*").alias("n"))


def op_datasource(spark, sf):
    from .sources import datasource

    datasource.register(spark)
    t = indexed(spark, sf, "uniform")
    return spark.read.format("prunedknn").option("path", t.path).load().groupBy("lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


def op_stream_ingest(spark, sf):
    """embeddings in five files, streamed into an indexed table; a planted query finds its row."""
    src = storage.scratch(spark, "stream-src")
    e = table(spark, sf, "embeddings")
    e.repartitionById(5, (F.col("vec_id") % 5).cast("int")).write.parquet(src)
    from .streaming.ingest import ingest

    empty = layout.write(e.limit(0), storage.scratch(spark, "stream-table"), SPEC, "uniform", files=1, filters=["vec_id"])
    stream = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 2).parquet(src)
    query, sink = ingest(stream, empty, storage.scratch(spark, "stream-ck"))
    query.awaitTermination()
    t = Table(spark, empty.path)
    return _out(search.knn(t, query_vector(spark, sf), K, nprobe="all"), "vec_id")


def op_vector_mean(spark, sf):
    from .functions.tables import vector_mean

    means = table(spark, sf, "embeddings").groupBy("label").agg(vector_mean(F.col("embedding"), DIM).alias("m"))
    return means.select("label", F.posexplode("m").alias("i", "x")).select("label", F.col("i").cast("bigint").alias("i"), F.round("x", 6).alias("mean"))


def op_knn_table_function(spark, sf):
    from .functions import tables

    tables.register(spark)
    table(spark, sf, "embeddings").createOrReplaceTempView("prunedknn_vectors")
    q = ", ".join(f"{float(x):.9g}D" for x in query_vector(spark, sf))
    text = f"SELECT id AS vec_id, dist FROM knn_topk(TABLE(SELECT vec_id, embedding FROM prunedknn_vectors), array({q}), {K})"
    return _out(spark.sql(text).orderBy("dist", "vec_id").limit(K), "vec_id")


def knn_file_pq(spark, sf):
    """Product codes beside a file's lists narrow the candidates; all that is left is re-scored exactly."""
    t = _latent_table(spark, sf)
    coded = build.create_index(t, algo="lloyd", iters=5, pq=16).table
    queries = _latent_queries(t, 20)
    truth = storage.written(search.knn_batch(t, queries, K, tie="id", exact=True).rows.select("query_id", "id"), "truth-pq")
    rows = []
    for name, own in (("lists", t), ("lists_and_codes", coded)):
        found = search.knn_batch(own, queries, K, tie="id", nprobe=20, overfetch=1)
        r, m = measures.recall_distribution(measures.recall_at_k(found.rows, truth, K)).first(), found.metrics()
        rows.append((name, r["mean"], r["least"], m["candidates"] / len(queries)))
    return spark.createDataFrame(rows, "index string, mean_recall double, least_recall double, candidates double")


def knn_sidecar(spark, sf):
    base = layout.write(docs(spark, sf), storage.scratch(spark, "sidecar"), SPEC, "uniform", files=3, filters=["label"], presence=["label"])
    t = build.create_index(base, sidecar=True).table
    return _out(search.knn(t, query_vector(spark, sf), K, "label = 3", ["label"], nprobe="all"), "vec_id", "label")
