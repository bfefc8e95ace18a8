"""DuckDB SQL beside the workload queries."""

from __future__ import annotations

from . import workloads as W

_FACT = """
docs AS (
  SELECT e.vec_id, e.embedding, e.label, d.lang, d.source, d.n_chars, d.text, e.vec_id % (SELECT count(*) FROM customer) AS customer_id
  FROM embeddings e JOIN documents d ON e.vec_id = d.doc_id
), dim AS (
  SELECT c_custkey AS customer_id, c_mktsegment AS segment, r_name AS region FROM customer
  JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
), q AS (SELECT embedding::DOUBLE[] AS v FROM embeddings WHERE vec_id = 7)
"""
_D = "list_distance(embedding::DOUBLE[], (SELECT v FROM q))"


def _top(columns: str = "vec_id", where: str = "true", source: str = "docs", k: int = 10) -> str:
    return f"WITH {_FACT} SELECT {columns}, round({_D}, 6) AS dist FROM {source} WHERE {where} ORDER BY {_D}, vec_id LIMIT {k}"


#: Files by vec_id % 8, the first 16 vectors of each as centroids, every row in the list of its nearest one.
_SEED = """
f AS (SELECT vec_id, embedding::DOUBLE[] AS v, vec_id % 8 AS f, row_number() OVER (PARTITION BY vec_id % 8 ORDER BY vec_id) - 1 AS r FROM embeddings),
c AS (SELECT f, r AS list, v AS cv FROM f WHERE r < 16),
own AS (
  SELECT f.vec_id, f.f, f.v, arg_min(c.list, list_distance(f.v, c.cv)) AS list FROM f JOIN c USING (f) GROUP BY f.vec_id, f.f, f.v
)
"""
#: Filtered search over 4 of 16 lists a file: a file whose lists hold fewer than 10 matches is taken whole.
_FILTERED = f"""{_SEED}, lim AS (SELECT unnest([1, 2, 4, 7, 10]::BIGINT[]) AS below),
qs AS (SELECT vec_id AS query_id, embedding::DOUBLE[] AS qv FROM embeddings WHERE vec_id % 20 = 0),
probed AS (SELECT query_id, f, list FROM qs, c QUALIFY row_number() OVER (PARTITION BY query_id, f ORDER BY list_distance(cv, qv), list) <= 4),
hit AS (
  SELECT below, query_id, f, vec_id, list_distance(v, qv) AS d, p.list IS NOT NULL AS near
  FROM own JOIN embeddings e USING (vec_id) JOIN lim ON e.label < below CROSS JOIN qs LEFT JOIN probed p USING (query_id, f, list)
),
cand AS (SELECT *, count(*) FILTER (near) OVER (PARTITION BY below, query_id, f) AS n_near, count(*) OVER (PARTITION BY below, query_id, f) AS n_all FROM hit)
"""
_FILES = "lpad(range::VARCHAR, 5, '0')"

ORACLE_SQL = {
    "knn_brute": f"WITH {_FACT} SELECT vec_id, round({_D}, 6) AS dist FROM embeddings ORDER BY {_D}, vec_id LIMIT 10",
    "knn_ivf_full_probe": _top(),
    "knn_ivf_seed_probe": f"""WITH q AS (SELECT embedding::DOUBLE[] AS v FROM embeddings WHERE vec_id = 7), {_SEED},
      probed AS (SELECT f, list FROM c QUALIFY row_number() OVER (PARTITION BY f ORDER BY list_distance(cv, (SELECT v FROM q)), list) <= 4)
      SELECT vec_id, round(list_distance(v, (SELECT v FROM q)), 6) AS dist FROM own JOIN probed USING (f, list)
      ORDER BY list_distance(v, (SELECT v FROM q)), vec_id LIMIT 10""",
    "knn_filtered_value_local": _top("vec_id, label, lang", "label = 3"),
    "knn_filtered_uniform": _top("vec_id, label, lang", "label = 3"),
    "knn_filtered_range": _top("vec_id, label, lang", "n_chars >= 500 AND n_chars < 2000"),
    "knn_filtered_in_list": _top("vec_id, label, lang", "label IN (1, 4, 7) AND lang IN ('de', 'fr')"),
    "knn_filtered_negated": _top("vec_id, label, lang", "NOT (label IN (1, 4, 7) OR lang LIKE 'e%')"),
    "knn_filtered_opaque": _top("vec_id, label, lang", "n_chars % 3 = 1"),
    "knn_pure_gate": _top("vec_id, label, lang", "label = 3"),
    "knn_sorted_boundary": _top("vec_id, lang", "lang = 'fr'"),
    "knn_postfilter": f"WITH {_FACT}, t AS (SELECT vec_id, label, {_D} AS d FROM docs ORDER BY d, vec_id LIMIT 20) SELECT vec_id, label, round(d, 6) AS dist FROM t WHERE label = 3 ORDER BY d, vec_id LIMIT 10",
    "knn_policy": _top("vec_id, lang", "lang = 'en' AND label = 2"),
    "knn_mixed_files": f"WITH {_FACT}, m AS (SELECT vec_id, embedding FROM docs UNION ALL SELECT -1, embedding FROM docs WHERE vec_id = 7) SELECT vec_id, round({_D}, 6) AS dist FROM m ORDER BY {_D}, vec_id LIMIT 10",
    "knn_empty_survivors": _top("vec_id, label, lang", "label = 99"),
    "knn_wide_lookup": _top("vec_id, md5(text) AS text_md5"),
    "knn_batch_topk": """WITH qs AS (SELECT vec_id AS query_id, embedding::DOUBLE[] AS v FROM embeddings WHERE vec_id % 20 = 0),
      e AS (SELECT e.vec_id, e.embedding::DOUBLE[] AS x FROM embeddings e JOIN documents d ON e.vec_id = d.doc_id)
      SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY list_distance(x, v), vec_id) AS rank, vec_id, round(list_distance(x, v), 6) AS dist
      FROM qs, e QUALIFY rank <= 5""",
    "recall_at_k": f"""WITH {_SEED}, qs AS (SELECT vec_id AS query_id, embedding::DOUBLE[] AS qv FROM embeddings WHERE vec_id % 20 = 0),
      probed AS (SELECT query_id, qv, f, list FROM qs, c QUALIFY row_number() OVER (PARTITION BY query_id, f ORDER BY list_distance(cv, qv), list) <= 4),
      found AS (SELECT query_id, vec_id FROM probed JOIN own USING (f, list) QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY list_distance(v, qv), vec_id) <= 10),
      truth AS (SELECT query_id, vec_id FROM qs, f QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY list_distance(v, qv), vec_id) <= 10)
      SELECT t.query_id, round(count(f.vec_id) / 10.0, 6) AS recall FROM truth t LEFT JOIN found f USING (query_id, vec_id) GROUP BY t.query_id""",
    "recall_bins": f"""WITH {_SEED}, qs AS (SELECT vec_id AS query_id, embedding::DOUBLE[] AS qv FROM embeddings WHERE vec_id % 20 = 0),
      probed AS (SELECT query_id, qv, f, list FROM qs, c QUALIFY row_number() OVER (PARTITION BY query_id, f ORDER BY list_distance(cv, qv), list) <= 4),
      found AS (SELECT query_id, vec_id FROM probed JOIN own USING (f, list) QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY list_distance(v, qv), vec_id) <= 10),
      truth AS (SELECT query_id, vec_id FROM qs, f QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY list_distance(v, qv), vec_id) <= 10),
      hits AS (SELECT t.query_id, count(f.vec_id) AS bin FROM truth t LEFT JOIN found f USING (query_id, vec_id) GROUP BY t.query_id)
      SELECT bin, count(*) AS queries FROM hits GROUP BY bin""",
    "recall_by_selectivity": f"""WITH {_FILTERED},
      found AS (SELECT below, query_id, vec_id FROM cand WHERE near OR n_near < 10 QUALIFY row_number() OVER (PARTITION BY below, query_id ORDER BY d, vec_id) <= 10),
      truth AS (SELECT below, query_id, vec_id FROM cand QUALIFY row_number() OVER (PARTITION BY below, query_id ORDER BY d, vec_id) <= 10)
      SELECT t.below, t.query_id, round(count(f.vec_id) / least(count(*), 10)::DOUBLE, 6) AS recall FROM truth t LEFT JOIN found f USING (below, query_id, vec_id) GROUP BY t.below, t.query_id""",
    "work_by_selectivity": f"""WITH {_FILTERED},
      per AS (SELECT below, query_id, f, any_value(n_near) AS n_near, any_value(n_all) AS n_all FROM cand GROUP BY below, query_id, f)
      SELECT below, sum(CASE WHEN n_near < 10 THEN n_all ELSE n_near END)::BIGINT AS candidates, (SELECT count(*) FROM c) * (SELECT count(*) FROM qs) AS centroids,
        (SELECT count(*) FROM f) * (SELECT count(*) FROM qs) AS rows_in_files, count(*) FILTER (n_near < 10 AND n_all > n_near) AS whole_files FROM per GROUP BY below""",
    "knn_ablation": f"WITH {_FACT}, t AS (SELECT vec_id, {_D} AS d FROM docs WHERE label = 3 ORDER BY d, vec_id LIMIT 10) SELECT s AS setting, vec_id, round(d, 6) AS dist FROM t, unnest(['cold', 'rr', 'block', 'node', 'rescan', 'rescore']) AS u(s)",
    "knn_sql_rewrite": f"WITH {_FACT} SELECT vec_id, label, round({_D}, 6) AS dist, 'ivf' AS path FROM docs WHERE label IN (2, 5) ORDER BY {_D}, vec_id LIMIT 10",
    "knn_by_waves": _top(),
    "selectivity_sweep": f"""WITH {_FACT} SELECT below, vec_id, n_chars, round({_D}, 6) AS dist FROM docs, unnest([200, 500, 1000, 2000, 5000, 100000]::BIGINT[]) AS u(below)
      WHERE n_chars < below QUALIFY row_number() OVER (PARTITION BY below ORDER BY {_D}, vec_id) <= 5""",
    "join_refreshed_region": f"WITH {_FACT} SELECT vec_id, 'NORTH' AS region, round({_D}, 6) AS dist, true AS unchanged_kept FROM docs JOIN dim USING (customer_id) WHERE region = 'EUROPE' AND customer_id % 2 = 0 ORDER BY {_D}, vec_id LIMIT 10",
    "join_key_set": f"WITH {_FACT} SELECT customer_id FROM dim WHERE region = 'EUROPE'",
    "join_snowflake_keys": "SELECT c_custkey FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA'",
    "join_outer_fallback": f"WITH {_FACT} SELECT vec_id, segment, round({_D}, 6) AS dist FROM docs LEFT JOIN (SELECT * FROM dim WHERE segment = 'BUILDING') USING (customer_id) ORDER BY {_D}, vec_id LIMIT 10",
    "prune_report_layouts": f"""WITH {_FACT}, u AS (SELECT vec_id % 8 AS f, count(*) AS n, bool_or(label = 3) AS hit FROM docs GROUP BY 1),
      v AS (SELECT label AS f, count(*) AS n, bool_or(label = 3) AS hit FROM docs GROUP BY 1),
      r AS (SELECT region AS f, count(*) AS n, bool_or(region = 'EUROPE') AS hit FROM docs JOIN dim USING (customer_id) GROUP BY 1),
      a AS (SELECT 'uniform' AS layout, n, hit FROM u UNION ALL SELECT 'value_local', n, hit FROM v UNION ALL SELECT 'region', n, hit FROM r)
      SELECT layout, count(*) AS files_total, count(*) FILTER (hit) AS files_surviving, sum(n)::BIGINT AS rows_total, coalesce(sum(n) FILTER (hit), 0)::BIGINT AS rows_surviving FROM a GROUP BY layout""",
    "scattered_prunes_nothing": "SELECT 17::BIGINT AS files_total, 0::BIGINT AS files_pruned",
    "locality_by_column": f"""WITH {_FACT}, a AS (SELECT 'uniform' AS layout, label, vec_id % 8 AS f FROM docs UNION ALL SELECT 'value_local', label, label FROM docs),
      t AS (SELECT layout, count(DISTINCT f) AS files_total FROM a GROUP BY layout)
      SELECT layout, label::VARCHAR AS value, count(DISTINCT f) AS files_with, any_value(files_total) AS files_total, round(1 - count(DISTINCT f) / any_value(files_total)::DOUBLE, 6) AS prune_ratio
      FROM a JOIN t USING (layout) GROUP BY layout, label""",
    "zone_map_stats": f"WITH {_FACT} SELECT min(n_chars)::DOUBLE AS lo, max(n_chars)::DOUBLE AS hi, count(*) FILTER (n_chars IS NULL) AS nulls, count(*) AS rows FROM docs GROUP BY vec_id % 8",
    "presence_index": f"WITH {_FACT} SELECT min(vec_id) OVER (PARTITION BY vec_id % 8) AS first_id, label::VARCHAR AS value FROM docs QUALIFY row_number() OVER (PARTITION BY vec_id % 8, label) = 1",
    "files_touched_uniform": f"""WITH {_FACT}, a AS (SELECT vec_id % 8 AS f, count(*) AS n, min(n_chars) AS least FROM docs GROUP BY 1)
      SELECT below, count(*) AS files_total, count(*) FILTER (least < below) AS files_surviving, coalesce(sum(n) FILTER (least < below), 0)::BIGINT AS rows_surviving
      FROM a, unnest([60, 100, 200, 1000]::BIGINT[]) AS u(below) GROUP BY below""",
    "worked_trace": """SELECT 444::BIGINT AS files, 355::BIGINT AS pruned, (89 * 25978)::BIGINT AS rows_left, round(89 * 25978 * 10 / 1024.0)::BIGINT AS candidates,
      (89 * 1024)::BIGINT AS centroid_distances, round(444 / (89 * 10 / 1024.0), 1)::DOUBLE AS reduction, round(444 * 25978 / (89 * 25978 * 10 / 1024.0 + 89 * 1024), 1)::DOUBLE AS honest_reduction""",
    "cost_model_grid": """WITH g AS (SELECT s::DOUBLE AS sigma, c, p FROM unnest([0.01, 0.05, 0.1, 0.2, 0.5, 1.0]) AS a(s), unnest([256, 1024, 4096]::BIGINT[]) AS b(c), unnest([1, 10, 100]::BIGINT[]) AS d(p)),
      x AS (SELECT *, 11534160::DOUBLE * sigma * p / c AS cand, 444::DOUBLE * sigma * c AS cent FROM g)
      SELECT sigma, c, p, round(cand, 3) AS candidates, round(cent, 3) AS centroids, round(11534160 / cand, 3) AS reduction, round(11534160 / (cand + cent), 3) AS honest_reduction FROM x""",
    "choose_centroids": "SELECT r AS rows, least(r, (2 ^ ceil(log2(4 * sqrt(r))))::BIGINT) AS c FROM unnest([1, 2, 10, 62, 500, 1000, 4096, 26000, 34000, 125000, 1000000]::BIGINT[]) AS t(r)",
    "placement_hrw": f"SELECT 'part-' || {_FILES} AS file, arg_max(s, md5('part-' || {_FILES} || ':' || s)) AS slot FROM range(444), unnest(range(11)) AS t(s) GROUP BY range",
    "placement_moved": f"""WITH a AS (SELECT range AS f, arg_max(s, md5('part-' || {_FILES} || ':' || s)) FILTER (s < 11) AS x, arg_max(s, md5('part-' || {_FILES} || ':' || s)) AS y FROM range(444), unnest(range(12)) AS t(s) GROUP BY range)
      SELECT 'hrw' AS kind, round(avg((x <> y)::INT), 6) AS moved FROM a UNION ALL SELECT 'rr', round(avg((f % 11 <> f % 12)::INT), 6) FROM a""",
    "table_doubling": f"WITH {_FACT} SELECT label, count(*) * 4 AS n FROM docs GROUP BY label",
    "snapshot_replace": f"WITH {_FACT} SELECT s AS snapshot, 8::BIGINT AS files, (SELECT count(*) FROM docs) AS rows, s * 8 AS indexed FROM range(2) AS t(s)",
    "time_travel_diff": f"WITH {_FACT} SELECT 0::BIGINT AS only_old, 0::BIGINT AS only_new, count(*) AS rows FROM docs",
    "ivf_assignments": f"WITH {_SEED}, n AS (SELECT f, list, count(*) AS n FROM own GROUP BY ALL) SELECT c.f AS file_no, c.list, coalesce(n.n, 0) AS size FROM c LEFT JOIN n ON n.f = c.f AND n.list = c.list",
    "kmeans_one_step": """WITH s AS (SELECT vec_id AS c, embedding::DOUBLE[] AS sv FROM embeddings ORDER BY vec_id LIMIT 16),
      own AS (SELECT e.vec_id, any_value(e.embedding::DOUBLE[]) AS v, arg_min(c, list_distance(e.embedding::DOUBLE[], sv)) AS c FROM embeddings e, s GROUP BY e.vec_id)
      SELECT c, i - 1 AS i, round(avg(v[i]), 6) AS mean, count(*) AS n FROM own, unnest(range(1, 65)) AS t(i) GROUP BY c, i""",
    "global_ivf_seed": """WITH q AS (SELECT embedding::DOUBLE[] AS v FROM embeddings WHERE vec_id = 7),
      s AS (SELECT row_number() OVER (ORDER BY vec_id) AS c, embedding::DOUBLE[] AS sv FROM embeddings ORDER BY vec_id LIMIT 32),
      own AS (SELECT e.vec_id, any_value(e.embedding::DOUBLE[]) AS x, arg_min(c, list_distance(e.embedding::DOUBLE[], sv)) AS c FROM embeddings e, s GROUP BY e.vec_id),
      p AS (SELECT c FROM s ORDER BY list_distance(sv, (SELECT v FROM q)), c LIMIT 8)
      SELECT vec_id, round(list_distance(x, (SELECT v FROM q)), 6) AS dist FROM own JOIN p USING (c) ORDER BY list_distance(x, (SELECT v FROM q)), vec_id LIMIT 10""",
    "op_vector_functions": """WITH q AS (SELECT embedding::DOUBLE[] AS v FROM embeddings WHERE vec_id = 7), e AS (SELECT vec_id, embedding::DOUBLE[] AS x FROM embeddings)
      SELECT vec_id, round(list_distance(x, v) ** 2, 6) AS l2_squared, round(list_inner_product(x, v), 6) AS inner, round(list_cosine_distance(x, v), 6) AS cosine, round(sqrt(list_inner_product(x, x)), 6) AS norm FROM e, q""",
    "op_cube": "SELECT lang, source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY CUBE (lang, source)",
    "op_rollup": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, sum(o_totalprice::DECIMAL(18, 2))::DOUBLE AS total FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
    "op_pivot": "SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'es') AS es, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY source",
    "op_asof_join": """SELECT e.event_id, (SELECT arg_max(c.event_id, (c.ts, c.event_id)) FROM events c WHERE c.user_id = e.user_id AND c.event_type = 'click' AND (c.ts, c.event_id) < (e.ts, e.event_id)) AS click_id
      FROM events e WHERE e.event_type = 'error'""",
    "op_range_join": """SELECT a.event_id AS error_id, b.event_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 2 MINUTE
      WHERE a.event_type = 'error' AND b.event_type <> 'error'""",
    "op_session_window": """WITH g AS (SELECT user_id, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS first FROM events)
      SELECT user_id, sum(first)::BIGINT AS sessions, count(*) AS events FROM g GROUP BY user_id""",
    "op_tumbling_window": "SELECT date_trunc('day', ts)::TIMESTAMP AS start, event_type, count(*) AS n, round(sum(value::DECIMAL(18, 4))::DOUBLE, 4) AS total FROM events GROUP BY ALL",
    "op_topk_per_group": "SELECT c_mktsegment, c_custkey, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer QUALIFY r <= 3",
    "op_set_operations": """SELECT 'union' AS op, count(*) AS n, count(DISTINCT k) AS distinct_k FROM (SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier)
      UNION ALL SELECT 'intersect', count(*), count(DISTINCT k) FROM (SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier)
      UNION ALL SELECT 'except', count(*), count(DISTINCT k) FROM (SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier)""",
    "op_semi_anti": "SELECT c_mktsegment, count(*) FILTER (b) AS buyers, count(*) FILTER (NOT b) AS others FROM (SELECT c_mktsegment, EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) AS b FROM customer) GROUP BY c_mktsegment",
    "op_json": "SELECT event_type, sum((props::JSON ->> 'k')::INT)::BIGINT AS k_sum, count((props::JSON ->> 'k')::INT) AS k_n FROM events GROUP BY event_type",
    "op_percentiles": "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 6) AS p50, round(quantile_cont(l_quantity, 0.9), 6) AS p90, round(quantile_cont(l_quantity, 0.95), 6) AS p95, round(quantile_cont(l_quantity, 0.99), 6) AS p99 FROM lineitem GROUP BY l_returnflag",
    "op_star_revenue": """SELECT n_name, round(sum(l_extendedprice::DECIMAL(18, 2) * (1 - l_discount::DECIMAL(4, 2))), 2)::DOUBLE AS revenue, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey
      JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE l_returnflag = 'R' GROUP BY n_name""",
    "op_datasource": f"WITH {_FACT} SELECT lang, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM docs GROUP BY lang",
    "op_stream_ingest": f"WITH {_FACT} SELECT vec_id, round({_D}, 6) AS dist FROM embeddings ORDER BY {_D}, vec_id LIMIT 10",
}
for _name in ("join_reduced_region", "join_materialized_region", "join_abandoned_broad", "join_sweep"):
    ORACLE_SQL[_name] = f"WITH {_FACT} SELECT vec_id, region, round({_D}, 6) AS dist FROM docs JOIN dim USING (customer_id) WHERE region = 'EUROPE' ORDER BY {_D}, vec_id LIMIT 10"
ORACLE_SQL["knn_sidecar"] = _top("vec_id, label", "label = 3")
ORACLE_SQL["op_knn_table_function"] = ORACLE_SQL["knn_brute"]
ORACLE_SQL["op_vector_mean"] = "SELECT label, i - 1 AS i, round(avg(embedding[i]::DOUBLE), 6) AS mean FROM embeddings, unnest(range(1, 65)) AS t(i) GROUP BY label, i"
ORACLE_SQL["knn_brute_arrow"] = ORACLE_SQL["knn_brute"]
ORACLE_SQL["knn_wide_inline"] = ORACLE_SQL["knn_wide_lookup"]

QUERIES = {
    "knn_filtered_value_local": W._filtered("value_local", "label = 3"),
    "knn_filtered_uniform": W._filtered("uniform", "label = 3"),
    "knn_filtered_range": W._filtered("by_length", "n_chars >= 500 and n_chars < 2000"),
    "knn_filtered_in_list": W._filtered("uniform", "label in (1, 4, 7) and lang in ('de', 'fr')"),
    "knn_filtered_negated": W._filtered("value_local", "not (label in (1, 4, 7) or lang like 'e%')"),
    "knn_filtered_opaque": W._filtered("uniform", "n_chars % 3 = 1", overfetch=1000),
    "knn_pure_gate": W._filtered("value_local", "label = 3", gate="pure"),
    "knn_empty_survivors": W._filtered("value_local", "label = 99"),
    "join_reduced_region": W._join(),
    "join_abandoned_broad": W._join(max_keys=3),
    "join_sweep": W._join(mode="sweep", join_overfetch=40),
} | {
    name: getattr(W, name)
    for name in (
        "knn_brute", "knn_brute_arrow", "knn_ivf_full_probe", "knn_ivf_seed_probe", "knn_sorted_boundary", "knn_postfilter", "knn_policy",
        "knn_mixed_files", "knn_wide_lookup", "knn_wide_inline", "knn_batch_topk", "recall_at_k", "recall_bins", "recall_by_selectivity", "work_by_selectivity", "knn_ablation", "knn_sql_rewrite", "knn_by_waves",
        "selectivity_sweep", "join_materialized_region", "join_refreshed_region", "join_key_set", "join_snowflake_keys", "join_outer_fallback", "join_file_reduction",
        "prune_report_layouts", "scattered_prunes_nothing", "locality_by_column", "zone_map_stats", "presence_index", "files_touched", "files_touched_uniform",
        "worked_trace", "cost_model_grid", "choose_centroids", "placement_hrw", "placement_moved", "table_doubling", "snapshot_replace",
        "time_travel_diff", "ivf_assignments", "kmeans_one_step", "global_ivf_seed", "recall_probe_sweep", "warm_latency", "warm_ablation", "global_ivfpq", "hnsw_service",
        "build_over_clustered", "cost_choice", "op_vector_functions", "op_cube", "op_rollup", "op_pivot", "op_asof_join", "op_range_join",
        "op_session_window", "op_tumbling_window", "op_topk_per_group", "op_set_operations", "op_semi_anti", "op_json", "op_percentiles",
        "op_star_revenue", "op_datasource", "op_stream_ingest", "op_vector_mean", "op_knn_table_function", "knn_file_pq", "knn_sidecar",
    )
}
