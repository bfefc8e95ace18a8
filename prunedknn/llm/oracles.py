"""DuckDB SQL for the operators that SQL can express; the others are tested by brute force."""

#: crc32 by its byte table (made by the rule, eight shifts an entry), one fold over the text's bytes.
_CRC32 = """
WITH RECURSIVE steps(i, k, c) AS (
  SELECT range, 0, range::BIGINT FROM range(256)
  UNION ALL
  SELECT i, k + 1, CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END FROM steps WHERE k < 8
), lookup AS (SELECT list(c ORDER BY i) AS t FROM steps WHERE k = 8),
"""

_SHARDS = _CRC32 + """
raw AS (
  SELECT doc_id, coalesce(octet_length(encode(text)), 0) + 1 AS size, coalesce(text, '') AS text,
         CASE WHEN source IS NULL THEN 'n' ELSE 's' || source END AS source FROM documents
), coded AS (
  SELECT doc_id, size, source,
    xor(4294967295, list_reduce(
      list_prepend(4294967295::BIGINT,
        list_transform(range(1, octet_length(encode(text)) + 1),
          lambda i: ('0x' || hex(encode(text))[2 * i - 1 : 2 * i])::BIGINT)),
      lambda c, b: xor(c >> 8, t[(xor(c, b) & 255) + 1]))) AS text_crc32
  FROM raw, lookup
), mixed AS (
  SELECT *, md5('mix-1|' || coalesce(doc_id::VARCHAR, 'null') || '|' || size || '|' || text_crc32) AS m FROM coded
), inside AS (
  SELECT *, row_number() OVER (PARTITION BY source ORDER BY m) - 1 AS r, count(*) OVER (PARTITION BY source) AS n FROM mixed
), placed AS (
  SELECT *, count(*) OVER () AS total, row_number() OVER (ORDER BY
    (r + ('0x' || md5('mix-1' || source)[1:8])::BIGINT::DOUBLE / 4294967296.0) / n, source, m) - 1 AS position FROM inside
)
SELECT doc_id, size::BIGINT AS size, text_crc32, 'rows' AS law, (position * 8 // total)::INTEGER AS shard,
  (row_number() OVER (PARTITION BY position * 8 // total ORDER BY position) - 1)::BIGINT AS slot, NULL::INTEGER AS grown_shard
FROM placed
"""

#: The article of the given pages' one template: tags out, references decoded, blocks in order.
_PAGES = r"""
WITH body AS (
  SELECT page_id, url, regexp_extract(html, '(?s)<article>(.*?)</article>', 1) AS a FROM pages
), blocks AS (
  SELECT page_id, url, string_split(regexp_replace(regexp_replace(a, '<br>', ' ', 'g'), '</?(p|h1)>', chr(1), 'g'), chr(1)) AS b FROM body
), clean AS (
  SELECT page_id, url, list_filter(list_transform(b, lambda x: trim(regexp_replace(
    replace(replace(replace(replace(replace(regexp_replace(regexp_replace(x, '<[^>]*>', '', 'g'), '&amp(;)?', '&', 'g'),
      '&quot;', '"'), '&#x27;', ''''), '&lt;', '<'), '&gt;', '>'), '&#39;', ''''), '\s+', ' ', 'g'))), lambda x: x <> '') AS b FROM blocks
)
SELECT page_id, url, coalesce(array_to_string(b, chr(10) || chr(10)), '') AS text,
  length(coalesce(array_to_string(b, chr(10) || chr(10)), ''))::BIGINT AS n_chars FROM clean
"""

_AZ = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

_NEAR = rf"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all({_AZ}, '[^\x20\x09-\x0D]+') AS w FROM documents
), s AS (
  SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) = 1 THEN [w[1]]
    ELSE list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) END) AS s FROM w
), n AS (SELECT doc_id, len(s)::BIGINT AS n FROM s),
e AS (SELECT doc_id, unnest(s) AS g FROM s),
f AS (SELECT g FROM e GROUP BY g HAVING count(*) > 1),
x AS MATERIALIZED (SELECT e.doc_id, e.g FROM e JOIN f USING (g)),
pairs AS MATERIALIZED (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM x a JOIN x b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL
), links AS MATERIALIZED (
  SELECT p.a, p.b FROM pairs p JOIN n m ON m.doc_id = p.a JOIN n o ON o.doc_id = p.b WHERE 100 * p.i >= 80 * (m.n + o.n - p.i)
), both_ways AS MATERIALIZED (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach(a, b) AS (SELECT doc_id, doc_id FROM n UNION SELECT r.a, l.b FROM reach r JOIN both_ways l ON l.a = r.b)
SELECT n.doc_id, n.n AS n_shingles, min(reach.b) AS component_id, n.doc_id = min(reach.b) AS kept
FROM n JOIN reach ON reach.a = n.doc_id GROUP BY n.doc_id, n.n
"""

_LEAKS = rf"""
WITH dw AS (
  SELECT doc_id, regexp_extract_all({_AZ}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), bw AS (
  SELECT item_id, regexp_extract_all({_AZ}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark
), win AS (
  SELECT DISTINCT item_id, least(len(w), 10) AS k, array_to_string(w[i : i + least(len(w), 10) - 1], ' ') AS g
  FROM bw, unnest(range(1, greatest(len(w) - 10, 0) + 2)) AS t(i) WHERE len(w) > 0
), ks AS (SELECT DISTINCT k FROM win),
grams AS (
  SELECT doc_id, k, i, array_to_string(w[i : i + k - 1], ' ') AS g FROM dw, ks, unnest(range(1, len(w) - k + 2)) AS t(i)
), hits AS MATERIALIZED (SELECT doc_id, item_id, i, k FROM grams JOIN win USING (k, g)),
cover AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM hits, unnest(range(i, i + k)) AS t(p) GROUP BY doc_id),
items AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids
  FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS item_id FROM hits) GROUP BY doc_id
)
SELECT dw.doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM dw LEFT JOIN cover USING (doc_id) LEFT JOIN items USING (doc_id)
"""

_URLS = r"""
WITH u AS (
  SELECT page_id, url, CASE WHEN contains(url, '://') THEN
    split_part(split_part(substr(url, strpos(url, '://') + 3), '#', 1), '?', 1) END AS rest FROM pages
), p AS (
  SELECT page_id, url,
    coalesce(translate(split_part(rest, '/', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
    coalesce(CASE WHEN contains(rest, '/') THEN substr(rest, strpos(rest, '/')) END, '') AS path FROM u
), t AS (
  SELECT *, list_sort(list_distinct(list_filter(list_concat(
    list_transform(string_split(host, '.'), lambda x: 'host=' || x),
    list_transform(string_split_regex(regexp_replace(path, '[0-9]+', '0', 'g'), '[/._-]+'), lambda x: 'path=' || x),
    list_transform(string_split(regexp_extract(coalesce(url, ''), '\?([^#]*)', 1), '&'), lambda x: 'query=' || split_part(x, '=', 1))),
    lambda x: x NOT IN ('host=', 'path=', 'query=')))) AS tokens FROM p
), marks AS (
  SELECT doc_id, max(CASE WHEN quality = 0 OR toxic = 1 THEN 1 ELSE 0 END) AS bad FROM labels
  WHERE quality IS NOT NULL OR toxic IS NOT NULL GROUP BY doc_id
), b AS (
  SELECT tokens, bad FROM t JOIN marks ON doc_id = try_cast(nullif(regexp_extract(path, '/([0-9]+)', 1), '') AS BIGINT)
), least_n AS (SELECT ceil(greatest(0.005, 5.0 / greatest(count(*), 1)) * count(*)) AS m FROM b),
sets AS (
  SELECT array_to_string(list_filter(tokens, lambda x, i: (s >> (i - 1)) & 1 = 1), ' ') AS k,
    list_filter(tokens, lambda x, i: (s >> (i - 1)) & 1 = 1) AS xs, bad
  FROM b, unnest(range(1, (1 << len(tokens))::BIGINT)) AS q(s)
), rules AS (
  SELECT k, any_value(xs) AS xs FROM sets GROUP BY k
  HAVING sum(bad) >= (SELECT m FROM least_n) AND sum(bad)::DOUBLE / count(*) >= 0.5
), mined AS (SELECT DISTINCT tokens FROM t, rules WHERE list_has_all(tokens, xs)),
given(kind, domain, start) AS (VALUES ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'),
  ('allow', 'com', '/fr/'), ('block', 'com', '/de/')),
fit AS (
  SELECT page_id, url, arg_max(domain || start, length(domain || start)) AS rule, arg_max(kind, length(domain || start)) AS kind
  FROM (SELECT DISTINCT page_id, url, host, path FROM t), given
  WHERE (host = domain OR ends_with(host, '.' || domain)) AND starts_with(path, start) GROUP BY page_id, url
)
SELECT t.page_id, t.host, t.path, fit.rule, coalesce(fit.kind, CASE WHEN mined.tokens IS NOT NULL THEN 'block' ELSE 'allow' END) AS verdict
FROM t LEFT JOIN fit ON fit.page_id = t.page_id AND fit.url IS NOT DISTINCT FROM t.url LEFT JOIN mined ON mined.tokens = t.tokens
"""

ORACLE_SQL = {
    "op1_shard_mixture": _SHARDS,
    "op2_html_difference": _PAGES,
    "op4_minhash_bbit": _NEAR,
    "op7_url_rules": _URLS,
    "op9_fm_decontam": _LEAKS,
}
