"""URL filtering by association rules, with DataFrame and SQL functions only.

Spark's FP-growth mines which combinations of URL tokens go with a bad label; rules are
pruned by support and confidence, then by redundancy (a rule that holds all tokens of another
adds nothing), and matched through an inverted index from token to rule. Equal token sets are
matched once; what was found goes back to the pages salted, since one set may stand for a third
of them.
A list of host and path rules stands before them: the longest that fits decides.

Edge cases: a null url and one without "://" have an empty host and path and no tokens;
repeated rows are each judged; with no labelled page, or none that is bad, no rule is mined
and the method allows; empty tables give no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._shared import written

LEAST_SHARE, LEAST_COUNT, LEAST_CONFIDENCE = 0.005, 5, 0.5
SALTS = 64
BAD = "label=bad"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _after(url: Column) -> Column:
    return F.when(F.instr(url, "://") > 0, F.substring_index(F.expr("substr(_url, instr(_url, '://') + 3)"), "#", 1))


def parts(pages: DataFrame, url_col: str = "url") -> DataFrame:
    """pages with host and path."""
    cut = F.substring_index(_after(F.col("_url")), "?", 1)
    return (
        pages.withColumn("_url", F.col(url_col))
        .withColumn("_rest", cut)
        .withColumn("host", F.coalesce(F.translate(F.substring_index("_rest", "/", 1), _UPPER, _LOWER), F.lit("")))
        .withColumn(
            "path", F.coalesce(F.when(F.instr("_rest", "/") > 0, F.expr("substr(_rest, instr(_rest, '/'))")), F.lit(""))
        )
        .drop("_url", "_rest")
    )


def tokens(host: Column, path: Column, url: Column) -> Column:
    """Distinct tokens: host labels, words of the path, its extension, names of the query; numbers stand for any number."""
    labels = F.transform(F.split(host, r"\."), lambda x: F.concat(F.lit("host="), x))
    words = F.transform(
        F.split(F.regexp_replace(path, r"[0-9]+", "0"), r"[/._-]+"), lambda x: F.concat(F.lit("path="), x)
    )
    names = F.transform(
        F.split(F.coalesce(F.regexp_extract(url, r"\?([^#]*)", 1), F.lit("")), "&"),
        lambda x: F.concat(F.lit("query="), F.substring_index(x, "=", 1)),
    )
    found = F.array_distinct(F.concat(labels, words, names))
    return F.filter(found, lambda x: ~x.isin("host=", "path=", "query="))


def longest_fit(host: Column, path: Column, rules: list[tuple[str, str]]) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits; rules: ("block", "example.org/es/")."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, text in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        at = text.index("/")
        fits = (host == text[:at]) | host.endswith("." + text[:at])
        fits = fits & path.startswith(text[at:])
        rule, verdict = F.when(fits, F.lit(text)).otherwise(rule), F.when(fits, F.lit(kind)).otherwise(verdict)
    return rule, verdict


def mine(labelled: DataFrame) -> DataFrame:
    """(rule_id, token, size): mined rules as an inverted index. labelled: (tokens, bad)."""
    spark = labelled.sparkSession
    baskets = written(
        labelled.select(F.when(F.col("bad") == 1, F.array_append("tokens", BAD)).otherwise(F.col("tokens")).alias("items")),
        "url-baskets",
    )
    total = baskets.count()
    empty = spark.createDataFrame([], "rule_id string, token string, size int")
    if not total:
        return empty
    share = max(LEAST_SHARE, LEAST_COUNT / total)
    if share > 1:
        return empty
    model = FPGrowth(itemsCol="items", minSupport=share, minConfidence=LEAST_CONFIDENCE).fit(baskets)
    rules = model.associationRules.where(F.col("consequent") == F.array(F.lit(BAD))).select(
        F.array_join(F.array_sort("antecedent"), " ").alias("rule_id"), "antecedent"
    )
    index = written(
        rules.select("rule_id", F.explode("antecedent").alias("token"), F.size("antecedent").cast("int").alias("size")), "url-mined"
    )
    # a rule is redundant if a shorter one has all its tokens among this one's
    inside = (
        index.select("rule_id", "token", F.col("size").alias("_long"))
        .join(index.select(F.col("rule_id").alias("_other"), "token", "size"), "token").where("size < _long")
        .groupBy("rule_id", "_other").agg(F.count("*").alias("n"), F.first("size").alias("size")).where("n = size")
    )
    return written(index.join(inside.select("rule_id").distinct(), "rule_id", "left_anti"), "url-rules")


def judged(pages: DataFrame, labels: DataFrame, rules: list[tuple[str, str]], id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """(id, host, path, rule, verdict, mined) of every page; labels: (doc_id, quality, toxic), where
    the number in a page's path names the document it shows."""
    cut = parts(pages.select(id_col, url_col), url_col).withColumn(
        "tokens", tokens(F.col("host"), F.col("path"), F.coalesce(F.col(url_col), F.lit("")))
    )
    number = F.expr("try_cast(regexp_extract(path, '/([0-9]+)', 1) AS BIGINT)")
    marks = labels.where("quality is not null or toxic is not null").groupBy("doc_id").agg(
        F.max(F.when((F.col("quality") == 0) | (F.col("toxic") == 1), 1).otherwise(0)).alias("bad")
    )
    labelled = cut.withColumn("doc_id", number).join(marks, "doc_id").select("tokens", "bad")
    index = mine(labelled)
    # a page's tokens are few; equal token sets are matched once
    key = F.array_join(F.array_sort("tokens"), " ")
    sets = cut.select(key.alias("_key"), "tokens").distinct().select("_key", F.explode("tokens").alias("token"))
    hits = (
        sets.join(index, "token").groupBy("_key", "rule_id").agg(F.count("*").alias("n"), F.first("size").alias("size"))
        .where("n = size").groupBy("_key").agg(F.min("rule_id").alias("mined"))
    )
    rule, verdict = longest_fit(F.col("host"), F.col("path"), rules)
    salt = F.pmod(F.xxhash64(F.col(id_col).cast("string"), F.col(url_col).cast("string"), F.monotonically_increasing_id()), F.lit(SALTS))
    hits = hits.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))).alias("_salt"))
    return (
        cut.withColumn("_key", key).withColumn("_salt", salt).join(hits, ["_key", "_salt"], "left")
        .select(
            id_col, "host", "path", rule.alias("rule"),
            F.coalesce(verdict, F.when(F.col("mined").isNotNull(), F.lit("block")).otherwise(F.lit("allow"))).alias("verdict"),
            "mined",
        )
    )


