"""Recall, latency and counting measures."""

from __future__ import annotations

import math
import statistics
import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def recall_at_k(found: DataFrame, truth: DataFrame, k: int, id_col: str = "id") -> DataFrame:
    """(query_id, recall) for every query of truth; ids as sets, over k."""
    hits = truth.select("query_id", id_col).join(found.select("query_id", id_col), ["query_id", id_col]).groupBy("query_id").agg(F.count("*").alias("hit"))
    asked = truth.groupBy("query_id").agg(F.count("*").alias("n"))
    return asked.join(hits, "query_id", "left").select("query_id", (F.coalesce("hit", F.lit(0)) / F.least(F.col("n"), F.lit(k))).alias("recall"))


def recall_distribution(recalls: DataFrame) -> DataFrame:
    return recalls.agg(F.avg("recall").alias("mean"), F.min("recall").alias("least"), F.percentile("recall", 0.1).alias("p10"), F.count("*").alias("queries"))


def recall_histogram(recalls: DataFrame, bins: int = 10) -> DataFrame:
    return recalls.select(F.floor(F.col("recall") * bins).alias("bin")).groupBy("bin").agg(F.count("*").alias("queries"))


def same_rows(a: DataFrame, b: DataFrame) -> bool:
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def outside(rows: DataFrame, condition: str) -> int:
    """Returned rows that do not satisfy the filter; must be 0."""
    return rows.where(f"NOT coalesce(({condition}), false)").count()


def percentile(values: Sequence[float], p: float) -> float:
    ordered = sorted(values)
    return ordered[min(len(ordered) - 1, max(0, math.ceil(p / 100 * len(ordered)) - 1))]


def latency(runs: Sequence[Callable[[], object]], repeats: int = 3, warm_up: int = 1) -> dict[str, float]:
    """Each query's median of so many runs, then percentiles over queries; the first warm_up queries are
    run once before and their time is given apart."""
    cold = []
    for run in runs[:warm_up]:
        began = time.time()
        run()
        cold.append(time.time() - began)
    medians = []
    for run in runs:
        times = []
        for _ in range(repeats):
            began = time.time()
            run()
            times.append(time.time() - began)
        medians.append(statistics.median(times))
    return {f"p{p}": percentile(medians, p) for p in (50, 90, 95, 99)} | {"cold_first": cold[0] if cold else 0.0}


def speedup(own: dict[str, float], brute: dict[str, float]) -> float:
    return brute["p50"] / own["p50"]
