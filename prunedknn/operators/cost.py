"""What a search costs, by counting, and which path that favours."""

from __future__ import annotations

from dataclasses import dataclass

from ..manifest import Table
from ..plans.pred import Pred
from ..plans.prune import plan_survivors


@dataclass(frozen=True)
class Cost:
    """files: surviving; candidates: rows re-scored; centroids: distances to centroids; reduction: all
    rows over candidates alone; reduction_with_centroids: over both; bytes_ratio: of the bytes read."""

    files: float
    candidates: float
    centroids: float
    reduction: float
    reduction_with_centroids: float
    bytes_ratio: float


def predict(n: float, files: float, c: int, p: int, sigma: float) -> Cost:
    """n rows in so many files of c centroids, p lists probed, a fraction sigma of the files left."""
    p = min(p, c)
    left = files * sigma
    candidates = n * sigma * p / c
    centroids = left * c
    whole = candidates + centroids
    return Cost(left, candidates, centroids, n / candidates if candidates else float("inf"), n / whole if whole else float("inf"), sigma)


def choose(table: Table, pred: Pred | None, k: int, nprobe: int = 10) -> tuple[str, Cost]:
    """brute, pruned (index within the survivors) or sweep (index everywhere, filter later), by
    distances to compute; the fraction comes from the manifest."""
    _, report = plan_survivors(table, pred)
    manifest = table.manifest()
    if not report.rows_surviving:
        return "empty", predict(max(report.rows_total, 1), max(report.files_total, 1), 1, 1, 0.0)
    from pyspark.sql import functions as F

    c = max(1, round(manifest.agg(F.avg("centroids")).first()[0] or 1))
    sigma = report.files_surviving / max(report.files_total, 1)
    pruned = predict(report.rows_total, report.files_total, c, nprobe, sigma)
    brute = report.rows_surviving
    if c <= 1 or brute <= pruned.candidates + pruned.centroids:
        return "brute", pruned
    return ("sweep" if sigma > 0.95 else "pruned"), pruned
