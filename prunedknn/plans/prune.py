"""Which files a predicate can touch, from statistics alone; the manifest stays a DataFrame throughout."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..manifest import Table
from .pred import TIERS, Pred


@dataclass
class PruneReport:
    files_total: int
    files_surviving: int
    rows_total: int
    rows_surviving: int
    pruned_by: dict[str, int] = field(default_factory=dict)


def survivors(manifest: DataFrame, pred: Pred | None, tiers=TIERS) -> DataFrame:
    """manifest rows that may hold a match, with verdict "all" where every row must match, else "some"."""
    if pred is None:
        return manifest.withColumn("verdict", F.lit("all"))
    return manifest.where(pred.might(tiers)).withColumn("verdict", F.when(pred.must(), F.lit("all")).otherwise(F.lit("some")))


def plan_survivors(table: Table, pred: Pred | None, tiers=TIERS) -> tuple[DataFrame, PruneReport]:
    """(survivors, report); each tier is charged with the files that the tiers before it left."""
    manifest = table.manifest()
    if pred is None:  # every file is left: the snapshot knows how many
        meta = table.meta()
        return survivors(manifest, pred, tiers), PruneReport(meta["n_files"], meta["n_files"], meta["n_rows"], meta["n_rows"], dict.fromkeys(tiers, 0))
    aggs = [F.count("*").alias("n"), F.coalesce(F.sum("rows"), F.lit(0)).alias("r")]
    alive = F.lit(True)
    for tier in tiers:
        own = pred.might((tier,))
        aggs.append(F.count_if(alive & ~own).alias(f"by_{tier}"))
        alive = alive & own
    kept = alive & pred.might(tiers)
    aggs += [F.count_if(kept).alias("left"), F.coalesce(F.sum(F.when(kept, F.col("rows"))), F.lit(0)).alias("rows_left")]
    got = manifest.agg(*aggs).first()
    report = PruneReport(got["n"], got["left"], got["r"], got["rows_left"], {t: got[f"by_{t}"] for t in tiers})
    return survivors(manifest, pred, tiers), report


def by_ball(manifest: DataFrame, q: list[float], bound: float) -> DataFrame:
    """Files whose ball of vectors reaches within bound of q: distance(q, centre) - radius <= bound."""
    from ..functions.vectors import l2_distance, literal

    gap = l2_distance(F.col("ball.centre"), literal(q)) - F.col("ball.radius")
    return manifest.where(F.coalesce(gap <= F.lit(float(bound)), F.lit(True)))


def pure_columns(table: Table) -> set[str]:
    """Columns of which every file holds one value: partition and recorded value-set columns. Sort and
    z-order columns are left out even where a file happens to hold one value."""
    return set(table.meta()["pure_columns"])
