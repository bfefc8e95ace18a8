"""Proportional stratified interleaving of documents into shards.

Rows are shuffled with a seed inside their source, get a fractional rank in (0, 1) there,
and the order by that fraction over all sources is cut into equal runs. Each run then holds
every source in the proportion of the whole, to within two rows a source.

Edge cases: a null source is a stratum of its own; null and empty texts have size 1; an
empty table gives no rows; rows that are equal in all inputs are interchangeable, each gets
its own slot; a text of any length is only measured; other columns are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._shared import ranked, written

LAW = "rows"


def _hex_unit(text: Column) -> Column:
    """The first 32 bits of md5(text) as a fraction of 2**32; exact in a double."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def stratum(source: Column) -> Column:
    return F.when(source.isNull(), F.lit("n")).otherwise(F.concat(F.lit("s"), source.cast("string")))


def interleave(
    docs: DataFrame, shards: int, seed: str = "mix-1", id_col: str = "doc_id", text_col: str = "text",
    source_col: str = "source",
) -> DataFrame:
    """(id, size, text_crc32, source, position, shard, slot) of every row.

    Only narrow columns are shuffled: texts are measured where they are read. The ranks in a
    source come from a global order (source, seeded hash), so a source with a third of all
    rows is spread like any other.
    """
    size = F.coalesce(F.octet_length(F.col(text_col)), F.lit(0)).cast("long") + 1
    crc = F.coalesce(F.crc32(F.col(text_col).cast("binary")), F.lit(0).cast("long"))
    ident = F.coalesce(F.col(id_col).cast("string"), F.lit("null"))
    narrow = docs.select(
        F.col(id_col), size.alias("size"), crc.alias("text_crc32"), stratum(F.col(source_col)).alias("source"),
    ).withColumn("_mixed", F.md5(F.concat_ws("|", F.lit(seed), ident, F.col("size"), F.col("text_crc32"))))
    inside = ranked(narrow, ["source", "_mixed"], "_at", "mixture-source")
    # one row a source, written so that its size is known: a small one goes to the rows, not the rows to it
    strata = written(inside.groupBy("source").agg(F.min("_at").alias("_start"), F.count("*").alias("_n")), "mixture-strata")
    fraction = (F.col("_at") - F.col("_start") + _hex_unit(F.concat(F.lit(seed), F.col("source")))) / F.col("_n")
    spread = inside.join(strata, "source").select(*narrow.columns, fraction.alias("_fraction"))
    placed = ranked(spread, ["_fraction", "source", "_mixed"], "position", "mixture-order")
    total = max(placed.count(), 1)  # one number; placed reads a written table
    shard = F.floor(F.col("position") * F.lit(shards) / F.lit(float(total)))
    start = F.ceil(F.col("shard") * F.lit(float(total)) / F.lit(float(shards)))
    return (
        placed.withColumn("shard", shard.cast("int"))
        .select(
            F.col(id_col), "size", "text_crc32", "source", "position", "shard",
            (F.col("position") - start).cast("long").alias("slot"),
        )
    )
