"""Bins of at most L documents in a seeded order that doesn't depend on how the data is partitioned."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def shuffle_key(seed, turn, id_col: str = "id") -> Column:
    """md5 of seed, turn and id: the same order in any engine."""
    return F.md5(F.concat(F.lit(f"{seed}:{turn}:"), F.col(id_col).cast("string")).cast("binary"))


def positions(items: DataFrame, seed, turn, keys: list[str], digits: int = 3) -> DataFrame:
    """Adds ``pos``, from 0 within the keys, in the order of the shuffle key.

    No task sorts a whole scope: counts by the key's first hex digits give each slice its offset, and only slices are
    numbered. ``digits`` sets how many slices a scope has (16 to that power).
    """
    x = items.withColumn("_key", shuffle_key(seed, turn)).withColumn("_slice", F.substring("_key", 1, digits))
    counts = x.groupBy(*keys, "_slice").agg(F.count("*").alias("_n"))
    before = W.partitionBy(*keys).orderBy("_slice").rowsBetween(W.unboundedPreceding, -1)
    offsets = counts.withColumn("_offset", F.coalesce(F.sum("_n").over(before), F.lit(0))).drop("_n")
    numbered = x.withColumn("_at", F.row_number().over(W.partitionBy(*keys, "_slice").orderBy("_key", "id")) - 1)
    return numbered.join(offsets, [*keys, "_slice"]).withColumn("pos", (F.col("_offset") + F.col("_at")).cast("long")).drop("_slice", "_offset", "_at", "_key")


def assign_bins(items: DataFrame, size: int, seed, turn, keys: list[str] | None = None, mode: str = "exact") -> DataFrame:
    """Adds ``bin`` and ``slot``. exact: consecutive positions of the shuffle; balanced: bin sizes differ by at most one;
    local: chunks inside partitions, without an exchange, ragged at each partition's end."""
    keys = keys or ["scope"]
    if mode == "local":
        n = F.monotonically_increasing_id()
        x = items.withColumn("_n", n)
        return x.withColumn("bin", F.floor(F.col("_n") / size)).withColumn("slot", F.pmod(F.col("_n"), F.lit(size)).cast("int")).drop("_n")
    x = positions(items, seed, turn, keys)
    if mode == "balanced":
        total = items.groupBy(*keys).agg(F.ceil(F.count("*") / size).alias("_bins"))
        return x.join(total, keys).withColumn("bin", F.pmod("pos", F.col("_bins"))).withColumn("slot", F.floor(F.col("pos") / F.col("_bins")).cast("int")).drop("_bins", "pos")
    return x.withColumn("bin", F.floor(F.col("pos") / size)).withColumn("slot", F.pmod(F.col("pos"), F.lit(size)).cast("int")).drop("pos")
