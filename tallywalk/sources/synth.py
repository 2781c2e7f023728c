"""Generated streams: a slow tail without a gap between head and tail, and large sets that overlap many small ones. Draws are hashes, so every run gives the same rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tallywalk.sources.pairs import pairs


def uniform(column: Column, tag: str) -> Column:
    """A draw in [0, 1) that depends on the value alone."""
    return F.shiftrightunsigned(F.xxhash64(F.lit(tag), column), 11) / F.lit(float(1 << 53))


def slow_tail(spark: SparkSession, n_labels: int = 100_000, exponent: float = 0.2, entries: int = 100_000_000, seed: int = 0) -> DataFrame:
    """Entries with items of their own and a label drawn with a chance of rank ** -exponent: the inverse of the cumulated chances, in closed form."""
    rows = spark.range(entries)
    rank = F.floor(F.lit(float(n_labels)) * F.pow(uniform(F.col("id"), f"tail{seed}"), F.lit(1 / (1 - exponent)))) + 1
    return pairs(rows.select("id", rank.alias("label")), "label", "id", order_by=["id"])


def overlap(spark: SparkSession, n_small: int = 100_000, n_big: int = 20_000, big_sets: int = 1000, small_size: int = 1000, universe: int = 1_000_000, common: int = 100_000, seed: int = 0) -> DataFrame:
    """n_small sets of small_size items from the common part, then big_sets sets of n_big items from all of the universe."""

    def sets(count: int, size: int, items: int, name: str) -> DataFrame:
        rows = spark.range(count * size).select(F.floor(F.col("id") / size).alias("k"), "id")
        return rows.select(F.concat(F.lit(name), "k").alias("label"), F.floor(uniform(F.col("id"), f"{name}{seed}") * items).alias("item"), "id")

    rows = sets(n_small, small_size, common, "small").union(sets(big_sets, n_big, universe, "big"))
    # small and big sets come in one mixed order
    return pairs(rows.withColumn("at", F.xxhash64("label", "id")), "label", "item", order_by=["at"])
