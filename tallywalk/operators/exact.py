"""The exact answer, and baselines that are neither walks nor grids."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallywalk.functions.hashing import HASH_BITS, hash52
from tallywalk.functions.registers import estimate_of
from tallywalk.operators.sketches import Sketches, build_sketch
from tallywalk.operators.walk import EntryTable
from tallywalk.sources.pairs import with_hashes


def exact_sizes(pairs: DataFrame) -> DataFrame:
    """label_key, d. Distinct pairs first, so that a label with very many items is counted by all tasks."""
    return pairs.select("label_key", "item_key").distinct().groupBy("label_key").agg(F.count(F.lit(1)).alias("d"))


def label_count(pairs: DataFrame) -> int:
    """How many labels there are: the room that a walk needs to drop none. One pass, now."""
    return pairs.agg(F.count_distinct("label_key")).first()[0]


def exact_top_k(pairs: DataFrame, k: int) -> DataFrame:
    return exact_sizes(pairs).orderBy(F.desc("d"), "label_key").limit(k)


def label_registers(pairs: DataFrame, m: int = 1024, hash: str = "portable", by: list[str] | None = None) -> DataFrame:
    """The registers of one counter for each label (and group): label_key, bucket, rank of the filled ones. Merging is taking the maximum again."""
    hashed = with_hashes(pairs, m, hash)
    return hashed.groupBy(*(by or []), "label_key", "bucket").agg(F.max("rank").alias("rank"))


def register_estimates(registers: DataFrame, m: int, estimator: str = "histogram", by: list[str] | None = None) -> DataFrame:
    keys = [*(by or []), "label_key"]
    sums = registers.groupBy(*keys).agg(F.count(F.lit(1)).alias("filled"), F.sum(F.pow(F.lit(2.0), -F.col("rank"))).alias("powers"))
    return sums.select(*keys, estimate_of(estimator, m, F.col("filled"), F.col("powers")).alias("estimate"))


def per_label_sketch(pairs: DataFrame, lgk: int = 10) -> DataFrame:
    """One of the JVM's own sketches for each label: as many as there are labels."""
    made = pairs.groupBy("label_key").agg(F.hll_sketch_agg(F.col("item_key"), F.lit(lgk)).alias("sketch"))
    return made.select("label_key", F.hll_sketch_estimate("sketch").cast("double").alias("estimate"))


def approx_distinct(pairs: DataFrame, rsd: float = 0.05) -> DataFrame:
    return pairs.groupBy("label_key").agg(F.approx_count_distinct("item_key", rsd).cast("double").alias("estimate"))


def distinct_count(df: DataFrame, item: str, exact: bool = False, rsd: float = 0.05) -> DataFrame:
    """The number of distinct items of a single set."""
    return df.agg((F.count_distinct(item) if exact else F.approx_count_distinct(item, rsd)).alias("d"))


def inverse_min_hash(pairs: DataFrame, hash: str = "portable") -> DataFrame:
    """The largest draw of each label's items: a rough size from one number. Its mean is infinite; look at medians."""
    least = F.min((hash52(F.col("item_key"), "g", hash) + F.lit(0.5)) / F.lit(float(1 << HASH_BITS)))
    return pairs.groupBy("label_key").agg((1 / least).alias("estimate"))


def sampled_pairs(pairs: DataFrame, rate: float, hash: str = "fast") -> DataFrame:
    """Pairs whose hash falls under the rate are kept, by value and so without repeats mattering; distinct ones are counted and scaled up."""
    pair = hash52(F.concat_ws("\1", "label_key", "item_key"), "p", hash)
    kept = pairs.where(pair < F.lit(int(rate * (1 << HASH_BITS))))
    return exact_sizes(kept).select("label_key", (F.col("d") / F.lit(rate)).alias("estimate"))


def sampled_sketch(pairs: DataFrame, s: int, rate: float, **options) -> Sketches:
    """The nearest relative that samples and sketches: a fixed gate of the pair's hash before a recycled walk. Our own guess at a method whose text is
    missing; it can't be merged exactly and is not scored."""
    hash = options.get("hash", "fast")
    kept = pairs.where(hash52(F.concat_ws("\1", "label_key", "item_key"), "p", hash) < F.lit(int(rate * (1 << HASH_BITS))))
    return build_sketch(kept, kind="recycled", s=s, **options)


def heavy_entries(pairs: DataFrame, s: int) -> DataFrame:
    """Plain heavy hitters: labels by entries, repeats included. A table of s counters for each partition; counts are added over partitions."""
    slim = pairs.select("label_key")

    def walk(batches):
        import pyarrow as pa

        table = EntryTable(s)
        for b in batches:
            table.consume(b.column(0).to_pylist())
        if table.counts:
            yield pa.RecordBatch.from_pydict({"label_key": list(table.counts), "entries": [c for (c,) in table.counts.values()]})

    return slim.mapInArrow(walk, "label_key string, entries bigint").groupBy("label_key").agg(F.sum("entries").alias("entries")).orderBy(F.desc("entries"), "label_key").limit(s)


def zero_answer(truth: DataFrame) -> DataFrame:
    """Every size 0: whatever scores above 1 is worse than this."""
    return truth.select("label_key", F.lit(0.0).alias("estimate"))
