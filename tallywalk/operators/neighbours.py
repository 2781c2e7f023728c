"""What stands beside the walks: a gate before them, overlaps of label sets, entry counts and size distributions by Spark's own sketches, uncertainty of merges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallywalk.functions.hashing import draw, hash52
from tallywalk.operators.sketches import Sketches


def pre_gate(pairs: DataFrame, sketch: Sketches, whole_labels: bool = True) -> DataFrame:
    """The pairs that a sketch, taken further, could use. A JVM filter, so that the rest never reaches Python.

    whole_labels: all pairs of its members, and of labels with any pair whose draw beats its threshold; the others can never be let in, so the walk ends as if it had seen all
    (one shuffle by label). Otherwise only the members' pairs and those that beat the threshold themselves: no shuffle, but what a label let in later had before its own draws is lost. For another stream
    than the sketch's either is an approximation."""
    hash, gate_on, seed = sketch.hash_id.split(":")
    gate = F.col("item_key") if gate_on == "item" else F.concat_ws("\1", "label_key", "item_key")
    # at most s labels, and one number
    counters, facts = sketch.facts()
    members = pairs.sparkSession.createDataFrame([(x, True) for x in sorted({r["label_key"] for r in counters})], "label_key string, member boolean")
    told = pairs.join(F.broadcast(members), "label_key", "left")
    passed = told.where(F.col("member") | (draw(hash52(gate, "g", hash, int(seed))) > facts["threshold"]))
    if whole_labels:
        return pairs.join(passed.select("label_key").distinct(), "label_key", "left_semi").select(*pairs.columns)
    return passed.select(*pairs.columns)


def theta_overlap(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """first, second, both, either: estimated overlap of the item sets of given pairs of labels (first, second)."""
    asked = labels.select(F.explode(F.array("first", "second")).alias("label_key")).distinct()
    sketches = pairs.join(asked, "label_key", "left_semi").groupBy("label_key").agg(F.theta_sketch_agg("item_key").alias("sketch"))
    one = lambda side: sketches.select(F.col("label_key").alias(side), F.col("sketch").alias(f"s_{side}"))
    both = labels.join(one("first"), "first").join(one("second"), "second")
    return both.select("first", "second", F.theta_sketch_estimate(F.theta_intersection("s_first", "s_second")).alias("both"), F.theta_sketch_estimate(F.theta_union("s_first", "s_second")).alias("either"))


def size_quantiles(sizes: DataFrame, at: list[float], column: str = "d") -> DataFrame:
    """Approximate quantiles of the sizes of all labels, in one pass."""
    return sizes.agg(F.percentile_approx(column, at, 10_000).alias("q")).select(F.posexplode("q").alias("i", "size")).select(F.get(F.array(*map(F.lit, at)), F.col("i")).alias("at"), "size")


def merge_uncertainty(streams: Sketches, merged: Sketches) -> DataFrame:
    """The merged answer with what each label may have lost: the sum of the floors of the streams that do not hold it."""
    floors = streams.meta.select("sketch_id", "floor")
    every = floors.agg(F.sum("floor").alias("every"))
    known = streams.counters.select("sketch_id", "label_key").join(F.broadcast(floors), "sketch_id").groupBy("label_key").agg(F.sum("floor").alias("known"))
    told = merged.counters.select("label_key", "estimate").join(known, "label_key", "left").join(F.broadcast(every))
    return told.select("label_key", "estimate", (F.col("every") - F.coalesce("known", F.lit(0.0))).alias("may_miss"))


def false_positives(answer: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Reported labels that are not among the true k largest."""
    best = truth.orderBy(F.desc("d"), "label_key").limit(k).select("label_key")
    return answer.orderBy(F.desc("estimate"), "label_key").limit(k).join(F.broadcast(best), "label_key", "left_anti")


def size_bands(sizes: DataFrame, bands: DataFrame) -> DataFrame:
    """Number of labels in each band (name, low, high), high excluded: a range join with a few rows."""
    hit = sizes.join(F.broadcast(bands), (F.col("d") >= F.col("low")) & (F.col("d") < F.col("high")))
    return hit.groupBy("name").agg(F.count(F.lit(1)).alias("labels"))
