"""Accuracy measures over true and self-reported heavy sets, and statistics of pairs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tallywalk.operators.exact import exact_sizes
from tallywalk.operators.sketches import Sketches

KS = (10, 100, 1000)


def first_k(df: DataFrame, value: str, k: int, tie: str = "label_key") -> DataFrame:
    return df.orderBy(F.desc(value), tie).limit(k)


def true_heavy(truth: DataFrame, k: int) -> DataFrame:
    """The k labels of the most distinct items, ties by label."""
    return first_k(truth, "d", k)


def reported_heavy(answer: DataFrame, k: int) -> DataFrame:
    """The k labels that the answer itself puts first."""
    return first_k(answer, "estimate", k)


def scored(labels: DataFrame, answer: DataFrame, truth: DataFrame) -> DataFrame:
    """label_key, d, estimate of some labels; what one side does not have is 0 there."""
    out = labels.select("label_key").join(truth.select("label_key", "d"), "label_key", "left").join(answer.select("label_key", "estimate"), "label_key", "left")
    return out.select("label_key", F.coalesce(F.col("d").cast("double"), F.lit(0.0)).alias("d"), F.coalesce("estimate", F.lit(0.0)).alias("estimate"))


def errors(df: DataFrame) -> DataFrame:
    e = F.col("estimate") - F.col("d")
    return df.withColumns({"absolute": F.abs(e), "relative": e / F.col("d"), "squared": e * e})


def nae() -> Column:
    """Sum of absolute errors over the sum of true sizes."""
    return F.sum(F.abs(F.col("d") - F.col("estimate"))) / F.sum("d")


def nrse() -> Column:
    """Root of the sum of squared errors over the sum of squared sizes."""
    return F.sqrt(F.sum(F.pow(F.col("d") - F.col("estimate"), F.lit(2.0))) / F.sum(F.pow("d", F.lit(2.0))))


def rmae() -> Column:
    """Mean of the errors relative to the sizes."""
    return F.avg(F.abs(F.col("d") - F.col("estimate")) / F.col("d"))


def rrmse() -> Column:
    """The count outside the root, the size to the first power inside; rrmse_usual is the common form."""
    return F.sqrt(F.sum(F.pow(F.col("d") - F.col("estimate"), F.lit(2.0)) / F.col("d"))) / F.count(F.lit(1))


def rrmse_usual() -> Column:
    return F.sqrt(F.avg(F.pow((F.col("d") - F.col("estimate")) / F.col("d"), F.lit(2.0))))


def quadratic_mean(a: Column, b: Column) -> Column:
    return F.sqrt((a * a + b * b) / 2)


MEASURES = {"nae": nae, "nrse": nrse, "rmae": rmae, "rrmse": rrmse, "rrmse_usual": rrmse_usual}


def score(answer: DataFrame, truth: DataFrame, k: int, measures: tuple[str, ...] = tuple(MEASURES)) -> DataFrame:
    """One row: each measure over the true and the reported k (names with _true and _reported), Q of each, precision, recall and F1."""
    t, s = true_heavy(truth, k), reported_heavy(answer, k)
    on_true = scored(t, answer, truth).agg(*(MEASURES[m]().alias(f"{m}_true") for m in measures), F.count(F.lit(1)).alias("n_true"))
    on_reported = scored(s, answer, truth).agg(*(MEASURES[m]().alias(f"{m}_reported") for m in measures), F.count(F.lit(1)).alias("n_reported"))
    both = t.select("label_key").join(s.select("label_key"), "label_key").agg(F.count(F.lit(1)).alias("n_both"))
    # three rows of numbers
    row = on_true.crossJoin(on_reported).crossJoin(both).withColumn("k", F.lit(k))
    row = row.withColumns({("q" if m == "nae" else f"q_{m}"): quadratic_mean(F.col(f"{m}_true"), F.col(f"{m}_reported")) for m in measures})
    p, r = F.col("n_both") / F.col("n_reported"), F.col("n_both") / F.col("n_true")
    return row.withColumns({"precision": p, "recall": r, "f1": F.when(p + r > 0, 2 * p * r / (p + r)).otherwise(0.0)})


def nae_over(answer: DataFrame, truth: DataFrame, threshold: float) -> DataFrame:
    """The earlier practice: the error over the truly heavy labels above a threshold alone."""
    return scored(truth.where(F.col("d") >= threshold), answer, truth).agg(nae().alias("nae"), F.count(F.lit(1)).alias("n"))


def describe_pairs(pairs: DataFrame) -> DataFrame:
    """One row: entries, labels, items, distinct pairs, mean, percentiles and maximum of the sizes, shares of the entries that are unique pairs or of the top 100 and 1000 labels."""
    per = pairs.groupBy("label_key").agg(F.count(F.lit(1)).alias("entries"))
    sizes = exact_sizes(pairs).join(per, "label_key")
    ranked = sizes.withColumn("place", F.row_number().over(Window.orderBy(F.desc("d"), "label_key")))
    top = ranked.where(F.col("place") <= 1000).agg(F.sum(F.when(F.col("place") <= 100, F.col("entries"))).alias("e100"), F.sum("entries").alias("e1000"))
    pct = lambda p: F.percentile("d", F.lit(p))
    body = sizes.agg(F.sum("entries").alias("entries"), F.count(F.lit(1)).alias("labels"), F.sum("d").alias("pairs"), F.avg("d").alias("mean_d"), pct(0.5).alias("p50"), pct(0.9).alias("p90"), pct(0.99).alias("p99"), F.max("d").alias("max_d"))
    items = pairs.agg(F.count_distinct("item_key").alias("items"))
    out = body.crossJoin(items).crossJoin(top)
    return out.select("entries", "labels", "items", "pairs", "mean_d", "p50", "p90", "p99", "max_d", (F.col("pairs") / F.col("entries")).alias("unique_share"), (F.col("e100") / F.col("entries")).alias("top100_share"), (F.col("e1000") / F.col("entries")).alias("top1000_share"))


def measured_bytes(sk: Sketches) -> DataFrame:
    """Bytes of the stored counters: registers, labels, offsets."""
    return sk.counters.agg(F.sum(F.coalesce(F.octet_length("registers"), F.lit(0)) + F.octet_length("label_key") + 16).alias("bytes"), F.count(F.lit(1)).alias("counters"))


def check_invariants(sk: Sketches, truth: DataFrame, eps: float, delta: float = 0.01) -> DataFrame:
    """invariant, checked, violated for one sketch against the true sizes. The bounds of gated walks may fail with a chance of delta."""
    from tallywalk.functions.bounds import bound_gated, bound_plain

    counters, facts = sk.facts()
    known = truth.sparkSession.createDataFrame([(r["label_key"], r["estimate"]) for r in counters], "label_key string, estimate double")
    meta = {c: F.lit(facts[c]) for c in ("entries", "floor", "evicted")} | {"s": F.lit(sk.s)}
    rows = truth.join(F.broadcast(known), "label_key", "left").withColumns(meta)
    gated = sk.kind.startswith("gated")
    s, m, a, d = F.col("s").cast("double"), F.col("entries").cast("double"), F.col("floor"), F.col("d").cast("double")
    bound = bound_gated(m, s, F.lit(eps), F.lit(delta)) if gated else bound_plain(m, s, F.lit(eps))
    absent_d = a / (1 - eps) + (a * F.ln(F.lit(1 / delta)) if gated else 0)
    member = F.col("estimate").isNotNull()
    value = F.coalesce("estimate", F.when(F.col("evicted"), a).otherwise(0.0))
    slack = F.lit(1e-9)
    tests = {
        "floor_within_share": (F.lit(True), a <= m / s * (1 + eps) + slack),
        "value_within_floor": (member, F.col("estimate") <= d * (1 + eps) + a * (1 + eps) + slack),
        "value_not_below": (member & F.lit(not gated), F.col("estimate") >= d * (1 - eps) - slack),
        "absent_within_floor": (~member & F.col("evicted"), d <= absent_d + slack),
        "error_within_bound": (F.lit(True), F.abs(value - d) <= bound + slack),
    }
    sums = rows.agg(*(x for name, (applies, holds) in tests.items() for x in (F.count_if(applies).alias(f"{name}_n"), F.count_if(applies & ~holds).alias(f"{name}_bad"))))
    table = F.explode(F.array(*(F.struct(F.lit(n).alias("invariant"), F.col(f"{n}_n").alias("checked"), F.col(f"{n}_bad").alias("violated")) for n in tests))).alias("x")
    return sums.select(table).select("x.*")
