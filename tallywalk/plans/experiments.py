"""The experiments: accuracy against memory, equal widths, counter sizes, ablation, merging, overlap, throughput, query time.

Each gives rows (dicts) of the score table: workload, method, s or width, registers, modelled bytes, Q for each k, and seconds where it is timed. Run as

    python -m tallywalk.plans.experiments /root/testdata/sf0.1 ablation merging ...
"""

from __future__ import annotations

import sys
import time
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

from tallywalk.functions import bounds
from tallywalk.operators import exact, grids
from tallywalk.operators.sketches import build_sketch, merge_sketches
from tallywalk.plans import metrics
from tallywalk.sources import synth
from tallywalk.sources.pairs import WORKLOADS

CONTENDERS = ("gated", "shared_grid", "cell_grid")
KIB = 1 << 10


def answer_of(method: str, pairs: DataFrame, size: int, m: int, depth: int | None = None, streams: int | str = 1, k: int = 1000) -> DataFrame:
    """label_key, estimate from one method: all counters of a walk, the k largest of a grid."""
    if method == "cell_grid":
        return grids.grid_top_k(grids.cell_grid(pairs, depth or 4, size, m), k)
    if method == "shared_grid":
        return grids.shared_top_k(grids.shared_grid(pairs, depth or 512, size), k)
    sk = build_sketch(pairs, kind=method, s=size, m=m, streams=streams)
    return (sk if streams == 1 else merge_sketches(sk)).counters.select("label_key", "estimate")


def scored(workload: str, method: str, pairs: DataFrame, truth: DataFrame, size: int, m: int, depth: int | None = None, ks=metrics.KS, **options) -> dict:
    answer = answer_of(method, pairs, size, m, depth, **options).persist()
    row = {"workload": workload, "method": method, "size": size, "m": m, "bytes": bounds.bytes_of(method, size, m, depth)}
    for k in ks:
        row[f"q_{k}"] = round(metrics.score(answer, truth, k, ("nae",)).first()["q"], 4)
    answer.unpersist()
    return row


def loaded(spark: SparkSession, sf_dir: str, workload: str) -> tuple[DataFrame, DataFrame]:
    pairs = WORKLOADS[workload](spark, sf_dir).persist()
    return pairs, exact.exact_sizes(pairs).persist()


def memory_sweep(spark: SparkSession, sf_dir: str, workloads=("doc_words", "word_docs", "word_conversations", "customer_parts"), limits=tuple(n * KIB for n in (32, 128, 512)), methods=CONTENDERS) -> Iterator[dict]:
    """Q against bytes. Registers: 1024 a counter where that leaves room, else fewer; 64 a cell; a register matrix with 64 rows at small limits."""
    for w in workloads:
        pairs, truth = loaded(spark, sf_dir, w)
        for limit in limits:
            for method in methods:
                m, depth = (64, 4) if method == "cell_grid" else (0, 64) if method == "shared_grid" else (256, None)
                yield scored(w, method, pairs, truth, max(1, bounds.size_for(method, limit, m, depth)), m or 64, depth)


def same_width(spark: SparkSession, sf_dir: str, width: int = 500, m: int = 256) -> Iterator[dict]:
    """The same number of counters, cells and columns, and the same registers: what the labels' memory hides."""
    pairs, truth = loaded(spark, sf_dir, "word_conversations")
    for method in CONTENDERS:
        yield scored("word_conversations", method, pairs, truth, width, m, {"cell_grid": 4, "shared_grid": m}.get(method))


def counter_sizes(spark: SparkSession, sf_dir: str, limit: int = 256 * KIB, sizes=(64, 128, 256, 512, 1024, 2048, 4096)) -> Iterator[dict]:
    """More counters against better counters under one limit."""
    pairs, truth = loaded(spark, sf_dir, "word_conversations")
    for m in sizes:
        yield scored("word_conversations", "gated", pairs, truth, bounds.size_for("gated", limit, m), m)


def width_effect(spark: SparkSession, sf_dir: str, limit: int = 256 * KIB, sizes=(64, 128, 438, 1024), workload: str = "word_conversations") -> Iterator[dict]:
    """The cell grid under one limit: wide rows of small cells against narrow rows of large ones."""
    pairs, truth = loaded(spark, sf_dir, workload)
    for m in sizes:
        yield scored(workload, "cell_grid", pairs, truth, max(1, bounds.size_for("cell_grid", limit, m, 4)), m, 4)


def ablation(spark: SparkSession, sf_dir: str, sizes=(400, 2000), m: int = 256, workloads=("word_conversations", "word_docs", "customer_parts")) -> Iterator[dict]:
    """What the gate and the recycling are good for."""
    for w in workloads:
        pairs, truth = loaded(spark, sf_dir, w)
        for s in sizes:
            for kind in ("offset", "recycled", "gated"):
                yield scored(w, kind, pairs, truth, s, m)


def merging(spark: SparkSession, sf_dir: str, s: int = 500, m: int = 256, streams: int = 64, workloads=("word_conversations", "customer_parts")) -> Iterator[dict]:
    """The price of cutting the stream into pieces."""
    for w in workloads:
        pairs, truth = loaded(spark, sf_dir, w)
        for n in (1, streams):
            yield scored(w, "gated", pairs, truth, s, m, streams=n) | {"streams": n}


def overlap(spark: SparkSession, sf_dir: str = "", scale: int = 100, n_small: int = 100_000, sizes=(20_000, 100_000, 500_000), width: int = 1000, m: int = 256) -> Iterator[dict]:
    """Large sets that share items with many small ones; all counts divided by scale, widths too."""
    for n in sizes:
        pairs = synth.overlap(spark, n_small // scale, n // scale, 1000 // (scale // 10 or 1), 1000 // scale, 1_000_000 // scale, 100_000 // scale).persist()
        truth = exact.exact_sizes(pairs).persist()
        for method in ("recycled", "gated", "cell_grid", "shared_grid"):
            yield scored(f"overlap n={n}/{scale}", method, pairs, truth, max(20, width // (scale // 10 or 1)), m, {"cell_grid": 4, "shared_grid": 64}.get(method), ks=(10, 100))


def slow_tail(spark: SparkSession, sf_dir: str = "", n_labels: int = 5_000, entries: int = 1_000_000, limit: int = 256 * KIB) -> Iterator[dict]:
    pairs = synth.slow_tail(spark, n_labels, entries=entries).persist()
    truth = exact.exact_sizes(pairs).persist()
    for method in CONTENDERS:
        m, depth = (64, 4) if method == "cell_grid" else (64, 64) if method == "shared_grid" else (256, None)
        yield scored("slow_tail", method, pairs, truth, bounds.size_for(method, limit, m, depth), m, depth)


def timed_build(pairs: DataFrame, method: str, limit: int = 3 * bounds.MIB, m: int = 1024, streams: int | str = "as_is") -> float:
    """Seconds from reading the input to the finished structure."""
    began = time.time()
    if method == "cell_grid":
        grids.cell_grid(pairs, 4, bounds.size_for("cell_grid", limit, 64), 64).rows.write.format("noop").mode("overwrite").save()
    elif method == "shared_grid":
        grids.shared_grid(pairs, 512, bounds.size_for("shared_grid", limit)).rows.write.format("noop").mode("overwrite").save()
    else:
        build_sketch(pairs, kind=method, s=bounds.size_for(method, limit, m), m=m, streams=streams).rows.write.format("noop").mode("overwrite").save()
    return time.time() - began


def throughput(spark: SparkSession, sf_dir: str, workloads=("doc_words", "word_docs", "word_conversations", "customer_parts")) -> Iterator[dict]:
    for w in workloads:
        pairs = WORKLOADS[w](spark, sf_dir)
        n = pairs.count()
        for method in CONTENDERS:
            timed_build(pairs, method)
            s = timed_build(pairs, method)
            yield {"workload": w, "method": method, "entries": n, "seconds": round(s, 2), "entries_per_ms": round(n / s / 1000, 1)}


def query_time(spark: SparkSession, sf_dir: str, k: int = 1000) -> Iterator[dict]:
    """Seconds to produce the k largest from a finished structure."""
    pairs, _ = loaded(spark, sf_dir, "word_conversations")
    sk = build_sketch(pairs, s=2778, m=1024, streams=1)
    held = sk.rows.persist()
    held.count()
    cell, shared = grids.cell_grid(pairs, 4, 1024, 64), grids.shared_grid(pairs, 512, 64)
    from dataclasses import replace

    from tallywalk.operators.sketches import top_k

    def frozen(g: grids.Grid) -> grids.Grid:
        out = replace(g, registers=g.registers.persist(), labels=g.labels.persist())
        out.registers.count(), out.labels.count()
        return out

    cell, shared = frozen(cell), frozen(shared)
    for method, ask in (("gated", lambda: top_k(replace(sk, rows=held), k)), ("cell_grid", lambda: grids.grid_top_k(cell, k)), ("shared_grid", lambda: grids.shared_top_k(shared, k))):
        times = []
        for _ in range(2):
            began = time.time()
            ask().write.format("noop").mode("overwrite").save()
            times.append(time.time() - began)
        yield {"workload": "word_conversations", "method": method, "k": k, "seconds": round(min(times), 3)}


EXPERIMENTS = {f.__name__: f for f in (memory_sweep, same_width, counter_sizes, width_effect, ablation, merging, overlap, slow_tail, throughput, query_time)}


def main(args: list[str]) -> None:
    spark = SparkSession.builder.config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "6g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    sf_dir, *names = args
    for name in names or EXPERIMENTS:
        for row in EXPERIMENTS[name](spark, sf_dir):
            print(name, row, flush=True)
        spark.catalog.clearCache()


if __name__ == "__main__":
    main(sys.argv[1:])

