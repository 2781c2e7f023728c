"""Times the headline queries and prints one line of JSON. BENCH_SF_DIR: the tables; BENCH_CPUS: threads."""

import json
import os
import statistics
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
RUNS = 3


def main() -> None:
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        # the tables have one row group each: small splits let all threads read
        .config("spark.sql.files.maxPartitionBytes", "4m")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from tallywalk.operators import exact
    from tallywalk.operators.sketches import build_sketch, merge_sketches, top_k
    from tallywalk.plans.experiments import timed_build
    from tallywalk.sources.pairs import WORKLOADS

    def run(df) -> None:
        df.write.format("noop").mode("overwrite").save()

    loads = {w: WORKLOADS[w](spark, SF_DIR) for w in ("doc_words", "word_docs", "word_conversations", "customer_parts")}
    entries = {w: p.count() for w, p in loads.items()}
    jobs = {f"build_{m}_{w}": (lambda p=p, m=m: timed_build(p, m)) for w, p in loads.items() for m in ("gated", "shared_grid", "cell_grid")}
    jobs |= {
        "gated_one_stream_word_docs": lambda: timed_build(loads["word_docs"], "gated", streams=1),
        "gated_build_merge_top_word_docs": lambda: run(top_k(merge_sketches(build_sketch(loads["word_docs"], s=2778, m=1024)), 1000)),
        "exact_top_word_docs": lambda: run(exact.exact_top_k(loads["word_docs"], 1000)),
        "per_label_sketch_word_docs": lambda: run(exact.per_label_sketch(loads["word_docs"])),
    }
    times = {}
    for name, job in jobs.items():
        began = time.time()
        job()  # compiles code and starts Python workers
        took = []
        for _ in range(RUNS if time.time() - began < 4 else 1):
            began = time.time()
            job()
            took.append(time.time() - began)
        times[name] = round(statistics.median(took), 3)
    rates = {n: round(entries[w] / t / 1000, 1) for n, t in times.items() for w in entries if n.startswith("build_") and n.endswith(w)}
    print(json.dumps({"metric": "total seconds of the headline queries", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(SF_DIR.rstrip("/")), "entries": entries, "entries_per_ms": rates}))


if __name__ == "__main__":
    main()
