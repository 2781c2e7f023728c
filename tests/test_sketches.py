import numpy as np
import pytest
from pyspark.sql import functions as F

from tallywalk.functions import bounds
from tallywalk.functions.registers import estimate_arrays, estimate_registers
from tallywalk.operators import exact, grids
from tallywalk.operators.sketches import Sketches, build_sketch, estimate, merge_pair, merge_sketches, over, recount, roll_up, top_k
from tallywalk.plans import metrics
from tallywalk.sources import synth
from tallywalk.sources.pairs import LINE_ORDER, WORKLOADS, pairs, table, with_hashes
from tallywalk.streaming import panes

D = "/root/testdata/sf0.01"


def rows_of(sk: Sketches):
    return sorted((r["label_key"], r["offset"], bytes(r["registers"] or b""), tuple(r["items"] or ())) for r in sk.counters.collect())


@pytest.fixture(scope="module")
def customers(spark):
    p = WORKLOADS["customer_parts"](spark, D).persist()
    return p, exact.exact_sizes(p).persist()


def test_histogram_estimate_never_steps_down_and_both_are_near():
    rng = np.random.default_rng(1)
    for m in (64, 1024):
        regs, last = np.zeros((1, m), np.uint8), 0.0
        for n in range(1, 4000):
            regs[0, rng.integers(m)] = max(regs[0, rng.integers(m)], min(40, rng.geometric(0.5)))
            if n % 7 == 0:
                grown = np.maximum(regs, (rng.random((1, m)) < 0.01) * rng.geometric(0.5, (1, m)).astype(np.uint8))
                assert estimate_arrays(grown)[0] >= estimate_arrays(regs)[0] - 1e-9
                regs = grown
    full = np.zeros((1, 1024), np.uint8)
    for _ in range(20_000):
        b = rng.integers(1024)
        full[0, b] = max(full[0, b], min(40, rng.geometric(0.5)))
    for kind in ("histogram", "classic"):
        assert abs(estimate_arrays(full, kind)[0] / 20_000 - 1) < 0.12
    assert estimate_arrays(np.zeros((1, 64), np.uint8))[0] == 0


def test_registers_in_the_walk_are_those_of_the_plan(spark, customers):
    p = customers[0].where(F.col("label_key").cast("int") < 40)
    sk = build_sketch(p, s=500, m=64, streams=3, hash="portable")
    merged = merge_sketches(sk).counters.select("label_key", estimate_registers()("registers").alias("e"))
    plain = exact.register_estimates(exact.label_registers(p, 64), 64)
    for r in merged.join(plain, "label_key").collect():
        assert abs(r["e"] - r["estimate"]) < 1e-6


def test_variants_order(spark, customers):
    p, truth = customers
    q = {}
    for kind in ("offset", "recycled", "gated"):
        answer = build_sketch(p, kind=kind, s=400, counter="exact", streams=1).counters.select("label_key", "estimate")
        q[kind] = metrics.score(answer, truth, 100, ("nae",)).first()["q"]
    assert q["gated"] < 0.3 < 1.0 < q["recycled"] <= q["offset"]


def test_flagship_beats_both_grids_at_equal_memory(spark, customers):
    p, truth = customers
    limit = 256 * 1024
    answers = {
        "gated": build_sketch(p, s=bounds.size_for("gated", limit, 256), m=256, streams=1).counters.select("label_key", "estimate"),
        "cell": grids.grid_top_k(grids.cell_grid(p, 4, bounds.size_for("cell_grid", limit, 64), 64), 1000),
        "shared": grids.shared_top_k(grids.shared_grid(p, 64, bounds.size_for("shared_grid", limit, depth=64)), 1000),
    }
    q = {k: metrics.score(a, truth, 100, ("nae",)).first()["q"] for k, a in answers.items()}
    assert q["gated"] < min(q["cell"], q["shared"])
    merged = merge_sketches(build_sketch(p, s=bounds.size_for("gated", limit, 256), m=256, streams=16)).counters.select("label_key", "estimate")
    assert metrics.score(merged, truth, 100, ("nae",)).first()["q"] < 1


def test_merge_laws(spark, customers, tmp_path):
    p = customers[0]
    half = [p.where(F.pmod(F.xxhash64("label_key", "item_key"), F.lit(2)) == i) for i in (0, 1)]
    a, b = (build_sketch(x, s=50, m=64, streams=1) for x in half)
    assert rows_of(merge_pair(a, b)) == rows_of(merge_pair(b, a))
    assert rows_of(merge_pair(a, a)) == rows_of(a)
    nothing = build_sketch(p.limit(0), s=50, m=64, streams=1)
    assert rows_of(merge_pair(a, nothing)) == rows_of(a)
    floors = [x.meta.first()["floor"] for x in (a, b, merge_pair(a, b))]
    assert floors[2] >= max(floors[:2])
    many = build_sketch(p, s=50, m=64, streams=8).stored(str(tmp_path / "many"))  # the blocks' bounds are sampled anew each time
    assert rows_of(merge_sketches(Sketches(many.rows.repartition(5), *(getattr(many, n) for n in ("kind", "s", "m", "counter", "estimator", "hash_id"))))) == rows_of(merge_sketches(many))
    tree = merge_sketches(many, mode="tree", fan_in=3)
    assert tree.counters.count() == 50 and tree.meta.count() == 1
    with pytest.raises(ValueError):
        merge_pair(a, build_sketch(half[1], s=50, m=128, streams=1))
    with pytest.raises(ValueError):
        merge_pair(a, build_sketch(half[1], s=50, m=64, streams=1, hash="portable"))


def test_offset_merge_with_floors_keeps_upper_values(spark):
    rows = table(spark, D, "lineitem").where("l_orderkey < 800")
    p = pairs(rows, "l_suppkey", "l_partkey", order_by=LINE_ORDER, source=F.floor(F.col("l_orderkey") / 200))
    truth = {r["label_key"]: r["d"] for r in exact.exact_sizes(p).collect()}
    sk = build_sketch(p, kind="offset", s=20, counter="exact", streams="by_source")
    for r in merge_sketches(sk, absent_offset="floor").counters.collect():
        assert r["estimate"] >= truth[r["label_key"]]


def test_threshold_after_a_merge_that_is_not_full(spark):
    rows = [("a", i) for i in range(5)] + [("b", i) for i in range(5)]
    p = pairs(spark.createDataFrame(rows, "l string, i int"), "l", "i")
    merged = merge_sketches(build_sketch(p, s=3, counter="exact", streams=2))
    assert merged.meta.first()["threshold"] == 0 and not merged.meta.first()["is_full"]


def test_point_queries_and_floor_of_the_offset_walk(spark):
    rows = [("a", i) for i in range(5)] + [("b", i) for i in range(3)] + [("c", 0)]
    p = pairs(spark.createDataFrame([(k, l, i) for k, (l, i) in enumerate(rows)], "k int, l string, i int"), "l", "i", order_by=["k"])
    sk = build_sketch(p, kind="offset", s=2, counter="exact", streams=1)
    asked = spark.createDataFrame([("a",), ("b",), ("c",)], "label_key string")
    got = {a: {r["label_key"]: r["estimate"] for r in estimate(sk, asked, a).collect()} for a in ("min", "literal", "zero", "null")}
    assert got["min"] == {"a": 5, "b": 4, "c": 4}
    assert got["literal"]["b"] == 1 and got["zero"]["b"] == 0 and got["null"]["b"] is None
    roomy = build_sketch(p, s=9, counter="exact", streams=1)
    assert {r["label_key"]: r["estimate"] for r in estimate(roomy, spark.createDataFrame([("zz",)], "label_key string")).collect()} == {"zz": 0}
    assert {r["label_key"] for r in over(roomy, threshold=3).collect()} == {"a", "b"}
    assert {r["label_key"] for r in over(roomy, fraction=0.5).collect()} == {"a"}
    assert [tuple(r) for r in recount(top_k(roomy, 1), p).select("label_key", "d").collect()] == [("a", 5)]


def test_single_scan_and_bounded_state(spark, customers):
    p = WORKLOADS["supplier_parts"](spark, D)
    sk = build_sketch(p, s=10, m=64, streams=4)
    plan = sk.rows._jdf.queryExecution().executedPlan().toString()
    assert plan.count("FileScan") == 1 and "ReadSchema" in plan and "l_comment" not in plan
    assert max(r["count"] for r in sk.counters.groupBy("sketch_id").count().collect()) <= 10


def test_degenerate_pairs(spark):
    schema = "l string, i string, k int"
    assert build_sketch(pairs(spark.createDataFrame([], schema), "l", "i"), s=3).rows.count() == 0
    rows = [(None, "x", 1), ("a", None, 2), ("a", "x", 3)]
    df = spark.createDataFrame(rows, schema)
    assert [r["label_key"] for r in build_sketch(pairs(df, "l", "i"), s=3, counter="exact", streams=1).counters.collect()] == ["a"]
    assert exact.exact_sizes(pairs(df, "l", "i", keep_null_label=True)).count() == 2
    assert top_k(build_sketch(pairs(df, "l", "i"), s=1, counter="exact", streams=1), 5).count() == 1
    both = pairs(df.where("l = 'a'"), F.struct("l", "k"), "i")
    assert exact.exact_sizes(both).first()["label_key"] == '{"l":"a","k":3}'
    with pytest.raises(TypeError):
        pairs(df.withColumn("x", F.lit(1.5)), "l", "x")
    with pytest.raises(TypeError):
        pairs(df.withColumn("x", F.array("l")), "x", "i")
    with pytest.raises(ValueError):
        grids.grid_top_k(grids.shared_grid(both, 4, 4, labels=False), 3)


def test_invariants_of_gated_walks_over_seeds(spark, customers):
    p, truth = customers
    bad = 0
    for seed in range(3):
        got = {r["invariant"]: r for r in metrics.check_invariants(build_sketch(p, s=100, counter="exact", streams=1, seed=seed), truth, 0.0).collect()}
        bad += got["error_within_bound"]["violated"] + got["absent_within_floor"]["violated"] + got["floor_within_share"]["violated"]
    assert bad <= 0.02 * 3 * truth.count()


def test_slow_tail_and_overlap_families(spark):
    tail = metrics.describe_pairs(synth.slow_tail(spark, 1000, entries=100_000)).first()
    assert tail["entries"] == 100_000 and 990 <= tail["labels"] <= 1000 and tail["pairs"] == 100_000
    assert 80 <= tail["p50"] <= 105 and tail["p90"] > tail["p50"]
    over_ = synth.overlap(spark, 100, 400, 10, 50, 10_000, 1000)
    sizes = exact.exact_sizes(over_)
    assert sizes.count() == 110 and sizes.agg(F.max("d")).first()[0] > 350


def test_shared_solvers_agree(spark, customers):
    p, truth = customers
    g = grids.shared_grid(p, 64, 64)
    labels = metrics.true_heavy(truth, 20)
    a = {r["label_key"]: r["estimate"] for r in grids.shared_estimate(g, labels, "ladder", 1.02, 1e5).collect()}
    b = {r["label_key"]: r["estimate"] for r in grids.shared_estimate(g, labels, "newton", largest=1e5).collect()}
    for k, v in a.items():
        assert abs(v - b[k]) <= 0.05 * v + 1


def test_jvm_baselines_are_near(spark, customers):
    p, truth = customers
    top = metrics.true_heavy(truth, 50)
    for answer in (exact.per_label_sketch(p, 12), exact.approx_distinct(p, 0.02)):
        assert metrics.scored(top, answer, truth).agg(metrics.nae()).first()[0] < 0.05


def test_inverse_min_hash_median(spark):
    df = pairs(spark.range(200 * 100).select((F.col("id") % 200).alias("l"), "id"), "l", "id")
    got = sorted(r["estimate"] for r in exact.inverse_min_hash(df).collect())
    assert 100 / np.log(2) * 0.75 < got[100] < 100 / np.log(2) * 1.35


def test_gate_draws_pass_with_their_chance(spark):
    p = with_hashes(pairs(spark.range(20_000).select(F.lit("a").alias("l"), "id"), "l", "id"))
    share = p.agg(F.avg((F.col("draw") > 10).cast("int")), F.min("draw")).first()
    assert abs(share[0] - 0.1) < 0.01 and share[1] > 1


def test_pairs_of_panes_streams_and_roll_ups(spark, tmp_path):
    import datetime
    import pathlib

    events = table(spark, "/root/testdata/sf0.001", "events")
    days = [r[0] for r in events.select(F.to_date("ts")).distinct().orderBy(F.to_date("ts")).collect()]
    source = tmp_path / "days"
    for i, day in enumerate(days[:4]):
        part = events.where(F.to_date("ts") == day).coalesce(1)
        part.write.parquet(str(tmp_path / f"one{i}"))
        source.mkdir(exist_ok=True)
        file = next(pathlib.Path(tmp_path / f"one{i}").glob("part-*.parquet"))
        file.rename(source / f"{i}.parquet")
        import os

        os.utime(source / f"{i}.parquet", (1_700_000_000 + i, 1_700_000_000 + i))
    assert isinstance(days[0], datetime.date)
    few = events.where(F.to_date("ts").isin(days[:4]))
    batch = panes.pane_sizes(pairs(few, "event_type", "user_id", ts="ts"), "1 day")
    stream = panes.stream_pairs(panes.event_stream(spark, str(source), events.schema), "event_type", "user_id")
    q = panes.stream_sizes(stream, "1 day", "1 hour").writeStream.format("memory").queryName("sizes").outputMode("update").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c1")).start()
    q.awaitTermination(120)
    got = {(r["pane"], r["label_key"]): r["d"] for r in spark.table("sizes").groupBy("pane", "label_key").agg(F.max("d").alias("d")).collect()}
    assert got == {(r["pane"], r["label_key"]): r["d"] for r in batch.collect()}

    options = {"s": 50, "m": 64, "counter": "exact"}
    panes.stream_sketches(stream, str(tmp_path / "store"), str(tmp_path / "c2"), "1 hour", **options).awaitTermination(120)
    like = panes.pane_sketches(pairs(few, "event_type", "user_id", ts="ts"), "1 hour", **options)
    stored = roll_up(panes.read_store(spark, str(tmp_path / "store"), like), "1 day")
    assert {(r["sketch_id"], r["label_key"]): r["estimate"] for r in stored.counters.collect()} == got

    q = panes.stateful_sketches(stream, 2, s=50, m=256).writeStream.format("memory").queryName("walks").outputMode("update").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c3")).start()
    q.awaitTermination(120)
    walked = {r["label_key"]: r["e"] for r in spark.table("walks").groupBy("label_key").agg(F.max("estimate").alias("e")).collect()}
    truth = {r["label_key"]: r["d"] for r in exact.exact_sizes(pairs(few, "event_type", "user_id")).collect()}
    assert walked.keys() == truth.keys() and all(abs(walked[k] - truth[k]) <= 0.3 * truth[k] + 2 for k in truth)


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    import os
    import time

    schema = "ts timestamp_ntz, event_type string, user_id bigint"
    day = lambda n, users: [(f"2024-01-0{n} {h:02d}:30:00", "a" if u % 2 else "b", u) for h in (1, 12) for u in users]
    files = [day(1, range(10)), day(2, range(5)), day(3, range(7)), day(1, range(100, 108)), day(3, range(20, 24))]  # the fourth comes too late, the fifth does not
    os.mkdir(tmp_path / "in")
    for i, rows in enumerate(files):
        spark.createDataFrame(rows, "ts string, event_type string, user_id bigint").withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1).write.parquet(str(tmp_path / f"one{i}"))
        part = next((tmp_path / f"one{i}").glob("part-*.parquet"))
        part.rename(tmp_path / "in" / f"{i}.parquet")
        os.utime(tmp_path / "in" / f"{i}.parquet", (1_700_000_000 + i, 1_700_000_000 + i))
    listener = panes.LateRows()
    spark.streams.addListener(listener)
    try:
        stream = panes.stream_pairs(panes.event_stream(spark, str(tmp_path / "in"), schema), "event_type", "user_id")
        q = panes.stream_sizes(stream, "1 day", "1 hour").writeStream.format("memory").queryName("late").outputMode("update").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
        q.awaitTermination(120)
        assert panes.late_rows(q) == len(files[3])
        for _ in range(50):
            if listener.dropped.get(str(q.id)) == len(files[3]):
                break
            time.sleep(0.1)
        assert listener.dropped[str(q.id)] == len(files[3])
    finally:
        spark.streams.removeListener(listener)
    got = {(r["pane"], r["label_key"]): r["d"] for r in spark.table("late").groupBy("pane", "label_key").agg(F.max("d").alias("d")).collect()}
    in_time = spark.createDataFrame([r for i, f in enumerate(files) if i != 3 for r in f], "ts string, event_type string, user_id bigint")
    assert got == {(r["pane"], r["label_key"]): r["d"] for r in panes.pane_sizes(pairs(in_time, "event_type", "user_id", ts="ts"), "1 day").collect()}


def test_grids_read_their_input_once(spark):
    p = WORKLOADS["supplier_parts"](spark, "/root/testdata/sf0.001")
    for g in (grids.cell_grid(p, 2, 16, 16, "portable"), grids.shared_grid(p, 16, 32, hash="portable")):
        rows = g.rows
        got = rows.collect()
        plan = rows._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0]
        assert plan.count("FileScan") == 1 and "ReusedExchange" in plan
        assert {(r["row"], r["col"], r["label_key"], r["rank"]) for r in got if r["bucket"] < 0} == {(r["row"], r["col"], r["label_key"], r["level"]) for r in g.labels.collect()}
        assert sum(r["bucket"] >= 0 for r in got) == g.registers.count()


def test_deletes_are_refused(spark):
    from tallywalk.sources.pairs import insert_only

    feed = spark.createDataFrame([("a", 1, "insert"), ("a", 2, None), ("b", 1, "delete")], "l string, i int, _change_type string")
    assert exact.exact_sizes(pairs(insert_only(feed.where("l = 'a'")), "l", "i")).first()["d"] == 2
    with pytest.raises(Exception, match="only inserted rows can be counted, found: delete"):
        exact.exact_sizes(pairs(insert_only(feed), "l", "i")).collect()
    assert insert_only(feed.limit(0)).columns == ["l", "i"]


def test_stored_sketches(spark, tmp_path, customers):
    sk = build_sketch(customers[0], s=20, m=64, streams=1)
    kept = sk.stored(str(tmp_path / "sk"))
    assert rows_of(kept) == rows_of(sk)
    assert metrics.measured_bytes(kept).first()["counters"] == 20


def test_sizes_of_structures():
    for m, s in {64: 18289, 128: 13329, 256: 8642, 512: 5073, 1024: 2778, 2048: 1459, 4096: 748}.items():
        assert bounds.size_for("gated", 3 * bounds.MIB, m) == s
    assert bounds.size_for("cell_grid", 3 * bounds.MIB, 64) == 4572
    assert bounds.size_for("shared_grid", 3 * bounds.MIB) == 1024


def scans(df):
    return df._jdf.queryExecution().executedPlan().toString().count("FileScan")


def test_merges_and_answers_read_the_input_once(spark, sf):
    from tallywalk.sources.pairs import WORKLOADS

    merged = merge_sketches(build_sketch(WORKLOADS["word_docs"](spark, sf), s=50, m=64))
    assert scans(merged.rows) == scans(merged.meta) == 1
    assert scans(over(merged, fraction=0.01)) == scans(top_k(merged, 5)) == 1
    assert "TakeOrdered" not in merged.rows._jdf.queryExecution().executedPlan().toString() and "Window" not in merged.rows._jdf.queryExecution().executedPlan().toString()
