"""The walks and merges against recursive SQL, written apart from the queries' twins, on a short table; and against a plain walk with dictionaries on whole tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tallywalk.functions.registers import estimate_arrays
from tallywalk.operators.sketches import build_sketch, merge_sketches, top_k
from tallywalk.plans import twins
from tallywalk.plans.queries import QUERIES, SLOT, SLOTS, WALKS, S, neighbours
from tallywalk.sources.pairs import WORKLOADS, with_hashes
from tests import oracle, recursive

LOW, HIGH = 330, 480


@pytest.fixture(scope="module")
def short(spark, sf, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("short"))
    lines = spark.read.parquet(f"{sf}/lineitem.parquet").where(F.col("l_orderkey").between(LOW, HIGH - 1))
    lines.coalesce(1).write.parquet(f"{folder}/lineitem.parquet")
    low, high, rows = lines.agg(F.min("l_orderkey"), F.max("l_orderkey"), F.count("*")).first()
    assert (low, high) == (LOW, HIGH - 1) and rows < 2000
    return folder


@pytest.fixture(scope="module")
def con(short):
    import duckdb

    made = duckdb.connect()
    made.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{short}/lineitem.parquet/*.parquet'")
    return made


def walks(kind, parts):
    cuts = [LOW - (LOW - HIGH) * i // parts for i in range(parts + 1)]
    return ", ".join(recursive.walk(n, recursive.prefix(a, b), kind, S) for n, a, b in zip("abce", cuts, cuts[1:]))


SQL = {f"walk_{k}": f"WITH RECURSIVE {walks(k, 1)} {SLOTS} FROM a" for k in WALKS}
SQL |= {f"walk_{k}_point_query": f"WITH RECURSIVE {walks(k, 1)} SELECT label_key, a.estimate IS NOT NULL AS member, coalesce(a.estimate, (SELECT min(estimate) FROM a)) AS estimate FROM (SELECT DISTINCT label AS label_key FROM a_in) LEFT JOIN a USING (label_key)" for k in WALKS}
SQL |= {
    "walk_gated_top_3": f"WITH RECURSIVE {walks('gated', 1)} SELECT label_key, estimate, CAST(row_number() OVER (ORDER BY estimate DESC, label_key) AS INTEGER) AS rank FROM a QUALIFY rank <= 3",
    "walk_gated_over_threshold": f"WITH RECURSIVE {walks('gated', 1)} SELECT label_key, estimate FROM a WHERE estimate >= 30",
    "walk_offset_over_fraction": f"WITH RECURSIVE {walks('offset', 1)} SELECT label_key, estimate, estimate >= (SELECT count(*) FROM a_in) * 0.125 AS reported FROM a",
    "merge_pair_gated": f"WITH RECURSIVE {walks('gated', 2)} {SLOT} FROM ({twins.union_of(['a', 'b'], S)})",
    "merge_offset": f"WITH RECURSIVE {walks('offset', 2)} {SLOTS} FROM ({twins.union_of(['a', 'b'], S)})",
    "merge_flat": f"WITH RECURSIVE {walks('gated', 4)} {SLOT} FROM ({twins.union_of(['a', 'b', 'c', 'e'], S)})",
    "merge_tree": f"WITH RECURSIVE {walks('gated', 4)}, ab AS ({twins.union_of(['a', 'b'], S)}), ce AS ({twins.union_of(['c', 'e'], S)}) {SLOT} FROM ({twins.union_of(['ab', 'ce'], S)})",
}


@pytest.mark.parametrize("name", list(SQL))
def test_whole_table(spark, short, con, name):
    assert oracle.differences(spark, con, QUERIES[name], SQL[name], short) == ""


def test_later_orders_and_suppliers_are_seen(spark, tmp_path):
    rows = [(1, 1, s, 100 + s) for s in range(5)] + [(10**6, 1, 77, p) for p in range(60)] + [(None, 1, 88, 1)]
    spark.createDataFrame(rows, "l_orderkey bigint, l_linenumber int, l_suppkey bigint, l_partkey bigint").write.parquet(f"{tmp_path}/lineitem.parquet")
    for name in ("walk_offset", "walk_gated_point_query", "merge_flat", "merge_pair_gated"):
        got = {r["label_key"]: r["estimate"] for r in QUERIES[name](spark, str(tmp_path)).collect()}
        assert got == {**{str(s): 1.0 for s in range(5)}, "77": 60.0, "88": 1.0}, name
    assert {r["label_key"] for r in QUERIES["walk_offset_over_fraction"](spark, str(tmp_path)).where("reported").collect()} == {"77"}


def test_pre_gate_drops_rows_and_changes_nothing(spark, sf, monkeypatch):
    seen, real = [], neighbours.pre_gate

    def gate(p, sk):
        out = real(p, sk)
        seen.append((p.count(), out.count()))
        return out

    monkeypatch.setattr(neighbours, "pre_gate", gate)
    assert QUERIES["pre_gated_walk_equals_walk"](spark, sf).first()["differences"] == 0
    assert 0 < seen[0][1] <= seen[0][0]


def naive(rows, kind, s, m):
    """A stream walked entry by entry; rows: label, item, bucket, rank, draw. Slots, their offsets and what they hold; m None: sets."""
    labels, held, offsets, threshold = [], [], [], 0.0

    def value(i):
        return offsets[i] + (len(held[i]) if m is None else float(estimate_arrays(held[i][None, :])[0]))

    def take(i, item, bucket, rank):
        if m is None:
            held[i].add(item)
        else:
            held[i][bucket] = max(held[i][bucket], rank)
        values[i] = value(i)

    values, place = [], {}
    for label, item, bucket, rank, draw in rows:
        if label in place:
            take(place[label], item, bucket, rank)
            continue
        if len(labels) < s:
            place[label] = len(labels)
            labels.append(label)
            held.append(set() if m is None else np.zeros(m, np.uint8))
            offsets.append(0.0)
            values.append(0.0)
            take(place[label], item, bucket, rank)
            continue
        if kind == "gated" and draw <= threshold:
            continue
        least = min(range(s), key=values.__getitem__)
        threshold = max(threshold, values[least])
        if kind.startswith("gated") and draw <= values[least]:
            continue
        del place[labels[least]]
        place[label], labels[least] = least, label
        if kind == "offset":
            offsets[least] = values[least]
            held[least] = set() if m is None else np.zeros(m, np.uint8)
        take(least, item, bucket, rank)
    return labels, offsets, held, values


def entries(pairs, m):
    got = with_hashes(pairs, m).select("ord", "source", "label_key", "item_key", "bucket", "rank", "draw").collect()
    return sorted(got, key=lambda r: tuple(r["ord"]))


WHOLE = {"supplier_parts": 6, "customer_parts": 30, "word_docs": 60}


@pytest.mark.parametrize("load", WHOLE)
@pytest.mark.parametrize("counter", ["registers", "exact"])
@pytest.mark.parametrize("kind", WALKS)
def test_every_eviction_on_whole_tables(spark, sf, load, counter, kind):
    s, m = WHOLE[load], 64
    p = WORKLOADS[load](spark, sf)
    p = p if "source" in p.columns else p.withColumn("source", F.lit("a"))
    rows = [tuple(r)[2:] for r in entries(p, m)]
    labels, offsets, held, values = naive(rows, kind, s, m if counter == "registers" else None)
    got = build_sketch(p, kind=kind, s=s, m=m, counter=counter, streams=1, min_search="heap").counters.orderBy("slot").collect()
    assert [r["label_key"] for r in got] == labels
    assert [r["offset"] for r in got] == pytest.approx(offsets)
    assert [r["estimate"] for r in got] == pytest.approx(values)
    if counter == "registers":
        assert [r["registers"] for r in got] == [h.tobytes() for h in held]
    else:
        assert [set(r["items"]) for r in got] == held
    assert len({r[0] for r in rows}) > s


@pytest.mark.parametrize("kind", WALKS)
def test_merge_of_walks_by_source_and_the_flagship(spark, sf, kind):
    """Each source walked alone, all counters of a label united, the s largest kept, the top told."""
    s, m = 60, 64
    p = WORKLOADS["word_docs"](spark, sf)
    streams = {}
    for r in entries(p, m):
        streams.setdefault(r["source"], []).append(tuple(r)[2:])
    assert len(streams) > 3
    whole = {}
    for rows in streams.values():
        labels, offsets, held, _ = naive(rows, kind, s, m)
        for label, o, h in zip(labels, offsets, held):
            was = whole.get(label, (0.0, np.zeros(m, np.uint8)))
            whole[label] = was[0] + o, np.maximum(was[1], h)
    values = {x: o + float(estimate_arrays(h[None, :])[0]) for x, (o, h) in whole.items()}
    best = sorted(values, key=lambda x: (-values[x], x))[:s]
    merged = merge_sketches(build_sketch(p, kind=kind, s=s, m=m, streams="by_source"))
    got = top_k(merged, 20).orderBy("rank").collect()
    assert [r["label_key"] for r in got] == best[:20]
    assert [r["estimate"] for r in got] == pytest.approx([values[x] for x in best[:20]])
    kept = {r["label_key"]: r["registers"] for r in merged.counters.collect()}
    assert kept == {x: whole[x][1].tobytes() for x in best}


@pytest.mark.parametrize("name, walks", [("gated_equals_eager_customer_parts", 2), ("gated_equals_eager_word_docs", 2), ("walk_offset_over_fraction", 1), ("pre_gated_walk_equals_walk", 2), ("walk_recycled", 1)])
def test_no_walk_is_taken_twice(spark, sf, name, walks):
    plan = QUERIES[name](spark, sf)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("MapInArrow walk(") == walks


def test_differing_rows_are_counted_with_repeats(spark):
    from tallywalk.plans.queries import differing

    a, b = (spark.createDataFrame(x, "k int, v string") for x in ([(1, "a"), (1, "a"), (2, None)], [(1, "a"), (2, None), (3, "c")]))
    assert differing(a, b).first()["differences"] == 2 and differing(a, a).first()["differences"] == 0


def test_blocks_keep_the_whole_stream_in_order(spark):
    from tallywalk.operators.sketches import _blocks, _unpacked

    rows = spark.range(50_000).select(F.col("id").cast("string").alias("label_key"), (F.col("id") * 7919 % 50_021).alias("a"), F.lit(None).cast("string").alias("x"))
    got = _blocks(rows, ["a"])
    assert got.rdd.getNumPartitions() == 1
    import pyarrow as pa

    table = pa.Table.from_batches([pa.record_batch([pa.array([bytes(r["block"]) for r in got.collect()], pa.binary())], names=["block"])])
    labels = [x for b in _unpacked(table.to_batches()) for x in b.column(0).to_pylist()]
    assert labels == [r["label_key"] for r in rows.orderBy("a").collect()]


@pytest.mark.parametrize("name", ["heavy_entries_roomy", "sql_merged_registers", *(f"walk_{k}_unbounded" for k in WALKS)])
def test_every_label_has_room(spark, tmp_path, name):
    """More suppliers than any fixed room: the answer has all of them, and equals the query's SQL."""
    import duckdb

    from tallywalk.plans.queries import ORACLES

    n = 5400
    rows = spark.range(2 * n).select(F.col("id").alias("l_orderkey"), F.lit(1).alias("l_linenumber"), (F.col("id") % n).alias("l_suppkey"), (F.col("id") * 31 % 997).alias("l_partkey"))
    rows.coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    assert oracle.differences(spark, con, QUERIES[name], ORACLES[name], str(tmp_path)) == ""
    assert QUERIES[name](spark, str(tmp_path)).count() == n
