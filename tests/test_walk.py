import numpy as np
import pytest

from tallywalk.operators.walk import CounterTable, EntryTable

# (label, item, draw), exact counters, s = 2
STREAM = [("a", "p", 1.2), ("a", "q", 1.1), ("a", "r", 5), ("b", "p", 1.2), ("b", "q", 1.1), ("c", "p", 1.2), ("c", "r", 5), ("d", "q", 1.1), ("d", "t", 9), ("a", "q", 1.1), ("b", "r", 5), ("e", "p", 1.2)]


def walk(rows, batch=None, **options):
    table = CounterTable(counter="exact", **options)
    for a in range(0, len(rows), batch or len(rows)):
        part = rows[a : a + (batch or len(rows))]
        labels = sorted({r[0] for r in part})
        table.consume(labels, np.array([labels.index(r[0]) for r in part]), np.array([r[1] for r in part], object), None, np.array([float(r[2]) for r in part]))
    return table


def values(table):
    return {c["label_key"]: c["estimate"] for c in table.counters()}


@pytest.mark.parametrize("batch", [1, 2, 5, 12])
@pytest.mark.parametrize(("kind", "want"), [("offset", {"b": 6, "e": 6}), ("recycled", {"d": 4, "e": 3}), ("gated_eager", {"d": 4, "b": 3}), ("gated", {"d": 4, "b": 3})])
def test_micro_stream(kind, want, batch):
    assert values(walk(STREAM, batch, kind=kind, s=2)) == want
    assert values(walk(STREAM, batch, kind=kind, s=2, min_search="heap")) == want


@pytest.mark.parametrize("kind", ["offset", "recycled", "gated_eager", "gated"])
def test_tight_cases(kind):
    assert values(walk([("a", i, 2.0) for i in range(50)], kind=kind, s=3)) == {"a": 50}
    cycle = [(x, "one", 1.5) for x in "abcd" * 3]
    got = sorted(values(walk(cycle, kind=kind, s=3)).values())
    assert got == ([4, 4, 4] if kind == "offset" else [1, 1, 1])


def random_stream(n=4000, seed=1):
    rng = np.random.default_rng(seed)
    labels = rng.zipf(1.3, n) % 97
    items = rng.integers(0, 300, n)
    draws = {i: float(1 / u) for i, u in enumerate(rng.random(300))}
    return [(f"l{a}", int(b), draws[int(b)]) for a, b in zip(labels, items)]


@pytest.mark.parametrize("seed", range(4))
def test_cached_gate_equals_eager_gate_in_any_batches(seed):
    rows = random_stream(seed=seed)
    eager = walk(rows, kind="gated_eager", s=10)
    for batch in (1, 7, 1000, len(rows)):
        cached = walk(rows, batch, kind="gated", s=10)
        assert cached.counters() == eager.counters()
        assert cached.min_scans < eager.min_scans


@pytest.mark.parametrize("kind", ["offset", "recycled"])
def test_bounds_and_upper_values_with_exact_counters(kind):
    rows = random_stream(seed=9)
    truth = {}
    for a, b, _ in rows:
        truth.setdefault(a, set()).add(b)
    table = walk(rows, kind=kind, s=10)
    floor = table.floor()
    assert floor <= len(rows) / 10
    for label, items in truth.items():
        got = values(table).get(label)
        if got is None:
            assert len(items) <= floor
        else:
            assert abs(got - len(items)) <= len(rows) / 10
            assert got <= len(items) + floor


def test_floor_never_falls():
    rows, last = random_stream(seed=3), 0.0
    table = CounterTable(counter="exact", kind="gated", s=10)
    for a, b, d in rows:
        table.consume([a], np.array([0]), np.array([b], object), None, np.array([d]))
        assert table.floor() >= last
        last = table.floor()


def test_degenerate_tables():
    assert CounterTable().counters() == []
    assert values(walk(STREAM[:1], kind="gated", s=1)) == {"a": 1}
    with pytest.raises(ValueError):
        CounterTable(kind="other")
    with pytest.raises(ValueError):
        CounterTable(s=0)


def test_entry_table_keeps_sums_and_bounds():
    rows = [r[0] for r in random_stream(seed=5)]
    table = EntryTable(10)
    table.consume(rows)
    assert sum(c[0] for c in table.counts.values()) == len(rows)
    for x, (c,) in table.counts.items():
        assert rows.count(x) <= c <= rows.count(x) + len(rows) / 10


@pytest.mark.parametrize("kind", ["offset", "recycled", "gated"])
def test_heap_stays_as_small_as_the_table(kind):
    rows = random_stream(n=30_000, seed=6)
    table = walk(rows, 500, kind=kind, s=50, min_search="heap")
    assert len(table.heap) <= 100
    assert table.counters() == walk(rows, kind=kind, s=50).counters()


def test_table_function_registers_of_any_number():
    from tallywalk.functions.sqlapi import register_of

    for m in (64, 438, 1000):
        got = [register_of(str(i), m) for i in range(20_000)]
        assert {b for b, _ in got} == set(range(m)) and min(r for _, r in got) == 1
        assert 0.45 < sum(r == 1 for _, r in got) / len(got) < 0.55


def register_batches(n=6000, m=64):
    rng = np.random.default_rng(8)
    names, items = rng.zipf(1.3, n) % 997, rng.integers(0, 3000, n)
    draws, buckets, ranks = 1 / rng.random(3000), rng.integers(0, m, 3000), rng.geometric(0.5, 3000).astype(np.uint8)
    for a in range(0, n, 1500):
        labels, codes = np.unique(names[a : a + 1500], return_inverse=True)
        some = items[a : a + 1500]
        yield [f"l{x}" for x in labels], codes, some, buckets[some], ranks[some], draws[some]


def batches_walked(**options):
    table = CounterTable(m=64, s=30, **options)
    for labels, codes, items, buckets, ranks, draws in register_batches():
        exact = table.counter == "exact"
        table.consume(labels, codes, items.astype(str).astype(object) if exact else buckets, None if exact else ranks, draws)
    return table


@pytest.mark.parametrize("estimator", ["histogram", "classic"])
@pytest.mark.parametrize("counter", ["registers", "exact"])
@pytest.mark.parametrize("kind", ["offset", "recycled", "gated_eager", "gated"])
def test_one_by_one_and_in_stretches_are_the_same(monkeypatch, kind, counter, estimator):
    from tallywalk.operators import walk as module

    got = []
    for dense, search in ((0, "heap"), (10**9, "heap"), (10**9, "argmin"), (32, "heap")):
        monkeypatch.setattr(module, "DENSE", dense)
        table = batches_walked(kind=kind, counter=counter, estimator=estimator, min_search=search, dense=dense > 0)
        got.append((table.counters(), table.meta()))
    assert got[0] == got[1] == got[2] == got[3]
    assert [c["estimate"] for c in table.counters(contents=False)] == [c["estimate"] for c in got[0][0]]
    assert all(c["registers"] is None and c["items"] is None for c in table.counters(contents=False))


@pytest.mark.parametrize("kind", ["offset", "recycled", "gated_eager"])
def test_strange_labels_cost_no_look_at_all_counters(monkeypatch, kind):
    calls, real = [], CounterTable.refresh
    monkeypatch.setattr(CounterTable, "refresh", lambda table: calls.append(1) or real(table))
    table = batches_walked(kind=kind)
    assert table.min_scans > 1000 and len(calls) < 20


@pytest.mark.parametrize("kind", ["offset", "recycled"])
@pytest.mark.parametrize("s", [1, 3, 40])
def test_keys_walk_as_texts_do(kind, s):
    """Entries by their own keys, numbers and strings mixed, take the steps of those by codes."""
    rng = np.random.default_rng(s)
    labels = [int(x) if x % 3 else f"0{x}" for x in np.minimum(rng.zipf(1.3, 4000), 300)]
    items = [int(x) if x % 2 else f"i{x}" for x in rng.integers(0, 50, 4000)]
    by_key, by_code = (CounterTable(kind=kind, s=s, counter="exact") for _ in range(2))
    for a in range(0, 4000, 700):
        by_key.consume_keys(labels[a : a + 700], items[a : a + 700])
        texts = [str(x) for x in labels[a : a + 700]]
        known = sorted(set(texts))
        by_code.consume(known, np.array([known.index(x) for x in texts]), np.array([str(x) for x in items[a : a + 700]], object), None, np.ones(len(texts)))
    assert by_key.counters() == by_code.counters() and by_key.meta() == by_code.meta()


def test_keys_stay_what_they_are(spark):
    """Texts that are read as the same number are labels and items of their own; numbers beyond 64 bits too."""
    from tallywalk.operators.sketches import build_sketch

    texts = ["7", "07", "+7", " 7", "7 ", "7.0", "-7", "", "x", "9" * 19, "9" * 40, "-0", "0"]
    rows = [(a, b) for a in texts for b in texts]
    pairs = spark.createDataFrame(rows, "label_key string, item_key string")
    for streams in (1, "by_label"):
        got = build_sketch(pairs, kind="recycled", s=100, counter="exact", streams=streams).counters.select("label_key", "items").collect()
        assert {r["label_key"]: r["items"] for r in got} == {t: sorted(texts) for t in texts}


def test_table_function_takes_batches():
    """Each batch whole, nulls and repeated or forgotten items included, as a walk over the rows' own hashes."""
    import pyarrow as pa
    import xxhash

    from tallywalk.functions.hashing import HASH_BITS
    from tallywalk.functions.sqlapi import HeavyLabels

    rng, m = np.random.default_rng(5), 16
    rows = [(int(a) or None, int(b) or None) for a, b in zip(rng.integers(0, 60, 6000), rng.integers(0, 900, 6000))]
    made = HeavyLabels()
    made.REMEMBERED = 300
    for a in range(0, 6000, 500):
        batch = pa.RecordBatch.from_pydict({"label": [r[0] for r in rows[a : a + 500]], "item": [r[1] for r in rows[a : a + 500]]})
        made.eval(batch, pa.array([4]), pa.array([20]), pa.array([m]), pa.array(["gated"]))
    (got,) = made.terminate()
    plain, rest = CounterTable(kind="gated", s=20, m=m), HASH_BITS - 4
    for a, b in rows:
        if a is None or b is None:
            continue
        c, g = (xxhash.xxh64_intdigest(f"{t}|{b}") >> 12 for t in "cg")
        plain.consume([str(a)], np.array([0]), np.array([c >> rest]), np.array([rest + 1 - (c & ((1 << rest) - 1)).bit_length()], np.uint8), np.array([2.0**HASH_BITS / (g + 0.5)]))
    best = sorted(plain.counters(), key=lambda r: (-r["estimate"], r["label_key"]))[:4]
    assert got.to_pylist() == [{"label": r["label_key"], "estimate": r["estimate"], "rank": i + 1} for i, r in enumerate(best)]
