import corpus_pipeline
from tallywalk.llm import langid
from tallywalk.llm._words import words_of
from tests.llm.test_text_operators import base_by_reading, brute_leaks, brute_links, classes


def test_stages_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = {r["doc_id"]: r for r in docs.collect()}
    items = {r["item_id"]: r["text"] for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    stages = dict(corpus_pipeline.STAGES)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "near_copies", "benchmark", "secrets", "tokens"]

    known = stages["language"](spark, docs, sf)
    assert known.columns == docs.columns
    kept = {r["doc_id"] for r in known.collect()}
    assert kept == {i for i, r in rows.items() if words_of(r["text"])}

    one = stages["near_copies"](spark, docs, sf)
    got = {r["doc_id"] for r in one.collect()}
    root = classes(brute_links({i: r["text"] for i, r in rows.items()}))
    assert len(got) == len(set(root.values())) and {root[i] for i in got} == set(root.values())
    assert one.columns == docs.columns

    clean = stages["benchmark"](spark, docs, sf)
    inside = {i for i, r in rows.items() if any(f" {' '.join(words_of(x))} " in f" {' '.join(words_of(r['text']))} " for x in items.values())}
    left = {r["doc_id"] for r in clean.collect()}
    assert not left & inside and len(left) >= len(rows) - len(inside) - 2
    few = {i: rows[i]["text"] for i in sorted(rows)[:15]}
    assert set(few) - left == set(brute_leaks(few, items))

    redacted = {r["doc_id"]: r for r in stages["secrets"](spark, docs, sf).collect()}
    assert set(redacted) == set(rows)
    for i, r in redacted.items():
        if not base_by_reading(rows[i]["text"]):
            assert r["text"] == rows[i]["text"] or "<secret>" in r["text"]
        assert r["n_chars"] == len(r["text"]) or r["text"] == rows[i]["text"]


def test_whole_run(spark, sf):
    out = corpus_pipeline.run(spark, sf).collect()
    assert 0 < len(out) <= spark.read.parquet(f"{sf}/documents.parquet").count()
    assert len({r["doc_id"] for r in out}) == len(out)


def test_odd_documents(spark):
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "the same words again", "en", "a", 20), (3, "the same words again", "en", "a", 20), (None, "other words in here password=abc123xyz", "en", "b", 9)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    spark.createDataFrame([(0, "x y z")], "item_id bigint, text string").write.mode("overwrite").parquet("/tmp/tallywalk-test/benchmark.parquet")
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, "/tmp/tallywalk-test")
        if name == "near_copies":
            assert sorted(str(r["doc_id"]) for r in docs.collect()) == ["3", "None"]
    assert docs.count() == 2
    empty = spark.createDataFrame([], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    for _, stage in corpus_pipeline.STAGES:
        empty = stage(spark, empty, "/tmp/tallywalk-test")
    assert empty.count() == 0


def test_model_is_small():
    assert langid.LONGEST == 4


def test_the_driver_gives_stretched_heap_back(spark, monkeypatch):
    """Written tables look at the heap; garbage is collected where it has stretched, and not again before it has grown by a quarter."""
    from tallywalk.llm import _frame

    monkeypatch.setattr(_frame, "_left", [0])
    assert not _frame.trim_driver(spark, share=2.0)
    assert _frame.trim_driver(spark, share=0.0) and _frame._left[0] > 0
    assert not _frame.trim_driver(spark, share=0.0)
    seen = []
    monkeypatch.setattr(_frame, "trim_driver", seen.append)
    assert _frame.written(spark.range(3), "three").count() == 3 and seen == [spark]
