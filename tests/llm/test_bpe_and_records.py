import hashlib
import random
import zlib

import numpy as np
import pytest
import public_tokenizers
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from tallywalk.llm import bpe, queries, records
from tallywalk.llm._frame import fresh_path

PATH = public_tokenizers.path("word_bpe_49k.json")
LIBRARY = Tokenizer.from_file(PATH)
TEXTS = [None, "", " ", "\n\t", "Hello, World's 123!!", "a" * 300 + " " + "xy" * 5000, "Straße ÉCOLE Σίσυφος ΟΔΟΣ", "<|endoftext|> a<|startoftext|>b", "a\x1cb\x1d c", "e\u0301 \u0301x", "\U0001e6dd<x\u088f", "日本語 テキスト", "\x85\xa0x", "I'LL don't"]


def ids_of(text):
    return LIBRARY.encode(text or "", add_special_tokens=False).ids


@pytest.mark.parametrize("text", TEXTS)
def test_same_ids_and_text_as_the_library(text):
    codec = bpe.codec(PATH)
    assert codec.encode(text) == ids_of(text)
    assert codec.decode(ids_of(text)) == LIBRARY.decode(ids_of(text), skip_special_tokens=False)
    assert list(records.encoder(PATH).encode_all([text])) == [np.array(ids_of(text), "<u2").tobytes()]


@settings(max_examples=200, deadline=None)
@given(st.lists(st.text(st.characters(exclude_categories=["Cs"]), max_size=30), max_size=8))
def test_any_texts(texts):
    assert bpe.codec(PATH).encode_all(texts) == list(map(ids_of, texts))
    assert [np.frombuffer(b, "<u2").tolist() for b in records.encoder(PATH).encode_all(texts)] == list(map(ids_of, texts))


def plain_merge(symbols, pairs):
    symbols = list(symbols)
    while True:
        best = min(((pairs[p][0], i) for i, p in enumerate(zip(symbols, symbols[1:])) if p in pairs), default=None)
        if best is None:
            return symbols
        i = best[1]
        symbols[i : i + 2] = [pairs[symbols[i], symbols[i + 1]][1]]


def test_segment_tree_merges_the_leftmost_lowest_rank():
    rng = random.Random(4)
    pairs, new = {}, 4
    for rank in range(12):
        p = rng.randrange(new), rng.randrange(new)
        if p not in pairs:
            pairs[p] = rank, new
            new += 1
    table = bpe.PairTable(pairs)
    words = [[rng.randrange(4) for _ in range(rng.randrange(2, 17))] for _ in range(400)]
    want = [plain_merge(w, pairs) for w in words]
    assert [bpe.merge_word(w, pairs) for w in words] == want
    assert [list(x) for x in bpe.merge_words(words, 16, table)] == want


def test_encode_and_decode_frames(spark):
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(TEXTS)], "id int, text string, ids2 string")
    rows = bpe.decode(bpe.encode(df, PATH), PATH).orderBy("id").collect()
    for r, t in zip(rows, TEXTS):
        assert r["ids"] == ids_of(t)
        assert r["decoded"] == LIBRARY.decode(ids_of(t), skip_special_tokens=False)
        assert r["ids2"] == "x"


def test_digests(spark):
    df = spark.createDataFrame([(i, t) for i, t in enumerate(TEXTS)], "doc_id bigint, text string")
    for r in bpe.digest(df, PATH, ["doc_id"]).collect():
        ids = ids_of(TEXTS[r["doc_id"]])
        assert r["n_tokens"] == len(ids)
        assert r["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(LIBRARY.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    assert bpe.digest(df.limit(0), PATH, ["doc_id"]).count() == 0


def test_checksum_is_masked_crc32c_and_frames_round_trip():
    table = records.byte_table()

    def plain(data):
        c = 0xFFFFFFFF
        for b in data:
            c = int(table[(c ^ b) & 255]) ^ (c >> 8)
        c ^= 0xFFFFFFFF
        return (((c >> 15) | (c << 17)) + records.MASK_DELTA) & 0xFFFFFFFF

    # the published check value of CRC-32C
    assert plain(b"123456789") == (((0xE3069283 >> 15) | (0xE3069283 << 17)) + records.MASK_DELTA) & 0xFFFFFFFF
    rng = np.random.default_rng(0)
    pieces = [rng.integers(0, 256, n).astype(np.uint8).tobytes() for n in (0, 1, 3, 4, 5, 63, 64, 65, 128, 1000, 4999)]
    assert records.masked_crc32c(pieces).tolist() == list(map(plain, pieces))
    data, lengths = records.frame(pieces)
    assert records.unframe(data, np.array(lengths)) == pieces
    for at in (3, 9, 100, len(data) - 1):
        broken = data[:at] + bytes([data[at] ^ 1]) + data[at + 1 :]
        with pytest.raises(ValueError):
            records.unframe(broken, np.array(lengths))
    with pytest.raises(ValueError):
        records.unframe(data[:-1], np.array(lengths))


def test_files_hold_all_documents_in_order(spark):
    rows = [(None if i == 3 else i * 7 % 11, t) for i, t in enumerate([*TEXTS, *TEXTS])]
    df = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3)
    folder = fresh_path(spark, "test-records")
    listing = records.write(df, folder, PATH, end_id=2, shards=3)
    got = records.read(listing, folder, records=4).orderBy("start").collect()
    assert len(got) == len(rows)
    keys = [-1 if r["doc_id"] is None else r["doc_id"] for r in got]
    assert keys == sorted(keys)
    assert sorted((r["doc_id"] or 0, r["ids"]) for r in got) == sorted((k or 0, [*ids_of(t), 2]) for k, t in rows)
    start = 0
    for r in got:
        assert r["start"] == start
        start += r["n_tokens"]
    shuffled = records.read(listing, folder, records=4, shuffle_seed=5)
    assert sorted(map(str, shuffled.collect())) == sorted(map(str, got))
    for r in records.read(listing, folder, digests=True).collect():
        same = next(x for x in got if x["start"] == r["start"])
        assert r["ids_crc32"] == zlib.crc32(np.array(same["ids"], "<u4").tobytes())


def test_no_documents_no_shards(spark):
    df = spark.createDataFrame([], "doc_id bigint, text string")
    folder = fresh_path(spark, "test-records")
    listing = records.write(df, folder, PATH, end_id=2)
    assert listing.count() == 0
    assert records.read(listing, folder).count() == 0


def test_query_against_the_library(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").collect()
    got = {r["doc_id"]: r for r in queries.op8_token_records(spark, sf).collect()}
    start = 0
    for d in docs:
        ids = [*ids_of(d["text"]), 2]
        assert tuple(got[d["doc_id"]]) == (d["doc_id"], start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    assert len(got) == len(docs)
    first = queries.op4_bpe_round_trip(spark, sf).where(F.col("doc_id") < 20).collect()
    assert all(r["n_tokens"] == len(ids_of(docs[r["doc_id"]]["text"])) for r in first)
