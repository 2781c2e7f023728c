"""Token ids in length-delimited binary records with masked checksums, and an offset index for shuffled reads.

A shard is a file of records:

    length of the payload   unsigned 64 bit, little-endian
    masked CRC-32C of these 8 bytes
    payload                 document id (signed 64 bit), flags (bit 0: the id is null; bit 1: ids of 32 bits, else 16), the ids
    masked CRC-32C of the payload

which is the framing of TFRecord files, so that their readers can read it too. Beside it lies an index: for each record,
in order, its offset in the shard and the number of ids of all records before it (two unsigned 64-bit numbers), and at the end the shard's size and number of ids; so a range of records is
found by reading its own part of the index alone. Shards are ranges of document ids in ascending order, null first, ties in any order.

Tasks write under a name of their own and then rename, so a task that runs twice leaves one whole file. The folder can be in
any store that pyarrow can open.

Defined results: a null or empty text is a record of the end id alone. Rows that repeat are records of their own. An empty
table gives no shard. Other columns are not read. Ids need not be unique.
"""

from __future__ import annotations

import json
import uuid
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallywalk.llm._frame import Memo, alone, in_parts, small_batches
from tallywalk.llm.bpe import is_latin

MASK_DELTA = 0xA282EAD8  # of the TFRecord framing
POLYNOMIAL = 0x82F63B78  # CRC-32C, reflected
BLOCK = 64


@lru_cache(maxsize=1)
def byte_table() -> np.ndarray:
    t = np.arange(256, dtype=np.uint32)
    for _ in range(8):
        t = np.where(t & 1, (t >> 1) ^ np.uint32(POLYNOMIAL), t >> 1)
    return t


def through_zeros(state: np.ndarray, n: int) -> np.ndarray:
    for _ in range(n):
        state = byte_table()[state & 255] ^ (state >> 8)
    return state


@lru_cache(maxsize=64)
def shift_tables(level: int) -> tuple[np.ndarray, np.ndarray]:
    """For BLOCK * 2**level zero bytes (level -1: for 4): what each half of a CRC state becomes."""
    halves = np.arange(1 << 16, dtype=np.uint32), np.arange(1 << 16, dtype=np.uint32) << np.uint32(16)
    if level > 0:
        return tuple(shifted(shifted(h, level - 1), level - 1) for h in halves)
    return tuple(through_zeros(h, BLOCK if level == 0 else 4) for h in halves)


def shifted(state: np.ndarray, level: int) -> np.ndarray:
    low, high = shift_tables(level)
    return low[state & 0xFFFF] ^ high[state >> 16]


def masked_crc32c(pieces: list[bytes]) -> np.ndarray:
    """Masked CRC-32C of many pieces at once: their 64-byte blocks side by side, four bytes in a step, then pairs of blocks, level by level."""
    n = len(pieces)
    if not n:
        return np.zeros(0, np.uint32)
    lengths = np.fromiter(map(len, pieces), np.int64, n)
    blocks = np.maximum(1, -(-lengths // BLOCK))
    first = np.concatenate([[0], np.cumsum(blocks)])
    # zero bytes in front do not change a CRC that starts from 0
    zeros = b"\0" * BLOCK
    padded = np.frombuffer(bytearray().join(x for p in pieces for x in (zeros[: -len(p) % BLOCK] if p else zeros, p)), np.uint8).copy()
    # the usual start of all ones is the same as turning the first four bytes over
    to = first[1:] * BLOCK - lengths
    for i in range(4):
        padded[(to + i)[lengths > i]] ^= 255
    state = np.zeros(int(first[-1]), np.uint32)
    for column in np.ascontiguousarray(padded.view("<u4").reshape(-1, BLOCK // 4).T):
        state = shifted(state ^ column, -1)
    level = 0
    while blocks.max() > 1:
        halves = (blocks + 1) // 2
        where = np.concatenate([[0], np.cumsum(halves)])
        # an odd block in front stays alone
        pos = np.arange(int(first[-1])) - np.repeat(first[:-1] - blocks % 2, blocks)
        target = np.repeat(where[:-1], blocks) + pos // 2
        merged = np.zeros(int(where[-1]), np.uint32)
        left = pos % 2 == 0
        merged[target[left]] = shifted(state[left], level)
        merged[target[~left]] ^= state[~left]
        state, blocks, first, level = merged, halves, where, level + 1
    crc = state ^ np.uint32(0xFFFFFFFF)
    for i in np.flatnonzero(lengths < 4):  # fewer bytes to turn over than the state has
        c = np.array([0xFFFFFFFF], np.uint32)
        for b in pieces[i]:
            c = byte_table()[(c ^ np.uint32(b)) & 255] ^ (c >> 8)
        crc[i] = c[0] ^ np.uint32(0xFFFFFFFF)
    return ((crc >> 15 | crc << 17) + np.uint32(MASK_DELTA)).astype(np.uint32)


def frame(payloads: list[bytes]) -> tuple[bytes, list[int]]:
    """The records of these payloads, and their lengths in the file."""
    lengths = [len(p).to_bytes(8, "little") for p in payloads]
    heads, tails = (masked_crc32c(x).astype("<u4").tobytes() for x in (lengths, payloads))
    parts = (x for i, p in enumerate(payloads) for x in (lengths[i], heads[4 * i : 4 * i + 4], p, tails[4 * i : 4 * i + 4]))
    return b"".join(parts), [len(p) + 16 for p in payloads]


def unframe(data: bytes, lengths: np.ndarray) -> list[bytes]:
    """The payloads of whole records of these lengths in the file. Raises ValueError where a length or a checksum does not fit."""
    ends = np.cumsum(lengths).tolist()
    if len(data) != (ends[-1] if ends else 0):
        raise ValueError("the file is shorter than its index says")
    starts = [0, *ends[:-1]]
    heads = [data[a : a + 8] for a in starts]
    if any(int.from_bytes(h, "little") != b - a - 16 for h, a, b in zip(heads, starts, ends)) or b"".join(data[a + 8 : a + 12] for a in starts) != masked_crc32c(heads).astype("<u4").tobytes():
        raise ValueError("a record's length does not fit its checksum or the index")
    payloads = [data[a + 12 : b - 4] for a, b in zip(starts, ends)]
    if b"".join(data[b - 4 : b] for b in ends) != masked_crc32c(payloads).astype("<u4").tobytes():
        raise ValueError("a record's payload does not fit its checksum")
    return payloads


def payload(doc_id: int | None, ids: bytes, wide: bool) -> bytes:
    return (doc_id or 0).to_bytes(8, "little", signed=True) + bytes([(doc_id is None) | wide << 1]) + ids


def opened(payload_: bytes) -> tuple[int | None, np.ndarray]:
    flags = payload_[8]
    return None if flags & 1 else int.from_bytes(payload_[:8], "little", signed=True), np.frombuffer(payload_, "<u4" if flags & 2 else "<u2", offset=9)


class LibraryEncoder:
    """Ids of texts as the tokenizers library gives them, as little-endian bytes.

    Words repeat, and no rule of a vocabulary of this kind joins pieces over white space, so a batch of Latin texts is cut at white space, each distinct
    word goes to the library once while it is remembered, and the ids are put together by array arithmetic. All other texts go to the library whole."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.own = Tokenizer.from_file(path)
        self.own.no_truncation()
        self.own.no_padding()
        self.wide = self.own.get_vocab_size() > 1 << 16
        self.kind = np.dtype("<u4" if self.wide else "<u2")
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        split = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.pieces = regex.compile(split + r"|\n")
        self.special = [t["content"] for t in spec["added_tokens"]]
        vocab = self.own.get_vocab(with_added_tokens=True)
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for t, i in vocab.items() if t.endswith(spec["model"]["end_of_word_suffix"])]] = True
        self.words = Memo(1 << 18)

    def plain(self, text: str | None) -> bool:
        return bool(text) and is_latin(text) and not any(c in text for c in "\x1c\x1d\x1e\x1f") and not any(s in text for s in self.special)

    def learn(self, pieces: list[str]) -> None:
        """The library's ids of words; it gets them as one text, in which every word ends with a token of its own kind."""
        for a in range(0, len(pieces), 20_000):
            part = pieces[a : a + 20_000]
            ids = np.array(self.own.encode_batch_fast([" ".join(part)], add_special_tokens=False)[0].ids, np.int64)
            ends = np.flatnonzero(self.ends[ids]) + 1
            if len(ends) != len(part):
                raise ValueError("the vocabulary does not end each word with a token of its own")
            raw, width = ids.astype(self.kind).tobytes(), self.kind.itemsize
            self.words.now.update(zip(part, (raw[i * width : j * width] for i, j in zip([0, *ends[:-1].tolist()], ends.tolist()))))

    def encode_plain(self, texts: list[str]) -> list[bytes]:
        cut = pc.utf8_split_whitespace(pa.array(texts, pa.string()))
        coded = cut.flatten().dictionary_encode()
        distinct = pa.ListArray.from_arrays(pa.array([0, len(coded.dictionary)], pa.int32()), coded.dictionary)
        text = pc.binary_join(distinct, "\n")[0].as_py()
        pieces = pa.array(self.pieces.findall(text.lower()), pa.string()).dictionary_encode()
        words = pieces.dictionary.to_numpy(zero_copy_only=False).tolist()
        self.learn(self.words.make_room(w for w in words if w != "\n"))
        known_ids = self.words.now
        known = [b"" if w == "\n" else known_ids[w] for w in words]
        width = self.kind.itemsize
        # ids of each distinct word: the pieces between line ends
        stream = pieces.indices.to_numpy()
        sizes = (np.fromiter(map(len, known), np.int64, len(known)) // width)[stream]
        group = np.cumsum(stream == (words.index("\n") if "\n" in words else -1))
        lengths = np.bincount(group, sizes, minlength=len(coded.dictionary)).astype(np.int64)
        flat = map(known.__getitem__, stream.tolist())
        ids = np.frombuffer(b"".join(flat), self.kind)
        where = np.cumsum(lengths) - lengths
        which = coded.indices.to_numpy()
        counts = lengths[which]
        ends = np.cumsum(counts)
        at = np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(where[which] - (ends - counts), counts)
        out = ids[at]
        bounds = np.concatenate([[0], ends])[cut.offsets.to_numpy()].tolist()
        return [out[i:j].tobytes() for i, j in zip(bounds, bounds[1:])]

    def encode_all(self, texts: list[str | None]):
        for some in in_parts(texts, 1 << 24):
            plain = [self.plain(t) for t in some]
            fast = iter(self.encode_plain([t for t, p in zip(some, plain) if p]))
            for text, p in zip(some, plain):
                yield next(fast) if p else np.array(self.own.encode(text, add_special_tokens=False).ids if text else [], self.kind).tobytes()


@alone
def encoder(path: str) -> LibraryEncoder:
    return LibraryEncoder(path)


def gathered(batches, chars: int = 1 << 24):
    """Keys and texts of several batches at a time: more texts share more words."""
    keys, texts, total = [], [], 0
    for batch in batches:
        keys += batch.column(0).to_pylist()
        more = batch.column(1).to_pylist()
        texts += more
        total += sum(len(t) for t in more if t)
        if total >= chars:
            yield keys, texts
            keys, texts, total = [], [], 0
    if keys:
        yield keys, texts


def write(df: DataFrame, folder: str, vocabulary: str, end_id: int, text: str = "text", key: str = "doc_id", shards: int | None = None) -> DataFrame:
    """Writes shards and indexes below folder, and gives a row for each shard: shard, path, first_key, n_records, n_ids (a few numbers a file)."""
    small_batches()
    spark = df.sparkSession
    slim = df.select(F.col(key).cast("bigint").alias("key"), F.col(text).alias("text"), F.xxhash64(text).alias("tie"))  # many rows of one id still make many shards
    dealt = slim.repartitionByRange(*([shards] if shards else []), F.col("key").asc_nulls_first(), "tie").sortWithinPartitions(F.col("key").asc_nulls_first(), "tie").drop("tie")

    def run(batches):
        store, base = pafs.FileSystem.from_uri(folder)
        enc = encoder(vocabulary)
        end = np.array([end_id], enc.kind).tobytes()
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        own = f"{base}/.{part:06d}-{uuid.uuid4().hex}"
        out, offset, index, first, n_ids = None, 0, [], None, 0
        try:
            for keys, texts in gathered(batches):
                if out is None:
                    store.create_dir(base, recursive=True)
                    out, first = store.open_output_stream(own), keys[0]
                width = 4 if enc.wide else 2
                ids = [x + end for x in enc.encode_all(texts)]
                for a in range(0, len(ids), 1024):
                    data, lengths = frame([payload(k, x, enc.wide) for k, x in zip(keys[a : a + 1024], ids[a : a + 1024])])
                    out.write(data)
                    counts = np.array([len(x) // width for x in ids[a : a + 1024]], np.int64)
                    index.append(np.array([np.cumsum(lengths) - lengths + offset, np.cumsum(counts) - counts + n_ids], "<u8").T)
                    offset += len(data)
                    n_ids += int(counts.sum())
        finally:
            if out is not None:
                out.close()
        if out is None:
            return
        table = np.concatenate([*index, np.array([[offset, n_ids]], "<u8")])
        with store.open_output_stream(own + ".index") as f:
            f.write(table.tobytes())
        path = f"{base}/{part:06d}.rec"
        store.move(own + ".index", path + ".index")
        store.move(own, path)
        yield pa.RecordBatch.from_pydict({"shard": [part], "path": [path], "first_key": [first], "n_records": [len(table) - 1], "n_ids": [n_ids]}, schema=pa.schema([("shard", pa.int64()), ("path", pa.string()), ("first_key", pa.int64()), ("n_records", pa.int64()), ("n_ids", pa.int64())]))

    made = dealt.mapInArrow(run, "shard bigint, path string, first_key bigint, n_records bigint, n_ids bigint")
    listing = f"{folder}/listing"
    made.write.parquet(listing)
    return spark.read.schema(made.schema).parquet(listing)


def starts(listing: DataFrame) -> DataFrame:
    """The listing with the number of ids in all shards before each. One row a file: small for any corpus."""
    from pyspark.sql import Window

    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    return listing.withColumn("start", F.coalesce(F.sum("n_ids").over(before), F.lit(0)))


def read(listing: DataFrame, folder: str, records: int = 4096, digests: bool = False, shuffle_seed: int | None = None) -> DataFrame:
    """The documents of the shards: doc_id, start (ids of all documents before it), n_tokens, and ids as array<int>, or with digests their CRC-32.

    Index ranges of so many records are dealt to the tasks, so that reading is as even as the data; each opens its shard at the range's
    offset. With a seed the ranges come in another order, and the records in each as well."""
    spark = listing.sparkSession
    ranges = starts(listing).select("path", "start", "n_records", F.explode(F.sequence(F.lit(0), F.greatest(F.col("n_records") - 1, F.lit(0)), F.lit(records))).alias("at"))
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    order = F.xxhash64("path", "at", F.lit(shuffle_seed or 0))
    dealt = ranges.repartition(parts, order)
    if shuffle_seed is not None:
        dealt = dealt.sortWithinPartitions(order)
    value = ("ids_crc32", pa.int64()) if digests else ("ids", pa.list_(pa.int32()))
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), value])

    def run(batches):
        store, _ = pafs.FileSystem.from_uri(folder)
        for batch in batches:
            for row in batch.to_pylist():
                n, at = row["n_records"], row["at"]
                with store.open_input_file(row["path"] + ".index") as f:
                    f.seek(16 * at)
                    table = np.frombuffer(f.read(16 * (min(records, n - at) + 1)), "<u8").reshape(-1, 2).astype(np.int64)
                with store.open_input_file(row["path"]) as f:
                    for a in range(0, len(table) - 1, 512):
                        b = min(a + 512, len(table) - 1)
                        begin, finish = int(table[a, 0]), int(table[b, 0])
                        f.seek(begin)
                        docs = [opened(p) for p in unframe(f.read(finish - begin), np.diff(table[a : b + 1, 0]))]
                        begins = (table[a:b, 1] + row["start"]).tolist()
                        counts = np.diff(table[a : b + 1, 1])
                        values = [zlib.crc32(ids.astype("<u4").tobytes()) for _, ids in docs] if digests else [ids.astype(np.int32) for _, ids in docs]
                        got = {"doc_id": [k for k, _ in docs], "start": begins, "n_tokens": counts.tolist(), value[0]: values}
                        if shuffle_seed is not None:
                            mix = np.random.default_rng([shuffle_seed, at + a]).permutation(b - a).tolist()
                            got = {k: [v[i] for i in mix] for k, v in got.items()}
                        yield pa.RecordBatch.from_pydict(got, schema=schema)

    return dealt.mapInArrow(run, f"doc_id bigint, start bigint, n_tokens bigint, {'ids_crc32 bigint' if digests else 'ids array<int>'}")
