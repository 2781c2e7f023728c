"""Benchmark decontamination: SimHash of item-sized windows, a multi-index over Hamming blocks, and exact weighted-shingle similarity.

For each benchmark item a document is looked at in windows of as many words as the item has (a shorter document is one window). A window's
fingerprint is the 64-bit SimHash of its weighted word shingles. The index cuts fingerprints into 8 blocks of 8 bits: if two of them differ in at most
RADIUS = 23 bits, one block differs in at most 2. So every item is filed, in a table for each number of words and each block, under the 37 values that differ from its
own block in at most 2 bits, and a window reads one entry of each of the 8 tables; what it finds there and is within the radius is a candidate. Each candidate is
verified by the weighted Jaccard similarity of its shingles with the window's, at least 0.8.

Windows that share no shingle with any item of their size have similarity 0 and are not fingerprinted; that loses nothing.
A shingle weighs 1 + ln(items / items that have it), so that phrases of many items count less.

The benchmark goes to the tasks in slices of at most about `slice_words` words, one pass over the documents after the other; a pass holds one slice, and leaves a table of what it
found. Usual benchmarks are one slice. Weights are those of the whole benchmark however it is sliced: each slice is sent the shingles that two items or more of the whole have (12 bytes each).

Defined results: null or empty texts are clean, as is everything with an empty benchmark. Null or empty items match nothing. Repeated items are all reported. Repeated rows
get equal verdicts. An item of 1 to 4 words has one shingle of all its words and is found only where it is a whole text, never as a passage of a longer one (as in the SQL twin). Words are runs of
letters, digits and "_", in lower case. Other columns are kept unread, but for one of the name of the result, which the result replaces; texts are searched whole.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallywalk.llm._frame import struct_udf, with_row_key, written
from tallywalk.llm._words import LEAST, WIDTH, shingled

BLOCKS, BLOCK_BITS, BLOCK_RADIUS = 8, 8, 2
RADIUS = BLOCKS * (BLOCK_RADIUS + 1) - 1
BITS = np.arange(64, dtype=np.uint64)
PAIRS = 1 << 21  # entries of the tables that are read at once
ITEM_WORDS = 160  # what an item's places in the tables weigh, in words


def signs(hashes: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """The weight of each shingle, positive or negative by each of its bits."""
    return np.where(hashes[:, None] >> BITS & np.uint64(1), weights[:, None], -weights[:, None])


def packed(sums: np.ndarray) -> np.ndarray:
    """Fingerprints of rows of 64 sums."""
    return ((sums > 0).astype(np.uint64) << BITS).sum(axis=1, dtype=np.uint64)


def looked_up(keys: np.ndarray, values: np.ndarray, wanted: np.ndarray, otherwise: float) -> np.ndarray:
    """The values of wanted keys; keys are sorted."""
    if not len(keys):
        return np.full(len(wanted), otherwise)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return np.where(keys[at] == wanted, values[at], otherwise)


def block_values(prints: np.ndarray) -> np.ndarray:
    """A row for each fingerprint, its blocks as numbers."""
    return (prints[:, None] >> (np.arange(BLOCKS, dtype=np.uint64) * np.uint64(BLOCK_BITS)) & np.uint64((1 << BLOCK_BITS) - 1)).astype(np.int64)


def runs(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """starts[0], starts[0] + 1 and so on, counts[0] of them, then those of the next run."""
    return np.repeat(starts - (np.cumsum(counts) - counts), counts) + np.arange(int(counts.sum()))


class Blocks:
    """The tables of items of one number of words: for each block and value the items whose block is within BLOCK_RADIUS of it."""

    def __init__(self, items: np.ndarray, prints: np.ndarray):
        values = np.arange(1 << BLOCK_BITS)
        around = [values[np.bitwise_count(values ^ v) <= BLOCK_RADIUS] for v in values]
        self.items, self.prints = items, prints
        self.starts = np.zeros((BLOCKS, (1 << BLOCK_BITS) + 1), np.int64)
        filed, total = [], 0
        for b, own in enumerate(block_values(prints).T):
            under = np.concatenate([around[v] for v in own])
            order = np.argsort(under, kind="stable")
            filed.append(np.repeat(np.arange(len(items), dtype=np.int32), len(around[0]))[order])
            self.starts[b] = total + np.searchsorted(under[order], np.arange((1 << BLOCK_BITS) + 1))
            total += len(under)
        self.filed = np.concatenate(filed)

    def near(self, prints: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pairs (window, place in items) within RADIUS, in order."""
        got, a, blocks = [], 0, np.arange(BLOCKS)
        values = block_values(prints)
        counts = self.starts[blocks, values + 1] - self.starts[blocks, values]
        reach = np.cumsum(counts.sum(axis=1))
        while a < len(prints):
            before = int(reach[a - 1]) if a else 0
            b = max(a + 1, int(np.searchsorted(reach, before + PAIRS, "right")))
            some = counts[a:b].ravel()
            there = self.filed[runs(self.starts[blocks, values[a:b]].ravel(), some)]
            pair = np.unique(np.repeat(np.repeat(np.arange(a, b), BLOCKS), some) * len(self.items) + there)
            w, i = pair // len(self.items), pair % len(self.items)
            close = np.bitwise_count(prints[w] ^ self.prints[i]) <= RADIUS
            got.append((w[close], i[close]))
            a = b
        return tuple(np.concatenate(x) for x in zip(*got))


def sliding(grams: list[int], shared: list[bool], counts: list[int], weights: list[float], starts: list[int], span: int) -> list[float]:
    """The weight that each window shares with an item of these counts; grams are numbers of the item's shingles where shared."""
    out, held, total, first, end = [], [0] * len(counts), 0.0, starts[0], starts[0]
    for s in starts:
        if s >= end:
            held, total, first, end = [0] * len(counts), 0.0, s, s
        for p in range(end, s + span):
            if shared[p]:
                g = grams[p]
                held[g] += 1
                total += weights[g] if held[g] <= counts[g] else 0.0
        for p in range(first, s):
            if shared[p]:
                g = grams[p]
                total -= weights[g] if held[g] <= counts[g] else 0.0
                held[g] -= 1
        first, end = s, s + span
        out.append(total)
    return out


@dataclass
class Item:
    grams: np.ndarray  # distinct shingles, sorted
    counts: np.ndarray
    weights: np.ndarray

    @property
    def total(self) -> float:
        return float(self.counts @ self.weights)


@dataclass
class Index:
    ids: list[int]
    lengths: np.ndarray  # words of each item
    items: list[Item]
    total: int  # items of the whole benchmark
    common: np.ndarray  # shingles of two items or more of the whole benchmark, sorted
    common_weight: np.ndarray
    known: np.ndarray  # all shingles, sorted
    sizes: list[np.ndarray]  # numbers of words of the items of each known shingle
    maybe: np.ndarray  # a bit filter of the known shingles
    blocks: dict[int, Blocks]

    @classmethod
    def of(cls, ids: list[int], texts: list[str | None], corpus: tuple[int, np.ndarray, np.ndarray] | None = None) -> Index:
        """corpus, of a slice: the whole benchmark's number of items, its shared shingles, sorted, and how many items have each."""
        found = [(i, n, np.unique(g, return_counts=True)) for i, (n, g) in zip(ids, shingled(texts)) if n]
        n = len(found)
        owned = np.concatenate([g for _, _, (g, _) in found]) if n else np.zeros(0, np.uint64)
        lengths = np.array([k for _, k, _ in found], np.int64)
        known, counts = np.unique(owned, return_counts=True)
        if corpus is None:
            corpus = n, known[counts > 1], counts[counts > 1]
        total, common, common_counts = corpus
        common_weight, rare = 1 + np.log(total / common_counts), 1 + math.log(max(1, total))
        items = [Item(g, c, looked_up(common, common_weight, g, rare)) for _, _, (g, c) in found]
        prints = np.array([packed((signs(x.grams, x.weights * x.counts)).sum(axis=0)[None, :].round(9))[0] for x in items], np.uint64)
        of_item = np.repeat(lengths, [len(x.grams) for x in items]) if n else lengths
        pairs = np.unique(np.stack([np.searchsorted(known, owned), of_item]), axis=1) if n else np.zeros((2, 0), np.int64)
        sizes = np.split(pairs[1], np.flatnonzero(np.diff(pairs[0])) + 1) if n else []
        maybe = np.zeros(1 << max(16, min(24, (8 * len(known)).bit_length())), bool)
        maybe[(known & np.uint64(len(maybe) - 1)).astype(np.int64)] = True
        blocks = {int(k): Blocks(w := np.flatnonzero(lengths == k), prints[w]) for k in np.unique(lengths)}
        return cls([i for i, _, _ in found], lengths, items, total, common, common_weight, known, sizes, maybe, blocks)

    @property
    def rare(self) -> float:
        return 1 + math.log(max(1, self.total))

    def known_places(self, grams: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where grams are known, and which of the known shingles they are."""
        at = np.flatnonzero(self.maybe[(grams & np.uint64(len(self.maybe) - 1)).astype(np.int64)])
        if not len(at):
            return at, at
        k = np.minimum(np.searchsorted(self.known, grams[at]), len(self.known) - 1)
        hit = self.known[k] == grams[at]
        return at[hit], k[hit]

    def similarities(self, item: Item, grams: np.ndarray, weights: np.ndarray, starts: np.ndarray, span: int) -> np.ndarray:
        """Of the windows that begin at these places, in order, of a document's shingles."""
        low, high = int(starts[0]), int(starts[-1]) + span
        own = np.minimum(np.searchsorted(item.grams, grams[low:high]), len(item.grams) - 1)
        shared = item.grams[own] == grams[low:high]
        sums = np.append(0.0, np.cumsum(weights[low:high]))
        whole = sums[starts - low + span] - sums[starts - low]
        both = np.zeros(len(starts))
        step = max(1, PAIRS // (len(item.grams) + span))
        if span * len(item.grams) > 1 << 18:  # long items: what enters and leaves from window to window
            both[:] = sliding(own.tolist(), shared.tolist(), item.counts.tolist(), item.weights.tolist(), (starts - low).tolist(), span)
        else:
            for a in range(0, len(starts), step):
                some = starts[a : a + step] - low
                for c in np.split(some, np.flatnonzero(np.diff(some) > span) + 1):
                    first, last = int(c[0]), int(c[-1]) + span
                    where = np.flatnonzero(shared[first:last])
                    seen = np.zeros((last - first + 1, len(item.grams)), np.int32)
                    seen[where + 1, own[first:last][where]] = 1
                    np.cumsum(seen, axis=0, out=seen)
                    there = seen[c - first + span] - seen[c - first]
                    k = a + int(np.searchsorted(some, c[0]))
                    both[k : k + len(c)] = np.minimum(there, item.counts) @ item.weights
        return (both / (item.total + whole - both)).round(10)

    def search(self, words: int, grams: np.ndarray, least: float) -> dict[int, tuple[float, int]]:
        """For each item found in a document of these shingles: the best similarity and its window's first word."""
        out: dict[int, tuple[float, int]] = {}
        at, k = self.known_places(grams)
        if not len(at):
            return out
        weights = looked_up(self.common, self.common_weight, grams, self.rare)
        touched: dict[int, list[int]] = {}  # size to positions of shared shingles
        for p, s in zip(at.tolist(), k.tolist()):
            for length in self.sizes[s].tolist():
                touched.setdefault(length, []).append(p)
        for length, found in touched.items():
            span = max(1, min(length, words) - WIDTH + 1)  # shingles of a window
            last = len(grams) - span
            # starts of the windows that hold one of these shingles
            mark = np.zeros(last + 2, np.int64)
            p = np.array(found)
            np.add.at(mark, np.clip(p - span + 1, 0, last), 1)
            np.add.at(mark, np.minimum(p, last) + 1, -1)
            starts = np.flatnonzero(np.cumsum(mark[:-1]) > 0)
            table = self.blocks[length]
            for group in np.split(starts, np.flatnonzero(np.diff(starts) > span) + 1):
                for a in range(0, len(group), 4096):
                    part = group[a : a + 4096]
                    prints = self.fingerprints(grams, weights, part, span)
                    w, i = table.near(prints)
                    order = np.lexsort((w, i))
                    for one in np.split(order, np.flatnonzero(np.diff(i[order])) + 1):
                        if not len(one):
                            continue
                        item, where = int(table.items[i[one[0]]]), part[w[one]]
                        got = self.similarities(self.items[item], grams, weights, where, span)
                        best = int(got.argmax())
                        if got[best] >= least - 1e-9 and got[best] > out.get(item, (0.0, 0))[0] + 1e-12:
                            out[item] = float(got[best]), int(where[best])
        return out

    @staticmethod
    def fingerprints(grams: np.ndarray, weights: np.ndarray, starts: np.ndarray, span: int) -> np.ndarray:
        """SimHash of the windows that begin at these places, in order."""
        low, high = int(starts[0]), int(starts[-1]) + span
        out = np.zeros(len(starts), np.uint64)
        sums = np.zeros((high - low + 1, 64))
        np.cumsum(signs(grams[low:high], weights[low:high]), axis=0, out=sums[1:])
        out[:] = packed(np.round(sums[starts - low + span] - sums[starts - low], 9))
        return out


def whole_counts(items: DataFrame) -> tuple[int, np.ndarray, np.ndarray]:
    """Number of items with words; the shingles that two or more have, sorted; how many have each."""

    def run(texts):
        return {"v": [np.unique(g).view(np.int64).tolist() for _, g in shingled(texts)]}

    grams = written(items.select(struct_udf(run, "v array<bigint>")(F.col("text"))["v"].alias("v")), "item-shingles")
    shared = grams.select(F.explode("v").alias("s")).groupBy("s").agg(F.count(F.lit(1)).cast("int").alias("n")).where("n > 1").toArrow()
    keys, counts = shared["s"].to_numpy().view(np.uint64), shared["n"].to_numpy()
    order = np.argsort(keys)
    return grams.where(F.size("v") > 0).count(), keys[order], counts[order]


FOUND = "found array<struct<item_id:bigint,similarity:double,first_word:int>>"


def search(df: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item: str = "text", least: float = LEAST, slice_words: int = 2_000_000, out: str = "found") -> DataFrame:
    """df with an array of (item_id, similarity, first_word), ordered by item, best window of each."""
    items = benchmark.select(F.col(item_id).cast("bigint").alias("id"), F.col(item).alias("text"))
    weight, number = items.agg(F.sum(F.length("text") / 6 + ITEM_WORDS), F.count("text")).first()
    slices = min(max(1, math.ceil((weight or 0) / slice_words)), max(1, number))
    if slices == 1:
        rows = items.orderBy("id", "text").collect()
        return df.withColumn(out, found_in(df, rows, None, least)(F.col(text)))
    items = written(items.withColumn("slice", F.pmod(F.xxhash64("id", "text"), F.lit(slices))), "items")
    corpus = whole_counts(items)
    kept = written(with_row_key(df, "__row"), "rows")
    tables = []
    for s in sorted(r["slice"] for r in items.select("slice").distinct().collect()):
        rows = items.where(F.col("slice") == s).orderBy("id", "text").collect()
        one = kept.select("__row", found_in(df, rows, corpus, least)(F.col(text)).alias("__v")).where(F.size("__v") > 0)
        tables.append(written(one, "slice"))
    union = tables[0]
    for t in tables[1:]:
        union = union.unionByName(t)
    # at most one row for each slice and document
    whole = union.groupBy("__row").agg(F.array_sort(F.flatten(F.collect_list("__v"))).alias("__found"))
    told = kept.join(whole, "__row", "left")
    empty = F.array().cast(FOUND.split(" ", 1)[1])
    return told.withColumn(out, F.coalesce("__found", empty)).drop("__row", "__found")


def found_in(df: DataFrame, rows: list, corpus: tuple[int, np.ndarray, np.ndarray] | None, least: float):
    """A function of a text that searches it for these rows (id, text) of the benchmark."""
    sent = df.sparkSession.sparkContext.broadcast(Index.of([r["id"] for r in rows], [r["text"] for r in rows], corpus))

    def run(texts):
        index, found = sent.value, []
        for n, grams in shingled(texts):
            got = index.search(n, grams, least) if n else {}
            found.append(sorted(({"item_id": index.ids[k], "similarity": round(v, 6), "first_word": w} for k, (v, w) in got.items()), key=lambda x: (x["item_id"] is None, x["item_id"] or 0, x["first_word"])))
        return {"v": found}

    made = struct_udf(run, FOUND.replace("found", "v", 1))
    return lambda c: made(c)["v"]
