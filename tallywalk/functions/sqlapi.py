"""The walk and the registers for SQL users: a table function and two aggregates.

    register(spark)
    SELECT label, sum(estimate) FROM heavy_labels(TABLE(SELECT shard, label, item, ord FROM t) PARTITION BY (shard) ORDER BY (ord), 100, 1000, 256, 'gated') GROUP BY label

`heavy_labels` walks each partition of its table argument in the given order and returns the k largest labels of its sketch; columns are found by the names label and
item. `merge_registers` is the register-wise maximum of BINARY registers, `estimate_registers` their distinct count.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from tallywalk.functions.hashing import HASH_BITS, LOW_BITS
from tallywalk.functions.registers import estimate_registers


def hashes_of(texts: list[str], tag: str) -> np.ndarray:
    """52-bit hashes by the rules of the plans, from a 64-bit hash with a seed of its own: registers made of them can't be merged with those of the plans."""
    return (np.fromiter((xxhash.xxh64_intdigest(f"{tag}|{x}") for x in texts), np.uint64, len(texts)) >> np.uint64(12)).astype(np.int64)


def registers_of(texts: list[str], m: int) -> tuple[np.ndarray, np.ndarray]:
    """Buckets and ranks of items, any m."""
    h = hashes_of(texts, "c")
    digits = lambda w: np.frexp(w.astype(np.float64))[1]  # noqa: E731  below 2**53: exact
    if m & (m - 1) == 0:
        rest = HASH_BITS - (m.bit_length() - 1)
        return h >> rest, (rest + 1 - digits(h & ((1 << rest) - 1))).astype(np.uint8)
    return (h & ((1 << LOW_BITS) - 1)) % m, (HASH_BITS - LOW_BITS + 1 - digits(h >> LOW_BITS)).astype(np.uint8)


def register_of(text: str, m: int) -> tuple[int, int]:
    """Bucket and rank of one item."""
    bucket, rank = registers_of([text], m)
    return int(bucket[0]), int(rank[0])


def draws_of(texts: list[str]) -> np.ndarray:
    return math.ldexp(1.0, HASH_BITS) / (hashes_of(texts, "g") + 0.5)


def _texts(column: pa.DictionaryArray) -> list[str]:
    known = column.dictionary.to_pylist()
    if pa.types.is_timestamp(column.type.value_type):  # as in rows, without a zone
        known = [x.replace(tzinfo=None) for x in known]
    return [str(x) for x in known]


class HeavyLabels:
    """Rows come in Arrow batches of one partition each, in its order. What the items' hashes say is remembered for REMEMBERED items."""

    REMEMBERED = 1 << 17

    def __init__(self) -> None:
        self.table, self.k, self.place, self.facts = None, 0, {}, None

    def eval(self, batch: pa.RecordBatch, k: pa.Array, s: pa.Array, m: pa.Array, kind: pa.Array):
        from tallywalk.operators.walk import CounterTable

        if not batch.num_rows:
            return
        if self.table is None:
            self.table, self.k = CounterTable(kind=kind[0].as_py(), s=s[0].as_py(), m=m[0].as_py()), k[0].as_py()
        label, item = batch.column("label"), batch.column("item")
        given = pc.and_(label.is_valid(), item.is_valid())
        labels, items = (c.filter(given).dictionary_encode() for c in (label, item))
        if len(items):
            where = self._hashed(_texts(items))[items.indices.to_numpy()]
            self.table.consume(_texts(labels), labels.indices.to_numpy(), *(f[where] for f in self.facts))

    def _hashed(self, items: list[str]) -> np.ndarray:
        """Where the facts of different items are: bucket, rank and draw."""
        new = [x for x in items if x not in self.place]
        if self.facts is None or len(self.place) + len(new) > self.REMEMBERED:
            self.place, self.facts, new = {}, None, items
        if new:
            self.place.update(zip(new, range(len(self.place), len(self.place) + len(new))))
            made = (*registers_of(new, self.table.m), draws_of(new))
            self.facts = made if self.facts is None else tuple(map(np.concatenate, zip(self.facts, made)))
        return np.array([self.place[x] for x in items])

    def terminate(self):
        if self.table is None:
            return
        best = sorted(self.table.counters(), key=lambda c: (-c["estimate"], c["label_key"]))[: self.k]
        if best:
            yield pa.RecordBatch.from_pydict({"label": [c["label_key"] for c in best], "estimate": [c["estimate"] for c in best], "rank": pa.array(range(1, len(best) + 1), pa.int32())})


def merge_registers(column: pa.Array) -> bytes | None:
    rows = [x for x in column.to_pylist() if x is not None]
    return np.maximum.reduce([np.frombuffer(x, np.uint8) for x in rows]).tobytes() if rows else None


def register(spark: SparkSession) -> None:
    spark.udtf.register("heavy_labels", F.arrow_udtf(HeavyLabels, returnType="label string, estimate double, rank int"))
    spark.udf.register("estimate_registers", estimate_registers())
    spark.udf.register("merge_registers", merge_registers_udf())


def merge_registers_udf():
    """A grouped Arrow aggregate: convenient for few rows a group. Python aggregates have no partial step, so merge_sketches is the way for many."""
    def typed(column: pa.Array) -> bytes:
        return merge_registers(column)

    typed.__annotations__ = {}
    return F.arrow_udf(typed, "binary", functionType=F.ArrowUDFType.GROUPED_AGG)
