"""Sketches as tables: built from streams of pairs, merged over space and time, asked for labels.

A sketch is at most s rows of the counter table with one sketch_id, and one row of metadata. Both come out of one pass, as `record` "counter" and "meta" rows of the
same schema, so that nothing is computed twice when the rows are written (`stored`); sketches read back from there cost a small scan. Counter rows repeat what answers need of the metadata
(entries, threshold, floor, evicted), so that an answer is one pass as well. A merge is one pass too: labels are united as they stream by, every task keeps the s largest of each group, and what
the tasks kept meets in `MEET` tasks a group and then in one, which holds 2 * s counters at a time.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from tallywalk.functions.registers import estimate_arrays
from tallywalk.operators.walk import CounterTable
from tallywalk.sources.pairs import with_hashes

COUNTER = "sketch_id string, record string, slot int, label_key string, offset double, registers binary, items array<string>, estimate double"
META = "entries bigint, threshold double, floor double, is_full boolean, evicted boolean, hits bigint, admissions bigint, min_scans bigint, rejected bigint"
SCHEMA = f"{COUNTER}, {META}"
COUNTER_NAMES = [c.split()[0] for c in COUNTER.split(", ")]
META_NAMES = [c.split()[0] for c in META.split(", ")]
TOLD = ("entries", "threshold", "floor", "evicted")  # of the metadata, repeated with each counter
ADDED = ("entries", "hits", "admissions", "min_scans", "rejected")  # of the metadata, summed by merges
MEET = 32  # tasks in which what the others kept of a group is cut again before the last one


@dataclass(frozen=True)
class Sketches:
    rows: DataFrame
    kind: str
    s: int
    m: int
    counter: str
    estimator: str
    hash_id: str

    @property
    def counters(self) -> DataFrame:
        return self.rows.where("record = 'counter'").select("sketch_id", "slot", "label_key", "offset", "registers", "items", "estimate")

    @property
    def meta(self) -> DataFrame:
        return self.rows.where("record = 'meta'").select("sketch_id", F.lit(self.kind).alias("kind"), F.lit(self.s).alias("s"), F.lit(self.m).alias("m"), F.lit(self.hash_id).alias("hash_id"), *META_NAMES)

    def stored(self, path: str, mode: str = "errorifexists") -> Sketches:
        """The same sketches, read from the store to which they are written now."""
        self.rows.write.mode(mode).parquet(path)
        return replace(self, rows=self.rows.sparkSession.read.schema(self.rows.schema).parquet(path))

    def facts(self) -> tuple[list, dict]:
        """The counters (label_key, offset, estimate) of all sketches, and threshold, floor, entries and evicted over them, on the driver: s rows a sketch, from one pass."""
        rows = self.rows.select("record", "label_key", "offset", "estimate", "entries", "threshold", "floor", "evicted").collect()
        meta = [r for r in rows if r["record"] == "meta"]
        least = lambda c: min((r[c] for r in meta), default=0.0)
        return [r for r in rows if r["record"] == "counter"], {"threshold": least("threshold"), "floor": least("floor"), "entries": sum(r["entries"] for r in meta), "evicted": any(r["evicted"] for r in meta)}

    def alike(self, other: Sketches) -> None:
        mine, its = ((x.kind, x.m, x.counter, x.hash_id) for x in (self, other))
        if mine != its:
            raise ValueError(f"sketches of different make can't be merged: {mine} and {its}")


def _arrow_schema(spark_schema) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(spark_schema)


def _rows(sketch_id: str, table: CounterTable, contents: bool = True) -> list[dict]:
    nothing, meta = dict.fromkeys([*COUNTER_NAMES, *META_NAMES]), table.meta()
    out = [nothing | {"sketch_id": sketch_id, "record": "counter"} | {c: meta[c] for c in TOLD} | c for c in table.counters(contents)]
    return [*out, nothing | {"sketch_id": sketch_id, "record": "meta"} | meta]


def _coded(column: pa.Array) -> pa.DictionaryArray:
    return column if isinstance(column, pa.DictionaryArray) else column.dictionary_encode()


def _blocks(rows: DataFrame, order: list[str]) -> DataFrame:
    """All rows in their order, in one partition. Ranges of the order are sorted and packed by many tasks, a block for each of their Arrow batches, so that the last task, which has to
    take the stream entry by entry, has only the blocks to sort."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, n = TaskContext.get().partitionId(), 0  # ranges come in the order of their partitions
        for batch in batches:
            columns = [_coded(c) if pa.types.is_string(c.type) or pa.types.is_large_string(c.type) else c for c in batch.columns]
            block, sink = pa.RecordBatch.from_arrays(columns, names=batch.schema.names), pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, block.schema, options=pa.ipc.IpcWriteOptions(compression="lz4")) as writer:
                writer.write_batch(block)
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([n], pa.int32()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["part", "n", "block"])
            n += 1

    ranges = rows.repartitionByRange(*order).sortWithinPartitions(*order).drop(*order)
    return ranges.mapInArrow(pack, "part int, n int, block binary").repartition(1).sortWithinPartitions("part", "n").select("block")


def _unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for block in batch.column(0):
            with pa.ipc.open_stream(block.as_buffer()) as reader:
                yield from reader


def _key(name: str) -> list[Column]:
    """A key as a number where that is written just like it, else as text; the other of the two is null."""
    number = F.col(name).try_cast("bigint")
    number = F.when(number.cast("string") == F.col(name), number)
    return [number.alias(f"{name}_number"), F.when(number.isNull(), F.col(name)).alias(f"{name}_text")]


def _keys(numbers: pa.Array, texts: pa.Array) -> list:
    """Numbers, and strings where there are none."""
    if not numbers.null_count:
        return numbers.to_numpy().tolist()
    return [t if n is None else n for n, t in zip(numbers.to_pylist(), texts.to_pylist())]


def build_sketch(
    pairs: DataFrame,
    kind: str = "gated",
    s: int = 1000,
    m: int = 1024,
    counter: str = "registers",
    estimator: str = "histogram",
    streams: str | int = "as_is",
    min_search: str = "heap",
    hash: str = "fast",
    gate_on: str = "item",
    seed: int = 0,
    contents: bool = True,
) -> Sketches:
    """One sketch for each stream.

    streams: "as_is", the input's partitions, without a shuffle of data (their number is the number of sketches: set spark.sql.files.maxPartitionBytes to
    gigabytes at large scale); "by_source", the values of the column source; "by_label", labels dealt to the shuffle's partitions, which loses nothing
    when merged; or a number, in blocks of the order (whose bounds Spark samples for each
    run: `stored` fixes a result that is used more than once). If the pairs have `ord`, each stream is walked in that order.
    contents=False: without what the counters hold (registers, items), for answers that need the values alone; such sketches can't be merged."""
    CounterTable(kind=kind, s=s, m=m, counter=counter, min_search=min_search)  # checks the arguments
    exact = counter == "exact"
    hashed = with_hashes(pairs, m, hash, gate_on, seed)
    by_key = exact and not kind.startswith("gated")
    if not kind.startswith("gated"):
        hashed = hashed.withColumn("draw", F.lit(1.0))  # which these walks don't look at
    id_col = F.coalesce("source", F.lit("")) if streams == "by_source" else F.lit(None).cast("string")
    what = [*_key("label_key"), *_key("item_key")] if by_key else ["label_key", "draw", *(["item_key"] if exact else ["bucket", "rank"])]
    # the order's fields as columns of their own: rows stay small, and Spark sorts by the first one's bits
    by = {}
    if "ord" in pairs.columns:
        kind_of = pairs.schema["ord"].dataType
        by = {f"__ord{i}": F.col("ord").getField(f) for i, f in enumerate(kind_of.fieldNames())} if isinstance(kind_of, StructType) else {"__ord0": F.col("ord")}
    order = list(by)
    slim = hashed.select(id_col.alias("sketch_id"), *what, *(c.alias(n) for n, c in by.items()))
    packed = False
    if streams == "by_source":
        slim, order = slim.repartition("sketch_id"), ["sketch_id", *order]
    elif streams == "by_label":
        slim = slim.repartition(*(["label_key_number", "label_key_text"] if by_key else ["label_key"]))
    elif isinstance(streams, int):
        packed = streams == 1 and bool(order)
        if packed:
            slim = _blocks(slim, order)
        elif streams == 1:
            slim = slim.repartition(1)
        elif order:
            slim = slim.repartitionByRange(streams, *order)
        else:
            slim = slim.repartition(streams)
    elif streams != "as_is":
        raise ValueError("streams must be as_is, by_source, by_label or a number")
    if order and not packed:
        slim = slim.sortWithinPartitions(*order)
    slim = slim.drop(*by)

    schema = _arrow_schema(pairs.sparkSession.createDataFrame([], SCHEMA).schema)

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = f"{TaskContext.get().partitionId():08d}"
        table, now, held = None, None, {}

        def closed() -> pa.RecordBatch:
            return pa.RecordBatch.from_pylist(_rows(part if now is None else now, table, contents), schema=schema)

        for batch in _unpacked(batches) if packed else batches:
            if not batch.num_rows:
                continue
            ids = batch.column(0).fill_null("") if streams == "by_source" else None
            cuts = [0, batch.num_rows]
            if ids is not None:
                runs = pa.compute.run_end_encode(ids)
                cuts = [0, *runs.run_ends.to_pylist()]
            for a, b in zip(cuts, cuts[1:]):
                name = ids[a].as_py() if ids is not None else None
                if table is None or name != now:
                    if table is not None:
                        yield closed()
                    table, now = CounterTable(kind=kind, s=s, m=m, counter=counter, estimator=estimator, min_search=min_search), name
                some = batch.slice(a, b - a)
                if by_key:
                    table.consume_keys(_keys(*some.columns[1:3]), _keys(*some.columns[3:5]))
                    continue
                coded = _coded(some.column(1))
                draws = some.column(2).to_numpy()
                if exact:
                    items = _coded(some.column(3))
                    # one string for an item, however many counters hold it
                    known = [held.setdefault(x, x) for x in items.dictionary.to_pylist()]
                    values, rank = np.array(known, dtype=object)[items.indices.to_numpy()], None
                else:
                    values, rank = some.column(3).to_numpy().astype(np.int64), some.column(4).to_numpy().astype(np.uint8)
                table.consume(coded.dictionary.to_pylist(), coded.indices.to_numpy(), values, rank, draws)
        if table is not None:
            yield closed()

    return Sketches(slim.mapInArrow(walk, SCHEMA), kind, s, m, counter, estimator, f"{hash}:{gate_on}:{seed}")


class Best:
    """The s largest of the labels of one group so far, in any order, from at most 2 * s that are held."""

    def __init__(self, s: int):
        self.s, self.rows, self.meta = s, [], None

    def add(self, row: dict) -> None:
        self.rows.append(row)
        if len(self.rows) >= 2 * self.s:
            self.cut()

    def cut(self) -> None:
        # where floors count, each label is to gain those of all sketches less those that hold it: the former are the same for all
        self.rows.sort(key=lambda r: (r["floor"] - r["estimate"], r["label_key"]))
        del self.rows[self.s :]

    def tell(self, row: dict) -> None:
        """Metadata of one of the group's sketches, or of several."""
        if self.meta is None:
            self.meta = dict(row)
            return
        for c in (*ADDED, "floor"):
            self.meta[c] += row[c]
        self.meta["evicted"] |= row["evicted"]


def _by_group(rows: DataFrame, sk: Sketches, take, done) -> DataFrame:
    """mapInArrow over rows of SCHEMA that come sorted by group: take(best, row) for every row, done(best) gives the rows of a group at its end."""
    schema, s = _arrow_schema(rows.sparkSession.createDataFrame([], SCHEMA).schema), sk.s

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best, now = None, None

        def closed() -> Iterator[pa.RecordBatch]:
            out = done(best, now)
            for a in range(0, len(out), 1024):
                yield pa.RecordBatch.from_pylist(out[a : a + 1024], schema=schema)

        for batch in batches:
            for row in batch.to_pylist():
                if best is None or row["sketch_id"] != now:
                    if best is not None:
                        yield from closed()
                    best, now = Best(s), row["sketch_id"]
                take(best, row)
        if best is not None:
            yield from closed()

    return rows.select(*COUNTER_NAMES, *META_NAMES).mapInArrow(run, SCHEMA)


def _flat(sk: Sketches, grp: Column, absent_offset: str) -> Sketches:
    """All sketches of a group made one. Runs of equal labels are united as they stream by, a register-wise maximum each."""
    exact, estimator, s, gated = sk.counter == "exact", sk.estimator, sk.s, sk.kind.startswith("gated")
    floors = absent_offset == "floor" and sk.kind == "offset"
    rows = sk.rows.withColumn("sketch_id", grp)
    # the metadata of a group comes together at one task, as do its counters of one label
    dealt = rows.repartition("sketch_id", "label_key").sortWithinPartitions("sketch_id", "label_key")

    def finish(best: Best) -> None:
        """The values of the labels that were united since the last time."""
        fresh = [r for r in best.rows if r["estimate"] is None]
        if fresh:
            got = [float(len(r["items"])) for r in fresh] if exact else estimate_arrays(np.stack([np.frombuffer(r["registers"], np.uint8) if isinstance(r["registers"], bytes) else r["registers"] for r in fresh]), estimator).tolist()
            for r, e in zip(fresh, got):
                r["estimate"] = e + r["offset"]

    def unite(best: Best, row: dict) -> None:
        if row["record"] == "meta":
            best.tell(row)
            return
        if not floors:
            row["floor"] = 0.0
        last = best.rows[-1] if best.rows else None
        if last is not None and last["label_key"] == row["label_key"] and last["estimate"] is None:
            last["offset"] += row["offset"]
            last["floor"] += row["floor"]
            if exact:
                last["items"] = last["items"] | set(row["items"])
            else:
                last["registers"] = np.maximum(last["registers"], np.frombuffer(row["registers"], np.uint8))
            return
        if len(best.rows) >= 2 * s:
            finish(best)
            best.cut()
        row["estimate"] = None
        if exact:
            row["items"] = set(row["items"])
        else:
            row["registers"] = np.frombuffer(row["registers"], np.uint8)
        best.rows.append(row)

    def united(best: Best, group: str) -> list[dict]:
        finish(best)
        best.cut()
        for r in best.rows:
            if exact:
                r["items"] = sorted(r["items"])
            else:
                r["registers"] = bytes(r["registers"])
        return best.rows + ([best.meta] if best.meta else [])

    def collect(best: Best, row: dict) -> None:
        best.tell(row) if row["record"] == "meta" else best.add(row)

    def passed(best: Best, group: str) -> list[dict]:
        best.cut()
        return best.rows + ([best.meta] if best.meta else [])

    def ended(best: Best, group: str) -> list[dict]:
        best.cut()
        meta = best.meta or dict.fromkeys([*COUNTER_NAMES, *META_NAMES]) | dict.fromkeys(ADDED, 0) | {"sketch_id": group, "record": "meta", "evicted": False, "floor": 0.0}
        if floors:
            for r in best.rows:
                more = meta["floor"] - r["floor"]
                r["offset"], r["estimate"] = r["offset"] + more, r["estimate"] + more
        # a merged floor gates later entries only if the table is full; a merge may cut labels off as well
        full = len(best.rows) >= s
        least = min(r["estimate"] for r in best.rows) if full else 0.0
        meta = meta | {"threshold": least if gated else 0.0, "floor": least, "is_full": full, "evicted": meta["evicted"] or full}
        told = {c: meta[c] for c in TOLD}
        return [r | told | {"slot": i} for i, r in enumerate(best.rows)] + [meta]

    kept = _by_group(dealt, sk, unite, united)
    if int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")) > 2 * MEET:
        some = F.pmod(F.xxhash64("label_key"), F.lit(MEET))
        kept = _by_group(kept.repartition("sketch_id", some).sortWithinPartitions("sketch_id"), sk, collect, passed)
    whole = kept.repartition("sketch_id").sortWithinPartitions("sketch_id")
    return replace(sk, rows=_by_group(whole, sk, collect, ended))


def merge_sketches(sk: Sketches, by: Column | str | None = None, mode: str = "flat", fan_in: int = 64, absent_offset: str = "none", store: str | None = None) -> Sketches:
    """All sketches of a group (by: an expression over sketch_id; none: all) made one.

    flat: all counters of a label at once, then the s largest. tree: the pairwise rule repeated, fan_in sketches at a time in the order of their ids, cut to s after each
    round; it loses more. With a store (a path), every round is written there, which ends its lineage."""
    by = F.lit("all") if by is None else F.col(by) if isinstance(by, str) else by
    if mode == "flat":
        return _flat(sk, F.coalesce(by.cast("string"), F.lit("")), absent_offset)
    if mode != "tree" or fan_in < 2:
        raise ValueError("mode must be flat or tree, and fan_in at least 2")
    # numbers of the streams: a sort of ids, one for each sketch
    numbers = sk.rows.where("record = 'meta'").select(by.cast("string").alias("top"), "sketch_id").withColumn("k", F.row_number().over(Window.partitionBy("top").orderBy("sketch_id")) - 1)
    most = numbers.agg(F.max("k")).first()[0] or 0
    now = replace(sk, rows=sk.rows.join(numbers, "sketch_id").withColumn("sketch_id", F.concat_ws("/", "top", "k")).select(*sk.rows.columns))
    rounds = 0
    while most > 0:
        head, number = F.regexp_extract("sketch_id", r"^(.*)/\d+$", 1), F.substring_index("sketch_id", "/", -1).cast("bigint")
        now = _flat(now, F.concat_ws("/", head, F.floor(number / fan_in).cast("string")), absent_offset)
        if store:
            now = now.stored(f"{store}/round{rounds}")
        most, rounds = most // fan_in, rounds + 1
    return replace(now, rows=now.rows.withColumn("sketch_id", F.regexp_extract("sketch_id", r"^(.*)/\d+$", 1)))


def merge_pair(a: Sketches, b: Sketches, absent_offset: str = "none") -> Sketches:
    a.alike(b)
    both = a.rows.withColumn("sketch_id", F.concat(F.lit("a"), "sketch_id")).unionByName(b.rows.withColumn("sketch_id", F.concat(F.lit("b"), "sketch_id")))
    return _flat(replace(a, rows=both, s=max(a.s, b.s)), F.lit("all"), absent_offset)


def roll_up(sk: Sketches, every: str = "1 day", slide: str | None = None) -> Sketches:
    """Sketches of panes (sketch_id: the pane's start, yyyy-MM-dd HH:mm:ss) merged to longer spans; with slide, to spans that overlap."""
    start = F.to_timestamp("sketch_id", "yyyy-MM-dd HH:mm:ss")
    span = F.window(start, every, slide) if slide else F.window(start, every)
    rows = sk.rows.withColumn("span", span).withColumn("grp", F.date_format("span.start", "yyyy-MM-dd HH:mm:ss"))
    return _flat(replace(sk, rows=rows.drop("span")), F.col("grp"), "none")


# ---- answers


def _ranked(answer: DataFrame) -> DataFrame:
    by = ["sketch_id"] if "sketch_id" in answer.columns else []
    return answer.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("estimate"), "label_key")))


def top_k(sk: Sketches, k: int, per_sketch: bool = False) -> DataFrame:
    """label_key, estimate, rank of the k largest, from the sketch alone."""
    if per_sketch:
        return _ranked(sk.counters.select("sketch_id", "label_key", "estimate")).where(F.col("rank") <= k)
    best = sk.counters.select("label_key", "estimate").orderBy(F.desc("estimate"), "label_key").limit(k)
    return _ranked(best)


def reached(sk: Sketches, threshold: float | None = None, fraction: float | None = None) -> DataFrame:
    """Every label of the sketches, and whether it is `reported`: of at least a value, or of at least a fraction of all entries."""
    counters = sk.rows.where("record = 'counter'")
    if threshold is None and fraction is None:
        raise ValueError("a threshold or a fraction is needed")
    least = F.lit(threshold) if threshold is not None else F.col("entries") * fraction
    return counters.select("sketch_id", "label_key", "estimate", (F.col("estimate") >= least).alias("reported"))


def over(sk: Sketches, threshold: float | None = None, fraction: float | None = None) -> DataFrame:
    """Labels of at least a value, or of at least a fraction of all entries."""
    return reached(sk, threshold, fraction).where("reported").drop("reported")


def estimate(sk: Sketches, labels: DataFrame, absent: str = "min", label: str = "label_key") -> DataFrame:
    """The labels with their estimates from one sketch. absent: what a label without a counter gets: "min", the smallest value (0 if the sketch has never dropped
    a label); "literal", the smallest count without its offset; "zero"; "null". The sketch's s labels come to the driver now, and go out with the plan."""
    counters, facts = sk.facts()
    least = {"min": lambda r: r["estimate"], "literal": lambda r: r["estimate"] - r["offset"]}
    other = None if absent == "null" else 0.0
    if absent in least and facts["evicted"]:
        other = min(map(least[absent], counters), default=0.0)
    elif absent not in (*least, "zero", "null"):
        raise ValueError("absent must be min, literal, zero or null")
    known = labels.sparkSession.createDataFrame([(r["label_key"], r["estimate"]) for r in counters], "label_key string, estimate double")
    # at most s rows
    wanted = labels.select(F.col(label).alias("label_key")).join(F.broadcast(known), "label_key", "left")
    return wanted.select("label_key", F.col("estimate").isNotNull().alias("member"), F.coalesce("estimate", F.lit(other).cast("double")).alias("estimate"))


def recount(answer: DataFrame, pairs: DataFrame) -> DataFrame:
    """The answer with the exact sizes of its labels, by a second pass over the pairs of these labels alone."""
    sizes = pairs.join(F.broadcast(answer.select("label_key")), "label_key", "left_semi").groupBy("label_key").agg(F.count_distinct("item_key").alias("d"))
    return answer.join(sizes, "label_key", "left")
