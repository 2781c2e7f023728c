"""Panes: a sketch for each span of event time, kept in a store and merged to longer spans on demand."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery, StreamingQueryListener

from tallywalk.operators.sketches import SCHEMA, Sketches, build_sketch, merge_sketches
from tallywalk.sources.pairs import pairs as make_pairs

STAMP = "yyyy-MM-dd HH:mm:ss"


def pane_of(ts: str = "ts", every: str = "1 hour"):
    return F.date_format(F.window(ts, every).start, STAMP)


def pane_sketches(pairs: DataFrame, every: str = "1 hour", **options) -> Sketches:
    """One sketch for each pane of a batch of pairs with `ts`; sketch_id is the pane's start."""
    return build_sketch(pairs.withColumn("source", pane_of("ts", every)), streams="by_source", **options)


def pane_sizes(pairs: DataFrame, every: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Exact sizes in tumbling or sliding windows."""
    span = F.window("ts", every, slide) if slide else F.window("ts", every)
    distinct = pairs.select(span.alias("w"), "label_key", "item_key").distinct()
    return distinct.groupBy(F.date_format("w.start", STAMP).alias("pane"), "label_key").agg(F.count(F.lit(1)).alias("d"))


def session_sizes(pairs: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Entries and distinct items of each label's sessions."""
    return pairs.groupBy(F.session_window("ts", gap).alias("w"), "label_key").agg(F.count(F.lit(1)).alias("entries"), F.count_distinct("item_key").alias("d")).select("label_key", F.date_format("w.start", STAMP).alias("start"), "entries", "d")


def latest_pane(reports: DataFrame, panes: DataFrame, at: str = "at", pane: str = "pane") -> DataFrame:
    """As-of: each report time with the last pane that starts at or before it. Panes are few, one a span."""
    distinct = panes.select(F.col(pane).alias("__p")).distinct()
    return reports.join(F.broadcast(distinct), F.to_timestamp("__p", STAMP) <= F.col(at), "left").groupBy(*reports.columns).agg(F.max("__p").alias(pane))


def event_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """Event files as a stream, oldest first, with `ts` as a timestamp that can carry a watermark."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_pairs(rows: DataFrame, label, item) -> DataFrame:
    return make_pairs(rows, label, item, ts="ts")


def stream_sizes(pairs: DataFrame, every: str = "1 hour", watermark: str = "1 hour") -> DataFrame:
    """Exact panes as a stream: distinct pairs of a pane within the watermark, then counts. Late rows for closed panes are dropped."""
    marked = pairs.withWatermark("ts", watermark).select(F.window("ts", every).alias("w"), "label_key", "item_key")
    distinct = marked.dropDuplicates(["w", "label_key", "item_key"])
    return distinct.groupBy("w", "label_key").agg(F.count(F.lit(1)).alias("d")).select(F.date_format("w.start", STAMP).alias("pane"), "label_key", "d")


class LateRows(StreamingQueryListener):
    """Counts the rows that came after their pane was closed and were dropped, by query id: `spark.streams.addListener(LateRows())`. What a query's progress tells, summed over all of its batches."""

    def __init__(self) -> None:
        self.dropped: dict[str, int] = {}

    def onQueryStarted(self, event) -> None:
        self.dropped.setdefault(str(event.id), 0)

    def onQueryProgress(self, event) -> None:
        late = sum(max(0, o.numRowsDroppedByWatermark) for o in event.progress.stateOperators)
        self.dropped[str(event.progress.id)] = self.dropped.get(str(event.progress.id), 0) + late

    def onQueryIdle(self, event) -> None:
        pass

    def onQueryTerminated(self, event) -> None:
        pass


def late_rows(query: StreamingQuery) -> int:
    """The same from the progress that a query still remembers (its last 100 batches, unless set otherwise)."""
    return sum(max(0, o.numRowsDroppedByWatermark) for p in query.recentProgress for o in p.stateOperators)


def stream_sketches(pairs: DataFrame, store: str, checkpoint: str, every: str = "1 hour", **options) -> StreamingQuery:
    """Every micro-batch is sketched by pane and put into the store under its number, so a batch that runs again overwrites itself. `read_store` merges what it asks for."""

    def keep(batch: DataFrame, number: int) -> None:
        pane_sketches(batch, every, **options).stored(f"{store}/batch={number}", mode="overwrite")

    return pairs.writeStream.foreachBatch(keep).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def read_store(spark: SparkSession, store: str, like: Sketches) -> Sketches:
    """One sketch a pane: the micro-batches' sketches of it merged."""
    from dataclasses import replace

    rows = spark.read.schema(SCHEMA).parquet(f"{store}/batch=*")
    # a micro-batch may hold several sketches of one pane: each is a stream of its own
    numbered = rows.withColumn("__file", F.input_file_name()).withColumn("pane", F.col("sketch_id")).withColumn("sketch_id", F.concat_ws("@", "sketch_id", F.md5("__file"))).drop("__file")
    return merge_sketches(replace(like, rows=numbered), by="pane")


def stateful_sketches(pairs: DataFrame, shards: int, **options) -> DataFrame:
    """A walk across micro-batches: each shard of labels keeps one bounded table in the state store and emits it after every batch."""
    import pickle

    import numpy as np
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    from tallywalk.operators.walk import CounterTable
    from tallywalk.sources.pairs import with_hashes

    m = options.get("m", 1024)
    hashed = with_hashes(pairs, m).withColumn("shard", F.pmod(F.xxhash64("label_key"), F.lit(shards)))

    def step(key, frames, state: GroupState):
        table = pickle.loads(state.get[0]) if state.exists else CounterTable(**options)
        for f in frames:
            labels, codes = np.unique(f["label_key"].to_numpy(dtype=object).astype(str), return_inverse=True)
            table.consume(labels.tolist(), codes, f["bucket"].to_numpy(np.int64), f["rank"].to_numpy(np.uint8), f["draw"].to_numpy(float))
        state.update((pickle.dumps(table),))
        yield pd.DataFrame([{"shard": key[0], "label_key": c["label_key"], "estimate": c["estimate"]} for c in table.counters()])

    return hashed.select("shard", "label_key", "bucket", "rank", "draw").groupBy("shard").applyInPandasWithState(step, "shard bigint, label_key string, estimate double", "table binary", "update", GroupStateTimeout.NoTimeout)


def ranks(panes: DataFrame, k: int) -> DataFrame:
    """The k largest labels of every pane."""
    best = Window.partitionBy("pane").orderBy(F.desc("d"), "label_key")
    return panes.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)


def deduplicated(pairs: DataFrame, id: str, watermark: str = "1 hour") -> DataFrame:
    """For agents that deliver at least once: a row's id counts once within the watermark."""
    return pairs.withWatermark("ts", watermark).dropDuplicatesWithinWatermark([id])


def within(left: DataFrame, right: DataFrame, key: str, span: str = "10 minutes", watermark: str = "1 hour") -> DataFrame:
    """Interval join of two streams (or tables): rows of one key where the right one's ts follows the left one's within the span."""
    a = left.withWatermark("ts", watermark).alias("a")
    b = right.withWatermark("ts", watermark).alias("b")
    return a.join(b, (F.col(f"a.{key}") == F.col(f"b.{key}")) & (F.col("b.ts") >= F.col("a.ts")) & (F.col("b.ts") < F.col("a.ts") + F.expr(f"interval {span}")))
