"""Pairs (label, item) from tables: two projected columns, the stream's order, and its source."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tallywalk.functions.hashing import bucket_and_rank, canonical, draw, hash52


def pairs(df: DataFrame, label: str | Column, item: str | Column, order_by: list[str] | None = None, source: str | Column | None = None, ts: str | Column | None = None, keep_null_label: bool = False) -> DataFrame:
    """label_key and item_key (canonical strings), ord (a struct, if order_by), source and ts as asked for.

    Pairs without an item count nothing and are left out; so are those without a label, unless keep_null_label gives them the label "\\0null"."""
    as_column = lambda c: F.col(c) if isinstance(c, str) else c
    typed = df.select(as_column(label).alias("l"), as_column(item).alias("i"))
    lab, it = canonical(as_column(label), typed.schema["l"].dataType), canonical(as_column(item), typed.schema["i"].dataType)
    if keep_null_label:
        lab = F.coalesce(lab, F.lit("\0null"))
    out = [lab.alias("label_key"), it.alias("item_key")]
    if order_by:
        out.append(F.struct(*order_by).alias("ord"))
    if source is not None:
        out.append(as_column(source).cast("string").alias("source"))
    if ts is not None:
        out.append(as_column(ts).cast("timestamp").alias("ts"))
    return df.select(*out).where(F.col("label_key").isNotNull() & F.col("item_key").isNotNull())


def insert_only(rows: DataFrame, change: str = "_change_type", inserts: tuple[str, ...] = ("insert",)) -> DataFrame:
    """Rows of a change feed without its column `change`. A row that is no insert stops the query with an error: no counter here can give an item back. No change (null) is an insert."""
    kind = F.coalesce(F.col(change).cast("string"), F.lit(inserts[0]))
    refused = F.raise_error(F.concat(F.lit("only inserted rows can be counted, found: "), kind)).cast("boolean")
    return rows.where(F.when(kind.isin(*inserts), True).otherwise(refused)).drop(change)


def word_pairs(docs: DataFrame, text: str = "text", id: str = "doc_id", role: str = "word_label", source: str | None = None, order_by: list[str] | None = None) -> DataFrame:
    """Words of texts (lower case, cut at single blanks) as labels of their documents, or the other way round. Ordered by document, then position."""
    keep = [id, *([source] if source else []), *(c for c in order_by or [] if c != id)]
    words = docs.select(*keep, F.posexplode(F.split(F.lower(text), " ")).alias("pos", "word"))
    label, item = ("word", id) if role == "word_label" else (id, "word")
    return pairs(words, label, item, order_by=[*(order_by or [id]), "pos"], source=source)


def read(spark: SparkSession, path: str, format: str = "parquet", **options: str) -> DataFrame:
    """A table in any of Spark's file formats; columns are pruned by the select that follows."""
    return spark.read.format(format).options(**options).load(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def with_hashes(df: DataFrame, m: int = 1024, hash: str = "fast", gate_on: str = "item", seed: int = 0) -> DataFrame:
    """bucket and rank for the counters, and draw for the gate."""
    if gate_on not in ("item", "pair"):
        raise ValueError("gate_on must be item or pair")
    bucket, rank = bucket_and_rank(hash52(F.col("item_key"), "c", hash, seed), m)
    gate = F.col("item_key") if gate_on == "item" else F.concat_ws("\1", "label_key", "item_key")
    return df.withColumns({"bucket": bucket, "rank": rank, "draw": draw(hash52(gate, "g", hash, seed))})


# the experiments' data on the given tables


def doc_words(spark: SparkSession, d: str) -> DataFrame:
    """Which document has the most distinct words: few labels, a sharp head."""
    return word_pairs(table(spark, d, "documents"), role="doc_label", source="source")


def host_urls(spark: SparkSession, d: str) -> DataFrame:
    return pairs(table(spark, d, "pages"), F.split_part("url", F.lit("/"), F.lit(3)), "url", order_by=["page_id"])


def word_docs(spark: SparkSession, d: str) -> DataFrame:
    """Which word is in the most documents."""
    return word_pairs(table(spark, d, "documents"), role="word_label", source="source")


def word_conversations(spark: SparkSession, d: str) -> DataFrame:
    """Which word is in the most conversations: labels within an order of the entries."""
    return word_pairs(table(spark, d, "conversations"), id="conv_id", role="word_label", order_by=["conv_id", "turn"])


def _lines_with_orders(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_suppkey", "l_partkey")
    return lines.join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))


LINE_ORDER = ["l_orderkey", "l_linenumber", "l_suppkey", "l_partkey"]


def part_customers(spark: SparkSession, d: str) -> DataFrame:
    return pairs(_lines_with_orders(spark, d), "l_partkey", "o_custkey", order_by=LINE_ORDER)


def customer_parts(spark: SparkSession, d: str) -> DataFrame:
    """Which customer has bought the most distinct parts: a slow tail."""
    return pairs(_lines_with_orders(spark, d), "o_custkey", "l_partkey", order_by=LINE_ORDER)


def supplier_parts(spark: SparkSession, d: str) -> DataFrame:
    """Which supplier delivers the most distinct parts: sets that overlap."""
    return pairs(table(spark, d, "lineitem"), "l_suppkey", "l_partkey", order_by=LINE_ORDER)


def day_parts(spark: SparkSession, d: str) -> DataFrame:
    return pairs(table(spark, d, "lineitem").withColumn("day", F.to_date("l_shipdate")), "day", "l_partkey", order_by=LINE_ORDER)


def event_users(spark: SparkSession, d: str) -> DataFrame:
    return pairs(table(spark, d, "events"), "event_type", "user_id", order_by=["ts", "event_id"], ts="ts")


def event_key_users(spark: SparkSession, d: str) -> DataFrame:
    return pairs(table(spark, d, "events"), F.concat_ws(":", "event_type", F.get_json_object("props", "$.k")), "user_id", order_by=["ts", "event_id"], ts="ts")


WORKLOADS = {
    "doc_words": doc_words,
    "word_docs": word_docs,
    "word_conversations": word_conversations,
    "part_customers": part_customers,
    "customer_parts": customer_parts,
    "supplier_parts": supplier_parts,
    "day_parts": day_parts,
    "host_urls": host_urls,
    "event_users": event_users,
    "event_key_users": event_key_users,
}
