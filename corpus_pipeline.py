"""The corpus pipeline: language ID, near copies, benchmark passages, secrets, token ids.

Every stage takes (spark, docs, sf_dir), works on all that the stage before it kept, and gives the columns of documents; the last gives token counts and
digests. run() applies them to the table documents, each on the written result of the one before.
"""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallywalk.llm import bpe, decontaminate, jaccard, langid, secrets
from tallywalk.llm._frame import may_hold, trim_executors, with_row_key, written, written_alone
from tallywalk.llm.queries import vocabulary

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter go, and those in whose words the model knows nothing, not even a letter. It learns from the documents that name their language; if none does,
    all documents stay."""
    model = langid.fit(docs)
    if not model.languages:
        return docs.select(*COLUMNS)
    return langid.predict(docs, model, out="__language").where((F.col("__language.lang_pred") != "und") & (F.col("__language.evidence") > 0)).select(*COLUMNS)


def one_of_each_class(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The first document of each class of near copies stays."""
    trim_executors(spark)
    kept = written(with_row_key(docs, "__id"), "rows")
    others = written(jaccard.labelled(kept.select(F.col("__id").alias("key"), "text")).where(~F.col("first")).select(F.col("key").alias("__id")), "others")
    told = kept.withColumn("__maybe", may_hold(others, "__id")(F.col("__id")))
    some = told.where("__maybe").join(others, "__id", "left_anti")
    return told.where(~F.col("__maybe")).select(*COLUMNS).unionByName(some.select(*COLUMNS))


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a passage like a benchmark item go."""
    trim_executors(spark)
    found = decontaminate.search(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), out="__found")
    return found.where(F.size("__found") == 0).select(*COLUMNS)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Live secrets are replaced by a mark; examples that many owners copied stay."""
    trim_executors(spark)
    kept = written(with_row_key(docs, "__id"), "rows")
    spans = written(secrets.scan(kept, ["__id"]).where(F.exists("spans", lambda s: s["verdict"] == "live")).select("__id", "spans"), "spans")
    told = kept.withColumn("__maybe", may_hold(spans, "__id")(F.col("__id")))
    some = told.where("__maybe").join(spans, "__id", "left")
    changed = F.col("spans").isNotNull()
    cleaned = secrets.redact(some.withColumn("changed", changed), "text", "spans").withColumn("n_chars", F.when(F.col("changed"), F.length("text").cast("bigint")).otherwise(F.col("n_chars")))
    return told.where(~F.col("__maybe")).select(*COLUMNS).unionByName(cleaned.select(*COLUMNS))


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Number of tokens and digests of the ids and of the decoded text."""
    trim_executors(spark)
    return bpe.digest(docs, vocabulary(), ["doc_id", "source"])


STAGES = [
    ("language", known_language),
    ("near_copies", one_of_each_class),
    ("benchmark", without_benchmark),
    ("secrets", without_secrets),
    ("tokens", token_ids),
]

#: The stages learn models and verify candidates; SQL can't express them. tests/llm holds the brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select(*COLUMNS)
    for name, stage in STAGES[:-1]:
        docs = written_alone(partial(stage, spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
