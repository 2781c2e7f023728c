"""URL filter: host and path rules first, then gradient-boosted trees on lexical features. DataFrame and SQL functions only.

Features: lengths of url, host, path and query; path depth; labels of the host; digit, hyphen and non-letter shares; entropy of the
letters; parameters; a fragment; kinds of file ending; and for the host's last label how often training saw it blocked.

Training takes a bounded sample (most_rows) of the labelled urls, chosen by a hash of the url.

Defined results: a null url, or one without "://", has empty host and path, fits no rule, and gets the model's verdict on empty features.
With no labelled url, or labels of one kind alone, that kind (or "allow") is the verdict. Ties of rule length go to the rule given first.
Repeated rows get equal verdicts. Other columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass
from string import ascii_lowercase, ascii_uppercase

from pyspark.ml.classification import GBTClassificationModel, GBTClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tallywalk.llm._frame import unclashing, written

PARTS = r"(?s)^.*?://([^/?#]*)([^?#]*)(.*)$"


@dataclass(frozen=True)
class Rule:
    verdict: str
    host: str
    path: str

    @property
    def name(self) -> str:
        return self.host + self.path

    @classmethod
    def of(cls, verdict: str, name: str) -> Rule:
        host, slash, path = name.partition("/")
        return cls(verdict, host, slash + path)


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(url, PARTS, 1), ascii_uppercase, ascii_lowercase), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, PARTS, 2), F.lit(""))


def rest_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, PARTS, 3), F.lit(""))


def longest_rule(host: Column, path: Column, rules: list[Rule]) -> tuple[Column, Column]:
    """Name and verdict of the longest fitting rule, or null."""
    name = verdict = None
    for r in sorted(rules, key=lambda r: -len(r.name)):
        fits = ((host == r.host) | F.endswith(host, F.lit("." + r.host))) & F.startswith(path, F.lit(r.path))
        name = F.when(fits, r.name) if name is None else name.when(fits, r.name)
        verdict = F.when(fits, r.verdict) if verdict is None else verdict.when(fits, r.verdict)
    return (name, verdict) if rules else (F.lit(None).cast("string"), F.lit(None).cast("string"))


def share(part: Column, whole: Column) -> Column:
    return F.when(whole > 0, part / whole).otherwise(0.0)


def count_of(s: Column, pattern: str) -> Column:
    return F.length(s) - F.length(F.regexp_replace(s, pattern, ""))


def entropy(s: Column) -> Column:
    """Bits a letter, from the counts of the distinct letters."""
    n = F.length(s)
    counts = F.transform(F.array_distinct(F.split(s, "")), lambda c: n - F.length(F.replace(s, c, F.lit(""))))
    terms = F.transform(counts, lambda k: F.when(k > 0, -(k / n) * F.log2(k / n)).otherwise(0.0))
    return F.when(n > 0, F.aggregate(terms, F.lit(0.0), lambda a, b: a + b)).otherwise(0.0)


def features(df: DataFrame, url: str, suffix_rates: dict[str, float], base_rate: float) -> tuple[DataFrame, list[str]]:
    """df with a column for each feature; the suffix table is bounded by `fit`."""
    u = F.coalesce(F.col(url), F.lit(""))
    host, path, rest = host_of(F.col(url)), path_of(F.col(url)), rest_of(F.col(url))
    suffix = F.substring_index(host, ".", -1)
    rate = F.lit(base_rate)
    if suffix_rates:
        rate = F.coalesce(F.create_map(*(F.lit(x) for kv in sorted(suffix_rates.items()) for x in kv))[suffix], rate)
    ending = F.regexp_extract(path, r"\.([A-Za-z0-9]{1,5})$", 1)
    made = {
        "f_length": F.length(u),
        "f_host_length": F.length(host),
        "f_path_length": F.length(path),
        "f_query_length": F.length(rest),
        "f_depth": count_of(path, "/"),
        "f_labels": F.when(host == "", 0).otherwise(count_of(host, r"\.") + 1),
        "f_digits": share(count_of(u, "[0-9]"), F.length(u)),
        "f_host_digits": share(count_of(host, "[0-9]"), F.length(host)),
        "f_hyphens": count_of(host, "-"),
        "f_others": share(count_of(u, "[^A-Za-z0-9]"), F.length(u)),
        "f_entropy": entropy(u),
        "f_host_entropy": entropy(host),
        "f_parameters": F.when(F.startswith(rest, F.lit("?")), count_of(rest, "&") + 1).otherwise(0),
        "f_fragment": F.contains(rest, F.lit("#")),
        "f_secure": F.startswith(u, F.lit("https")),
        "f_ending": F.when(ending == "", 0).when(F.lower(ending).isin("html", "htm"), 1).otherwise(2),
        "f_suffix_length": F.length(suffix),
        "f_suffix_rate": rate,
    }
    return df.withColumns({k: v.cast("double") for k, v in made.items()}), list(made)


@dataclass
class UrlModel:
    trees: GBTClassificationModel | None
    default: str
    suffix_rates: dict[str, float]
    base_rate: float


def fit(df: DataFrame, url: str = "url", verdict: str = "verdict", most_rows: int = 20_000, most_suffixes: int = 200, rounds: int = 15, depth: int = 4) -> UrlModel:
    """Trees from urls labelled allow or block; other labels and null are left out."""
    labelled = df.where(F.col(verdict).isin("allow", "block")).select(F.coalesce(F.col(url), F.lit("")).alias("url"), (F.col(verdict) == "block").cast("double").alias("label"))
    n, blocked = labelled.agg(F.count(F.lit(1)), F.sum("label")).first()
    if not n or not blocked or blocked == n:
        return UrlModel(None, "block" if n and blocked == n else "allow", {}, 0.0)
    draw = F.pmod(F.xxhash64("url"), F.lit(1 << 20))
    sample = written(labelled.where(draw < int(min(1.0, most_rows / n) * (1 << 20))).repartition(8), "url-sample")
    suffix = F.substring_index(host_of(F.col("url")), ".", -1).alias("suffix")
    # the most frequent suffixes, smoothed towards the share of all
    base = blocked / n
    rows = sample.groupBy(suffix).agg(F.count(F.lit(1)).alias("n"), F.sum("label").alias("b")).orderBy(F.desc("n"), "suffix").limit(most_suffixes).collect()
    rates = {r["suffix"]: (r["b"] + 10 * base) / (r["n"] + 10) for r in rows}
    data, names = features(sample, "url", rates, base)
    vectors = VectorAssembler(inputCols=names, outputCol="features").transform(data).select("features", "label")
    kinds = vectors.agg(F.min("label"), F.max("label")).first()
    if kinds[0] == kinds[1]:  # the sample has one kind, or nothing
        return UrlModel(None, "block" if kinds[0] == 1.0 else "allow", rates, base)
    trees = GBTClassifier(maxIter=rounds, maxDepth=depth, seed=7, cacheNodeIds=False, checkpointInterval=-1).fit(vectors)
    return UrlModel(trees, "allow", rates, base)


def judge(df: DataFrame, rules: list[Rule], model: UrlModel, url: str = "url", keep: list[str] | None = None) -> DataFrame:
    """keep (or all columns of df), then host, path, rule, verdict, and p_block, the model's probability (null without trees). Kept columns of these names are replaced."""
    keep = unclashing(df.columns if keep is None else keep, "host", "path", "rule", "verdict", "p_block")
    names = [f"__k{i}" for i in range(len(keep))]
    slim = df.select(*(F.col(k).alias(n) for k, n in zip(keep, names)), F.col(url).alias("__url"))
    if model.trees is None:
        scored = slim.withColumn("__p", F.lit(None).cast("double"))
    else:
        data, fs = features(slim, "__url", model.suffix_rates, model.base_rate)
        scored = model.trees.transform(VectorAssembler(inputCols=fs, outputCol="features").transform(data)).withColumn("__p", vector_to_array("probability")[1])
    parsed = scored.select(*names, host_of(F.col("__url")).alias("__host"), path_of(F.col("__url")).alias("__path"), "__p")
    rule, verdict = longest_rule(F.col("__host"), F.col("__path"), rules)
    own = F.when(F.col("__p") > 0.5, "block").when(F.col("__p").isNotNull(), "allow").otherwise(model.default)
    return parsed.select(*(F.col(n).alias(k) for k, n in zip(keep, names)), F.col("__host").alias("host"), F.col("__path").alias("path"), rule.alias("rule"), F.coalesce(verdict, own).alias("verdict"), F.col("__p").alias("p_block"))
