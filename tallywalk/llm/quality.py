"""Quality rules as a bitmask ledger.

Every rule is evaluated once on every document; the ledger keeps the measurements and one number whose bit i says that rule i
failed. A policy is a versioned set of rules, so applying one is a bitwise "and" of the stored number, and an ablation (what would
be kept without a rule) is a count by masks: no text is read again.

Defined results: a null or empty text has no words, fails the rule for short texts, and no ratio rule. Repeated rows are rows of their own.
Lines end at a line feed. Other columns are not read. Texts of any length are measured whole.
"""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallywalk.llm._frame import struct_udf, unclashing

MEASURES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_chars", "n_letters", "n_upper", "n_marked_words", "longest_word"]

#: Name and the failing condition over the measurements, as SQL; the position is the bit and never changes, new rules go to the end.
RULES: list[tuple[str, str]] = [
    ("short", "n_words < 50"),
    ("repeats", "100 * n_repeat_words > 50 * n_words"),
    ("symbols", "100 * n_symbols > 30 * n_words"),
    ("duplicate_lines", "n_lines >= 4 and 100 * n_dup_lines > 50 * n_lines"),
    ("word_length", "n_words > 0 and (word_chars < 2 * n_words or word_chars > 20 * n_words)"),
    ("letters", "word_chars > 0 and 100 * n_letters < 60 * word_chars"),
    ("shouting", "n_letters > 0 and 100 * n_upper > 60 * n_letters"),
    ("marked_words", "100 * n_marked_words > 40 * n_words"),
    ("long_word", "longest_word > 1000"),
]
BIT = {name: 1 << i for i, (name, _) in enumerate(RULES)}

#: Versioned policies: the rules that count. A policy's rules never change; another set is another version.
POLICIES: dict[str, list[str]] = {
    "base-1": ["short", "repeats"],
    "web-1": ["short", "repeats", "symbols", "duplicate_lines", "letters", "shouting", "marked_words"],
    "strict-1": [name for name, _ in RULES],
}

SYMBOLS = "#*$%&|<>"
BLANK = "\x20\x09\x0a\x0b\x0c\x0d"
LETTERS = re.compile(r"[^\W\d_]+")
UPPER = re.compile(r"[A-ZÀ-ÖØ-Þ]+")
MARKED = re.compile(rb"[^\x00-\x20]*[#*$%&|<>!]{2,}(?=[\x09-\x0d\x20]|$)")


def mask(policy: str) -> int:
    return sum(BIT[name] for name in POLICIES[policy])


def measure(text: str | None) -> tuple[int, ...]:
    text = text or ""
    words = text.encode("utf-8", "surrogatepass").split()  # of bytes: ASCII white space alone
    n = len(words)
    windows = list(zip(words, words[1:], words[2:]))
    repeated = 0
    if len(set(windows)) < len(windows):
        counts, until = Counter(windows), 0
        for i, w in enumerate(windows):
            if counts[w] > 1:
                repeated += i + 3 - max(i, until)
                until = i + 3
    lines = [x for x in text.split("\n") if x.strip(BLANK)]
    letters = LETTERS.findall(text)
    return (
        n,
        len(text) - sum(map(text.count, BLANK)),
        sum(map(text.count, SYMBOLS)),
        len(lines) - len(set(lines)),
        repeated,
        len(lines),
        len(text),
        sum(map(len, letters)),
        sum(map(len, UPPER.findall(text))),
        len(MARKED.findall(text.encode("utf-8", "surrogatepass"))),
        max(map(len, words), default=0),
    )


def _measure(texts: list[str | None]) -> dict:
    columns = zip(*map(measure, texts)) if texts else [()] * len(MEASURES)
    return dict(zip(MEASURES, columns))


def ledger(df: DataFrame, keys: list[str], text: str = "text") -> DataFrame:
    """keys, the measurements (long), and failed (long): the bits of the rules that failed. Keys of these names are replaced."""
    keys = unclashing(keys, *MEASURES, "failed")
    names = [f"__k{i}" for i in range(len(keys))]
    made = struct_udf(_measure, ", ".join(f"{m} bigint" for m in MEASURES))
    slim = df.select(*(F.col(k).alias(n) for k, n in zip(keys, names)), made(F.col(text)).alias("__made"))
    bits = [f"case when {rule} then {BIT[name]}L else 0L end" for name, rule in RULES]
    flat = slim.select(*names, "__made.*").withColumn("failed", F.expr(" | ".join(f"({b})" for b in bits)))
    return flat.select(*(F.col(n).alias(k) for k, n in zip(keys, names)), *MEASURES, "failed")


def apply_policy(ledger_: DataFrame, policy: str, kept: str = "kept") -> DataFrame:
    return ledger_.withColumn(kept, F.col("failed").bitwiseAND(F.lit(mask(policy)).cast("bigint")) == 0)


def ablations(ledger_: DataFrame, policy: str) -> DataFrame:
    """For each rule of a policy: documents that fail it, that fail it alone, and that would be kept without it. At most one row of counts
    for each mask leaves a task, whatever the number of documents."""
    m = mask(policy)
    masks = ledger_.groupBy(F.col("failed").bitwiseAND(F.lit(m).cast("bigint")).alias("bits")).agg(F.count(F.lit(1)).alias("n"))
    rules = F.explode(F.array(*(F.struct(F.lit(name).alias("rule"), F.lit(BIT[name]).cast("bigint").alias("bit")) for name in POLICIES[policy])))
    per = masks.select("bits", "n", rules.alias("r")).select("bits", "n", "r.*")
    return per.groupBy("rule").agg(
        F.sum(F.when(F.col("bits").bitwiseAND(F.col("bit")) != 0, F.col("n")).otherwise(0)).alias("n_failed"),
        F.sum(F.when(F.col("bits") == F.col("bit"), F.col("n")).otherwise(0)).alias("n_failed_alone"),
        F.sum(F.when(F.col("bits").bitwiseAND(F.bitwise_not(F.col("bit"))) == 0, F.col("n")).otherwise(0)).alias("n_kept_without"),
        F.sum(F.when(F.col("bits") == 0, F.col("n")).otherwise(0)).alias("n_kept"),
    )
