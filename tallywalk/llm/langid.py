"""Language identification, word first with back-off to character n-grams.

Training counts words and the 1- to 4-letter pieces of words (with marks for the word's ends) for each language. A word that
the model knows scores its log frequency in each language; an unknown one is looked up by its longest pieces, then by shorter and
shorter ones until some are known, and scores their mean log frequency, less a penalty for each step. A document scores the mean of its words; the answer is the language
of the largest mean, its score the share of that language in the exponentials of the means.

The model is fitted on a bounded sample of the labelled rows: about `per_language` documents of each language, chosen by a hash of the key. All words and pieces
of the sample are kept, as 64-bit hashes with one number for each language, so the model's size is that of the sample's vocabulary whatever the corpus is. Texts are cut, hashed and
looked up by array arithmetic over their code points; no word becomes an object.

Defined results: null texts and texts without a letter (general categories Lu, Ll, Lt, Lm, Lo; numbers are not letters) are "und" with score 0. Rows with a null language are not learned from. With no
row to learn from every text is "und". Ties go to the language first in the alphabet. A text whose words have no known piece has an evidence of 0, equal scores, and so the first language.
Texts are scored whole. Other columns are kept unread, but for one of the name of the result, which the result replaces.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tallywalk.llm._frame import alone, in_parts, struct_udf
from tallywalk.llm._words import PART, between_words, code_points, hash_runs, letters, runs_of

LONGEST = 4
BACK_OFF = math.log(0.4)
BEGIN, END = ord("^"), ord("$")  # marks of a word's ends


def hash_of(keys: list[str]) -> np.ndarray:
    """The hashes of strings, none empty, as those of words in texts."""
    codes = np.frombuffer("".join(keys).encode("utf-32-le", "surrogatepass"), np.uint32)
    return hash_runs(codes, np.fromiter(map(len, keys), np.int64, len(keys)))


@dataclass
class Table:
    """Log frequencies of hashed words or pieces: a row for each, in order of the hashes, a column for each language."""

    hashes: np.ndarray
    rows: np.ndarray

    @classmethod
    def of(cls, keys: list[str], counts: np.ndarray) -> Table:
        """counts: a row for each key; a part that one language lacks counts there as half of one occurrence."""
        hashes = hash_of(keys)
        order = np.argsort(hashes)
        rows = np.log(np.maximum(counts, 0.5)) - np.log(counts.sum(axis=0) + 1)
        return cls(hashes[order], rows[order].astype(np.float32))

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """The row of each hash, -1 for unknown ones."""
        if not len(self.hashes):
            return np.full(len(hashes), -1)
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        return np.where(self.hashes[at] == hashes, at, -1)


@dataclass
class Model:
    languages: list[str]
    words: Table
    grams: list[Table]  # of 1 to LONGEST letters

    def back_off(self, codes: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For unknown words, whose code points follow each other: the mean of their longest known pieces with a penalty for each step, else zeros; and whether any piece is known."""
        marked = lengths + 2
        first = np.cumsum(marked) - marked
        flat = np.zeros(int(marked.sum()), np.uint32)
        flat[first], flat[first + marked - 1] = BEGIN, END
        inner = np.ones(len(flat), bool)
        inner[first] = inner[first + marked - 1] = False
        flat[inner] = codes
        word = np.repeat(np.arange(len(lengths)), marked)
        left = marked[word] - (np.arange(len(flat)) - first[word])  # code points from here to the word's end
        out, known = np.zeros((len(lengths), len(self.languages))), np.zeros(len(lengths), bool)
        for n in range(LONGEST, 0, -1):
            at = np.flatnonzero((left >= n) & ~known[word] & (inner if n == 1 else True))  # a mark alone tells nothing
            if not len(at):
                continue
            row = self.grams[n - 1].find(hash_runs(flat[at[:, None] + np.arange(n)].ravel(), np.full(len(at), n)))
            at, row = at[row >= 0], row[row >= 0]
            if not len(at):
                continue
            begins = np.flatnonzero(np.diff(word[at], prepend=-1))
            those, counts = word[at][begins], np.diff(np.append(begins, len(at)))
            out[those] = np.add.reduceat(self.grams[n - 1].rows[row].astype(float), begins) / counts[:, None] + (LONGEST + 1 - n) * BACK_OFF
            known[those] = True
        return out, known

    def score_words(self, codes: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For words whose code points follow each other: a row of scores, and whether the word or a piece of it is known."""
        hashes = hash_runs(codes, lengths)
        row = self.words.find(hashes)
        scores, known = np.zeros((len(hashes), len(self.languages))), row >= 0
        scores[known] = self.words.rows[row[known]]
        strange = np.flatnonzero(~known)
        if len(strange):  # each different one once
            _, one, back = np.unique(hashes[strange], return_index=True, return_inverse=True)
            some = strange[one]
            first = np.cumsum(lengths) - lengths
            size = lengths[some]
            at = np.repeat(first[some] - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))
            values, any_known = self.back_off(codes[at], size)
            scores[strange], known[strange] = values[back], any_known[back]
        return scores, known

    def score_word(self, word: str) -> tuple[float, ...]:
        codes = np.frombuffer(word.encode("utf-32-le"), np.uint32)
        return tuple(self.score_words(codes, np.array([len(codes)]))[0][0].tolist())

    def predict(self, texts: list[str | None]) -> list[tuple[str, float, float]]:
        """Language, score, and evidence: the share of the words that are known or have a known piece."""
        out: list[tuple[str, float, float]] = []
        for some in in_parts(texts, PART):
            if not self.languages:
                out += [("und", 0.0, 0.0)] * len(some)
                continue
            codes, ends = code_points(some)
            sums, counts, known = np.zeros((len(some), len(self.languages))), np.zeros(len(some)), np.zeros(len(some))
            for a, b in between_words(codes, letters()):
                inner, first, lengths = runs_of(codes[a:b], letters())
                if not len(first):
                    continue
                scores, hit = self.score_words(inner, lengths)
                text = np.searchsorted(ends, first + a, "right")
                begins = np.flatnonzero(np.diff(text, prepend=-1))
                sums[text[begins]] += np.add.reduceat(scores, begins)
                known[text[begins]] += np.add.reduceat(hit.astype(float), begins)
                counts[text[begins]] += np.diff(np.append(begins, len(text)))
            means = sums / np.maximum(counts, 1)[:, None]
            best = means.argmax(axis=1)
            share = 1 / np.exp(means - means.max(axis=1, keepdims=True)).sum(axis=1)
            for n, k, s, e in zip(counts.tolist(), best.tolist(), share.tolist(), known.tolist()):
                out.append((self.languages[k], s, e / n) if n else ("und", 0.0, 0.0))
        return out


def pieces(word: Column) -> Column:
    """All pieces of 1 to LONGEST letters of a marked word, after their number of letters; the marks alone are none."""
    marked = F.concat(F.lit(chr(BEGIN)), word, F.lit(chr(END)))
    cut = lambda x, n: F.transform(F.sequence(F.lit(1), F.greatest(F.length(x) - n + 1, F.lit(1))), lambda i: F.concat(F.lit(str(n)), F.substring(x, i, n)))
    longer = (F.when(F.length(marked) >= n, cut(marked, n)).otherwise(F.array().cast("array<string>")) for n in range(2, LONGEST + 1))
    return F.concat(cut(word, 1), *longer)


def fit(df: DataFrame, text: str = "text", lang: str = "lang", key: str = "doc_id", per_language: int = 1500) -> Model:
    """Counts on the executors: of each language's words first, of the different words' pieces then. What reaches the driver is the vocabulary of a sample whose documents per_language bounds."""
    rows = df.where(F.col(lang).isNotNull() & F.col(text).isNotNull()).select(F.col(lang).alias("lang"), F.col(text).alias("text"), F.col(key).alias("key"))
    sizes = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not sizes:
        none = Table(np.zeros(0, np.uint64), np.zeros((0, 0), np.float32))
        return Model([], none, [none] * LONGEST)
    languages = sorted(sizes)
    rate = F.create_map(*(F.lit(x) for k in languages for x in (k, min(1.0, per_language / sizes[k]))))
    draw = F.pmod(F.xxhash64(F.col("key").cast("string")), F.lit(1 << 20)) / F.lit(float(1 << 20))
    sample = rows.where(draw < rate[F.col("lang")])
    words = sample.select("lang", F.explode(F.split(F.lower("text"), r"\P{L}+")).alias("word")).where("word <> ''").groupBy("lang", "word").agg(F.count(F.lit(1)).alias("n"))
    parts = words.select("lang", "n", F.explode(F.concat(F.array(F.concat(F.lit("w"), F.col("word"))), pieces(F.col("word")))).alias("part"))
    count = [F.sum(F.when(F.col("lang") == l, F.col("n")).otherwise(0)).cast("double").alias(f"n{i}") for i, l in enumerate(languages)]
    got = parts.groupBy("part").agg(*count).toArrow()
    keys = got["part"].to_pylist()
    return model_of(languages, keys, np.column_stack([got[f"n{i}"].to_numpy() for i in range(len(languages))]) if keys else np.zeros((0, len(languages))))


def model_of(languages: list[str], parts: list[str], counts: np.ndarray) -> Model:
    """parts: words and pieces after a letter for their kind, "w" or their length; counts: a row for each, a column for each language."""
    kinds = np.array([p[0] for p in parts])
    tables = []
    for kind in ["w", *map(str, range(1, LONGEST + 1))]:
        at = np.flatnonzero(kinds == kind) if len(parts) else np.zeros(0, np.int64)
        tables.append(Table.of([parts[i][1:] for i in at.tolist()], counts[at]))
    return Model(languages, tables[0], tables[1:])


@alone
def at_work() -> bool:
    """Nothing of its own: the model comes with the task. What other operators remember goes."""
    return True


def predict(df: DataFrame, model: Model, text: str = "text", out: str = "language") -> DataFrame:
    """df with a struct (lang_pred, score, evidence)."""
    sent = df.sparkSession.sparkContext.broadcast(model)

    def run(texts):
        at_work()
        names, scores, known = zip(*sent.value.predict(texts)) if texts else ((), (), ())
        return {"lang_pred": names, "score": scores, "evidence": known}

    return df.withColumn(out, struct_udf(run, "lang_pred string, score double, evidence double")(F.col(text)))
