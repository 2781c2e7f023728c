"""Secret scan with the corpus-wide ownership frequency of each candidate.

Every candidate string is hashed; over the whole corpus a hash has a number of distinct repositories and of distinct owners.
A hash that many owners have is a copied example; one that few owners have, and whose string is not of a placeholder's kind
(one letter or run over and over), looks live. Only hashes leave the scan, never the strings.

Base kinds (their spans always stay): assign, access, hex. The method adds: private (a private-key block up to its END line; the digest is of the key's letters alone), jwt, forge
(prefixed tokens of code hosts), and opaque (24 or more base64 letters of all three classes with at least 4 bits of entropy
a letter), as far as they look live and do not overlap a base span; a private-key block is cut around the base spans in it, all pieces with the block's digest.
A block without an END line within BLOCK_MOST code points ends with its lines of base64. A block of fewer than 32 letters has no key: its digest is its first line's.

Defined results: a null or empty text has no span. Null repositories or owners count as one value. Repeated rows are rows of
their own and one owner's. Other columns, whatever their names, pass unread; texts are scanned whole; an empty table gives an
empty table.
"""

from __future__ import annotations

import bisect
import hashlib
import itertools
import math
import re
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tallywalk.llm._frame import join_counted, struct_udf, unclashing, with_row_key, written

# fixed values: the base kinds' patterns, their least lengths, and the order of all kinds
BASE = {
    "assign": (re.compile(r"""(?ai:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""), 6),
    "access": (re.compile(r"(AKIA[A-Z0-9]+)"), 20),
    "hex": (re.compile(r"([0-9a-f]{24,})"), 24),
}
ADDED = {
    "private": re.compile(r"-----(?:BEGIN|END) (?:[A-Z]+ ){0,3}PRIVATE KEY-----"),
    "jwt": re.compile(r"(?<![A-Za-z0-9_-])(eyJ[A-Za-z0-9_-]{8,}+\.eyJ[A-Za-z0-9_-]{8,}+\.[A-Za-z0-9_-]{8,}+)"),
    "forge": re.compile(r"((?:gh[pousr]_|glpat-|xox[abpr]-)[A-Za-z0-9_-]{16,})"),
    "opaque": re.compile(r"(?<![A-Za-z0-9+/_=-])([A-Za-z0-9+/_-]{24,}+={0,2}+)(?![A-Za-z0-9+/_=-])"),
}
BLOCK_MOST = 1 << 16
ARMOR = re.compile(r"(?m)^[^\S\n]*[A-Za-z][A-Za-z-]*:[^\S\n].*$")  # a block's own headers
NOT_KEY = re.compile(r"""\\[nrt]|["']\s*\+\s*["']|[^A-Za-z0-9+/=]""")
LOOSE = re.compile(r"""(?:(?:\s|\\[nrt])*+[A-Za-z][A-Za-z-]*:[^\S\n][^\n]*+)*+(?:(?:\\[nrt]|[\s"',>#;|*]|\+(?=\s))*+[A-Za-z0-9+/=]{16,}+)*+(?:(?:\\[nrt]|[\s"',>#;|*])*+[A-Za-z0-9+/]{1,15}={1,2})?""")
KINDS = [*BASE, *ADDED]
MARKS = {"private": "PRIVATE KEY-----", "jwt": "eyJ"}
FOUND = "array<struct<kind:int,start:int,finish:int,digest:string,weak:boolean>>"


def entropy(s: str) -> float:
    return -sum(c / len(s) * math.log2(c / len(s)) for c in Counter(s).values())


def weak(s: str) -> bool:
    """Of a placeholder's kind: very few letters, or nearly all alike."""
    return len(set(s)) <= 4 or entropy(s) < 2.0


def base_spans(text: str) -> list[tuple[int, int, int, str]]:
    """Start, kind, end and secret of the base kinds, in order of start and then kind."""
    out = []
    for kind, (name, (pattern, least)) in enumerate(BASE.items()):
        if name == "assign" and ":" not in text and "=" not in text or name == "access" and "AKIA" not in text:
            continue
        out += [(m.start(), kind, m.end(), m[1]) for m in pattern.finditer(text) if len(m[1]) >= least]
    return sorted(out, key=lambda x: x[:2])


def key_blocks(text: str) -> list[tuple[int, int, str]]:
    """Start, end and key of each private-key block."""
    marks, out = list(ADDED["private"].finditer(text)), []
    for m, after in zip(marks, [*marks[1:], None]):
        if m[0].startswith("-----END"):
            continue
        if after and after[0].startswith("-----END") and after.start() - m.end() <= BLOCK_MOST:
            stop, end = after.start(), after.end()
        else:
            stop = end = LOOSE.match(text, m.end()).end()
        key = NOT_KEY.sub("", ARMOR.sub("", text[m.end() : stop]))
        out.append((m.start(), end, key if len(key) >= 32 else m[0]))
    return out


class Cover:
    """Spans in order of their start, to be asked which of them meet a stretch."""

    def __init__(self, spans: list[tuple[int, int, int, str]]):
        self.spans = sorted((a, b) for a, _, b, _ in spans)
        self.starts = [a for a, _ in self.spans]
        self.reach = list(itertools.accumulate((b for _, b in self.spans), max))  # the farthest end so far

    def meets(self, a: int, b: int) -> bool:
        n = bisect.bisect_left(self.starts, b)
        return n > 0 and self.reach[n - 1] > a

    def outside(self, a: int, b: int) -> list[tuple[int, int]]:
        """What of a to b no span covers."""
        out = []
        for i in range(bisect.bisect_right(self.reach, a), bisect.bisect_left(self.starts, b)):
            x, y = self.spans[i]
            if x > a:
                out.append((a, x))
            a = max(a, y)
        return [*out, (a, b)] if a < b else out


def added_spans(text: str, base: list[tuple[int, int, int, str]]) -> list[tuple[int, int, int, str]]:
    out, own = [], Cover(base)
    for name, pattern in ADDED.items():
        if name in MARKS and MARKS[name] not in text:
            continue
        kind = KINDS.index(name)
        if name == "private":
            out += [(x, kind, y, key) for a, b, key in key_blocks(text) for x, y in own.outside(a, b)]
            continue
        cover = Cover([*base, *out]) if out else own
        for m in pattern.finditer(text):
            s = m[1]
            if name == "opaque" and (s.isalpha() or not (re.search("[a-z]", s) and re.search("[A-Z]", s) and re.search("[0-9]", s)) or entropy(s) < 4):
                continue
            if not cover.meets(m.start(), m.end()):
                out.append((m.start(), kind, m.end(), s))
    return out


def listed(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def _scan(texts: list[str | None]) -> dict:
    out: dict[str, list] = {"n_assign": [], "n_access": [], "n_hex": [], "base_sha256": [], "found": []}
    for text in texts:
        base = base_spans(text or "")
        counts = Counter(k for _, k, _, _ in base)
        for kind, name in enumerate(BASE):
            out[f"n_{name}"].append(counts[kind])
        out["base_sha256"].append(hashlib.sha256(listed([x[:3] for x in base]).encode()).hexdigest())
        every = sorted([*base, *added_spans(text or "", base)], key=lambda x: x[:2])
        out["found"].append([{"kind": k, "start": a, "finish": b, "digest": hashlib.sha256(s.encode()).hexdigest()[:32], "weak": weak(s)} for a, k, b, s in every])
    return out


def candidates(df: DataFrame, keys: list[str], text: str = "text") -> DataFrame:
    """keys, counts of the base kinds, their digest, and all candidates of each row as an array (FOUND)."""
    made = struct_udf(_scan, f"n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, found {FOUND}")
    return df.select(*keys, made(F.col(text)).alias("__made")).select(*keys, "__made.*")


def frequency(found: DataFrame, digest: str = "digest", repository: str = "repository", owner: str = "owner") -> DataFrame:
    """For each digest: n_rows, and its numbers of distinct repositories and owners over the whole corpus.

    Rows of one digest meet pre-aggregated: first by (digest, repository, owner) on every task, then distinct values, then counts."""
    nil = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("\0"))  # noqa: E731  null is one value
    triples = found.groupBy(digest, nil(repository).alias("r"), nil(owner).alias("o")).agg(F.count(F.lit(1)).alias("n"))
    return triples.groupBy(digest).agg(F.sum("n").alias("n_rows"), F.count_distinct("r").alias("n_repositories"), F.count_distinct("o").alias("n_owners"))


def verdict(owners: Column, weak_: Column, most_owners: int) -> Column:
    return F.when(owners > most_owners, "example").when(weak_, "placeholder").otherwise("live")


def scan(df: DataFrame, keys: list[str], text: str = "text", repository: str = "doc_id", owner: str = "source", most_owners: int = 2) -> DataFrame:
    """A row for each row of df: keys, n_assign, n_access, n_hex, base_sha256, spans (array of kind, start, finish, digest, verdict, n_owners,
    n_repositories in order). Keys of these names are replaced. most_owners: the most owners of a digest that still looks owner-specific."""
    keys = unclashing(keys, "n_assign", "n_access", "n_hex", "base_sha256", "spans")
    names = [f"__k{i}" for i in range(len(keys))]
    slim = df.select(*(F.col(k).alias(n) for k, n in zip(keys, names)), F.col(repository).alias("__repo"), F.col(owner).alias("__owner"), F.col(text).alias("__text"))
    first = written(with_row_key(candidates(slim, [*names, "__repo", "__owner"], "__text")), "secrets")
    rows = first.where(F.size("found") > 0).select("__row", F.col("__repo").alias("repository"), F.col("__owner").alias("owner"), F.inline("found"))
    table = written(frequency(rows), "secret-frequency")
    told = join_counted(rows.drop("repository", "owner"), table, "digest", "n_rows")
    told = told.withColumn("verdict", verdict(F.col("n_owners"), F.col("weak"), most_owners)).where((F.col("kind") < len(BASE)) | (F.col("verdict") == "live"))
    kinds = F.array(*map(F.lit, KINDS))
    span = F.struct("start", "kind", kinds[F.col("kind")].alias("name"), "finish", "digest", "verdict", "n_owners", "n_repositories")
    spans = told.groupBy("__row").agg(F.sort_array(F.collect_list(span)).alias("spans"))  # the spans of one document
    whole = first.drop("found", "__repo", "__owner").join(spans, "__row", "left")
    return whole.select(*(F.col(n).alias(k) for k, n in zip(keys, names)), "n_assign", "n_access", "n_hex", "base_sha256", F.coalesce("spans", F.array().cast(dict(whole.dtypes)["spans"])).alias("spans"))


def spans_text(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["name"], s["start"], s["finish"])), ",")


def redact(df: DataFrame, text: str, spans: str, mark: str = "<secret>") -> DataFrame:
    """df with every live span (code points) of the text replaced by the mark; overlapping spans by one."""

    def run(texts, all_spans):
        out = []
        for t, some in zip(texts, all_spans):
            live, parts, at = sorted((s["start"], s["finish"]) for s in some or () if s["verdict"] == "live"), [], 0
            for a, b in live:
                if a >= at:
                    parts += [t[at:a], mark]
                at = max(at, b)
            out.append("".join([*parts, t[at:]]) if live else t)
        return {"v": out}

    return df.withColumn(text, struct_udf(run, "v string")(F.col(text), F.col(spans))["v"])
