"""Similarity join of documents on sets of five-word shingles, by chosen paths.

Documents with equal sets are copies; one of them stands for all. Each set is embedded in COORDINATES min-hash values, and so for every coordinate two sets agree
with the probability of their Jaccard similarity: agreeing means sharing the sampled token. A run splits all sets by one coordinate. Small buckets are
compared by brute force on the coordinates. In a large bucket all sets are compared with a few hubs; those that agree with one (ALIKE) become its candidates and leave; those that are like none of them, and
whose other buckets do not suffice for the recall, split again by coordinates drawn for their path, about BRANCHES of them, and so on down; what is still crowded on the last level becomes one candidate group. A
pair at the threshold survives a run with a probability of at least `survival(levels)`, and runs are repeated until the chance to miss it is below 1 - recall. That bound leaves out pairs of which one set leaves
with a hub and the other does not; they are left to the other buckets and runs (crowded buckets lost no link in the tests).

What was found alike makes candidate groups: the connected components. Within a group all sets are compared exactly (32-bit shingle hashes), so that links are complete there and counted once. A
group of M sets is cut into blocks of about 2 * sqrt(M), and every two blocks meet in a task of their own: no task holds a large group, and what leaves it are numbers of links and a spanning
forest, never pairs. Classes are the connected components of the links.

Result: a row for each document: class_id (the least document id of its class), copy_id (the least id among its copies), n_links (other documents with similarity of at
least 0.8).

Defined results: null and empty texts link to nothing and are classes of their own. Texts of fewer than five words have one shingle of all words. Documents with a null id take part; a class
without any id has a null class_id. Repeated rows are copies. Other columns are not read; texts are used whole. An empty table gives an empty table.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tallywalk.llm._frame import forget, join_counted, may_hold, struct_udf, with_row_key, written, written_alone
from tallywalk.llm._words import LEAST, shingled

COORDINATES = 64
BRANCHES = 2.0
BUCKET = 10  # sets of a bucket that is compared by brute force
LEVELS = 6
HUBS = 3
ALIKE = 0.4  # agreement with a hub that makes a candidate group; far below the threshold, so that the likes of a member are members
SEEDS = np.random.default_rng(20).integers(1, 1 << 63, COORDINATES, dtype=np.uint64)


def survival(levels: int, similarity: float = LEAST) -> float:
    """The least probability that a pair of this similarity shares a bucket of the last level, in one run."""
    p = 1.0
    for _ in range(levels - 1):
        p = 1 - math.exp(-BRANCHES * similarity * p)
    return similarity * p


def runs_for(recall: float, levels: int = LEVELS, similarity: float = LEAST) -> int:
    return max(1, math.ceil(math.log(1 - recall) / math.log(1 - survival(levels, similarity))))


def settled(runs: int, recall: float, similarity: float = LEAST) -> int:
    """How many of a set's first-level buckets must be small for its links to be found in them with this recall.

    If k of the runs end in small buckets, about 1 - k / runs of the set's tokens are common ones. Even where all of those are shared with a partner, the two agree on each of the k others with a chance
    of at least 1 - (1 - similarity) * runs / k, and one agreement is enough."""
    for k in range(1, runs + 1):
        miss = min(1.0, (1 - similarity) * runs / k)
        if miss**k <= 1 - recall:
            return k
    return runs + 1


def min_hashes(grams: np.ndarray) -> np.ndarray:
    """COORDINATES min-hash values of a set of 64-bit hashes, as signed 32-bit numbers."""
    out = np.full(COORDINATES, 0xFFFFFFFF, np.uint64)
    with np.errstate(over="ignore"):
        for a in range(0, len(grams), 2048):
            mixed = (grams[a : a + 2048, None] ^ SEEDS) * np.uint64(0xD6E8FEB86659FD93)
            out = np.minimum(out, (mixed >> np.uint64(32)).min(axis=0))
    return out.astype(np.uint32).view(np.int32)


def _sets(texts: list[str | None], runs: int) -> dict:
    out: dict[str, list] = {"set_a": [], "set_b": [], "n": [], "tops": [], "paths": []}
    for _, grams in shingled(texts):
        g = np.unique(grams)
        with np.errstate(over="ignore"):
            out["set_a"].append(int(g.sum(dtype=np.uint64).view(np.int64)))
            out["set_b"].append(int(((g ^ (g >> np.uint64(31))) * np.uint64(0x94D049BB133111EB)).sum(dtype=np.uint64).view(np.int64)))
        out["n"].append(len(g))
        values = min_hashes(g) if len(g) else None
        out["tops"].append(None if values is None else values[:runs])
        out["paths"].append(None if values is None else values.astype(np.int16))
    return out


def _grams(texts: list[str | None]) -> dict:
    return {"v": [np.unique(g.astype(np.uint32)).tobytes() for _, g in shingled(texts)]}


def sets_of(texts: DataFrame, members: DataFrame) -> DataFrame:
    """(rep, grams) of the given sets alone, by a second look at the texts; members: rep, print. A bit filter keeps most other texts out of the shuffle."""
    test = may_hold(members, "print")
    some = texts.select(F.xxhash64("text").alias("print"), "text").where(test(F.col("print")))
    one = some.groupBy("print").agg(F.first("text").alias("text")).join(members.select("rep", "print"), "print")
    return one.select("rep", struct_udf(_grams, "v binary")("text")["v"].alias("grams"))


def agreement(x: Column, y: Column) -> Column:
    """The share of coordinates on which two sets agree."""
    return F.aggregate(F.zip_with(x, y, lambda a, b: (a == b).cast("int")), F.lit(0), lambda n, m: n + m) / F.lit(float(COORDINATES))


def split(rows: DataFrame) -> DataFrame:
    """The rows (path, rep, paths) of large buckets at the next level."""
    chosen = F.filter(F.sequence(F.lit(0), F.lit(COORDINATES - 1)), lambda i: F.pmod(F.xxhash64(F.col("path"), i), F.lit(1 << 20)) < F.lit(int(BRANCHES / COORDINATES * (1 << 20))))
    deeper = rows.withColumn("i", F.explode(chosen))
    return deeper.select(F.xxhash64("path", "i", F.get("paths", F.col("i"))).alias("path"), "rep", "paths")


def compared(rows: DataFrame, least: float) -> DataFrame:
    """Edges (a, b) between sets of one bucket whose coordinates agree about as often as the threshold asks."""
    # six deviations below the threshold: not a filter that a true link fails
    slack = 6 * math.sqrt(least * (1 - least) / COORDINATES)
    x, y = (rows.select("path", F.col("rep").alias(r), F.col("paths").alias(p)) for r, p in (("a", "pa"), ("b", "pb")))
    return x.join(y, "path").where((F.col("a") < F.col("b")) & (agreement(F.col("pa"), F.col("pb")) >= least - slack)).select("a", "b")


def candidate_edges(level: DataFrame, least: float, runs: int, recall: float) -> DataFrame:
    """Edges that connect all sets which a path has brought together and which may be alike. level: path, rep, paths, and k, the sets of the path."""
    edges = []
    pick = [F.min_by(F.struct("rep", "paths"), F.xxhash64("rep", F.lit(k))).alias(f"h{k}") for k in range(HUBS)]
    for depth in range(LEVELS):
        sized = written(level, "level")
        if depth:
            counts = written(sized.groupBy("path").agg(F.count(F.lit(1)).alias("k")).where("k > 1"), "counts")
            sized = written(join_counted(sized, counts, "path", "k").where("k is not null"), "sized")
        edges.append(compared(sized.where(F.col("k") <= BUCKET), least))
        inside = sized.where(F.col("k") > BUCKET).select("path", "rep", "paths")
        if not inside.limit(1).count():
            break
        hubs = written(inside.groupBy("path").agg(F.count(F.lit(1)).alias("n"), *pick), "bucket-hubs")
        met = join_counted(inside, hubs, "path", "n")
        agreed = [agreement(F.col("paths"), F.col(f"h{k}.paths")) for k in range(HUBS)]
        near = [F.when(a >= ALIKE, F.col(f"h{k}.rep")) for k, a in enumerate(agreed)]
        # what can't be split any more is one group, whose hub is the first one
        last = F.col("h0.rep") if depth == LEVELS - 1 else F.lit(None).cast("bigint")
        met = written(met.select("path", "rep", "paths", F.array_distinct(F.array_compact(F.array(*near, last))).alias("near"), (F.greatest(*agreed) >= ALIKE).alias("settled")), "met")
        ends = met.select(F.col("rep").alias("x"), F.explode("near").alias("y")).where("x <> y")
        edges.append(ends.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")))
        if depth == LEVELS - 1:
            break
        rest = met.where("not settled").select("path", "rep", "paths")
        if depth == 0:
            # sets that enough small buckets have settled need no split: see `settled`
            crowded = inside.groupBy("rep").agg(F.count(F.lit(1)).alias("crowded"))
            rest = rest.join(crowded.where(F.lit(runs) - F.col("crowded") < settled(runs, recall, least)).select("rep"), "rep", "left_semi").select("path", "rep", "paths")
        level = split(rest)
    found = edges[0]
    for e in edges[1:]:
        found = found.union(e)
    return found.distinct()


def compare_cell(sets: list[bytes], left: int, copies: np.ndarray, least: float) -> tuple[np.ndarray, np.ndarray]:
    """For the sets of a cell, the first `left` of them against the others (all against all, if there are no others): how many documents each links to, and the
    least place that links lead to from it."""
    n, arrays = len(sets), [np.frombuffer(x, np.uint32) for x in sets]
    sizes = np.fromiter(map(len, arrays), np.int64, n)
    _, at, counts = np.unique(np.concatenate(arrays), return_inverse=True, return_counts=True)
    shared = counts > 1  # the others are in no intersection
    column = np.cumsum(shared) - 1
    rows, at = np.repeat(np.arange(n), sizes), at
    rows, at = rows[shared[at]], column[at[shared[at]]]
    order = np.argsort(at, kind="stable")
    rows, at = rows[order], at[order]
    cross = left < n
    a, b = (left, n - left) if cross else (n, n)
    both = np.zeros((a, b), np.float32)
    for low in range(0, int(shared.sum()), 8192):
        i, j = np.searchsorted(at, [low, low + 8192])
        part = np.zeros((n, min(8192, int(shared.sum()) - low)), np.float32)
        part[rows[i:j], at[i:j] - low] = 1
        both += part[:a] @ part[n - b :].T
    either = sizes[:a, None] + sizes[None, n - b :] - both
    linked = both >= least * either - 1e-6
    if not cross:
        np.fill_diagonal(linked, False)
    links = np.zeros(n, np.int64)
    links[:a] += linked @ copies[n - b :]
    if cross:
        links[a:] += copies[:a] @ linked
    lead = np.arange(n)
    while True:
        before = lead.copy()
        if linked.any():
            lead[:a] = np.minimum(lead[:a], np.where(linked, lead[None, n - b :], n).min(axis=1))
            lead[n - b :] = np.minimum(lead[n - b :], np.where(linked, lead[:a, None], n).min(axis=0))
        if (lead == before).all():
            return links, lead


def group_links(members: DataFrame, texts: DataFrame, least: float) -> DataFrame:
    """(rep, links, lead) from the exact comparison of candidate groups; members: rep, root, copies, print. A set has a row for each cell in which it links."""
    size = written(members.groupBy("root").agg(F.count(F.lit(1)).alias("n")), "group-sizes")
    told = join_counted(members, size, "root", "n")
    blocks = F.ceil(F.col("n") / F.greatest(F.lit(32.0), 2 * F.sqrt("n"))).cast("int")
    placed = told.select("rep", "root", "copies", blocks.alias("nb"), F.pmod(F.xxhash64("rep"), blocks).cast("int").alias("block"))
    fat = written(placed.join(sets_of(texts, members), "rep"), "group-sets")
    other = F.explode(F.sequence(F.lit(0), F.col("nb") - 1)).alias("other")
    spread = fat.select("root", "block", other, "rep", "copies", "grams").select("root", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "rep", "copies", "grams")
    dealt = spread.repartition("root", "i", "j").sortWithinPartitions("root", "i", "j", "block")

    def run(batches):
        key, rows = None, []

        def done():
            if len(rows) < 2:
                return None
            blocks_, reps, copies, grams = zip(*rows)
            left = blocks_.count(blocks_[0])
            if key[1] != key[2] and left == len(rows):  # one of the two blocks is empty
                return None
            links, lead = compare_cell(list(grams), left, np.array(copies, np.int64), least)
            keep = np.flatnonzero(links)
            if not len(keep):
                return None
            reps = np.array(reps, np.int64)
            return pa.RecordBatch.from_pydict({"rep": reps[keep], "links": links[keep], "lead": reps[lead[keep]]})

        for batch in batches:
            for root, i, j, *row in zip(*(c.to_pylist() for c in batch.columns)):
                if key != (root, i, j):
                    if (out := done()) is not None:
                        yield out
                    key, rows = (root, i, j), []
                rows.append(row)
        if (out := done()) is not None:
            yield out

    return dealt.mapInArrow(run, "rep bigint, links bigint, lead bigint")


def components(edges: DataFrame) -> DataFrame:
    """(rep, root) for all ends of the edges (a, b): the least key of each connected component, by alternating large and small stars until nothing changes. The
    number of rounds grows with the logarithm of the edges; each round's tables are removed after the next."""
    spark = edges.sparkSession
    now = written(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct(), "edges")
    before = None
    while True:

        def stars(now: DataFrame = now) -> DataFrame:
            both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
            least = written(both.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n")).withColumn("m", F.least("m", "u")), "least")
            large = written(join_counted(both, least, "u", "n").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").distinct(), "large-star")
            smaller = written(large.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n")), "smaller")
            rest = join_counted(large, smaller, "u", "n").where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
            return rest.union(smaller.select("u", F.col("m").alias("v"))).distinct()

        older, now = now, written_alone(stars, "edges")
        forget(spark, older)
        state = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == before:
            break
        before = state
    ends = now.groupBy(F.col("u").alias("rep")).agg(F.min("v").alias("root"))
    return ends.union(ends.select(F.col("root").alias("rep"), "root").distinct())


RESULT = ("class_id", "copy_id", "n_links", "first")


def join(df: DataFrame, key: str = "doc_id", text: str = "text", least: float = LEAST, recall: float = 0.9999) -> DataFrame:
    """A row for each row of df: key, class_id, copy_id, n_links."""
    return labelled(df.select(F.col(key).alias("key"), F.col(text).alias("text")), least, recall).select(F.col("key").alias(key), "class_id", "copy_id", "n_links")


def labelled(rows: DataFrame, least: float = LEAST, recall: float = 0.9999) -> DataFrame:
    """For rows (key, text, and others): key and the others, then class_id, copy_id, n_links, and first, true for one row of each class. Others of these names are replaced."""
    runs = min(COORDINATES, runs_for(recall))
    made = struct_udf(lambda texts: _sets(texts, runs), "set_a bigint, set_b bigint, n int, tops array<int>, paths array<smallint>")
    others = [c for c in rows.columns if c not in ("text", *RESULT)]
    kept = F.struct(*(F.col(c) for c in others)).alias("__others")  # under names of their own
    first = written(with_row_key(rows.select(kept, "key", F.xxhash64("text").alias("print"), made(F.col("text")).alias("made")).select("__others", "key", "print", "made.*")), "sets")
    docs = first.where("n > 0").select("__row", "key", "print", "set_a", "set_b", "n")
    same = ["set_a", "set_b", "n"]
    copies = written(docs.groupBy(*same).agg(F.min("__row").alias("rep"), F.count(F.lit(1)).alias("copies"), F.min("key").alias("copy_id"), F.min_by("print", "__row").alias("print")), "copies")
    reps = written(first.where("n > 0").select(F.col("__row").alias("rep"), "tops", "paths").join(copies.select("rep"), "rep", "left_semi"), "paths")

    top = reps.select("rep", F.posexplode("tops").alias("i", "value")).select(F.xxhash64("i", "value").alias("path"), "rep")
    # a set that is alone in a bucket has nothing to do with it: counted on slim rows, before the coordinates come along
    shared = written(top.groupBy("path").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "shared")
    met = join_counted(top, shared, "path", "n").where("n is not null").select("path", "rep", F.col("n").alias("k"))
    level = met.join(reps.select("rep", "paths"), "rep")
    weight = copies.select("rep", "copies", "print")
    groups = components(candidate_edges(level, least, runs, recall))
    members = written(groups.join(weight, "rep"), "members")
    found = written(group_links(members, rows.select("text"), least), "links")
    across = found.groupBy("rep").agg(F.sum("links").alias("across"))
    root = components(found.select(F.col("rep").alias("a"), F.col("lead").alias("b")))
    told = copies.join(root, "rep", "left").join(across, "rep", "left")
    told = told.withColumn("root", F.coalesce("root", "rep")).withColumn("n_links", F.col("copies") - 1 + F.coalesce("across", F.lit(0)))
    told = written(told.select(*same, "rep", "root", "copy_id", "n_links"), "told")
    least_id = written(told.groupBy("root").agg(F.min("copy_id").alias("class_id"), F.count(F.lit(1)).alias("members")), "classes")
    told = join_counted(told, least_id, "root", "members").select(*same, "copy_id", "n_links", "class_id", (F.col("rep") == F.col("root")).alias("is_root"), "rep")
    out = first.drop("print", "paths", "tops").join(told, same, "left")
    alone = F.col("rep").isNull()
    return out.select(
        "__others.*",
        F.when(alone, F.col("key")).otherwise(F.col("class_id")).alias("class_id"),
        F.when(alone, F.col("key")).otherwise(F.col("copy_id")).alias("copy_id"),
        F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"),
        (alone | (F.col("is_root") & (F.col("__row") == F.col("rep")))).alias("first"),
    )
