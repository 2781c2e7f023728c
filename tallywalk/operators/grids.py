"""Two grids of cells that can be merged and asked for labels. All DataFrame operations; rows meet pre-aggregated, at most a cell's registers for each task.

cell grid: `depth` rows of `width` cells; in each row a label has one cell, whose counter takes the pair; the cell's label is the one whose pair hash had the highest level.
A label's estimate is the smallest of its cells'.

shared-register grid: one matrix of registers. The pair hash picks the row, the label the column in it; a label's vector is its register in every row, polluted
by others. Its size is the most likely one against each row's distribution of registers. Augmented, every cell also holds the label of the highest level.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tallywalk.functions.hashing import HASH_BITS, bit_length, bucket_and_rank, hash52
from tallywalk.functions.registers import estimate_of

LADDER_STEP = 1.02
TINY = 1e-300


@dataclass(frozen=True)
class Grid:
    registers: DataFrame
    labels: DataFrame | None
    depth: int
    width: int
    m: int
    hash: str
    kind: str

    @property
    def rows(self) -> DataFrame:
        """row, col, bucket, rank, label_key: the whole structure as one table, its labels at bucket -1. Both halves begin with the same exchange, which is planned once, so the input is read once."""
        bucket = F.col("bucket") if self.kind == "cell" else F.lit(0).alias("bucket")
        registers = self.registers.select("row", "col", bucket, "rank", F.lit(None).cast("string").alias("label_key"))
        if self.labels is None:
            return registers
        return registers.unionByName(self.labels.select("row", "col", F.lit(-1).alias("bucket"), F.col("level").alias("rank"), "label_key"))


def best_label() -> Column:
    """The label of the highest level, the first in order of equals."""
    return F.min(F.struct((-F.col("level")).alias("low"), "label_key")).alias("best")


def rows_of(depth: int) -> Column:
    return F.explode(F.sequence(F.lit(0), F.lit(depth - 1)))


def column_of(row: Column, width: int, hash: str) -> Column:
    """The column of a label in a row; the row is part of what is hashed."""
    return F.pmod(hash52(F.concat_ws("|", row.cast("string"), F.col("label_key")), "r", hash), F.lit(width)).cast("int")


def pair_text() -> Column:
    return F.concat_ws("\1", "label_key", "item_key")


# ---- cell grid


def cell_grid(pairs: DataFrame, depth: int = 4, width: int = 4572, m: int = 64, hash: str = "fast") -> Grid:
    bucket, rank = bucket_and_rank(hash52(pair_text(), "p", hash), m)
    hashed = pairs.select("label_key", bucket.alias("bucket"), rank.alias("rank"))
    # what a label sends to a register once, it need not send again for every row of the grid
    slim = hashed.groupBy("label_key", "bucket").agg(F.max("rank").alias("rank"))
    placed = slim.withColumn("row", rows_of(depth)).withColumn("col", column_of(F.col("row"), width, hash))
    registers = placed.groupBy("row", "col", "bucket").agg(F.max("rank").alias("rank"))
    # from the same exchange as the registers
    levels = slim.groupBy("label_key").agg(F.max("rank").alias("level")).withColumn("row", rows_of(depth)).withColumn("col", column_of(F.col("row"), width, hash))
    labels = levels.groupBy("row", "col").agg(best_label()).select("row", "col", F.col("best.label_key").alias("label_key"), (-F.col("best.low")).cast("tinyint").alias("level"))
    return Grid(registers, labels, depth, width, m, hash, "cell")


def cells(grid: Grid, estimator: str = "histogram") -> DataFrame:
    """row, col, estimate of every cell in use."""
    sums = grid.registers.groupBy("row", "col").agg(F.count(F.lit(1)).alias("filled"), F.sum(F.pow(F.lit(2.0), -F.col("rank"))).alias("powers"))
    return sums.select("row", "col", estimate_of(estimator, grid.m, F.col("filled"), F.col("powers")).alias("estimate"))


def grid_estimate(grid: Grid, labels: DataFrame, estimator: str = "histogram") -> DataFrame:
    wanted = labels.select("label_key").distinct().withColumn("row", rows_of(grid.depth)).withColumn("col", column_of(F.col("row"), grid.width, grid.hash))
    # depth * width rows: the grid's own fixed size
    found = wanted.join(F.broadcast(cells(grid, estimator)), ["row", "col"], "left")
    return found.groupBy("label_key").agg(F.min(F.coalesce("estimate", F.lit(0.0))).alias("estimate"))


def grid_top_k(grid: Grid, k: int, estimator: str = "histogram") -> DataFrame:
    if grid.labels is None:
        raise ValueError("a grid without labels can only be asked for given labels")
    return grid_estimate(grid, grid.labels, estimator).orderBy(F.desc("estimate"), "label_key").limit(k)


def merge_grids(a: Grid, b: Grid) -> Grid:
    same = lambda g: (g.kind, g.depth, g.width, g.m, g.hash)
    if same(a) != same(b):
        raise ValueError("grids of different make can't be merged")
    by = ["row", "col", "bucket"] if a.kind == "cell" else ["row", "col"]
    registers = a.registers.unionByName(b.registers).groupBy(*by).agg(F.max("rank").alias("rank"))
    labels = None
    if a.labels is not None and b.labels is not None:
        labels = a.labels.unionByName(b.labels).groupBy("row", "col").agg(best_label()).select("row", "col", F.col("best.label_key").alias("label_key"), (-F.col("best.low")).cast("tinyint").alias("level"))
    return replace(a, registers=registers, labels=labels)


# ---- shared-register grid


def shared_grid(pairs: DataFrame, depth: int = 512, width: int = 1024, labels: bool = True, hash: str = "fast", row_hash: str = "pair") -> Grid:
    """row_hash: what picks the row and the rank, "pair" or "item"."""
    text = pair_text() if row_hash == "pair" else F.col("item_key")
    h = hash52(text, "p" if row_hash == "pair" else "i", hash)
    rest = HASH_BITS - max(1, (depth - 1).bit_length())
    row = F.pmod(h, F.lit(depth)).cast("int")
    rank = (rest + 1 - bit_length(F.floor(h / depth).bitwiseAND(F.lit((1 << rest) - 1)))).cast("tinyint")
    slim = pairs.select("label_key", row.alias("row"), rank.alias("rank")).groupBy("label_key", "row").agg(F.max("rank").alias("rank"))
    placed = slim.withColumn("col", column_of(F.col("row"), width, hash))
    registers = placed.groupBy("row", "col").agg(F.max("rank").alias("rank"))
    held = None
    if labels:
        best = placed.withColumn("level", F.col("rank")).groupBy("row", "col").agg(best_label())
        held = best.select("row", "col", F.col("best.label_key").alias("label_key"), (-F.col("best.low")).cast("tinyint").alias("level"))
    return Grid(registers, held, depth, width, depth, hash, "shared")


def row_distribution(grid: Grid) -> DataFrame:
    """row, v, below, upto: the shares of the row's cells whose register is below v, and at most v, for every value v that occurs, 0 for untouched cells."""
    counts = grid.registers.groupBy("row", F.col("rank").cast("int").alias("v")).agg(F.count(F.lit(1)).alias("n"))
    used = counts.groupBy("row").agg(F.sum("n").alias("used"))
    empty = used.where(F.col("used") < grid.width).select("row", F.lit(0).alias("v"), (F.lit(grid.width) - F.col("used")).alias("n"))
    run = Window.partitionBy("row").orderBy("v").rowsBetween(Window.unboundedPreceding, 0)
    upto = F.sum("n").over(run)
    return counts.unionByName(empty).select("row", "v", ((upto - F.col("n")) / F.lit(float(grid.width))).alias("below"), (upto / F.lit(float(grid.width))).alias("upto"))


def vectors(grid: Grid, labels: DataFrame) -> DataFrame:
    """label_key, row, v, below, upto: a label's register in every row, beside the row's distribution there. The distribution of untouched rows is 1 at 0."""
    wanted = labels.select("label_key").distinct().withColumn("row", rows_of(grid.depth)).withColumn("col", column_of(F.col("row"), grid.width, grid.hash))
    # depth * width rows at most, whatever the data
    got = wanted.join(F.broadcast(grid.registers), ["row", "col"], "left").select("label_key", "row", F.coalesce(F.col("rank").cast("int"), F.lit(0)).alias("v"))
    return got.join(F.broadcast(row_distribution(grid)), ["row", "v"], "left").select("label_key", "row", "v", F.coalesce("below", F.lit(0.0)).alias("below"), F.coalesce("upto", F.lit(1.0)).alias("upto"))


def ladder(largest: float, step: float = LADDER_STEP) -> list[float]:
    """Candidate sizes: 0, then a geometric series."""
    out, n = [0.0], 1.0
    while n <= largest:
        out.append(n)
        n *= step
    return out


def log_likelihood(n: Column, depth: int) -> Column:
    """Of a register value v, if the label has n items over `depth` rows: the chance that the larger of its own part and the noise is v."""
    own = lambda v: F.exp(-n / depth * F.pow(F.lit(2.0), -v))
    upper = own(F.col("v")) * F.col("upto")
    lower = F.when(F.col("v") == 0, 0.0).otherwise(own(F.col("v") - 1) * F.col("below"))
    return F.ln(F.greatest(upper - lower, F.lit(TINY)))


def shared_estimate(grid: Grid, labels: DataFrame, solver: str = "ladder", step: float = LADDER_STEP, largest: float = 1e7) -> DataFrame:
    """label_key, estimate: the candidate of the greatest likelihood, the smallest of equals (ladder); or refined around it (newton)."""
    own = vectors(grid, labels)
    if solver == "ladder":
        rungs = F.explode(F.array(*map(F.lit, ladder(largest, step)))).alias("n")
        # equal observations of a label are scored once
        seen = own.groupBy("label_key", "v", "below", "upto").agg(F.count(F.lit(1)).alias("k"))
        scored = seen.select("*", rungs).groupBy("label_key", "n").agg(F.sum(F.col("k") * log_likelihood(F.col("n"), grid.depth)).alias("score"))
        return scored.groupBy("label_key").agg(F.min(F.struct((-F.round("score", 6)).alias("low"), "n")).alias("best")).select("label_key", F.col("best.n").alias("estimate"))
    if solver != "newton":
        raise ValueError("solver must be ladder or newton")
    lists = own.groupBy("label_key").agg(F.collect_list(F.struct("v", "below", "upto")).alias("rows"))  # depth rows each
    depth = grid.depth

    def run(batches):
        import numpy as np
        import pyarrow as pa

        rungs = np.array(ladder(largest, step))
        for b in batches:
            out = []
            for rows in b.column(1).to_pylist():
                v, below, upto = (np.array([r[x] for r in rows], float) for x in ("v", "below", "upto"))

                def score(n, v=v, below=below, upto=upto):
                    n = np.atleast_1d(n)[:, None]
                    up = np.exp(-n / depth * 2.0**-v) * upto
                    low = np.where(v == 0, 0.0, np.exp(-n / depth * 2.0 ** (1 - v)) * below)
                    return np.log(np.maximum(up - low, TINY)).sum(axis=1)

                coarse = rungs[::16]
                i = int(score(coarse).argmax())
                lo, hi = coarse[max(0, i - 1)], coarse[min(len(coarse) - 1, i + 1)]
                for _ in range(12):  # the likelihood has one hill between these
                    grid_ = np.linspace(lo, hi, 9)
                    j = int(score(grid_).argmax())
                    lo, hi = grid_[max(0, j - 1)], grid_[min(8, j + 1)]
                out.append(float((lo + hi) / 2) if hi > 0.5 else 0.0)
            yield pa.RecordBatch.from_pydict({"label_key": b.column(0), "estimate": out})

    return lists.mapInArrow(run, "label_key string, estimate double")


def shared_top_k(grid: Grid, k: int, solver: str = "newton", **options) -> DataFrame:
    """The k largest of all labels that the cells hold."""
    if grid.labels is None:
        raise ValueError("a grid without labels can only be asked for given labels")
    return shared_estimate(grid, grid.labels, solver, **options).orderBy(F.desc("estimate"), "label_key").limit(k)
