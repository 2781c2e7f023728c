"""The library's queries, each with its SQL twin where SQL can say it. A query takes (spark, directory) and gives a DataFrame."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tallywalk.functions import bounds, sqlapi
from tallywalk.functions.hashing import draw, gate_pass_probability, hash52
from tallywalk.functions.registers import estimate_registers
from tallywalk.operators import exact, grids, neighbours
from tallywalk.operators.sketches import Sketches, build_sketch, estimate, merge_pair, merge_sketches, over, reached, recount, roll_up, top_k
from tallywalk.plans import experiments, metrics, twins
from tallywalk.sources.pairs import LINE_ORDER, WORKLOADS, insert_only, pairs, table, word_pairs
from tallywalk.sources.shared import fresh_folder
from tallywalk.streaming import panes

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
WALKS = ("offset", "recycled", "gated_eager", "gated")


def query(name: str, oracle: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return keep


def r6(*names: str) -> list:
    return [F.round(F.col(n), 6).alias(n) for n in names]


def values(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def roomy(p: DataFrame, least: int) -> int:
    """Room for so many counters at least, and for one of every label of the table, however large it is."""
    return max(least, exact.label_count(p))


# ---- exact answers (and the data's statistics)

TOPS = {"words": "word_docs", "docs": "doc_words", "suppliers": "supplier_parts", "customers": "customer_parts", "hosts": "host_urls", "event_types": "event_users", "days": "day_parts", "conversation_words": "word_conversations", "parts": "part_customers", "event_keys": "event_key_users"}
for _name, _load in TOPS.items():
    query(f"exact_top_{_name}", f"{twins.sizes(twins.PAIRS[_load])} ORDER BY d DESC, label_key LIMIT 100")(lambda spark, d, load=_load: exact.exact_top_k(WORKLOADS[load](spark, d), 100))


@query("exact_over_threshold", f"SELECT * FROM ({twins.sizes(twins.PAIRS['word_docs'])}) WHERE d >= 20")
def exact_over_threshold(spark: SparkSession, d: str) -> DataFrame:
    return exact.exact_sizes(WORKLOADS["word_docs"](spark, d)).where("d >= 20")


@query("exact_over_fraction", f"SELECT * FROM ({twins.sizes(twins.PAIRS['customer_parts'])}) WHERE d >= (SELECT count(*) FROM {twins.JOINED}) / 1000.0")
def exact_over_fraction(spark: SparkSession, d: str) -> DataFrame:
    p = WORKLOADS["customer_parts"](spark, d)
    n = p.agg(F.count(F.lit(1)).alias("entries"))
    return exact.exact_sizes(p).join(F.broadcast(n)).where(F.col("d") >= F.col("entries") / 1000.0).drop("entries")


for _w, _load in {"w1": "doc_words", "w2": "word_docs", "w3": "word_conversations", "w4": "customer_parts", "w5": "supplier_parts"}.items():
    _p = twins.PAIRS[_load]
    _o = f"""WITH p AS MATERIALIZED ({_p}), z AS (SELECT label_key, count(*) AS entries, count(DISTINCT item_key) AS d FROM p GROUP BY label_key), k AS (SELECT *, row_number() OVER (ORDER BY d DESC, label_key) AS place FROM z)
        SELECT CAST(sum(entries) AS BIGINT) AS entries, count(*) AS labels, CAST(sum(d) AS BIGINT) AS pairs, (SELECT count(DISTINCT item_key) FROM p) AS items, round(avg(d), 6) AS mean_d, quantile_cont(d, 0.5) AS p50, round(quantile_cont(d, 0.9), 6) AS p90,
        round(quantile_cont(d, 0.99), 6) AS p99, max(d) AS max_d, round(sum(d) / sum(entries), 6) AS unique_share, round(sum(entries) FILTER (place <= 100) / sum(entries), 6) AS top100_share, round(sum(entries) FILTER (place <= 1000) / sum(entries), 6) AS top1000_share FROM k"""
    query(f"sizes_profile_{_w}", _o)(lambda spark, d, load=_load: metrics.describe_pairs(WORKLOADS[load](spark, d)).select("entries", "labels", "items", "pairs", "p50", "max_d", *r6("mean_d", "p90", "p99", "unique_share", "top100_share", "top1000_share")))

for _k in metrics.KS:
    query(f"true_heavy_{_k}", f"SELECT label_key, d FROM ({twins.sizes(twins.PAIRS['word_docs'])}) ORDER BY d DESC, label_key LIMIT {_k}")(lambda spark, d, k=_k: metrics.true_heavy(exact.exact_sizes(WORKLOADS["word_docs"](spark, d)), k))


@query("heavy_entries_exact", "SELECT CAST(l_partkey AS VARCHAR) AS label_key, count(*) AS entries FROM lineitem GROUP BY 1 ORDER BY entries DESC, label_key LIMIT 100")
def heavy_entries_exact(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "lineitem").select(F.col("l_partkey").cast("string").alias("label_key"))
    return p.groupBy("label_key").agg(F.count(F.lit(1)).alias("entries")).orderBy(F.desc("entries"), "label_key").limit(100)


@query("heavy_entries_roomy", "SELECT CAST(l_suppkey AS VARCHAR) AS label_key, count(*) AS entries FROM lineitem GROUP BY 1")
def heavy_entries_roomy(spark: SparkSession, d: str) -> DataFrame:
    """With a counter for each label the plain walk is exact."""
    p = WORKLOADS["supplier_parts"](spark, d)
    return exact.heavy_entries(p, roomy(p, 5000))


@query("distinct_single_set", "SELECT count(DISTINCT l_partkey) AS d FROM lineitem")
def distinct_single_set(spark: SparkSession, d: str) -> DataFrame:
    return exact.distinct_count(table(spark, d, "lineitem"), "l_partkey", exact=True)


# ---- registers, hashes and the gate

M = 256
_regs = twins.registers(twins.LINES, M)


@query("registers_per_label", f"SELECT label_key, CAST(bucket AS INTEGER) AS bucket, CAST(rank AS INTEGER) AS rank FROM ({_regs})")
def registers_per_label(spark: SparkSession, d: str) -> DataFrame:
    return exact.label_registers(WORKLOADS["supplier_parts"](spark, d), M).select("label_key", "bucket", F.col("rank").cast("int").alias("rank"))


for _form, _sql in {"histogram": twins.histogram, "classic": twins.classic}.items():
    query(f"{_form}_estimate_per_label", f"SELECT label_key, round(estimate, 6) AS estimate FROM ({twins.estimates(_regs, M, form=_sql)})")(
        lambda spark, d, form=_form: exact.register_estimates(exact.label_registers(WORKLOADS["supplier_parts"](spark, d), M), M, form).select("label_key", *r6("estimate"))
    )

_month = "strftime(l_shipdate, '%Y-%m')"


@query("label_sketch_union_by_month", f"SELECT label_key, round(estimate, 6) AS estimate FROM ({twins.estimates(_regs, M)})")
def label_sketch_union_by_month(spark: SparkSession, d: str) -> DataFrame:
    """Registers of each month, then of the whole time from these alone."""
    lines = table(spark, d, "lineitem")
    p = pairs(lines, "l_suppkey", "l_partkey", source=F.date_format("l_shipdate", "yyyy-MM"))
    months = exact.label_registers(p, M, by=["source"])
    whole = months.groupBy("label_key", "bucket").agg(F.max("rank").alias("rank"))
    return exact.register_estimates(whole, M).select("label_key", *r6("estimate"))


@query("min_hash_inverse", f"SELECT label_key, round(max({twins.draw()}), 6) AS estimate FROM ({twins.LINES}) GROUP BY label_key")
def min_hash_inverse(spark: SparkSession, d: str) -> DataFrame:
    return exact.inverse_min_hash(WORKLOADS["supplier_parts"](spark, d)).select("label_key", *r6("estimate"))


@query("gate_survivors", f"SELECT label_key, item_key, count(*) AS entries FROM ({twins.LINES}) WHERE {twins.draw()} > 50 GROUP BY ALL")
def gate_survivors(spark: SparkSession, d: str) -> DataFrame:
    """What a gate at a fixed floor lets through."""
    p = WORKLOADS["supplier_parts"](spark, d).where(draw(hash52(F.col("item_key"), "g")) > 50)
    return p.groupBy("label_key", "item_key").agg(F.count(F.lit(1)).alias("entries"))


@query("gate_pass_rates", f"SELECT a, round(1.0 / a, 6) AS expected, round(count(*) FILTER ({twins.draw()} > a) / count(*), 6) AS observed FROM (SELECT DISTINCT item_key FROM ({twins.LINES})), (SELECT unnest([2.0, 5.0, 10.0, 50.0, 100.0]) AS a) GROUP BY a")
def gate_pass_rates(spark: SparkSession, d: str) -> DataFrame:
    items = WORKLOADS["supplier_parts"](spark, d).select("item_key").distinct().withColumn("draw", draw(hash52(F.col("item_key"), "g")))
    a = F.explode(F.array(*map(F.lit, (2.0, 5.0, 10.0, 50.0, 100.0)))).alias("a")
    rows = items.select("draw", a).groupBy("a").agg((F.count_if(F.col("draw") > F.col("a")) / F.count(F.lit(1))).alias("observed"))
    return rows.select("a", F.round(gate_pass_probability(F.col("a")), 6).alias("expected"), *r6("observed"))


# ---- walks and merges over all of lineitem, exact counters

S = 8


def lines(spark: SparkSession, d: str, parts: int = 1) -> DataFrame:
    """All lines in the stream's order; source: which of so many equal ranges of order keys a line is in (lines without a key are in the first)."""
    rows = table(spark, d, "lineitem")
    low, high = rows.agg(F.min("l_orderkey"), F.max("l_orderkey")).first() if parts > 1 else (None, None)
    part = F.lit(0) if low is None else F.coalesce(F.floor((F.col("l_orderkey") - low) * parts / (high - low + 1)), F.lit(0))
    return pairs(rows, "l_suppkey", "l_partkey", order_by=LINE_ORDER, source=part)


def walked(p: DataFrame, kind: str, streams: str | int = 1, contents: bool = True) -> Sketches:
    return build_sketch(p, kind=kind, s=S, counter="exact", streams=streams, hash="portable", contents=contents)


def differing(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: how many rows are in one of the tables only, repeats counted. Each table is read once."""
    both = a.withColumn("__side", F.lit(1)).unionByName(b.withColumn("__side", F.lit(-1)))
    return both.groupBy(*a.columns).agg(F.abs(F.sum("__side")).alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("differences"))


def in_ranges(spark: SparkSession, d: str, kind: str, parts: int) -> Sketches:
    return walked(lines(spark, d, parts), kind, "by_source")


def merged_pair(spark: SparkSession, d: str, kind: str) -> DataFrame:
    p = lines(spark, d, 2)
    return merge_pair(*(walked(p.where(F.col("source") == i), kind) for i in ("0", "1"))).counters


def walks_sql(kind: str, parts: int = 1) -> str:
    """CTEs a, b and so on, one for each range of order keys."""
    return "WITH " + ", ".join(twins.walk(n, twins.stream(i, parts), kind, S) for i, n in enumerate("abce"[:parts]))


SLOTS = 'SELECT CAST(slot AS INTEGER) AS slot, label_key, CAST("offset" AS DOUBLE) AS "offset", estimate'
SLOT = "SELECT CAST(slot AS INTEGER) AS slot, label_key, estimate"
for _kind in WALKS:
    query(f"walk_{_kind}", f"{walks_sql(_kind)} {SLOTS} FROM a")(lambda spark, d, kind=_kind: walked(lines(spark, d), kind, contents=False).counters.select("slot", "label_key", "offset", "estimate"))
    query(f"walk_{_kind}_point_query", f"{walks_sql(_kind)} SELECT label_key, a.estimate IS NOT NULL AS member, coalesce(a.estimate, (SELECT min(estimate) FROM a)) AS estimate FROM (SELECT DISTINCT CAST(label AS VARCHAR) AS label_key FROM a_in) LEFT JOIN a USING (label_key)")(
        lambda spark, d, kind=_kind: estimate(walked(lines(spark, d), kind, contents=False), lines(spark, d).select("label_key").distinct())
    )


@query("walk_gated_top_3", f"{walks_sql('gated')} SELECT label_key, estimate, CAST(row_number() OVER (ORDER BY estimate DESC, label_key) AS INTEGER) AS rank FROM a QUALIFY rank <= 3")
def walk_gated_top_3(spark: SparkSession, d: str) -> DataFrame:
    return top_k(walked(lines(spark, d), "gated", contents=False), 3)


@query("walk_gated_over_threshold", f"{walks_sql('gated')} SELECT label_key, estimate FROM a WHERE estimate >= 30")
def walk_gated_over_threshold(spark: SparkSession, d: str) -> DataFrame:
    return over(walked(lines(spark, d), "gated", contents=False), threshold=30).select("label_key", "estimate")


@query("walk_offset_over_fraction", f"{walks_sql('offset')} SELECT label_key, estimate, estimate >= (SELECT count(*) FROM a_in) * 0.125 AS reported FROM a")
def walk_offset_over_fraction(spark: SparkSession, d: str) -> DataFrame:
    """Every member, and whether it is over the fraction."""
    return reached(walked(lines(spark, d), "offset", contents=False), fraction=0.125).drop("sketch_id")


for _load in ("word_docs", "customer_parts"):

    @query(f"gated_equals_eager_{_load}", "SELECT CAST(0 AS BIGINT) AS differences")
    def gated_equals_eager(spark: SparkSession, d: str, load: str = _load) -> DataFrame:
        p = WORKLOADS[load](spark, d)
        a, b = (build_sketch(p, kind=k, s=200, m=64, streams=1).counters.select("slot", "label_key", "registers") for k in ("gated", "gated_eager"))
        return differing(a, b)


query("merge_pair_gated", f"{walks_sql('gated', 2)} {SLOT} FROM ({twins.union_of(['a', 'b'], S)})")(lambda spark, d: merged_pair(spark, d, "gated").select("slot", "label_key", "estimate"))
query("merge_offset", f"{walks_sql('offset', 2)} {SLOTS} FROM ({twins.union_of(['a', 'b'], S)})")(lambda spark, d: merged_pair(spark, d, "offset").select("slot", "label_key", "offset", "estimate"))
query("merge_flat", f"{walks_sql('gated', 4)} {SLOT} FROM ({twins.union_of(['a', 'b', 'c', 'e'], S)})")(lambda spark, d: merge_sketches(in_ranges(spark, d, "gated", 4)).counters.select("slot", "label_key", "estimate"))
query("merge_tree", f"{walks_sql('gated', 4)}, ab AS ({twins.union_of(['a', 'b'], S)}), ce AS ({twins.union_of(['c', 'e'], S)}) {SLOT} FROM ({twins.union_of(['ab', 'ce'], S)})")(
    lambda spark, d: merge_sketches(in_ranges(spark, d, "gated", 4), mode="tree", fan_in=2).counters.select("slot", "label_key", "estimate")
)


@query("merge_offset_floors")
def merge_offset_floors(spark: SparkSession, d: str) -> DataFrame:
    """Offset walks whose merge stays an upper bound: every true size is at most the value."""
    sk = merge_sketches(in_ranges(spark, d, "offset", 4), absent_offset="floor")
    return sk.counters.select("label_key", "offset", "estimate").join(exact.exact_sizes(lines(spark, d)), "label_key")


@query("walk_gated_on_pairs")
def walk_gated_on_pairs(spark: SparkSession, d: str) -> DataFrame:
    """The gate drawn for pairs, not for items alone."""
    return build_sketch(lines(spark, d), s=S, counter="exact", streams=1, hash="portable", gate_on="pair").counters.select("slot", "label_key", "estimate")


_event_regs = twins.registers(f"SELECT * EXCLUDE ts, strftime(date_trunc('day', ts), '%Y-%m-%d 00:00:00') AS pane FROM ({twins.PAIRS['event_users']})", 64, "pane, label_key")


@query("roll_up_days", f"SELECT pane, label_key, round(estimate, 6) AS estimate FROM ({twins.estimates(_event_regs, 64, 'pane, label_key')})")
def roll_up_days(spark: SparkSession, d: str) -> DataFrame:
    """Hourly sketches with room for all labels, merged to days: the registers of the days."""
    hours = panes.pane_sketches(WORKLOADS["event_users"](spark, d), "1 hour", s=50, m=64, hash="portable")
    return roll_up(hours, "1 day").counters.select(F.col("sketch_id").alias("pane"), "label_key", *r6("estimate"))


for _kind in WALKS:

    @query(f"walk_{_kind}_unbounded", f"SELECT label_key, round(estimate, 6) AS estimate FROM ({twins.estimates(_regs, M)})")
    def walk_unbounded(spark: SparkSession, d: str, kind: str = _kind) -> DataFrame:
        """With a counter for each label no walk drops one, so labels may be dealt to many tasks."""
        p = WORKLOADS["supplier_parts"](spark, d)
        return build_sketch(p, kind=kind, s=roomy(p, 2000), m=M, streams="by_label", hash="portable").counters.select("label_key", *r6("estimate"))


# ---- tight cases and worked scenarios


@query("tight_single_label", "SELECT 'a' AS label_key, CAST(500 AS DOUBLE) AS estimate")
def tight_single_label(spark: SparkSession, d: str) -> DataFrame:
    p = pairs(spark.range(500).select(F.lit("a").alias("l"), "id"), "l", "id", order_by=["id"])
    return build_sketch(p, s=3, counter="exact", streams=1).counters.select("label_key", "estimate")


@query("tight_cycle_recycled", "SELECT CAST(unnest([0, 1, 2]) AS INTEGER) AS slot, CAST(1 AS DOUBLE) AS estimate")
def tight_cycle(spark: SparkSession, d: str, kind: str = "recycled") -> DataFrame:
    """Four labels in turn with one item, room for three."""
    p = pairs(spark.range(12).select((F.col("id") % 4).alias("l"), F.lit("one").alias("i"), "id"), "l", "i", order_by=["id"])
    return build_sketch(p, kind=kind, s=3, counter="exact", streams=1).counters.select("slot", "estimate")


def in_turn(rows: DataFrame, key: str, labels: int) -> DataFrame:
    """Rows dealt to so many labels in turn, in the order of an integer key without repeats. The rows before a range of keys are counted, so that no task numbers the whole table."""
    span = 1 << 16
    cut = rows.where(F.col(key).isNotNull()).select(F.col(key).cast("bigint").alias("k")).withColumn("range", F.floor(F.col("k") / span))
    sizes = cut.groupBy("range").agg(F.count(F.lit(1)).alias("n"))
    # one row for 65,536 keys
    starts = sizes.select("range", (F.sum("n").over(Window.orderBy("range")) - F.col("n")).alias("before"))
    numbered = cut.join(F.broadcast(starts), "range").withColumn("n", F.col("before") + F.row_number().over(Window.partitionBy("range").orderBy("k")) - 1)
    return numbered.select((F.col("n") % labels).alias("l"), F.lit("one").alias("i"), "k")


for _kind in ("offset", "gated"):

    @query(f"tight_cycle_{_kind}", f"SELECT CAST(j AS INTEGER) AS slot, CAST({'ceil((n - j) / 3.0)' if _kind == 'offset' else 1} AS DOUBLE) AS estimate FROM (SELECT count(event_id) AS n FROM events), (SELECT unnest(range(3)) AS j) WHERE j < n")
    def tight_cycle_of_events(spark: SparkSession, d: str, kind: str = _kind) -> DataFrame:
        """All events, dealt to four labels in turn with one item, room for three: the offset walk's values add up to the entries, the others' stay 1."""
        p = pairs(in_turn(table(spark, d, "events"), "event_id", 4), "l", "i", order_by=["k"])
        return build_sketch(p, kind=kind, s=3, counter="exact", streams=1, contents=False).counters.select("slot", "estimate")


SCENARIOS = "day_parts"


def placed(spark: SparkSession, d: str) -> DataFrame:
    """label_key, d, place of the days by their distinct parts; those after the 30th share place 31."""
    sizes = exact.exact_sizes(WORKLOADS[SCENARIOS](spark, d))
    # 30 rows
    first = metrics.true_heavy(sizes, 30).select("label_key", F.row_number().over(Window.orderBy(F.desc("d"), "label_key")).alias("place"))
    return sizes.join(F.broadcast(first), "label_key", "left").select("label_key", "d", F.coalesce("place", F.lit(31)).alias("place"))


_placed = f"SELECT *, least(31, row_number() OVER (ORDER BY d DESC, label_key)) AS place FROM ({twins.sizes(twins.PAIRS[SCENARIOS])})"


def scenario_one(spark: SparkSession, d: str, ties_first: bool) -> tuple[DataFrame, DataFrame]:
    """The ten largest labels answered rightly, and all others with ten times the largest size. Names decide which of the equals come first: those after the 20th, or the second ten."""
    base = placed(spark, d)
    tie = F.when(F.col("place") <= 10, 0).when((F.col("place") > 20) == F.lit(ties_first), 1).otherwise(2)
    base = base.withColumn("label_key", F.concat_ws("-", tie.cast("string"), "label_key"))
    most = base.agg(F.max("d").alias("most"))
    answer = base.crossJoin(F.broadcast(most)).select("label_key", F.when(F.col("place") <= 10, F.col("d")).otherwise(10 * F.col("most")).cast("double").alias("estimate"))
    return answer, base.select("label_key", "d")


def scenario_one_sql(first: str, columns: str) -> str:
    """e: the error over the ten reported labels."""
    reported = f"SELECT d FROM placed WHERE place > 10 ORDER BY CASE WHEN {first} THEN 0 ELSE 1 END, label_key LIMIT 10"
    return f"WITH placed AS MATERIALIZED ({_placed}), e AS (SELECT sum(10 * (SELECT max(d) FROM placed) - d) / sum(d) AS e FROM ({reported})), t AS (SELECT sum(abs(d - estimate)) / sum(d) AS t FROM (SELECT d, CASE WHEN place <= 10 THEN d ELSE 10 * (SELECT max(d) FROM placed) END AS estimate FROM placed ORDER BY d DESC, place LIMIT 10)) SELECT {columns} FROM e, t"


def scored_row(answer: DataFrame, truth: DataFrame, k: int, *columns: str) -> DataFrame:
    return metrics.score(answer, truth, k).select(*r6(*columns))


_one_sql = "round(e, 6) AS nae_reported, round(sqrt((t * t + e * e) / 2), 6) AS q"


@query("scenario_one_true", scenario_one_sql("place > 20", "round(t, 6) AS nae_true"))
def scenario_one_true(spark: SparkSession, d: str) -> DataFrame:
    return scored_row(*scenario_one(spark, d, True), 10, "nae_true")


@query("scenario_one_reported", scenario_one_sql("place > 20", _one_sql))
def scenario_one_reported(spark: SparkSession, d: str) -> DataFrame:
    return scored_row(*scenario_one(spark, d, True), 10, "nae_reported", "q")


@query("scenario_one_other_ties", scenario_one_sql("place BETWEEN 11 AND 20", _one_sql))
def scenario_one_other_ties(spark: SparkSession, d: str) -> DataFrame:
    return scored_row(*scenario_one(spark, d, False), 10, "nae_reported", "q")


def scenario_two(spark: SparkSession, d: str, known: str) -> tuple[DataFrame, DataFrame]:
    """Twenty of the thirty largest labels answered rightly, and all others with 0."""
    base = placed(spark, d)
    return base.select("label_key", F.when(F.expr(known), F.col("d").cast("double")).otherwise(0.0).alias("estimate")), base.select("label_key", "d")


for _name, _known in (("first", "place <= 10 or place between 21 and 30"), ("second", "place between 11 and 30")):
    query(
        f"scenario_two_{_name}",
        f"SELECT CAST(0 AS DOUBLE) AS nae_reported, round(e, 6) AS nae_true, round(e / sqrt(2.0), 6) AS q FROM (SELECT sum(d) FILTER (NOT ({_known})) / sum(d) AS e FROM ({_placed}) WHERE place <= 20)",
    )(lambda spark, d, known=_known: scored_row(*scenario_two(spark, d, known), 20, "nae_reported", "nae_true", "q"))

# ---- grids

DEPTH, WIDTH, CELL = 4, 64, 64
_cell = twins.cell_registers(twins.LINES, DEPTH, WIDTH, CELL)
_cell_labels = twins.cell_labels(twins.LINES, DEPTH, WIDTH, CELL)


def small_cells(spark: SparkSession, d: str, p: DataFrame | None = None, m: int = CELL) -> grids.Grid:
    return grids.cell_grid(WORKLOADS["supplier_parts"](spark, d) if p is None else p, DEPTH, WIDTH, m, hash="portable")


def ints(*names: str) -> list:
    """Columns as they are, and the last one as int."""
    return [*names[:-1], F.col(names[-1]).cast("int").alias(names[-1])]


REG_INTS = ("row", "col", "bucket", "rank")


def reg_sql(sql: str, bucket: bool = True) -> str:
    return f"SELECT CAST(row AS INTEGER) AS row, CAST(col AS INTEGER) AS col, {'CAST(bucket AS INTEGER) AS bucket, ' if bucket else ''}CAST(rank AS INTEGER) AS rank FROM ({sql})"


def label_sql(sql: str) -> str:
    return f"SELECT CAST(row AS INTEGER) AS row, CAST(col AS INTEGER) AS col, label_key, CAST(level AS INTEGER) AS level FROM ({sql})"


LABEL_INTS = ("row", "col", "label_key", "level")

query("cell_grid_registers", reg_sql(_cell))(lambda spark, d: small_cells(spark, d).registers.select(*ints(*REG_INTS)))
query("cell_grid_labels", label_sql(_cell_labels))(lambda spark, d: small_cells(spark, d).labels.select(*ints(*LABEL_INTS)))
_all_est = twins.cell_estimates(_cell, twins.LINES, DEPTH, WIDTH, CELL)
query("cell_grid_estimates", f"SELECT label_key, round(estimate, 6) AS estimate FROM ({_all_est})")(lambda spark, d: grids.grid_estimate(small_cells(spark, d), WORKLOADS["supplier_parts"](spark, d)).select("label_key", *r6("estimate")))
_top_est = twins.cell_estimates(_cell, _cell_labels, DEPTH, WIDTH, CELL)
query("cell_grid_top_k", f"SELECT label_key, round(estimate, 6) AS estimate FROM ({_top_est}) ORDER BY estimate DESC, label_key LIMIT 20")(
    lambda spark, d: grids.grid_estimate(small_cells(spark, d), small_cells(spark, d).labels).select("label_key", *r6("estimate")).orderBy(F.desc("estimate"), "label_key").limit(20)
)


def halves(spark: SparkSession, d: str) -> list[DataFrame]:
    lines = table(spark, d, "lineitem")
    return [pairs(lines.where(F.col("l_orderkey") % 2 == i), "l_suppkey", "l_partkey") for i in (0, 1)]


query("cell_grid_merge", reg_sql(_cell))(lambda spark, d: grids.merge_grids(*(small_cells(spark, d, p) for p in halves(spark, d))).registers.select(*ints(*REG_INTS)))
query("cell_grid_merge_labels", label_sql(_cell_labels))(lambda spark, d: grids.merge_grids(*(small_cells(spark, d, p) for p in halves(spark, d))).labels.select(*ints(*LABEL_INTS)))
_cell438 = twins.cell_registers(twins.LINES, DEPTH, WIDTH, 438)
query("cell_grid_m438", f"SELECT label_key, round(estimate, 6) AS estimate FROM ({twins.cell_estimates(_cell438, twins.LINES, DEPTH, WIDTH, 438)})")(
    lambda spark, d: grids.grid_estimate(small_cells(spark, d, m=438), WORKLOADS["supplier_parts"](spark, d)).select("label_key", *r6("estimate"))
)

SDEPTH, SWIDTH, STEP, LARGEST = 64, 32, 1.1, 1e5
_shared = twins.shared_registers(twins.LINES, SDEPTH, SWIDTH)


def small_shared(spark: SparkSession, d: str, p: DataFrame | None = None, labels: bool = True) -> grids.Grid:
    return grids.shared_grid(WORKLOADS["supplier_parts"](spark, d) if p is None else p, SDEPTH, SWIDTH, labels, hash="portable")


SHARED_INTS = ("row", "col", "rank")
query("shared_grid_registers", reg_sql(_shared, bucket=False))(lambda spark, d: small_shared(spark, d, labels=False).registers.select(*ints(*SHARED_INTS)))
query("shared_grid_labels", label_sql(twins.shared_labels(twins.LINES, SDEPTH, SWIDTH)))(lambda spark, d: small_shared(spark, d).labels.select(*ints(*LABEL_INTS)))
query("shared_grid_row_distribution", f"SELECT CAST(row AS INTEGER) AS row, v, round(below, 6) AS below, round(upto, 6) AS upto FROM ({twins.distribution(_shared, SWIDTH)})")(
    lambda spark, d: grids.row_distribution(small_shared(spark, d)).select("row", "v", *r6("below", "upto"))
)
_shared_est = twins.shared_estimates(_shared, twins.LINES, SDEPTH, SWIDTH, STEP, LARGEST)
query("shared_grid_ladder_estimate", f"SELECT label_key, round(estimate, 6) AS estimate FROM ({_shared_est})")(
    lambda spark, d: grids.shared_estimate(small_shared(spark, d), WORKLOADS["supplier_parts"](spark, d), "ladder", STEP, LARGEST).select("label_key", *r6("estimate"))
)
_shared_top = twins.shared_estimates(_shared, twins.shared_labels(twins.LINES, SDEPTH, SWIDTH), SDEPTH, SWIDTH, STEP, LARGEST)
query("shared_grid_top_k", f"SELECT label_key, round(estimate, 6) AS estimate FROM ({_shared_top}) ORDER BY estimate DESC, label_key LIMIT 20")(
    lambda spark, d: grids.shared_top_k(small_shared(spark, d), 20, "ladder", step=STEP, largest=LARGEST).select("label_key", *r6("estimate"))
)
query("shared_grid_merge", reg_sql(_shared, bucket=False))(lambda spark, d: grids.merge_grids(*(small_shared(spark, d, p) for p in halves(spark, d))).registers.select(*ints(*SHARED_INTS)))
query("shared_grid_newton_top_k")(lambda spark, d: grids.shared_top_k(small_shared(spark, d), 20, "newton", largest=LARGEST))

# ---- other baselines

_rate_hash = twins.h(twins.PAIR, "p")


@query("sampled_pairs_estimate", f"SELECT label_key, count(DISTINCT item_key) / 0.25 AS estimate FROM ({twins.PAIRS['customer_parts']}) WHERE {_rate_hash} < {int(0.25 * (1 << 52))} GROUP BY label_key")
def sampled_pairs_estimate(spark: SparkSession, d: str) -> DataFrame:
    return exact.sampled_pairs(WORKLOADS["customer_parts"](spark, d), 0.25, hash="portable")


query("sampled_sketch_top")(lambda spark, d: top_k(exact.sampled_sketch(WORKLOADS["customer_parts"](spark, d), 200, 0.5, m=64, streams=1), 20))
query("jvm_label_sketch")(lambda spark, d: exact.per_label_sketch(WORKLOADS["supplier_parts"](spark, d)))
query("approx_distinct_label")(lambda spark, d: exact.approx_distinct(WORKLOADS["supplier_parts"](spark, d)))
query("heavy_entries_bounded")(lambda spark, d: exact.heavy_entries(WORKLOADS["part_customers"](spark, d), 100))


@query("zero_answer_scores", "SELECT CAST(unnest([10, 100, 1000]) AS INTEGER) AS k, 1.0::DOUBLE AS nae_true, 1.0::DOUBLE AS nrse_true, 1.0::DOUBLE AS rmae_true")
def zero_answer_scores(spark: SparkSession, d: str) -> DataFrame:
    truth = exact.exact_sizes(WORKLOADS["word_docs"](spark, d))
    parts = [metrics.score(exact.zero_answer(truth), truth, k).select("k", "nae_true", "nrse_true", "rmae_true") for k in metrics.KS]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


# ---- measures, with the cell grid as the contender

_w3 = twins.PAIRS["word_conversations"]
MWIDTH = 512
_w3_labels = twins.cell_labels(_w3, DEPTH, MWIDTH, CELL)
_answer = f"SELECT label_key, round(estimate, 6) AS estimate FROM ({twins.cell_estimates(twins.cell_registers(_w3, DEPTH, MWIDTH, CELL), _w3_labels, DEPTH, MWIDTH, CELL)})"
_scored = {k: twins.score_columns(twins.sizes(_w3), _answer, k) for k in (10, 100)}


def contender(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    p = WORKLOADS["word_conversations"](spark, d)
    g = grids.cell_grid(p, DEPTH, MWIDTH, CELL, hash="portable")
    return grids.grid_estimate(g, g.labels).select("label_key", *r6("estimate")), exact.exact_sizes(p)


def measure_sql(k: int, measure: str, q: bool) -> str:
    body = twins.MEASURES[measure]
    both = f"(SELECT {body} AS t FROM on_true), (SELECT {body} AS r FROM on_reported)"
    q_col = ", round(sqrt((t * t + r * r) / 2), 5) AS q" if q else ""
    return f"WITH {_scored[k]} SELECT CAST({k} AS INTEGER) AS k, round(t, 5) AS on_true, round(r, 5) AS on_reported{q_col} FROM {both}"


def r5(column, name: str):
    return F.round(column, 5).alias(name)


for _m in twins.MEASURES:
    query(f"{_m}_table", measure_sql(100, _m, False))(lambda spark, d, m=_m: metrics.score(*contender(spark, d), 100, (m,) if m == "nae" else ("nae", m)).select("k", r5(F.col(f"{m}_true"), "on_true"), r5(F.col(f"{m}_reported"), "on_reported")))
query("q_table", measure_sql(10, "nae", True))(lambda spark, d: metrics.score(*contender(spark, d), 10, ("nae",)).select("k", r5(F.col("nae_true"), "on_true"), r5(F.col("nae_reported"), "on_reported"), r5(F.col("q"), "q")))
query("q_nrse_table", measure_sql(100, "nrse", True))(lambda spark, d: metrics.score(*contender(spark, d), 100, ("nae", "nrse")).select("k", r5(F.col("nrse_true"), "on_true"), r5(F.col("nrse_reported"), "on_reported"), r5(F.col("q_nrse"), "q")))
query("precision_recall_table", f"WITH {_scored[100]}, n AS (SELECT (SELECT count(*) FROM on_true) AS t, (SELECT count(*) FROM on_reported) AS r, (SELECT count(*) FROM on_true JOIN on_reported USING (label_key)) AS b) SELECT round(b / r, 6) AS precision, round(b / t, 6) AS recall, round(CASE WHEN b > 0 THEN 2.0 * b / (r + t) ELSE 0 END, 6) AS f1 FROM n")(
    lambda spark, d: metrics.score(*contender(spark, d), 100, ("nae",)).select(*r6("precision", "recall", "f1"))
)
query("nae_over_threshold", f"WITH {_scored[10]} SELECT round(sum(abs(d - coalesce(estimate, 0.0))) / sum(d), 5) AS nae, count(*) AS n FROM truth LEFT JOIN answer USING (label_key) WHERE d >= 10")(
    lambda spark, d: metrics.nae_over(*contender(spark, d), 10).select(r5(F.col("nae"), "nae"), "n")
)
query("label_errors", f"WITH {_scored[100]} SELECT label_key, round(abs(d - estimate), 6) AS absolute, round((estimate - d) / d, 6) AS relative, round(pow(estimate - d, 2), 4) AS squared FROM on_true")(
    lambda spark, d: (lambda a, t: metrics.errors(metrics.scored(metrics.true_heavy(t, 100), a, t)))(*contender(spark, d)).select("label_key", *r6("absolute", "relative"), F.round("squared", 4).alias("squared"))
)

# ---- bounds and sizes


_entries = f"(SELECT CAST(count(*) AS DOUBLE) AS n FROM ({twins.LINES}) WHERE label_key IS NOT NULL AND item_key IS NOT NULL)"
_s_and_eps = "(SELECT unnest([5.0, 100.0, 2000.0]) AS s), (SELECT unnest([0.0, 0.01, 0.1]) AS eps)"


def stream_bounds(spark: SparkSession, d: str) -> DataFrame:
    """s, eps, and n, the entries of the suppliers' stream, to which the walks' bounds are in proportion."""
    rows = values(spark, [(s, e) for s in (5.0, 100.0, 2000.0) for e in (0.0, 0.01, 0.1)], "s double, eps double")
    return rows.crossJoin(WORKLOADS["supplier_parts"](spark, d).agg(F.count(F.lit(1)).cast("double").alias("n")))


@query("bounds_plain", f"SELECT s, eps, round(n * (1 / s + (1 + 1 / s) * eps), 6) AS bound FROM {_entries}, {_s_and_eps}")
def bounds_plain(spark: SparkSession, d: str) -> DataFrame:
    return stream_bounds(spark, d).select("s", "eps", F.round(bounds.bound_plain(F.col("n"), F.col("s"), F.col("eps")), 6).alias("bound"))


@query("bounds_gated", f"SELECT s, eps, round(n / s * (1 + eps) + n * greatest((ln(1 / 0.01) - 1) * (1 + eps) / s, eps), 6) AS bound FROM {_entries}, {_s_and_eps}")
def bounds_gated(spark: SparkSession, d: str) -> DataFrame:
    return stream_bounds(spark, d).select("s", "eps", F.round(bounds.bound_gated(F.col("n"), F.col("s"), F.col("eps"), F.lit(0.01)), 6).alias("bound"))


_table3 = {64: 18289, 128: 13329, 256: 8642, 512: 5073, 1024: 2778, 2048: 1459, 4096: 748}


def labels_sql(load: str) -> str:
    return f"(SELECT count(DISTINCT label_key) AS labels FROM ({twins.PAIRS[load]}))"


def labels_of(spark: SparkSession, d: str, load: str) -> DataFrame:
    return WORKLOADS[load](spark, d).agg(F.count_distinct("label_key").alias("labels"))


@query("sizing_table3", f"SELECT m, s, labels, least(s, labels) AS held FROM ({' UNION ALL '.join(f'SELECT {m} AS m, CAST({s} AS BIGINT) AS s' for m, s in _table3.items())}), {labels_sql('supplier_parts')}")
def sizing_table3(spark: SparkSession, d: str) -> DataFrame:
    """Counters in 3 MiB, and how many of the suppliers they can hold."""
    rows = values(spark, [(m, bounds.size_for("gated", 3 * bounds.MIB, m)) for m in _table3], "m int, s bigint")
    return rows.crossJoin(labels_of(spark, d, "supplier_parts")).withColumn("held", F.least("s", "labels"))


STRUCTURES = {"gated": {"m": 1024}, "shared_grid": {"depth": 1024}, "cell_grid": {"m": 1024}}


def sizing_sql(load: str) -> str:
    each = " UNION ALL ".join(f"SELECT '{n}' AS method, CAST({b} AS BIGINT) AS b" for n, b in (("gated", 1132), ("shared_grid", 6144), ("cell_grid", 4528)))
    return f"SELECT method, round(labels * b / 1048576.0, 6) AS mib FROM ({each}), {labels_sql(load)}"


def sized(spark: SparkSession, d: str, load: str) -> DataFrame:
    """MiB of the structures with a counter, a column or a cell of each row for every label of the table."""
    rows = values(spark, [(n, bounds.bytes_of(n, 1, **o)) for n, o in STRUCTURES.items()], "method string, b bigint")
    return rows.crossJoin(labels_of(spark, d, load)).select("method", F.round(F.col("labels") * F.col("b") / float(bounds.MIB), 6).alias("mib"))


query("sizing_table2", sizing_sql("day_parts"))(lambda spark, d: sized(spark, d, "day_parts"))
query("sizing_overlap", sizing_sql("supplier_parts"))(lambda spark, d: sized(spark, d, "supplier_parts"))


# ---- event time

_ev = twins.PAIRS["event_users"]
_stamp = "'%Y-%m-%d %H:%M:%S'"


@query("event_panes_exact", f"SELECT strftime(date_trunc('hour', ts), {_stamp}) AS pane, label_key, count(DISTINCT item_key) AS d FROM ({_ev}) GROUP BY ALL")
def event_panes_exact(spark: SparkSession, d: str) -> DataFrame:
    return panes.pane_sizes(WORKLOADS["event_users"](spark, d), "1 hour")


@query("event_panes_sliding", f"SELECT strftime(date_trunc('hour', ts) - to_hours(back), {_stamp}) AS pane, label_key, count(DISTINCT item_key) AS d FROM ({_ev}), (SELECT CAST(unnest(range(6)) AS INTEGER) AS back) GROUP BY ALL")
def event_panes_sliding(spark: SparkSession, d: str) -> DataFrame:
    return panes.pane_sizes(WORKLOADS["event_users"](spark, d), "6 hours", "1 hour")


_pane_tops = f"SELECT pane, label_key, d, CAST(row_number() OVER (PARTITION BY pane ORDER BY d DESC, label_key) AS INTEGER) AS rank FROM (SELECT strftime(date_trunc('day', ts), {_stamp}) AS pane, label_key, count(DISTINCT item_key) AS d FROM ({twins.PAIRS['event_key_users']}) GROUP BY ALL) QUALIFY rank <= 3"


@query("event_pane_tops", _pane_tops)
def event_pane_tops(spark: SparkSession, d: str) -> DataFrame:
    return panes.ranks(panes.pane_sizes(WORKLOADS["event_key_users"](spark, d), "1 day"), 3)


@query("stream_vs_batch_top", _pane_tops)
def stream_vs_batch_top(spark: SparkSession, d: str) -> DataFrame:
    """The same from a replay of the events as a stream: walks by hour and micro-batch in a store, merged and rolled up to days. Exact, as there is a counter for every label."""
    events, folder = table(spark, d, "events"), fresh_folder(spark, "replay")
    rows = panes.event_stream(spark, f"{d}/event[s].parquet", events.schema)
    stream = panes.stream_pairs(rows, F.concat_ws(":", "event_type", F.get_json_object("props", "$.k")), "user_id")
    options = {"s": 1000, "m": 64, "counter": "exact"}
    panes.stream_sketches(stream, f"{folder}/store", f"{folder}/checkpoint", "1 hour", **options).awaitTermination()
    like = panes.pane_sketches(WORKLOADS["event_key_users"](spark, d).limit(0), "1 hour", **options)
    days = roll_up(panes.read_store(spark, f"{folder}/store", like), "1 day")
    return panes.ranks(days.counters.select(F.col("sketch_id").alias("pane"), "label_key", F.col("estimate").cast("bigint").alias("d")), 3)


@query("insert_only_events", twins.sizes(_ev))
def insert_only_events(spark: SparkSession, d: str) -> DataFrame:
    """Events as a change feed, where a delete would stop the query."""
    feed = table(spark, d, "events").withColumn("_change_type", F.lit("insert"))
    return exact.exact_sizes(pairs(insert_only(feed), "event_type", "user_id"))


@query(
    "event_sessions",
    f"""WITH e AS (SELECT label_key, item_key, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS fresh FROM ({_ev}) WINDOW w AS (PARTITION BY label_key ORDER BY ts)),
    g AS (SELECT *, sum(fresh) OVER (PARTITION BY label_key ORDER BY ts) AS session FROM e)
    SELECT label_key, strftime(min(ts), {_stamp}) AS start, count(*) AS entries, count(DISTINCT item_key) AS d FROM g GROUP BY label_key, session""",
)
def event_sessions(spark: SparkSession, d: str) -> DataFrame:
    return panes.session_sizes(WORKLOADS["event_users"](spark, d))


@query("latest_pane_as_of", f"SELECT strftime(report, {_stamp}) AS report, max(pane) AS pane FROM (SELECT DISTINCT date_trunc('day', ts) + INTERVAL 90 MINUTE AS report FROM ({_ev})), (SELECT DISTINCT strftime(date_trunc('hour', ts), {_stamp}) AS pane, date_trunc('hour', ts) AS p FROM ({_ev})) WHERE p <= report GROUP BY report")
def latest_pane_as_of(spark: SparkSession, d: str) -> DataFrame:
    p = WORKLOADS["event_users"](spark, d)
    reports = p.select((F.date_trunc("day", F.col("ts")) + F.expr("interval 90 minutes")).alias("report")).distinct()
    got = panes.latest_pane(reports, panes.pane_sizes(p, "1 hour").select("pane").distinct(), at="report").where("pane is not null")
    return got.select(F.date_format("report", panes.STAMP).alias("report"), "pane")


# ---- answers in their surroundings


@query("top_suppliers_by_nation", f"SELECT n_name, s_name, d, CAST(row_number() OVER (PARTITION BY n_name ORDER BY d DESC, s_name) AS INTEGER) AS rank FROM ({twins.sizes(twins.LINES)}) JOIN supplier ON CAST(s_suppkey AS VARCHAR) = label_key JOIN nation ON s_nationkey = n_nationkey QUALIFY rank <= 3")
def top_suppliers_by_nation(spark: SparkSession, d: str) -> DataFrame:
    sizes = exact.exact_sizes(WORKLOADS["supplier_parts"](spark, d))
    who = table(spark, d, "supplier").select(F.col("s_suppkey").cast("string").alias("label_key"), "s_name", "s_nationkey")
    named = sizes.join(who, "label_key").join(table(spark, d, "nation").select("n_nationkey", "n_name"), F.col("s_nationkey") == F.col("n_nationkey"))
    best = Window.partitionBy("n_name").orderBy(F.desc("d"), "s_name")
    return named.withColumn("rank", F.row_number().over(best)).where("rank <= 3").select("n_name", "s_name", "d", "rank")


@query("top_words_per_lang", "SELECT lang, word, count(DISTINCT doc_id) AS d, CAST(row_number() OVER (PARTITION BY lang ORDER BY count(DISTINCT doc_id) DESC, word) AS INTEGER) AS rank FROM (SELECT lang, doc_id, unnest(string_split(lower(text), ' ')) AS word FROM documents) GROUP BY lang, word QUALIFY rank <= 10")
def top_words_per_lang(spark: SparkSession, d: str) -> DataFrame:
    words = table(spark, d, "documents").select("lang", "doc_id", F.explode(F.split(F.lower("text"), " ")).alias("word")).distinct()
    sizes = words.groupBy("lang", "word").agg(F.count(F.lit(1)).alias("d"))
    return sizes.withColumn("rank", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("d"), "word"))).where("rank <= 10")


@query("top_words_toxic_filtered", f"SELECT * FROM ({twins.sizes(twins.words('(SELECT * FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1))'))}) ORDER BY d DESC, label_key LIMIT 50")
def top_words_toxic_filtered(spark: SparkSession, d: str) -> DataFrame:
    toxic = table(spark, d, "labels").where("toxic = 1").select("doc_id")
    clean = table(spark, d, "documents").join(toxic, "doc_id", "left_anti")
    return exact.exact_top_k(word_pairs(clean), 50)


@query("cube_region_segment_distinct", "SELECT r_name, c_mktsegment, count(DISTINCT l_partkey) AS d FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (r_name, c_mktsegment)")
def cube_region_segment_distinct(spark: SparkSession, d: str) -> DataFrame:
    t = lambda n: table(spark, d, n)
    rows = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    rows = rows.join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.cube("r_name", "c_mktsegment").agg(F.count_distinct("l_partkey").alias("d"))


@query("class_codes", "SELECT CAST(label AS VARCHAR) AS label_key, count(DISTINCT CAST(embedding[1] > 0 AS INTEGER) + 2 * CAST(embedding[2] > 0 AS INTEGER) + 4 * CAST(embedding[3] > 0 AS INTEGER)) AS d FROM embeddings WHERE label IS NOT NULL GROUP BY 1")
def class_codes(spark: SparkSession, d: str) -> DataFrame:
    """Which class has the most distinct sign codes of its vectors' first three places."""
    code = F.aggregate(F.sequence(F.lit(0), F.lit(2)), F.lit(0), lambda a, i: a + F.when(F.get("embedding", i) > 0, F.pow(F.lit(2), i).cast("int")).otherwise(0))
    return exact.exact_sizes(pairs(table(spark, d, "embeddings"), "label", code))


# ---- the flagship


@query("gated_top_words")
def gated_top_words(spark: SparkSession, d: str) -> DataFrame:
    """The words found in the most documents: a sketch for each of the input's partitions, merged."""
    return top_k(merge_sketches(build_sketch(WORKLOADS["word_docs"](spark, d), s=2778, m=1024)), 100)


@query("gated_top_words_by_source")
def gated_top_words_by_source(spark: SparkSession, d: str) -> DataFrame:
    return top_k(merge_sketches(build_sketch(WORKLOADS["word_docs"](spark, d), s=1000, m=256, streams="by_source")), 100)


@query("invariants_recycled", "SELECT unnest(['floor_within_share', 'value_within_floor', 'value_not_below', 'absent_within_floor', 'error_within_bound']) AS invariant, CAST(0 AS BIGINT) AS violated")
def invariants_recycled(spark: SparkSession, d: str) -> DataFrame:
    p = WORKLOADS["customer_parts"](spark, d)
    return metrics.check_invariants(build_sketch(p, kind="recycled", s=200, counter="exact", streams=1, contents=False), exact.exact_sizes(p), 0.0).select("invariant", "violated")


@query("invariants_gated")
def invariants_gated(spark: SparkSession, d: str) -> DataFrame:
    p = WORKLOADS["customer_parts"](spark, d)
    return metrics.check_invariants(build_sketch(p, kind="gated", s=200, counter="exact", streams=1, contents=False), exact.exact_sizes(p), 0.0)


# ---- neighbours of the walks


@query("size_bands", f"SELECT name, count(*) AS labels FROM ({twins.sizes(twins.PAIRS['word_docs'])}) JOIN (VALUES ('once', 1, 2), ('few', 2, 10), ('many', 10, 1000000)) b(name, low, high) ON d >= low AND d < high GROUP BY name")
def size_bands(spark: SparkSession, d: str) -> DataFrame:
    bands = values(spark, [("once", 1, 2), ("few", 2, 10), ("many", 10, 1_000_000)], "name string, low int, high int")
    return neighbours.size_bands(exact.exact_sizes(WORKLOADS["word_docs"](spark, d)), bands)


@query("reported_false_positives", f"WITH {_scored[100]} SELECT label_key FROM (SELECT label_key FROM answer ORDER BY estimate DESC, label_key LIMIT 100) WHERE label_key NOT IN (SELECT label_key FROM truth ORDER BY d DESC, label_key LIMIT 100)")
def reported_false_positives(spark: SparkSession, d: str) -> DataFrame:
    return neighbours.false_positives(*contender(spark, d), 100).select("label_key")


@query(
    "views_then_clicks",
    "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 6 HOUR AND a.event_type < b.event_type",
)
def views_then_clicks(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of events of one user within six hours, of types in order of name."""
    e = table(spark, d, "events").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    got = panes.within(e, e, "user_id", "6 hours").where(F.col("a.event_type") < F.col("b.event_type"))
    return got.select(F.col("a.event_id").alias("first_id"), F.col("b.event_id").alias("second_id"))


@query("pre_gated_walk_equals_walk", "SELECT CAST(0 AS BIGINT) AS differences")
def pre_gated_walk_equals_walk(spark: SparkSession, d: str) -> DataFrame:
    """A stream walked to its end, and walked to its middle and on over what a gate before the walk lets through of the rest: the same slots, labels and values."""
    p = lines(spark, d, 2)
    first, rest = (p.where(F.col("source") == i) for i in ("0", "1"))
    passed = neighbours.pre_gate(rest, walked(first, "gated", contents=False))
    one = walked(p, "gated").counters.select("slot", "label_key", "items")
    other = walked(first.unionByName(passed), "gated").counters.select("slot", "label_key", "items")
    return differing(one, other)


@query("verified_top_words")
def verified_top_words(spark: SparkSession, d: str) -> DataFrame:
    """The flagship's answer, recounted exactly for the labels it reports."""
    p = WORKLOADS["word_docs"](spark, d)
    return recount(top_k(build_sketch(p, s=1000, m=256, streams=1), 20), p)


query("merge_uncertainty")(lambda spark, d: (lambda sk: neighbours.merge_uncertainty(sk, merge_sketches(sk)))(build_sketch(WORKLOADS["word_docs"](spark, d), s=500, m=64, streams="by_source")))
query("theta_overlaps")(lambda spark, d: neighbours.theta_overlap(WORKLOADS["supplier_parts"](spark, d), values(spark, [("1", "2"), ("3", "4")], "first string, second string")))
query("size_quantiles")(lambda spark, d: neighbours.size_quantiles(exact.exact_sizes(WORKLOADS["word_docs"](spark, d)), [0.5, 0.9, 0.99]))
query("work_counters")(lambda spark, d: build_sketch(WORKLOADS["word_docs"](spark, d), s=400, m=64, streams=1).meta.unionByName(build_sketch(WORKLOADS["word_docs"](spark, d), kind="gated_eager", s=400, m=64, streams=1).meta))
query("measured_bytes")(lambda spark, d: metrics.measured_bytes(build_sketch(WORKLOADS["word_docs"](spark, d), s=400, m=256, streams=1)))


@query("sql_heavy_labels")
def sql_heavy_labels(spark: SparkSession, d: str) -> DataFrame:
    """The walk as a table function of SQL."""
    sqlapi.register(spark)
    # keys as they are: slim rows, as the whole of a shard is sorted in one task
    lines = table(spark, d, "lineitem").where("l_suppkey IS NOT NULL AND l_partkey IS NOT NULL")
    lines.selectExpr("l_suppkey AS label", "l_partkey AS item", "l_orderkey", "l_linenumber", "cast(l_orderkey % 2 AS int) AS shard").createOrReplaceTempView("tallywalk_pairs")
    return spark.sql("SELECT * FROM heavy_labels(TABLE(tallywalk_pairs) PARTITION BY (shard) ORDER BY (l_orderkey, l_linenumber, label, item), 5, 20, 256, 'gated')")


@query("sql_merged_registers", f"SELECT label_key, round(estimate, 6) AS estimate FROM ({twins.estimates(_regs, M)})")
def sql_merged_registers(spark: SparkSession, d: str) -> DataFrame:
    """Registers of two streams, merged and estimated by the SQL aggregates."""
    p = WORKLOADS["supplier_parts"](spark, d)
    sk = build_sketch(p, s=roomy(p, 2000), m=M, streams=2, hash="portable")
    merged = sk.counters.groupBy("label_key").agg(sqlapi.merge_registers_udf()("registers").alias("registers"))
    return merged.select("label_key", F.round(estimate_registers()("registers"), 6).alias("estimate"))


# ---- experiments, each on one workload of a size that a query may take


def experiment(rows, spark: SparkSession) -> DataFrame:
    got = list(rows)
    return spark.createDataFrame([{k: float(v) if isinstance(v, float) else v for k, v in r.items()} for r in got])


query("experiment_ablation")(lambda spark, d: experiment(experiments.ablation(spark, d, sizes=(400,), workloads=("customer_parts",)), spark))
query("experiment_same_width")(lambda spark, d: experiment(experiments.same_width(spark, d, 100, 64), spark))
query("experiment_counter_sizes")(lambda spark, d: experiment(experiments.counter_sizes(spark, d, 128 << 10, (64, 256, 1024)), spark))
query("experiment_width_effect")(lambda spark, d: experiment(experiments.width_effect(spark, d, 128 << 10, (64, 438, 1024)), spark))
query("experiment_memory_sweep")(lambda spark, d: experiment(experiments.memory_sweep(spark, d, ("customer_parts",), (64 << 10,)), spark))
query("experiment_merging")(lambda spark, d: experiment(experiments.merging(spark, d, 200, 64, 8, ("customer_parts",)), spark))
query("experiment_overlap")(lambda spark, d: experiment(experiments.overlap(spark, d, 1000, sizes=(100_000,)), spark))
query("experiment_slow_tail")(lambda spark, d: experiment(experiments.slow_tail(spark, d, 1000, 100_000, 64 << 10), spark))
query("experiment_query_time")(lambda spark, d: experiment(experiments.query_time(spark, d, 100), spark))
query("experiment_throughput")(lambda spark, d: experiment(experiments.throughput(spark, d, ("customer_parts",)), spark))
