"""SQL twins: the pieces from which the queries' DuckDB forms are put together."""

from __future__ import annotations

import math

from tallywalk.functions.hashing import HASH_BITS, LOW_BITS
from tallywalk.functions.registers import SERIES, alpha

LINES = "SELECT CAST(l_suppkey AS VARCHAR) AS label_key, CAST(l_partkey AS VARCHAR) AS item_key FROM lineitem"
JOINED = "lineitem JOIN orders ON l_orderkey = o_orderkey"


def words(table: str = "documents", id: str = "doc_id", role: str = "word_label", more: str = "") -> str:
    a, b = ("word", f"CAST({id} AS VARCHAR)") if role == "word_label" else (f"CAST({id} AS VARCHAR)", "word")
    return f"SELECT {a} AS label_key, {b} AS item_key{more} FROM (SELECT *, unnest(string_split(lower(text), ' ')) AS word FROM {table})"


PAIRS = {
    "doc_words": words(role="doc_label"),
    "word_docs": words(),
    "word_conversations": words("conversations", "conv_id"),
    "part_customers": f"SELECT CAST(l_partkey AS VARCHAR) AS label_key, CAST(o_custkey AS VARCHAR) AS item_key FROM {JOINED}",
    "customer_parts": f"SELECT CAST(o_custkey AS VARCHAR) AS label_key, CAST(l_partkey AS VARCHAR) AS item_key FROM {JOINED}",
    "supplier_parts": LINES,
    "day_parts": "SELECT CAST(CAST(l_shipdate AS DATE) AS VARCHAR) AS label_key, CAST(l_partkey AS VARCHAR) AS item_key FROM lineitem",
    "host_urls": "SELECT split_part(url, '/', 3) AS label_key, url AS item_key FROM pages WHERE url IS NOT NULL",
    "event_users": "SELECT event_type AS label_key, CAST(user_id AS VARCHAR) AS item_key, ts FROM events",
    "event_key_users": "SELECT event_type || ':' || (props::JSON->>'k') AS label_key, CAST(user_id AS VARCHAR) AS item_key, ts FROM events",
}


def h(text: str, tag: str) -> str:
    return f"CAST(('0x' || substr(md5('{tag}|' || {text}), 1, 13)) AS BIGINT)"


def draw(item: str = "item_key") -> str:
    return f"({float(1 << HASH_BITS)} / ({h(item, 'g')} + 0.5))"


def bits(w: str) -> str:
    return f"(CASE WHEN {w} = 0 THEN 0 ELSE length(bin({w})) END)"


def bucket(hash_: str, m: int) -> str:
    rest = HASH_BITS - (m.bit_length() - 1)
    return f"({hash_} >> {rest})" if m & (m - 1) == 0 else f"(({hash_} & {(1 << LOW_BITS) - 1}) % {m})"


def rank(hash_: str, m: int) -> str:
    if m & (m - 1) == 0:
        rest = HASH_BITS - (m.bit_length() - 1)
        return f"({rest + 1} - {bits(f'({hash_} & {(1 << rest) - 1})')})"
    return f"({HASH_BITS - LOW_BITS + 1} - {bits(f'({hash_} >> {LOW_BITS})')})"


PAIR = "(label_key || chr(1) || item_key)"


def registers(pairs: str, m: int, keys: str = "label_key") -> str:
    """Registers of one counter for each key."""
    hashed = f"SELECT *, {h('item_key', 'c')} AS h FROM ({pairs})"
    return f"SELECT {keys}, {bucket('h', m)} AS bucket, max({rank('h', m)}) AS rank FROM ({hashed}) GROUP BY ALL"


def histogram(m: int, filled: str, powers: str) -> str:
    x = f"(({m} - {filled}) / {float(m)})"
    sigma = f"({x} + list_sum(list_transform(range(1, {SERIES + 1}), lambda k: pow({x}, pow(2.0, k)) * pow(2.0, k - 1))))"
    return f"(CASE WHEN {filled} = 0 THEN 0.0 ELSE {m * m / (2 * math.log(2))} / ({float(m)} * {sigma} + {powers}) END)"


def classic(m: int, filled: str, powers: str) -> str:
    raw = f"({alpha(m) * m * m} / ({powers} + {m} - {filled}))"
    return f"(CASE WHEN {raw} <= {2.5 * m} AND {m} - {filled} > 0 THEN {float(m)} * ln({float(m)} / ({m} - {filled})) ELSE {raw} END)"


def estimates(regs: str, m: int, keys: str = "label_key", form=histogram) -> str:
    sums = f"SELECT {keys}, count(*) AS filled, sum(pow(2.0, -rank)) AS powers FROM ({regs}) GROUP BY ALL"
    return f"SELECT {keys}, {form(m, 'filled', 'powers')} AS estimate FROM ({sums})"


def sizes(pairs: str) -> str:
    return f"SELECT label_key, count(DISTINCT item_key) AS d FROM ({pairs}) GROUP BY label_key"


def column(row: str, width: int) -> str:
    return f"({h(f'CAST({row} AS VARCHAR) || chr(124) || label_key', 'r')} % {width})"


def cell_registers(pairs: str, depth: int, width: int, m: int) -> str:
    hashed = f"SELECT label_key, {bucket('h', m)} AS bucket, max({rank('h', m)}) AS rank FROM (SELECT label_key, {h(PAIR, 'p')} AS h FROM ({pairs})) GROUP BY ALL"
    placed = f"SELECT row, {column('row', width)} AS col, bucket, rank FROM ({hashed}), (SELECT unnest(range({depth})) AS row)"
    return f"SELECT row, col, bucket, max(rank) AS rank FROM ({placed}) GROUP BY ALL"


def cell_labels(pairs: str, depth: int, width: int, m: int) -> str:
    levels = f"SELECT label_key, max({rank('h', m)}) AS level FROM (SELECT label_key, {h(PAIR, 'p')} AS h FROM ({pairs})) GROUP BY ALL"
    placed = f"SELECT row, {column('row', width)} AS col, label_key, level FROM ({levels}), (SELECT unnest(range({depth})) AS row)"
    return f"SELECT row, col, label_key, level FROM ({placed}) QUALIFY row_number() OVER (PARTITION BY row, col ORDER BY level DESC, label_key) = 1"


def cell_estimates(regs: str, labels: str, depth: int, width: int, m: int) -> str:
    wanted = f"SELECT label_key, row, {column('row', width)} AS col FROM (SELECT DISTINCT label_key FROM ({labels})), (SELECT unnest(range({depth})) AS row)"
    return f"SELECT label_key, min(coalesce(estimate, 0.0)) AS estimate FROM ({wanted}) LEFT JOIN ({estimates(regs, m, 'row, col')}) USING (row, col) GROUP BY label_key"


def shared_slim(pairs: str, depth: int, width: int) -> str:
    rest = HASH_BITS - max(1, (depth - 1).bit_length())
    r = f"({rest + 1} - {bits(f'((h // {depth}) & {(1 << rest) - 1})')})"
    slim = f"SELECT label_key, h % {depth} AS row, max({r}) AS rank FROM (SELECT label_key, {h(PAIR, 'p')} AS h FROM ({pairs})) GROUP BY ALL"
    return f"SELECT *, {column('row', width)} AS col FROM ({slim})"


def shared_registers(pairs: str, depth: int, width: int) -> str:
    return f"SELECT row, col, max(rank) AS rank FROM ({shared_slim(pairs, depth, width)}) GROUP BY ALL"


def shared_labels(pairs: str, depth: int, width: int) -> str:
    return f"SELECT row, col, label_key, rank AS level FROM ({shared_slim(pairs, depth, width)}) QUALIFY row_number() OVER (PARTITION BY row, col ORDER BY rank DESC, label_key) = 1"


def distribution(regs: str, width: int) -> str:
    counts = f"SELECT row, CAST(rank AS INTEGER) AS v, count(*) AS n FROM ({regs}) GROUP BY ALL UNION ALL SELECT row, 0, {width} - count(*) FROM ({regs}) GROUP BY row HAVING count(*) < {width}"
    return f"SELECT row, v, (up - n) / {float(width)} AS below, up / {float(width)} AS upto FROM (SELECT row, v, n, sum(n) OVER (PARTITION BY row ORDER BY v) AS up FROM ({counts}))"


def shared_estimates(regs: str, labels: str, depth: int, width: int, step: float, largest: float) -> str:
    from tallywalk.operators.grids import TINY, ladder

    wanted = f"SELECT label_key, row, {column('row', width)} AS col FROM (SELECT DISTINCT label_key FROM ({labels})), (SELECT unnest(range({depth})) AS row)"
    got = f"SELECT label_key, row, CAST(coalesce(rank, 0) AS INTEGER) AS v FROM ({wanted}) LEFT JOIN ({regs}) USING (row, col)"
    seen = f"SELECT label_key, v, coalesce(below, 0.0) AS below, coalesce(upto, 1.0) AS upto, count(*) AS k FROM ({got}) LEFT JOIN ({distribution(regs, width)}) USING (row, v) GROUP BY ALL"
    own = lambda v: f"exp(-n / {depth} * pow(2.0, -({v})))"
    like = f"ln(greatest({own('v')} * upto - (CASE WHEN v = 0 THEN 0.0 ELSE {own('v - 1')} * below END), {TINY}))"
    rungs = ", ".join(f"CAST({x!r} AS DOUBLE)" for x in ladder(largest, step))
    scored = f"SELECT label_key, n, round(sum(k * {like}), 6) AS score FROM ({seen}), (SELECT unnest([{rungs}]) AS n) GROUP BY ALL"
    return f"SELECT label_key, n AS estimate FROM ({scored}) QUALIFY row_number() OVER (PARTITION BY label_key ORDER BY score DESC, n) = 1"


def stream(part: int = 0, parts: int = 1) -> str:
    """All lines, or those of one of so many equal ranges of order keys, numbered in the stream's order, with draws."""
    low, high = ("(SELECT min(l_orderkey) FROM lineitem)", "(SELECT max(l_orderkey) FROM lineitem)")
    which = "" if parts == 1 else f"AND coalesce(floor((l_orderkey - {low}) * {float(parts)} / ({high} - {low} + 1)), 0) = {part}"
    return f"""SELECT row_number() OVER (ORDER BY l_orderkey NULLS FIRST, l_linenumber NULLS FIRST, l_suppkey, l_partkey) AS n, l_suppkey AS label, l_partkey AS item,
        {draw('CAST(l_partkey AS VARCHAR)')} AS draw FROM lineitem WHERE l_suppkey IS NOT NULL AND l_partkey IS NOT NULL {which}"""


def walk(name: str, rows: str, kind: str, s: int) -> str:
    """CTEs that walk a stream with exact counters, as a fold over its list of entries; `name` has slot, label_key, offset, items, estimate. The state: labels, items and offsets of the slots, and
    their values."""
    has, place, low, least = "list_contains", "coalesce(list_position(c.labels, x.label), 0)", "list_position(c.vals, list_min(c.vals))", "list_min(c.vals)"
    put = lambda list_, at, x: f"({list_}[1:{at} - 1] || [{x}] || {list_}[{at} + 1:])"
    grown = lambda at, list_, x: f"CASE WHEN {has}(c.items[{at}], x.item) THEN c.{list_} ELSE {put(f'c.{list_}', at, x)} END"
    items = lambda at: grown(at, "items", f"list_append(c.items[{at}], x.item)")
    values = lambda at: grown(at, "vals", f"c.vals[{at}] + 1")
    anew = kind == "offset"
    gate = f"x.draw > {least}" if kind.startswith("gated") else "true"
    step = lambda list_, hit, fill, taken: f"'{list_}': CASE WHEN {place} > 0 THEN {hit} WHEN len(c.labels) < {s} THEN list_append(c.{list_}, {fill}) WHEN {gate} THEN {taken} ELSE c.{list_} END"
    state = ", ".join(
        (
            step("labels", "c.labels", "x.label", put("c.labels", low, "x.label")),
            step("items", items(place), "[x.item]", put("c.items", low, "[x.item]") if anew else items(low)),
            step("offs", "c.offs", "CAST(0 AS DOUBLE)", put("c.offs", low, least) if anew else "c.offs"),
            step("vals", values(place), "CAST(1 AS DOUBLE)", put("c.vals", low, f"{least} + 1") if anew else values(low)),
        )
    )
    empty = "{'labels': CAST([] AS BIGINT[]), 'items': CAST([] AS BIGINT[][]), 'offs': CAST([] AS DOUBLE[]), 'vals': CAST([] AS DOUBLE[])}"
    return f"""{name}_in AS MATERIALIZED ({rows}),
    {name}_end AS MATERIALIZED (SELECT list_reduce(list({{'label': label, 'item': item, 'draw': draw}} ORDER BY n), lambda c, x: {{{state}}}, {empty}) AS w FROM {name}_in),
    {name} AS (SELECT j - 1 AS slot, CAST(w.labels[j] AS VARCHAR) AS label_key, w.offs[j] AS "offset", w.items[j] AS items, w.vals[j] AS estimate FROM (SELECT w, unnest(range(1, len(w.labels) + 1)) AS j FROM {name}_end))"""


def union_of(names: list[str], s: int) -> str:
    """The flat merge of walked sketches: items united, offsets added, the s largest kept."""
    every = " UNION ALL ".join(f'SELECT label_key, "offset", unnest(items) AS item, \'{n}\' AS who FROM {n}' for n in names)
    # each sketch's offset of a label counts once
    offs = " UNION ALL ".join(f'SELECT label_key, "offset" FROM {n}' for n in names)
    both = f'SELECT a.label_key, list(DISTINCT item) AS items, any_value(o.o) AS "offset", CAST(count(DISTINCT item) + any_value(o.o) AS DOUBLE) AS estimate FROM ({every}) a JOIN (SELECT label_key, sum("offset") AS o FROM ({offs}) GROUP BY ALL) o ON o.label_key = a.label_key GROUP BY a.label_key'
    return f"SELECT *, row_number() OVER (ORDER BY estimate DESC, label_key) - 1 AS slot FROM ({both}) QUALIFY slot < {s}"


def score_columns(truth: str, answer: str, k: int) -> str:
    """CTEs on_true and on_reported (label_key, d, estimate) of k labels."""
    pick = lambda src, by: f"SELECT label_key FROM ({src}) ORDER BY {by} DESC, label_key LIMIT {k}"
    values = lambda src: f"SELECT label_key, coalesce(CAST(d AS DOUBLE), 0.0) AS d, coalesce(estimate, 0.0) AS estimate FROM ({src}) LEFT JOIN truth USING (label_key) LEFT JOIN answer USING (label_key)"
    return f"truth AS MATERIALIZED ({truth}), answer AS MATERIALIZED ({answer}), on_true AS ({values(pick('SELECT * FROM truth', 'd'))}), on_reported AS ({values(pick('SELECT * FROM answer', 'estimate'))})"


MEASURES = {
    "nae": "sum(abs(d - estimate)) / sum(d)",
    "nrse": "sqrt(sum(pow(d - estimate, 2)) / sum(pow(d, 2)))",
    "rmae": "avg(abs(d - estimate) / d)",
    "rrmse": "sqrt(sum(pow(d - estimate, 2) / d)) / count(*)",
    "rrmse_usual": "sqrt(avg(pow((d - estimate) / d, 2)))",
}
