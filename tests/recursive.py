"""The walks as recursive SQL, an entry a step: slow, short streams only, and written apart from the folds that the queries' twins use."""

from tallywalk.plans.twins import draw


def prefix(low: int = 0, high: int = 400) -> str:
    """A stream's beginning in its order, numbered from 1, with draws."""
    return f"""SELECT row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_suppkey, l_partkey) AS n, CAST(l_suppkey AS VARCHAR) AS label, CAST(l_partkey AS VARCHAR) AS item,
        {draw('CAST(l_partkey AS VARCHAR)')} AS draw FROM lineitem WHERE l_orderkey >= {low} AND l_orderkey < {high}"""


def walk(name: str, stream: str, kind: str, s: int) -> str:
    """CTEs that walk a short stream entry by entry with exact counters; `name` has slot, label_key, offset, items, estimate."""
    gate = "draw > least" if kind.startswith("gated") else "true"
    put = lambda list_, at, x: f"({list_}[1:{at} - 1] || [{x}] || {list_}[{at} + 1:])"
    taken = "[item]" if kind == "offset" else "list_distinct(list_append(items[low], item))"
    off = put("offs", "low", "least") if kind == "offset" else "offs"
    return f"""{name}_in AS MATERIALIZED ({stream}),
    {name}_walk AS (
        SELECT CAST(0 AS BIGINT) AS n, CAST([] AS VARCHAR[]) AS labels, CAST([] AS VARCHAR[][]) AS items, CAST([] AS DOUBLE[]) AS offs
        UNION ALL
        SELECT n, CASE WHEN pos > 0 THEN labels WHEN room THEN list_append(labels, label) WHEN {gate} THEN {put('labels', 'low', 'label')} ELSE labels END,
            CASE WHEN pos > 0 THEN {put('items', 'pos', 'list_distinct(list_append(items[pos], item))')} WHEN room THEN list_append(items, [item]) WHEN {gate} THEN {put('items', 'low', taken)} ELSE items END,
            CASE WHEN pos > 0 THEN offs WHEN room THEN list_append(offs, CAST(0 AS DOUBLE)) WHEN {gate} THEN {off} ELSE offs END
        FROM (
            SELECT *, coalesce(list_position(vals, list_min(vals)), 0) AS low, list_min(vals) AS least FROM (
                SELECT i.n, i.label, i.item, i.draw, labels, items, offs, coalesce(list_position(labels, i.label), 0) AS pos, len(labels) < {s} AS room,
                    list_transform(range(1, len(labels) + 1), lambda j: len(items[j]) + offs[j]) AS vals
                FROM {name}_walk w JOIN {name}_in i ON i.n = w.n + 1))),
    {name}_end AS (SELECT * FROM {name}_walk ORDER BY n DESC LIMIT 1),
    {name} AS (SELECT j - 1 AS slot, labels[j] AS label_key, offs[j] AS "offset", items[j] AS items, CAST(len(items[j]) + offs[j] AS DOUBLE) AS estimate FROM (SELECT *, unnest(range(1, len(labels) + 1)) AS j FROM {name}_end))"""
