"""Runs a query in Spark and its twin in DuckDB, and compares rows as the driver does: columns by name, order aside."""

import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir):
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def canonical(row):
    out = []
    for v in row:
        if isinstance(v, float):
            v = round(v, 6) + 0.0
        elif hasattr(v, "as_tuple"):
            v = float(v)
        out.append(str(v))
    return tuple(out)


def rows_of(columns, rows):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return [columns[i] for i in order], sorted(canonical([r[i] for i in order]) for r in rows)


def differences(spark, con, query, sql, sf_dir):
    df = query(spark, sf_dir)
    a = rows_of(df.columns, [tuple(r) for r in df.collect()])
    rel = con.execute(sql)
    b = rows_of([c[0] for c in rel.description], rel.fetchall())
    if a[0] != b[0]:
        return f"columns {a[0]} and {b[0]}"
    if a[1] != b[1]:
        x, y = set(a[1]), set(b[1])
        return f"{len(a[1])} and {len(b[1])} rows; {sorted(x - y)[:3]} against {sorted(y - x)[:3]}"
    return ""
