"""Rows of a Spark query against its DuckDB twin, columns by name, in any order."""

import glob
import math
import os

import duckdb

SF_SMOKE, SF = "/root/testdata/sf0.001", "/root/testdata/sf0.01"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def duck(sf_dir):
    con = duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for t in TABLES:
        p = f"{sf_dir}/{t}.parquet"
        con.execute(f"create view {t} as select * from read_parquet('{p + '/*.parquet' if os.path.isdir(p) else p}')")
    return con


def plain(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return None
    if isinstance(v, bool):
        return v
    if isinstance(v, float):
        return round(v, 6)
    if isinstance(v, (list, tuple)):
        return [plain(x) for x in v]
    if hasattr(v, "asDict"):
        return [plain(x) for x in v]
    if isinstance(v, dict):
        return [plain(x) for x in v.values()]
    return v


def rows_of_spark(df):
    cols = sorted(df.columns)
    return cols, sorted((repr([plain(r[c]) for c in cols]) for r in df.collect()))


def rows_of_duck(con, sql):
    res = con.execute(sql)
    names = [d[0] for d in res.description]
    order = sorted(range(len(names)), key=lambda i: names[i])
    return [names[i] for i in order], sorted(repr([plain(r[i]) for i in order]) for r in res.fetchall())


def differences(df, sql, con):
    a_cols, a = rows_of_spark(df)
    b_cols, b = rows_of_duck(con, sql)
    if a_cols != b_cols:
        return f"columns {a_cols} / {b_cols}"
    if a != b:
        sa, sb = set(a), set(b)
        return f"{len(a)} / {len(b)} rows; only spark {sorted(sa - sb)[:3]}; only duck {sorted(sb - sa)[:3]}"
    return None
