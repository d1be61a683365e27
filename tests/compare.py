"""Rows of a query beside rows of its SQL, in any order."""

import os

import duckdb


def views(sf):
    con = duckdb.connect()
    con.execute("SET TimeZone='UTC'")
    for f in os.listdir(sf):
        at = f"{sf}/{f}" + ("/*.parquet" if os.path.isdir(f"{sf}/{f}") else "")
        con.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM read_parquet('{at}')")
    return con


def plain(v):
    return repr(round(v, 6)) if isinstance(v, float) else str(v)


def same(df, sql, con):
    rel = con.execute(sql)
    names = [d[0] for d in rel.description]
    cols = sorted(df.columns)
    assert sorted(names) == cols
    want = sorted(tuple(plain(r[names.index(c)]) for c in cols) for r in rel.fetchall())
    got = sorted(tuple(plain(v) for v in r) for r in df.select(*cols).collect())
    assert got == want
