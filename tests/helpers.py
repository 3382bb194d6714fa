"""Plain versions to hold results against, and the comparison with DuckDB."""

import math
import os
from collections import defaultdict

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def brute_paths(edges, length, directed=False, f=sum):
    """All simple paths: [(nodes, weight)], best first."""
    near = defaultdict(list)
    for a, b, w in edges:
        near[a].append((b, w))
        if not directed:
            near[b].append((a, w))
    out = []

    def walk(nodes, ws):
        if len(ws) == length:
            if directed or nodes[0] < nodes[-1]:
                out.append((tuple(nodes), f(ws)))
            return
        for t, w in near[nodes[-1]]:
            if t not in nodes:
                walk([*nodes, t], [*ws, w])

    for n in list(near):
        walk([n], [])
    return sorted(out, key=lambda r: (-r[1], r[0]))


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else float(f"{v:.12g}")
    if hasattr(v, "isoformat"):
        return v.isoformat()
    return float(f"{float(v):.12g}") if type(v).__name__ == "Decimal" else v


def rows_of(df):
    cols = sorted(df.columns)
    return cols, sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=repr)


def duck(sql, sf=None, frames=None):
    con = duckdb.connect()
    con.execute("set TimeZone='UTC'")
    for t in TABLES if sf else ():
        p = f"{sf}/{t}.parquet"
        con.execute(f"create view {t} as select * from '{p + '/*.parquet' if os.path.isdir(p) else p}'")
    for name, table in (frames or {}).items():
        con.register(name, table)
    c = con.execute(sql)
    names = [x[0] for x in c.description]
    order = [names.index(n) for n in sorted(names)]
    return sorted(names), sorted((tuple(plain(r[i]) for i in order) for r in c.fetchall()), key=repr)
