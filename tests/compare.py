"""Runs a registered query and its SQL twin on the same tables and compares their rows."""

from __future__ import annotations

import math
import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connection(sf_dir: str):
    con = duckdb.connect()
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def _plain(x):
    if isinstance(x, float):
        return None if math.isnan(x) else round(x, 6) + 0.0
    if isinstance(x, (list, tuple)):
        return tuple(map(_plain, x))
    if hasattr(x, "isoformat"):
        return x.isoformat()[:19].replace("T00:00:00", "")
    return x if x is None or isinstance(x, (int, str)) else float(x) if not isinstance(x, bool) else x


def _key(row):
    return tuple((v is None, str(type(v)), v if not isinstance(v, tuple) else str(v)) if v is not None else (True, "", "") for v in row)


def mismatch(spark, sf_dir: str, run, sql: str) -> str:
    """Empty if both sides give the same columns and rows."""
    df = run(spark, sf_dir)
    names = sorted(df.columns)
    mine = sorted((tuple(_plain(r[c]) for c in names) for r in df.collect()), key=_key)
    con = connection(sf_dir)
    cur = con.execute(sql)
    theirs_names = [d[0] for d in cur.description]
    if sorted(theirs_names) != names:
        return f"columns {names} against {sorted(theirs_names)}"
    order = [theirs_names.index(c) for c in names]
    theirs = sorted((tuple(_plain(r[i]) for i in order) for r in cur.fetchall()), key=_key)
    if len(mine) != len(theirs):
        return f"{len(mine)} rows against {len(theirs)}; {mine[:2]} {theirs[:2]}"
    bad = [(a, b) for a, b in zip(mine, theirs) if a != b]
    return f"{len(bad)} of {len(mine)} rows differ, such as {str(bad[0])[:600]}" if bad else ""
