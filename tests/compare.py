"""Runs a query and its SQL twin and compares rows, without order."""

from __future__ import annotations

import datetime
import math
import os
from collections import Counter

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str):
    con = duckdb.connect()
    for t in TABLES:
        p = f"{sf_dir}/{t}.parquet"
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{p}{'/*.parquet' if os.path.isdir(p) else ''}')")
    return con


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else float(f"{v:.12g}")
    if isinstance(v, (datetime.datetime, datetime.date)):
        return str(v)
    if isinstance(v, list):
        return tuple(plain(x) for x in v)
    return v


def difference(df, con, sql: str) -> str:
    """Empty if both have the same columns and rows."""
    cur = con.execute(sql)
    names = [c[0] for c in cur.description]
    theirs = cur.fetchall()
    cols = sorted(df.columns)
    if cols != sorted(names):
        return f"columns {cols} and {sorted(names)}"
    at = [names.index(c) for c in cols]
    a = Counter(tuple(plain(r[c]) for c in cols) for r in df.collect())
    b = Counter(tuple(plain(r[k]) for k in at) for r in theirs)
    return "" if a == b else f"{sum(a.values())} and {sum(b.values())} rows; only ours {list((a - b).items())[:3]}; only theirs {list((b - a).items())[:3]}"
