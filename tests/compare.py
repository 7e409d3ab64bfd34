"""Runs queries beside their SQL over the small tables: columns sorted by name, rows as multisets."""

import os
from collections import Counter
from datetime import datetime
from decimal import Decimal

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def plain(v):
    if isinstance(v, bool) or v is None or isinstance(v, str):
        return v
    if isinstance(v, (int, float, Decimal)):
        return round(float(v), 6) + 0.0
    if isinstance(v, datetime):
        return v.replace(tzinfo=None).isoformat()
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    if isinstance(v, dict):
        return tuple(sorted((str(k), plain(x)) for k, x in v.items()))
    return str(v)


def of_spark(df):
    names = sorted(df.columns)
    return names, Counter(tuple(plain(r[c]) for c in names) for r in (x.asDict(recursive=True) for x in df.collect()))


def of_duckdb(sql, sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        if os.path.exists(f"{sf_dir}/{t}.parquet"):
            con.execute(f"create view {t} as select * from read_parquet('{sf_dir}/{t}.parquet{'/*' if os.path.isdir(f'{sf_dir}/{t}.parquet') else ''}')")
    con.execute("set timezone='UTC'")
    cur = con.execute(sql)
    cols = [d[0] for d in cur.description]
    order = sorted(range(len(cols)), key=lambda i: cols[i])
    return sorted(cols), Counter(tuple(plain(r[i]) for i in order) for r in cur.fetchall())


def same(df, sql, sf_dir):
    a, b = of_spark(df), of_duckdb(sql, sf_dir)
    assert a[0] == b[0], (a[0], b[0])
    assert a[1] == b[1], (list((a[1] - b[1]).items())[:3], list((b[1] - a[1]).items())[:3], sum(a[1].values()), sum(b[1].values()))
    return sum(a[1].values())
