"""Compare a query with its SQL: names, number of rows, and values without regard to order."""

import os
from collections import Counter
from datetime import date, datetime
from decimal import Decimal


def views(sf_dir):
    import duckdb

    con = duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for f in sorted(os.listdir(sf_dir)):
        con.execute(f"create view {f.removesuffix('.parquet')} as select * from '{sf_dir}/{f}'")
    return con


def plain(v):
    if v is None or v != v:
        return None
    if isinstance(v, bool):
        return int(v)
    if isinstance(v, Decimal):
        return float(v)
    if isinstance(v, float):
        return 0.0 if v == 0 else v
    if isinstance(v, datetime):
        return v.replace(tzinfo=None).isoformat()
    if isinstance(v, date):
        return v.isoformat()
    if hasattr(v, "item"):
        return plain(v.item())
    return v


def differences(df, con, sql):
    """An empty text, or what differs."""
    names = sorted(df.columns)
    mine = [tuple(plain(r[n]) for n in names) for r in df.collect()]
    rel = con.execute(sql)
    cols = [c[0] for c in rel.description]
    if sorted(cols) != names:
        return f"columns {names} and {sorted(cols)}"
    at = [cols.index(n) for n in names]
    theirs = [tuple(plain(r[i]) for i in at) for r in rel.fetchall()]
    a, b = Counter(mine), Counter(theirs)
    if a == b:
        return ""
    only, lack = list((a - b).elements()), list((b - a).elements())
    key = lambda r: tuple(str(x) for x in r)
    return f"{len(mine)} and {len(theirs)} rows, {len(only)} and {len(lack)} of them alone; {names}: {sorted(only, key=key)[:3]} against {sorted(lack, key=key)[:3]}"
