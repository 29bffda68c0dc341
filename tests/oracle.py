"""Comparison of a registered query with its SQL on DuckDB; also a command: python tests/oracle.py SF_DIR [KEY...]."""

from __future__ import annotations

import math
import os
import sys
import time
from decimal import Decimal

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf: str):
    con = duckdb.connect()
    for t in TABLES:
        p = f"{sf}/{t}.parquet"
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{p}{'/*.parquet' if os.path.isdir(p) else ''}'")
    return con


def norm(v):
    if isinstance(v, (float, Decimal)):
        v = float(v)
        return "nan" if math.isnan(v) else round(v, 5) + 0.0
    if isinstance(v, (list, tuple)):
        return tuple(map(norm, v))
    if isinstance(v, dict):
        return tuple((k, norm(x)) for k, x in v.items())
    if hasattr(v, "asDict"):
        return norm(v.asDict())
    if hasattr(v, "tzinfo") and hasattr(v, "replace"):
        return v.replace(tzinfo=None)
    return v


def difference(spark, con, sf, query, sql) -> str | None:
    got = query(spark, sf)
    want = con.sql(sql)
    a, b = sorted(got.columns), sorted(want.columns)
    if a != b:
        return f"columns {a} and {b}"
    x = sorted(repr(tuple(norm(r[c]) for c in a)) for r in got.collect())
    y = sorted(repr(tuple(map(norm, r))) for r in want.select(*(f'"{c}"' for c in a)).fetchall())
    if x != y:
        only = [r for r in x if r not in set(y)][:3], [r for r in y if r not in set(x)][:3]
        return f"{len(x)} and {len(y)} rows; only here {only[0]}; only there {only[1]}"
    return None if x or "empty" in sql else "no rows"


if __name__ == "__main__":
    sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    from codeprov.oracles import SQL
    from codeprov.queries import QUERIES
    from codeprov.session import local_session

    spark = local_session(int(os.environ.get("CORES", "8")))
    spark.sparkContext.setLogLevel("OFF")
    sf, *keys = sys.argv[1:]
    con = connect(sf)
    bad = 0
    for k in keys and [q for q in QUERIES if any(q.startswith(x) for x in keys)] or QUERIES:
        began = time.time()
        try:
            said = difference(spark, con, sf, QUERIES[k], SQL[k]) if k in SQL else f"no SQL; {QUERIES[k](spark, sf).count()} rows"
        except Exception as e:  # a report for the developer; the tests raise
            said = f"{type(e).__name__} {str(e)[:700]}"
        bad += said is not None and not said.startswith("no SQL")
        print(f"{k}: {'equal' if said is None else said} ({time.time() - began:.1f} s)", flush=True)
    print("different:", bad)
