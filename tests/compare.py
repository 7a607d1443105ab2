"""Runs a query and its DuckDB SQL side by side and compares the rows as sets with counts."""

from __future__ import annotations

import glob
import os
from collections import Counter

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str) -> duckdb.DuckDBPyConnection:
    c = duckdb.connect()
    c.execute("SET threads = 4")
    for t in TABLES:
        path = f"{sf_dir}/{t}.parquet"
        if glob.glob(path):
            c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{path}{'/*.parquet' if os.path.isdir(path) else ''}'")
    return c


def plain(v):
    return v.isoformat() if hasattr(v, "isoformat") else v


def differences(spark_df, con: duckdb.DuckDBPyConnection, sql: str) -> str | None:
    """None where both have the same columns, kinds and rows."""
    relation = con.sql(sql)
    names = sorted(spark_df.columns)
    if names != sorted(relation.columns):
        return f"columns {names} / {sorted(relation.columns)}"
    want_types = {c: str(t) for c, t in zip(relation.columns, relation.types, strict=True)}
    kinds = {"bigint": "BIGINT", "int": "INTEGER", "double": "DOUBLE", "string": "VARCHAR", "boolean": "BOOLEAN", "date": "DATE", "timestamp_ntz": "TIMESTAMP"}
    for c, t in spark_df.dtypes:
        if kinds.get(t, want_types[c]) != want_types[c]:
            return f"{c}: {t} / {want_types[c]}"
    order = [relation.columns.index(c) for c in names]
    want = Counter(tuple(plain(r[k]) for k in order) for r in relation.fetchall())
    got = Counter(tuple(plain(v) for v in r) for r in spark_df.select(*names).collect())
    if got != want:
        return f"{sum(got.values())} / {sum(want.values())} rows; only here {list((got - want).items())[:3]}; only there {list((want - got).items())[:3]}"
    return None
