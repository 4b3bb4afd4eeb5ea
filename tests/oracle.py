"""Compares a query with its SQL on the given tables, as the driver does."""

from __future__ import annotations

import glob
import os

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str) -> duckdb.DuckDBPyConnection:
    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    return con


def differences(df, con: duckdb.DuckDBPyConnection, sql: str) -> list[str]:
    """What differs between a DataFrame and a SQL result, ignoring the order of rows and columns."""
    want = con.execute(sql).to_arrow_table()
    got = df.toArrow()
    out = []
    if sorted(got.column_names) != sorted(want.column_names):
        return [f"columns {sorted(got.column_names)} and {sorted(want.column_names)}"]
    names = sorted(got.column_names)
    kinds = {n: (str(got.schema.field(n).type), str(want.schema.field(n).type)) for n in names}
    for n, (a, b) in kinds.items():
        same = {a.replace("large_", ""), b.replace("large_", "")}
        if len(same) > 1 and not same <= {"int32", "int64"} and not any(x.startswith("timestamp") for x in same):
            out.append(f"{n}: {a} and {b}")
    rows = lambda t: sorted((tuple(map(repr, r.values())) for r in t.select(names).to_pylist()))
    a, b = rows(got), rows(want)
    if len(a) != len(b):
        out.append(f"{len(a)} and {len(b)} rows")
    if a != b:
        x = next((p for p in a if p not in set(b)), None)
        y = next((p for p in b if p not in set(a)), None)
        out.append(f"rows differ, as {x} and {y}")
    return out
