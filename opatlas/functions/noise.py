"""Repeatable noise that SQL engines compute alike: the first eight hex digits of an md5, over 2 to the 32nd."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def noise(*parts: Column | str) -> Column:
    """In [0, 1), from the parts joined by '|'; strings are literals."""
    cols = [F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *cols)), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def noise_sql(*parts: str) -> str:
    """The same in DuckDB; parts are SQL expressions."""
    return f"(('0x' || substr(md5(concat_ws('|', {', '.join(f'({p})::VARCHAR' for p in parts)})), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"
