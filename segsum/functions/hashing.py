"""Uniform draws that any engine with md5 can repeat; a retried task draws the same."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def md5_int(*parts: Column | str) -> Column:
    """First 32 bits of the md5 of the parts joined by '|'."""
    cols = [F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *cols)), 1, 8), 16, 10).cast("long")


def uniform(seed: int | str, *parts: Column) -> Column:
    """In [0, 1)."""
    return md5_int(str(seed), *parts) / F.lit(float(1 << 32))
