"""Repeatable draws: the first 32 bits of an MD5 over (key, attribute, seed), equal in every engine."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def draw(key: Column, attr: str, seed: int = 0) -> Column:
    """A number from 0 to 2^32 - 1."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", key.cast("string"), F.lit(attr), F.lit(str(seed)))), 1, 8), 16, 10).cast("long")


def pick(key: Column, attr: str, pool: list, seed: int = 0) -> Column:
    """One value of a fixed pool."""
    return F.element_at(F.array(*(F.lit(p) for p in pool)), (draw(key, attr, seed) % len(pool)).cast("int") + 1)


def draw_sql(key: str, attr: str, seed: int = 0) -> str:
    """The same in DuckDB."""
    return f"concat('0x', substr(md5(concat_ws(':', cast({key} as varchar), '{attr}', '{seed}')), 1, 8))::bigint"
