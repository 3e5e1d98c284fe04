"""Hashed priorities: the same value for the same item on every retry, and in any engine that has md5."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Hex digits of the digest that make a priority: 0 … 16**15 - 1 fits a BIGINT (fixed value).
HEX = 15
SPAN = 16**HEX


def digest(seed: int | str | Column, item: Column, window: Column | None = None) -> Column:
    """The hex digits of a priority; they sort as the priority does and cost half as much."""
    parts = [F.lit(str(seed)) if not isinstance(seed, Column) else seed.cast("string")]
    parts += [window.cast("string")] if window is not None else []
    text = F.concat_ws("|", *parts, item.cast("string"))
    return F.substring(F.md5(text), 1, HEX)


def priority_of(digits: Column) -> Column:
    return F.conv(digits, 16, 10).cast("bigint")


def priority(seed: int | str | Column, item: Column, window: Column | None = None) -> Column:
    """Priority of an item; with `window` a fresh one per window, without it a permanent one."""
    return priority_of(digest(seed, item, window))


def priority_value(seed, item, window=None) -> int:
    """`priority` in Python."""
    parts = [seed, item] if window is None else [seed, window, item]
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:HEX], 16)


def priority_sql(seed: str, item: str, window: str | None = None) -> str:
    """`priority` as ANSI SQL text (DuckDB); arguments are SQL expressions."""
    parts = [seed, *([window] if window else []), item]
    return f"CAST('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, {HEX}) AS BIGINT)"
