"""Coins: pure functions of seed, trial, worker and rank, so that replays agree.

``portable`` coins come from md5 and are the same in any SQL engine; ``fast`` ones
from a 64-bit hash, for large runs.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, functions as F

#: Leading md5 digits used, and their range.
DIGITS, RANGE = 13, float(1 << 52)


def coin_text(*parts: Column | int | str) -> Column:
    return F.concat_ws(":", *[(p if isinstance(p, Column) else F.lit(p)).cast("string") for p in parts])


def coin(*parts: Column | int | str, kind: str = "portable") -> Column:
    """Uniform in [0, 1)."""
    if kind == "fast":
        cols = [p if isinstance(p, Column) else F.lit(p) for p in parts]
        return F.shiftrightunsigned(F.xxhash64(*cols), 12) / F.lit(RANGE)
    return F.conv(F.substring(F.md5(coin_text(*parts)), 1, DIGITS), 16, 10).cast("bigint") / F.lit(RANGE)


def coin_sql(*parts: str) -> str:
    """The portable coin in DuckDB, of SQL expressions."""
    text = " || ':' || ".join(f"CAST({p} AS VARCHAR)" for p in parts)
    return f"(CAST('0x' || substr(md5({text}), 1, {DIGITS}) AS BIGINT) / {RANGE:.1f})"


def coin_value(*parts) -> float:
    """The portable coin in Python."""
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:DIGITS], 16) / RANGE


def colour(node: Column, k: int, seed: int, kind: str = "portable") -> Column:
    """Worker drawn uniformly for a node."""
    return F.floor(coin("f", seed, node, kind=kind) * k).cast("int")


def colour_sql(node: str, k: int, seed: int) -> str:
    return f"CAST(floor({coin_sql(chr(39) + 'f' + chr(39), str(seed), node)} * {k}) AS INTEGER)"


def colour_value(node: int, k: int, seed: int) -> int:
    return int(coin_value("f", seed, node) * k)
