"""Draws that depend on nothing but (seed, round, start, move): any plan, partitioning or retry gives the same walk."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 48
SPAN = 1 << BITS


def _column(x: Column | str | int) -> Column:
    return F.col(x) if isinstance(x, str) else F.lit(x) if isinstance(x, int) else x


def draw48(seed: Column | int, round_: Column | str | int, start: Column | str, move: Column | str | int, rng: str = "md5") -> Column:
    """A whole number below 2^48.  ``md5`` can be repeated by any engine; ``xxhash64`` is the fast form."""
    key = [_column(x) for x in (seed, round_, start, move)]
    if rng == "md5":
        return F.conv(F.substring(F.md5(F.concat_ws(":", *[k.cast("string") for k in key]).cast("binary")), 1, 12), 16, 10).cast("long")
    return F.shiftrightunsigned(F.xxhash64(*[k.cast("long") for k in key]), 64 - BITS)


def draw48_sql(seed: str, round_: str, start: str, move: str) -> str:
    """The same in DuckDB."""
    return f"CAST('0x' || substr(md5(concat_ws(':', {seed}, {round_}, {start}, {move})), 1, 12) AS BIGINT)"


def draws(seed: int, round_: int, start, moves) -> list[int]:
    """The md5 form in plain Python."""
    import hashlib

    return [int(hashlib.md5(f"{seed}:{round_}:{start}:{m}".encode()).hexdigest()[:12], 16) for m in moves]
