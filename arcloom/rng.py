"""Draws that depend on seed, purpose and key only, so that any partitioning and engine gives the same."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Hex digits of a draw: 52 bits, which a double holds exactly.
DIGITS = 13


def _text(seed: int, purpose: str, *keys: Column | str) -> Column:
    return F.concat_ws(":", F.lit(f"{seed}:{purpose}"), *[(F.col(k) if isinstance(k, str) else k).cast("string") for k in keys])


def bits(seed: int, purpose: str, *keys: Column | str, kind: str = "md5") -> Column:
    """A long of 52 bits. ``md5`` is the same in other engines, ``xx`` is faster."""
    text = _text(seed, purpose, *keys)
    if kind == "xx":
        return F.shiftrightunsigned(F.xxhash64(text), 12)
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, DIGITS), 16, 10).cast("long")


def uniform(seed: int, purpose: str, *keys: Column | str, kind: str = "md5") -> Column:
    return bits(seed, purpose, *keys, kind=kind) / F.lit(float(16**DIGITS))


def randint(seed: int, purpose: str, low: int, high: int, *keys: Column | str, kind: str = "md5") -> Column:
    """Uniform on low..high, both included."""
    return F.pmod(bits(seed, purpose, *keys, kind=kind), F.lit(high - low + 1)) + low


def sql_bits(seed: int, purpose: str, *keys: str) -> str:
    """The same draw in DuckDB's SQL."""
    return f"('0x' || substr(md5('{seed}:{purpose}'" + "".join(f" || ':' || ({k})" for k in keys) + f"), 1, {DIGITS}))::BIGINT"


def sql_uniform(seed: int, purpose: str, *keys: str) -> str:
    return f"({sql_bits(seed, purpose, *keys)} / {16**DIGITS}.0::DOUBLE)"
