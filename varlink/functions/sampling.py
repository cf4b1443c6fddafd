"""Seeded priorities: every row gets a number in [0, 1) from its key, the same on any machine and retry."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

_UNIT = float(1 << 32)


def priority_bits(seed: int | Column, *keys: Column) -> Column:
    """32 bits of the digest of the seed and the keys (integers and strings only, whose text all engines share)."""
    return F.conv(F.substring(_digest(seed, *keys), 1, 8), 16, 10).cast("long")


def _digest(seed: int | Column, *keys: Column) -> Column:
    s = seed.cast("string") if isinstance(seed, Column) else F.lit(str(seed))
    return F.md5(F.concat_ws("|", s, *[k.cast("string") for k in keys]).cast("binary"))


def below(share: Column, seed: int | Column, *keys: Column) -> Column:
    """Whether the priority is below ``share`` (less than 1), from the digits alone: nothing is converted for each row."""
    return _digest(seed, *keys) < F.lower(F.lpad(F.hex(F.ceil(share * F.lit(_UNIT)).cast("long")), 8, "0"))


def priority(seed: int | Column, *keys: Column) -> Column:
    return priority_bits(seed, *keys) / F.lit(_UNIT)


def priority_sql(seed: int | str, *keys: str) -> str:
    """The same number in DuckDB."""
    parts = ", ".join([f"'{seed}'" if isinstance(seed, int) else seed, *[f"({k})::VARCHAR" for k in keys]])
    return f"(('0x' || substr(md5(concat_ws('|', {parts})), 1, 8))::BIGINT / {_UNIT})"
