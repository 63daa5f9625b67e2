"""Reproducible draws: a hash of a seed and ids, the same in every engine and under any partitioning."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

#: One seed a purpose; no stage uses another's.
SEEDS = {"hold": 101, "init": 102, "inc": 103, "comp": 104, "rival": 105, "random": 106, "mask": 107, "gap": 108, "batch": 109, "sample": 110, "burst": 111, "group": 112, "value": 113, "generate": 114}
SPAN = float(1 << 32)


def draw(seed: int, *ids: Column | str) -> Column:
    """A whole number in [0, 2^32) from md5 of the seed and the ids as text."""
    parts = [F.lit(str(seed)), *((F.col(i) if isinstance(i, str) else i).cast("string") for i in ids)]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts).cast("binary")), 1, 8), 16, 10).cast("long")


def unit(seed: int, *ids: Column | str) -> Column:
    """A draw in [0, 1)."""
    return draw(seed, *ids) / F.lit(SPAN)


def draw_sql(seed: int, *ids: str) -> str:
    """The same draw in DuckDB."""
    return f"('0x' || substr(md5(concat_ws('|', {', '.join([repr(str(seed)), *(f'CAST({i} AS VARCHAR)' for i in ids)])})), 1, 8))::BIGINT"


def unit_sql(seed: int, *ids: str) -> str:
    return f"({draw_sql(seed, *ids)} / 4294967296.0)"


def draw_py(seed: int, *ids: object) -> int:
    """The same draw in Python."""
    return int(hashlib.md5("|".join(map(str, (seed, *ids))).encode()).hexdigest()[:8], 16)
