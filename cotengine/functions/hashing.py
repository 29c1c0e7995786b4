"""Deterministic hashing that Spark and any SQL engine with md5 agree on.

``h8`` is the integer of the first eight hex digits of an md5, ``unit`` a number in [0, 1) for
a seed and an id. Both are independent of partitioning, task retries and Python's hash seed.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Prime of the universal hash family, its seed, bands, rows of a band.
PRIME, SEED, BANDS, ROWS = (1 << 31) - 1, 42, 24, 10


def h8(text: Column) -> Column:
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def unit(key: Column, seed: int | str) -> Column:
    return h8(F.concat(F.lit(f"{seed}:"), key.cast("string"))) / F.lit(float(1 << 32))


def h8_of(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:8], 16)


def family(n: int = BANDS * ROWS, seed: int = SEED) -> tuple[list[int], list[int]]:
    """Multipliers and increments of ``n`` universal hashes."""
    return [1 + h8_of(f"{seed}:{i}:a") % (PRIME - 1) for i in range(n)], [h8_of(f"{seed}:{i}:b") % PRIME for i in range(n)]
