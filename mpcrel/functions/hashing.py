"""Public pairwise-independent hashing of keys to buckets."""

from __future__ import annotations

import random

from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1


def coefficients(limbs: int, seed: int) -> list[int]:
    """One multiplier for each limb and an addend, below the prime."""
    rng = random.Random(seed)
    return [rng.randrange(1, PRIME) for _ in range(limbs)] + [rng.randrange(PRIME)]


def pairwise(cols: list[Column], types: list[str], buckets: int, seed: int = 5) -> Column:
    """Affine hash modulo a prime over 31-bit limbs; words that are no integers enter through xxhash64."""
    *factors, total = coefficients(3 * len(cols), seed)
    out = F.lit(total).cast("long")
    for i, (c, kind) in enumerate(zip(cols, types)):
        word = c.cast("long") if kind in ("tinyint", "smallint", "int", "bigint") else F.xxhash64(c)
        limbs = [word.bitwiseAND(F.lit(PRIME)), F.shiftrightunsigned(word, 31).bitwiseAND(F.lit(PRIME)), F.shiftrightunsigned(word, 62)]
        for f, limb in zip(factors[3 * i :], limbs):
            out = (out + F.lit(f).cast("long") * limb) % PRIME
    return (out % buckets).cast("long")


def pairwise_sql(col: str, buckets: int, seed: int = 5) -> str:
    """The same in SQL, for one non-negative integer below 2^31."""
    *factors, total = coefficients(3, seed)
    return f"(({total} + {factors[0]} * CAST({col} AS BIGINT)) % {PRIME}) % {buckets}"
