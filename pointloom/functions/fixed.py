"""Fixed-point numbers and hashed draws that give the same values on any partitioning and in SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Draws are integers below this prime.
PRIME = 1_000_003
#: Multipliers of the seed and of up to five keys.
KEYS = (7919, 104_729, 224_737, 350_377, 479_909, 611_953)


def fx6(x: Column) -> Column:
    """Micro-units, half up; sums of them do not depend on order."""
    return F.floor(x * F.lit(1000000) + F.lit(0.5)).cast("long")


def draw(seed: int, *keys: Column) -> Column:
    """A pseudo-random integer in [0, PRIME) of a seed and integer keys: two rounds of a quadratic map, so near keys part."""
    total = F.lit(seed * KEYS[0]).cast("long")
    for k, m in zip(keys, KEYS[1:], strict=False):
        total = total + F.pmod(k.cast("long"), F.lit(PRIME)) * F.lit(m).cast("long")
    h = F.pmod(total, F.lit(PRIME).cast("long"))
    for _ in range(2):
        h = (h * h + h * 31 + 17) % F.lit(PRIME).cast("long")
    return h


def draw_of(seed: int, *keys: np.ndarray) -> np.ndarray:
    """:func:`draw` of arrays of whole numbers."""
    total = np.int64(seed * KEYS[0])
    for k, m in zip(keys, KEYS[1:], strict=False):
        total = total + np.mod(np.asarray(k, np.int64), PRIME) * m
    h = np.mod(total, PRIME)
    for _ in range(2):
        h = (h * h + h * 31 + 17) % PRIME
    return h


def unit_draw(seed: int, *keys: Column) -> Column:
    return draw(seed, *keys) / F.lit(float(PRIME))


def sql_fx6(x: str) -> str:
    return f"CAST(floor(({x}) * 1000000 + 0.5::DOUBLE) AS BIGINT)"


def sql_draw(seed: int, *keys: str) -> str:
    total = " + ".join([str(seed * KEYS[0]), *(f"((({k})::BIGINT % {PRIME} + {PRIME}) % {PRIME}) * {m}" for k, m in zip(keys, KEYS[1:], strict=False))])
    h = f"(({total})::BIGINT % {PRIME})"
    for _ in range(2):
        h = f"list_transform([{h}], lambda q: (q * q + q * 31 + 17) % {PRIME})[1]"
    return h


def sql_unit_draw(seed: int, *keys: str) -> str:
    return f"({sql_draw(seed, *keys)} / {float(PRIME)}::DOUBLE)"
