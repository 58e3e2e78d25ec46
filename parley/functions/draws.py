"""Seeded random draws by integer arithmetic modulo 2**31 - 1, equal in Spark, DuckDB and NumPy on any number of tasks.

Every key is multiplied in and folded; three more rounds of folding high bits into low ones and multiplying part the draws
of neighbouring keys (multiplication alone leaves them on lines). Leading numbers are mixed before a column is built.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P = 2147483647
#: Fixed multiplier of a key, and multipliers and shifts of the three last rounds.
MULT = 48271
LAST = ((69621, 15), (742938285, 12), (950706376, 17))


def _leading(keys: tuple) -> tuple[int, tuple]:
    """The state after the numbers that come first, and the other keys."""
    x, at = 17, 0
    while at < len(keys) and isinstance(keys[at], (int, np.integer)):
        x = (x * MULT + int(keys[at]) % P + 1) % P
        x ^= x >> 15
        at += 1
    return x, keys[at:]


def mixed(*keys: Column | int) -> Column:
    """An integer below P from integer keys."""
    start, rest = _leading(keys)
    x: Column = F.lit(start).cast("long")
    for k in rest:
        k = F.pmod(k.cast("long"), F.lit(P)) if isinstance(k, Column) else F.lit(int(k) % P).cast("long")
        x = F.pmod(x * MULT + k + 1, F.lit(P))
        x = x.bitwiseXOR(F.shiftright(x, 15))
    for times, shift in LAST:
        x = F.pmod(x.bitwiseXOR(F.shiftright(x, shift)) * times, F.lit(P))
    return x


def mixed_sql(*keys: str | int) -> str:
    start, rest = _leading(keys)
    x = f"{start}::BIGINT"
    for k in rest:
        own = f"((({k})::BIGINT % {P} + {P}) % {P})" if isinstance(k, str) else str(int(k) % P)
        x = f"((({x}) * {MULT} + {own} + 1) % {P})"
        x = f"xor({x}, {x} >> 15)"
    for times, shift in LAST:
        x = f"((xor({x}, {x} >> {shift}) * {times}) % {P})"
    return x


def mixed_np(*keys: np.ndarray | int) -> np.ndarray:
    x: np.ndarray = np.int64(17)
    for k in keys:
        x = (x * MULT + np.mod(np.asarray(k, np.int64), P) + 1) % P
        x = x ^ (x >> 15)
    for times, shift in LAST:
        x = ((x ^ (x >> shift)) * times) % P
    return x


def uniform(*keys: Column | int) -> Column:
    """In (0, 1)."""
    return (mixed(*keys) + 0.5) / float(P)


def uniform_np(*keys: np.ndarray | int) -> np.ndarray:
    return (mixed_np(*keys) + 0.5) / P


def normal(*keys: Column | int) -> Column:
    return F.sqrt(-2 * F.log(uniform(*keys, 1))) * F.cos(2 * np.pi * uniform(*keys, 2))


def normal_np(*keys: np.ndarray | int) -> np.ndarray:
    return np.sqrt(-2 * np.log(uniform_np(*keys, 1))) * np.cos(2 * np.pi * uniform_np(*keys, 2))


def laplace(*keys: Column | int) -> Column:
    u = uniform(*keys) - 0.5
    return -F.signum(u) * F.log(1 - 2 * F.abs(u))


def laplace_np(*keys: np.ndarray | int) -> np.ndarray:
    u = uniform_np(*keys) - 0.5
    return -np.sign(u) * np.log(1 - 2 * np.abs(u))
