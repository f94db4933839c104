"""A hash with the same values in Spark, in DuckDB and in Python: two rounds of a linear congruence around a half-word swap."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Multiplier, increment per salt, increment and modulus of a round.
A, S, C, M = 1103515245, 12345, 1013904223, 1 << 31


def _long(x) -> Column:
    return (F.lit(x) if isinstance(x, int) else F.col(x) if isinstance(x, str) else x).cast("long")


def mix(x, salt: int) -> Column:
    """One round, below 2^31."""
    return (_long(x) % M * A + (salt * S + C)) % M


def draw(x, salt: int, n) -> Column:
    """A number in 0 .. n-1 (n at most 2^21)."""
    m = mix(x, salt)
    swapped = F.shiftright(m, 16) + m % 65536 * 32768
    return F.shiftright(mix(swapped, salt + 7), 10) % _long(n)


def mix_sql(x: str, salt: int) -> str:
    return f"((({x})::BIGINT % {M}) * {A} + {salt * S + C}) % {M}"


def draw_sql(x: str, salt: int, n: str | int) -> str:
    m = f"({mix_sql(x, salt)})"
    return f"((({mix_sql(f'{m} // 65536 + {m} % 65536 * 32768', salt + 7)}) // 1024) % ({n}))"


def mix_py(x: int, salt: int) -> int:
    return (x % M * A + salt * S + C) % M


def draw_py(x: int, salt: int, n: int) -> int:
    m = mix_py(x, salt)
    return mix_py(m // 65536 + m % 65536 * 32768, salt + 7) // 1024 % n
