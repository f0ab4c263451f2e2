"""An arithmetic hash that Spark and DuckDB evaluate alike.

Three quadratic rounds modulo a Mersenne prime; every term stays below 2^63.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The modulus and the factors of the three rounds.
PRIME = 2147483647
FACTORS = (40503, 69069, 1013904223)


def arithmetic_hash(key: Column, seed: int | Column) -> Column:
    """A long in [0, PRIME) for a non-negative long key."""
    seed = F.lit(seed).cast("bigint") if isinstance(seed, int) else seed
    h = key.cast("bigint") + 1
    for c in FACTORS:
        h = (h * h + F.lit(c).cast("bigint") * h + seed) % F.lit(PRIME).cast("bigint")
    return h


def uniform(key: Column, seed: int | Column) -> Column:
    """A double in [0, 1)."""
    return arithmetic_hash(key, seed).cast("double") / F.lit(float(PRIME))


def hash_sql(key: str, seed: str | int) -> str:
    """The same hash as a DuckDB expression."""
    h = f"(CAST({key} AS BIGINT) + 1)"
    for c in FACTORS:
        h = f"(({h} * {h} + CAST({c} AS BIGINT) * {h} + CAST({seed} AS BIGINT)) % {PRIME})"
    return h


def hash_macro() -> str:
    """CTE-free form for SQL text: nested selects keep each round evaluated once."""
    return "list_reduce([{0}::BIGINT + 1, 40503, 69069, 1013904223], lambda h, c: (h * h + c * h + {1}) % 2147483647)"
