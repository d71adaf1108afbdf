"""Pseudo-random choices by an integer formula that Spark and other SQL engines evaluate alike."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The prime that bounds mix().
PRIME = 2147483647


def mix_sql(x: str, salt: int = 0) -> str:
    """SQL for mix(); x is an expression of a whole number that is not negative."""
    z = f"((48271 * (CAST({x} AS BIGINT) % {PRIME}) + {69621 * salt + 1}) % {PRIME})"
    return f"(({z} * {z} + 40692 * {z} + 17) % {PRIME})"


def mix(x: Column | str, salt: int = 0) -> Column:
    """A number in [0, PRIME) that looks random in x and salt. Other salts give other orders."""
    x = F.col(x) if isinstance(x, str) else x
    z = (F.lit(48271).cast("bigint") * (x.cast("bigint") % PRIME) + F.lit(69621 * salt + 1)) % PRIME
    return (z * z + F.lit(40692) * z + 17) % PRIME


def mix_int(x: int, salt: int = 0) -> int:
    z = (48271 * (x % PRIME) + 69621 * salt + 1) % PRIME
    return (z * z + 40692 * z + 17) % PRIME
