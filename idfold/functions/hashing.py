"""Portable hashes: plain integer arithmetic, the same in every engine."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The prime modulus and the multipliers and offsets of the hash functions by seed.
PRIME = 2147483647
CONSTANTS = ((48271, 12820163), (69621, 7368787), (16807, 1103515), (39373, 99991))


def universal(id_: Column, rows: Column | int, seed: int = 0) -> Column:
    """((a * (id mod p) + b) mod p) mod rows."""
    a, b = CONSTANTS[seed]
    return ((F.pmod(id_, F.lit(PRIME)) * a + b) % PRIME) % rows


def universal_sql(id_: str, rows: str | int, seed: int = 0) -> str:
    a, b = CONSTANTS[seed]
    return f"((({id_} % {PRIME}) * {a} + {b}) % {PRIME}) % {rows}"


def prehash(id_: Column, heights: Column | int) -> Column:
    """Ids outside 0 .. heights - 1 are hashed into the range; ids inside stay."""
    inside = (id_ >= 0) & (id_ < heights)
    return F.when(inside, id_).otherwise(universal(F.abs(id_), heights))
