"""Hashes that name parts. `mixed` is for production; `modular` can be written in any SQL and never leaves 64 bits."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Fixed values of the modular hash.
MODULUS, FACTOR, SECOND = 2147483647, 1597334677, 7919


def mixed(parts: int, *ids: Column) -> Column:
    return F.pmod(F.xxhash64(*ids), F.lit(parts)).cast("int")


def modular(parts: int, *ids: Column) -> Column:
    x = F.pmod(ids[0], F.lit(MODULUS))
    if len(ids) > 1:
        x = F.pmod(x + F.pmod(ids[1], F.lit(MODULUS)) * SECOND, F.lit(MODULUS))
    return F.pmod(F.pmod(x * FACTOR, F.lit(MODULUS)), F.lit(parts)).cast("int")


HASHES = {"mixed": mixed, "modular": modular}
