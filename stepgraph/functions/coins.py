"""Reproducible randomness that any SQL engine can repeat: a linear mix modulo a 31-bit prime."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = 2_147_483_647


def draw(ident: Column, *salt: int) -> Column:
    """An integer below PRIME; ids are reduced before they are multiplied, so nothing overflows."""
    x = F.pmod(ident.cast("long"), F.lit(PRIME))
    for k, s in enumerate(salt):
        x = F.pmod(x * (48_271 + 2 * k) + (s * 16_807 + 12_345) % PRIME, F.lit(PRIME))
    return F.pmod(x * 69_621 + 7, F.lit(PRIME))


def unit(ident: Column, *salt: int) -> Column:
    return draw(ident, *salt) / F.lit(float(PRIME))
