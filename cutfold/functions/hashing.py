"""Salted integer mixing that Spark and any SQL engine compute alike.

Two squarings between affine steps modulo 2**31 - 1; every product stays below
2**62, so BIGINT arithmetic never overflows. Salts enter each affine step with a
multiplier of their own, so changing the salt does not just shift the values.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P = 2**31 - 1
# Multipliers of the value, of the salt, and constants, per step.
_STEPS = ((1103515245, 747796405, 12345), (1664525, 1390208333, 1013904223), (69069, 1597334677, 362437))


def salt(seed: int, cycle: int = 0, level: int = 0, rnd: int = 0) -> int:
    return (seed * 1_000_003 + cycle * 10_007 + level * 101 + rnd) % P


def mix_sql(x: str, s: int) -> str:
    """SQL text of the mix of a BIGINT expression."""
    y = f"((({x}) % {P} + {P}) % {P})"
    for i, (a, b, c) in enumerate(_STEPS):
        y = f"(({y} * {a} + {(s * b + c) % P}) % {P})"
        if i < len(_STEPS) - 1:
            y = f"(({y} * {y}) % {P})"
    return y


def mix(x: Column, s: int) -> Column:
    """The mix of a BIGINT column, in [0, 2**31 - 1)."""
    y = F.pmod(x.cast("long"), F.lit(P).cast("long"))
    for i, (a, b, c) in enumerate(_STEPS):
        y = (y * F.lit(a) + F.lit((s * b + c) % P)) % F.lit(P)
        if i < len(_STEPS) - 1:
            y = (y * y) % F.lit(P)
    return y


def mix_int(x: int, s: int) -> int:
    y = x % P
    for i, (a, b, c) in enumerate(_STEPS):
        y = (y * a + (s * b + c) % P) % P
        if i < len(_STEPS) - 1:
            y = y * y % P
    return y


def _below(y: np.ndarray) -> np.ndarray:
    """``y % P`` for values under 2**62, by the bits of a Mersenne prime."""
    y = (y & P) + (y >> 31)
    y = (y & P) + (y >> 31)
    y -= P * (y >= P)
    return y


def mix_array(x: np.ndarray, s: int) -> np.ndarray:
    """The mix of an array of int64."""
    y = x.astype(np.int64) % P
    for i, (a, b, c) in enumerate(_STEPS):
        y = _below(y * a + (s * b + c) % P)
        if i < len(_STEPS) - 1:
            y = _below(y * y)
    return y


def part_array(x: np.ndarray, s: int, parts: int) -> np.ndarray:
    return mix_array(x, s) * parts // P


def part_of(x: Column, s: int, parts: int) -> Column:
    """One of ``parts`` parts, from the high end of the mix."""
    scaled = mix(x, s) * F.lit(parts)
    return ((scaled - scaled % F.lit(P)) / F.lit(P)).cast("int")


def part_sql(x: str, s: int, parts: int) -> str:
    m = f"({mix_sql(x, s)} * {parts})"
    return f"cast(({m} - {m} % {P}) / {P} AS INT)"


def tie(node: Column, other: Column, s: int) -> Column:
    """A hash of a pair of ids for breaking ties."""
    return mix(mix(node, s) + mix(other, (s + 1) % P), (s + 2) % P)


def tie_sql(node: str, other: str, s: int) -> str:
    return mix_sql(f"{mix_sql(node, s)} + {mix_sql(other, (s + 1) % P)}", (s + 2) % P)


def text_id(text: Column) -> Column:
    """60 bits of a text's MD5 as a BIGINT."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def text_id_sql(text: str) -> str:
    return f"cast('0x' || substr(md5({text}), 1, 15) AS BIGINT)"
