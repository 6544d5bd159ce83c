"""Draws that are pure functions of a seed and a key, so that retries, partitioning and engines don't change them."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Modulus of the universal hash.
PRIME = (1 << 31) - 1
#: A whole number is hashed as two digits of this base, so that products of a digit and a multiplier fit a BIGINT.
DIGIT_BITS = 30
UNIT = float(1 << 52)
_WORD = (1 << 32) - 1
#: Multiplier of the 32-bit mixer, below 2^31 so that products fit a BIGINT.
_MIX = 0x7FEB352D


def bits52(*key) -> Column:
    """52 bits from the md5 of the key's parts joined by colons."""
    parts = [k if isinstance(k, Column) else F.lit(str(k)) for k in key]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[p.cast("string") for p in parts]).cast("binary")), 1, 13), 16, 10).cast("long")


def bits52_of(*key) -> int:
    """``bits52`` of plain values."""
    return int(hashlib.md5(":".join(map(str, key)).encode()).hexdigest()[:13], 16)


def uniform(*key) -> Column:
    """A draw from [0, 1)."""
    return bits52(*key) / F.lit(UNIT)


def open_uniform(*key) -> Column:
    """A draw from (0, 1): its logarithm is finite."""
    return (bits52(*key) + F.lit(0.5)) / F.lit(UNIT)


def mix32(x):
    """Avalanche a 32-bit word: a Column of BIGINT or an array of int64."""
    if isinstance(x, Column):
        word, right = (lambda y: y.bitwiseAND(F.lit(_WORD))), F.shiftright
        cross = lambda a, b: a.bitwiseXOR(b)
    else:
        word, right, cross = (lambda y: y & _WORD), np.right_shift, np.bitwise_xor
    for shift in (16, 15):
        x = word(cross(x, right(x, shift)) * _MIX)
    return cross(x, right(x, 16))


def sql_mix32(x: str) -> str:
    for shift in (16, 15):
        x = f"((xor({x}, ({x}) >> {shift}) * {_MIX}) & {_WORD})"
    return f"xor({x}, ({x}) >> 16)"


def stream_word(seed: int, salt: str, index: int) -> int:
    """A 32-bit word that names a stream of draws, and one number in it."""
    return bits52_of(seed, salt, index) & _WORD


def universal_triple(seed: int, salt: str = "") -> tuple[int, int, int]:
    """Multipliers (not 0) of the low and the high digit and the shift of a 2-universal hash modulo PRIME."""
    mul = lambda name: 1 + bits52_of(name, f"{seed}{salt}") % (PRIME - 1)
    return mul("mul"), mul("high"), bits52_of("add", f"{seed}{salt}") % PRIME


def two_universal(col: Column, seed: int, m: int | None = None, salt: str = "") -> Column:
    """((a * low + c * high + b) mod p) mod m for whole numbers from 0 below 2^60, low and high their digits: numbers that
    differ collide by chance only, however large they are."""
    a, c, b = universal_triple(seed, salt)
    x = col.cast("long")
    low, high = x.bitwiseAND(F.lit((1 << DIGIT_BITS) - 1)), F.shiftright(x, DIGIT_BITS)
    h = F.pmod(low * F.lit(a) + high * F.lit(c) + F.lit(b), F.lit(PRIME))
    return h if m is None else F.pmod(h, F.lit(m))


#: Odd factor that spreads the low digit over a word.
_SPREAD = 0x5851F42D


def scramble(x, seed: int):
    """31 bits of a whole number from 0 below 2^60 (a Column, or an array of int64) without its order: a linear hash of
    neighbouring numbers keeps their lattice, and the least of such values isn't uniform over them."""
    word = stream_word(seed, "elem", 0)
    if isinstance(x, Column):
        low, high = x.bitwiseAND(F.lit((1 << DIGIT_BITS) - 1)), F.shiftright(x, DIGIT_BITS)
        near = mix32((high + word).bitwiseAND(F.lit(_WORD)))
        return F.shiftright(mix32((low * _SPREAD + near).bitwiseAND(F.lit(_WORD))), 1)
    return scramble_digits(x & ((1 << DIGIT_BITS) - 1), mix32(((x >> DIGIT_BITS) + word) & _WORD))


def scramble_digits(low: np.ndarray, near: np.ndarray) -> np.ndarray:
    """``scramble`` from the low digit and the mixed high one."""
    return mix32((low * _SPREAD + near) & _WORD) >> 1


def sql_scramble(expr: str, seed: int) -> str:
    near = sql_mix32(f"(((({expr}) >> {DIGIT_BITS}) + {stream_word(seed, 'elem', 0)}) & {_WORD})")
    return f"(({sql_mix32(f'(((({expr}) & {(1 << DIGIT_BITS) - 1}) * {_SPREAD} + {near}) & {_WORD})')}) >> 1)"


def sql_bits(*key: str) -> str:
    """``bits52`` for DuckDB; key parts are SQL expressions."""
    return f"('0x' || substr(md5(concat_ws(':', {', '.join(key)})), 1, 13))::BIGINT"


def sql_uniform(*key: str) -> str:
    return f"({sql_bits(*key)} / {UNIT})"


def sql_open(*key: str) -> str:
    return f"(({sql_bits(*key)} + 0.5::DOUBLE) / {UNIT})"


def sql_universal(expr: str, seed: int, salt: str = "") -> str:
    a, c, b = universal_triple(seed, salt)
    return f"((({expr})::BIGINT & {(1 << DIGIT_BITS) - 1}) * {a} + (({expr})::BIGINT >> {DIGIT_BITS}) * {c} + {b}) % {PRIME}"
