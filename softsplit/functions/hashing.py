"""Weights from hashes: the same numbers as Catalyst expressions and as numpy arrays.

Three codes are offered. `md5` has the same digits in other SQL engines, `xxh64` hashes feature, round and
cell with Spark's xxhash64, and `mix` hashes a feature once (xxhash64) and derives the code of each round
and cell by integer steps that Catalyst and numpy share; the trainers use `mix`.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, functions as F

#: Masks, multipliers and addends of the integer mixer (all factors below 2**31).
HALF, MASK = 2147483647, 4294967295
MULTIPLIERS = (1103515245, 1664525057, 1597334677)
ADDENDS = (12345, 1013904223, 741103597)
LOW_BITS = 8388607  # 2**23 - 1
CODE_BITS = 4611686018427387903  # 2**62 - 1


def bits_to_unit(code: Column) -> Column:
    """The low 23 bits as a number in [1, 2)."""
    return F.lit(1.0) + code.bitwiseAND(F.lit(LOW_BITS).cast("long")) / F.lit(float(LOW_BITS + 1))


def unit_to_sym(unit: Column) -> Column:
    """[1, 2) to [-1, 1)."""
    return unit * 2.0 - 3.0


def md5_code(text: Column) -> Column:
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def _xor_shift(x: Column, by: int) -> Column:
    return x.bitwiseXOR(F.shiftright(x, by))


def base_code(feature: Column, hash_fn: str = "xxh64") -> Column:
    """The code of a feature, made once: 62 bits of its xxhash64, or 60 of its md5."""
    name = feature.cast("string")
    if hash_fn == "md5":
        return F.conv(F.substring(F.md5(name), 1, 15), 16, 10).cast("long")
    return F.xxhash64(name).bitwiseAND(F.lit(CODE_BITS).cast("long"))


def _times(x: Column, by: int) -> Column:
    """The low 32 bits of x * by; x is below 2**32 and by below 2**31, so no product overflows."""
    return (x * F.lit(by).cast("long")).bitwiseAND(F.lit(MASK).cast("long"))


def mix_code(base: Column, round_: Column | int, cell: Column, seed: int = 0) -> Column:
    """The 32-bit code of (feature, round, cell) from the feature's base code.

    The low half of the base code meets the round before the high half joins, so two features that share a
    code in one round share none in the others.
    """
    mask = F.lit(MASK).cast("long")
    round_ = F.lit(round_).cast("long") if isinstance(round_, int) else round_.cast("long")
    low, high = base.bitwiseAND(F.lit(HALF).cast("long")), F.shiftright(base, 31)
    x = (low * F.lit(MULTIPLIERS[0]).cast("long") + (round_ + F.lit(seed * 1009 + 1)) * F.lit(ADDENDS[0]).cast("long")).bitwiseAND(mask)
    x = _xor_shift(_times(_xor_shift(x, 15).bitwiseXOR(high), MULTIPLIERS[2]), 13)
    x = _xor_shift(_times(x, MULTIPLIERS[1]), 16)
    x = x.bitwiseXOR(((cell.cast("long") + 1) * F.lit(ADDENDS[1]).cast("long")).bitwiseAND(mask))
    x = _xor_shift(_times(x, MULTIPLIERS[1]), 15)
    return _xor_shift(_times(x, MULTIPLIERS[2]), 16)


def mix_code_np(base: np.ndarray, round_: int, cells: np.ndarray, seed: int = 0) -> np.ndarray:
    """mix_code for all pairs of base codes and cells: (features x cells) uint32, whose products wrap by themselves."""
    base = base.astype(np.int64)
    x = ((base & HALF) * MULTIPLIERS[0] + (round_ + seed * 1009 + 1) * ADDENDS[0]) & MASK
    x = ((x ^ (x >> 15) ^ (base >> 31)) * MULTIPLIERS[2]) & MASK
    x = ((x ^ (x >> 13)) * MULTIPLIERS[1]) & MASK
    x ^= x >> 16
    y = x.astype(np.uint32)[:, None] ^ ((cells.astype(np.int64) + 1) * ADDENDS[1] & MASK).astype(np.uint32)[None, :]
    other = np.empty_like(y)
    for by, shift in ((MULTIPLIERS[1], 15), (MULTIPLIERS[2], 16)):
        y *= np.uint32(by)
        np.right_shift(y, np.uint32(shift), out=other)
        y ^= other
    return y


def sym_np(code: np.ndarray) -> np.ndarray:
    """The low 23 bits as a number in [-1, 1); exact."""
    out = (code & code.dtype.type(LOW_BITS)).astype(np.float64)
    out *= 2.0 / (LOW_BITS + 1)
    out -= 1.0
    return out


def md5_weights_np(names: int, round_: int, cells: int) -> np.ndarray:
    """The md5 weights of dense features 0 .. names-1 (names x cells), as hash_weight(..., "md5") has them."""
    codes = [[int(hashlib.md5(f"{i}|{round_}|{j}".encode()).hexdigest()[:8], 16) for j in range(cells)] for i in range(names)]
    return sym_np(np.array(codes, np.int64).reshape(names, cells))


def hash_weight(feature: Column, round_: int, cell: Column, hash_fn: str = "mix", seed: int = 0) -> Column:
    """The weight in [-1, 1) of a feature for a cell of a round."""
    if hash_fn == "md5":
        code = md5_code(F.concat_ws("|", feature.cast("string"), F.lit(str(round_)), cell.cast("string")))
    elif hash_fn == "xxh64":
        code = F.xxhash64(F.concat_ws("|", feature.cast("string"), F.lit(str(round_))), cell.cast("int"))
    elif hash_fn == "mix":
        code = mix_code(base_code(feature), round_, cell, seed)
    else:
        raise ValueError(f"unknown hash {hash_fn!r}")
    return unit_to_sym(bits_to_unit(code))


def law_np(sym: np.ndarray, sym2: np.ndarray, init: str, m: int = 1) -> np.ndarray:
    """Uniform codes in [-1, 1) turned to another weight law; sym2 is a second, independent set of codes."""
    if init == "uniform":
        return sym
    u, v = (sym + 1) / 2, (sym2 + 1) / 2
    normal = np.sqrt(-2 * np.log(np.maximum(1 - u, 1e-12))) * np.cos(2 * np.pi * v)
    if init == "normal":
        return normal
    if init == "mixture":
        return 0.5 * normal + np.where(((u * 8192).astype(np.int64) & 1) == 1, 0.5, -0.5)
    if init == "fan_avg":
        return sym * np.sqrt(6.0 / (m + 1))
    if init == "fan_in":
        return normal * np.sqrt(2.0 / m)
    raise ValueError(f"unknown weight law {init!r}")


def simhash(feats: Column, bits: int = 32) -> Column:
    """The sign projection for contrast: bit j is set when the weighted sum of +-1 hash bits j is not negative.

    feats: array<struct<f, v>>.
    """
    codes = F.transform(feats, lambda x: F.struct(md5_code(x["f"].cast("string")).alias("c"), x["v"].alias("v")))

    def bit(mask: int) -> Column:
        signed = lambda acc, x: acc + x["v"] * F.when(x["c"].bitwiseAND(F.lit(mask).cast("long")) != 0, 1.0).otherwise(-1.0)
        return F.when(F.aggregate(codes, F.lit(0.0), signed) >= 0, F.lit(mask).cast("long")).otherwise(F.lit(0).cast("long"))

    out = bit(1)
    for j in range(1, bits):
        out = out + bit(1 << j)
    return out
