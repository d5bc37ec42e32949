"""Cardinality counters as rows (register, rank), all in built-in functions."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geocentra.errors import ParameterError

#: Bits of the portable hash: 15 hexadecimal digits of an md5, equal in any engine.
MD5_BITS = 60

# Bias constants of the published estimator for small numbers of registers.
_ALPHA = {16: 0.673, 32: 0.697, 64: 0.709}


def log2_registers(p: int) -> int:
    """b for p = 2**b registers."""
    b = p.bit_length() - 1
    if p < 16 or p != 1 << b:
        raise ParameterError(f"p must be a power of two and at least 16, not {p}")
    return b


def alpha(p: int) -> float:
    return _ALPHA.get(p, 0.7213 / (1 + 1.079 / p))


def md5_bits(text: Column) -> Column:
    """The first 60 bits of a text's md5 as a number."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def rank(rest: Column, width: int) -> Column:
    """Leading zeros of a number of `width` bits, plus one; width + 1 for zero."""
    return F.when(rest == 0, width + 1).otherwise(width + 1 - F.length(F.bin(rest)))


def register_of(text: Column, p: int, hash: str = "md5", seed: Column | None = None) -> tuple[Column, Column]:
    """(reg, rho) of an item: the leading bits of its hash name a register, the rest give the rank of the first one bit.

    hash="md5" takes 60 bits of the md5 of the text; hash="xx64" takes 64 bits of
    xxhash64 over the text and the seed, and is faster.
    """
    b = log2_registers(p)
    if hash == "md5":
        width = MD5_BITS - b
        h = md5_bits(text)
        return F.shiftright(h, width).cast("int"), rank(h.bitwiseAND(F.lit((1 << width) - 1)), width).cast("int")
    if hash != "xx64":
        raise ParameterError(f"hash must be 'md5' or 'xx64', not {hash!r}")
    h = F.xxhash64(text) if seed is None else F.xxhash64(text, seed)
    width = 64 - b
    rest = F.shiftleft(h, b)
    return F.shiftrightunsigned(h, width).cast("int"), F.when(rest == 0, width + 1).otherwise(65 - F.length(F.bin(rest))).cast("int")


def union_registers(registers: DataFrame, keys: list[str]) -> DataFrame:
    """Registers of the union of counters: the largest rank of each register. Partial maxima come before the shuffle."""
    return registers.groupBy(*keys, "reg").agg(F.max("rho").alias("rho"))


def estimate_raw(sum_inverse: Column, p: int) -> Column:
    """Size from the sum of 2**-rho over all p registers (an untouched one counts 1)."""
    return F.lit(alpha(p) * p * p) / sum_inverse


def estimate(sum_inverse: Column, zeros: Column, p: int) -> Column:
    """Size with the published small-cardinality branch: linear counting while registers are untouched and the raw size is low."""
    raw = estimate_raw(sum_inverse, p)
    return F.when((raw <= 2.5 * p) & (zeros > 0), p * F.log(F.lit(float(p)) / zeros)).otherwise(raw)


def hll_count(df: DataFrame, item: str, by: list[str], p: int = 64, seed: int = 0, hash: str = "md5") -> DataFrame:
    """by, size: an estimate of the number of distinct items of each group."""
    reg, rho = register_of(F.concat_ws(":", F.lit(seed), F.col(item).cast("string")), p, hash)
    merged = union_registers(df.where(F.col(item).isNotNull()).select(*by, reg.alias("reg"), rho.alias("rho")), by)
    sums = merged.groupBy(*by).agg((F.lit(float(p)) - F.sum(1 - F.pow(F.lit(2.0), -F.col("rho")))).alias("s"), (F.lit(p) - F.count(F.lit(1))).alias("z"))
    return sums.select(*by, estimate(F.col("s"), F.col("z"), p).alias("size"))


def register_bits(n: int, total_weight: int | None = None) -> int:
    """Bits of a register for n items, or for their total weight."""
    items = max(4, total_weight or n)
    return math.ceil(math.log2(math.log2(items)))


def bits_of(n: Column) -> Column:
    """The same of a column of item counts."""
    return F.ceil(F.log2(F.log2(F.greatest(F.lit(4), n)))).cast("int")
