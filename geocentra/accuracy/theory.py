"""What theory expects of one counter, and what counters cost."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# The published constants of the relative standard deviation by number of registers.
BETA = {16: 1.106, 32: 1.070, 64: 1.054, 128: 1.046}
BETA_LIMIT = 1.039

#: Bytes a node beside its registers: one accumulator, and four flags of a bit.
NODE_BYTES = 4 + 0.5


def theoretical_rsd(p: int, k: int = 1) -> float:
    """The relative standard deviation of one counter of p registers, of the mean of k independent ones."""
    return BETA.get(p, BETA_LIMIT) / math.sqrt(p) / math.sqrt(k)


def theory_table(runs: DataFrame, ps: list[int]) -> DataFrame:
    """p, k, rsd for each distinct k of the rows."""
    p, beta = F.explode(F.array(*[F.lit(p) for p in ps])).alias("p"), F.lit(BETA_LIMIT)
    for registers, value in BETA.items():
        beta = F.when(F.col("p") == registers, value).otherwise(beta)
    rsd = beta / F.sqrt("p") / F.sqrt("k")
    # Rounded as a binary number: F.round takes the shortest decimal, and lifts what lies just below a half.
    return runs.select("k").distinct().select(p, "k").select("p", "k", (F.floor(rsd * 1e6 + 0.5) / 1e6).alias("rsd"))


def footprint(n: int, p: int, bits: int = 6) -> float:
    """Bytes of core memory for n nodes with p registers of `bits` bits."""
    return n * (p * bits / 8 + NODE_BYTES)


def footprint_table(counted: DataFrame, ps: list[int], digits: int = 1) -> DataFrame:
    """p, gib for the n of a row."""
    rows = counted.select("n", F.explode(F.array(*[F.lit(p) for p in ps])).alias("p"))
    return rows.select("p", F.round(F.col("n") * (F.col("p") * 6 / 8 + NODE_BYTES) / 2**30, digits).alias("gib"))


def throughput(seconds: float, arcs: int, cores: int) -> float:
    """Nanoseconds per arc and core of one iteration."""
    return seconds * cores / arcs * 1e9
