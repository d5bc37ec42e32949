"""Counters as one binary of p bytes a node: for dense sketches, where a row a register would be larger."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geocentra.sketch.registers import alpha


def _rows(column: pa.Array | pa.ChunkedArray, p: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint8).reshape(-1, p)


def pack_registers(registers: DataFrame, p: int) -> DataFrame:
    """node, regs from rows (node, reg, rho): byte j of regs is the rank of register j."""
    byte = F.lpad(F.hex("rho"), 2, "0")
    pairs = registers.groupBy("node").agg(F.map_from_entries(F.collect_list(F.struct("reg", byte.alias("x")))).alias("m"))
    return pairs.select("node", F.unhex(F.array_join(F.transform(F.sequence(F.lit(0), F.lit(p - 1)), lambda j: F.coalesce(F.element_at("m", j), F.lit("00"))), "")).alias("regs"))


def unpack_registers(packed: DataFrame, p: int) -> DataFrame:
    """node, reg, rho of all registers that are not zero."""
    digits = F.transform(F.sequence(F.lit(0), F.lit(p - 1)), lambda j: F.conv(F.substring(F.hex("regs"), j * 2 + 1, F.lit(2)), 16, 10).cast("int"))
    return packed.select("node", F.posexplode(digits).alias("reg", "rho")).where("rho > 0")


def estimate_packed(p: int):
    """A vectorised function from binaries to sizes; equals the built-in path."""
    from pyspark.sql.functions import arrow_udf

    @arrow_udf("double")
    def size(regs: pa.Array) -> pa.Array:
        table = _rows(regs, p)
        s, z = (2.0 ** -table.astype(float)).sum(axis=1), (table == 0).sum(axis=1)
        raw = alpha(p) * p * p / s
        with np.errstate(divide="ignore"):
            return pa.array(np.where((raw <= 2.5 * p) & (z > 0), p * np.log(p / np.maximum(z, 1)), raw))

    return size


def union_packed():
    """A grouped aggregate: the union of binaries."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("binary")
    def union(regs: pd.Series) -> bytes:
        return np.maximum.reduce([np.frombuffer(r, np.uint8) for r in regs]).tobytes()

    return union
