"""SQL functions and table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from geocentra.sketch.registers import MD5_BITS, alpha, log2_registers


def register_sql(spark: SparkSession, p: int = 64) -> None:
    """Temporary SQL functions, inlined by the optimiser: hll_hash, hll_reg, hll_rho, hll_est, and the discounts."""
    width = MD5_BITS - log2_registers(p)
    mask = (1 << width) - 1
    bodies = {
        "hll_hash(item STRING)": ("BIGINT", "CAST(conv(substring(md5(CAST(item AS BINARY)), 1, 15), 16, 10) AS BIGINT)"),
        "hll_reg(h BIGINT)": ("INT", f"CAST(shiftright(h, {width}) AS INT)"),
        "hll_rho(h BIGINT)": ("INT", f"CASE WHEN (h & {mask}L) = 0 THEN {width + 1} ELSE {width + 1} - length(bin(h & {mask}L)) END"),
        "hll_est(s DOUBLE, z DOUBLE)": ("DOUBLE", f"CASE WHEN {alpha(p) * p * p}D / s <= {2.5 * p}D AND z > 0 THEN {p}D * ln({float(p)}D / z) ELSE {alpha(p) * p * p}D / s END"),
        "discount_log(t INT)": ("DOUBLE", "1D / log2(t + 1)"),
        "discount_quadratic(t INT)": ("DOUBLE", "1D / (CAST(t AS DOUBLE) * t)"),
    }
    for signature, (kind, body) in bodies.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {signature} RETURNS {kind} RETURN {body}")


class NodeBalls:
    """Table function: a profile as an array of (t, size) structs -> rows t, size, grown."""

    def eval(self, steps):
        before = 0.0
        for step in sorted(steps or [], key=lambda s: s["t"]):
            yield step["t"], step["size"], step["size"] - before
            before = step["size"]


def register_node_balls(spark: SparkSession) -> None:
    spark.udtf.register("node_balls", F.udtf(NodeBalls, returnType="t int, size double, grown double"))


class ExpandRegisters:
    """Table function: a packed counter -> rows reg, rho of the registers that are not zero."""

    def eval(self, regs):
        for reg, rho in enumerate(regs or b""):
            if rho:
                yield reg, rho


def register_expand_registers(spark: SparkSession) -> None:
    spark.udtf.register("expand_registers", F.udtf(ExpandRegisters, returnType="reg int, rho int"))
