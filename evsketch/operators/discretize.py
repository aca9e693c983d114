"""Integer registers: rounding to a multiple of epsilon, and shift-rounding.

Both commute with the maximum (rounding is monotone), so they are applied to the surviving
registers; ``round_at="scan"`` rounds each item first and keeps the greatest, for comparison.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evsketch.functions import hashing
from evsketch.functions.gumbel import gumbel_from_hash
from evsketch.operators.registers import Cols, items
from evsketch.spec import SketchSpec


def real_registers(regs: DataFrame, spec: SketchSpec) -> DataFrame:
    """w replaced by the Gumbel value x."""
    return regs.withColumn("x", gumbel_from_hash(F.col("w"), spec.bits)).drop("w")


def shift_round_registers(regs: DataFrame, spec: SketchSpec) -> DataFrame:
    """w replaced by q = floor(x + c), a TINYINT; the value is q - c."""
    q = F.floor(gumbel_from_hash(F.col("w"), spec.bits) + hashing.offset(spec, F.col("reg")))
    return regs.withColumn("q", q.cast("tinyint")).drop("w")


def scan_rounded(df: DataFrame, cols: Cols, by: Sequence[str] = (), spec: SketchSpec = SketchSpec()) -> DataFrame:
    """Integer registers by rounding every item's draw before the maximum."""
    item = F.col("item")
    read = items(df, cols, by).select(*by, hashing.register(spec, item).alias("reg"), hashing.draw(spec, item).alias("w"))
    return shift_round_registers(read, spec).groupBy(*by, "reg").agg(F.max("q").alias("q"))


def round_registers(regs: DataFrame, eps: float, spec: SketchSpec, mode: str = "nearest") -> DataFrame:
    """w replaced by m, the multiple of eps nearest to x (or below it, ``floor``), a SMALLINT."""
    ratio = gumbel_from_hash(F.col("w"), spec.bits) / F.lit(eps)
    whole = {"nearest": F.floor(ratio + 0.5), "floor": F.floor(ratio)}[mode]
    return regs.withColumn("m", whole.cast("smallint")).drop("w")
