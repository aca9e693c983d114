"""Cost and accuracy measures, from many-seed runs and from single sketches."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evsketch.functions import gumbel
from evsketch.functions.gumbel import EULER_GAMMA

ERROR_SCALES = {"geometric": math.sqrt(gumbel.VARIANCE), "shifted": math.sqrt(gumbel.VARIANCE + gumbel.ROUNDING_VARIANCE), "harmonic": 1.0, "harmonic_shifted": math.sqrt((math.e + 1) / (math.e - 1) - 1), "loglog": 1.30, "hyperloglog": 1.04}


def _hex(text: Column, start: int, digits: int) -> Column:
    return F.conv(F.substring(text, start, digits), 16, 10).cast("long")


def _digest(*parts: Column) -> Column:
    return F.md5(F.concat(*[p.cast("string") for p in parts]).cast("binary"))


def seeded_draws(items: DataFrame, seeds: int) -> DataFrame:
    """(seed, h, w) of every distinct item under each of ``seeds`` portable seeds s1, s2, ...

    The seed grid is broadcast against distinct items: for test scale only.
    """
    spark = items.sparkSession
    grid = spark.range(1, seeds + 1).select(F.col("id").cast("int").alias("seed"))
    d = items.select("item").distinct().crossJoin(F.broadcast(grid)).select("seed", _digest(F.lit("s"), F.col("seed"), F.lit(":"), F.col("item")).alias("m"))
    return d.select("seed", _hex(F.col("m"), 17, 8).alias("h"), _hex(F.col("m"), 1, 13).alias("w"))


def seeded_registers(draws: DataFrame, ks: Sequence[int], seeds: int, dense: bool = True) -> DataFrame:
    """(k, seed, reg, w) averaged registers of each run, with seed draws if ``dense``."""
    spark = draws.sparkSession
    sizes = spark.createDataFrame([(k,) for k in ks], "k int")
    regs = draws.crossJoin(F.broadcast(sizes)).groupBy("k", "seed", F.pmod("h", F.col("k")).cast("int").alias("reg")).agg(F.min("w").alias("w"))
    if not dense:
        return regs
    grid = spark.range(1, seeds + 1).select(F.col("id").cast("int").alias("seed"))
    start = sizes.crossJoin(grid).withColumn("reg", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    start = start.withColumn("w", _hex(_digest(F.lit("s"), F.col("seed"), F.lit("#reg:"), F.col("reg")), 1, 13))
    return regs.unionByName(start).groupBy("k", "seed", "reg").agg(F.min("w").alias("w"))


def seeded_full(items: DataFrame, k: int, seeds: int) -> DataFrame:
    """(seed, reg, w) of all-register runs."""
    spark = items.sparkSession
    grid = spark.range(1, seeds + 1).select(F.col("id").cast("int").alias("seed"))
    spread = items.select("item").distinct().crossJoin(F.broadcast(grid)).withColumn("reg", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))
    w = _hex(_digest(F.lit("s"), F.col("seed"), F.lit("/"), F.col("reg"), F.lit(":"), F.col("item")), 1, 13)
    return spread.groupBy("seed", "reg").agg(F.min(w).alias("w"))


def offset(seed: Column, reg: Column) -> Column:
    return _hex(_digest(F.lit("s"), seed, F.lit("#off:"), reg), 1, 13) / F.lit(float(1 << 52))


def x_of(w: Column) -> Column:
    return gumbel.gumbel_from_hash(w, 52)


def geometric(factor: Column | float) -> Column:
    return factor * F.exp(F.avg(x_of(F.col("w"))) - EULER_GAMMA)


def harmonic(scale: Column | float) -> Column:
    return scale / F.sum(gumbel.exponential_from_hash(F.col("w"), 52))


def relative_error(z: Column, n: Column) -> Column:
    return F.abs(z - n) / n


def summary(runs: DataFrame, by: Sequence[str], k: Column) -> DataFrame:
    """Mean ratio, bias, normalised standard error and the share of runs within pi/sqrt(k) of n."""
    ratio = F.col("z") / F.col("n")
    inside = relative_error(F.col("z"), F.col("n")) <= math.pi / F.sqrt(k)
    held = runs.select(*by, k.alias("k__"), ratio.alias("ratio"), inside.cast("double").alias("inside"))
    return held.groupBy(*by).agg(
        F.round(F.avg("ratio"), 6).alias("mean_ratio"), F.round(F.avg("ratio") - 1, 6).alias("bias"), F.round(F.sqrt(F.max("k__")) * F.stddev_samp("ratio"), 6).alias("norm_std"), F.round(F.avg("inside"), 6).alias("coverage")
    )


def bits_for(low: int, high: int) -> int:
    """Bits of an integer register with values low..high."""
    return max(1, math.ceil(math.log2(high - low + 1)))


def space_table(eps: float, delta: float, n: float, universe: float) -> list[tuple[str, float]]:
    """Total bits by method: exact bitmap, optimal bound, trailing zeros, real, rounded, shift-rounded."""
    k = math.ceil(eps**-2)
    loglog = math.ceil(math.log2(math.log2(n)))
    reach = math.ceil(2 * math.log(n)) + 4
    return [
        ("bitmap", universe),
        ("optimal_bound", math.log2(1 / delta) / eps**2 + math.log2(n)),
        ("trailing_zeros", float(k * (loglog + 1))),
        ("real_registers", float(64 * k)),
        ("rounded_registers", float(k * math.ceil(math.log2(reach / eps)))),
        ("shift_rounded_registers", float(k * math.ceil(math.log2(reach)))),
    ]


def space_columns(eps: float, delta: float, n: Column, universe: Column) -> list[tuple[str, Column]]:
    """space_table for columns n (2 at least) and universe."""
    k = math.ceil(eps**-2)
    m = F.greatest(n, F.lit(2)).cast("double")

    def up(v: Column) -> Column:  # logarithms of powers of two may end just above a whole number
        return F.ceil(v - 1e-9).cast("double")

    reach = up(2 * F.ln(m)) + 4
    return [
        ("bitmap", universe.cast("double")),
        ("optimal_bound", math.log2(1 / delta) / eps**2 + F.log2(m)),
        ("trailing_zeros", k * (up(F.log2(F.log2(m))) + 1)),
        ("real_registers", F.lit(float(64 * k))),
        ("rounded_registers", k * up(F.log2(reach / eps))),
        ("shift_rounded_registers", k * up(F.log2(reach))),
    ]


def expected_ops(rows: int, k: int, layout: str) -> int:
    """Register updates that a stream of ``rows`` items costs."""
    return rows * (k if layout == "full" else 1)
