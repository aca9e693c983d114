"""What the sketches are compared with: exact counts, trailing-zero sketches, Spark's own."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evsketch.functions import hashing
from evsketch.functions.items import canonical_item
from evsketch.operators.registers import Cols, items
from evsketch.spec import SketchSpec

#: Correction of bit-pattern probabilistic counting (fixed value).
PATTERN_PHI = 0.77351


def exact_distinct(df: DataFrame, cols: Cols, by: Sequence[str] = ()) -> DataFrame:
    return items(df, cols, by).groupBy(*by).agg(F.count_distinct("item").alias("n"))


def bitmap_distinct(df: DataFrame, col: str) -> DataFrame:
    """Exact count of non-negative integers by a bitmap over the universe, one bit a value."""
    v = F.col(col).cast("long")
    bits = df.where(v >= 0).groupBy(F.bitmap_bucket_number(v + 1).alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(v + 1)).alias("bits"))
    return bits.agg(F.coalesce(F.sum(F.bitmap_count("bits")), F.lit(0)).cast("long").alias("n"))


def rank(w: Column, bits: int) -> Column:
    """Trailing zeros of w plus one; a zero counts as ``bits`` zeros."""
    return F.when(w == 0, F.lit(bits + 1)).otherwise(F.bit_count(w.bitwiseXOR(w - 1))).cast("int")


def rank_registers(df: DataFrame, cols: Cols, by: Sequence[str] = (), spec: SketchSpec = SketchSpec()) -> DataFrame:
    item = F.col("item")
    read = items(df, cols, by).select(*by, hashing.register(spec, item).alias("reg"), rank(hashing.draw(spec, item), spec.bits).alias("rank"))
    return read.groupBy(*by, "reg").agg(F.max("rank").alias("rank"))


def loglog_alpha(k: int) -> float:
    """(Gamma(-1/k) * (1 - 2**(1/k)) / ln 2)**-k, for k > 1."""
    if k < 2:
        return 0.39701
    gamma = -k * math.gamma(1 - 1 / k)
    return (gamma * (1 - 2 ** (1 / k)) / math.log(2)) ** -k


#: Bias constants of the harmonic average of ranks for small k (fixed values).
HLL_ALPHA = {16: 0.673, 32: 0.697, 64: 0.709}


def hll_alpha(k: int) -> float:
    return HLL_ALPHA.get(k, 0.7213 / (1 + 1.079 / k))


def loglog(ranks: DataFrame, spec: SketchSpec, by: Sequence[str] = ()) -> DataFrame:
    """Geometric average of 2**rank; untouched registers count as rank 0."""
    z = F.lit(loglog_alpha(spec.k) * spec.k) * F.pow(F.lit(2.0), F.sum("rank") / F.lit(spec.k))
    return ranks.groupBy(*by).agg(F.coalesce(z, F.lit(0.0)).alias("z"))


def hyperloglog(ranks: DataFrame, spec: SketchSpec, by: Sequence[str] = (), small_range: bool = False) -> DataFrame:
    """Harmonic average of 2**rank; ``small_range`` counts linearly while registers are empty and z <= 2.5k."""
    k = spec.k
    free = F.lit(k) - F.count("*")
    z = F.lit(hll_alpha(k) * k * k) / (F.coalesce(F.sum(F.pow(F.lit(2.0), -F.col("rank"))), F.lit(0.0)) + free)
    if small_range:
        z = F.when((z <= 2.5 * k) & (free > 0), F.lit(float(k)) * F.ln(F.lit(float(k)) / free)).otherwise(z)
    return ranks.groupBy(*by).agg(z.alias("z"))


def bit_pattern_count(df: DataFrame, cols: Cols, spec: SketchSpec) -> DataFrame:
    """Bit-pattern counting: per register the OR of 2**zeros, answered from the lowest unset bit."""
    item = F.col("item")
    w = hashing.draw(spec, item)
    bit = F.expr(f"shiftleft(1L, least(zeros, {spec.bits - 1}))")
    read = items(df, cols).select(hashing.register(spec, item).alias("reg"), (rank(w, spec.bits) - 1).alias("zeros"))
    maps = read.groupBy("reg").agg(F.bit_or(bit).alias("bits"))
    lowest = F.bit_count(F.col("bits").bitwiseXOR(F.col("bits") + 1)) - 1  # trailing ones
    z = F.lit(spec.k / PATTERN_PHI) * F.pow(F.lit(2.0), F.coalesce(F.sum(lowest), F.lit(0)) / F.lit(spec.k))
    return maps.agg(z.alias("z"))


def builtin_acd(df: DataFrame, cols: Cols, rsd: float = 0.05) -> DataFrame:
    return df.agg(F.approx_count_distinct(canonical_item(df, cols), rsd).alias("z"))


def builtin_hll(df: DataFrame, cols: Cols, lgk: int = 12) -> DataFrame:
    return df.agg(F.hll_sketch_estimate(F.hll_sketch_agg(canonical_item(df, cols), lgk)).alias("z"))


def builtin_theta(df: DataFrame, cols: Cols, lgk: int = 12) -> DataFrame:
    item = canonical_item(df, cols)
    return df.select(item.alias("item")).agg(F.expr(f"theta_sketch_estimate(theta_sketch_agg(item, {lgk}))").alias("z"))
