"""Relational operators around sketches: joins of sketch tables with data, intervals, set algebra."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evsketch.operators.registers import merge_rows
from evsketch.spec import SketchSpec


def range_join(points: DataFrame, at: str, spans: DataFrame, start: str, end: str, width: float) -> DataFrame:
    """Rows of ``points`` inside [start, end) of ``spans``: an equi join on buckets of ``width``
    (choose it near the usual span), with the range as its residual. A span is copied to each bucket
    it meets; no cross join."""
    cell = lambda v: F.floor(v / F.lit(width)).cast("long")
    cells = spans.where(F.col(start) < F.col(end)).withColumn("cell__", F.explode(F.sequence(cell(F.col(start)), cell(F.col(end)))))
    return points.withColumn("cell__", cell(F.col(at))).join(cells, "cell__").where((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("cell__")


def asof_join(left: DataFrame, right: DataFrame, left_on: str, right_on: str, by: Sequence[str] = (), carry: Sequence[str] = ()) -> DataFrame:
    """Each left row with ``carry`` of the latest right row at or before it: both sides in one
    window per key, no pairs. Rows without such a row carry nulls."""
    from pyspark.sql import Window

    cols = [c for c in left.columns]
    a = left.select(*cols, F.col(left_on).alias("at__"), F.lit(1).alias("side__"), *[F.lit(None).cast(right.schema[c].dataType).alias(f"{c}__") for c in carry])
    b = right.select(*[F.col(c) if c in by else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in cols], F.col(right_on).alias("at__"), F.lit(0).alias("side__"), *[F.col(c).alias(f"{c}__") for c in carry])
    over = Window.partitionBy(*by).orderBy("at__", "side__").rowsBetween(Window.unboundedPreceding, 0)
    held = F.struct(*[F.col(f"{c}__").alias(c) for c in carry])
    last = F.last(F.when(F.col("side__") == 0, held), ignorenulls=True).over(over)
    return a.unionByName(b).withColumn("last__", last).where("side__ = 1").select(*cols, *[F.col(f"last__.{c}").alias(c) for c in carry])


def intersect_estimate(a: DataFrame, b: DataFrame, spec: SketchSpec, estimator) -> DataFrame:
    """|A n B| by inclusion and exclusion over sketches; its error grows with the union."""
    z = [estimator(regs, spec).withColumnRenamed("z", n) for regs, n in ((a, "za"), (b, "zb"), (merge_rows(a.unionByName(b)), "zu"))]
    return z[0].crossJoin(z[1]).crossJoin(z[2]).select((F.col("za") + F.col("zb") - F.col("zu")).alias("z"))


def filtered_registers(rows: DataFrame, conditions: dict[str, Column]) -> DataFrame:
    """Several sketches in one pass over (reg, w, ...): min(w) FILTER per condition, in long form."""
    aggs = [F.min(F.when(cond, F.col("w"))).alias(name) for name, cond in conditions.items()]
    wide = rows.groupBy("reg").agg(*aggs)
    stack = ", ".join(f"'{n}', `{n}`" for n in conditions)
    return wide.select("reg", F.expr(f"stack({len(conditions)}, {stack}) as (name, w)")).where("w is not null")
