"""Building, seeding, merging and packing registers.

A sketch is a frame of rows (by..., reg, w): long form, fixed width, aggregated in two phases. No
item is shuffled, only registers: at most tasks * groups * k rows.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evsketch.functions import hashing
from evsketch.functions.items import canonical_item
from evsketch.spec import SketchSpec, same

#: Most registers that one aggregate computes side by side (generated methods stay under 64 KB).
WIDE_LIMIT = 64

Cols = str | Sequence[str]


def items(df: DataFrame, cols: Cols, by: Sequence[str] = ()) -> DataFrame:
    """(by..., item) of the rows that have an item."""
    return df.select(*by, canonical_item(df, cols).alias("item")).where("item is not null")


def registers(df: DataFrame, cols: Cols, by: Sequence[str] = (), spec: SketchSpec = SketchSpec()) -> DataFrame:
    """Averaged registers: one update per item. Repeats and order leave them unchanged."""
    read = items(df, cols, by)
    return read.select(*by, hashing.register(spec, F.col("item")).alias("reg"), hashing.draw(spec, F.col("item")).alias("w")).groupBy(*by, "reg").agg(F.min("w").alias("w"))


def full_registers(df: DataFrame, cols: Cols, by: Sequence[str] = (), spec: SketchSpec = SketchSpec(layout="full"), how: str = "auto", mode: str = "rehash") -> DataFrame:
    """All k registers see every item.

    ``wide``: k minima in one aggregate (k up to WIDE_LIMIT); ``explode``: k rows an item before the
    partial aggregate; ``arrow``: a numpy minimum per task, k rows out of it (no groups; rehash only).
    """
    if how == "auto":
        how = "wide" if spec.k <= WIDE_LIMIT else "explode"
    read = items(df, cols, by)
    item = F.col("item")
    if how == "wide":
        if spec.k > WIDE_LIMIT:
            raise ValueError(f"wide registers need k <= {WIDE_LIMIT}")
        one = read.groupBy(*by).agg(*[F.min(hashing.full_draw(spec, item, i, mode)).alias(f"w{i}") for i in range(spec.k)])
        pairs = F.array(*[F.struct(F.lit(i).alias("reg"), F.col(f"w{i}").alias("w")) for i in range(spec.k)])
        return one.select(*by, F.explode(pairs).alias("p")).select(*by, "p.reg", "p.w").where("w is not null")
    if how == "explode":
        spread = read.withColumn("reg", F.explode(F.sequence(F.lit(0), F.lit(spec.k - 1))))
        return spread.select(*by, "reg", hashing.full_draw(spec, item, F.col("reg"), mode).alias("w")).groupBy(*by, "reg").agg(F.min("w").alias("w"))
    if how == "arrow":
        if by or mode != "rehash":
            raise ValueError("arrow registers take no groups and rehash only")
        return read.mapInArrow(_arrow_minima(spec), "reg int, w long").groupBy("reg").agg(F.min("w").alias("w"))
    raise ValueError(f"unknown way: {how}")


def _arrow_minima(spec: SketchSpec):
    import hashlib

    def portable(texts):
        for i in range(spec.k):
            head = hashlib.md5(f"{spec.seed}/{i}:".encode())
            low = None
            for t in texts:
                h = head.copy()
                h.update(t)
                w = int.from_bytes(h.digest()[:7], "big") >> 4
                low = w if low is None or w < low else low
            yield low

    def run(batches):
        best = np.full(spec.k, np.iinfo(np.int64).max)
        seen = False
        for batch in batches:
            texts = {t.encode() for t in batch.column("item").to_pylist()}
            if texts:
                seen = True
                np.minimum(best, np.fromiter(portable(texts), np.int64, spec.k), out=best)
        if seen:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(spec.k, dtype=np.int32)), pa.array(best)], ["reg", "w"])

    if spec.family != "portable":
        raise ValueError("arrow registers are of the portable family")
    return run


def spine(spark: SparkSession, spec: SketchSpec) -> DataFrame:
    """Rows (reg, w0) of all registers with their seed draws."""
    return spark.range(spec.k).select(F.col("id").cast("int").alias("reg")).withColumn("w0", hashing.seed_draw(spec, F.col("reg")))


def with_seed_draws(regs: DataFrame, spec: SketchSpec, by: Sequence[str] = ()) -> DataFrame:
    """Dense registers that each started with its own draw; without groups an empty sketch becomes
    the seeds. Idempotent, and the same before and after a merge."""
    seeds = spine(regs.sparkSession, spec)
    return merge_rows(regs.select(*by, "reg", "w").unionByName(groups(regs, by).crossJoin(F.broadcast(seeds)).select(*by, "reg", F.col("w0").alias("w"))) if by else regs.select("reg", "w").unionByName(seeds.select("reg", F.col("w0").alias("w"))), by)


def groups(regs: DataFrame, by: Sequence[str]) -> DataFrame:
    return regs.select(*by).distinct()


def merge_rows(rows: DataFrame, by: Sequence[str] = (), value: str = "w") -> DataFrame:
    """Registers of the union of the items: least w, or greatest integer register."""
    keep = F.min(value) if value == "w" else F.max(value)
    return rows.groupBy(*by, "reg").agg(keep.alias(value))


def merge(*sketches: tuple[DataFrame, SketchSpec], by: Sequence[str] = (), value: str = "w") -> DataFrame:
    """Union of sketches of one spec; raises SpecMismatch otherwise."""
    same(*[spec for _, spec in sketches])
    first, *rest = [regs.select(*by, "reg", value) for regs, _ in sketches]
    for r in rest:
        first = first.unionByName(r)
    return merge_rows(first, by, value)


def rollup_registers(regs: DataFrame, sets: Sequence[Sequence[str]], by: Sequence[str]) -> DataFrame:
    """Registers of every grouping set from the finest ones; ``level`` tells the set (bit i set: by[i]
    rolled up). ``reg`` is kept in every set, items are not read again."""
    out = None
    for chosen in sets:
        level = sum(1 << i for i, c in enumerate(reversed(by)) if c not in chosen)
        part = merge_rows(regs, chosen).select(*[F.col(c) if c in chosen else F.lit(None).cast(regs.schema[c].dataType).alias(c) for c in by], F.lit(level).alias("level"), "reg", "w")
        out = part if out is None else out.unionByName(part)
    return out


def substream_counts(df: DataFrame, cols: Cols, spec: SketchSpec) -> DataFrame:
    """(reg, n_i): distinct items of each sub-stream, zeros included."""
    each = items(df, cols).distinct().groupBy(hashing.register(spec, F.col("item")).alias("reg")).agg(F.count("*").alias("n_i"))
    return spine(df.sparkSession, spec).select("reg").join(each, "reg", "left").select("reg", F.coalesce("n_i", F.lit(0)).cast("long").alias("n_i"))


def pack(qregs: DataFrame, spec: SketchSpec, by: Sequence[str] = (), missing: int = -128) -> DataFrame:
    """One row per group: qs, the integer registers in order as array<tinyint> (``missing`` where none)."""
    filled = F.transform(F.sequence(F.lit(0), F.lit(spec.k - 1)), lambda i: F.coalesce(F.try_element_at(F.col("m"), i.cast("int")), F.lit(missing)).cast("tinyint"))
    held = qregs.groupBy(*by).agg(F.map_from_entries(F.collect_list(F.struct(F.col("reg").cast("int"), F.col("q").cast("int")))).alias("m"))
    return held.select(*by, filled.alias("qs"))


def unpack(packed: DataFrame, by: Sequence[str] = (), missing: int = -128) -> DataFrame:
    return packed.select(*by, F.posexplode("qs").alias("reg", "q")).where(F.col("q") != missing)


def merge_packed(a: Column, b: Column) -> Column:
    """Union of two packed sketches."""
    return F.zip_with(a, b, lambda x, y: F.greatest(x, y))
