"""Sketches of streams: state is at most k registers a window, never items.

The registers of a window are an ordinary streaming aggregate, min(w) by (window, reg), so late rows
within the watermark only lower a minimum and order never matters. Seed draws are applied when a
sketch is read. Stateful queries don't adapt their partitions: set spark.sql.shuffle.partitions
before the first checkpoint.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evsketch.functions import hashing
from evsketch.functions.items import canonical_item
from evsketch.operators.registers import merge_rows
from evsketch.spec import SketchSpec

#: Registers that one aggregate can keep side by side for a session.
SESSION_LIMIT = 64


def stream_registers(stream: DataFrame, col: str, spec: SketchSpec, window=None, watermark: str | None = None, ts: str = "ts", by: Sequence[str] = ()) -> DataFrame:
    """Streaming registers by window (a Column of ``ts``, or none: one running sketch)."""
    rows = stream.withColumn("item", canonical_item(stream, col)).where("item is not null")
    if watermark:
        rows = rows.withWatermark(ts, watermark)
    keys = [window.alias("window")] if window is not None else []
    draws = rows.select(*keys, *by, hashing.register(spec, F.col("item")).alias("reg"), hashing.draw(spec, F.col("item")).alias("w"), *([ts] if window is None and watermark else []))
    return draws.groupBy(*(["window"] if keys else []), *by, "reg").agg(F.min("w").alias("w"))


def session_registers(stream: DataFrame, entity: str, col: str, gap: str, spec: SketchSpec, watermark: str, ts: str = "ts") -> DataFrame:
    """Sessions of an entity with all registers in one aggregate: sessions are cut per grouping key,
    so the register must not be one. k is at most SESSION_LIMIT."""
    if spec.k > SESSION_LIMIT:
        raise ValueError(f"sessions keep at most {SESSION_LIMIT} registers")
    rows = stream.withColumn("item", canonical_item(stream, col)).where("item is not null").withWatermark(ts, watermark)
    rows = rows.select(ts, entity, hashing.register(spec, F.col("item")).alias("reg"), hashing.draw(spec, F.col("item")).alias("w"))
    minima = [F.min(F.when(F.col("reg") == i, F.col("w"))).alias(f"w{i}") for i in range(spec.k)]
    return rows.groupBy(entity, F.session_window(ts, gap).alias("window")).agg(*minima)


def long_form(wide: DataFrame, spec: SketchSpec, keys: Sequence[str]) -> DataFrame:
    """Rows (keys..., reg, w) of a session's side-by-side registers."""
    pairs = F.array(*[F.struct(F.lit(i).alias("reg"), F.col(f"w{i}").alias("w")) for i in range(spec.k)])
    return wide.select(*keys, F.explode(pairs).alias("p")).select(*keys, "p.reg", "p.w").where("w is not null")


def run_available(query: DataFrame, mode: str = "complete", name: str | None = None) -> DataFrame:
    """Runs a streaming query over what is there, into a memory table, and returns that table."""
    name = name or f"stream_{uuid.uuid4().hex}"
    query.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return query.sparkSession.table(name)


def upsert_into(path: str, keys: Sequence[str]) -> Callable[[DataFrame, int], None]:
    """A foreachBatch sink that appends a batch's changed registers to a sketch table.

    Registers only fall, so readers take the minimum; a batch that is written twice changes nothing.
    """

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.select(*keys, "reg", "w").withColumn("batch", F.lit(batch_id)).write.mode("append").parquet(path)

    return write


def query_state(spark: SparkSession, path: str, keys: Sequence[str]) -> DataFrame:
    """Registers as the sink has them now."""
    return merge_rows(spark.read.parquet(path), keys)


def distinct_items(stream: DataFrame, col: str, watermark: str, ts: str = "ts") -> DataFrame:
    """The exact baseline: rows whose item is new within the watermark; state grows with the items."""
    return stream.withWatermark(ts, watermark).dropDuplicatesWithinWatermark([col])
