"""Sources and sinks: given tables, item files of several formats, streams, sketch tables."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evsketch.spec import SketchSpec, SpecMismatch

META = ("spec_id", "k", "family", "seed", "bits", "layout")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; Spark prunes its columns and pushes filters to the files."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_items(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """Items from csv, json, orc, parquet or text files, with a stated schema (never inferred)."""
    reader = spark.read if fmt == "text" else spark.read.schema(schema)
    return reader.format(fmt).load(path)


def simulate(spark: SparkSession, n: int) -> DataFrame:
    """n distinct items."""
    return spark.range(n).select(F.col("id").alias("item"))


def stream_events(spark: SparkSession, sf_dir: str, files_per_trigger: int | None = None) -> DataFrame:
    """The events table as a stream, its time as a TIMESTAMP (a watermark takes no TIMESTAMP_NTZ)."""
    kind = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    reader = spark.readStream.schema(kind)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(f"{sf_dir}/events*.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def save_sketch(regs: DataFrame, spec: SketchSpec, path: str, mode: str = "append", period: Sequence[str] = ()) -> None:
    """Registers as a durable table, partitioned by spec and period."""
    held = {"spec_id": spec.spec_id, "k": spec.k, "family": spec.family, "seed": spec.seed, "bits": spec.bits, "layout": spec.layout}
    regs.withColumns({c: F.lit(v) for c, v in held.items()}).write.mode(mode).partitionBy("spec_id", *period).parquet(path)


def load_sketch(spark: SparkSession, path: str, spec: SketchSpec) -> DataFrame:
    """Registers of ``spec`` only (partition pruned); raises SpecMismatch if the table has none of it."""
    found = spark.read.parquet(path)
    own = found.where(F.col("spec_id") == spec.spec_id)
    if own.isEmpty() and not found.isEmpty():
        raise SpecMismatch(f"{path} holds no sketch {spec.spec_id}")
    return own.drop(*META)
