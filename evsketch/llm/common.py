"""What the training-data operators share: table access, staging, Arrow helpers."""

from __future__ import annotations

import ctypes
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a Python worker handles as one numpy slice.
SLICE_BYTES = 1 << 20
#: Edges that a Python worker contracts at a time.
CONTRACT = 1 << 18

try:  # glibc only
    _TRIM = ctypes.CDLL(None).malloc_trim
except (AttributeError, OSError):
    _TRIM = None


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, with this package importable on the Python workers."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Put the folder that holds this package on the workers' path (a no-op where it is installed)."""
    root = str(Path(__file__).resolve().parents[2])
    env = spark.sparkContext.environment
    have = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if root not in have:
        env["PYTHONPATH"] = os.pathsep.join([root, *have])


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; a local one only where the session names none (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    given = spark.sparkContext.getCheckpointDir()
    if not given:
        given = Path(tempfile.mkdtemp(prefix="evsketch-")).as_uri()
        spark.sparkContext.setCheckpointDir(given)
    return given


def staged(df: DataFrame) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/staged-{uuid.uuid4().hex}"
    df.write.parquet(path)
    jvm, conf = spark._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(conf).deleteOnExit(target)
    return spark.read.schema(df.schema).parquet(path)


def small(df: DataFrame, rows: int = 1_000_000) -> DataFrame:
    """``df``, to be broadcast if it is staged and has at most ``rows`` (narrow) rows; else as it is,
    so that a join shuffles."""
    return F.broadcast(df) if df.count() <= rows else df


def fresh(df: DataFrame, name: str) -> str:
    """``name``, lengthened until no column of ``df`` has it."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def bitmap(rows: DataFrame, wide: int) -> bytes:
    """The bitmap of the low ``wide`` bits of column ``at``: 2**wide bits, whatever the rows."""
    at = F.expr(f"(at & {(1 << wide) - 1}) + 1")  # Spark's bitmap functions count from 1
    parts = rows.select(at.alias("at")).groupBy(F.bitmap_bucket_number(F.col("at")).alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(F.col("at"))).alias("bits")).collect()
    out = bytearray(1 << (wide - 3))
    for r in parts:  # 2**(wide - 15) rows of 4 KiB at most
        out[(r.b - 1) * 4096 : r.b * 4096] = r.bits
    return bytes(out)


def empty_safe(column: pa.Array | pa.ChunkedArray) -> pa.Array:
    """The text column as one large_string array, null read as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.cast(pa.large_string()).fill_null("")


def raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes and n+1 byte offsets of a large_string array, without copying."""
    n = len(column)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64)[column.offset : column.offset + n + 1] if n else np.zeros(1, np.int64)
    body = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return body, off


def slices(off: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Runs [a, b) of rows with about ``limit`` bytes each; one row may be larger than that."""
    a, n = 0, len(off) - 1
    while a < n:
        b = max(a + 1, int(np.searchsorted(off, off[a] + limit, "right")) - 1)
        yield a, min(b, n)
        a = min(b, n)


def give_back() -> None:
    """Returns a worker's free memory to the system: workers are kept between stages."""
    pa.default_memory_pool().release_unused()
    if _TRIM:
        _TRIM(0)


def released(batches):
    """The batches; between two of them free memory is given back."""
    for batch in batches:
        yield batch
        del batch
        give_back()


def arrow_map(df: DataFrame, fn: Callable[[pa.RecordBatch], Iterator[pa.RecordBatch] | pa.RecordBatch], schema: str) -> DataFrame:
    """mapInArrow for a function of one batch."""

    def run(batches):
        for batch in released(batches):
            if batch.num_rows:
                out = fn(batch)
                if isinstance(out, pa.RecordBatch):
                    yield out
                else:
                    yield from out

    return df.mapInArrow(run, schema)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (shift-multiply rounds) on uint64 arrays."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def packed(*parts: np.ndarray, level: int = 1) -> bytes:
    """Arrays of one length, each byte of their values apart (as equal bytes compress), compressed."""
    planes = [np.ascontiguousarray(x).view(np.uint8).reshape(len(x), -1).T.tobytes() for x in parts]
    return zstandard.ZstdCompressor(level=level).compress(np.int64(len(parts[0])).tobytes() + b"".join(planes))


def unpacked(body: bytes, *kinds: str) -> list[np.ndarray]:
    """The arrays that ``packed`` was given, of these types."""
    body = zstandard.ZstdDecompressor().decompress(body)
    n, at, out = int(np.frombuffer(body, np.int64, 1)[0]), 8, []
    for kind in kinds:
        width = np.dtype(kind).itemsize
        planes = np.frombuffer(body, np.uint8, n * width, at).reshape(width, n)
        out.append(np.ascontiguousarray(planes.T).view(kind).ravel())
        at += n * width
    return out


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges (node, root) that span the components of the links a-b."""
    nodes, inverse = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = inverse[: len(a)], inverse[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[x], label[y])
        new = label.copy()
        np.minimum.at(new, x, low)
        np.minimum.at(new, y, low)
        np.minimum.at(new, label[x], low)
        np.minimum.at(new, label[y], low)
        new = new[new]
        if (new == label).all():
            keep = label != np.arange(len(nodes))
            return nodes[keep], nodes[label[keep]]
        label = new


def contracted(edges: DataFrame) -> DataFrame:
    """Edges (a, b) with the components of ``edges``, fewer of them: of every CONTRACT edges that a task reads only a
    spanning forest stays, of stars round the least node."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, many = [], 0

        def star() -> pa.RecordBatch:
            ends = forest(*(np.concatenate([h[i] for h in held]) for i in (0, 1)))
            return pa.RecordBatch.from_arrays([pa.array(e) for e in ends], ["a", "b"])

        for batch in released(batches):
            held.append([batch.column(c).to_numpy() for c in ("a", "b")])
            many += batch.num_rows
            if many >= CONTRACT:
                yield star()
                held, many = [], 0
        if many:
            yield star()

    return edges.mapInArrow(run, "a long, b long")


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """Connected components of ``edges`` (a, b: long): rows (node, root), root the smallest node.

    Alternates large-star and small-star contraction, each round a pair of aggregations that Spark
    combines map-side, after which every task contracts the edges it holds; stops when all edges are
    stars: no node has two edges down, and none has both one down and one up. Every round is staged in the
    shared folder, so nothing is collected and a lost executor costs one round. An empty input gives no rows.
    """
    down = edges.where("a <> b").select(F.greatest("a", "b").cast("long").alias("a"), F.least("a", "b").cast("long").alias("b"))
    links = staged(contracted(down.distinct()))
    for _ in range(rounds):
        ends = links.select(F.col("a").alias("node"), F.lit(1).alias("lower"), F.lit(0).alias("upper")).union(links.select("b", F.lit(0), F.lit(1)))
        if ends.groupBy("node").agg(F.sum("lower").alias("lower"), F.max("upper").alias("upper")).where("lower > 1 or lower + upper > 1").isEmpty():
            return links.select(F.col("a").alias("node"), F.col("b").alias("root"))
        both = links.union(links.select("b", "a"))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")
        large = large.distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select(F.col("b").alias("x"), "a", "m")
        small = small.select(F.col("x").alias("a"), F.col("m").alias("b")).union(small.select("a", F.col("m").alias("b")))
        links = staged(contracted(small.where("a <> b").distinct()))
    raise RuntimeError(f"components: no fixed point after {rounds} rounds")
