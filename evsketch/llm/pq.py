"""Near-duplicate vectors through a product-quantised inverted index.

Equal vectors of a label are one class. A coarse k-means and a residual product quantiser are fitted
on a bounded, hash-chosen sample; every class is then coded: its list, a code per subspace, and what
the code leaves out (the length of the remainder and its product with the vector). A class probes
every list that can hold a partner: angles to a centroid differ by at most the angle of the
threshold, so lists are skipped only where no member can qualify. In a list, asymmetric
distances come from table lookups; with x the vector, r its remainder and t the threshold,
q.x >= t implies lookup(q, x) >= t - x.r - sqrt(2 - 2t) * |r|, so candidates are complete, and the
exact cosine in double precision decides. Recall is therefore that of brute force.

Lists are cut into blocks and queries into parts, so one tile's size is bounded however large a
label or list is. A tile returns counts and a spanning forest, never its pairs.

Defined cases: null or zero vectors, vectors with null or non-finite components, and null labels
link with nothing and are their own component; vectors of different lengths never link; rows are
told apart by position, so a repeated or null vec_id keeps its rows (a null id never names a
component of others); an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evsketch.llm.common import arrow_map, components, forest, staged


@dataclass(frozen=True)
class Index:
    """Sizes of the index; ``sample`` bounds the rows it is fitted on."""

    sample: int = 20_000
    lists: int | None = None  # sqrt(classes) / 8, from 4 to 1024
    subspaces: int = 8
    codes: int = 256
    block: int = 2048
    part: int = 8192
    batch: int = 512


def kmeans(x: np.ndarray, k: int, rounds: int = 8, seed: int = 7) -> np.ndarray:
    """Lloyd's centroids; an empty cluster keeps its centroid."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        to = nearest(x, c)
        sums = np.zeros_like(c)
        np.add.at(sums, to, x)
        n = np.bincount(to, minlength=len(c))
        c[n > 0] = sums[n > 0] / n[n > 0, None]
    return c


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    half = (c * c).sum(1) / 2
    return np.concatenate([np.argmax(x[i : i + 4096] @ c.T - half, axis=1) for i in range(0, len(x), 4096)]) if len(x) else np.zeros(0, np.int64)


@dataclass
class Coder:
    """Fitted centroids (lists x dim) and codebooks (subspaces x codes x width)."""

    coarse: np.ndarray
    books: np.ndarray

    @property
    def dim(self) -> int:
        return self.coarse.shape[1]

    def encode(self, unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """List, codes, x.r and |r| of unit vectors."""
        at = nearest(unit, self.coarse)
        rest = unit - self.coarse[at]
        m, _, width = self.books.shape
        padded = np.zeros((len(unit), m * width))
        padded[:, : self.dim] = rest
        codes = np.stack([nearest(padded[:, s * width : (s + 1) * width], self.books[s]) for s in range(m)], axis=1) if len(unit) else np.zeros((0, m), np.int64)
        made = np.concatenate([self.books[s][codes[:, s]] for s in range(m)], axis=1)[:, : self.dim]
        r = rest - made
        return at, codes.astype(np.int32), (unit * r).sum(1), np.sqrt((r * r).sum(1))

    def lookup(self, q: np.ndarray, at: int, codes: np.ndarray) -> np.ndarray:
        """Asymmetric products of queries with the coded members of list ``at``."""
        m, _, width = self.books.shape
        padded = np.zeros((len(q), m * width))
        padded[:, : self.dim] = q
        out = np.repeat((q @ self.coarse[at])[:, None], len(codes), axis=1)
        for s in range(m):
            out += (padded[:, s * width : (s + 1) * width] @ self.books[s].T)[:, codes[:, s]]
        return out


def fit(unit: np.ndarray, lists: int, how: Index) -> Coder:
    coarse = kmeans(unit, lists)
    rest = unit - coarse[nearest(unit, coarse)]
    width = -(-unit.shape[1] // how.subspaces)
    padded = np.zeros((len(unit), how.subspaces * width))
    padded[:, : unit.shape[1]] = rest
    books = [kmeans(padded[:, s * width : (s + 1) * width], how.codes, 5) for s in range(how.subspaces)]
    return Coder(coarse, np.stack(books))


def matrix(column: pa.Array, dim: int) -> np.ndarray:
    """Rows of a list column as float64, padded with zeros to ``dim``."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    size = column.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    out = np.zeros((len(size), dim))
    row = np.repeat(np.arange(len(size)), size)
    out[row, np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)] = flat
    return out


def unit_rows(x: np.ndarray) -> np.ndarray:
    """Rows of length one; a first division by the largest component keeps squares in range."""
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def near_vectors(vectors: DataFrame, key: str = "vec_id", vector: str = "embedding", label: str = "label", threshold: float = 0.93, how: Index = Index()) -> DataFrame:
    """Per row: key, n_links, component_id, kept."""
    spark = vectors.sparkSession
    v = F.col(vector)
    sound = F.coalesce(F.col(label).isNotNull() & (F.size(v) > 0) & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0), F.lit(False))
    rows = vectors.select(F.col(key).alias("key"), F.col(label).cast("string").alias("tag"), v.alias("v"), sound.alias("sound"))
    named = rows.withColumns({"row": F.monotonically_increasing_id(), "k1": F.xxhash64(F.lit(1), "tag", F.size("v"), "v"), "k2": F.xxhash64(F.lit(2), "v", F.size("v"), "tag")})
    named = staged(named)
    classes = named.where("sound").groupBy("k1", "k2").agg(F.min("row").alias("cid"), F.min("key").alias("low"), F.count("*").alias("copies"), F.any_value("tag").alias("tag"), F.any_value("v").alias("v"))
    classes = staged(classes.withColumn("tag", F.concat_ws(":", F.size("v"), "tag")))
    n, dim = classes.agg(F.count("*"), F.max(F.size("v"))).first()
    if not n:
        return named.select(F.col("key").alias(key), F.lit(0).cast("long").alias("n_links"), F.col("key").alias("component_id"), F.lit(True).alias("kept"))
    taken = classes.where(F.pmod(F.xxhash64("cid"), F.lit(1 << 20)) < max(1, int((1 << 20) * min(1.0, how.sample / n)))).select("v").limit(2 * how.sample).toArrow().column("v")
    sample = matrix(taken, dim) if len(taken) else matrix(classes.select("v").limit(how.codes).toArrow().column("v"), dim)
    lists = how.lists or int(min(1024, max(4, n**0.5 / 8)))
    coder = spark.sparkContext.broadcast(fit(unit_rows(sample), lists, how))  # bounded by dim * (lists + codes)

    def code(batch: pa.RecordBatch) -> pa.RecordBatch:
        c = coder.value
        unit = unit_rows(matrix(batch.column("v"), dim))
        at, codes, with_rest, left = c.encode(unit)
        axis = c.coarse[at] / np.maximum(1e-12, np.linalg.norm(c.coarse[at], axis=1, keepdims=True))
        angle = np.arccos(np.clip((unit * axis).sum(1), -1, 1))
        packed = pa.ListArray.from_arrays(pa.array(np.arange(len(at) + 1) * codes.shape[1], pa.int32()), pa.array(codes.ravel()))
        cols = [batch.column(x) for x in ("cid", "tag", "copies", "v")] + [pa.array(at, pa.int32()), packed, pa.array(with_rest), pa.array(left), pa.array(angle)]
        return pa.RecordBatch.from_arrays(cols, ["cid", "tag", "copies", "v", "list", "codes", "xr", "r", "angle"])

    kind = classes.schema["v"].dataType.simpleString()
    coded = staged(arrow_map(classes.select("cid", "tag", "copies", "v"), code, f"cid long, tag string, copies long, v {kind}, list int, codes array<int>, xr double, r double, angle double"))
    span = {r.list: (r.lo, r.hi) for r in coded.groupBy("list").agg(F.min("angle").alias("lo"), F.max("angle").alias("hi")).collect()}  # at most `lists` rows
    reach = float(np.arccos(threshold)) + 1e-6

    def probe(batch: pa.RecordBatch) -> pa.RecordBatch:
        c = coder.value
        unit = unit_rows(matrix(batch.column("v"), dim))
        axes = c.coarse / np.maximum(1e-12, np.linalg.norm(c.coarse, axis=1, keepdims=True))
        angle = np.arccos(np.clip(unit @ axes.T, -1, 1))
        ok = np.stack([(angle[:, i] + reach >= span[i][0]) & (angle[:, i] - reach <= span[i][1]) if i in span else np.zeros(len(unit), bool) for i in range(len(axes))], axis=1)
        row, at = np.nonzero(ok)
        take = pa.array(row, pa.int64())
        return pa.RecordBatch.from_arrays([*(batch.column(x).take(take) for x in ("cid", "tag", "v")), pa.array(at, pa.int32())], ["cid", "tag", "v", "list"])

    blocks = coded.groupBy("tag", "list").agg(F.ceil(F.count("*") / how.block).cast("int").alias("blocks"))
    parts = coded.groupBy("tag").agg(F.ceil(F.count("*") / how.part).cast("int").alias("parts"))
    sizes = staged(blocks.join(parts, "tag"))
    asked = arrow_map(coded.select("cid", "tag", "v"), probe, f"cid long, tag string, v {kind}, list int").join(sizes, ["tag", "list"])
    asked = asked.withColumn("part", F.pmod(F.xxhash64("cid"), F.col("parts")).cast("int")).withColumn("block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    held = coded.join(sizes, ["tag", "list"]).withColumn("block", F.pmod(F.xxhash64("cid"), F.col("blocks")).cast("int")).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    tile = ["tag", "list", "block", "part"]
    asked = asked.select(*tile, "cid", "v", F.lit(None).cast("long").alias("copies"), F.lit(None).cast("array<int>").alias("codes"), F.lit(None).cast("double").alias("xr"), F.lit(None).cast("double").alias("r"))
    held = held.select(*tile, "cid", "v", "copies", "codes", "xr", "r")
    slack = float(np.sqrt(max(0.0, 2 - 2 * threshold)))

    def compare(table: pa.Table) -> pa.Table:
        c = coder.value
        table = table.combine_chunks()
        own = table.column("copies").is_valid()
        data, query = table.filter(own), table.filter(pa.compute.invert(own))
        nodes, roots, who, many = [], [], [], []
        if data.num_rows and query.num_rows:
            at = data.column("list")[0].as_py()
            x, q = matrix(data.column("v"), dim), matrix(query.column("v"), dim)
            ux, uq = unit_rows(x), unit_rows(q)
            codes = np.array(data.column("codes").combine_chunks().flatten()).reshape(len(x), -1)
            floor = threshold - data.column("xr").to_numpy() - slack * data.column("r").to_numpy() - 1e-9
            xid, qid, copies = data.column("cid").to_numpy(), query.column("cid").to_numpy(), data.column("copies").to_numpy()
            for i in range(0, len(q), how.batch):
                a, b = np.nonzero(c.lookup(uq[i : i + how.batch], at, codes) >= floor)
                a += i
                near = np.concatenate([(uq[a[j : j + 65536]] * ux[b[j : j + 65536]]).sum(1) for j in range(0, len(a), 65536)]) if len(a) else np.zeros(0)
                close = np.flatnonzero(np.abs(near - threshold) < 1e-9)  # settled by the plain formula
                for j in close:
                    p, s = q[a[j]], x[b[j]]
                    near[j] = np.dot(p, s) / (np.sqrt(np.dot(p, p)) * np.sqrt(np.dot(s, s)))
                hit = (near >= threshold) & (qid[a] != xid[b])
                a, b = a[hit], b[hit]
                if len(a):
                    total = np.bincount(a - i, copies[b], minlength=0).astype(np.int64)
                    with_any = np.flatnonzero(total)
                    who.append(qid[i + with_any])
                    many.append(total[with_any])
                    u, w = forest(qid[a], xid[b])
                    nodes.append(u)
                    roots.append(w)
        e = np.concatenate(nodes) if nodes else np.zeros(0, np.int64)
        t = np.concatenate(roots) if roots else np.zeros(0, np.int64)
        g = np.concatenate(who) if who else np.zeros(0, np.int64)
        m = np.concatenate(many) if many else np.zeros(0, np.int64)
        return pa.table({"a": pa.array(np.concatenate([e, g])), "b": pa.array(np.concatenate([t, np.full(len(g), -1)])), "links": pa.array(np.concatenate([np.zeros(len(e), np.int64), m]))})

    out = staged(held.unionByName(asked).groupBy(*tile).applyInArrow(compare, "a long, b long, links long"))
    counted = out.where("b = -1").groupBy("a").agg(F.sum("links").alias("others")).withColumnRenamed("a", "cid")
    linked = components(out.where("b >= 0").select("a", "b")).withColumnRenamed("node", "cid")
    each = classes.select("cid", "k1", "k2", "low", "copies").join(counted, "cid", "left").join(linked, "cid", "left").withColumn("root", F.coalesce("root", "cid"))
    lows = each.groupBy("root").agg(F.min("low").alias("component_id"))
    answer = staged(each.join(lows, "root").select("k1", "k2", (F.coalesce("others", F.lit(0)) + F.col("copies") - 1).alias("n_links"), "component_id"))
    some = named.where("sound").select("key", "k1", "k2").join(answer, ["k1", "k2"]).select("key", "n_links", "component_id")
    none = named.where("not sound").select("key", F.lit(0).cast("long").alias("n_links"), F.col("key").alias("component_id"))
    return some.union(none).withColumn("kept", F.coalesce(F.col("key") == F.col("component_id"), F.col("component_id").isNull())).withColumnRenamed("key", key)
