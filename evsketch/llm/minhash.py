"""Near-duplicate documents: SuperMinHash, banding, verification, connected components.

A document's set is its distinct ``width``-word shingles, as 64-bit hashes. SuperMinHash gives each
element one random position per rank, through a permutation of its own, and the rank as the whole
part of its value: a slot filled at rank j holds a value below j + 1, so once every slot of a
document lies below the next rank no later rank can change it and its elements stop. Slots so
share their elements out more evenly than independent minima do, which lowers the variance.

Equal sets are one class. Classes that share a band meet in a bucket; in every bucket the smallest
class is the hub and others are verified against it on full sets, which is linear in the bucket:
first over the buckets of a few bands, which joins most of what belongs together, then over all
buckets for the members that are not in their hub's component yet. A pair is verified only if set
sizes allow it and if two bits of each slot agree about as often as the threshold implies
(``Banding.sigmas`` standard deviations below its expectation). Where members of a bucket are still
apart, blocks of it are searched for such likely pairs; what these join is a cluster, and a
cluster's blocks are settled on full sets, each document against the others until it is in their
component. Searches return spanning forests, never pairs, and no pair inside a component is
verified. Blocks bound a task's rows however large a bucket is, nothing is capped, and nothing is
collected but a bitmap of fixed size, which only spares shipping sets no bucket needs.

Defined cases: null or empty texts, and texts of white space, have an empty set, n_shingles 0 and
stand alone; fewer than ``width`` words make one shingle; a null key joins its class but is never
the component's id unless all keys are null (then kept is true); rows that repeat a key are one
document; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evsketch.llm.common import arrow_map, components, empty_safe, forest, fresh, mix64, raw, released, signed, slices, small, staged

_GOLD = 0x9E3779B97F4A7C15
#: Rows of a block where likely pairs are searched, and where they are settled on full sets.
SEARCH_BLOCK, SETTLE_BLOCK = 2048, 4096
#: log2 of the bits that tell which classes some bucket needs; fixed, whatever the input.
BITMAP_LOG2 = 24


@dataclass(frozen=True)
class Banding:
    """bands * rows slots; a pair of similarity s meets with probability 1 - (1 - s**rows)**bands."""

    bands: int = 40
    rows: int = 6
    first: int = 3  # bands of the first round
    sigmas: float = 4.0

    @property
    def slots(self) -> int:
        return self.bands * self.rows

    def least_agreement(self, share: float) -> int:
        """Slots whose two bits must agree for a pair of similarity ``share``, less ``sigmas`` deviations."""
        p = share + (1 - share) / 4
        return int(np.floor(self.slots * p - self.sigmas * (self.slots * p * (1 - p)) ** 0.5))


class _Words(dict):
    """64-bit hash of each word, bounded."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 150_000:
            self.clear()
        h = self[word] = xxhash.xxh64_intdigest(word)
        return h


_WORDS = _Words()


def shingles(text: bytes, width: int) -> np.ndarray:
    """Sorted distinct shingle hashes of a text (ASCII letters folded, words split at ASCII white space)."""
    words = text.lower().split()
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(_WORDS.__getitem__, words), np.uint64, n)
    w = min(width, n)
    out = mix64(h[: n - w + 1] + np.uint64(w if n < width else 0))
    for i in range(1, w):
        out = mix64(out * np.uint64(_GOLD) + h[i : n - w + 1 + i])
    out.sort()
    keep = np.ones(len(out), bool)
    keep[1:] = out[1:] != out[:-1]
    return out[keep]


def super_minhash(elements: np.ndarray, owner: np.ndarray, docs: int, slots: int) -> np.ndarray:
    """Signatures (docs x slots, uint64: rank in the high half) of sets given as element hashes and owners."""
    sig = np.full(docs * slots, np.uint64(slots) << np.uint64(32), np.uint64)
    rows = np.arange(len(elements))
    place = None
    e, own = elements, owner
    for j in range(slots):
        draw = mix64(e + np.uint64(((j + 1) * _GOLD) & 0xFFFFFFFFFFFFFFFF))
        k = (((draw & np.uint64(0xFFFFFFFF)) * np.uint64(slots - j)) >> np.uint64(32)).astype(np.int64) + j
        value = (draw >> np.uint64(32)) | np.uint64(j << 32)
        at = k if place is None else place[rows, k].astype(np.int64)
        np.minimum.at(sig, own * slots + at, value)
        going = np.unique(own)
        top = sig.reshape(docs, slots)[going].max(axis=1)
        going = going[top >= np.uint64((j + 1) << 32)]
        if not len(going):
            break
        alive = np.zeros(docs, bool)
        alive[going] = True
        keep = alive[own]
        if place is None:
            e, own, k = e[keep], own[keep], k[keep]
            place = np.tile(np.arange(slots, dtype=np.uint8 if slots <= 256 else np.uint16), (len(e), 1))
            rows = np.arange(len(e))
            place[rows, k] = 0  # position 0 went to k; position k's value was used
        else:
            place[rows, k] = place[rows, j]
            if not keep.all():
                e, own, place = e[keep], own[keep], place[keep]
                rows = np.arange(len(e))
    return sig.reshape(docs, slots)


def bands_of(sig: np.ndarray, how: Banding) -> np.ndarray:
    """docs x bands keys, different for different bands."""
    parts = sig.reshape(len(sig), how.bands, how.rows)
    key = np.broadcast_to(np.arange(1, how.bands + 1, dtype=np.uint64) * np.uint64(_GOLD), (len(sig), how.bands)).copy()
    for i in range(how.rows):
        key = mix64(key ^ parts[:, :, i])
    return key


def two_bits(sig: np.ndarray) -> np.ndarray:
    """The low two bits of each slot, 32 slots to a word."""
    docs, slots = sig.shape
    words = -(-slots // 32)
    low = np.zeros((docs, words * 32), np.uint64)
    low[:, :slots] = sig & np.uint64(3)
    return (low.reshape(docs, words, 32) << np.arange(0, 64, 2, dtype=np.uint64)).sum(axis=2, dtype=np.uint64)


def _agreement(words: int, slots: int, a: str, b: str):
    """Slots whose two bits agree, from columns {a}0.. and {b}0.. (unused places agree and are taken off)."""
    apart = []
    for i in range(words):
        x = f"({a}{i} ^ {b}{i})"
        apart.append(f"bit_count(({x} | shiftrightunsigned({x}, 1)) & 6148914691236517205L)")
    return F.lit(slots) - F.expr(" + ".join(apart))


def _sets(batch: pa.RecordBatch, text: str, width: int) -> Iterator[tuple[int, list[np.ndarray]]]:
    body, off = raw(empty_safe(batch.column(text)))
    for a, b in slices(off, 1 << 19):
        whole = body[off[a] : off[b]].tobytes()
        cut = (off[a : b + 1] - off[a]).tolist()
        yield a, [shingles(whole[i:j], width) for i, j in zip(cut, cut[1:], strict=False)]


def _class_key(s: np.ndarray) -> tuple[int, int]:
    """128 bits that stand for a set."""
    one = mix64(s ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64)
    two = mix64(s + np.uint64(0x14057B7EF767814F)).sum(dtype=np.uint64)
    return int(one.astype(np.int64)), int(two.astype(np.int64))


def signatures(docs: DataFrame, key: str, text: str, width: int, how: Banding) -> DataFrame:
    """Per row: key, n (set size), k1 and k2 (the set's name), bands, bits."""

    def run(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for a, sets in _sets(batch, text, width):
            size = np.array([len(s) for s in sets])
            owner = np.repeat(np.arange(len(sets)), size)
            every = np.concatenate(sets)
            sig = super_minhash(every, owner, len(sets), how.slots)
            names = [_class_key(s) for s in sets]
            keys = signed(bands_of(sig, how))
            bands = pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1) * how.bands, pa.int32()), pa.array(keys.ravel()))
            bits = signed(two_bits(sig))
            bits = pa.ListArray.from_arrays(pa.array(np.arange(len(sets) + 1) * bits.shape[1], pa.int32()), pa.array(bits.ravel()))
            cols = [batch.column(key).slice(a, len(sets)), pa.array(size, pa.int64()), pa.array([x[0] for x in names], pa.int64()), pa.array([x[1] for x in names], pa.int64()), bands, bits]
            yield pa.RecordBatch.from_arrays(cols, ["key", "n", "k1", "k2", "bands", "bits"])

    return arrow_map(docs.select(key, text), run, f"key {docs.schema[key].dataType.simpleString()}, n long, k1 long, k2 long, bands array<long>, bits array<long>")


def full_sets(docs: DataFrame, text: str, width: int, wanted: bytes) -> DataFrame:
    """(k1, k2, set) of the texts whose class the bitmap names (and a few it doesn't mean)."""
    holder = docs.sparkSession.sparkContext.broadcast(wanted)
    mask = (1 << BITMAP_LOG2) - 1

    def run(batches):
        bits = np.frombuffer(holder.value, np.uint8)
        done: set[tuple[int, int]] = set()
        for batch in released(batches):
            rows = []
            for _, sets in _sets(batch, text, width):
                for s in sets:
                    name = _class_key(s)
                    at = name[0] & mask
                    if len(s) and bits[at >> 3] >> (at & 7) & 1 and name not in done:
                        if len(done) < 200_000:
                            done.add(name)
                        rows.append((*name, s.tobytes()))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.binary()), strict=True)], ["k1", "k2", "set"])

    return docs.select(text).mapInArrow(run, "k1 long, k2 long, set binary")


def bitmap(classes: DataFrame) -> bytes:
    """The fixed-size bitmap of the classes' k1 (BITMAP_LOG2 bits)."""
    at = F.expr(f"(k1 & {(1 << BITMAP_LOG2) - 1}) + 1")  # Spark's bitmap functions count from 1
    rows = classes.select(at.alias("at")).groupBy(F.bitmap_bucket_number(F.col("at")).alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(F.col("at"))).alias("bits")).collect()
    out = bytearray((1 << BITMAP_LOG2 >> 3) + 4096 * 2)
    for r in rows:  # at most 2**(BITMAP_LOG2 - 15) + 1 rows of 4 KiB
        base = (r.b - 1) * 4096
        for i, byte in enumerate(r.bits):
            if byte:
                out[base + i] |= byte
    return bytes(out)


def verify(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """(a, b, inter, n_a, n_b) for each pair of classes, from their full sets."""
    left = sets.select(F.col("cid").alias("a"), F.col("set").alias("sa"))
    right = sets.select(F.col("cid").alias("b"), F.col("set").alias("sb"))

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        got = []
        for x, y in zip(batch.column("sa"), batch.column("sb"), strict=True):
            p, q = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
            small, large = (p, q) if len(p) <= len(q) else (q, p)
            spot = np.searchsorted(large, small)
            spot[spot == len(large)] = 0
            got.append((int((large[spot] == small).sum()), len(p), len(q)))
        cols = [batch.column("a"), batch.column("b"), *(pa.array(c, pa.int64()) for c in zip(*got, strict=True))]
        return pa.RecordBatch.from_arrays(cols, ["a", "b", "inter", "n_a", "n_b"])

    return arrow_map(pairs.join(left, "a").join(right, "b").select("a", "b", "sa", "sb"), run, "a long, b long, inter long, n_a long, n_b long")


def tiles(rows: DataFrame, block: int) -> DataFrame:
    """Rows with (block, tile): each home of ``size`` rows is cut into blocks by a hash, and a row goes to
    every tile that pairs its block with another or with itself."""
    blocks = F.ceil(F.col("size") / block).cast("int")
    cut = rows.withColumn("blocks", F.greatest(F.lit(1), blocks)).withColumn("block", F.pmod(F.xxhash64("cid"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    spread = cut.withColumn("other", other)
    tile = F.least("block", "other").cast("long") * F.lit(1 << 32) + F.greatest("block", "other")
    return spread.withColumn("tile", tile).drop("other", "blocks", "size")


def _columns(table: pa.Table):
    table = table.combine_chunks()
    bits = table.column("bits").combine_chunks()
    bits = (bits.chunk(0) if isinstance(bits, pa.ChunkedArray) else bits).flatten().to_numpy().view(np.uint64).reshape(table.num_rows, -1)
    return table, *(table.column(c).to_numpy() for c in ("cid", "root", "n", "block")), bits


def _agree(x: np.ndarray, y: np.ndarray, slots: int) -> np.ndarray:
    """Agreeing slots of one row of bits with many."""
    d = x ^ y
    return slots - np.bitwise_count((d | (d >> np.uint64(1))) & np.uint64(0x5555555555555555)).sum(axis=1, dtype=np.int64)


def _likely_pairs(percent: int, likely: int, slots: int):
    """Spanning forest of a tile's likely pairs of different components."""

    def run(table: pa.Table) -> pa.Table:
        table, cid, root, n, block, bits = _columns(table)
        low, high = np.flatnonzero(block == block.min()), np.flatnonzero(block == block.max())
        alone = block.min() == block.max()
        a, b, keep = [], [], []
        whole = table.column("tile")[0].as_py()
        if alone and (whole >> 32) != (whole & 0xFFFFFFFF):
            low = low[:0]  # the other block of this pair is empty
        for i in low.tolist():
            ok = (root[high] != root[i]) & (100 * np.minimum(n[high], n[i]) >= percent * np.maximum(n[high], n[i]))
            j = high[ok & (high > i)] if alone else high[ok]
            if len(j):
                j = j[_agree(bits[i], bits[j], slots) >= likely]
                a.append(np.full(len(j), cid[i]))
                b.append(cid[j])
                if sum(map(len, a)) > 500_000:
                    keep.append(forest(np.concatenate(a), np.concatenate(b)))
                    a, b = [], []
        if a:
            keep.append(forest(np.concatenate(a), np.concatenate(b)))
        return pa.table({"a": pa.array(np.concatenate([k[0] for k in keep]) if keep else np.zeros(0, np.int64), pa.int64()), "b": pa.array(np.concatenate([k[1] for k in keep]) if keep else np.zeros(0, np.int64), pa.int64())})

    return run


def _settled(percent: int, likely: int, slots: int):
    """Links that join a tile's components, by full sets; every likely pair is verified or already joined."""

    def run(table: pa.Table) -> pa.Table:
        table, cid, root, n, block, bits = _columns(table)
        sets = [np.frombuffer(x.as_buffer(), np.uint64) for x in table.column("set").combine_chunks()]
        names, own = np.unique(root, return_inverse=True)
        at = np.arange(len(names))  # component of each root
        main = int(np.bincount(own).argmax())
        tile = table.column("tile")[0].as_py()
        i_, j_ = tile >> 32, tile & 0xFFFFFFFF
        low, high = np.flatnonzero(block == i_), np.flatnonzero(block == j_)
        work = [(x, high) for x in low[own[low] != main].tolist()]
        if i_ != j_:  # pairs of the main component's rows in the first block with others in the second
            rest = low[own[low] == main]
            work += [(y, rest) for y in high[own[high] != main].tolist()]
        edges = []
        for x, others in work:
            ok = (at[own[others]] != at[own[x]]) & (100 * np.minimum(n[others], n[x]) >= percent * np.maximum(n[others], n[x]))
            others = others[ok]
            if not len(others):
                continue
            agree = _agree(bits[x], bits[others], slots)
            ok = agree >= likely
            others = others[ok][np.argsort(-agree[ok], kind="stable")]
            step = 8
            while len(others):
                head, others = others[:step], others[step:]
                size = np.array([len(sets[y]) for y in head.tolist()])
                every = np.concatenate([sets[y] for y in head.tolist()])
                spot = np.searchsorted(sets[x], every)
                spot[spot == len(sets[x])] = 0
                both = np.add.reduceat((sets[x][spot] == every).astype(np.int64), np.cumsum(size) - size)
                for y in head[100 * both >= percent * (size + len(sets[x]) - both)].tolist():
                    if at[own[x]] != at[own[y]]:
                        edges.append((cid[x], cid[y]))
                        at[at == at[own[x]]] = at[own[y]]
                others = others[at[own[others]] != at[own[x]]]
                step = min(4096, step * 4)
        return pa.table({"a": pa.array([e[0] for e in edges], pa.int64()), "b": pa.array([e[1] for e in edges], pa.int64())})

    return run


def _linked(percent: int):
    return F.expr(f"100 * inter >= {percent} * (n_a + n_b - inter)")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = 5, percent: int = 80, how: Banding = Banding()) -> DataFrame:
    """Per row of ``docs``: key, n_shingles, component_id (the smallest key of its component), kept."""
    meta = staged(signatures(docs, key, text, width, how))
    grouped = meta.where("n > 0").groupBy("k1", "k2").agg(F.min("key").alias("low"), F.any_value("n").alias("n"), F.any_value("bands").alias("bands"), F.any_value("bits").alias("bits"))
    classes = staged(grouped.withColumn("cid", F.monotonically_increasing_id()))
    words = -(-how.slots // 32)
    bits = classes.select("cid", "n", *[F.col("bits")[i].alias(f"m{i}") for i in range(words)])
    spread = classes.select("cid", F.posexplode("bands").alias("band", "bucket"))
    hubs = staged(spread.groupBy("bucket").agg(F.min("cid").alias("hub"), F.count("*").alias("c")).where("c > 1"))
    members = staged(spread.join(hubs, "bucket"))
    wanted = classes.join(members.select("cid").distinct(), "cid", "left_semi")
    named_sets = full_sets(docs, text, width, bitmap(wanted)).groupBy("k1", "k2").agg(F.any_value("set").alias("set"))
    sets = staged(named_sets.join(classes.select("cid", "k1", "k2"), ["k1", "k2"]).select("cid", "set"))
    likely = how.least_agreement(percent / 100)
    fits = lambda x, y: 100 * F.least(x, y) >= percent * F.greatest(x, y)

    def links(pairs: DataFrame) -> DataFrame:
        return verify(pairs, sets).where(_linked(percent)).select("a", "b")

    def rooted(roots: DataFrame) -> DataFrame:
        mine = roots.select(F.col("node").alias("cid"), "root")
        hubs_ = roots.select(F.col("node").alias("hub"), F.col("root").alias("hub_root"))
        out = members.join(mine, "cid", "left").join(hubs_, "hub", "left")
        return out.select("bucket", "c", "cid", "hub", F.coalesce("root", "cid").alias("root"), F.coalesce("hub_root", "hub").alias("hub_root"))

    # A bucket's members against its hub, where sizes and bits allow a link. Pairs are made single before
    # the join on the hub: nothing needs its rows together then, so that Spark can split a hub of many.
    met = members.where("cid <> hub").groupBy("hub", "cid").agg(F.min("band").alias("band"))
    member = met.join(bits.select("cid", F.col("n").alias("nx"), *[F.col(f"m{i}").alias(f"x{i}") for i in range(words)]), "cid")
    hub = bits.select(F.col("cid").alias("a"), F.col("n").alias("ny"), *[F.col(f"m{i}").alias(f"y{i}") for i in range(words)])
    allowed = fits(F.col("nx"), F.col("ny")) & (_agreement(words, how.slots, "x", "y") >= likely)
    star = staged(member.join(hub, (F.col("hub") == F.col("a")) & allowed).select("a", F.col("cid").alias("b"), "band"))
    # one round over few bands, one over what it left apart
    edges = staged(links(star.where(F.col("band") < how.first).select("a", "b")))
    roots = components(edges)
    left, right = roots.select(F.col("node").alias("a"), F.col("root").alias("ra")), roots.select(F.col("node").alias("b"), F.col("root").alias("rb"))
    apart = star.where(F.col("band") >= how.first).join(left, "a", "left").join(right, "b", "left").where(F.coalesce("ra", "a") != F.coalesce("rb", "b"))
    edges = staged(edges.union(links(apart.select("a", "b"))))
    # buckets with members that no hub reached: likely pairs, then whole sets a cluster at a time
    placed = staged(rooted(components(edges)))
    lone = placed.where("root <> hub_root").select("bucket").distinct()
    plain = classes.select("cid", "n", "bits")
    inside = tiles(placed.join(lone, "bucket", "left_semi").select(F.col("bucket").alias("home"), F.col("c").alias("size"), "cid", "root").join(plain, "cid"), SEARCH_BLOCK)
    forest_ = inside.groupBy("home", "tile").applyInArrow(_likely_pairs(percent, likely, how.slots), "a long, b long")
    cluster = components(forest_)
    sized = cluster.groupBy("root").agg(F.count("*").cast("long").alias("size"))
    whole = cluster.select(F.col("node").alias("cid"), F.col("root").alias("home")).union(sized.select(F.col("root").alias("cid"), F.col("root").alias("home")))
    sized = sized.select(F.col("root").alias("home"), (F.col("size") + 1).alias("size"))
    own = placed.groupBy("cid").agg(F.min("root").alias("root"))
    held = staged(whole.join(sized, "home").join(own, "cid").join(plain, "cid").join(sets, "cid").select("home", "size", "cid", "root", "n", "bits", "set"))
    more = tiles(held, SETTLE_BLOCK).groupBy("home", "tile").applyInArrow(_settled(percent, likely, how.slots), "a long, b long")
    linked = components(edges.union(more))
    named = classes.join(linked.withColumnRenamed("node", "cid"), "cid", "left").select("k1", "k2", "low", F.coalesce("root", "cid").alias("root"))
    lows = named.groupBy("root").agg(F.min("low").alias("component_id"))
    answer = staged(named.join(lows, "root").select("k1", "k2", "component_id"))
    rows = meta.select("key", F.col("n").alias("n_shingles"), "k1", "k2")
    some = rows.where("n_shingles > 0").join(answer, ["k1", "k2"]).select("key", "n_shingles", "component_id")
    none = rows.where("n_shingles = 0").select("key", "n_shingles", F.col("key").alias("component_id"))
    both = some.union(none).withColumn("kept", F.coalesce(F.col("key") == F.col("component_id"), F.col("component_id").isNull()))
    return both.withColumnRenamed("key", key)


def keep_one(docs: DataFrame, key: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """The rows of ``docs``, all columns, less the documents that are near copies of one kept; rows
    with a null key always stay."""
    name = fresh(docs, "gone")
    gone = staged(near_duplicates(docs.select(key, text), key, text, **how).where("not kept").select(F.col(key).alias(name)).distinct())
    return docs.join(small(gone), F.col(key) == F.col(name), "left_anti")
