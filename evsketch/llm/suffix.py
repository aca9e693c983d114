"""Exact substring dedup by common-prefix intervals of suffix arrays.

``repeat_groups`` is the method on one text collection: an enhanced suffix array (order and common
prefix lengths) is scanned once with a stack, whose intervals are the repeats; an interval whose
occurrences are preceded by different bytes cannot be extended to the left and is output as a
maximal repeat group with all its occurrences, neighbours or not.

For a corpus the suffixes are dealt out by anchors. An anchor is the 16-byte string of least hash in
a 50-byte window, so equal windows have equal anchors, and only places that share an anchor need a
common suffix array. Documents of equal text are found first by hash; all but the first of them go
whole and are not read further. Then, in narrow passes over the rest:

1. anchor hashes of each document, packed and dealt by hash range, give those that two documents or
   more share and those that more than ``HOT`` do, noted in two bitmaps of fixed size (they only
   spare or route work: full bitmaps give the same result);
2. a noted anchor's context (the windows it stands for) goes to the task of its anchor, packed with
   its document's key (and text hash, if the key has several texts), whose suffix
   array covers a bounded batch of different contexts; its intervals say which bytes of each context
   occur in an earlier document;
3. contexts of hot anchors are aggregated by content, then by window, and joined back, so no task
   holds all documents of a common passage;
4. the spans go back to their documents, told by another bitmap, and the bytes are cut.

Defined cases: null or empty texts have no bytes and lose none; texts shorter than a window lose
none; rows that share a key are one document and never remove each other's bytes; a null key is
neither earlier nor later than any; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evsketch.llm.common import bitmap, empty_safe, fresh, mix64, packed, raw, released, slices, staged, unpacked

LEAST = 50
ANCHOR = 16
#: log2 of the bits that note repeated anchors, hot anchors, and documents; fixed.
ANCHOR_BITS, HOT_BITS, CHANGED_BITS = 27, 23, 23
#: Anchors that a worker gathers before it writes them out.
FLUSH = 1_000_000
#: Documents of one anchor that meet in a suffix array (its memory is about 6 kB a context); beyond,
#: windows are aggregated.
HOT = 20_000
#: Bytes of runs (as counted in _both) that are broadcast.
SMALL = 48 << 20
#: Contexts in one suffix array.
BATCH = 10_000

_BASE = 0x9E3779B97F4A7C15


# -- the method on one collection ------------------------------------------------------------


def suffix_array(a: np.ndarray) -> np.ndarray:
    """Order of the suffixes of an integer array, by prefix doubling."""
    n = len(a)
    rank = np.unique(a, return_inverse=True)[1].astype(np.int64)
    width = 1
    while n:
        after = np.full(n, -1, np.int64)
        after[:-width or n] = rank[width:]
        order = np.lexsort((after, rank))
        step = np.ones(n, np.int64)
        step[0] = 0
        step[1:] = (rank[order[1:]] != rank[order[:-1]]) | (after[order[1:]] != after[order[:-1]])
        rank = np.empty(n, np.int64)
        rank[order] = np.cumsum(step)
        if rank[order[-1]] == n - 1:
            return order
        width *= 2
        if width >= n:
            width = n - 1 or 1
    return np.zeros(0, np.int64)


def common_prefixes(a: np.ndarray, order: np.ndarray) -> np.ndarray:
    """Length of the common prefix of each suffix with the one before it in order."""
    n = len(a)
    place = np.empty(n, np.int64)
    place[order] = np.arange(n)
    out, h, body = np.zeros(n, np.int64), 0, a.tolist()
    for i in range(n):
        p = place[i]
        if p:
            j = order[p - 1]
            while i + h < n and j + h < n and body[i + h] == body[j + h]:
                h += 1
            out[p] = h
            h = max(0, h - 1)
        else:
            h = 0
    return out


def intervals(common: Sequence[int], least: int) -> Iterator[tuple[int, int, int]]:
    """(length, first, last) of the common-prefix intervals of at least ``least``, by one stack scan."""
    stack: list[tuple[int, int]] = []  # (length, first)
    n = len(common)
    for i in range(1, n + 1):
        here = common[i] if i < n else 0
        first = i - 1
        while stack and stack[-1][0] > here:
            length, first = stack.pop()
            yield length, first, i - 1
        if here >= least and (not stack or stack[-1][0] < here):
            stack.append((here, first))


def repeat_groups(texts: Sequence[bytes], least: int = LEAST) -> list[tuple[bytes, list[tuple[int, int]]]]:
    """Maximal repeats: (string, all its occurrences as (text, start)), none across texts."""
    parts, text_of, start_of = [], [], []
    for i, t in enumerate(texts):
        parts += [np.frombuffer(t, np.uint8).astype(np.int64), np.array([256 + i])]
        text_of.append(np.full(len(t) + 1, i))
        start_of.append(np.arange(len(t) + 1))
    if not parts:
        return []
    a, owner, start = np.concatenate(parts), np.concatenate(text_of), np.concatenate(start_of)
    order = suffix_array(a)
    common = common_prefixes(a, order).tolist()
    out = []
    for length, lo, hi in intervals(common, least):
        at = order[lo : hi + 1]
        left = {int(a[p - 1]) if start[p] else -1 - int(p) for p in at}
        if len(left) > 1:
            spots = sorted((int(owner[p]), int(start[p])) for p in at)
            out.append((bytes(a[at[0] : at[0] + length].astype(np.uint8)), spots))
    return out


# -- anchors ---------------------------------------------------------------------------------


def _least(h: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every ``width`` neighbours."""
    out, have = h, 1
    while have * 2 <= width:
        out = np.minimum(out[:-have], out[have:])
        have *= 2
    more = width - have
    return np.minimum(out[: len(out) - more], out[more:]) if more else out


def anchor_hashes(body: np.ndarray) -> np.ndarray:
    """A 64-bit hash (never 0) of every ANCHOR-byte string of ``body`` (ANCHOR is a power of two)."""
    h, base, width = body.astype(np.uint64) + np.uint64(1), _BASE, 1
    while width < ANCHOR:
        h = h[:-width] * np.uint64(base) + h[width:]
        base = base * base & 0xFFFFFFFFFFFFFFFF
        width *= 2
    return mix64(h) | np.uint64(1)


def anchors(body: np.ndarray, cut: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Positions of the anchors in texts laid end to end, all hashes, and the least hash of each
    window (0 where a window crosses a text's end)."""
    span = LEAST - ANCHOR + 1
    if len(body) < LEAST:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    h = anchor_hashes(body)
    low = _least(h, span)
    edge = np.zeros(len(body) + 1, np.int32)  # windows that start in the last 49 bytes of a text are none
    np.add.at(edge, np.maximum(cut[:-1], cut[1:] - (LEAST - 1)), 1)
    np.add.at(edge, cut[1:], -1)
    low = np.where(np.cumsum(edge[:-1])[: len(low)] > 0, np.uint64(0), low)
    pad = np.zeros(span - 1, np.uint64)
    best = ~_least(~np.concatenate([pad, low, pad]), span)
    return np.flatnonzero(best[: len(h)] == h), h, low


def names_of(h: np.ndarray) -> np.ndarray:
    """Anchors' names: their hashes mixed again, as hashes that are least in a window are small."""
    return mix64(h ^ np.uint64(0x5851F42D4C957F2D))


def _texts(batch: pa.RecordBatch) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    body, off = raw(empty_safe(batch.column("text")))
    for a, b in slices(off, 1 << 19):
        yield a, body[off[a] : off[b]], off[a : b + 1] - off[a]


def _tasks(df: DataFrame, ranges: int) -> int:
    """Tasks that ranges are dealt to: the session's shuffle partitions or a quarter of the ranges, at most one a range."""
    return max(1, min(ranges, max(ranges // 4, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))))


# -- pass 1: anchors of two documents or more ------------------------------------------------


def _pack(h40: np.ndarray) -> bytes:
    """Sorted values by their differences."""
    return packed(np.diff(h40, prepend=np.uint64(0)))


def _unpack(body: bytes) -> np.ndarray:
    return np.cumsum(unpacked(body, "u8")[0], dtype=np.uint64)


def repeated_anchors(docs: DataFrame, keep, ranges: int, most: int = HOT) -> tuple[bytes, bytes]:
    """Bitmaps of the anchors that two documents share (2**ANCHOR_BITS bits), and that more than ``most`` do."""
    log = max(6, min(16, (ranges - 1).bit_length()))

    def bits_of(values: np.ndarray, r: int, wide: int) -> bytes:
        bits = np.zeros(1 << (wide - log - 3), np.uint8)
        at = (values >> np.uint64(40 - wide)) - (np.uint64(r) << np.uint64(wide - log))
        np.bitwise_or.at(bits, (at >> np.uint64(3)).astype(np.int64), np.left_shift(np.uint8(1), (at & np.uint64(7)).astype(np.uint8)))
        return bits.tobytes()

    def gather(batches):
        held: list[np.ndarray] = []
        size = 0

        def flushed():
            every = np.concatenate(held)
            every.sort()
            bounds = np.searchsorted(every, np.arange((1 << log) + 1, dtype=np.uint64) << np.uint64(40 - log))
            some = np.flatnonzero(np.diff(bounds))
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array([_pack(every[bounds[r] : bounds[r + 1]]) for r in some], pa.binary())], ["range", "packed"])

        for batch in map(keep, released(batches)):
            for _, body, cut in _texts(batch):
                at, h, _ = anchors(body, cut)
                owner = np.searchsorted(cut, at, "right").astype(np.uint64)
                # once per document: sort by (hash, owner), drop equals
                v = names_of(h[at]) >> np.uint64(24)
                order = np.lexsort((owner, v))
                v, owner = v[order], owner[order]
                first = np.ones(len(v), bool)
                first[1:] = (v[1:] != v[:-1]) | (owner[1:] != owner[:-1])
                held.append(v[first])
                size += int(first.sum())
                if size > FLUSH:
                    yield flushed()
                    size = 0
        if size:
            yield flushed()

    def mark(batches):
        parts: dict[int, list[np.ndarray]] = {}

        def marked(r: int):
            v = np.concatenate(parts.pop(r))
            v.sort()
            twice = v[1:][v[1:] == v[:-1]]
            often = v[most:][v[most:] == v[: len(v) - most]] if len(v) > most else v[:0]
            return pa.RecordBatch.from_arrays([pa.array([r], pa.int32()), pa.array([bits_of(twice, r, ANCHOR_BITS)], pa.binary()), pa.array([bits_of(often, r, HOT_BITS)], pa.binary())], ["range", "bits", "hot"])

        for batch in batches:  # sorted by range
            for r, body in zip(batch.column("range").to_pylist(), batch.column("packed").to_pylist(), strict=True):
                for done in [x for x in parts if x != r]:
                    yield marked(done)
                parts.setdefault(r, []).append(_unpack(body))
        for r in list(parts):
            yield marked(r)

    dealt = docs.mapInArrow(gather, "range int, packed binary").repartition(_tasks(docs, 1 << log), "range").sortWithinPartitions("range")
    some, hot = bytearray(1 << (ANCHOR_BITS - 3)), bytearray(1 << (HOT_BITS - 3))
    for r in dealt.mapInArrow(mark, "range int, bits binary, hot binary").collect():  # fixed bits in all
        for out, part in ((some, r.bits), (hot, r.hot)):
            out[r.range * len(part) : (r.range + 1) * len(part)] = part
    return bytes(some), bytes(hot)


def _has(bits: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Whether the bitmap has each position (uint64)."""
    return (bits[(at >> np.uint64(3)).astype(np.int64)] >> (at & np.uint64(7)).astype(np.uint8)) & 1 == 1


# -- pass 2: contexts ------------------------------------------------------------------------

#: Contexts that a worker gathers before it writes them out.
HELD = 200_000


def _blob(doc, tag, at, inner, ctx: list[bytes]) -> bytes:
    """Rows of contexts, column by column, compressed; ``inner`` is where a context's anchor begins."""
    size = np.fromiter(map(len, ctx), np.uint8, len(ctx))
    head = packed(np.diff(doc, prepend=0), tag, at, inner, size)
    return np.int64(len(head)).tobytes() + head + zstandard.ZstdCompressor(level=7).compress(b"".join(ctx))


def _rows(blob: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, list[bytes]]:
    """Names of the anchors, documents, tags, positions and contexts."""
    cut = 8 + int(np.frombuffer(blob, np.int64, 1)[0])
    doc, tag, at, inner, size = unpacked(blob[8:cut], "i8", "i8", "i4", "u1", "u1")
    body = zstandard.ZstdDecompressor().decompress(blob[cut:])
    ends = np.cumsum(size, dtype=np.int64)
    name = names_of(anchor_hashes(np.frombuffer(body, np.uint8))[ends - size + inner]).view(np.int64)
    return name, np.cumsum(doc), tag, at, [body[e - z : e] for e, z in zip(ends.tolist(), size.tolist(), strict=True)]


def contexts(docs: DataFrame, keep, noted: tuple[bytes, bytes], ranges: int, common: bool) -> DataFrame:
    """Contexts of the noted anchors: packed by hash range (range, blob); or, with ``common``, those of
    hot anchors, a row each (doc, tag, at, ctx)."""
    holder = docs.sparkSession.sparkContext.broadcast(noted)
    span = LEAST - ANCHOR + 1
    log = (ranges - 1).bit_length()

    def run(batches):
        some, often = (np.frombuffer(x, np.uint8) for x in holder.value)
        held: list[tuple] = []
        size = 0

        def flushed():
            kh, doc, tag, at, inner = (np.concatenate([h[i] for h in held]) for i in range(5))
            ctx = [c for h in held for c in h[5]]
            held.clear()
            to = (kh.view(np.uint64) >> np.uint64(64 - log)).astype(np.int64) if log else np.zeros(len(kh), np.int64)
            order = np.argsort(to, kind="stable")
            some_, first = np.unique(to[order], return_index=True)
            bounds = [*first.tolist(), len(order)]
            blobs = []
            for i, j in zip(bounds, bounds[1:], strict=False):
                o = order[i:j]
                blobs.append(_blob(doc[o], tag[o], at[o], inner[o], [ctx[x] for x in o.tolist()]))
            return pa.RecordBatch.from_arrays([pa.array(some_.astype(np.int32)), pa.array(blobs, pa.binary())], ["range", "blob"])

        for batch in map(keep, released(batches)):
            keys, marks = batch.column("doc").to_numpy(), batch.column("tag").to_numpy()
            for a, body, cut in _texts(batch):
                at, h, low = anchors(body, cut)
                name = names_of(h[at])
                wanted = _has(some, name >> np.uint64(64 - ANCHOR_BITS)) & (_has(often, name >> np.uint64(64 - HOT_BITS)) == common)
                at, name = at[wanted], name[wanted]
                if not len(at):
                    continue
                padded = np.concatenate([np.zeros(span - 1, np.uint64), low, np.zeros(span, np.uint64)])
                own = padded[at[:, None] + np.arange(span)] == h[at][:, None]
                first = at - (span - 1) + own.argmax(axis=1)
                last = at - own[:, ::-1].argmax(axis=1)
                owner = np.searchsorted(cut, at, "right") - 1
                whole = body.tobytes()
                ctx = [whole[i : j + LEAST] for i, j in zip(first.tolist(), last.tolist(), strict=True)]
                kh, doc, tag, begin, inner = name.view(np.int64), keys[a + owner], marks[a + owner], (first - cut[owner]).astype(np.int32), (at - first).astype(np.uint8)
                if common:
                    yield pa.RecordBatch.from_arrays([pa.array(doc), pa.array(tag), pa.array(begin), pa.array(ctx, pa.binary())], ["doc", "tag", "at", "ctx"])
                    continue
                held.append((kh, doc, tag, begin, inner, ctx))
                size += len(kh)
                if size >= HELD:
                    yield flushed()
                    size = 0
        if size:
            yield flushed()

    return docs.mapInArrow(run, "doc long, tag long, at int, ctx binary" if common else "range int, blob binary")


# -- pass 3: suffix arrays of contexts -------------------------------------------------------


def _words(starts: np.ndarray, ends: np.ndarray, flat: np.ndarray, words: int) -> list[np.ndarray]:
    """The suffixes as sort keys, seven bytes a word, zero beyond their ends (bytes are stored plus one)."""
    out = []
    for w in range(words):
        key = np.zeros(len(starts), np.uint64)
        for b in range(7):
            p = starts + 7 * w + b
            live = p < ends
            key = key * np.uint64(512) + np.where(live, flat[np.minimum(p, len(flat) - 1)] + np.uint64(1), np.uint64(0))
        out.append(key)
    return out


def covered(ctx: Sequence[bytes], first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(context, start, end) as arrays: runs of a context whose windows occur in an earlier document.

    ``first`` is the first document of each context. The suffixes that start a window of some
    context are sorted; the intervals of their common prefixes are repeat groups.
    """
    size = np.array([len(c) for c in ctx])
    flat = np.frombuffer(b"".join(ctx), np.uint8).astype(np.uint64)
    base = np.cumsum(size) - size
    many = size - LEAST + 1
    row = np.repeat(np.arange(len(ctx)), many)
    starts = base[row] + np.arange(len(row)) - np.repeat(np.cumsum(many) - many, many)
    h, base_, width, built = flat + np.uint64(1), _BASE, 1, None
    need = LEAST  # hash of every LEAST bytes of the flat text, by doubling
    while need:
        if need & 1:
            built = h if built is None else built[: len(built) - width] * np.uint64(base_) + h[len(flat) - len(built) + 1 :][: len(built) - width]
        need >>= 1
        if need:
            h = h[:-width] * np.uint64(base_) + h[width:]
            base_ = base_ * base_ & 0xFFFFFFFFFFFFFFFF
            width *= 2
    same = mix64(built)[starts]
    order = np.argsort(same, kind="stable")
    twin = np.zeros(len(order), bool)
    twin[1:] = same[order[1:]] == same[order[:-1]]
    twin[:-1] |= twin[1:]
    live = order[twin]  # windows that are alone start no repeat
    if not len(live):
        return (np.zeros(0, np.int64),) * 3
    live.sort()
    row, starts = row[live], starts[live]
    ends = (base + size)[row]
    longest = int((ends - starts).max())
    keys = _words(starts, ends, flat, -(-longest // 7))
    order = np.lexsort(keys[::-1])
    row, starts, ends = row[order], starts[order], ends[order]
    common = np.zeros(len(order), np.int64)
    going = np.arange(1, len(order))
    depth = 0
    while len(going):
        p, q = starts[going] + depth, starts[going - 1] + depth
        going = going[(p < ends[going]) & (q < ends[going - 1]) & (flat[np.minimum(p, len(flat) - 1)] == flat[np.minimum(q, len(flat) - 1)])]
        common[going] += 1
        depth += 1
    inner = starts > base[row]
    before = np.where(inner, flat[np.maximum(starts - 1, 0)].astype(np.int64), -1 - row)
    by = first[row]
    best = np.zeros(len(row), np.int64)  # longest repeat from each suffix that an earlier document has
    for length, lo, hi in intervals(common.tolist(), LEAST):
        left = before[lo : hi + 1]
        if (left == left[0]).all():
            continue  # the same repeat, one byte further left, covers this one
        docs = by[lo : hi + 1]
        np.maximum(best[lo : hi + 1], np.where(docs > docs.min(), length, 0), out=best[lo : hi + 1])
    hit = np.flatnonzero(best)
    start = starts[hit] - base[row[hit]]
    return _runs(row[hit], start, start + best[hit])


def _runs(name: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Spans [a, b) of the same name that touch, as one."""
    order = np.lexsort((b, a, name))
    name, a, b = name[order], a[order], b[order]
    if not len(name):
        return name, a, b
    group = np.cumsum(np.concatenate([[0], name[1:] != name[:-1]])).astype(np.int64)
    reach = np.maximum.accumulate(b + group * (1 << 40)) - group * (1 << 40)
    at = np.flatnonzero(np.concatenate([[True], (group[1:] != group[:-1]) | (a[1:] > reach[:-1])]))
    return name[at], a[at], np.maximum.reduceat(b, at)


def _solve(kh, doc, tag, at, body: list[bytes]) -> pa.RecordBatch:
    """Spans (doc, tag, a, b) of the documents of whole anchors."""
    number: dict[bytes, int] = {}
    kind = np.fromiter((number.setdefault(c, len(number)) for c in body), np.int64, len(body))
    kinds = list(number)
    first, anchor = np.full(len(kinds), np.iinfo(np.int64).max), np.zeros(len(kinds), np.int64)
    np.minimum.at(first, kind, doc)
    anchor[kind] = kh
    size = np.fromiter(map(len, kinds), np.int64, len(kinds))
    own = np.flatnonzero(doc > first[kind])  # the first document of a context keeps it, others don't
    rows, starts, lengths = [own], [np.zeros(len(own), np.int64)], [size[kind[own]]]
    _, back, many = np.unique(anchor, return_inverse=True, return_counts=True)
    several = np.flatnonzero(many[back] > 1)
    which, start, end = covered([kinds[i] for i in several.tolist()], first[several]) if len(several) else (several, several, several)
    if len(which):
        which = several[which]
        order = np.argsort(kind, kind="stable")
        lo, hi = np.searchsorted(kind[order], which, "left"), np.searchsorted(kind[order], which, "right")
        n = hi - lo
        rows.append(order[np.repeat(lo - (np.cumsum(n) - n), n) + np.arange(n.sum())])
        starts.append(np.repeat(start, n))
        lengths.append(np.repeat(end - start, n))
    row, start, length = (np.concatenate(x) for x in (rows, starts, lengths))
    a = at[row] + start
    text, back = np.unique(np.stack([doc[row], tag[row]], axis=1), axis=0, return_inverse=True)
    name, a, b = _runs(back.ravel(), a, a + length)
    return pa.RecordBatch.from_arrays([pa.array(text[name, 0]), pa.array(text[name, 1]), pa.array(a.astype(np.int32)), pa.array(b.astype(np.int32))], ["doc", "tag", "a", "b"])


def cold_spans(packed: DataFrame, ranges: int) -> DataFrame:
    """(doc, tag, a, b) from the packed contexts, a hash range at a time, whole anchors at a time."""

    def solved(blobs: list[bytes]):
        got = [_rows(b) for b in blobs]
        kh, doc, tag, at = (np.concatenate([g[i] for g in got]) for i in range(4))
        ctx = [c for g in got for c in g[4]]
        order = np.argsort(kh, kind="stable")
        kh, doc, tag, at, a = kh[order], doc[order], tag[order], at[order], 0
        order = order.tolist()
        while a < len(kh):
            b = int(np.searchsorted(kh, kh[min(a + BATCH, len(kh)) - 1], "right"))
            yield _solve(kh[a:b], doc[a:b], tag[a:b], at[a:b], [ctx[i] for i in order[a:b]])
            a = b

    def run(batches):
        here, held = None, []
        for batch in released(batches):  # sorted by range
            for r, blob in zip(batch.column("range").to_pylist(), batch.column("blob"), strict=True):
                if r != here and held:
                    yield from solved(held)
                    held = []
                here = r
                held.append(blob.as_py())
        if held:
            yield from solved(held)

    dealt = packed.repartition(_tasks(packed, ranges), "range").sortWithinPartitions("range")
    return dealt.mapInArrow(run, "doc long, tag long, a int, b int")


def hot_spans(found: DataFrame) -> DataFrame:
    """(doc, tag, a, b) from the contexts of common anchors, by aggregation alone."""
    kinds = staged(found.groupBy("ctx").agg(F.min("doc").alias("first")))
    windows = kinds.select("ctx", "first", F.explode(F.sequence(F.lit(0), F.length("ctx") - LEAST)).alias("s")).withColumn("w", F.substring("ctx", F.col("s") + 1, F.lit(LEAST)))
    firsts = staged(windows.groupBy("w").agg(F.min("first").alias("f")))
    lost = staged(windows.join(firsts, "w").groupBy("ctx").agg(F.collect_list(F.struct("s", "f")).alias("lost")))
    each = found.join(lost, "ctx").select("doc", "tag", "at", F.explode("lost").alias("x")).where("doc > x.f")
    return each.select("doc", "tag", (F.col("at") + F.col("x.s")).alias("a"), (F.col("at") + F.col("x.s") + LEAST).alias("b"))


# -- pass 4: the documents -------------------------------------------------------------------


def _merge(spans) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


#: Keys of several texts that are broadcast.
SEVERAL = 1_000_000


def tagged(rows: DataFrame, several: DataFrame | None, key: str, th: str, tag: str) -> DataFrame:
    """``rows`` with their tag, which tells texts of one key apart: ``th``, or 0 if the key has but one text."""
    if several is None:
        return rows.withColumn(tag, F.col(th))
    other = fresh(rows, "several")
    with_ = rows.join(F.broadcast(several.select(F.col("doc").alias(other))), F.col(key).cast("long") == F.col(other), "left")
    return with_.withColumn(tag, F.when(F.col(other).isNull(), F.lit(0).cast("long")).otherwise(F.col(th))).drop(other)


def spans(docs: DataFrame, key: str = "doc_id", text: str = "text", hot: int = HOT) -> tuple[DataFrame, DataFrame | None]:
    """(doc, tag, cut): for each document that loses bytes its merged runs as array<struct<a, b>>; and
    the keys of several texts (None if there are more than SEVERAL). Documents are named by key and tag."""
    t = F.col(text)
    source = docs.select(F.col(key).cast("long").alias("doc"), t.alias("text"), F.xxhash64(t).alias("th"), F.xxhash64(F.lit(7), t).alias("t2")).where("doc is not null")
    names = staged(source.select("doc", "th", "t2", F.coalesce(F.octet_length("text"), F.lit(0)).alias("n")))
    several = staged(names.groupBy("doc").agg(F.min("th").alias("a"), F.max("th").alias("b")).where("a <> b").select("doc"))
    if several.count() > SEVERAL:
        several = None
    names = names.where(F.col("n") >= LEAST)  # shorter ones have no window
    copied = staged(names.groupBy("th", "t2", "n").agg(F.min("doc").alias("first"), F.max("doc").alias("last")).where("last > first"))
    copies = bitmap(copied.select(F.col("th").alias("at")), CHANGED_BITS)
    mask = np.uint64((1 << CHANGED_BITS) - 1)
    shared = docs.sparkSession.sparkContext.broadcast(copies)

    def routed(batches):
        for batch in batches:
            yield batch.filter(pa.array(_has(np.frombuffer(shared.value, np.uint8), batch.column("th").to_numpy().view(np.uint64) & mask)))

    # Which of the noted texts are later copies is settled exactly; all others are noted as read.
    known = staged(names.mapInArrow(routed, names.schema).join(copied, ["th", "t2", "n"], "left").select("doc", "th", "n", "first"))
    read = bitmap(known.where("first is null or doc <= first").select(F.xxhash64("doc", "th").alias("at")), CHANGED_BITS)
    holder = docs.sparkSession.sparkContext.broadcast((copies, read))

    def keep(batch: pa.RecordBatch) -> pa.RecordBatch:
        """Less the later copies: a full bitmap lets some of them through, and never drops another text."""
        copy, lead = (np.frombuffer(x, np.uint8) for x in holder.value)
        th, own = (batch.column(c).to_numpy().view(np.uint64) & mask for c in ("th", "name"))
        return batch.filter(pa.array(~_has(copy, th) | _has(lead, own)))

    rest = source.where(F.octet_length("text") >= LEAST).select("doc", "text", "th", F.xxhash64("doc", "th").alias("name"))
    parts = docs.rdd.getNumPartitions()
    noted = repeated_anchors(rest, keep, parts, hot)
    ranges = 1 << max(8, (4 * parts - 1).bit_length())
    rest = tagged(rest, several, "doc", "th", "tag")
    every = cold_spans(contexts(rest, keep, noted, ranges, False), ranges)
    if any(noted[1]):
        every = every.union(hot_spans(staged(contexts(rest, keep, noted, ranges, True))))
    gone = tagged(known.where("doc > first"), several, "doc", "th", "tag").select("doc", "tag", F.lit(0).alias("a"), F.col("n").alias("b"))
    every = every.union(gone)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        cut = [[{"a": a, "b": b} for a, b in _merge((x["a"], x["b"]) for x in xs)] for xs in batch.column("cut").to_pylist()]
        return pa.RecordBatch.from_arrays([batch.column("doc"), batch.column("tag"), pa.array(cut, pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())])))], ["doc", "tag", "cut"])

    gathered = every.groupBy("doc", "tag").agg(F.collect_set(F.struct("a", "b")).alias("cut"))
    return staged(gathered.mapInArrow(lambda bs: (run(b) for b in bs if b.num_rows), "doc long, tag long, cut array<struct<a:long,b:long>>")), several


def _both(docs: DataFrame, key: str, text: str, fn, schema: str, hot: int) -> DataFrame:
    """``fn(batch, cut)`` over all rows; cut is null where nothing goes. Runs of at most
    SMALL bytes in all are broadcast; beyond that, texts that a bitmap doesn't note are done where
    they are read and the others are joined to their runs."""
    lost, several = spans(docs, key, text, hot)
    n, m = lost.agg(F.count("*"), F.coalesce(F.sum(F.size("cut")), F.lit(0))).first()
    th, tag, cut_ = fresh(docs, "th"), fresh(docs, "tag"), fresh(docs, "cut")
    doc_, tag_, name = fresh(docs, "doc2"), fresh(docs, "tag2"), fresh(docs, "name")
    named = tagged(docs.withColumn(th, F.xxhash64(text)), several, key, th, tag).drop(th)
    cut = lost.select(F.col("doc").alias(doc_), F.col("tag").alias(tag_), F.col("cut").alias(cut_))

    def run(batches):
        for b in released(batches):
            if b.num_rows:
                yield fn(b, b.column(cut_))

    def joined(rows: DataFrame, runs_: DataFrame) -> DataFrame:
        out = rows.join(runs_, (F.col(key).cast("long") == F.col(doc_)) & (F.col(tag) == F.col(tag_)), "left")
        return out.select(*docs.columns, cut_).mapInArrow(run, schema)

    if 64 * n + 32 * m <= SMALL:
        return joined(named, F.broadcast(cut))
    holder = docs.sparkSession.sparkContext.broadcast(bitmap(lost.select(F.xxhash64("doc", "tag").alias("at")), CHANGED_BITS))
    named = named.withColumn(name, F.xxhash64(F.col(key).cast("long"), tag))
    mask = np.uint64((1 << CHANGED_BITS) - 1)
    runs = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))

    def noted(batch: pa.RecordBatch) -> np.ndarray:
        return _has(np.frombuffer(holder.value, np.uint8), batch.column(name).to_numpy().view(np.uint64) & mask)

    def same(batches):
        for batch in batches:
            batch = batch.filter(pa.array(~noted(batch)))
            if batch.num_rows:
                yield fn(batch, pa.nulls(batch.num_rows, runs))

    def changed(batches):
        for batch in batches:
            yield batch.filter(pa.array(noted(batch)))

    return named.mapInArrow(same, schema).union(joined(named.mapInArrow(changed, named.schema), cut))


def digest(docs: DataFrame, key: str = "doc_id", text: str = "text", hot: int = HOT) -> DataFrame:
    """Per row: key, n_bytes, n_removed, n_spans and the hash of the bytes that stay."""

    def run(batch: pa.RecordBatch, cuts: pa.Array) -> pa.RecordBatch:
        rows = []
        for t, cut in zip(batch.column(text).to_pylist(), cuts.to_pylist(), strict=True):
            body = (t or "").encode()
            runs = [(x["a"], x["b"]) for x in cut or ()]
            rows.append((len(body), sum(b - a for a, b in runs), len(runs), hashlib.sha256(without(body, runs)).hexdigest()))
        cols = [pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.string()), strict=True)]
        return pa.RecordBatch.from_arrays([batch.column(key), *cols], [key, "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return _both(docs.select(key, text), key, text, run, f"`{key}` {docs.schema[key].dataType.simpleString()}, n_bytes long, n_removed long, n_spans long, kept_sha256 string", hot)


def without(body: bytes, runs: Sequence[tuple[int, int]]) -> bytes:
    out, at = [], 0
    for a, b in runs:
        out.append(body[at:a])
        at = b
    return b"".join(out) + body[at:]


def whole_characters(body: bytes, runs: Sequence[tuple[int, int]]) -> list[tuple[int, int]]:
    """The runs shrunk so that no character is cut in two."""
    out = []
    for a, b in runs:
        while a < b and body[a] & 0xC0 == 0x80:
            a += 1
        while b > a and b < len(body) and body[b] & 0xC0 == 0x80:
            b -= 1
        if a < b:
            out.append((a, b))
    return out


def cut_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text", hot: int = HOT) -> DataFrame:
    """``docs``, all columns, with the repeated bytes (whole characters of them) gone from its texts."""
    fields = docs.schema.fields

    def run(batch: pa.RecordBatch, cuts: pa.Array) -> pa.RecordBatch:
        column, new = batch.column(text), []
        for t, cut in zip(column.to_pylist(), cuts.to_pylist(), strict=True):
            if t and cut:
                body = t.encode()
                t = without(body, whole_characters(body, [(x["a"], x["b"]) for x in cut])).decode()
            new.append(t)
        cols = [pa.array(new, column.type) if f.name == text else batch.column(f.name) for f in fields]
        return pa.RecordBatch.from_arrays(cols, [f.name for f in fields])

    return _both(docs, key, text, run, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in fields), hot)
