"""Vector best-fit packing of tokenised documents into fixed-length sequences.

A sequence has three capacities: tokens, documents and attention cost (the sum of squared piece
lengths). Pieces are taken by falling length; among the open sequences that can hold a piece under
every constraint the one with the best score takes it: ``dot`` is the weighted product of the
piece's demand and the residual (smallest residual along the demand wins), ``norm`` the weighted
norm of what would be left. Sequences of equal residual are interchangeable, so the search is over
distinct residuals, not over sequences.

Tokenising is one narrow pass; its small result (a row per piece) is staged, dealt at random into
groups of about ``GROUP`` pieces and each group is packed in one task. The number of groups grows
with the input, a task's rows do not, and a group loses at most its last sequences.

Defined cases: a null or empty text is the end id alone; only texts longer than a sequence are cut,
their first piece taking the remainder; equal lengths are packed in key order; rows are told apart
by position, so repeated keys keep their pieces; an empty table gives no rows; other columns are
not read.
"""

from __future__ import annotations

import bisect
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evsketch.llm.bpe import ids_of_all
from evsketch.llm.common import arrow_map, empty_safe, staged

#: Pieces that one task packs.
GROUP = 12_000


@dataclass(frozen=True)
class Bin:
    """Capacities of a sequence, the weight of each and the score. The defaults for documents and
    attention bind no earlier than the tokens do."""

    tokens: int = 2048
    documents: int = 2048
    attention: int = 2048 * 2048
    weights: tuple[float, float, float] = (1.0, 0.05, 0.05)
    score: str = "norm"


def piece_bounds(length: int, size: int) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces; the first takes the remainder."""
    first = length % size or size
    return [(0, min(first, length))] + [(a, size) for a in range(first, length, size)]


def best_fit(lengths: np.ndarray, box: Bin) -> tuple[np.ndarray, np.ndarray]:
    """Sequence number and offset of each piece; ``lengths`` must fall."""
    n = len(lengths)
    seq, offset = np.zeros(n, np.int64), np.zeros(n, np.int64)
    cap = np.array([box.tokens, box.documents, box.attention], float)
    w = np.array(box.weights)
    open_by: dict[int, dict[tuple[int, int], list[int]]] = {}  # free tokens -> (free documents, free attention) -> sequences
    frees: list[int] = []  # sorted keys of open_by
    made = 0

    def put(free: tuple[int, int, int], s: int) -> None:
        if free[0] <= 0 or free[1] <= 0:
            return
        if free[0] not in open_by:
            open_by[free[0]] = {}
            bisect.insort(frees, free[0])
        open_by[free[0]].setdefault(free[1:], []).append(s)

    def left(free: tuple[int, int, int], need: tuple[int, int, int]) -> float:
        rest = (np.array(free) - need) / cap
        if box.score == "dot":
            return float((w * np.array(free) / cap * (np.array(need) / cap)).sum())
        return float((w * rest * rest).sum())

    for i in range(n):
        size = int(lengths[i])
        need = (size, 1, size * size)
        chosen, best = None, float("inf")
        for free_tokens in frees[bisect.bisect_left(frees, size) :]:
            # the token residual alone bounds the score from below, and it only grows from here
            bound = w[0] * ((free_tokens - size) / cap[0]) ** 2 if box.score == "norm" else w[0] * free_tokens * size / cap[0] ** 2
            if bound > best:
                break
            for free in open_by[free_tokens]:
                if free[0] >= 1 and free[1] >= need[2]:
                    whole = (free_tokens, *free)
                    value = left(whole, need)
                    if value < best:
                        chosen, best = whole, value
        if chosen is None:
            chosen, s = (box.tokens, box.documents, box.attention), made
            made += 1
        else:
            group = open_by[chosen[0]]
            s = group[chosen[1:]].pop()
            if not group[chosen[1:]]:
                del group[chosen[1:]]
                if not group:
                    del open_by[chosen[0]]
                    del frees[bisect.bisect_left(frees, chosen[0])]
        seq[i], offset[i] = s, box.tokens - chosen[0]
        put((chosen[0] - need[0], chosen[1] - need[1], chosen[2] - need[2]), s)
    return seq, offset


def pieces(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text", size: int = 2048, end_id: int = 0) -> DataFrame:
    """A row per piece: row (position), key, piece, start, length, ids_crc32."""
    tail = int(end_id).to_bytes(4, "little")

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        take, cols = [], [[], [], [], []]
        for i, known in enumerate(ids_of_all(empty_safe(batch.column(text)), path)):
            ids = known.tobytes() + tail
            for p, (a, n) in enumerate(piece_bounds(len(ids) // 4, size)):
                take.append(i)
                for c, v in zip(cols, (p, a, n, zlib.crc32(ids[4 * a : 4 * (a + n)])), strict=True):
                    c.append(v)
        rows = pa.array(take, pa.int64())
        kinds = (pa.int32(), pa.int64(), pa.int64(), pa.int64())
        return pa.RecordBatch.from_arrays([batch.column("row").take(rows), batch.column("key").take(rows), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], ["row", "key", "piece", "start", "length", "ids_crc32"])

    kind = docs.schema[key].dataType.simpleString()
    source = docs.select(F.monotonically_increasing_id().alias("row"), F.col(key).alias("key"), F.col(text).alias(text))
    return arrow_map(source, run, f"row long, key {kind}, piece int, start long, length long, ids_crc32 long")


def pack(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text", box: Bin = Bin(), group: int = GROUP) -> DataFrame:
    """A row per piece with its sequence_id and offset in it."""
    cut = staged(pieces(docs, path, key, text, box.tokens))
    groups = max(1, -(-cut.count() // group))
    kind = docs.schema[key].dataType.simpleString()

    def run(batches):
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        table = pa.Table.from_batches(held).combine_chunks()
        length, row, piece = (table.column(c).to_numpy() for c in ("length", "row", "piece"))
        order = np.lexsort((piece, row, -length))
        seq, off = np.zeros(len(order), np.int64), np.zeros(len(order), np.int64)
        seq[order], off[order] = best_fit(length[order], box)
        part = table.column("part").to_numpy()[0]  # one partition is one group
        base = int(part) << 32
        out = table.drop_columns(["part", "row"]).append_column("sequence_id", pa.array(seq + base)).append_column("offset", pa.array(off))
        yield from out.to_batches()

    dealt = cut.repartition(groups, F.xxhash64("row", "piece")).withColumn("part", F.spark_partition_id().cast("long"))
    done = dealt.mapInArrow(run, f"key {kind}, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
    return done.withColumnRenamed("key", key)
