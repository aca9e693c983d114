"""Quality by an interpolated modified Kneser-Ney n-gram model of trusted text.

Text is a sequence of lower-cased characters of any script, each text after order-1 pads, and the
model is one of character n-grams. Its counts are those of all trusted documents but the held-out
ones (one in ``Model.hold``, by a hash of the key), so they grow with the corpus; nothing of them
reaches the driver but the counts of counts. One query goes through these steps:

1. documents are packed into blobs (compressed text of whole documents), written once to the shared
   folder as a table bucketed by blob, so that what is joined to a blob travels to it, never text;
2. labels are joined to keys, trusted positions travel to their blobs, and the n-grams there are
   counted per blob and summed by n-gram. Continuation counts, counts of counts, discounts and the
   interpolation are aggregations and joins of n-gram tables: an n-gram meets its context and its
   suffix, of which a table has at most as many as the alphabet has characters;
3. each blob asks once for every different window it holds, in every order. Questions and the
   model's entries are dealt by shards of the n-grams' hashes (and salts, which the entries are
   repeated for), and answers travel back to the blobs, where the unseen n-grams back off;
4. a document has two measures: its perplexity, and its peak, the perplexity of the ``order``
   neighbouring symbols that surprise the model most (a few foreign words, such as abuse, vanish in the mean
   of a long text). The quantiles of both over the held-out trusted documents of a language, times
   ``Model.margin``, are its thresholds. A kept document is over neither.

Defined cases: null or empty texts have no perplexity or peak and are not kept; a language (null counts as
one) with fewer than ``least`` held-out trusted documents takes the thresholds of all of them, and
without any held-out document at all that of the trusted ones; with fewer than ``least`` in all there
is no threshold of peaks (null) and they decide nothing; a null key is in no label; repeated rows get equal scores;
with no trusted text at all every row is kept; an empty table gives no rows; other columns are not
read.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evsketch.llm.common import mix64, packed, released, shared_dir, small, staged, unpacked

#: UTF-8 bytes of text in a blob; it ends after the document that reaches them.
BLOB = 12 << 20
#: Entries of a table that is addressed directly; beyond, values are ranked by sorting.
DIRECT = 1 << 24
#: Positions handled at a time.
CHUNK = 1 << 20
#: Model entries of a shard, and bytes of text that one shard and salt answer for.
SHARD, SALT = 1 << 18, 256 << 20
LEAST_SHARDS = 64
PAD = "\0"

_BASE = np.uint64(0x9E3779B97F4A7C15)


@dataclass(frozen=True)
class Model:
    """Order, share of trusted documents held out (one in ``hold``), and what sets the thresholds; a
    language of its own threshold has ``least`` held-out documents."""

    order: int = 5
    hold: int = 8
    least: int = 20
    quantile: float = 0.99
    margin: float = 1.25


# -- windows of a padded text --------------------------------------------------------------------


def _ranks(codes, size: int, many: int) -> tuple[np.ndarray, np.ndarray]:
    """Different values of a sequence, sorted, and each position's rank. ``codes(a, b)`` gives
    positions [a, b) of ``size``; values lie below ``many``."""
    spots = [(a, min(size, a + CHUNK)) for a in range(0, size, CHUNK)]
    if many <= DIRECT:
        seen = np.zeros(many, bool)
        for a, b in spots:
            seen[codes(a, b)] = True
        found = np.flatnonzero(seen)
        place = np.cumsum(seen, dtype=np.int32)
        place -= 1
        rank = np.empty(size, np.uint16 if len(found) <= 1 << 16 else np.int32)
        for a, b in spots:
            rank[a:b] = place[codes(a, b)]
        return found, rank
    found = np.zeros(0, np.int64)
    for a, b in spots:
        found = np.union1d(found, codes(a, b))
    rank = np.empty(size, np.int32)
    for a, b in spots:
        rank[a:b] = np.searchsorted(found, codes(a, b))
    return found, rank


@dataclass
class Windows:
    """Different windows of one size: where their context (one symbol less at the end) and suffix
    (one less at the start) stand among the windows one shorter, their last symbols and hashes."""

    context: np.ndarray
    suffix: np.ndarray
    last: np.ndarray
    raw: np.ndarray

    def keys(self, size: int) -> np.ndarray:
        return mix64(self.raw + np.uint64(size * 0xD6E8FEB86659FD93 & (1 << 64) - 1))


def symbol_hash(symbols: np.ndarray) -> np.ndarray:
    return mix64(symbols.astype(np.uint64) + np.uint64(0x51ED270B))


def windows(text: np.ndarray, order: int) -> tuple[list[Windows], np.ndarray]:
    """Windows of 1 to ``order`` symbols of ``text`` (code points that start with order-1 pads), and
    for each position the rank of the largest one that ends there."""
    size = len(text)
    alphabet, one = _ranks(lambda a, b: text[a:b], size, 0x110000)
    del text  # the caller holds no reference, so its memory is free
    many, marks = max(1, len(alphabet)), symbol_hash(alphabet)
    none = np.zeros(len(alphabet), np.int64)
    out = [Windows(none, none, alphabet, marks)]
    rank, before = one, alphabet
    for _ in range(order - 1):

        def codes(a: int, b: int, rank=rank) -> np.ndarray:
            left = rank[a - 1 : b - 1] if a else np.concatenate([rank[:1], rank[: b - 1]])
            return left.astype(np.int64) * many + one[a:b]

        found, now = _ranks(codes, size, len(before) * many)
        context, at = found // many, found % many
        top = out[-1]
        suffix = at if len(out) == 1 else np.searchsorted(before, top.suffix[context] * many + at)
        out.append(Windows(context, suffix, alphabet[at], top.raw[context] * _BASE + marks[at]))
        rank, before = now, found
    return out, rank


def spelled(levels: list[Windows], some: np.ndarray) -> list[str]:
    """The largest windows at the ranks ``some`` as strings."""
    order = len(levels)
    chars, at = np.empty((len(some), order), np.uint32), some
    for k in range(order - 1, -1, -1):
        chars[:, k] = levels[k].last[at]
        at = levels[k].context[at]
    text = chars.tobytes().decode("utf-32-le")
    return [text[i : i + order] for i in range(0, len(text), order)]


# -- blobs -------------------------------------------------------------------------------------


class Blobs:
    """The documents as a table (blob, size, keys, langs, chars, body) bucketed by blob."""

    def __init__(self, docs: DataFrame, key: str, text: str, lang: str, order: int):
        self.spark, self.kind = docs.sparkSession, docs.schema[key].dataType.simpleString()
        pads = PAD * (order - 1)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            keys, langs, texts, size, number = [], [], [], 0, TaskContext.get().partitionId() << 32
            key_type = None

            def blob() -> pa.RecordBatch:
                body = zstandard.ZstdCompressor(level=4).compress("".join(pads + t for t in texts).encode())
                cols = [pa.array([number]), pa.array([size]), pa.array([keys], pa.list_(key_type)), pa.array([langs], pa.list_(pa.string())), pa.array([[len(t) for t in texts]], pa.list_(pa.int32())), pa.array([body], pa.binary())]
                return pa.RecordBatch.from_arrays(cols, ["blob", "size", "keys", "langs", "chars", "body"])

            for batch in released(batches):
                key_type = batch.schema.field("k").type
                for k, t, name in zip(batch.column("k").to_pylist(), batch.column("t"), batch.column("l").to_pylist(), strict=True):
                    t = (t.as_py() or "").lower()
                    keys.append(k)
                    langs.append(name)
                    texts.append(t)
                    size += len(t) if t.isascii() else len(t.encode())
                    if size >= BLOB:
                        yield blob()
                        keys, langs, texts, size, number = [], [], [], 0, number + 1
            if keys:
                yield blob()

        rows = docs.select(F.col(key).alias("k"), F.col(text).cast("string").alias("t"), F.col(lang).cast("string").alias("l"))
        blobs = rows.mapInArrow(run, f"blob long, size long, keys array<{self.kind}>, langs array<string>, chars array<int>, body binary")
        self.buckets = max(1, min(50_000, docs.rdd.getNumPartitions()))
        self.name = f"blobs_{uuid.uuid4().hex}"
        self.path = f"{shared_dir(self.spark).rstrip('/')}/{self.name}"
        blobs.write.bucketBy(self.buckets, "blob").sortBy("blob").option("path", self.path).format("parquet").saveAsTable(self.name)

    def table(self) -> DataFrame:
        return self.spark.table(self.name)

    def meet(self, rows: DataFrame) -> DataFrame:
        """The blobs beside ``rows`` (one a blob), which alone are shuffled."""
        return self.table().join(rows.hint("shuffle_merge"), "blob")

    def travelling(self, rows: DataFrame) -> DataFrame:
        """``rows`` dealt as the blobs are."""
        return rows.repartition(self.buckets, "blob")

    def drop(self) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
        jvm, conf = self.spark._jvm, self.spark.sparkContext._jsc.hadoopConfiguration()
        target = jvm.org.apache.hadoop.fs.Path(self.path)
        target.getFileSystem(conf).delete(target, True)


def code_points(body: bytes) -> np.ndarray:
    return np.frombuffer(zstandard.ZstdDecompressor().decompress(body).decode().encode("utf-32-le"), np.uint32)


# -- counts and probabilities --------------------------------------------------------------------


def count_grams(marked: DataFrame, order: int) -> DataFrame:
    """(gram, n): n-grams of the documents at ``spots`` of each blob, summed per blob before the shuffle."""
    pads = order - 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            for body, chars, spots in zip(batch.column("body"), batch.column("chars"), batch.column("spots"), strict=True):
                text, size = code_points(body.as_py()), np.asarray(chars.as_py(), np.int64)
                end = np.cumsum(size + pads)
                taken = [(int(end[s] - size[s] - pads), int(end[s])) for s in sorted(set(spots.as_py())) if size[s]]
                if not taken:
                    continue
                levels, rank = windows(np.concatenate([text[a:b] for a, b in taken]), order)
                del text
                live = np.ones(len(rank), bool)
                at = np.cumsum([0] + [b - a for a, b in taken[:-1]])
                for i in range(pads):
                    live[at + i] = False
                n = np.bincount(rank[live], minlength=len(levels[-1].last))
                some = np.flatnonzero(n)
                yield pa.RecordBatch.from_arrays([pa.array(spelled(levels, some), pa.string()), pa.array(n[some].astype(np.int64))], ["gram", "n"])

    return marked.select("body", "chars", "spots").mapInArrow(run, "gram string, n long").groupBy("gram").agg(F.sum("n").alias("n"))


def _discounts(level: DataFrame) -> tuple[float, float, float]:
    """Discounts for counts of one, two and more, from the counts of counts."""
    met = level.agg(*[F.coalesce(F.sum((F.col("n") == i).cast("long")), F.lit(0)) for i in (1, 2, 3, 4)]).first()
    if not met[0]:
        return 0.5, 0.5, 0.5
    y = met[0] / (met[0] + 2 * met[1])
    return tuple(min(float(i), max(0.0, i - (i + 1) * y * met[i] / met[i - 1])) if met[i - 1] else 0.5 for i in (1, 2, 3))


def train(counts: DataFrame, order: int) -> tuple[DataFrame, float, float]:
    """The model from the counts (gram, n) of full n-grams: rows (gram, p, left), p the interpolated
    probability of a gram's last symbol and left what a context leaves to shorter ones (null where
    the gram isn't one); what the empty context leaves; and the share of one unseen symbol."""
    levels = [counts]
    for k in range(order - 1, 0, -1):  # continuation counts: how many symbols come before a gram
        levels.append(staged(levels[-1].groupBy(F.expr(f"right(gram, {k})").alias("gram")).agg(F.count("*").alias("n"))))
    lower = rest = None
    entries = []
    for k, level in enumerate(reversed(levels), start=1):
        d1, d2, d3 = _discounts(level)
        cut = F.when(F.col("n") == 1, d1).when(F.col("n") == 2, d2).otherwise(d3)
        named = level.withColumns({"context": F.expr(f"left(gram, {k - 1})"), "cut": cut})
        total = named.groupBy("context").agg(F.sum("n").alias("all"), F.sum("cut").alias("lost")).withColumn("left", F.col("lost") / F.col("all"))
        if lower is None:
            all_, lost = total.agg(F.sum("all"), F.sum("lost")).first()  # one context, the empty one
            rest, flat = lost / all_, 1 / (level.count() + 1)
            part = named.select("gram", ((F.col("n") - F.col("cut")) / F.lit(all_) + F.lit(rest * flat)).alias("p"))
        else:
            entries.append(total.select(F.col("context").alias("gram"), F.lit(None).cast("double").alias("p"), "left"))
            shares = named.join(total, "context").select("gram", ((F.col("n") - F.col("cut")) / F.col("all")).alias("share"), "left", F.expr(f"right(gram, {k - 1})").alias("suffix"))
            below = lower.select(F.col("gram").alias("suffix"), F.col("p").alias("q"))
            part = shares.join(below, "suffix").select("gram", (F.col("share") + F.col("left") * F.col("q")).alias("p"))
        lower = staged(part)
        entries.append(lower.select("gram", "p", F.lit(None).cast("double").alias("left")))
    every = entries[0]
    for e in entries[1:]:
        every = every.union(e)
    return staged(every.groupBy("gram").agg(F.max("p").alias("p"), F.max("left").alias("left"))), rest, flat


# -- questions and answers -----------------------------------------------------------------------


def _split(keys: np.ndarray, log: int) -> tuple[np.ndarray, np.ndarray]:
    """Order of the keys, and where each of 2**log shards begins in it."""
    order = np.argsort(keys)
    edges = np.arange(1, 1 << log, dtype=np.uint64) << np.uint64(64 - log)
    return order, np.concatenate([[0], np.searchsorted(keys[order], edges), [len(keys)]])


def _asked(body: bytes, order: int) -> tuple[list[Windows], np.ndarray, np.ndarray]:
    levels, rank = windows(code_points(body), order)
    return levels, rank, np.concatenate([w.keys(k) for k, w in enumerate(levels, start=1)])


def entries_by_shard(model: DataFrame, log: int) -> DataFrame:
    """(shard, body): entries of the model under their hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            size = pc.utf8_length(batch.column("gram")).to_numpy(zero_copy_only=False)
            keys = np.zeros(len(size), np.uint64)
            for k in np.unique(size).tolist():
                at = np.flatnonzero(size == k)
                chars = np.frombuffer("".join(batch.column("gram").take(pa.array(at)).to_pylist()).encode("utf-32-le"), np.uint32).reshape(len(at), k)
                raw = np.zeros(len(at), np.uint64)
                for i in range(k):
                    raw = raw * _BASE + symbol_hash(chars[:, i]) if i else symbol_hash(chars[:, 0])
                keys[at] = Windows(at, at, at, raw).keys(k)
            p, left = (batch.column(c).to_numpy(zero_copy_only=False).astype(np.float32) for c in ("p", "left"))  # null: not a number
            order, edge = _split(keys, log)
            shards = np.flatnonzero(np.diff(edge))
            packs = [packed(keys[o], p[o], left[o]) for o in (order[edge[s] : edge[s + 1]] for s in shards)]
            yield pa.RecordBatch.from_arrays([pa.array(shards.astype(np.int32)), pa.array(packs, pa.binary())], ["shard", "body"])

    return model.mapInArrow(run, "shard int, body binary")


def answers(blobs: DataFrame, model: DataFrame, order: int, log: int, salts: int) -> DataFrame:
    """(blob, shard, body): p and left for each key a blob has in a shard, in the keys' order."""

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            for blob, body in zip(batch.column("blob").to_pylist(), batch.column("body"), strict=True):
                keys = _asked(body.as_py(), order)[2]
                o, edge = _split(keys, log)
                keys = keys[o]
                some = np.flatnonzero(np.diff(edge))
                packs = [packed(np.diff(keys[edge[s] : edge[s + 1]], prepend=np.uint64(0))) for s in some]
                n = len(some)
                yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array([blob % salts] * n, pa.int32()), pa.array([blob] * n), pa.array(packs, pa.binary())], ["shard", "salt", "blob", "body"])

    def answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        here, parts, known = None, [], None
        for batch in released(batches):  # by shard and salt, the model's entries first
            blobs_, shards, out = [], [], []
            for shard, salt, blob, body in zip(*(batch.column(c).to_pylist() for c in ("shard", "salt", "blob")), batch.column("body"), strict=True):
                if (shard, salt) != here:
                    here, parts, known = (shard, salt), [], None
                if blob < 0:
                    parts.append(unpacked(body.as_py(), "u8", "f4", "f4"))
                    continue
                if known is None:
                    known = [np.concatenate([x, *(q[i] for q in parts)]) for i, x in enumerate((np.zeros(0, "u8"), np.zeros(0, "f4"), np.zeros(0, "f4")))]
                    o = np.argsort(known[0])
                    known = [x[o] for x in known]
                asked = np.cumsum(unpacked(body.as_py(), "u8")[0], dtype=np.uint64)
                p, left = (np.full(len(asked), np.nan, "f4") for _ in range(2))
                if len(known[0]):
                    at = np.minimum(np.searchsorted(known[0], asked), len(known[0]) - 1)
                    hit = known[0][at] == asked
                    p[hit], left[hit] = known[1][at[hit]], known[2][at[hit]]
                blobs_.append(blob)
                shards.append(shard)
                out.append(packed(p, left))
            yield pa.RecordBatch.from_arrays([pa.array(blobs_, pa.int64()), pa.array(shards, pa.int32()), pa.array(out, pa.binary())], ["blob", "shard", "body"])

    asked = blobs.select("blob", "body").mapInArrow(ask, "shard int, salt int, blob long, body binary")
    known = entries_by_shard(model, log).select("shard", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"), F.lit(-1).cast("long").alias("blob"), "body")
    groups = salts << log
    tasks = max(1, min(groups, max(groups // 4, int(model.sparkSession.conf.get("spark.sql.shuffle.partitions")))))
    dealt = asked.union(known).repartition(tasks, "shard", "salt").sortWithinPartitions("shard", "salt", "blob")
    return dealt.mapInArrow(answer, "blob long, shard int, body binary")


def scores(blobs: Blobs, model: DataFrame, rest: float, flat: float, order: int) -> DataFrame:
    """(key, lang, n, total, least): symbols, sum of log probabilities of every document, and the
    least sum of ``order`` neighbouring ones."""
    bytes_ = blobs.table().agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0]
    log = (max(LEAST_SHARDS, -(-model.count() // SHARD)) - 1).bit_length()
    salts = max(1, -(-bytes_ // SALT) >> log)
    back = blobs.travelling(answers(blobs.table(), model, order, log, salts)).groupBy("blob").agg(F.collect_list(F.struct("shard", "body")).alias("got"))
    pads = order - 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in released(batches):
            for body, chars, keys, langs, got in zip(*(batch.column(c) for c in ("body", "chars", "keys", "langs", "got")), strict=True):
                levels, rank, asked = _asked(body.as_py(), order)
                o, edge = _split(asked, log)
                p, left = np.full(len(asked), np.nan), np.full(len(asked), np.nan)
                for x in got:
                    s = x["shard"].as_py()
                    p[o[edge[s] : edge[s + 1]]], left[o[edge[s] : edge[s + 1]]] = unpacked(x["body"].as_py(), "f4", "f4")
                left[np.isnan(left)] = 1  # an unseen context leaves all
                start, below, weight = 0, np.full(1, flat), np.full(1, rest)
                for w in levels:
                    end = start + len(w.last)
                    p_, spare = p[start:end], weight[w.context] * below[w.suffix]
                    below, weight = np.where(np.isnan(p_), spare, p_), left[start:end]
                    start = end
                logs = np.log(below).astype(np.float32)
                del levels, w, asked, o, edge, p, p_, left, below, weight, spare
                size = np.asarray(chars.as_py(), np.int64)
                begin = np.cumsum(size + pads) - (size + pads)
                value = logs[rank]
                del rank
                for i in range(pads):
                    value[begin + i] = 0
                if not pads:
                    value = np.append(value, np.float32(0))
                sums = np.where(size > 0, np.add.reduceat(value, begin, dtype=np.float64), 0.0)
                near = value.copy()  # of a document's symbols and its pads, which are 0, no others
                for i in range(1, order):
                    near[i:] += value[:-i]
                for i in range(pads):
                    near[begin + i] = 0
                least = np.where(size > 0, np.minimum.reduceat(near, begin).astype(np.float64), 0.0)
                yield pa.RecordBatch.from_arrays([keys.values, langs.values, pa.array(size), pa.array(sums), pa.array(least)], ["key", "lang", "n", "total", "least"])

    return blobs.meet(back).select("body", "chars", "keys", "langs", "got").mapInArrow(run, f"key {blobs.kind}, lang string, n long, total double, least double")


def judge(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang", how: Model = Model()) -> DataFrame:
    """Per row: key, lang, perplexity, threshold, peak, peak_threshold, kept."""
    good = staged(labels.where("quality = 1 and coalesce(toxic, 0) = 0 and doc_id is not null").select(F.col("doc_id").alias("good"), (F.pmod(F.xxhash64(F.lit(how.hold), "doc_id"), F.lit(how.hold)) == 0).alias("held")).distinct())
    blobs = Blobs(docs, key, text, lang, how.order)
    try:
        places = blobs.table().select("blob", F.posexplode("keys").alias("spot", "good"))
        spots = places.join(small(good.where("not held").select("good")), "good")
        marked = blobs.meet(blobs.travelling(spots.select("blob", "spot")).groupBy("blob").agg(F.collect_list("spot").alias("spots")))
        counts = staged(count_grams(marked, how.order))
        if counts.isEmpty():
            rows = blobs.table().select(F.explode(F.arrays_zip("keys", "langs")).alias("x"))
            return staged(rows.select(F.col("x.keys").alias(key), F.col("x.langs").alias("lang"), *[F.lit(None).cast("double").alias(c) for c in ("perplexity", "threshold", "peak", "peak_threshold")], F.lit(True).alias("kept")))
        model, rest, flat = train(counts, how.order)
        some = F.col("n") > 0
        peak = F.exp(-F.col("least") / F.least(F.col("n"), F.lit(how.order)))
        scored = staged(scores(blobs, model, rest, flat, how.order).select("key", "lang", F.when(some, F.exp(-F.col("total") / F.col("n"))).alias("perplexity"), F.when(some, peak).alias("peak")))
    finally:
        blobs.drop()
    trusted = staged(scored.join(small(good), scored["key"] == good["good"]).select("lang", "perplexity", "peak", "held").where("perplexity is not null"))
    held, measures = F.col("held"), ("perplexity", "peak")

    def quantile(name: str, where=F.lit(True)):
        return F.percentile_approx(F.when(where, F.col(name)), how.quantile, 10_000)

    limits = staged(trusted.where(held).groupBy("lang").agg(F.count("*").alias("many"), *[quantile(m).alias(f"own_{m}") for m in measures]).where(F.col("many") >= how.least).drop("many"))
    enough = F.count_if(held) >= how.least  # an extreme of a handful of documents says nothing
    pooled = trusted.agg(F.coalesce(quantile("perplexity", held), quantile("perplexity")).alias("perplexity"), F.when(enough, quantile("peak", held)).alias("peak")).first()
    judged = scored.join(small(limits.withColumnRenamed("lang", "of")), F.col("lang").eqNullSafe(F.col("of")), "left")
    judged = judged.withColumns({c: F.lit(how.margin) * F.coalesce(f"own_{m}", F.lit(pooled[m]).cast("double")) for c, m in zip(("threshold", "peak_threshold"), measures, strict=True)})
    kept = (F.col("perplexity") <= F.col("threshold")) & (F.col("peak_threshold").isNull() | (F.col("peak") <= F.col("peak_threshold")))
    return judged.select(F.col("key").alias(key), "lang", "perplexity", "threshold", "peak", "peak_threshold", F.coalesce(kept, F.lit(False)).alias("kept"))
