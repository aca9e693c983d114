"""Personal data: pattern spans, then information-theoretic sanitisation.

Identifiers (email, ip, card, phone) are found by linear scans. They are the protected entities, and
so are the credentials that a text assigns to a name such as ``token`` (kind ``secret``). Most
identifiers stand in one document only, so evidence is pooled: an identifier counts as itself and as
the groups it belongs to (its ``faces``: an address's domain and the names in its local part, a
network, an issuer, an area code). The terms near each occurrence (``REACH`` code points to either
side, whole words only) are its context.

Over the whole corpus, documents are counted per face, per term and per pair of both. With N
documents, a face in e of them, a term in t and the pair in b, what the term tells of the face is
log(P(term | face) / P(term)), where P(term) = t/N and P(term | face) = (b + prior * t/N) / (e +
prior): one sighting speaks, but is half believed. A term that tells at least ``share`` of
the face's own information log(N/e), and makes the face at least ``lift`` times as likely, discloses
it and is a span of kind ``term`` wherever it stands in that face's context. Copies of a document
raise e, t and b alike, so they change no verdict. ``sanitise`` generalises identifiers to their
kind and removes disclosing terms.

Only terms that stand near an identifier are counted over the corpus. A bitmap of fixed size tells
the scan which ones those may be; it spares work and a full one gives the same result.

Defined cases: a null text is empty and has no span; a document without identifiers has no term
span; copies count as the documents they are; rows are told apart by position, so
null or repeated keys keep their rows; an empty table gives an empty result; other columns are
passed through unread.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evsketch.llm.common import bitmap, empty_safe, fresh, released, small, staged

KINDS = ("email", "ip", "card", "phone")
#: Code points of context to either side of an identifier.
REACH = 80
#: Terms of fewer letters are not counted.
LEAST_LETTERS = 4
#: Entries of a worker's term counter before it is written out.
FLUSH = 200_000
#: log2 of the bits that note the terms near identifiers; fixed.
NEAR_BITS = 25

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+")
_REGION = re.compile(r"[+0-9][+0-9 ().\-]*")
_IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
_CARD = re.compile(r"[0-9](?:[ \-]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9\-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")
_TERM = re.compile(rf"[^\W\d_]{{{LEAST_LETTERS},}}")
_NAMES = ("token", "secret", "passw", "key")
_SECRET = re.compile(r"""(?i)(?:token|secret|passw(?:or)?d|(?:api|access|private)[_-]?key)\b["']?[ \t]{0,4}[:=][ \t]{0,4}["']?([^\s"',;]{8,})""")

Span = tuple[str, int, int]


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) << (i & 1)
        total += d - 9 if d > 9 else d
    return total % 10 == 0


def _emails(text: str) -> Iterator[Span]:
    """Each @ is tried once: all starts in the run before it share its fate."""
    floor = 0
    at = text.find("@")
    while at >= 0:
        start = at
        while start > floor and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            yield "email", start, m.end()
            floor = m.end()
        else:
            floor = at + 1  # a run never reaches back over an @
        at = text.find("@", floor)


def base_spans(text: str) -> list[Span]:
    """The pattern spans, by kind and then start."""
    ip, card, phone = [], [], []
    for region in _REGION.finditer(text):
        a, b = region.span()
        if b - a < 7:
            continue
        for m in _IP.finditer(text, a, b):
            if all(len(x.lstrip("0")) <= 3 and int(x[-9:]) <= 255 for x in m[0].split(".")):
                ip.append(("ip", *m.span()))
        for m in _CARD.finditer(text, a, b):
            digits = m[0].replace(" ", "").replace("-", "")
            if 16 <= len(digits) <= 19 and luhn(digits):
                card.append(("card", *m.span()))
        for m in _PHONE.finditer(text, a, b):
            if 8 <= len(_DIGIT.findall(m[0])) <= 15:
                phone.append(("phone", *m.span()))
    return [*_emails(text), *ip, *card, *phone]


def secret_spans(text: str) -> list[Span]:
    """Values of at least 8 characters, a digit among them, that are assigned to a credential's name."""
    lower = text.lower()
    if not any(n in lower for n in _NAMES):
        return []
    return [("secret", *m.span(1)) for m in _SECRET.finditer(text) if _DIGIT.search(m[1])]


def entity(text: str, span: Span) -> str:
    """The protected value: digits of a card or phone, the lower-cased text of others."""
    kind, a, b = span
    value = text[a:b]
    return f"{kind}:{''.join(_DIGIT.findall(value)) if kind in ('card', 'phone') else value.lower()}"


def faces(text: str, span: Span) -> list[str]:
    """What an identifier counts as: itself, then the groups it belongs to."""
    value = entity(text, span)
    kind, _, rest = value.partition(":")
    if kind == "email":
        local, _, domain = rest.partition("@")
        return [value, f"domain:{domain}", *(f"name:{n}" for n in dict.fromkeys(_TERM.findall(local)))]
    if kind == "ip":
        return [value, f"net:{rest.rsplit('.', 2)[0]}"]
    return [value, f"{kind}s:{rest[:6]}"] if kind in ("card", "phone") else [value]


def h64(value: str) -> int:
    h = xxhash.xxh64_intdigest(value.encode("utf-8", "surrogatepass"))
    return h - (1 << 64) if h >> 63 else h


def contexts(text: str, spans: list[Span]) -> list[tuple[int, int, int, int]]:
    """(face, term, start, end): whole terms within reach of an identifier, outside all spans."""
    taken: list[list[int]] = []
    for a, b in sorted((a, b) for _, a, b in spans):
        if taken and a <= taken[-1][1]:
            taken[-1][1] = max(taken[-1][1], b)
        else:
            taken.append([a, b])
    starts = [a for a, _ in taken]
    found = {}
    for span in spans:
        _, a, b = span
        lo, hi = max(0, a - REACH), min(len(text), b + REACH)
        who = [h64(f) for f in faces(text, span)]
        for m in _TERM.finditer(text, lo, hi):
            s, e = m.span()
            if (s == lo and s and text[s - 1].isalpha()) or (e == hi and e < len(text) and text[e].isalpha()):
                continue
            i = bisect_left(starts, e)
            if i and taken[i - 1][1] > s:
                continue
            term = h64(m[0].lower())
            for f in who:
                found.setdefault((f, s), (f, term, s, e))
    return list(found.values())


_SCAN = "row long, n_email long, n_ip long, n_card long, n_phone long, base string, more string, n_base long, n_more long, faces array<long>, near array<struct<e:long,t:long,s:int,f:int>>"
_NEAR = pa.list_(pa.struct([("e", pa.int64()), ("t", pa.int64()), ("s", pa.int32()), ("f", pa.int32())]))
_FIELDS = pa.schema([("row", pa.int64()), *((f"n_{k}", pa.int64()) for k in KINDS), ("base", pa.string()), ("more", pa.string()), ("n_base", pa.int64()), ("n_more", pa.int64()), ("faces", pa.list_(pa.int64())), ("near", _NEAR)])


def joined(spans) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row per document: its spans, their faces and the terms near them."""
    for batch in released(batches):
        rows = []
        for row, text in zip(batch.column("row").to_pylist(), empty_safe(batch.column("text")).to_pylist(), strict=True):
            base, more = base_spans(text), secret_spans(text)
            spans = base + more
            n = [sum(s[0] == k for s in base) for k in KINDS]
            near = [dict(zip("etsf", x, strict=True)) for x in contexts(text, spans)] if spans else []
            rows.append((row, *n, joined(base), joined(more), len(base), len(more), list({h64(f) for s in spans for f in faces(text, s)}), near))
        if rows:
            cols = [pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _FIELDS, strict=True)]
            yield pa.RecordBatch.from_arrays([*cols, batch.column("key")], [*_FIELDS.names, "key"])


def term_counts(texts: DataFrame, noted: bytes) -> DataFrame:
    """(t, of_t): documents (rows of column ``text``) that hold each term of the bitmap."""
    holder = texts.sparkSession.sparkContext.broadcast(noted)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits, mask = holder.value, (1 << NEAR_BITS) - 1
        names: dict[str, int] = {}  # the term's hash, or 0 if it isn't noted
        counts: dict[int, int] = {}

        def flushed() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays([pa.array(counts.keys(), pa.int64()), pa.array(counts.values(), pa.int64())], ["t", "of_t"])
            counts.clear()
            return out

        for batch in released(batches):
            for text in empty_safe(batch.column("text")).to_pylist():
                for term in set(_TERM.findall(text.lower())):
                    h = names.get(term)
                    if h is None:
                        h = h64(term)
                        at = h & mask
                        h = names[term] = h if bits[at >> 3] >> (at & 7) & 1 else 0
                    if h:
                        counts[h] = counts.get(h, 0) + 1
                if len(names) > FLUSH:
                    names.clear()
                if len(counts) > FLUSH:
                    yield flushed()
        if counts:
            yield flushed()

    return texts.select("text").mapInArrow(run, "t long, of_t long").groupBy("t").agg(F.sum("of_t").alias("of_t"))


def disclosing(seen: DataFrame, texts: DataFrame, prior: float, share: float, lift: float) -> DataFrame:
    """Pairs (e, t) whose term discloses the face, from the staged scan and the texts."""
    of_document = F.array_distinct(F.transform("near", lambda x: F.struct(x["e"].alias("e"), x["t"].alias("t"))))
    pairs = staged(seen.select(F.explode(of_document).alias("x")).groupBy("x.e", "x.t").agg(F.count("*").alias("both")))
    noted = bitmap(pairs.select(F.col("t").alias("at")), NEAR_BITS)
    if not any(noted):
        return pairs.select("e", "t")
    docs_of_face = seen.select(F.explode("faces").alias("e")).groupBy("e").agg(F.count("*").alias("of_e"))
    counted = pairs.join(docs_of_face, "e").join(term_counts(texts, noted), "t")
    n = F.lit(float(max(2, seen.count())))
    told = F.log((F.col("both") + F.lit(prior) * F.col("of_t") / n) / (F.col("of_e") + F.lit(prior)) * n / F.col("of_t"))
    content = F.log(n / F.col("of_e"))
    return staged(counted.where((told >= F.lit(share) * content) & (told >= F.log(F.lit(lift)))).select("e", "t"))


def find(docs: DataFrame, key: str = "doc_id", text: str = "text", prior: float = 1.0, share: float = 0.9, lift: float = 20.0) -> DataFrame:
    """One row per row of ``docs``: key, counts, ``base``, ``more`` (spans as text) and ``terms`` (sorted
    array of struct<s,f>)."""
    texts = docs.select(F.monotonically_increasing_id().alias("row"), F.col(key).alias("key"), F.col(text).alias("text"))
    seen = staged(texts.mapInArrow(_scan, f"{_SCAN}, key {docs.schema[key].dataType.simpleString()}"))
    bad = disclosing(seen, texts, prior, share, lift)
    spots = seen.select("row", F.explode("near").alias("x")).select("row", "x.e", "x.t", "x.s", "x.f")
    terms = spots.join(bad, ["e", "t"], "left_semi").groupBy("row").agg(F.array_sort(F.collect_set(F.struct("s", "f"))).alias("terms"))
    rows = seen.select("row", F.col("key").alias(key), *(f"n_{k}" for k in KINDS), "base", "more", "n_base", "n_more")
    return rows.join(terms, "row", "left").withColumn("terms", F.coalesce("terms", F.array().cast("array<struct<s:int,f:int>>")))


def spans_column() -> Column:
    terms = F.transform("terms", lambda x: F.concat(F.lit("term:"), x["s"].cast("string"), F.lit(":"), x["f"].cast("string")))
    parts = F.filter(F.array(F.col("base"), F.col("more"), F.array_join(terms, ",")), lambda x: x != "")
    return F.array_join(parts, ",")


def digest(docs: DataFrame, **how) -> DataFrame:
    """Per document: counts, the hash of the base spans, all spans as text and their number."""
    n = (F.col("n_base") + F.col("n_more") + F.size("terms")).cast("long")
    return find(docs, **how).select("doc_id", *(f"n_{k}" for k in KINDS), F.sha2(F.col("base"), 256).alias("base_sha256"), spans_column().alias("spans"), n.alias("n_spans"))


def rewrite(text: str, spans: list[Span]) -> str:
    """Identifiers generalised to ``[KIND]``, disclosing terms removed; overlapping spans are merged."""
    out, at = [], 0
    merged: list[list] = []
    for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if merged and a < merged[-1][2]:
            merged[-1][2] = max(merged[-1][2], b)
        else:
            merged.append([kind, a, b])
    for kind, a, b in merged:
        out.append(text[at:a])
        out.append("" if kind == "term" else f"[{kind.upper()}]")
        at = b
    return "".join(out) + text[at:]


def sanitise(docs: DataFrame, key: str = "doc_id", text: str = "text", **how) -> DataFrame:
    """``docs``, all columns, its text rewritten. Pattern spans are found again where the text is;
    only disclosing terms travel, joined by ``key`` to the rows that have any."""
    name = fresh(docs, "disclosing")
    found = find(docs.select(key, text), key, text, **how).where(F.size("terms") > 0).groupBy(key).agg(F.array_distinct(F.flatten(F.collect_list("terms"))).alias(name))
    found = staged(found)
    kind = docs.schema

    def run(batches):
        for b in released(batches):
            texts = b.column(text)
            new = []
            for t, more in zip(texts.to_pylist(), b.column(name).to_pylist(), strict=True):
                if t is not None:
                    spans = base_spans(t) + secret_spans(t) + [("term", x["s"], x["f"]) for x in more or ()]
                    t = rewrite(t, spans) if spans else t
                new.append(t)
            cols = [pa.array(new, texts.type) if f.name == text else b.column(f.name) for f in kind.fields]
            yield pa.RecordBatch.from_arrays(cols, [f.name for f in kind.fields])

    return docs.join(small(found, 100_000), key, "left").select(*docs.columns, name).mapInArrow(run, kind)
