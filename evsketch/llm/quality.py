"""Quality rules as a short-circuit cascade.

Every rule is a predicate over lazily computed features of one text. ``calibrate`` runs all rules
on a bounded sample, measures each rule's seconds and rejections, and orders the rules by rejection
per second; ``judge`` then stops at the first rule that rejects. The order changes cost, never the
verdict, as a text is kept only if no rule rejects it.

Defined cases: a null text is empty; an empty text has no words and fails the base rule; rows are
judged one by one, so repeated rows get equal verdicts; an empty table gives an empty result; extra
columns are not read.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evsketch.llm.common import arrow_map, empty_safe, raw, released, slices

WINDOW = 5
#: Bounded sample on which costs and selectivities are estimated.
SAMPLE_ROWS = 256

_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_WORD_CHAR = ~_SPACE
_WORD_CHAR[0x80:0xC0] = False  # continuation bytes belong to the code point before them
_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True


def _repeated(windows: np.ndarray) -> np.ndarray:
    """True where a value occurs twice or more."""
    _, inverse, counts = np.unique(windows, return_inverse=True, return_counts=True)
    return counts[inverse] > 1


def repeat_words(words: Sequence[bytes], width: int = WINDOW) -> int:
    """Words that lie in a ``width``-word window found twice or more in the text.

    A hash that finds no equal windows settles most texts; otherwise windows are ranked exactly.
    """
    n = len(words)
    if n <= width:
        return 0
    h = np.fromiter(map(hash, words), np.int64, n).view(np.uint64)
    mixed = h[: n - width + 1].copy()
    for i in range(1, width):
        mixed = mixed * np.uint64(0x9E3779B97F4A7C15) + h[i : n - width + 1 + i]
    order = np.sort(mixed)
    if not (order[1:] == order[:-1]).any():
        return 0
    seen: dict[bytes, int] = {}
    ids = np.fromiter((seen.setdefault(w, len(seen)) for w in words), np.int64, n)
    rank = ids[: n - width + 1]
    for i in range(1, width):  # dense ranks keep every product below 2**63
        _, rank = np.unique(rank * len(seen) + ids[i : n - width + 1 + i], return_inverse=True)
    hit = np.flatnonzero(_repeated(rank))
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, hit, 1)
    np.add.at(edge, hit + width, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


class Text:
    """Lazy features of one text; ``word_chars`` and ``n_symbols`` come from the slice's counts."""

    def __init__(self, body: bytes, word_chars: int | None = None, n_symbols: int | None = None):
        self.body = body
        self._known: dict[str, object] = {}
        if word_chars is not None:
            self._known |= {"word_chars": word_chars, "n_symbols": n_symbols}

    def __getattr__(self, name: str):
        known = self.__dict__["_known"]
        if name not in known:
            known[name] = getattr(type(self), f"_{name}")(self)
        return known[name]

    def _words(self):
        return self.body.split()  # bytes.split() splits at 0x09-0x0D and 0x20 only

    def _n_words(self):
        return len(self.words)

    def _word_chars(self):
        return int(_WORD_CHAR[np.frombuffer(self.body, np.uint8)].sum())

    def _n_symbols(self):
        return int(_SYMBOL[np.frombuffer(self.body, np.uint8)].sum())

    def _lines(self):
        return [x for x in self.body.split(b"\n") if x and not x.isspace()]

    def _n_dup_lines(self):
        return len(self.lines) - len(set(self.lines))

    def _n_repeat_words(self):
        return repeat_words(self.words)

    def _letters(self):
        a = np.frombuffer(self.body, np.uint8)
        lower = a | 0x20
        return int(((lower >= 97) & (lower <= 122)).sum() + (a >= 0xC0).sum())

    def _capitals(self):
        a = np.frombuffer(self.body, np.uint8)
        return int(((a >= 65) & (a <= 90)).sum())


@dataclass(frozen=True)
class Rule:
    name: str
    rejects: Callable[[Text], bool]


def _too_few(t: Text) -> bool:
    return t.n_words < 10


def _too_repetitive(t: Text) -> bool:
    return 100 * t.n_repeat_words > 20 * t.n_words


def _symbols(t: Text) -> bool:
    return 10 * t.n_symbols > t.n_words


def _dup_lines(t: Text) -> bool:
    return len(t.lines) > 1 and 100 * t.n_dup_lines > 60 * len(t.lines)


def _word_length(t: Text) -> bool:
    return not 2 * t.n_words <= t.word_chars <= 20 * t.n_words


def _few_letters(t: Text) -> bool:
    return 4 * t.letters < t.word_chars


def _shouting(t: Text) -> bool:
    return 2 * t.capitals > t.letters


#: The two rules of the base, and the rules that the method adds; thresholds are parameters of the rules.
BASE = (Rule("too_few_words", _too_few), Rule("repeated_windows", _too_repetitive))
ADDED = (Rule("symbols_per_word", _symbols), Rule("duplicate_lines", _dup_lines), Rule("word_length", _word_length), Rule("few_letters", _few_letters), Rule("capitals", _shouting))


def order_rules(rules: Sequence[Rule], texts: Sequence[bytes]) -> tuple[list[Rule], list[tuple[str, float, float]]]:
    """Rules by falling rejection per second on ``texts``; and (name, seconds a text, share rejected)."""
    stats = []
    for rule in rules:
        began, rejected = time.perf_counter(), 0
        for body in texts:
            rejected += rule.rejects(Text(body))
        stats.append((rule.name, (time.perf_counter() - began) / max(1, len(texts)), rejected / max(1, len(texts))))
    rank = {name: (-(share / max(cost, 1e-9)), cost) for name, cost, share in stats}
    return sorted(rules, key=lambda r: rank[r.name]), stats


def judge(rules: Sequence[Rule], text: Text) -> bool:
    """True if no rule rejects; later rules are not evaluated after a rejection."""
    return not any(rule.rejects(text) for rule in rules)


def calibrate(docs: DataFrame, text: str = "text", rules: Sequence[Rule] = BASE + ADDED, sample_rows: int = SAMPLE_ROWS) -> list[Rule]:
    """The cascade's order, from at most ``sample_rows`` texts chosen by a hash of the text."""
    some = docs.where(F.pmod(F.xxhash64(text), F.lit(16)) == 0).select(text).limit(sample_rows).collect()
    return order_rules(rules, [(r[0] or "").encode() for r in some])[0]


def _texts(batch: pa.RecordBatch, text: str):
    body, off = raw(empty_safe(batch.column(text)))
    for a, b in slices(off):
        part = body[off[a] : off[b]]
        cut = off[a : b + 1] - off[a]
        chars = np.concatenate([[0], np.cumsum(_WORD_CHAR[part])])
        marks = np.concatenate([[0], np.cumsum(_SYMBOL[part])])
        whole = part.tobytes()
        for i in range(b - a):
            lo, hi = cut[i], cut[i + 1]
            yield Text(whole[lo:hi], int(chars[hi] - chars[lo]), int(marks[hi] - marks[lo]))


def score(docs: DataFrame, key: str = "doc_id", text: str = "text", rules: Sequence[Rule] | None = None) -> DataFrame:
    """One row per document: its counts, ``base_failed`` and the cascade's ``kept``."""
    ordered = list(rules if rules is not None else calibrate(docs, text))
    kind = docs.schema[key].dataType.simpleString()

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        rows = []
        for t in _texts(batch, text):
            base = any(r.rejects(t) for r in BASE)
            rows.append((t.n_words, t.word_chars, t.n_symbols, t.n_dup_lines, t.n_repeat_words, base, not base and judge(ordered, t)))
        cols = list(zip(*rows, strict=True))
        kinds = [pa.int64()] * 5 + [pa.bool_()] * 2
        names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]
        return pa.RecordBatch.from_arrays([batch.column(key), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], [key, *names])

    schema = f"`{key}` {kind}, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean"
    return arrow_map(docs.select(key, text), run, schema)


def keep_good(docs: DataFrame, text: str = "text", rules: Sequence[Rule] | None = None) -> DataFrame:
    """The rows of ``docs``, all columns, that the cascade keeps."""
    ordered = list(rules if rules is not None else calibrate(docs, text))

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        return batch.filter(pa.array([judge(ordered, t) for t in _texts(batch, text)], pa.bool_()))

    return docs.mapInArrow(lambda batches: (run(b) for b in released(batches) if b.num_rows), docs.schema)
