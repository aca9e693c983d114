"""The sharded model against a plain one, and what it is for."""

import math
import random
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from evsketch.llm import lm


class Plain:
    """Interpolated modified Kneser-Ney by dictionaries of strings."""

    def __init__(self, texts, order):
        self.order, pads = order, lm.PAD * (order - 1)
        top = Counter()
        for t in texts:
            t = pads + t.lower()
            top.update(t[i : i + order] for i in range(len(t) - order + 1))
        self.counts = {order: top}
        for k in range(order - 1, 0, -1):
            self.counts[k] = Counter(g[1:] for g in self.counts[k + 1])
        self.d, self.total, self.lost = {}, {}, {}
        for k, c in self.counts.items():
            n = Counter(c.values())
            y = n[1] / (n[1] + 2 * n[2]) if n[1] else None
            d = [min(i, max(0, i - (i + 1) * y * n[i + 1] / n[i])) if y is not None and n[i] else 0.5 for i in (1, 2, 3)]
            self.d[k], self.total[k], self.lost[k] = d, defaultdict(int), defaultdict(float)
            for g, x in c.items():
                self.total[k][g[:-1]] += x
                self.lost[k][g[:-1]] += d[min(x, 3) - 1]
        self.flat = 1 / (len(self.counts[1]) + 1)

    def p(self, gram):
        k = len(gram)
        if not k:
            return self.flat
        ctx, lower = gram[:-1], self.p(gram[1:])
        if not self.total[k].get(ctx):
            return lower
        x = self.counts[k].get(gram, 0)
        share = (x - self.d[k][min(x, 3) - 1]) / self.total[k][ctx] if x else 0
        return share + self.lost[k][ctx] / self.total[k][ctx] * lower

    def logs(self, text):
        t = lm.PAD * (self.order - 1) + text.lower()
        return [math.log(self.p(t[i : i + self.order])) for i in range(len(t) - self.order + 1)]

    def perplexity(self, text):
        logs = self.logs(text)
        return math.exp(-sum(logs) / len(logs)) if logs else None

    def peak(self, text):
        logs = self.logs(text)
        size = min(self.order, len(logs))
        return math.exp(-min(sum(logs[max(0, i - self.order + 1) : i + 1]) for i in range(len(logs))) / size) if logs else None


WORDS = ["the", "cat", "sat", "on", "a", "mat", "and", "then", "ran", "home", "\u00fcber", "\u7532\u9aa8"]


def corpus(n=90):
    rng = random.Random(5)
    prose = lambda: " ".join(rng.choice(WORDS) for _ in range(rng.randint(1, 60))).capitalize() + "."
    rows = [(i, prose(), "en" if i % 3 else "de") for i in range(n)]
    rows += [(200 + i, "zq#9 xv$!! \U0001f600" * 20, "en") for i in range(5)]
    return rows + [(300, None, "en"), (301, "", None), (302, prose(), "xx"), (303, "\0\0 x \0", "en"), (304, rows[1][1], "en"), (304, rows[1][1], "en"), (None, "the mat", "en")]


def tables(spark, rows, good):
    docs = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, lang string, blob string").repartition(3)
    labels = spark.createDataFrame([(i, 1, 0) for i in good] + [(200, 0, 0), (1, 1, None), (2, 1, 1), (None, 1, 0)], "doc_id long, quality int, toxic int")
    return docs, labels


@pytest.mark.parametrize(("order", "shape"), [(5, {}), (3, {"BLOB": 200, "DIRECT": 10, "CHUNK": 7, "SHARD": 50, "SALT": 300}), (1, {"LEAST_SHARDS": 1})])
def test_scores_equal_a_plain_model(spark, monkeypatch, order, shape):
    for k, v in shape.items():
        monkeypatch.setattr(lm, k, v)
    rows, good = corpus(), [i for i in range(60) if i != 2]
    docs, labels = tables(spark, rows, good)
    how = lm.Model(order=order, hold=4, least=2)
    held = {r.doc_id for r in labels.where(F.pmod(F.xxhash64(F.lit(4), "doc_id"), F.lit(4)) == 0).collect()}
    model = Plain([t for i, t, _ in rows if i in set(good) - held], order)
    got = lm.judge(docs, labels, how=how).collect()
    assert len(got) == len(rows)
    want = defaultdict(list)
    for i, t, _ in rows:
        want[i].append((model.perplexity(t or ""), model.peak(t or "")))
    for r in got:
        for seen, w in zip((r.perplexity, r.peak), want[r.doc_id][0], strict=True):
            assert (seen is None) == (w is None) and (w is None or math.isclose(seen, w, rel_tol=1e-5))
    for lang in ("en", "de"):
        limit = [sorted(want[i][0][m] for i, _, x in rows if x == lang and i in held and i in good)[-1] for m in (0, 1)]
        for seen, w in (({r.threshold for r in got if r.lang == lang}, limit[0]), ({r.peak_threshold for r in got if r.lang == lang}, limit[1])):
            assert len(seen) == 1 and math.isclose(seen.pop(), how.margin * w, rel_tol=1e-5)
    assert all(r.kept == (r.perplexity is not None and r.perplexity <= r.threshold and r.peak <= r.peak_threshold) for r in got)


def test_probabilities_sum_to_one(spark):
    texts = [t for _, t, _ in corpus(40) if t]
    counts = Counter()
    for t in texts:
        t = lm.PAD * 2 + t.lower()
        counts.update(t[i : i + 3] for i in range(len(t) - 2))
    model, rest, flat = lm.train(spark.createDataFrame(list(counts.items()), "gram string, n long"), 3)
    known = {r.gram: r for r in model.collect()}
    alphabet = [g for g, r in known.items() if len(g) == 1 and r.p is not None]
    assert abs(sum(known[c].p for c in alphabet) + rest * flat - 1) < 1e-9

    def p(g):
        if not g:
            return flat
        r, ctx = known.get(g), known.get(g[:-1])
        if r is not None and r.p is not None:
            return r.p
        left = rest if len(g) == 1 else ctx.left if ctx is not None and ctx.left is not None else 1
        return left * p(g[1:])

    for ctx in ("", "t", "th", "zz", "\0\0", "\0"):
        assert abs(sum(p(ctx + c) for c in [*alphabet, "\u2603"]) - 1) < 1e-9


def test_windows_are_exact(monkeypatch):
    rng = np.random.default_rng(1)
    text = np.concatenate([np.zeros(3, np.uint32), rng.integers(97, 101, 500).astype(np.uint32)])
    for direct in (1 << 24, 3):
        monkeypatch.setattr(lm, "DIRECT", direct)
        monkeypatch.setattr(lm, "CHUNK", 64)
        levels, rank = lm.windows(text, 4) if direct > 3 else lm.windows(text % 3, 4)
        body = text if direct > 3 else text % 3
        names = lm.spelled(levels, np.arange(len(levels[-1].last)))
        assert len(set(names)) == len(names)
        whole = "".join(map(chr, body))
        assert all(names[rank[i]] == whole[i - 3 : i + 1] for i in range(3, len(whole)))
        for k in (1, 2, 3):
            own, lower = levels[k], levels[k - 1]
            for w in range(len(own.last)):
                assert lower.last[own.suffix[w]] == own.last[w]


def test_foreign_text_goes_and_clean_text_stays(spark):
    rows = [(i + 1000 if i is not None and i < 200 else i, t, x) for i, t, x in corpus(200)]
    docs, labels = tables(spark, rows, range(1000, 1120))
    got = {r.doc_id: r for r in lm.judge(docs, labels).collect()}
    assert all(not got[200 + i].kept for i in range(5)) and sum(got[1000 + i].kept for i in range(200)) >= 195
    assert got[300].perplexity is None and not got[300].kept and got[302].kept and got[302].threshold > 0
    none = lm.judge(docs, labels.limit(0)).collect()
    assert len(none) == len(rows) and all(r.kept and r.perplexity is None for r in none)
    assert not spark.catalog.listTables() or all(not t.name.startswith("blobs_") for t in spark.catalog.listTables())


def test_a_few_foreign_words_in_a_long_text_are_its_peak(spark):
    rng = random.Random(7)
    prose = lambda: " ".join(rng.choice(WORDS) for _ in range(400))
    rows = [(i, prose(), "en") for i in range(160)] + [(500 + i, f"{prose()} {w} {prose()}", "en") for i, w in enumerate(["wqzj", "jkvx", "pfgw"])]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, 1, 0) for i in range(160)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in lm.judge(docs, labels, how=lm.Model(least=5)).collect()}
    planted = [got[500 + i] for i in range(3)]
    assert all(r.perplexity <= r.threshold and r.peak > r.peak_threshold and not r.kept for r in planted)
    assert sum(got[i].kept for i in range(160)) >= 155
