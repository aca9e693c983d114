import random

import numpy as np
import pytest

from evsketch.llm import minhash


def brute(rows, width=2):
    sets = {}
    for i, t in rows:
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w)} if 0 < len(w) < width else {tuple(w[j : j + width]) for j in range(len(w) - width + 1)}
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i), find(i) == i) for i in ids}


def corpus(seed):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(400)]
    rows = [(i, " ".join(rng.choice(words) for _ in range(rng.randint(0, 60)))) for i in range(80)]
    n = 100
    for _ in range(8):  # groups of near copies, some of which reach each other only through others
        base = [rng.choice(words) for _ in range(80)]
        for _ in range(25):
            t = list(base)
            for _ in range(rng.randint(0, 9)):
                t[rng.randrange(80)] = rng.choice(words)
            rows.append((n, " ".join(t)))
            n += 1
    rows += [(n + i, rows[100][1].upper()) for i in range(40)] + [(n + 50, None), (n + 51, ""), (n + 52, " \n"), (n + 53, "single"), (n + 54, "SINGLE"), (n + 55, "\x1cone")]
    rng.shuffle(rows)
    return rows


@pytest.mark.parametrize("blocks", [(2048, 4096), (6, 9)])
def test_components_equal_brute_force(docs, monkeypatch, blocks):
    monkeypatch.setattr(minhash, "SEARCH_BLOCK", blocks[0])
    monkeypatch.setattr(minhash, "SETTLE_BLOCK", blocks[1])
    rows = corpus(blocks[0])
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in minhash.near_duplicates(docs(rows), width=2).collect()}
    assert got == brute(rows)


def test_repeated_and_null_keys_and_empty(docs):
    t = "a b c d e f g h"
    got = sorted((r.doc_id or -1, r.component_id or -1, r.kept) for r in minhash.near_duplicates(docs([(4, t), (4, t), (None, t), (9, t), (None, "q r s t u v"), (8, "")])).collect())
    assert got == [(-1, -1, True), (-1, 4, False), (4, 4, True), (4, 4, True), (8, 8, True), (9, 4, False)]
    assert minhash.near_duplicates(docs([])).count() == 0
    kept = minhash.keep_one(docs([(4, t), (9, t), (8, "other words entirely in here")])).collect()
    assert sorted(r.doc_id for r in kept) == [4, 8] and kept[0].row == "x"


def test_super_minhash_equals_its_definition_and_has_lower_variance():
    rng = np.random.default_rng(1)

    def plain(elements, slots):
        h = [slots << 32] * slots
        for e in elements.tolist():
            p = list(range(slots))
            for j in range(slots):
                d = int(minhash.mix64(np.array([(e + (j + 1) * minhash._GOLD) & (2**64 - 1)], np.uint64))[0])
                k = j + ((d & 0xFFFFFFFF) * (slots - j) >> 32)
                p[j], p[k] = p[k], p[j]
                h[p[j]] = min(h[p[j]], (j << 32) | (d >> 32))
        return h

    sets = [rng.integers(0, 2**63, n, dtype=np.uint64) for n in (1, 5, 40)]
    sig = minhash.super_minhash(np.concatenate(sets), np.repeat([0, 1, 2], [1, 5, 40]), 3, 48)
    assert [s.tolist() for s in sig] == [plain(s, 48) for s in sets]
    errors = []
    for _ in range(300):
        base = rng.integers(0, 2**63, 30, dtype=np.uint64)
        a, b = base[:20], base[10:]
        s = minhash.super_minhash(np.concatenate([a, b]), np.repeat([0, 1], 20), 2, 48)
        errors.append((s[0] == s[1]).mean() - 1 / 3)
    assert abs(np.mean(errors)) < 0.01 and np.var(errors) < 0.9 * (1 / 3) * (2 / 3) / 48
