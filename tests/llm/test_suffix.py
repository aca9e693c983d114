import hashlib
import random

import numpy as np
import pytest

from evsketch.llm import suffix


def brute(rows):
    """n_bytes, n_removed, n_spans and hash of each (doc_id, text), by a set of windows."""
    seen, out = {}, {}
    for i in sorted({i for i, _ in rows if i is not None}):
        own = set()
        for j, t in rows:
            if j != i:
                continue
            b = (t or "").encode()
            mask = bytearray(len(b))
            for p in range(len(b) - 49):
                w = b[p : p + 50]
                if w in seen:
                    mask[p : p + 50] = b"\1" * 50
                own.add(w)
            kept = bytes(x for x, m in zip(b, mask, strict=True) if not m)
            runs = sum(m and not (k and mask[k - 1]) for k, m in enumerate(mask))
            out.setdefault(i, []).append((len(b), sum(mask), runs, hashlib.sha256(kept).hexdigest()))
        seen.update(dict.fromkeys(own, i))
    return out


def corpus(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcé ") for _ in range(rng.randint(1, 6)))
    text = lambda n: " ".join(word() for _ in range(n))
    shared = [text(30) for _ in range(4)]
    rows = []
    for i in range(60):
        parts = [text(rng.randint(0, 40))]
        for _ in range(rng.randint(0, 3)):
            s = rng.choice(shared)
            a = rng.randint(0, 30)
            parts += [s[a : a + rng.randint(40, 120)], text(rng.randint(0, 10))]
        rows.append((i, "".join(parts)))
    rows += [(100, rows[3][1]), (101, rows[3][1]), (102, None), (103, ""), (104, "a" * 400), (105, "a" * 300), (106, "ab" * 200), (107, shared[0][:50]), (108, shared[0][:49])]
    rng.shuffle(rows)
    return rows


@pytest.mark.parametrize(("hot", "small"), [(suffix.HOT, suffix.SMALL), (1, 0)])
@pytest.mark.parametrize("seed", [1, 2])
def test_query_equals_brute_force(docs, monkeypatch, seed, hot, small):
    monkeypatch.setattr(suffix, "SMALL", small)
    rows = corpus(seed)
    got = {r.doc_id: [tuple(r)[1:]] for r in suffix.digest(docs(rows), hot=hot).collect()}
    assert got == brute(rows)


@pytest.mark.parametrize("bits", [3, 5])
@pytest.mark.parametrize("seed", [1, 2])
def test_crowded_bitmaps_lose_no_document(docs, monkeypatch, seed, bits):
    monkeypatch.setattr(suffix, "CHANGED_BITS", bits)
    rows = corpus(seed)
    got = {r.doc_id: [tuple(r)[1:]] for r in suffix.digest(docs(rows)).collect()}
    assert got == brute(rows)


def test_text_that_shares_hash_bits_with_a_copy_is_read(docs):
    copy, own = "copied passage " * 8, "unrelated unique document 8789736 with more than fifty bytes of its own text"
    rows = [(1, copy), (2, copy), (3, own), (4, own + " and more")]
    got = {r.doc_id: [tuple(r)[1:]] for r in suffix.digest(docs(rows)).collect()}
    assert got == brute(rows) and got[4][0][1] == len(own)


def test_repeated_keys_nulls_and_empty(docs):
    t = "".join(chr(97 + i * i % 23) for i in range(120))
    rows = [(1, t), (1, t), (None, t), (2, t + "zz"), (3, None)]
    got = sorted((r.doc_id or -1, r.n_bytes, r.n_removed) for r in suffix.digest(docs(rows)).collect())
    assert got == [(-1, 120, 0), (1, 120, 0), (1, 120, 0), (2, 122, 120), (3, 0, 0)]
    assert suffix.digest(docs([])).count() == 0


def test_stage_keeps_columns_and_characters(docs):
    t = "é" * 80
    out = {r.doc_id: r for r in suffix.cut_repeats(docs([(1, t), (2, "x" + t + "y"), (3, "plain")])).collect()}
    assert out[1].text == t and out[2].text == "xy" and out[3].text == "plain" and out[1].row == "x"


def test_repeat_groups_equal_definition():
    rng = np.random.default_rng(5)
    texts = [bytes(rng.integers(97, 99, rng.integers(0, 40)).astype(np.uint8)) for _ in range(6)]
    got = {(s, tuple(at)) for s, at in suffix.repeat_groups(texts, 3)}
    spots = {}
    for i, t in enumerate(texts):
        for a in range(len(t)):
            for b in range(a + 3, len(t) + 1):
                spots.setdefault(t[a:b], []).append((i, a))
    want = set()
    for s, at in spots.items():
        left = {texts[i][a - 1] if a else (i, a) for i, a in at}
        right = {texts[i][a + len(s)] if a + len(s) < len(texts[i]) else (i, a) for i, a in at}
        if len(at) > 1 and len(left) > 1 and len(right) > 1:
            want.add((s, tuple(sorted(at))))
    assert got == want
