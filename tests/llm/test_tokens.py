import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from evsketch.llm import bpe, packing

PATH = public_tokenizers.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(PATH)


def texts():
    rng = random.Random(9)
    pool = ["the", "don't", " we'll", "\n", "  ", "\t", "é", "日本", "🙂", "<|endoftext|>", "<|endo", " ", "\x1c", "1234", "!!", "naïve", "x" * 50]
    out = ["".join(rng.choice(pool) for _ in range(rng.randint(0, 40))) for _ in range(1500)]
    return out + ["", " ", "a" * 5000, " " * 3000, "<|endoftext|><|endoftext|>", "trailing  ", "  \n x"]


def test_encoding_equals_the_library(library):
    every = texts()
    v = bpe.vocabulary(PATH, "words")
    for t, e in zip(every, library.encode_batch(every, add_special_tokens=False), strict=True):
        ids = np.frombuffer(bpe.ids_of(t, PATH), np.uint32).tolist()
        assert ids == e.ids
        assert v.decode(ids).decode() == library.decode(e.ids, skip_special_tokens=False) == t


def test_slices_equal_the_library(library, monkeypatch):
    every = ["skipped", *texts()]
    column = pa.array(every, pa.large_string())[1:]
    for sizes in ((4 << 20, 1 << 18), (300, 16), (1, 1)):
        monkeypatch.setattr(bpe, "ENCODE_BYTES", sizes[0])
        monkeypatch.setattr(bpe, "JOINED_BYTES", sizes[1])
        got = [i.tolist() for i in bpe.ids_of_all(column, PATH)]
        assert got == [e.ids for e in library.encode_batch(every[1:], add_special_tokens=False)]
    assert list(bpe.ids_of_all(column[:0], PATH)) == []
    assert [len(i) for i in bpe.ids_of_all(pa.array(["", ""], pa.large_string()), PATH)] == [0, 0]


def test_different_fragments_are_encoded_once(library, monkeypatch):
    text = "".join(f" word{i % 1000}" for i in range(20_000))  # more different ones than are remembered
    v, sizes = bpe.vocabulary(PATH, "words"), []
    monkeypatch.setattr(bpe, "CACHE_ENTRIES", 100)
    monkeypatch.setattr(v, "encode_fragment", lambda f: sizes.append(len(f)) or bpe.Vocabulary.encode_fragment(v, f))
    assert np.frombuffer(bpe.ids_of(text, PATH), np.uint32).tolist() == library.encode(text, add_special_tokens=False).ids
    assert sum(sizes) <= 1000 * len(" word999") and len(sizes) <= 2


def test_cuts_are_forced(library):
    v = bpe.vocabulary(PATH, "words")
    for a, b in np.argwhere(v.cuts).tolist():
        assert not any(bytes([a, b]) in token for i, token in list(v.bytes_of.items())[::97])


def test_query_and_roundtrip(docs, library):
    rows = list(enumerate(texts()[:200])) + [(500, None), (501, ""), (7, "again")]
    got = bpe.digest(docs(rows), PATH).collect()
    want = []
    for i, t in rows:
        ids = library.encode(t or "", add_special_tokens=False).ids
        want.append((i, len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    assert sorted(map(tuple, got)) == sorted(want)
    back = bpe.decode(bpe.encode(docs(rows), PATH), PATH)
    assert sorted((r.doc_id, r.text) for r in back.collect()) == sorted((i, t or "") for i, t in rows)
    assert bpe.digest(docs([]), PATH).count() == 0


@pytest.mark.parametrize("score", ["norm", "dot"])
def test_best_fit_constraints(score):
    rng = np.random.default_rng(2)
    lengths = np.sort(rng.integers(1, 300, 2000))[::-1]
    for box in (packing.Bin(512, 512, 512 * 512, score=score), packing.Bin(512, 4, 512 * 512, score=score), packing.Bin(512, 512, 90_000, score=score)):
        seq, off = packing.best_fit(lengths, box)
        for s in range(seq.max() + 1):
            own = seq == s
            order = np.argsort(off[own])
            ln, of = lengths[own][order], off[own][order]
            assert of[0] == 0 and (of[1:] == np.cumsum(ln)[:-1]).all()
            assert ln.sum() <= box.tokens and len(ln) <= box.documents and (ln**2).sum() <= box.attention
    free = packing.best_fit(lengths, packing.Bin(512, 512, 512 * 512, score=score))[0].max() + 1
    assert free <= 1.01 * -(-lengths.sum() // 512) + 1


def test_best_fit_picks_the_best_open_sequence():
    seq, _ = packing.best_fit(np.array([7, 6, 3, 2, 2]), packing.Bin(10, 10, 100))
    assert seq.tolist() == [0, 1, 0, 1, 1]  # 3 fits beside 7 exactly; 2 and 2 beside 6


def test_packing_query(docs, library):
    rows = [(i, t * 20) for i, t in enumerate(texts()[:300])] + [(900, "word " * 9000), (901, None), (902, ""), (5, "again")]
    got = packing.pack(docs(rows), PATH, group=100).collect()
    by, total = {}, 0
    for i, t in rows:
        ids = library.encode(t or "", add_special_tokens=False).ids + [0]
        total += len(ids)
        for p, (a, n) in enumerate(packing.piece_bounds(len(ids), 2048)):
            by.setdefault((i, p, a, n, zlib.crc32(np.array(ids[a : a + n], "<u4").tobytes())), []).append(1)
    assert sorted((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == sorted(k for k, v in by.items() for _ in v)
    rooms = {}
    for r in got:
        rooms.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for room in rooms.values():
        room.sort()
        assert room[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(room, room[1:], strict=False)) and sum(n for _, n in room) <= 2048
    assert len(rooms) <= 1.03 * -(-total // 2048) + 6
    assert packing.pack(docs([]), PATH).count() == 0
