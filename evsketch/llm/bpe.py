"""Byte-level BPE by forced boundaries.

From the vocabulary comes the set of byte pairs that stand side by side inside some token. A pair
outside that set can never be merged across, so a text may be cut between its two bytes. Cuts are
kept only where the pre-tokeniser cuts too whatever stands around them (an ASCII byte that is no
white space, then an ASCII white space byte), so each fragment's ids do not depend on its
neighbours. Fragments repeat, so each worker keeps a bounded cache of their ids; the ids of a text
are those of its fragments in order. Where only ids are wanted, a slice of many texts is cut at
once, its different fragments are told apart by Arrow and each is encoded once: together with those
beside it where a cut is forced between them, as the ids' bytes then tell whose they are. The special
token is taken out before anything else, as the public library does.

Defined cases: a null or empty text has no ids and decodes to the empty text; very long texts and
texts without any cut are single fragments; repeated rows repeat their results; other columns are
not read. The vocabulary file's path is a parameter and must exist on the workers.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from evsketch.llm.common import arrow_map, empty_safe, raw, slices

#: Fragments a worker remembers, and the longest fragment that is worth remembering.
CACHE_ENTRIES, CACHE_BYTES = 200_000, 40
#: Bytes of text whose different fragments are told apart at once, and of fragments that the encoder gets at once.
ENCODE_BYTES, JOINED_BYTES = 4 << 20, 1 << 18

_SPACES = (9, 10, 11, 12, 13, 32)


def _byte_letters() -> dict[str, int]:
    """The vocabulary's letter for each byte: printable bytes stand for themselves, others from U+0100."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


class Vocabulary:
    """Tokens of a byte-level BPE file, its cut table and its encoder for one fragment."""

    def __init__(self, path: str):
        import public_tokenizers
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        letters = _byte_letters()
        self.bytes_of = {i: bytes(letters[c] for c in token) for token, i in spec["model"]["vocab"].items() if token not in self.special}
        self.bytes_of |= {i: token.encode() for token, i in self.special.items()}
        ranks = {self.bytes_of[i]: i for t, i in spec["model"]["vocab"].items() if t not in self.special}
        self._encoder = tiktoken.Encoding("fragments", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        inside = np.zeros((256, 256), bool)
        for token in ranks:
            t = np.frombuffer(token, np.uint8)
            inside[t[:-1], t[1:]] = True
        self.cuts = np.zeros((256, 256), bool)
        left = [b for b in range(33, 127)]
        for b in _SPACES:
            self.cuts[left, b] = ~inside[left, b]
        self._ids: dict[bytes, object] = {}
        self.sizes = np.zeros(max(self.bytes_of) + 1, np.int64)
        self.sizes[list(self.bytes_of)] = [len(b) for b in self.bytes_of.values()]

    def fragments(self, body: bytes) -> list[bytes]:
        """``body`` cut at every forced boundary."""
        a = np.frombuffer(body, np.uint8)
        if len(a) < 2:
            return [body] if body else []
        at = (np.flatnonzero(self.cuts[a[:-1], a[1:]]) + 1).tolist()
        if not at:
            return [body]
        return [body[i:j] for i, j in zip([0, *at], [*at, len(body)], strict=True)]

    def encode_fragment(self, fragment: bytes) -> list[int]:
        return self._encoder.encode_ordinary(fragment.decode("utf-8"))

    def ids_of_each(self, body: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the fragments (none empty) that lie in ``body`` between the offsets, and where each one's begin and end."""
        if len(off) < 2:
            return np.zeros(0, np.uint32), np.zeros(1, np.int64)
        inner = off[1:-1]
        apart = ~self.cuts[body[inner - 1], body[inner]] | (off[:-2] // JOINED_BYTES != inner // JOINED_BYTES)
        ends = [int(off[0]), *inner[apart].tolist(), int(off[-1])]
        ids = np.concatenate([np.array(self.encode_fragment(body[a:b].tobytes()), np.uint32) for a, b in zip(ends[:-1], ends[1:], strict=True)])
        return ids, np.searchsorted(np.concatenate([[0], np.cumsum(self.sizes[ids])]), off - off[0])

    def decode(self, ids) -> bytes:
        """Bytes of the ids, special tokens included; bytes that are no UTF-8 become U+FFFD."""
        body = b"".join(map(self.bytes_of.__getitem__, ids))
        return body.decode("utf-8", "replace").encode("utf-8")

    def remembered(self, fragment: bytes, make):
        """``make(ids)`` of a fragment, from the cache if it is there."""
        known = self._ids.get(fragment)
        if known is None:
            known = make(self.encode_fragment(fragment))
            if len(fragment) <= CACHE_BYTES:
                if len(self._ids) >= CACHE_ENTRIES:
                    self._ids.clear()
                self._ids[fragment] = known
        return known

    def sections(self, text: str):
        """(text, special id or None) in order; special tokens stand alone."""
        if not any(s in text for s in self.special):
            yield text, None
            return
        while text:
            at, name = min(((text.find(s), s) for s in self.special if s in text), default=(-1, ""))
            if at < 0:
                yield text, None
                return
            if at:
                yield text[:at], None
            yield name, self.special[name]
            text = text[at + len(name) :]

    def pack(self, text: str, make) -> list:
        """``make(ids)`` of each fragment of ``text``, in order."""
        out = []
        get, remembered = self._ids.get, self.remembered
        for part, special in self.sections(text):
            if special is not None:
                out.append(make([special]))
                continue
            for f in self.fragments(part.encode("utf-8")):
                out.append(get(f) or remembered(f, make))
        return out


@lru_cache(maxsize=4)
def vocabulary(path: str, use: str) -> Vocabulary:
    """One per worker, file and use (a cache holds one kind of value)."""
    return Vocabulary(path)


def ids_of_slice(body: np.ndarray, off: np.ndarray, v: Vocabulary) -> tuple[np.ndarray, np.ndarray]:
    """Ids of the texts that lie in ``body`` between the offsets, and where each text's begin and end."""
    body, off = body[off[0] : off[-1]], off - off[0]
    whole, special = body.tobytes(), {}
    starts = np.zeros(len(body) + 1, bool)
    starts[1:-1] = v.cuts.ravel().take((body[:-1].astype(np.uint16) << 8) | body[1:])
    starts[off] = True
    names = [s.encode() for s in v.special]
    if any(s in whole for s in names):
        for a, b in zip(off[:-1].tolist(), off[1:].tolist(), strict=True):
            if any(s in whole[a:b] for s in names):
                for part, known in v.sections(whole[a:b].decode("utf-8")):
                    end = a + len(part.encode("utf-8"))
                    if known is not None:
                        starts[a:end] = False
                        special[a] = known
                    starts[[a, end]] = True
                    a = end
    at = np.flatnonzero(starts)  # the end of the last fragment, too
    every = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(at) - 1, [None, pa.py_buffer(at), pa.py_buffer(whole)]).dictionary_encode()
    ids, to = v.ids_of_each(*raw(every.dictionary))
    codes = every.indices.to_numpy()
    if special:
        codes = codes.copy()
        codes[np.searchsorted(at, list(special))] = len(to) - 1 + np.arange(len(special))
        ids = np.concatenate([ids, np.array(list(special.values()), np.uint32)])
        to = np.concatenate([to, to[-1] + 1 + np.arange(len(special))])
    packed = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(to) - 1, [None, pa.py_buffer(4 * to), pa.py_buffer(ids)])
    words, ends = raw(packed.take(pa.array(codes)))
    return words[: ends[-1]].view(np.uint32), ends[np.searchsorted(at, off)] // 4


def ids_of_all(texts: pa.Array, path: str) -> Iterator[np.ndarray]:
    """The ids (unsigned 32-bit) of each text of a large_string array without nulls."""
    v = vocabulary(path, "words")
    body, off = raw(texts)
    for a, b in slices(off, ENCODE_BYTES):
        ids, at = ids_of_slice(body, off[a : b + 1], v)
        for i, j in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
            yield ids[i:j]


def ids_of(text: str | None, path: str) -> bytes:
    """The text's ids, packed as unsigned 32-bit words."""
    return next(ids_of_all(pa.array([text or ""], pa.large_string()), path)).tobytes()


def digest(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per document: key, n_tokens, and hashes of its ids and of the text decoded from them."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        v = vocabulary(path, "digest")

        def made(ids):
            return len(ids), ",".join(map(str, ids)).encode(), b"".join(map(v.bytes_of.__getitem__, ids))

        rows = []
        for t in empty_safe(batch.column(text)).to_pylist():
            parts = v.pack(t, made)
            decoded = b"".join([p[2] for p in parts])
            decoded = decoded.decode("utf-8", "replace").encode("utf-8")
            rows.append((sum([p[0] for p in parts]), hashlib.sha256(b",".join([p[1] for p in parts])).hexdigest(), hashlib.sha256(decoded).hexdigest()))
        n, ids, back = zip(*rows, strict=True)
        return pa.RecordBatch.from_arrays([batch.column(key), pa.array(n, pa.int64()), pa.array(ids), pa.array(back)], [key, "n_tokens", "ids_sha256", "decoded_sha256"])

    kind = docs.schema[key].dataType.simpleString()
    return arrow_map(docs.select(key, text), run, f"`{key}` {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Per document: key and ids (array<int>)."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        ids = [i.astype(np.int32) for i in ids_of_all(empty_safe(batch.column(text)), path)]
        return pa.RecordBatch.from_arrays([batch.column(key), pa.array(ids, pa.list_(pa.int32()))], [key, "ids"])

    return arrow_map(docs.select(key, text), run, f"`{key}` {docs.schema[key].dataType.simpleString()}, ids array<int>")


def decode(encoded: DataFrame, path: str, key: str = "doc_id", ids: str = "ids") -> DataFrame:
    """Per row: key and the text of its ids; null ids give an empty text."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        v = vocabulary(path, "digest")
        texts = [v.decode(x or ()).decode() for x in batch.column(ids).to_pylist()]
        return pa.RecordBatch.from_arrays([batch.column(key), pa.array(texts, pa.string())], [key, "text"])

    return arrow_map(encoded.select(key, ids), run, f"`{key}` {encoded.schema[key].dataType.simpleString()}, text string")
