import hashlib
import random
import re

from evsketch.llm import pii

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def digits(s):
    return re.sub("[^0-9]", "", s)


def plain(t):
    out = [("email", *m.span()) for m in EMAIL.finditer(t)]
    out += [("ip", *m.span()) for m in IP.finditer(t) if all(int(x) <= 255 for x in m[0].split("."))]
    out += [("card", *m.span()) for m in CARD.finditer(t) if 16 <= len(digits(m[0])) <= 19 and pii.luhn(digits(m[0]))]
    return out + [("phone", *m.span()) for m in PHONE.finditer(t) if 8 <= len(digits(m[0])) <= 15]


def test_base_spans_equal_the_patterns():
    rng = random.Random(4)
    for _ in range(5000):
        t = "".join(rng.choice("a1234.@ -+()5é\n00") for _ in range(rng.randint(0, 70)))
        assert pii.base_spans(t) == plain(t)
    fixed = "x 4111 1111-1111 1111 y 4539148803436467 +1 (706) 555-3138 a.b@c-d.org 256.1.1.1 10.0.0.255 é 0010.1.1.1"
    assert pii.base_spans(fixed) == plain(fixed) and {s[0] for s in plain(fixed)} == {"email", "ip", "card", "phone"}


def test_long_texts_are_linear():
    for t in ("1" * 200_000, "a" * 200_000 + "@", "+1" * 100_000, "a@" * 100_000, "1." * 100_000):
        pii.base_spans(t)


def corpus():
    rng = random.Random(1)
    words = ["".join(rng.choice("aeioulnrst") for _ in range(6)) for _ in range(200)]
    fill = lambda n: " ".join(rng.choice(words) for _ in range(n))
    rows = [(i, fill(40)) for i in range(300)]
    for i in range(300, 306):  # a nickname only ever seen beside one address
        rows.append((i, f"{fill(10)} Zaphodine wrote from z.beeble@heart.example.org today {fill(10)}"))
    rows += [(400, "card 4539148803436467 " + fill(5)), (401, None), (402, ""), (402, "")]
    return rows


def test_disclosing_terms_are_found_and_others_left(docs):
    rows = corpus()
    got = pii.digest(docs(rows)).collect()
    assert len(got) == len(rows)
    for r in got:
        t = next(x for i, x in rows if i == r.doc_id) or ""
        base = plain(t)
        text = ",".join(f"{k}:{a}:{b}" for k, a, b in base)
        assert r.base_sha256 == hashlib.sha256(text.encode()).hexdigest() and r.n_email == sum(k == "email" for k, _, _ in base)
        terms = [s for s in r.spans.split(",") if s.startswith("term:")]
        assert r.spans.startswith(text)
        if 300 <= r.doc_id < 306:
            at = t.index("Zaphodine")
            assert f"term:{at}:{at + 9}" in terms
        else:
            assert terms == []


def test_sanitised_texts(docs):
    out = {r.doc_id: r for r in pii.sanitise(docs(corpus())).collect()}
    assert "[EMAIL]" in out[303].text and "Zaphodine" not in out[303].text and "heart.example" not in out[303].text
    assert out[400].text.startswith("card [CARD] ") and out[401].text is None and out[5].text == dict(corpus())[5] and out[5].row == "x"
    assert pii.sanitise(docs([])).count() == 0 and pii.digest(docs([])).count() == 0


def disclosed(rows, spark_docs, **how):
    """Terms flagged in each document, and the definition's: counts of documents by brute force."""
    import math

    texts = [(i, t or "") for i, t in rows]
    seen = {}
    for n, (_, t) in enumerate(texts):
        seen[n] = {(e, x) for e, x, _, _ in pii.contexts(t, pii.base_spans(t) + pii.secret_spans(t))}
    of_t, of_e, both = {}, {}, {}
    for n, (_, t) in enumerate(texts):
        for x in {pii.h64(w) for w in pii._TERM.findall(t.lower())}:
            of_t[x] = of_t.get(x, 0) + 1
        for e in {pii.h64(f) for s in pii.base_spans(t) + pii.secret_spans(t) for f in pii.faces(t, s)}:
            of_e[e] = of_e.get(e, 0) + 1
        for pair in seen[n]:
            both[pair] = both.get(pair, 0) + 1
    n_docs = len(texts)

    def bad(e, x):
        told = math.log((both[e, x] + of_t[x] / n_docs) / (of_e[e] + 1) * n_docs / of_t[x])
        return told >= 0.9 * math.log(n_docs / of_e[e]) and told >= math.log(20)

    want = {}
    for i, t in texts:
        found = {(s, e) for f, x, s, e in pii.contexts(t, pii.base_spans(t) + pii.secret_spans(t)) if bad(f, x)}
        want[i] = sorted(found)
    got = {r.doc_id: sorted((x.s, x.f) for x in r.terms) for r in pii.find(spark_docs).collect()}
    return got, want


def test_rare_and_pooled_entities_equal_the_definition(docs, monkeypatch):
    rng = random.Random(7)
    words = ["".join(rng.choice("aeioulnrst") for _ in range(6)) for _ in range(150)]
    fill = lambda n: " ".join(rng.choice(words) for _ in range(n))
    rows = [(i, fill(30)) for i in range(2000)]
    rows[10] = (10, f"{fill(9)} Quuxington at +1 (212) 555-0147 {fill(9)}")  # one sighting of both
    for i in range(20, 30):  # a firm named beside ten addresses of its domain, each met once
        rows[i] = (i, f"{fill(9)} Frobnicorp staff{i}@frob.example {fill(9)}")
    rows[40] = (40, f'{fill(9)} the token = "04dbebab91ab85687d33" of Snarkleton {fill(9)}')
    got, want = disclosed(rows, docs(rows))
    assert got == want
    at = {i: rows[i][1].index(w) for i, w in ((10, "Quuxington"), (25, "Frobnicorp"), (40, "Snarkleton"))}
    assert all((at[i], at[i] + 10) in got[i] for i in at) and not any(got[i] for i in range(100, 2000))
    monkeypatch.setattr(pii, "NEAR_BITS", 15)
    assert disclosed(rows, docs(rows))[0] == want


def test_secrets_and_their_spans(docs):
    t = 'x token = "04dbebab91ab85687d33eeaaf9ac" y Password: hunter2hunter API_KEY=abc1def2g3 monkey: 12345678 token of love'
    got = [(t[a:b]) for _, a, b in pii.secret_spans(t)]
    assert got == ["04dbebab91ab85687d33eeaaf9ac", "hunter2hunter", "abc1def2g3"]
    row = pii.digest(docs([(1, t)])).first()
    assert row.base_sha256 == hashlib.sha256(b"").hexdigest() and row.spans.startswith("secret:11:39,") and row.n_spans == 3
    out = pii.sanitise(docs([(1, t)])).first().text
    assert "hunter2" not in out and out.count("[SECRET]") == 3 and out.endswith("token of love")


def test_many_identifiers_in_one_text():
    t = "name word a.b@c.org 10.0.0.1 and " * 4000
    found = pii.contexts(t, pii.base_spans(t))
    assert found and all(t[s:e] in ("name", "word") for _, _, s, e in found)
    for t in ('token="' * 30_000, "key=" * 50_000, "token" + " " * 100_000):
        pii.secret_spans(t)
