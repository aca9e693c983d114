import random

import pytest

from evsketch.llm import quality, urlfilter


def plain(text):
    b = (text or "").encode()
    words = "".join(c if c not in " \t\n\x0b\x0c\r" else " " for c in text or "").split(" ")
    words = [w for w in words if w]
    wins = {}
    for i in range(len(words) - 4):
        wins.setdefault(tuple(words[i : i + 5]), []).append(i)
    hit = {i + j for at in wins.values() if len(at) > 1 for i in at for j in range(5)}
    lines = [x for x in (text or "").split("\n") if x.strip(" \t\n\x0b\x0c\r")]
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(hit)


def samples():
    rng = random.Random(3)
    out = [None, "", " \n\t", "a", "a b " * 30, "x\x1cy z w é\x85ü", "one two\none two\n\none two ", "word " * 4]
    for _ in range(150):
        out.append("".join(rng.choice(["a ", "b ", "cc ", "\n", "# ", "é", "the ", "end. ", "\x0b"]) for _ in range(rng.randint(0, 120))))
    return out


def test_quality_counts_and_base(docs):
    rows = list(enumerate(samples()))
    got = {r.doc_id: r for r in quality.score(docs(rows)).collect()}
    for i, t in rows:
        r = got[i]
        n, *rest = plain(t)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (n, *rest), t
        assert r.base_failed == (n < 10 or 100 * rest[3] > 20 * n)
        assert r.kept == (not r.base_failed and not any(x.rejects(quality.Text((t or "").encode())) for x in quality.ADDED))
    assert quality.score(docs([])).count() == 0


def test_cascade_orders_by_rejection_per_cost_and_stops():
    seen = []

    def rule(name, rejects, work):
        def check(t):
            seen.append(name)
            sum(range(work))
            return rejects

        return quality.Rule(name, check)

    rules = [rule("dear_useless", False, 20_000), rule("cheap_useful", True, 1), rule("dear_useful", True, 20_000)]
    ordered, stats = quality.order_rules(rules, [b"x"] * 20)
    assert [r.name for r in ordered][:2] == ["cheap_useful", "dear_useful"] and len(stats) == 3
    seen.clear()
    assert not quality.judge(ordered, quality.Text(b"x")) and seen == ["cheap_useful"]


def test_stage_keeps_columns(docs):
    good = "This is a perfectly ordinary line of prose that nobody would want to throw away at all."
    out = quality.keep_good(docs([(1, good), (2, "too short"), (3, None), (4, "# $ % " * 20)])).collect()
    assert [(r.doc_id, r.text, r.row) for r in out] == [(1, good, "x")]


def test_urls(spark):
    cases = {
        "http://A.Example.ORG/en/12?x": ("a.example.org", "/en/12", "example.org/en/1", "block"),
        "https://www.example.org/es/": ("www.example.org", "/es/", "example.org/es/", "block"),
        "ftp://x.org": ("x.org", "", None, "allow"),
        "http://x.org/": ("x.org", "/", "org/", "allow"),
        "http://badexample.org/es/1": ("badexample.org", "/es/1", "org/", "allow"),
        "http://a.com/de/1#f": ("a.com", "/de/1", "com/de/", "block"),
        "http://a.com/fr/1": ("a.com", "/fr/1", "com/fr/", "allow"),
        "no scheme.com/de/": ("", "", None, "allow"),
        "http://É.com/q?u=http://b.org/": ("É.com", "/q", None, "allow"),
        None: ("", "", None, "allow"),
    }
    df = spark.createDataFrame([(i, u, "x") for i, u in enumerate(cases)] + [(99, "http://x.org/", "x")], "page_id long, url string, host string")
    got = {r.page_id: r for r in urlfilter.judge_urls(df).collect()}
    for i, want in enumerate(cases.values()):
        assert (got[i].host, got[i].path, got[i].rule, got[i].verdict) == want
    assert got[99].rule == "org/"
    assert urlfilter.judge_urls(df.limit(0)).count() == 0


def test_mined_rules_carry_over(spark):
    rows = [(i, f"http://s{i % 40}.com/de/{i}") for i in range(200)] + [(200 + i, f"http://s{i % 40}.org/en/{i}") for i in range(200)]
    rows += [(900, "http://new.com/xx/de"), (901, "http://new.net/de/4"), (902, "http://new.net/zz/4")]
    df = spark.createDataFrame(rows, "page_id long, url string")
    got = {r.page_id: r for r in urlfilter.judge_urls(df, min_support=0.05).collect()}
    assert got[901].rule is None and got[901].mined == "block" and got[901].verdict == "block"
    assert got[902].mined is None and got[902].verdict == "allow"
    plan = urlfilter.judge_urls(df)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


@pytest.mark.parametrize("how", [{}, {"inline": 0}])
def test_certain_rules_do_not_crowd_out_others(spark, how):
    rows = [(i, "http://a.b.org/c/d/e/f/g/h/i/j") for i in range(100)]  # 2,047 rules of confidence 1
    rows += [(100 + i, f"http://s{i}.com/{'fr' if i < 5 else 'de'}/zz") for i in range(100)]
    rows += [(900, "http://new.net/zz"), (901, "http://new.net/c/q"), (902, "http://new.net/q"), (903, None)]
    df = spark.createDataFrame(rows, "page_id long, url string")
    got = {r.page_id: r for r in urlfilter.judge_urls(df, min_support=0.05, **how).collect()}
    assert len(got) == len(rows)
    assert (got[900].mined, got[900].verdict) == ("block", "block") and got[901].mined == "allow"
    assert got[902].mined is None and got[903].mined is None and got[903].verdict == "allow"
