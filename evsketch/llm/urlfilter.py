"""URL filtering by stated rules and by association rules mined with Spark's FP-growth.

Native: DataFrame and SQL functions only. URLs are tokenised into host labels, path segments and
query keys. URLs that a stated rule decides are the labels; FP-growth over (tokens + verdict)
finds frequent combinations, association rules whose consequent is a verdict are pruned by support
and confidence, redundant ones go, and all others form an inverted index from a rule's first token
to the rule: a constant of the plan while they are few, else a table. A URL without a stated rule takes the verdict of the best mined rule whose
tokens it all has, else the default.

Defined cases: a null URL, or one without ``://``, has empty host and path, no tokens and gets the
default verdict; repeated rows are judged alike; with no labelled URL nothing is mined; extra
columns are not read.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evsketch.llm.common import staged

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_PARTS = r"(?s)^.*?://([^/?#]*)([^?#]*)"


@dataclass(frozen=True)
class UrlRule:
    verdict: str
    host: str
    path: str

    @property
    def text(self) -> str:
        return self.host + self.path


def parse_rules(lines: Sequence[str]) -> list[UrlRule]:
    """``allow org/`` or ``block example.org/en/1`` become rules."""
    rules = []
    for line in lines:
        verdict, target = line.split()
        host, slash, path = target.partition("/")
        rules.append(UrlRule(verdict, host, slash + path))
    return rules


#: The stated rules (fixed values).
STATED = parse_rules(["allow org/", "block example.org/es/", "block example.org/en/1", "allow com/fr/", "block com/de/"])


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, _PARTS, 1), F.lit("")), _UPPER, _LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, _PARTS, 2), F.lit(""))


def stated_rule(host: Column, path: Column, rules: Sequence[UrlRule]) -> Column:
    """The longest stated rule that fits (ties: the smaller text), as struct(rule, verdict), or null."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for r in sorted(rules, key=lambda r: (len(r.text), [-ord(c) for c in r.text])):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        out = F.when(fits, F.struct(F.lit(r.text).alias("rule"), F.lit(r.verdict).alias("verdict"))).otherwise(out)
    return out


def tokens_of(url: Column) -> Column:
    """Distinct tokens: ``h:`` host labels, ``p:`` path segments, ``q:`` query keys."""
    query = F.regexp_extract(url, r"(?s)\?([^#]*)", 1)

    def tagged(kind: str, parts: Column) -> Column:
        return F.transform(F.filter(parts, lambda x: x != ""), lambda x: F.concat(F.lit(kind), x))

    keys = F.transform(F.split(query, "&"), lambda x: F.substring_index(x, "=", 1))
    every = F.concat(tagged("h:", F.split(host_of(url), r"\.")), tagged("p:", F.split(path_of(url), "/")), tagged("q:", keys))
    return F.array_sort(F.array_distinct(F.coalesce(every, F.array().cast("array<string>"))))


@dataclass(frozen=True)
class MinedRule:
    tokens: tuple[str, ...]
    verdict: str
    confidence: float
    support: float


def mine(labelled: DataFrame, min_support: float = 0.005, min_confidence: float = 0.9, max_rows: int = 100_000) -> DataFrame | None:
    """Association rules tokens -> verdict from rows (tokens, verdict): all that support and
    confidence leave, but the redundant ones, staged (first token, tokens, verdict, confidence, support).

    ``max_rows`` bounds the labelled rows that are mined: beyond it rows are taken by a hash of
    their URL.
    """
    n = labelled.count()
    if not n:
        return None
    if n > max_rows:
        labelled = labelled.where(F.pmod(F.xxhash64("url"), F.lit(1 << 20)) < int((1 << 20) * max_rows / n))
    baskets = labelled.select(F.concat("tokens", F.array(F.concat(F.lit("="), "verdict"))).alias("items"))
    model = FPGrowth(itemsCol="items", minSupport=min_support, minConfidence=min_confidence).fit(baskets)
    found = (
        model.associationRules.where(F.element_at("consequent", 1).startswith("="))
        .where(~F.exists("antecedent", lambda x: x.startswith("=")))
        .select(F.array_sort("antecedent").alias("tokens"), F.substring(F.element_at("consequent", 1), 2, 64).alias("verdict"), "confidence", "support")
    )
    found = staged(found.select(F.element_at("tokens", 1).alias("first"), "*"))
    # A rule is redundant if a shorter one with its verdict is at least as confident: its support is
    # no less either and it fits wherever the longer one does, so no verdict changes.
    short = found.select("first", F.col("tokens").alias("some"), "verdict", F.col("confidence").alias("c"))
    longer = found.select(F.explode("tokens").alias("first"), "tokens", "verdict", "confidence")
    inside = (F.size("some") < F.size("tokens")) & (F.size(F.array_except("some", "tokens")) == 0) & (F.col("c") >= F.col("confidence"))
    redundant = longer.join(short, ["first", "verdict"]).where(inside).select("tokens", "verdict").distinct()
    return staged(found.join(redundant, ["tokens", "verdict"], "left_anti"))


def mined_verdict(tokens: Column, rules: Sequence[MinedRule]) -> Column:
    """Verdict of the most confident mined rule whose tokens are all present, or null.

    The inverted index is a constant map from each rule's first token to its rules.
    """
    if not rules:
        return F.lit(None).cast("string")
    index: dict[str, list[MinedRule]] = {}
    for r in rules:
        index.setdefault(r.tokens[0], []).append(r)

    def entry(r: MinedRule) -> Column:
        return F.struct(F.lit(r.confidence).alias("c"), F.lit(r.support).alias("s"), F.lit(r.verdict).alias("v"), F.array(*map(F.lit, r.tokens)).alias("t"))

    postings = F.create_map(*[x for k, rs in index.items() for x in (F.lit(k), F.array(*map(entry, rs)))])
    hits = F.flatten(F.filter(F.transform(tokens, lambda t: F.try_element_at(postings, t)), lambda x: x.isNotNull()))
    fitting = F.filter(hits, lambda r: F.size(F.array_except(r["t"], tokens)) == 0)
    return F.array_max(fitting)["v"]


def with_mined(judged: DataFrame, found: DataFrame | None, inline: int) -> DataFrame:
    """``judged`` with a column ``mined``; more than ``inline`` rules stay a table, joined on a rule's first token."""
    if found is None:
        return judged.withColumn("mined", F.lit(None).cast("string"))
    if found.count() <= inline:
        rules = [MinedRule(tuple(r.tokens), r.verdict, r.confidence, r.support) for r in found.orderBy("tokens", "verdict").collect()]
        return judged.withColumn("mined", mined_verdict(F.col("tokens"), rules))
    index = found.select("first", F.struct(F.col("confidence").alias("c"), F.col("support").alias("s"), F.col("verdict").alias("v"), F.col("tokens").alias("t")).alias("r"))
    sets = judged.select("tokens").distinct().select("tokens", F.explode("tokens").alias("first"))
    best = sets.join(index, "first").where(F.size(F.array_except("r.t", "tokens")) == 0).groupBy("tokens").agg(F.max("r").alias("r"))
    return judged.join(best.select("tokens", F.col("r.v").alias("mined")), "tokens", "left")


def judge_urls(pages: DataFrame, key: str = "page_id", url: str = "url", rules: Sequence[UrlRule] = STATED, default: str = "allow", inline: int = 400, **mining) -> DataFrame:
    """One row per page: key, host, path, rule, verdict, mined (the mined verdict, or null)."""
    u = F.col(url)
    read = pages.select(F.col(key), host_of(u).alias("host"), path_of(u).alias("path"), tokens_of(u).alias("tokens"), u.alias("url"))
    judged = read.withColumn("stated", stated_rule(F.col("host"), F.col("path"), rules))
    labelled = judged.where("stated is not null").select("tokens", "url", F.col("stated.verdict").alias("verdict"))
    judged = with_mined(judged, mine(labelled, **mining), inline)
    return judged.select(key, "host", "path", F.col("stated.rule").alias("rule"), F.coalesce(F.col("stated.verdict"), F.col("mined"), F.lit(default)).alias("verdict"), "mined")
