"""The baselines on the given tables."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from evsketch.operators import baselines as bl
from evsketch.sources.tables import load
from evsketch.spec import SketchSpec
from evsketch.workloads.common import K, query, r, spec_at, w
from evsketch.workloads.methods import z6

_RANK = f"case when {w('l_orderkey')} = 0 then 53 else cast(bit_count(xor({w('l_orderkey')}, {w('l_orderkey')} - 1)) as integer) end"
_RANKS = f"(select {r('l_orderkey')} as reg, max({_RANK}) as rank from lineitem group by all)"


def _ranks(spark, sf_dir):
    spec = spec_at(sf_dir)
    return bl.rank_registers(load(spark, sf_dir, "lineitem"), "l_orderkey", spec=spec), spec


@query("select count(distinct l_orderkey) as n from lineitem")
def b1_exact(spark, sf_dir):
    return bl.exact_distinct(load(spark, sf_dir, "lineitem"), "l_orderkey")


@query("select l_suppkey, count(distinct l_partkey) as n from lineitem group by l_suppkey")
def b1_exact_grouped(spark, sf_dir):
    return bl.exact_distinct(load(spark, sf_dir, "lineitem"), "l_partkey", ["l_suppkey"])


@query("select count(distinct l_orderkey) as n from lineitem")
def b2_bitmap(spark, sf_dir):
    return bl.bitmap_distinct(load(spark, sf_dir, "lineitem"), "l_orderkey")


@query(f"select round({bl.loglog_alpha(K) * K} * pow(2.0::double, sum(rank) / {float(K)}::double), 6) as z from {_RANKS}")
def b3_loglog(spark, sf_dir):
    return z6(bl.loglog(*_ranks(spark, sf_dir)))


_HLL = f"{bl.hll_alpha(K) * K * K} / (sum(pow(2.0::double, -rank)) + {K} - count(*))"


@query(f"select round({_HLL}, 6) as z from {_RANKS}")
def b4_hll(spark, sf_dir):
    return z6(bl.hyperloglog(*_ranks(spark, sf_dir)))


_USER_RANK = _RANK.replace("l_orderkey", "user_id")
_USER_RANKS = f"(select {r('user_id')} as reg, max({_USER_RANK}) as rank from events group by all)"


@query(f"select round(case when {_HLL} <= {2.5 * K} and count(*) < {K} then {K} * ln({float(K)} / ({K} - count(*))) else {_HLL} end, 6) as z from {_USER_RANKS}")
def b4_hll_small(spark, sf_dir):
    spec = spec_at(sf_dir)
    ranks = bl.rank_registers(load(spark, sf_dir, "events"), "user_id", spec=spec)
    return z6(bl.hyperloglog(ranks, spec, small_range=True))


def _within(z, n, sigma):
    """Whether an estimate lies within five standard errors."""
    return (F.abs(F.col(z) - F.col(n)) <= 5 * sigma * F.col(n)).alias("inside")


@query("select true as inside")
def b5_acd(spark, sf_dir):
    df = load(spark, sf_dir, "lineitem")
    return bl.builtin_acd(df, "l_orderkey", 0.05).crossJoin(bl.exact_distinct(df, "l_orderkey")).select(_within("z", "n", 0.05))


@query("select true as inside")
def b6_hll_sketch(spark, sf_dir):
    df = load(spark, sf_dir, "lineitem")
    return bl.builtin_hll(df, "l_orderkey", 12).crossJoin(bl.exact_distinct(df, "l_orderkey")).select(_within("z", "n", 1.04 / 64))


@query("select true as inside")
def b7_theta(spark, sf_dir):
    df = load(spark, sf_dir, "lineitem")
    return bl.builtin_theta(df, "l_orderkey", 12).crossJoin(bl.exact_distinct(df, "l_orderkey")).select(_within("z", "n", 1 / 64))


_ZEROS = f"({_RANK} - 1)"
_PATTERN = f"(select {r('l_orderkey')} as reg, bit_or(1::bigint << least({_ZEROS}, 51)) as bits from lineitem group by all)"


@query(f"select round({K / bl.PATTERN_PHI} * pow(2.0::double, sum(bit_count(xor(bits, bits + 1)) - 1) / {float(K)}::double), 6) as z from {_PATTERN}")
def b8_bit_pattern(spark, sf_dir):
    return z6(bl.bit_pattern_count(load(spark, sf_dir, "lineitem"), "l_orderkey", spec_at(sf_dir)))
