"""Exact invariants of the registers, and the documented answers of edge inputs."""

import math

import pytest
from pyspark.sql import functions as F

from evsketch.functions import hashing
from evsketch.functions.gumbel import gumbel_from_hash
from evsketch.functions.items import canonical_item
from evsketch.operators import baselines, discretize, estimate
from evsketch.operators import registers as rg
from evsketch.operators import relational as rel
from evsketch.plans.checks import plan_facts
from evsketch.sources.tables import load
from evsketch.spec import SketchSpec, SpecMismatch, registers_for

SF = "/root/testdata/sf0.001"
SPEC = SketchSpec(k=64)


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


def regs(df, spec=SPEC):
    return rows(rg.registers(df, "l_orderkey", spec=spec).select("reg", "w"))


@pytest.mark.parametrize("family", ["portable", "fast"])
def test_repeats_order_and_partitions_change_nothing(spark, family):
    spec = SPEC.with_(family=family)
    keys = load(spark, SF, "lineitem").select("l_orderkey")
    base = regs(keys, spec)
    assert base == regs(keys.distinct(), spec) == regs(keys.union(keys), spec) == regs(keys.repartition(7), spec) == regs(keys.orderBy(F.desc("l_orderkey")), spec)


def test_merge_is_associative_idempotent_and_equals_the_union(spark):
    keys = load(spark, SF, "lineitem").select("l_orderkey")
    a, b, c = (rg.registers(keys.where(f"l_orderkey % 5 in ({x})"), "l_orderkey", spec=SPEC) for x in ("0,1", "1,2,3", "4"))
    ab_c = rg.merge((rg.merge((a, SPEC), (b, SPEC)), SPEC), (c, SPEC), (a, SPEC))
    a_bc = rg.merge((a, SPEC), (rg.merge((c, SPEC), (b, SPEC)), SPEC))
    assert rows(ab_c.select("reg", "w")) == rows(a_bc.select("reg", "w")) == regs(keys)


def test_seeds_are_idempotent_and_commute_with_merging(spark):
    keys = load(spark, SF, "lineitem").select("l_orderkey")
    a, b = (rg.registers(keys.where(f"l_orderkey % 2 = {x}"), "l_orderkey", spec=SPEC) for x in (0, 1))
    late = rg.with_seed_draws(rg.merge((a, SPEC), (b, SPEC)), SPEC)
    early = rg.merge((rg.with_seed_draws(a, SPEC), SPEC), (rg.with_seed_draws(b, SPEC), SPEC))
    twice = rg.with_seed_draws(late, SPEC)
    assert rows(late.select("reg", "w")) == rows(early.select("reg", "w")) == rows(twice.select("reg", "w"))
    assert late.count() == 64


def test_specs_must_match(spark):
    r = rg.registers(load(spark, SF, "orders"), "o_orderkey", spec=SPEC)
    with pytest.raises(SpecMismatch):
        rg.merge((r, SPEC), (r, SPEC.with_(seed="s2")))


def test_empty_and_all_null_inputs(spark):
    for df in (spark.createDataFrame([], "v long"), spark.createDataFrame([(None,), (None,)], "v long")):
        r = rg.registers(df, "v", spec=SPEC)
        assert r.count() == 0
        assert estimate.estimate_geometric(r, SPEC).first().z == 0.0
        assert estimate.estimate_harmonic(r, SPEC).first().z == 0.0
        dense = rg.with_seed_draws(r, SPEC)
        z = estimate.estimate_geometric(dense, SPEC).first().z
        assert dense.count() == 64 and 0 < z < 64**1.5
        assert baselines.bitmap_distinct(df, "v").first().n == 0
        assert baselines.hyperloglog(baselines.rank_registers(df, "v", spec=SPEC), SPEC, small_range=True).first().z == pytest.approx(0)


def test_linear_counting_is_infinite_once_every_register_is_occupied(spark):
    r = rg.registers(load(spark, SF, "orders"), "o_orderkey", spec=SPEC)
    assert r.count() == SPEC.k and estimate.estimate_small(r, SPEC).first().z == math.inf
    assert estimate.estimate_small(r.where("reg > 0"), SPEC).first().z == pytest.approx(SPEC.k * math.log(SPEC.k))


def test_one_register_and_odd_k(spark):
    for k in (1, 3, 100):
        spec = SketchSpec(k=k)
        r = rg.with_seed_draws(rg.registers(load(spark, SF, "orders"), "o_orderkey", spec=spec), spec)
        assert r.count() == k and estimate.estimate_geometric(r, spec).first().z > 0


def test_transform_is_finite_at_both_ends(spark):
    for bits in (52, 63):
        w = spark.createDataFrame([(0,), ((1 << bits) - 1,)], "w long")
        lo, hi = (r.x for r in w.select(gumbel_from_hash(F.col("w"), bits).alias("x")).collect())
        assert math.isfinite(lo) and math.isfinite(hi) and lo > 30 and hi < -3


def test_canonical_items(spark):
    def item(value, kind):
        df = spark.createDataFrame([(value,)], f"v {kind}")
        return df.select(canonical_item(df, "v")).first()[0]

    assert item(7, "int") == item(7, "long") == item(7, "smallint")
    assert item(0.0, "double") == item(-0.0, "double")
    assert item(float("nan"), "double") == item(float("nan"), "double")
    assert item([1, None], "array<int>") != item([None, 1], "array<int>")
    assert item(["a", "b"], "array<string>") != item(["ab"], "array<string>")
    assert item({"a": 1, "b": 2}, "map<string,int>") == item({"b": 2, "a": 1}, "map<string,int>")
    assert item("", "string") == "" and item(None, "string") is None
    import decimal

    assert item(decimal.Decimal("1.0"), "decimal(5,1)") == item(decimal.Decimal("1.00"), "decimal(5,2)")
    pairs = spark.createDataFrame([("a", "bc"), ("ab", "c"), ("a", None)], "x string, y string")
    got = [r[0] for r in pairs.select(canonical_item(pairs, ["x", "y"])).collect()]
    assert got[0] != got[1] and got[2] is None


def test_rounding_before_and_after_the_maximum(spark):
    orders = load(spark, SF, "orders")
    scan = discretize.scan_rounded(orders, "o_orderkey", spec=SPEC)
    store = discretize.shift_round_registers(rg.registers(orders, "o_orderkey", spec=SPEC), SPEC)
    assert rows(scan.select("reg", "q")) == rows(store.select("reg", "q"))


def test_full_registers_agree_three_ways(spark):
    spec = SketchSpec(k=16, layout="full")
    orders = load(spark, SF, "orders")
    wide, explode, arrow = (rows(rg.full_registers(orders, "o_orderkey", spec=spec, how=h).select("reg", "w")) for h in ("wide", "explode", "arrow"))
    assert wide == explode == arrow


def test_plan_is_two_hash_aggregates_without_python(spark):
    facts = plan_facts(rg.registers(load(spark, SF, "lineitem"), "l_orderkey", spec=SPEC.with_(family="fast")))
    assert facts["hash_aggregates"] == 2 and facts["exchanges"] == 1 and facts["python"] == 0 and facts["object_aggregates"] == 0
    assert facts["read"] == ["l_orderkey:bigint"] and "IsNotNull(l_orderkey)" in facts["pushed"][0]


def test_registers_for_error():
    assert registers_for(0.1) == 100 and registers_for(0.05, "proved") == math.ceil((math.pi / 0.05) ** 2)
    assert SketchSpec.for_error(0.125).k == 64
    with pytest.raises(ValueError):
        SketchSpec(k=0)


def test_asof_and_range_joins_against_plain_loops(spark):
    left = [(k, t) for k in "ab" for t in range(0, 20, 3)] + [("c", 5)]
    right = [(k, t, t * 10) for k in "ab" for t in (1, 1, 7, 12)]
    got = rows(rel.asof_join(spark.createDataFrame(left, "k string, t long"), spark.createDataFrame(right, "k string, u long, v long"), "t", "u", ["k"], ["v"]))
    want = sorted(((k, t, max((v for q, u, v in right if q == k and u <= t), default=None)) for k, t in left), key=str)
    assert got == want
    spans = [(1, 0.0, 2.5), (2, 2.5, 2.5), (3, -7.0, 30.0)]
    points = [(float(x) / 2,) for x in range(-20, 40)]
    got = rows(rel.range_join(spark.createDataFrame(points, "p double"), "p", spark.createDataFrame(spans, "i int, a double, b double"), "a", "b", 3.0).select("p", "i"))
    assert got == sorted(((p, i) for (p,) in points for i, a, b in spans if a <= p < b), key=str)


def test_pack_roundtrip(spark):
    q = discretize.shift_round_registers(rg.registers(load(spark, SF, "orders"), "o_orderkey", ["o_orderpriority"], SPEC), SPEC)
    back = rg.unpack(rg.pack(q, SPEC, ["o_orderpriority"]), ["o_orderpriority"])
    assert rows(back.select("o_orderpriority", "reg", F.col("q").cast("int"))) == rows(q.select("o_orderpriority", "reg", F.col("q").cast("int")))


def test_seed_draws_and_offsets_do_not_depend_on_the_plan(spark):
    a = spark.range(64).select(hashing.seed_draw(SPEC, F.col("id").cast("int")).alias("w0"), hashing.offset(SPEC, F.col("id").cast("int")).alias("c"))
    got = a.collect()
    assert len({r.w0 for r in got}) == 64 and all(0 <= r.c < 1 for r in got)
