"""The methods and their variants, each on a given table."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evsketch.functions import gumbel, hashing
from evsketch.functions.gumbel import EULER_GAMMA
from evsketch.operators import accuracy, baselines, discretize, estimate
from evsketch.operators import registers as rg
from evsketch.sources.tables import load
from evsketch.spec import SketchSpec, registers_for
from evsketch.workloads.common import K, K_FULL, WORD, c, e, fast_dense, full, geo, harm, md, query, r, regs, seeded, spec_at, w, x

EPS = (1.0, 0.5, 0.25, 0.125, 0.015625)


def z6(df: DataFrame) -> DataFrame:
    return df.withColumn("z", F.round("z", 6))


def _orderkeys(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").select("l_orderkey")


def _full(spark, sf_dir, how="auto", mode="rehash"):
    spec = SketchSpec(k=K_FULL, layout="full")
    return rg.full_registers(load(spark, sf_dir, "orders"), "o_orderkey", spec=spec, how=how, mode=mode), spec


_FULL = full("orders", "o_orderkey")
_RAW = regs("lineitem", "l_orderkey")
_DENSE = seeded(_RAW)
_USERS = "(select strftime(ts, '%Y-%m-%d') as day, user_id from events)"
_USER_DENSE = seeded(regs(_USERS, "user_id", "day"), "day")


def users_by_day(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "events").select(F.date_format("ts", "yyyy-MM-dd").alias("day"), "user_id")


#: Customers' orders as groups of n items: items in each of three sub-streams, most trailing zeros, least w.
GROUPS = (
    "(select o_custkey, count(*) as n, count(*) filter (where part = 0) as n0, count(*) filter (where part = 1) as n1, count(*) filter (where part = 2) as n2, "
    "max(case when w = 0 then 53 else cast(bit_count(xor(w, w - 1)) as integer) end) - 1 as zeros, min(w) as w "
    f"from (select distinct o_custkey, o_orderkey, {r('o_orderkey', 3)} as part, {w('o_orderkey')} as w from orders where o_custkey is not null and o_orderkey is not null) group by o_custkey)"
)


def customer_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec, item = SketchSpec(k=3), F.col("item")
    each = rg.items(load(spark, sf_dir, "orders").where("o_custkey is not null"), "o_orderkey", ["o_custkey"]).distinct()
    drawn = each.select("o_custkey", hashing.register(spec, item).alias("part"), hashing.draw(spec, item).alias("w"))
    parts = [F.count_if(F.col("part") == i).alias(f"n{i}") for i in range(3)]
    return drawn.groupBy("o_custkey").agg(F.count("*").alias("n"), *parts, (F.max(baselines.rank(F.col("w"), 52)) - 1).alias("zeros"), F.min("w").alias("w"))


@query(geo(_FULL, 1))
def m1_full_geo(spark, sf_dir):
    return z6(estimate.estimate_geometric(*_full(spark, sf_dir)))


@query(geo(_FULL, 1 / gumbel.geometric_bias(K_FULL)))
def m1_full_geo_debiased(spark, sf_dir):
    return z6(estimate.estimate_geometric(*_full(spark, sf_dir), debias=True))


@query(geo(_FULL, 1))
def m1_full_wide(spark, sf_dir):
    return z6(estimate.estimate_geometric(*_full(spark, sf_dir, "wide")))


@query(geo(_FULL, 1))
def m1_full_explode(spark, sf_dir):
    return z6(estimate.estimate_geometric(*_full(spark, sf_dir, "explode")))


@query(geo(_FULL, 1))
def m1_full_arrow(spark, sf_dir):
    return z6(estimate.estimate_geometric(*_full(spark, sf_dir, "arrow")))


_LINEAR = f"(select i as reg, min((cast('0x' || substr(m, 1, 13) as bigint) + (i + 1) * cast('0x' || substr(m, 14, 13) as bigint)) % 4503599627370496) as w from (select {md('o_orderkey')} as m from orders) cross join range({K_FULL}) t(i) group by all)"


@query(geo(_LINEAR, 1))
def m1_linear_hash(spark, sf_dir):
    return z6(estimate.estimate_geometric(*_full(spark, sf_dir, "explode", "linear")))


@query(f"select cast(reg as bigint) as reg, w from {_RAW}")
def m2_registers(spark, sf_dir):
    return rg.registers(_orderkeys(spark, sf_dir), "l_orderkey", spec=spec_at(sf_dir)).select(F.col("reg").cast("long").alias("reg"), "w")


def _dense(spark, sf_dir, **more):
    spec = spec_at(sf_dir, **more)
    found = rg.registers(_orderkeys(spark, sf_dir), "l_orderkey", spec=spec)
    return (rg.with_seed_draws(found, spec) if spec.init == "seeded" else found), spec


@query(geo(_DENSE, K))
def m2_geo(spark, sf_dir):
    return z6(estimate.estimate_geometric(*_dense(spark, sf_dir)))


def _dense_days(spark, sf_dir):
    spec = spec_at(sf_dir)
    return rg.with_seed_draws(rg.registers(users_by_day(spark, sf_dir), "user_id", ["day"], spec), spec, ["day"]), spec


@query(geo(_USER_DENSE, K, "day"))
def m2_geo_by_group(spark, sf_dir):
    return z6(estimate.estimate_geometric(*_dense_days(spark, sf_dir), by=["day"]))


@query(geo(_RAW, K))
def m2_geo_unseeded(spark, sf_dir):
    return z6(estimate.estimate_geometric(*_dense(spark, sf_dir, init="none")))


@query(f"select z, z >= {float(K) ** 1.5} as in_regime from ({geo(_DENSE, K)})")
def m2_regime_flag(spark, sf_dir):
    found, spec = _dense(spark, sf_dir)
    return z6(estimate.estimate_geometric(found, spec)).withColumn("in_regime", estimate.in_regime(F.col("z"), spec.k))


def _shifted(source: str) -> str:
    return f"(select reg, floor({x('w')} + {c('reg')}) as q from {source})"


def _shift_geo(source: str, factor: int) -> str:
    return f"select round({factor} * exp(avg(q - {c('reg')}) + 0.5::double - {EULER_GAMMA}), 6) as z from {_shifted(source)}"


@query(_shift_geo(_DENSE, K))
def m3_shift_geo(spark, sf_dir):
    found, spec = _dense(spark, sf_dir)
    return z6(estimate.estimate_shifted(discretize.shift_round_registers(found, spec), spec))


@query(_shift_geo(_FULL, 1))
def m3_shift_full_geo(spark, sf_dir):
    found, spec = _full(spark, sf_dir)
    return z6(estimate.estimate_shifted(discretize.shift_round_registers(found, spec), spec))


@query(f"select round({K * K * (math.e - 1)} / sum(exp(-(q - {c('reg')}))), 6) as z from {_shifted(_DENSE)}")
def m3_shift_harm(spark, sf_dir):
    found, spec = _dense(spark, sf_dir)
    return z6(estimate.estimate_harmonic_shifted(discretize.shift_round_registers(found, spec), spec))


@query("select cast(0 as bigint) as violations")
def m3_registers_scan_eq_store(spark, sf_dir):
    """Registers that differ when items are rounded before, and registers after, the maximum."""
    spec = spec_at(sf_dir, init="none")
    scan = discretize.scan_rounded(_orderkeys(spark, sf_dir), "l_orderkey", spec=spec).withColumnRenamed("q", "qs")
    store = discretize.shift_round_registers(rg.registers(_orderkeys(spark, sf_dir), "l_orderkey", spec=spec), spec)
    return scan.join(store, "reg", "full").where("not (q <=> qs)").agg(F.count("*").alias("violations"))


@query(f"select cast(reg as bigint) as reg, round({c('reg')}, 9) as c, cast(q as bigint) as q, round(q - {c('reg')}, 9) as value from {_shifted(_DENSE)}")
def m3_offsets(spark, sf_dir):
    """Each register's offset, beside the integer that it holds for the order keys and the value this stands for."""
    found, spec = _dense(spark, sf_dir)
    offset = hashing.offset(spec, F.col("reg"))
    held = discretize.shift_round_registers(found, spec)
    return held.select(F.col("reg").cast("long").alias("reg"), F.round(offset, 9).alias("c"), F.col("q").cast("long").alias("q"), F.round(F.col("q").cast("double") - offset, 9).alias("value"))


@query(harm(_DENSE, K * K))
def m4_harm(spark, sf_dir):
    return z6(estimate.estimate_harmonic(*_dense(spark, sf_dir)))


@query(harm(_FULL, K_FULL))
def m4_harm_full(spark, sf_dir):
    return z6(estimate.estimate_harmonic(*_full(spark, sf_dir)))


@query(harm(_DENSE, K * (K - 1)))
def m4_harm_debiased(spark, sf_dir):
    return z6(estimate.estimate_harmonic(*_dense(spark, sf_dir), debias=True))


@query(harm(_USER_DENSE, K * K, "day"))
def m4_harm_by_group(spark, sf_dir):
    return z6(estimate.estimate_harmonic(*_dense_days(spark, sf_dir), by=["day"]))


_EXPECTED = f"({float(K)} * (1 - pow(1 - 1.0::double / {K}, exp((lo + hi) / 2) + 1)) / (exp((lo + hi) / 2) + 1))"


@query(
    f"with recursive m as (select avg({e('w')}) as mean from {_DENSE}), b(i, lo, hi, mean) as (select 0, -20.0::double, 60.0::double, mean from m union all "
    f"select i + 1, case when {_EXPECTED} > mean then (lo + hi) / 2 else lo end, case when {_EXPECTED} > mean then hi else (lo + hi) / 2 end, mean from b where i < 60) "
    "select round(exp((lo + hi) / 2), 3) as z from b where i = 60"
)
def m15_harm_inverted(spark, sf_dir):
    return estimate.estimate_harmonic_inverted(*_dense(spark, sf_dir)).select(F.round("z", 3).alias("z"))


def _eps_values() -> str:
    return "(values " + ", ".join(f"({v}::double)" for v in EPS) + ") v(eps)"


def _rounded_sql(rounding: str, answer: str) -> str:
    return f"select eps, {answer} as z from (select eps, {rounding} as m from (select {x('w')} as x from {_DENSE}) cross join {_eps_values()}) group by eps"


def _rounded(spark, sf_dir, mode, kind):
    found, spec = _dense(spark, sf_dir)
    parts = [z6(estimate.estimate_rounded(discretize.round_registers(found, v, spec, mode), v, spec, kind=kind)).select(F.lit(v).alias("eps"), "z") for v in EPS]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


_GEO_M = f"round({K} * exp(avg(m * eps) - {EULER_GAMMA}), 6)"


@query(_rounded_sql("floor(x / eps + 0.5::double)", _GEO_M))
def m5_round_nearest(spark, sf_dir):
    return _rounded(spark, sf_dir, "nearest", "geometric")


@query(_rounded_sql("floor(x / eps)", _GEO_M))
def m5_round_floor(spark, sf_dir):
    return _rounded(spark, sf_dir, "floor", "geometric")


@query(_rounded_sql("floor(x / eps + 0.5::double)", f"round({K * K} / sum(exp(-m * eps)), 6)"))
def m5_round_harm(spark, sf_dir):
    return _rounded(spark, sf_dir, "nearest", "harmonic")


_KEY_DRAWS = f"(select {w('o_orderkey')} as w from (select distinct o_orderkey from orders where o_orderkey is not null))"


def _key_draws(spark, sf_dir):
    return rg.items(load(spark, sf_dir, "orders"), "o_orderkey").distinct().select(hashing.draw(SketchSpec(), F.col("item")).alias("w"))


@query(
    f"with seen as (select floor({x('w')} * 4) / 4 as x, count(*) as items from {_KEY_DRAWS} group by all), placed as (select x, items, round(coalesce(sum(items) over (order by x rows between unbounded preceding and 1 preceding), 0)::double / (sum(items) over ())::double, 9) as below from seen) "
    "select x, mu, items, below, round(exp(-exp(-(x - mu))), 9) as cdf, round(exp(-exp(-(x - mu)) - (x - mu)), 9) as pdf from placed cross join (values (0.0::double), (1.0::double), (2.5::double)) m(mu)"
)
def m6_gumbel_table(spark, sf_dir):
    """Distribution and density at the quarters that the order keys' draws fall in, with the draws in each quarter and
    the share of those below it (the distribution at mu = 0)."""
    mus = spark.createDataFrame([(0.0,), (1.0,), (2.5,)], "mu double")
    x_, mu = F.col("x"), F.col("mu")
    draws = _key_draws(spark, sf_dir).select((F.floor(gumbel.gumbel_from_hash(F.col("w"), 52) * 4) / 4.0).alias("x"))
    before = Window.orderBy("x").rowsBetween(Window.unboundedPreceding, -1)  # a row for each quarter, some 80 in all
    below = F.coalesce(F.sum("items").over(before), F.lit(0)).cast("double") / F.sum("items").over(Window.partitionBy()).cast("double")
    placed = draws.groupBy("x").agg(F.count("*").alias("items")).select("x", "items", F.round(below, 9).alias("below"))
    return placed.crossJoin(F.broadcast(mus)).select("x", "mu", "items", "below", F.round(gumbel.gumbel_cdf(x_, mu), 9).alias("cdf"), F.round(gumbel.gumbel_pdf(x_, mu), 9).alias("pdf"))


@query(
    f"with seen as (select n, count(*) as groups, round(avg({x('w')}), 4) as seen_mean, round(var_pop({x('w')}), 4) as seen_variance, round(avg({e('w')}), 4) as seen_mean_exp_neg, round(var_pop({e('w')}), 4) as seen_variance_exp_neg from {GROUPS} group by n), "
    "grid as (select i * 0.001::double - 6 as z from range(46000) t(i)), law as (select n, ln(n) + z as x, exp(-exp(-z) - z) as f from seen cross join grid), "
    "laws as (select n, round(ln(n), 9) as mu, round(sum(x * f) * 0.001::double, 4) as mean, round(sum(x * x * f) * 0.001::double - pow(sum(x * f) * 0.001::double, 2), 4) as variance, round(sum(exp(-x) * f) * 0.001::double, 4) as mean_exp_neg, "
    "round(sum(exp(-2 * x) * f) * 0.001::double - pow(sum(exp(-x) * f) * 0.001::double, 2), 4) as variance_exp_neg from law group by n) "
    "select n, groups, mu, mean, variance, mean_exp_neg, variance_exp_neg, seen_mean, seen_variance, seen_mean_exp_neg, seen_variance_exp_neg from laws join seen using (n)"
)
def m6_gumbel_moments(spark, sf_dir):
    """The closed moments at mu = ln n, for the numbers n of orders that customers have (the oracle integrates the
    density), beside the moments of these customers' greatest draws."""
    x_, e_ = gumbel.gumbel_from_hash(F.col("w"), 52), gumbel.exponential_from_hash(F.col("w"), 52)
    measured = {"seen_mean": F.avg(x_), "seen_variance": F.var_pop(x_), "seen_mean_exp_neg": F.avg(e_), "seen_variance_exp_neg": F.var_pop(e_)}
    seen = customer_groups(spark, sf_dir).groupBy("n").agg(F.count("*").alias("groups"), *[F.round(v, 4).alias(a) for a, v in measured.items()])
    closed = gumbel.moment_columns(F.ln("n"))
    return seen.select("n", "groups", F.round(F.ln("n"), 9).alias("mu"), *[F.round(v, 4).alias(a) for a, v in closed.items()], *measured)


@query(
    f"select cast(floor(t * 100) as bigint) as percent, mu, count(*) as items, round(avg(t), 6) as t, round(avg(x), 6) as x, round(avg(exp(-exp(-(x - mu)))), 6) as back, max(abs(exp(-exp(-(x - mu))) - t)) < 1e-12 as near "
    f"from (select t, mu, mu - ln(-ln(t)) as x from (select (cast(w as double) + 0.5::double) / {WORD} as t from {_KEY_DRAWS}) cross join (values (0.0::double), (3.0::double)) m(mu)) group by all"
)
def m6_quantile_roundtrip(spark, sf_dir):
    """The order keys' uniforms t, their quantiles x and the distribution there, which is t again: means by percent of t."""
    mus = spark.createDataFrame([(0.0,), (3.0,)], "mu double")
    t = _key_draws(spark, sf_dir).select(((F.col("w").cast("double") + 0.5) / float(1 << 52)).alias("t")).crossJoin(F.broadcast(mus))
    q = t.withColumn("q", gumbel.gumbel_quantile(F.col("t"), F.lit(0.0)) + F.col("mu")).withColumn("back", gumbel.gumbel_cdf(F.col("q"), F.col("mu")))
    means = [F.round(F.avg(v), 6).alias(a) for a, v in (("t", "t"), ("x", "q"), ("back", "back"))]
    return q.groupBy(F.floor(F.col("t") * 100).alias("percent"), "mu").agg(F.count("*").alias("items"), *means, (F.max(F.abs(F.col("back") - F.col("t"))) < 1e-12).alias("near"))


_COUNTS = f"(select reg, coalesce(n_i, 0) as n_i from (select i as reg from range({K}) t(i)) left join (select {r('o_orderkey')} as reg, count(distinct o_orderkey) as n_i from orders group by all) using (reg))"


@query(f"select reg, n, round(x, 9) as x, round(pow(exp(-exp(-x)), n), 6) as by_product, round(exp(-exp(-(x - ln(n)))), 6) as by_shift from (select reg, n, {x('w')} as x from {regs('orders', 'o_orderkey')} join (select reg, n_i as n from {_COUNTS}) using (reg))")
def m7_max_stability(spark, sf_dir):
    """G(x)^n = G(x - ln n), at the order keys' registers: x what one holds, n the distinct keys it has seen."""
    spec, keys = spec_at(sf_dir), load(spark, sf_dir, "orders")
    held = discretize.real_registers(rg.registers(keys, "o_orderkey", spec=spec), spec).join(rg.substream_counts(keys, "o_orderkey", spec), "reg")
    g = held.select(F.col("reg").cast("long").alias("reg"), F.col("n_i").alias("n"), "x")
    return g.select("reg", "n", F.round("x", 9).alias("x"), F.round(F.pow(gumbel.gumbel_cdf(F.col("x")), F.col("n")), 6).alias("by_product"), F.round(gumbel.max_law_cdf(F.col("x"), F.col("n")), 6).alias("by_shift"))


def _shift_round_sql(value: str) -> str:
    return f"floor({value} + c) - c"


@query(
    f"select count(*) as pairs, count(*) filter (where greatest(fa, fb) <> fm) as not_commuting, count(*) filter (where a - fa < 0 or a - fa >= 1 + 1e-12) as out_of_unit, abs(avg(a - fa) - 0.5) < 0.02 as mean_near_half from (select a, {_shift_round_sql('a')} as fa, {_shift_round_sql('b')} as fb, {_shift_round_sql('greatest(a, b)')} as fm "
    f"from (select {x('wa')} as a, {x('wb')} as b, c from (select {w('o_orderkey')} as wa, {w('o_custkey')} as wb, {c(r('o_orderkey', 4096))} as c from orders where o_orderkey is not null and o_custkey is not null)))"
)
def m8_shift_round_props(spark, sf_dir):
    """Shift-rounding commutes with the maximum and moves a value down by less than one, by 1/2 on average: for the
    draws of each order's key and customer, under the offset of the key's register."""
    spec, key = SketchSpec(k=4096), F.col("o_orderkey")
    pairs = load(spark, sf_dir, "orders").where("o_orderkey is not null and o_custkey is not null")
    at = pairs.select(hashing.register(spec, key).alias("reg"), gumbel.gumbel_from_hash(hashing.draw(spec, key), 52).alias("a"), gumbel.gumbel_from_hash(hashing.draw(spec, F.col("o_custkey")), 52).alias("b"))
    at = at.withColumn("c", hashing.offset(spec, F.col("reg")))
    fa, fb, fm = (gumbel.shift_round(v, F.col("c")) for v in (F.col("a"), F.col("b"), F.greatest("a", "b")))
    gap = F.col("a") - fa
    return at.select((F.greatest(fa, fb) != fm).alias("bad"), ((gap < 0) | (gap >= 1 + 1e-12)).alias("off"), gap.alias("gap")).agg(
        F.count("*").alias("pairs"), F.count_if("bad").alias("not_commuting"), F.count_if("off").alias("out_of_unit"), (F.abs(F.avg("gap") - 0.5) < 0.02).alias("mean_near_half")
    )


@query(f"select reg, n_i from {_COUNTS}")
def m9_substreams(spark, sf_dir):
    return rg.substream_counts(load(spark, sf_dir, "orders"), "o_orderkey", spec_at(sf_dir)).select(F.col("reg").cast("long").alias("reg"), "n_i")


@query(
    f"select round(sum(1.0::double / (n_i + 1)), 6) as sum_inverse, round(sum(ln(n_i + 1)), 6) as sum_log, round(sum(-ln(n_i + 1)), 6) as log_product_inverse, round({K} / (sum(n_i) / {float(K)} + 1), 6) as expected_inverse, round({K} * ln(sum(n_i) / {float(K)} + 1), 6) as expected_log from {_COUNTS}"
)
def m10_functionals(spark, sf_dir):
    """Sums and (the logarithm of) products of f(n_i), beside k f(n/k)."""
    k = spec_at(sf_dir).k
    n = rg.substream_counts(load(spark, sf_dir, "orders"), "o_orderkey", spec_at(sf_dir))
    inverse, log = 1 / (F.col("n_i") + 1), F.log1p("n_i")
    mean = F.sum("n_i") / F.lit(float(k))
    cols = {"sum_inverse": F.sum(inverse), "sum_log": F.sum(log), "log_product_inverse": F.sum(F.ln(inverse)), "expected_inverse": k / (mean + 1), "expected_log": k * F.log1p(mean)}
    return n.agg(*[F.round(v, 6).alias(a) for a, v in cols.items()])


_GRID_EPS = (0.5, 0.25, 0.1, 0.05, 0.02, 0.01)


@query(
    "with grid as (select eps, cast(ceil(1 / (eps * eps) - 1e-9) as bigint) as k_order, cast(ceil(pow(pi() / eps, 2) - 1e-9) as bigint) as k_proved from (values " + ", ".join(f"({v}::double)" for v in _GRID_EPS) + ") v(eps)), "
    f"sizes as (select k_order as k from grid union select k_proved from grid), keys as (select distinct o_orderkey from orders where o_orderkey is not null), "
    f"drawn as (select {r('o_orderkey', 1 << 32)} as h, {w('o_orderkey')} as w from keys), starts as (select i, {w('i', tag='#reg')} as w from range((select max(k) from sizes)) t(i)), "
    "regs as (select k, reg, min(w) as w from (select k, h % k as reg, w from drawn cross join sizes union all select k, i, w from starts join sizes on i < k) group by k, reg), "
    f"z as (select k, k * exp(avg({x('w')}) - {EULER_GAMMA}) as z from regs group by k), n as (select count(*)::double as n from keys) "
    "select eps, k_order, k_proved, round((a.z - n) / nullif(n, 0), 6) as error_order, round((b.z - n) / nullif(n, 0), 6) as error_proved, n >= pow(k_order, 1.5::double) as regime_order, n >= pow(k_proved, 1.5::double) as regime_proved "
    "from grid join z a on k_order = a.k join z b on k_proved = b.k cross join n"
)
def m11_k_for_eps(spark, sf_dir):
    """k for an error eps, and the relative errors (null without keys) that sketches of the order keys have at these k."""
    rows = [(v, registers_for(v), registers_for(v, "proved")) for v in _GRID_EPS]
    items = rg.items(load(spark, sf_dir, "orders"), "o_orderkey")
    runs = accuracy.seeded_registers(accuracy.seeded_draws(items, 1), sorted({k for row in rows for k in row[1:]}), 1)
    z = runs.groupBy("k").agg(accuracy.geometric(F.col("k")).alias("z"))
    n = items.agg(F.count_distinct("item").cast("double").alias("n"))
    out = spark.createDataFrame(rows, "eps double, k_order long, k_proved long").crossJoin(F.broadcast(n))
    for what in ("order", "proved"):
        k = F.col(f"k_{what}")
        out = out.join(F.broadcast(z.select(F.col("k").cast("long").alias(f"k_{what}"), F.col("z").alias(f"z_{what}"))), f"k_{what}")
        out = out.withColumns({f"error_{what}": F.round(F.try_divide(F.col(f"z_{what}") - F.col("n"), F.col("n")), 6), f"regime_{what}": F.col("n") >= F.pow(k.cast("double"), F.lit(1.5))})
    return out.select("eps", "k_order", "k_proved", "error_order", "error_proved", "regime_order", "regime_proved")


@query(geo(_DENSE, K))
def m13_merge(spark, sf_dir):
    """Sketches of three overlapping parts, merged (one of them twice), then seeded."""
    spec = spec_at(sf_dir)
    keys = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber")
    parts = [rg.registers(keys.where(cond), "l_orderkey", spec=spec) for cond in ("l_linenumber <= 2", "l_linenumber between 2 and 5", "l_linenumber > 4")]
    merged = rg.merge(*[(p, spec) for p in [*parts, parts[0]]])
    return z6(estimate.estimate_geometric(rg.with_seed_draws(merged, spec), spec))


@query(f"select round(-{K} * ln(1 - count(*) / {float(K)}), 6) as z from {regs('events', 'user_id')}")
def m14_linear_counting(spark, sf_dir):
    spec = spec_at(sf_dir, init="none")
    return z6(estimate.estimate_small(rg.registers(load(spark, sf_dir, "events"), "user_id", spec=spec), spec))


_COPIES = ("s1", "s2", "s3", "s4", "s5")


@query("select round(quantile_cont(z, 0.5), 6) as z from (" + " union all ".join(geo(seeded(regs("lineitem", "l_orderkey", seed=f"'{s}'"), seed=f"'{s}'"), K) for s in _COPIES) + ")")
def m16_median_copies(spark, sf_dir):
    out = None
    for s in _COPIES:
        one = z6(estimate.estimate_geometric(*_dense(spark, sf_dir, seed=s)))
        out = one if out is None else out.union(one)
    return z6(estimate.median_estimate(out))


@query("select * from (values ('averaged_geometric', true), ('averaged_harmonic', true), ('averaged_shifted', true), ('full_geometric', true)) v(method, inside)")
def fast_family(spark, sf_dir):
    """The xxhash64 family against exact counts: each answer within five standard errors."""
    spec = spec_at(sf_dir, family="fast")
    keys = _orderkeys(spark, sf_dir)
    dense = rg.with_seed_draws(rg.registers(keys, "l_orderkey", spec=spec), spec)
    full = SketchSpec(k=K_FULL, layout="full", family="fast")
    answers = {
        "averaged_geometric": (estimate.estimate_geometric(dense, spec), 1.2825 / spec.k**0.5),
        "averaged_harmonic": (estimate.estimate_harmonic(dense, spec), 1 / spec.k**0.5),
        "averaged_shifted": (estimate.estimate_shifted(discretize.shift_round_registers(dense, spec), spec), 1.3146 / spec.k**0.5),
        "full_geometric": (estimate.estimate_geometric(rg.full_registers(keys, "l_orderkey", spec=full), full), 1.2825 / full.k**0.5),
    }
    n = keys.agg(F.count_distinct("l_orderkey").alias("n"))
    out = None
    for method, (z, scale) in answers.items():
        one = z.crossJoin(n).select(F.lit(method).alias("method"), (F.abs(F.col("z") - F.col("n")) <= 5 * scale * F.col("n") + spec.k).alias("inside"))
        out = one if out is None else out.union(one)
    return out


@query(f"with {fast_dense('lineitem', 'l_orderkey')} {geo('(select w / 2048.0::double as w from dense)', K)}")
def fast_geo(spark, sf_dir):
    """The default way at scale: averaged registers by xxhash64, geometric answer."""
    return z6(estimate.estimate_geometric(*_dense(spark, sf_dir, family="fast")))
