"""Accuracy and cost measures, the figure's laws, and tests of the theorems."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from evsketch.functions import gumbel
from evsketch.functions.gumbel import EULER_GAMMA
from evsketch.operators import accuracy as ac
from evsketch.operators import baselines as bl
from evsketch.operators import discretize, estimate
from evsketch.operators import registers as rg
from evsketch.sources.tables import load
from evsketch.spec import SketchSpec
from evsketch.workloads.common import K, K_FULL, SEEDS, WORD, c, e, query, regs, seeded, spec_at, w, x
from evsketch.workloads.methods import EPS, GROUPS, customer_groups, z6

KS = (16, 64, 256, 1024)
#: Key bounds of the sweep over n; 0 is the whole table.
NS = (64, 512, 4096, 15000, 0)


def _items(spark, sf_dir, table="orders", col="o_orderkey"):
    return rg.items(load(spark, sf_dir, table), col)


_S = "'s' || cast(seed as varchar)"


def _draws(table="orders", col="o_orderkey"):
    m = f"md5({_S} || ':' || cast({col} as varchar))"
    return f"(select seed, cast('0x' || substr(m, 17, 8) as bigint) as h, cast('0x' || substr(m, 1, 13) as bigint) as w, item from (select seed, {col} as item, {m} as m from (select distinct {col} from {table}) cross join range(1, {SEEDS + 1}) s(seed)))"


def _runs(draws: str, ks, dense=True) -> str:
    sizes = "(values " + ", ".join(f"({k})" for k in ks) + ") v(k)"
    start = f" union all select k, seed, reg, cast('0x' || substr(md5({_S} || '#reg:' || cast(reg as varchar)), 1, 13) as bigint) as w from {sizes} cross join range(1, {SEEDS + 1}) s(seed) cross join range({max(ks)}) g(reg) where reg < k" if dense else ""
    return f"(select k, seed, reg, min(w) as w from (select k, seed, h % k as reg, w from {draws} cross join {sizes}{start}) group by all)"


def _full_runs(table="events", col="user_id", k=K_FULL):
    return f"(select seed, reg, min(cast('0x' || substr(md5({_S} || '/' || cast(reg as varchar) || ':' || cast({col} as varchar)), 1, 13) as bigint)) as w from (select distinct {col} from {table}) cross join range(1, {SEEDS + 1}) s(seed) cross join range({k}) g(reg) group by all)"


def _off() -> str:
    return f"(cast('0x' || substr(md5({_S} || '#off:' || cast(reg as varchar)), 1, 13) as bigint) / {WORD})"


_SUMMARY = "round(avg(z / n), 6) as mean_ratio, round(avg(z / n) - 1, 6) as bias, round(sqrt(max(k)) * stddev_samp(z / n), 6) as norm_std, round(avg(case when abs(z - n) / n <= pi() / sqrt(k) then 1.0::double else 0.0::double end), 6) as coverage"
_GEO = f"k * exp(avg({x('w')}) - {EULER_GAMMA})"
_HARM = f"k * k / sum({e('w')})"


@query(
    f"select method, k, {_SUMMARY} from (select 'geometric' as method, k, seed, {_GEO} as z from {_runs(_draws(), KS)} group by k, seed union all select 'harmonic', k, seed, {_HARM} from {_runs(_draws(), KS)} group by k, seed) cross join (select count(distinct o_orderkey)::double as n from orders) group by method, k"
)
def a_error_sweep_k(spark, sf_dir):
    """Error against k over many seeds: std falls as 1/sqrt(k)."""
    items = _items(spark, sf_dir)
    runs = ac.seeded_registers(ac.seeded_draws(items, SEEDS), KS, SEEDS)
    k = F.col("k")
    z = runs.groupBy("k", "seed").agg(ac.geometric(k).alias("geometric"), ac.harmonic(k * k).alias("harmonic"))
    z = z.select("k", "seed", F.expr("stack(2, 'geometric', geometric, 'harmonic', harmonic) as (method, z)"))
    n = items.agg(F.count_distinct("item").cast("double").alias("n"))
    return ac.summary(z.crossJoin(F.broadcast(n)), ["method", "k"], F.col("k").cast("double"))


_NSQL = " union all ".join(
    f"select {n} as below, z, n, z >= 512 as in_regime, seed, 64 as k from (select seed, {_GEO} as z from {_runs('(select seed, h, w from ' + _draws() + (f' where item < {n})' if n else ')'), (64,))} group by k, seed) cross join (select count(distinct o_orderkey)::double as n from orders{f' where o_orderkey < {n}' if n else ''})" for n in NS
)


@query(f"select below, {_SUMMARY}, count(*) filter (where in_regime) as runs_in_regime from ({_NSQL}) group by below")
def a_error_sweep_n(spark, sf_dir):
    """Error against n at k = 64, crossing n = k**1.5 = 512, up to the whole table (below = 0)."""
    out, orders = None, load(spark, sf_dir, "orders")
    for n in NS:
        items = rg.items(orders.where(F.col("o_orderkey") < n) if n else orders, "o_orderkey")
        runs = ac.seeded_registers(ac.seeded_draws(items, SEEDS), (64,), SEEDS)
        z = runs.groupBy("k", "seed").agg(ac.geometric(F.col("k")).alias("z"))
        exact = items.agg(F.count_distinct("item").cast("double").alias("n"))
        z = z.crossJoin(F.broadcast(exact)).withColumn("below", F.lit(n))
        flagged = z.groupBy("below").agg(F.sum(F.col("z").__ge__(512.0).cast("long")).alias("runs_in_regime"))
        one = ac.summary(z, ["below"], F.col("k").cast("double")).join(flagged, "below")
        out = one if out is None else out.union(one)
    return out


_RANK = "case when w = 0 then 53 else cast(bit_count(xor(w, w - 1)) as integer) end"
_R64 = _runs(_draws(), (64,))
_RANKS = f"(select seed, h % 64 as reg, max({_RANK}) as rank from {_draws()} group by all)"
_FULLR = _full_runs()
_COMPARE = " union all ".join(
    f"select '{items}' as items, '{m}' as method, 64 as k, seed, z from (select seed, {z} as z from {source} group by seed)"
    for items, m, z, source in (
        ("orders", "averaged_geometric", f"64 * exp(avg({x('w')}) - {EULER_GAMMA})", _R64),
        ("orders", "averaged_shifted", f"64 * exp(avg(floor({x('w')} + {_off()}) - {_off()}) + 0.5::double - {EULER_GAMMA})", _R64),
        ("orders", "averaged_harmonic", f"64 * 64 / sum({e('w')})", _R64),
        ("orders", "averaged_rounded", f"64 * exp(avg(floor({x('w')} / 0.5::double + 0.5::double) * 0.5::double) - {EULER_GAMMA})", _R64),
        ("orders", "loglog", f"{bl.loglog_alpha(64) * 64} * pow(2.0::double, sum(rank) / 64.0::double)", _RANKS),
        ("orders", "hyperloglog", f"{bl.hll_alpha(64) * 64 * 64} / (sum(pow(2.0::double, -rank)) + 64 - count(*))", _RANKS),
        ("users", "full_geometric", f"exp(avg({x('w')}) - {EULER_GAMMA})", _FULLR),
        ("users", "full_shifted", f"exp(avg(floor({x('w')} + {_off()}) - {_off()}) + 0.5::double - {EULER_GAMMA})", _FULLR),
        ("users", "full_harmonic", f"64 / sum({e('w')})", _FULLR),
    )
)


@query(f"select items, method, {_SUMMARY} from (select r.*, n from ({_COMPARE}) r join (select 'orders' as items, count(distinct o_orderkey)::double as n from orders union all select 'users', count(distinct user_id)::double from events) using (items)) group by items, method")
def a_method_compare(spark, sf_dir):
    """All methods and the trailing-zero baselines at k = 64 over the same seeds."""
    orders, users = _items(spark, sf_dir), _items(spark, sf_dir, "events", "user_id")
    draws = ac.seeded_draws(orders, SEEDS)
    regs_ = ac.seeded_registers(draws, (64,), SEEDS)
    xc, off = ac.x_of(F.col("w")), ac.offset(F.col("seed"), F.col("reg"))
    shifted = F.avg(F.floor(xc + off).cast("double") - off) + 0.5 - EULER_GAMMA
    averaged = regs_.groupBy("seed").agg(
        ac.geometric(F.lit(64.0)).alias("averaged_geometric"), (64 * F.exp(shifted)).alias("averaged_shifted"), ac.harmonic(F.lit(4096.0)).alias("averaged_harmonic"), (64 * F.exp(F.avg(F.floor(xc / 0.5 + 0.5) * 0.5) - EULER_GAMMA)).alias("averaged_rounded")
    )
    ranks = draws.groupBy("seed", F.pmod("h", F.lit(64)).alias("reg")).agg(F.max(bl.rank(F.col("w"), 52)).alias("rank"))
    spec = SketchSpec(k=64)
    trailing = bl.loglog(ranks, spec, ["seed"]).withColumnRenamed("z", "loglog").join(bl.hyperloglog(ranks, spec, ["seed"]).withColumnRenamed("z", "hyperloglog"), "seed")
    full = ac.seeded_full(users, K_FULL, SEEDS).groupBy("seed").agg(ac.geometric(F.lit(1.0)).alias("full_geometric"), F.exp(shifted).alias("full_shifted"), ac.harmonic(F.lit(64.0)).alias("full_harmonic"))

    def long(df, items):
        names = [n for n in df.columns if n != "seed"]
        return df.select(F.lit(items).alias("items"), "seed", F.expr(f"stack({len(names)}, " + ", ".join(f"'{n}', {n}" for n in names) + ") as (method, z)"))

    z = long(averaged, "orders").union(long(trailing, "orders")).union(long(full, "users"))
    n = orders.agg(F.lit("orders").alias("items"), F.count_distinct("item").cast("double").alias("n")).union(users.agg(F.lit("users").alias("items"), F.count_distinct("item").cast("double").alias("n")))
    return ac.summary(z.join(F.broadcast(n), "items"), ["items", "method"], F.lit(64.0))


@query(
    f"select round(avg(x) - ln(n), 6) as mean_less_log, round(var_samp(x), 6) as variance, round(avg(s) - ln(n), 6) as shifted_mean_less_log, round(var_samp(s), 6) as shifted_variance from (select {x('w')} as x, floor({x('w')} + {_off()}) - {_off()} as s from {_FULLR}) cross join (select count(distinct user_id)::double as n from events) group by n"
)
def a_register_moments(spark, sf_dir):
    """Registers about ln n: gamma and pi^2/6; shift-rounded: gamma - 1/2 and pi^2/6 + 1/12."""
    users = _items(spark, sf_dir, "events", "user_id")
    x_, off = ac.x_of(F.col("w")), ac.offset(F.col("seed"), F.col("reg"))
    held = ac.seeded_full(users, K_FULL, SEEDS).select(x_.alias("x"), (F.floor(x_ + off).cast("double") - off).alias("s"))
    n = F.broadcast(users.agg(F.count_distinct("item").cast("double").alias("n")))
    rows = held.crossJoin(n).groupBy("n").agg(*[F.round(f, 6).alias(a) for a, f in (("mean_less_log", F.avg("x") - F.ln("n")), ("variance", F.var_samp("x")), ("shifted_mean_less_log", F.avg("s") - F.ln("n")), ("shifted_variance", F.var_samp("s")))])
    return rows.drop("n")


@query("select * from (values ('full', true), ('averaged', true)) v(layout, holds)")
def a_coverage(spark, sf_dir):
    """Shares of runs inside pi/sqrt(k): 5/6 or more with all registers, 2/3 or more when averaged."""
    got = a_method_compare(spark, sf_dir)
    full = got.where("method = 'full_geometric'").select(F.lit("full").alias("layout"), (F.col("coverage") >= 5 / 6).alias("holds"))
    return full.union(got.where("method = 'averaged_geometric'").select(F.lit("averaged"), F.col("coverage") >= 2 / 3))


_DENSE = seeded(regs("lineitem", "l_orderkey"))


@query(
    "select eps, round(exp(avg(floor(x / eps + 0.5::double) * eps - x)), 9) as nearest, round(exp(avg(floor(x / eps) * eps - x)), 9) as below, true as nearest_in_half, true as below_in_whole from "
    + f"(select {x('w')} as x from {_DENSE}) cross join (values " + ", ".join(f"({v}::double)" for v in EPS) + ") v(eps) group by eps"
)
def a_distortion(spark, sf_dir):
    """Z'/Z of rounded registers: within exp(eps/2) for nearest, exp(eps) for floor."""
    spec = spec_at(sf_dir)
    dense = rg.with_seed_draws(rg.registers(load(spark, sf_dir, "lineitem"), "l_orderkey", spec=spec), spec)
    sizes = F.broadcast(spark.createDataFrame([(v,) for v in EPS], "eps double"))
    xs = discretize.real_registers(dense, spec).crossJoin(sizes)
    near, low = F.exp(F.avg(F.floor(F.col("x") / F.col("eps") + 0.5) * F.col("eps") - F.col("x"))), F.exp(F.avg(F.floor(F.col("x") / F.col("eps")) * F.col("eps") - F.col("x")))
    out = xs.groupBy("eps").agg(F.round(near, 9).alias("nearest"), F.round(low, 9).alias("below"))
    return out.withColumns({"nearest_in_half": F.abs(F.ln("nearest")) <= F.col("eps") / 2 + 1e-9, "below_in_whole": F.abs(F.ln("below")) <= F.col("eps") + 1e-9})


_SPLIT = f"(select seed, reg, coalesce(c, 0) as c from (select seed, reg from range(1, {SEEDS + 1}) s(seed) cross join range(64) g(reg)) left join (select seed, h % 64 as reg, count(*) as c from {_draws()} group by all) using (seed, reg))"


@query(f"select seed, round(sum(ln(c + 1)), 6) as y, sum(ln(c + 1)) <= 64 * ln(sum(c) / 64.0::double + 1) + 1e-9 as under_upper, sum(ln(c + 1)) >= 64 * ln(sum(c) / 64.0::double) - ln(6.0::double) as over_lower from {_SPLIT} group by seed")
def a_tail_lemma(spark, sf_dir):
    """Log-sums of the sub-streams: always under k ln(n/k + 1), over k ln(n/k) - ln 6 in 5/6 of splits."""
    counts = ac.seeded_draws(_items(spark, sf_dir), SEEDS).groupBy("seed", F.pmod("h", F.lit(64)).alias("reg")).agg(F.count("*").alias("c"))
    every = spark.range(1, SEEDS + 1).select(F.col("id").cast("int").alias("seed")).withColumn("reg", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(63).cast("long"))))
    c_ = every.join(counts, ["seed", "reg"], "left").select("seed", F.coalesce("c", F.lit(0)).alias("c"))
    y, n = F.sum(F.ln(F.col("c") + 1)), F.sum("c")
    return c_.groupBy("seed").agg(F.round(y, 6).alias("y"), (y <= 64 * F.ln(n / 64.0 + 1) + 1e-9).alias("under_upper"), (y >= 64 * F.ln(n / 64.0) - math.log(6.0)).alias("over_lower")).select(F.col("seed").cast("long").alias("seed"), "y", "under_upper", "over_lower")


@query(f"select round(max(greatest(abs(cd - f), abs(cd - 1.0::double / total - f))), 6) as distance from (select cume_dist() over (order by x) as cd, count(*) over () as total, exp(-exp(-(x - ln(n)))) as f from (select {x('w')} as x from {_FULLR}) cross join (select count(distinct user_id)::double as n from events))")
def a_max_law_distance(spark, sf_dir):
    """Largest gap between the empirical law of maxima over n items and Gumbel(ln n)."""
    from pyspark.sql import Window

    users = _items(spark, sf_dir, "events", "user_id")
    n = F.broadcast(users.agg(F.count_distinct("item").cast("double").alias("n")))
    xs = ac.seeded_full(users, K_FULL, SEEDS).select(ac.x_of(F.col("w")).alias("x")).crossJoin(n)
    whole = Window.orderBy("x")  # a sample of seeds times registers, whatever the input
    rows = xs.select(F.cume_dist().over(whole).alias("cd"), gumbel.gumbel_cdf(F.col("x"), F.ln("n")).alias("f"), F.count("*").over(Window.partitionBy()).alias("total"))
    return rows.agg(F.round(F.max(F.greatest(F.abs(F.col("cd") - F.col("f")), F.abs(F.col("cd") - 1 / F.col("total") - F.col("f")))), 6).alias("distance"))


@query(
    f"with seen as (select n as k, count(*) as groups, round(avg(zeros) - log2(n), 6) as seen_geometric, round(avg({x('w')}) - ln(n), 6) as seen_gumbel from {GROUPS} group by n) "
    "select k, groups, round(sum(1 - pow(1 - pow(2.0::double, -j), k)) - ln(k) / ln(2.0::double), 6) as geometric, round(0.5772156649015329::double, 6) as gumbel, seen_geometric, seen_gumbel from seen cross join range(1, 80) t(j) group by k, groups, seen_geometric, seen_gumbel"
)
def a_smoothness(spark, sf_dir):
    """E[max] of k draws less log k: oscillates with log2 k for geometric draws, constant for Gumbel ones; for
    the numbers k of orders that customers have, beside the means over these customers."""
    k, log2 = F.col("k"), F.ln("k") / math.log(2.0)
    seen = customer_groups(spark, sf_dir).withColumnRenamed("n", "k").groupBy("k").agg(F.count("*").alias("groups"), F.avg("zeros").alias("zeros"), F.avg(ac.x_of(F.col("w"))).alias("x"))
    mean = F.aggregate(F.sequence(F.lit(1), F.lit(79)), F.lit(0.0), lambda total, j: total + 1 - F.pow(1 - F.pow(F.lit(2.0), -j), k))
    laws = F.round(mean - log2, 6).alias("geometric"), F.round(F.lit(EULER_GAMMA), 6).alias("gumbel")
    return seen.select("k", "groups", *laws, F.round(F.col("zeros") - log2, 6).alias("seen_geometric"), F.round(F.col("x") - F.ln("k"), 6).alias("seen_gumbel"))


_REACH = "(ceil(2 * ln(m) - 1e-9) + 4)"
_SPACE_SQL = {
    "bitmap": "universe",
    "optimal_bound": f"{math.log2(1 / 0.01) / 0.05**2} + log2(m)",
    "trailing_zeros": "400 * (ceil(log2(log2(m)) - 1e-9) + 1)",
    "real_registers": "64 * 400",
    "rounded_registers": f"400 * ceil(log2({_REACH} / 0.05::double) - 1e-9)",
    "shift_rounded_registers": f"400 * ceil(log2({_REACH}) - 1e-9)",
}


@query(
    "with seen as (" + " union all ".join(f"select '{v}' as item, count(distinct {v}) as n, max({v}) + 1 as universe, greatest(count(distinct {v}), 2)::double as m from orders" for v in ("o_orderkey", "o_custkey")) + ") "
    + " union all ".join(f"select item, n, universe, '{a}' as method, round(({v})::double, 3) as bits from seen" for a, v in _SPACE_SQL.items())
)
def c_space_table(spark, sf_dir):
    """Total bits at eps = 0.05, delta = 0.01 for both keys of the orders: n distinct ones, over the universe from 0 to the largest."""
    keys = ("o_orderkey", "o_custkey")
    seen = load(spark, sf_dir, "orders").agg(*[f(v).alias(f"{a}_{v}") for v in keys for a, f in (("n", F.count_distinct), ("max", F.max))])
    seen = seen.select(F.expr("stack(2, " + ", ".join(f"'{v}', n_{v}, max_{v} + 1" for v in keys) + ") as (item, n, universe)"))
    bits = ac.space_columns(0.05, 0.01, F.col("n"), F.col("universe"))
    every = F.explode(F.array(*[F.struct(F.lit(m).alias("method"), F.round(b, 3).alias("bits")) for m, b in bits])).alias("b")
    return seen.select("item", "n", "universe", every).select("item", "n", "universe", "b.method", "b.bits")


@query(f"select layout, k, rows_, case layout when 'full' then rows_ * k else rows_ end as updates from (values ('full', {K_FULL}), ('averaged', {K})) v(layout, k) cross join (select count(*) as rows_ from lineitem where l_orderkey is not null)")
def c_ops_table(spark, sf_dir):
    """Register updates of both layouts over one scan."""
    rows = load(spark, sf_dir, "lineitem").where("l_orderkey is not null").agg(F.count("*").alias("rows_"))
    layouts = spark.createDataFrame([("full", K_FULL), ("averaged", spec_at(sf_dir).k)], "layout string, k int")
    return layouts.crossJoin(F.broadcast(rows)).withColumn("updates", F.when(F.col("layout") == "full", F.col("rows_") * F.col("k")).otherwise(F.col("rows_")))


@query(
    f"select 'shift_rounded' as kind, 1.0::double as eps, cast(ceil(log2(max(q) - min(q) + 1)) as bigint) as bits from (select floor({x('w')} + {c('reg')}) as q from {_DENSE}) union all select 'rounded', eps, cast(ceil(log2(max(m) - min(m) + 1)) as bigint) from (select eps, floor(x / eps + 0.5::double) as m from (select {x('w')} as x from {_DENSE}) cross join (values "
    + ", ".join(f"({v}::double)" for v in EPS) + ") v(eps)) group by eps"
)
def c_register_bits(spark, sf_dir):
    """Bits that the integer registers of one sketch really span."""
    spec = spec_at(sf_dir)
    dense = rg.with_seed_draws(rg.registers(load(spark, sf_dir, "lineitem"), "l_orderkey", spec=spec), spec)
    width = lambda v: F.ceil(F.log2(F.max(v) - F.min(v) + 1)).cast("long").alias("bits")
    out = discretize.shift_round_registers(dense, spec).agg(width(F.col("q").cast("int"))).select(F.lit("shift_rounded").alias("kind"), F.lit(1.0).alias("eps"), "bits")
    for v in EPS:
        out = out.union(discretize.round_registers(dense, v, spec).agg(width(F.col("m").cast("int"))).select(F.lit("rounded"), F.lit(v), "bits"))
    return out


@query("select * from (values ('linear', true), ('rehash', true)) v(mode, near)")
def a_hash_independence(spark, sf_dir):
    """Registers of one item set under re-hashed and under linear hashes: variance near pi^2/6."""
    out = None
    spec = SketchSpec(k=512, layout="full", family="fast")
    for mode in ("linear", "rehash"):
        regs_ = rg.full_registers(load(spark, sf_dir, "orders").select("o_orderkey").distinct(), "o_orderkey", spec=spec, how="explode", mode=mode)
        one = discretize.real_registers(regs_, spec).agg(F.var_samp("x").alias("v")).select(F.lit(mode).alias("mode"), (F.abs(F.col("v") - gumbel.VARIANCE) < 0.5).alias("near"))
        out = one if out is None else out.union(one)
    return out


_FIG_K = (1, 2, 4, 8, 16, 32, 64)
_KV = "(values " + ", ".join(f"({k})" for k in _FIG_K) + ") v(k)"


@query(
    f"with seen as (select n as k, cast(zeros as bigint) as x, count(*) as n from {GROUPS} group by all), panel as (select k, groups, unnest(range(greatest(10, top) + 1)) as x from (select k, cast(sum(n) as bigint) as groups, max(x) as top from seen group by k)) "
    "select k, x, round(pow(1 - pow(2.0::double, -x - 1), k) - pow(1 - pow(2.0::double, -x), k), 9) as p, coalesce(n, 0) as n, groups from panel left join seen using (k, x)"
)
def w1_geom_max_law(spark, sf_dir):
    """Left panel: the law of the maximum of k geometric draws, for the numbers k of orders that customers have, beside
    these customers by the most trailing zeros of their orders (n of the groups)."""
    x_, k = F.col("x"), F.col("k")
    p = F.pow(1 - F.pow(F.lit(2.0), -x_ - 1), k) - F.pow(1 - F.pow(F.lit(2.0), -x_), k)
    seen = customer_groups(spark, sf_dir).groupBy(F.col("n").alias("k"), F.col("zeros").cast("long").alias("x")).agg(F.count("*").alias("n"))
    held = seen.groupBy("k").agg(F.map_from_entries(F.collect_list(F.struct("x", "n"))).alias("ns"), F.sum("n").alias("groups"), F.max("x").alias("top"))
    panel = held.withColumn("x", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest("top", F.lit(10).cast("long")))))
    return panel.select("k", "x", F.round(p, 9).alias("p"), F.coalesce(F.try_element_at("ns", x_), F.lit(0).cast("long")).alias("n"), "groups")


@query(f"select k, i, round(exp(-exp(-x + ln(k)) - x + ln(k)), 9) as f from (select i, -2.0::double + i * (12.0::double / 199) as x from range(200) t(i)) cross join {_KV}")
def w2_gumbel_max_law(spark, sf_dir):
    """Right panel: the density of the maximum of k Gumbel draws, shapes shifted by ln k."""
    ks = F.broadcast(spark.createDataFrame([(k,) for k in _FIG_K], "k int"))
    g = spark.range(200).select(F.col("id").alias("i"), (F.lit(-2.0) + F.col("id") * F.lit(12.0 / 199)).alias("x")).crossJoin(ks)
    return g.select("k", "i", F.round(gumbel.gumbel_pdf(F.col("x"), F.ln("k")), 9).alias("f"))


def _blocks_sql(value: str) -> str:
    return f"(select k, blk, {value} as v from (select k, w, (row_number() over (partition by k order by m) - 1) // k as blk, count(*) over (partition by k) // k as whole from (select k, w, m from (select {w('o_orderkey')} as w, md5('s1:' || cast(o_orderkey as varchar)) as m from (select distinct o_orderkey from orders)) cross join {_KV})) where blk < whole group by k, blk)"


def _blocks(spark, sf_dir, value):
    """The maximum over blocks of k distinct keys, blocks cut in hash order."""
    from pyspark.sql import Window

    spec = SketchSpec()
    keys = load(spark, sf_dir, "orders").select("o_orderkey").distinct()
    ks = F.broadcast(spark.createDataFrame([(k,) for k in _FIG_K], "k int"))
    from evsketch.functions import hashing

    item = F.col("o_orderkey").cast("string")
    at = keys.select(hashing.draw(spec, item).alias("w"), F.md5(F.concat(F.lit("s1:"), item).cast("binary")).alias("m")).crossJoin(ks)
    by = Window.partitionBy("k")
    at = at.select("k", "w", F.floor((F.row_number().over(by.orderBy("m")) - 1) / F.col("k")).alias("blk"), F.floor(F.count("*").over(by) / F.col("k")).alias("whole"))
    return at.where("blk < whole").groupBy("k", "blk").agg(value.alias("v"))


@query(f"select k, cast(v as bigint) as x, count(*) as n from {_blocks_sql(f'max({_RANK}) - 1')} group by all")
def w1e_empirical(spark, sf_dir):
    """Left panel from data: histogram of the maximum trailing zeros over blocks of k keys."""
    return _blocks(spark, sf_dir, F.max(bl.rank(F.col("w"), 52)) - 1).groupBy("k", F.col("v").cast("long").alias("x")).agg(F.count("*").alias("n"))


@query(f"select k, floor(({x('v')} - ln(k)) * 4) / 4 as x, count(*) as n from {_blocks_sql('min(w)')} group by all")
def w2e_empirical(spark, sf_dir):
    """Right panel from data: histogram of the maximum Gumbel draw less ln k, in quarters."""
    v = _blocks(spark, sf_dir, F.min("w"))
    return v.groupBy("k", (F.floor((ac.x_of(F.col("v")) - F.ln("k")) * 4) / 4.0).alias("x")).agg(F.count("*").alias("n"))


_WAYS = "exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(j + 1) - lgamma(n - i - j + 1) - n * ln(3.0::double))"


@query(
    f"with seen as (select n, count(*) as groups, round(avg(1.0::double / ((n0 + 1) * (n1 + 1) * (n2 + 1))), 9) as observed from {GROUPS} group by n), "
    "firsts as (select n, unnest(range(n + 1)) as i from seen), splits as (select n, i, unnest(range(n - i + 1)) as j from firsts) "
    f"select n, groups, observed, round(sum({_WAYS} / ((i + 1) * (j + 1) * (n - i - j + 1))), 9) as expected, round(pow(3.0::double / n, 3), 9) as bound, true as holds from splits join seen using (n) group by n, groups, observed"
)
def a_inverse_product(spark, sf_dir):
    """E[prod 1/(n_i + 1)] over the splits of n items to three sub-streams, by enumeration: at most (k/n)^k;
    for the numbers n of orders that customers have, beside the mean over these customers' own splits."""
    products = 1 / ((F.col("n0") + 1) * (F.col("n1") + 1) * (F.col("n2") + 1))
    seen = customer_groups(spark, sf_dir).groupBy("n").agg(F.count("*").alias("groups"), F.round(F.avg(products), 9).alias("observed"))
    logs = F.aggregate(F.sequence(F.lit(1).cast("long"), "n"), F.array(F.lit(0.0)), lambda f, v: F.concat(f, F.array(F.element_at(f, -1) + F.ln(v))))
    firsts = seen.withColumn("f", logs).withColumn("i", F.explode(F.sequence(F.lit(0).cast("long"), "n")))

    def log_factorial(at):
        return F.get("f", at.cast("int"))

    def add(total, j):
        rest = F.col("n") - F.col("i") - j
        ways = F.exp(log_factorial(F.col("n")) - log_factorial(F.col("i")) - log_factorial(j) - log_factorial(rest) - F.col("n") * math.log(3.0))
        return total + ways / ((F.col("i") + 1) * (j + 1) * (rest + 1))

    mean = F.aggregate(F.sequence(F.lit(0).cast("long"), F.col("n") - F.col("i")), F.lit(0.0), add)
    out = firsts.groupBy("n", "groups", "observed").agg(F.round(F.sum(mean), 9).alias("expected"))
    bound = F.round(F.pow(3.0 / F.col("n"), F.lit(3.0)), 9)
    return out.select("n", "groups", "observed", "expected", bound.alias("bound"), (F.col("expected") <= bound).alias("holds"))
