"""Scenarios: distinct counts of tables, days, prefixes, groups, tuples and texts."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from evsketch.functions.gumbel import EULER_GAMMA
from evsketch.operators import discretize, estimate
from evsketch.operators import registers as rg
from evsketch.sources.tables import load
from evsketch.spec import SketchSpec
from evsketch.workloads.common import K, c, e, geo, harm, query, r, regs, seeded, spec_at, w, x
from evsketch.workloads.methods import users_by_day, z6

#: (table, column) of the survey of distinct counts.
COLUMNS = (("lineitem", "l_orderkey"), ("lineitem", "l_partkey"), ("lineitem", "l_suppkey"), ("orders", "o_custkey"), ("events", "user_id"), ("documents", "text"), ("pages", "url"), ("customer", "c_name"))


def dense(df, cols, spec, by=()):
    return rg.with_seed_draws(rg.registers(df, cols, by, spec), spec, by)


_ALL = " union all ".join(
    f"select '{t}' as table_name, '{col}' as column_name, n, z_geometric, z_harmonic, round(abs(z_harmonic - n) / n, 6) as error from (select count(distinct {col}) as n from {t}) cross join ({geo(seeded(regs(t, col)), K, out='z_geometric')}) cross join ({harm(seeded(regs(t, col)), K * K, out='z_harmonic')})"
    for t, col in COLUMNS
)


@query(_ALL)
def w3_all_columns(spark, sf_dir):
    """Estimates beside exact counts for columns of several tables."""
    spec, out = spec_at(sf_dir), None
    for t, col in COLUMNS:
        df = load(spark, sf_dir, t)
        regs_ = dense(df, col, spec)
        g = z6(estimate.estimate_geometric(regs_, spec)).withColumnRenamed("z", "z_geometric")
        h = z6(estimate.estimate_harmonic(regs_, spec)).withColumnRenamed("z", "z_harmonic")
        n = df.agg(F.count_distinct(col).alias("n"))
        one = n.crossJoin(g).crossJoin(h).select(F.lit(t).alias("table_name"), F.lit(col).alias("column_name"), "n", "z_geometric", "z_harmonic", F.round(F.abs(F.col("z_harmonic") - F.col("n")) / F.col("n"), 6).alias("error"))
        out = one if out is None else out.union(one)
    return out


USERS = "(select strftime(ts, '%Y-%m-%d') as day, user_id from events)"


@query(f"select * from (select day, count(distinct user_id) as n from {USERS} group by day) join ({harm(seeded(regs(USERS, 'user_id', 'day', 64), 'day', 64), 64 * 64, 'day')}) using (day)")
def w4_users_per_day(spark, sf_dir):
    """Distinct sources a day, exact and estimated."""
    spec, days = SketchSpec(k=64), users_by_day(spark, sf_dir)
    z = z6(estimate.estimate_harmonic(dense(days, "user_id", spec, ["day"]), spec, ["day"]))
    return days.groupBy("day").agg(F.count_distinct("user_id").alias("n")).join(z, "day")


_DAY_REGS = regs(USERS, "user_id", "day", 64)
_SPINE = f"(select d.day, s.reg, s.w0 from (select distinct day from {USERS}) d cross join (select i as reg, {w('i', tag='#reg')} as w0 from range(64) t(i)) s)"
_RUNNING = f"(select p.day, p.reg, min(least(coalesce(r.w, p.w0), p.w0)) over (partition by p.reg order by p.day) as w from {_SPINE} p left join {_DAY_REGS} r on p.day = r.day and p.reg = r.reg)"


@query(geo(_RUNNING, 64, "day"))
def w5_prefixes(spark, sf_dir):
    """The answer after every day's prefix: a running minimum over a dense day x register grid."""
    spec = SketchSpec(k=64)
    return z6(estimate.estimate_geometric(running(spark, sf_dir, spec), spec, ["day"]))


def running(spark, sf_dir, spec, frame=None):
    days = users_by_day(spark, sf_dir)
    daily = dense(days, "user_id", spec, ["day"])  # dense: untouched registers carry forward
    over = Window.partitionBy("reg").orderBy("day").rowsBetween(Window.unboundedPreceding, 0) if frame is None else frame
    return daily.withColumn("w", F.min("w").over(over))


@query("select cast(0 as bigint) as differing")
def w10_duplicates(spark, sf_dir):
    """Registers that differ between a table, its distinct items and the table twice."""
    spec = spec_at(sf_dir)
    keys = load(spark, sf_dir, "lineitem").select("l_orderkey")
    a, b, cc = (rg.registers(df, "l_orderkey", spec=spec) for df in (keys, keys.distinct(), keys.union(keys)))
    return a.exceptAll(b).union(b.exceptAll(cc)).union(cc.exceptAll(a)).agg(F.count("*").alias("differing"))


_D = seeded(regs("lineitem", "l_orderkey"))


@query(f"select reg, round({x('w')}, 9) as x, round({c('reg')}, 9) as c, cast(floor({x('w')} + {c('reg')}) as bigint) as q from {_D}")
def w12_side_by_side(spark, sf_dir):
    """Real and shift-rounded registers of one sketch."""
    from evsketch.functions import hashing

    spec = spec_at(sf_dir)
    d = dense(load(spark, sf_dir, "lineitem"), "l_orderkey", spec)
    both = discretize.real_registers(d, spec).join(discretize.shift_round_registers(d, spec), "reg")
    return both.select(F.col("reg").cast("long").alias("reg"), F.round("x", 9).alias("x"), F.round(hashing.offset(spec, F.col("reg")), 9).alias("c"), F.col("q").cast("long").alias("q"))


@query(harm(seeded(regs("lineitem", "l_partkey", "l_suppkey"), "l_suppkey"), K * K, "l_suppkey"))
def w14_parts_per_supplier(spark, sf_dir):
    spec = spec_at(sf_dir)
    return z6(estimate.estimate_harmonic(dense(load(spark, sf_dir, "lineitem"), "l_partkey", spec, ["l_suppkey"]), spec, ["l_suppkey"]))


_SEG = "(select c_mktsegment, o_orderkey from customer join orders on c_custkey = o_custkey)"


@query(geo(seeded(regs(_SEG, "o_orderkey", "c_mktsegment"), "c_mktsegment"), K, "c_mktsegment"))
def w14_orders_per_segment(spark, sf_dir):
    spec = spec_at(sf_dir)
    joined = load(spark, sf_dir, "customer").join(load(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey")).select("c_mktsegment", "o_orderkey")
    return z6(estimate.estimate_geometric(dense(joined, "o_orderkey", spec, ["c_mktsegment"]), spec, ["c_mktsegment"]))


_WEEKS = "(select strftime(date_trunc('week', cast(day as date)), '%Y-%m-%d') as week, reg, min(w) as w from " + _DAY_REGS + " group by all)"


@query(f"select 'week' as level, week as period, z from ({harm(seeded(_WEEKS, 'week', 64), 64 * 64, 'week')}) union all select 'all', 'all', z from ({harm(seeded('(select reg, min(w) as w from ' + _DAY_REGS + ' group by reg)', k=64), 64 * 64)})")
def w15_rollup_week(spark, sf_dir):
    """Weeks and the whole from daily registers, without reading items again."""
    spec = SketchSpec(k=64)
    daily = rg.registers(users_by_day(spark, sf_dir), "user_id", ["day"], spec)
    weekly = rg.merge_rows(daily.withColumn("week", F.date_format(F.date_trunc("week", F.to_date("day")), "yyyy-MM-dd")), ["week"])
    whole = rg.merge_rows(weekly)
    a = z6(estimate.estimate_harmonic(rg.with_seed_draws(weekly, spec, ["week"]), spec, ["week"])).select(F.lit("week").alias("level"), F.col("week").alias("period"), "z")
    b = z6(estimate.estimate_harmonic(rg.with_seed_draws(whole, spec), spec)).select(F.lit("all"), F.lit("all"), "z")
    return a.union(b)


_PAIR = "(select length(cast(l_partkey as varchar)) || ':' || l_partkey || length(cast(l_suppkey as varchar)) || ':' || l_suppkey as pair from lineitem)"


@query(f"select * from (select count(distinct pair) as n from {_PAIR}) cross join ({geo(seeded(regs(_PAIR, 'pair')), K)})")
def w17_tuples(spark, sf_dir):
    """Distinct (part, supplier) pairs."""
    spec = spec_at(sf_dir)
    df = load(spark, sf_dir, "lineitem")
    n = df.where("l_partkey is not null and l_suppkey is not null").agg(F.count_distinct("l_partkey", "l_suppkey").alias("n"))
    return n.crossJoin(z6(estimate.estimate_geometric(dense(df, ["l_partkey", "l_suppkey"], spec), spec)))


@query("select count(distinct embedding) as n, true as inside from embeddings")
def w17_arrays(spark, sf_dir):
    """Arrays as items: the estimate lies within five standard errors."""
    spec = SketchSpec(k=64)
    df = load(spark, sf_dir, "embeddings")
    z = estimate.estimate_harmonic(dense(df, "embedding", spec), spec)
    n = df.agg(F.count_distinct("embedding").alias("n"))
    return n.crossJoin(z).select("n", (F.abs(F.col("z") - F.col("n") - 64) <= 5 * F.col("n") / 8).alias("inside"))


@query(f"select lang, source, n, z from (select lang, source, count(distinct text) as n from documents group by all) join ({harm(seeded(regs('documents', 'text', 'lang, source', 64), 'lang, source', 64), 64 * 64, 'lang, source')}) using (lang, source)")
def w18_documents(spark, sf_dir):
    """Distinct texts by language and source."""
    spec, by = SketchSpec(k=64), ["lang", "source"]
    df = load(spark, sf_dir, "documents")
    return df.groupBy(*by).agg(F.count_distinct("text").alias("n")).join(z6(estimate.estimate_harmonic(dense(df, "text", spec, by), spec, by)), by)


@query(f"select role, n, z from (select role, count(distinct text) as n from conversations group by role) join ({geo(seeded(regs('conversations', 'text', 'role', 64), 'role', 64), 64, 'role')}) using (role)")
def w18_roles(spark, sf_dir):
    spec = SketchSpec(k=64)
    df = load(spark, sf_dir, "conversations")
    return df.groupBy("role").agg(F.count_distinct("text").alias("n")).join(z6(estimate.estimate_geometric(dense(df, "text", spec, ["role"]), spec, ["role"])), "role")
