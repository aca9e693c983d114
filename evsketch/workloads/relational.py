"""Relational operators a user needs around the sketches."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from evsketch.functions import hashing
from evsketch.operators import discretize, estimate
from evsketch.operators import registers as rg
from evsketch.operators import relational as rel
from evsketch.sources.tables import load
from evsketch.spec import SketchSpec
from evsketch.workloads.common import c, geo, harm, query, r, regs, seeded, w, x
from evsketch.workloads.methods import users_by_day, z6
from evsketch.workloads.scenarios import USERS, dense, running

KR = 64
SPEC = SketchSpec(k=KR)


def _geo(df, col, by=()):
    return z6(estimate.estimate_geometric(dense(df, col, SPEC, by), SPEC, by))


def _sql_geo(table: str, item: str, by: str = "") -> str:
    return geo(seeded(regs(table, item, by, KR), by, KR), KR, by)


@query(_sql_geo("(select l_orderkey from lineitem where l_shipdate >= timestamp '1995-01-01' and l_shipdate < timestamp '1996-01-01' and l_returnflag in ('A', 'R'))", "l_orderkey"))
def op_filter_sketch(spark, sf_dir):
    df = load(spark, sf_dir, "lineitem").where("l_shipdate >= timestamp_ntz '1995-01-01' and l_shipdate < timestamp_ntz '1996-01-01' and l_returnflag in ('A', 'R')")
    return _geo(df, "l_orderkey")


_LOC = "(select c_mktsegment, l_partkey from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey)"


@query(_sql_geo(_LOC, "l_partkey", "c_mktsegment"))
def op_join_sketch(spark, sf_dir):
    """Distinct parts by customer segment, through two equi joins."""
    li, o, cu = (load(spark, sf_dir, t) for t in ("lineitem", "orders", "customer"))
    return _geo(li.join(o, li.l_orderkey == o.o_orderkey).join(cu, o.o_custkey == cu.c_custkey).select("c_mktsegment", "l_partkey"), "l_partkey", ["c_mktsegment"])


_NAT = "(select n_name, c_custkey from customer join nation on c_nationkey = n_nationkey)"


@query(_sql_geo(_NAT, "c_custkey", "n_name"))
def op_broadcast_join(spark, sf_dir):
    """Customers by nation; the nation table has 25 rows by definition."""
    cu, na = load(spark, sf_dir, "customer"), load(spark, sf_dir, "nation")
    return _geo(cu.join(F.broadcast(na), cu.c_nationkey == na.n_nationkey).select("n_name", "c_custkey"), "c_custkey", ["n_name"])


@query(_sql_geo("(select o_orderkey from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_returnflag = 'R'))", "o_orderkey"))
def op_semi(spark, sf_dir):
    o, li = load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem").where("l_returnflag = 'R'")
    return _geo(o.join(li, o.o_orderkey == li.l_orderkey, "left_semi"), "o_orderkey")


@query(_sql_geo("(select o_orderkey from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey))", "o_orderkey"))
def op_anti(spark, sf_dir):
    o, li = load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem")
    return _geo(o.join(li, o.o_orderkey == li.l_orderkey, "left_anti"), "o_orderkey")


_SPANS = [(1, 0.0, 3.5), (2, 2.0, 9.0), (3, 20.0, 21.0), (4, 25.0, 40.0)]
_SPAN_SQL = "(values " + ", ".join(f"({i}, {a}::double, {b}::double)" for i, a, b in _SPANS) + ") v(span, a, b)"
_AT_SQL = "(select user_id, epoch(ts) / 86400.0::double - 19723 as t0 from events)"


@query(_sql_geo(f"(select span, user_id from {_AT_SQL} join {_SPAN_SQL} on t0 >= a and t0 < b)", "user_id", "span"))
def op_range_join(spark, sf_dir):
    """Users in overlapping day spans given as rows."""
    spans = spark.createDataFrame(_SPANS, "span int, a double, b double")
    ev = load(spark, sf_dir, "events").select("user_id", (F.unix_micros(F.col("ts").cast("timestamp")) / 1e6 / 86400 - 19723).alias("at"))
    return _geo(rel.range_join(ev, "at", spans, "a", "b", 5.0), "user_id", ["span"])


_RUN_GEO = geo(f"(select day, reg, min(w) over (partition by reg order by day) as w from {seeded(regs(USERS, 'user_id', 'day', KR), 'day', KR)})", KR, "day")
_ASKED = [("2023-12-31",), ("2024-01-03",), ("2024-01-10",), ("2024-03-01",)]


@query("select asked, z from (values " + ", ".join(f"('{a}')" for (a,) in _ASKED) + f") q(asked) asof left join ({_RUN_GEO}) s on asked >= day")
def op_asof_sketch(spark, sf_dir):
    """The latest stored answer at or before each query day."""
    stored = z6(estimate.estimate_geometric(running(spark, sf_dir, SPEC), SPEC, ["day"]))
    asked = spark.createDataFrame(_ASKED, "asked string")
    return rel.asof_join(asked, stored, "asked", "day", carry=["z"])


_SEGZ = _sql_geo("(select c_mktsegment, o_orderkey from customer join orders on c_custkey = o_custkey)", "o_orderkey", "c_mktsegment")


def _segments(spark, sf_dir):
    cu, o = load(spark, sf_dir, "customer"), load(spark, sf_dir, "orders")
    return _geo(cu.join(o, cu.c_custkey == o.o_custkey).select("c_mktsegment", "o_orderkey"), "o_orderkey", ["c_mktsegment"])


@query(f"select a.c_mktsegment as larger, b.c_mktsegment as smaller from ({_SEGZ}) a join ({_SEGZ}) b on a.z > b.z")
def op_theta_pairs(spark, sf_dir):
    """Pairs of segments (five by definition) with one estimate above the other."""
    s = _segments(spark, sf_dir)
    a, b = s.select(F.col("c_mktsegment").alias("larger"), F.col("z").alias("za")), s.select(F.col("c_mktsegment").alias("smaller"), F.col("z").alias("zb"))
    return a.join(b, F.col("za") > F.col("zb")).select("larger", "smaller")


_FLAGS = ("l_returnflag", "l_linestatus")
_FINE = regs("lineitem", "l_suppkey", "l_returnflag, l_linestatus", KR)


def _sets(kind: str) -> str:
    return f"select l_returnflag, l_linestatus, cast(grouping(l_returnflag, l_linestatus) as integer) as level, round({KR} * exp(avg({x('w')}) - 0.5772156649015329), 6) as z from (select l_returnflag, l_linestatus, reg, min(w) as w, grouping(l_returnflag, l_linestatus) as g from {_FINE} group by {kind}) group by all"


def _grouped(sets) -> str:
    parts = []
    for chosen in sets:
        level = sum(1 << i for i, f in enumerate(reversed(_FLAGS)) if f not in chosen)
        cols = ", ".join(f if f in chosen else f"cast(null as varchar) as {f}" for f in _FLAGS)
        keys = "".join(f"{f}, " for f in _FLAGS if f in chosen)
        parts.append(f"select {cols}, {level} as level, round({KR} * exp(avg({x('w')}) - 0.5772156649015329), 6) as z from (select {keys}reg, min(w) as w from {_FINE} group by all) {'group by ' + keys.rstrip(', ') if keys else ''}")
    return " union all ".join(parts)


_CUBE = [_FLAGS, _FLAGS[:1], _FLAGS[1:], ()]


def _levels(spark, sf_dir, sets):
    fine = rg.registers(load(spark, sf_dir, "lineitem"), "l_suppkey", _FLAGS, SPEC)
    return z6(estimate.estimate_geometric(rg.rollup_registers(fine, sets, _FLAGS), SPEC, [*_FLAGS, "level"]))


@query(_grouped(_CUBE))
def op_cube(spark, sf_dir):
    return _levels(spark, sf_dir, _CUBE)


@query(_grouped([_FLAGS, _FLAGS[:1], ()]))
def op_rollup(spark, sf_dir):
    return _levels(spark, sf_dir, [_FLAGS, _FLAGS[:1], ()])


@query(_grouped([_FLAGS[:1], _FLAGS[1:]]))
def op_grouping_sets(spark, sf_dir):
    return _levels(spark, sf_dir, [_FLAGS[:1], _FLAGS[1:]])


_FILTERS = {"all": "true", "returned": "l_returnflag = 'R'", "late": "l_shipdate >= timestamp '1997-01-01'"}


@query(" union all ".join(f"select '{n}' as name, z from ({geo(regs(f'(select l_orderkey from lineitem where {cond})', 'l_orderkey', k=KR), KR)})" for n, cond in _FILTERS.items()))
def op_filtered_agg(spark, sf_dir):
    """Three sketches in one pass."""
    df = load(spark, sf_dir, "lineitem")
    item = F.col("l_orderkey")
    rows = df.where("l_orderkey is not null").select(hashing.register(SPEC, item).alias("reg"), hashing.draw(SPEC, item).alias("w"), "l_returnflag", "l_shipdate")
    conds = {n: F.expr(cond.replace("timestamp ", "timestamp_ntz ")) for n, cond in _FILTERS.items()}
    return z6(estimate.estimate_geometric(rel.filtered_registers(rows, conds), SPEC, ["name"]))


_SUPZ = _sql_geo("lineitem", "l_partkey", "l_suppkey")


def _suppliers(spark, sf_dir):
    return _geo(load(spark, sf_dir, "lineitem"), "l_partkey", ["l_suppkey"])


@query(f"select l_suppkey, cast(rank() over (order by z desc) as integer) as rank, cast(dense_rank() over (order by z desc) as integer) as dense_rank, cast(row_number() over (order by z desc, l_suppkey) as integer) as row_number, cast(ntile(4) over (order by z desc, l_suppkey) as integer) as quarter, round(percent_rank() over (order by z desc), 6) as percent_rank from ({_SUPZ})")
def op_rank_groups(spark, sf_dir):
    """Groups ranked by estimate; the window is over one row per group."""
    z, tie = Window.orderBy(F.desc("z")), Window.orderBy(F.desc("z"), "l_suppkey")
    ranks = [F.rank().over(z).alias("rank"), F.dense_rank().over(z).alias("dense_rank"), F.row_number().over(tie).alias("row_number"), F.ntile(4).over(tie).alias("quarter"), F.round(F.percent_rank().over(z), 6).alias("percent_rank")]
    return _suppliers(spark, sf_dir).select("l_suppkey", *ranks)


_DAYZ = _sql_geo(USERS, "user_id", "day")


@query(f"select day, z, round(z - lag(z) over (order by day), 6) as change, lead(day) over (order by day) as following, first_value(z) over (order by day) as first_z, nth_value(z, 2) over (order by day rows between unbounded preceding and unbounded following) as second_z from ({_DAYZ})")
def op_lag_change(spark, sf_dir):
    z = _geo(users_by_day(spark, sf_dir), "user_id", ["day"])
    by = Window.orderBy("day")
    whole = by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return z.select("day", "z", F.round(F.col("z") - F.lag("z").over(by), 6).alias("change"), F.lead("day").over(by).alias("following"), F.first("z").over(by).alias("first_z"), F.nth_value("z", 2).over(whole).alias("second_z"))


@query(_RUN_GEO)
def op_running_window(spark, sf_dir):
    return z6(estimate.estimate_geometric(running(spark, sf_dir, SPEC), SPEC, ["day"]))


@query(geo(f"(select day, reg, min(w) over (partition by reg order by epoch(cast(day as date)) // 86400 range between 6 preceding and current row) as w from {seeded(regs(USERS, 'user_id', 'day', KR), 'day', KR)})", KR, "day"))
def op_trailing_7d(spark, sf_dir):
    """Distinct users of the trailing seven days, which COUNT(DISTINCT) OVER can't give."""
    frame = Window.partitionBy("reg").orderBy(F.unix_date(F.to_date("day"))).rangeBetween(-6, 0)
    return z6(estimate.estimate_geometric(running(spark, sf_dir, SPEC, frame), SPEC, ["day"]))


@query(f"select l_suppkey, z from ({_SUPZ}) order by z desc, l_suppkey limit 10")
def op_topk(spark, sf_dir):
    return _suppliers(spark, sf_dir).orderBy(F.desc("z"), "l_suppkey").limit(10)


_CUST_U = "(select c_custkey as key from customer union all select o_custkey from orders)"


@query(geo(seeded(regs(_CUST_U, "key", k=KR), k=KR), KR))
def op_union_merge(spark, sf_dir):
    """Union of two tables' items by merging their sketches."""
    a = rg.registers(load(spark, sf_dir, "customer"), "c_custkey", spec=SPEC)
    b = rg.registers(load(spark, sf_dir, "orders"), "o_custkey", spec=SPEC)
    return z6(estimate.estimate_geometric(rg.with_seed_draws(rg.merge((a, SPEC), (b, SPEC)), SPEC), SPEC))


@query("select count(*) as n from (select c_custkey from customer intersect select o_custkey from orders)")
def op_intersect_exact(spark, sf_dir):
    return load(spark, sf_dir, "customer").select("c_custkey").intersect(load(spark, sf_dir, "orders").select("o_custkey")).agg(F.count("*").alias("n"))


@query("select count(*) as n from (select l_orderkey from lineitem except all select o_orderkey from orders)")
def op_except_exact(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").select("l_orderkey").exceptAll(load(spark, sf_dir, "orders").select("o_orderkey")).agg(F.count("*").alias("n"))


def _h(source: str) -> str:
    return f"(select {KR * KR} / sum((2 * atanh(least((cast(w as double) + 0.5::double) / 4503599627370496::double, 0.99999999999999988897769753748::double) / (2 - least((cast(w as double) + 0.5::double) / 4503599627370496::double, 0.99999999999999988897769753748::double))))) from {source})"


@query(f"select round({_h(seeded(regs('customer', 'c_custkey', k=KR), k=KR))} + {_h(seeded(regs('orders', 'o_custkey', k=KR), k=KR))} - {_h(seeded(regs(_CUST_U, 'key', k=KR), k=KR))}, 6) as z")
def op_incl_excl(spark, sf_dir):
    """Intersection of two tables' items by inclusion and exclusion."""
    a, b = dense(load(spark, sf_dir, "customer"), "c_custkey", SPEC), dense(load(spark, sf_dir, "orders"), "o_custkey", SPEC)
    return z6(rel.intersect_estimate(a, b, SPEC, estimate.estimate_harmonic))


_FZ = _sql_geo("lineitem", "l_suppkey", "l_returnflag, l_linestatus")


@query(f"select l_returnflag, max(z) filter (where l_linestatus = 'F') as \"F\", max(z) filter (where l_linestatus = 'O') as \"O\" from ({_FZ}) group by l_returnflag")
def op_pivot(spark, sf_dir):
    z = _geo(load(spark, sf_dir, "lineitem"), "l_suppkey", list(_FLAGS))
    return z.groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.max("z"))


_QS = f"(select l_returnflag, reg, floor({x('w')} + {c('reg')}) as q from {seeded(regs('lineitem', 'l_suppkey', 'l_returnflag', KR), 'l_returnflag', KR)})"


@query(f"select l_returnflag, count(*) as regs, cast(sum(q) as bigint) as total, cast(sum(q * (reg + 1)) as bigint) as weighted from {_QS} group by l_returnflag")
def op_pack_unpack(spark, sf_dir):
    """Integer registers packed to one array a group, merged with themselves and unpacked."""
    q = discretize.shift_round_registers(dense(load(spark, sf_dir, "lineitem"), "l_suppkey", SPEC, ["l_returnflag"]), SPEC)
    packed = rg.pack(q, SPEC, ["l_returnflag"]).withColumn("qs", rg.merge_packed(F.col("qs"), F.col("qs")))
    back = rg.unpack(packed, ["l_returnflag"])
    return back.groupBy("l_returnflag").agg(F.count("*").alias("regs"), F.sum(F.col("q").cast("long")).alias("total"), F.sum(F.col("q").cast("long") * (F.col("reg") + 1)).alias("weighted"))


@query(f"select * from (select count(distinct json_extract_string(props, '$.k')) as n from events) cross join ({_sql_geo(chr(40) + 'select json_extract_string(props, ' + chr(39) + '$.k' + chr(39) + ') as k from events)', 'k')})")
def op_json_items(spark, sf_dir):
    df = load(spark, sf_dir, "events").select(F.get_json_object("props", "$.k").alias("k"))
    return df.agg(F.count_distinct("k").alias("n")).crossJoin(_geo(df, "k"))


_HOSTS = "(select regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) as host from pages)"


@query(f"select * from (select count(distinct host) as n from {_HOSTS}) cross join ({_sql_geo(_HOSTS, 'host')})")
def op_url_host(spark, sf_dir):
    df = load(spark, sf_dir, "pages").select(F.parse_url("url", F.lit("HOST")).alias("host"))
    return df.agg(F.count_distinct("host").alias("n")).crossJoin(_geo(df, "host"))


@query(_sql_geo("(select strftime(date_trunc('month', o_orderdate), '%Y-%m') as month, o_custkey from orders)", "o_custkey", "month"))
def op_date_trunc(spark, sf_dir):
    df = load(spark, sf_dir, "orders").select(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month"), "o_custkey")
    return _geo(df, "o_custkey", ["month"])
