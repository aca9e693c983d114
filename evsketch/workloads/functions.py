"""SQL functions, grouped Arrow aggregate and table function."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from evsketch.functions import hashing, udfs
from evsketch.operators import discretize
from evsketch.operators import registers as rg
from evsketch.sources.tables import load
from evsketch.spec import SketchSpec
from evsketch.workloads.common import c, geo, query, regs, seeded, x
from evsketch.workloads.methods import users_by_day, z6
from evsketch.workloads.scenarios import USERS, dense

SPEC = SketchSpec(k=64)


@query(
    f"select cast(reg as bigint) as reg, round(exp(-exp(-(x - mean))), 9) as cdf, round(exp(-exp(-(x - mean)) - (x - mean)), 9) as pdf, round(mean - ln(-ln(exp(-exp(-(x - mean))))), 6) as quantile, round(floor(x + c) - c, 9) as rounded, round(64 * exp(mean - 0.5772156649015329::double), 3) as z "
    f"from (select reg, x, {c('reg')} as c, avg(x) over () as mean from (select reg, {x('w')} as x from {seeded(regs('orders', 'o_orderkey', k=64), k=64)}))"
)
def udf_sql_functions(spark, sf_dir):
    """Every SQL function at the order keys' registers, over the rows of the table function."""
    udfs.register_sql(spark)
    held = discretize.real_registers(dense(load(spark, sf_dir, "orders"), "o_orderkey", SPEC, []), SPEC)
    held.select("reg", "x", hashing.offset(SPEC, F.col("reg")).alias("c"), F.avg("x").over(Window.partitionBy()).alias("mean")).createOrReplaceTempView("key_registers")
    return spark.sql(
        "select cast(s.reg as bigint) as reg, round(gumbel_cdf(x, mean), 9) as cdf, round(gumbel_pdf(x, mean), 9) as pdf, round(gumbel_quantile(gumbel_cdf(x, mean), mean), 6) as quantile, "
        "round(shift_round(x, c), 9) as rounded, round(estimate_from_mean(64, mean), 3) as z from sketch_spine(64) s left join key_registers h on s.reg = h.reg"
    )


@query(geo(regs(USERS, "user_id", "day", 64), 64, "day"))
def udf_grouped(spark, sf_dir):
    return z6(udfs.grouped_gumbel_distinct(users_by_day(spark, sf_dir), "day", "user_id", 64))


@query(f"select l_returnflag, reg, cast(floor({x('w')} + {c('reg')}) as integer) as q from {seeded(regs('lineitem', 'l_suppkey', 'l_returnflag', 64), 'l_returnflag', 64)}")
def udtf_explode(spark, sf_dir):
    """Packed binary sketches exploded by the table function."""
    q = discretize.shift_round_registers(dense(load(spark, sf_dir, "lineitem"), "l_suppkey", SPEC, ["l_returnflag"]), SPEC)
    spark.udtf.register("explode_registers", udfs.explode_registers_udtf())
    udfs.binary_registers(rg.pack(q, SPEC, ["l_returnflag"]), ["l_returnflag"]).createOrReplaceTempView("packed_sketches")
    return spark.sql("select l_returnflag, cast(e.reg as bigint) as reg, e.q from packed_sketches, lateral explode_registers(qs) e")
