"""Queries that once made their data up: each reads a given table and follows what is in it."""

import math

import duckdb
import pytest

from evsketch import registry
from evsketch.operators.accuracy import space_columns, space_table
from evsketch.plans.checks import plan_facts

SF = "/root/testdata/sf0.001"
NAMES = [
    "a_inverse_product",
    "a_smoothness",
    "c_space_table",
    "m11_k_for_eps",
    "m3_offsets",
    "m6_gumbel_moments",
    "m6_gumbel_table",
    "m6_quantile_roundtrip",
    "m7_max_stability",
    "m8_shift_round_props",
    "udf_sql_functions",
    "w1_geom_max_law",
]


def norm(v):
    return round(v, 6) if isinstance(v, float) and not math.isnan(v) else v


@pytest.fixture(scope="module")
def odd(tmp_path_factory):
    """Half of the orders and their lines, some rows twice, and rows with null keys."""
    root = tmp_path_factory.mktemp("odd")
    for table, key, other in (("orders", "o_orderkey", "o_custkey"), ("lineitem", "l_orderkey", "l_partkey")):
        rows = f"'{SF}/{table}.parquet'"
        blank = [f"select * replace (cast(null as bigint) as {c}) from {rows} where {key} < 9" for c in (key, other)]
        duckdb.sql(f"copy (select * from {rows} where {key} % 2 = 0 union all select * from {rows} where {key} in (2, 4, 6) union all {' union all '.join(blank)}) to '{root}/{table}.parquet' (format parquet)")
    return str(root)


def answers(df):
    cols = sorted(df.columns)
    return sorted((tuple(norm(r[c]) for c in cols) for r in df.collect()), key=str)


@pytest.mark.parametrize("name", NAMES)
def test_query_reads_its_table_and_equals_sql_on_odd_rows(spark, odd, name):
    df = registry.queries()[name](spark, odd)
    assert plan_facts(df)["read"]
    con = duckdb.connect()
    for table in ("orders", "lineitem"):
        con.execute(f"create view {table} as select * from '{odd}/{table}.parquet'")
    cur = con.execute(registry.oracle_sql()[name])
    names = [d[0] for d in cur.description]
    want = sorted((tuple(norm(r[names.index(c)]) for c in sorted(names)) for r in cur.fetchall()), key=str)
    assert sorted(names) == sorted(df.columns) and answers(df) == want
    assert want != answers(registry.queries()[name](spark, SF))


def test_space_columns_equal_the_table_of_numbers(spark):
    for n in (3, 65536, 150_000, 10**9):
        df = spark.createDataFrame([(n, 1 << 32)], "n long, u long")
        got = df.select(*[b.alias(m) for m, b in space_columns(0.05, 0.01, df.n, df.u)]).first().asDict()
        assert got == pytest.approx(dict(space_table(0.05, 0.01, n, 2.0**32)))


def test_the_universe_of_a_key_counts_zero(spark):
    df = registry.queries()["c_space_table"](spark, SF)
    assert all(r.universe >= r.n for r in df.collect())  # keys are 0, 1, 2, ...: a bitmap needs a bit for each
