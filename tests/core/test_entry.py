"""Every registered query has DuckDB rows equal to its own at the smallest size, or is rows-only."""

import math

import duckdb
import pytest

from evsketch import registry
from evsketch.workloads.common import K, K_BY_SIZE, spec_at, xx

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: A few of each kind; the whole registry runs against DuckDB at sf0.01 outside the tests.
NAMES = ["fast_geo", "m1_full_geo", "m2_geo_by_group", "m3_shift_geo", "m8_shift_round_props", "b1_exact", "b4_hll", "a_tail_lemma", "w2_gumbel_max_law", "w18_roles", "op_cube", "op_asof_sketch", "op_range_join", "st_equals_batch", "io_csv_items", "udf_sql_functions", "udtf_explode"]


def norm(v):
    return round(v, 6) if isinstance(v, float) and not math.isnan(v) else v


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_oracle(spark, duck, monkeypatch, name):
    monkeypatch.setitem(K_BY_SIZE, "sf0.001", 256)  # the oracles' k
    df = registry.queries()[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted((tuple(norm(r[c]) for c in cols) for r in df.collect()), key=str)
    cur = duck.execute(registry.oracle_sql()[name])
    names = [d[0] for d in cur.description]
    want = sorted((tuple(norm(r[names.index(c)]) for c in cols) for r in cur.fetchall()), key=str)
    assert sorted(names) == cols and got == want


def test_entry_and_registry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 1
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(registry.queries()) >= 100


def test_registers_do_not_depend_on_the_name_of_the_input():
    assert {spec_at(f"/data/{name}").k for name in ("sf0.001", "sf0.01", "sf0.1", "sf0.1/", "other")} == {K}


def test_the_oracle_of_the_fast_family_hashes_as_spark_does(spark):
    texts = ["", "a", "abc", "abcd", "abcdefg", "12345678", "123456789012", "9223372036854775807", "x" * 31]
    rows = ", ".join(f"('{t}')" for t in texts)
    bytes_ = "list_filter(list_transform(string_split(s, ''), lambda y: ascii(y)), lambda y: y > 0)"
    found = duckdb.sql(f"with given as (select s, {bytes_} as b, 42::uhugeint as h from (values {rows}) t(s)), {xx('given', 'done')} select s, h from done").fetchall()
    want = spark.createDataFrame([(t,) for t in texts], "s string").selectExpr("s", "xxhash64(s) as h").collect()
    assert dict(found) == {r.s: r.h % (1 << 64) for r in want}
