"""The queries that have SQL give the SQL's rows, on the smallest tables and on planted small ones."""

import duckdb
import pytest

from evsketch.llm import queries

SF = "/root/testdata/sf0.001"


def compare(spark, name, sf_dir, table):
    con = duckdb.connect()
    con.execute(f"create view {table} as select * from '{sf_dir}/{table}.parquet'")
    df = queries.queries()[name](spark, sf_dir)
    got = sorted((tuple(r[c] for c in sorted(df.columns)) for r in df.collect()), key=str)
    found = con.execute(queries.oracle_sql()[name])
    names = [d[0] for d in found.description]
    want = sorted((tuple(r[names.index(c)] for c in sorted(names)) for r in found.fetchall()), key=str)
    assert sorted(names) == sorted(df.columns) and got == want
    return got


@pytest.mark.parametrize(("name", "table"), [("op1_pii", "documents"), ("op4_quality_rules", "documents"), ("op5_embedding_dedup", "embeddings"), ("op7_url_filter", "pages"), ("op9_near_dedup", "documents"), ("op10_suffix_dedup", "documents")])
def test_query_equals_sql(spark, name, table):
    assert compare(spark, name, SF, table)


def test_repeats_of_any_script_and_odd_texts(spark, tmp_path):
    shared = "Ein geteilter Absatz, über den es nichts weiter zu sagen gäbe, auch wenn er länger wäre als nötig."
    texts = [(1, shared), (2, None), (3, ""), (4, "vorher " + shared + " nachher"), (5, "x" * 49), (6, "x" * 49), (7, "y" * 2000), (8, "z" + "y" * 700), (9, shared[:30] + "語" * 40), (10, "語" * 40 + shared[20:])]
    pandas = spark.createDataFrame(texts, "doc_id long, text string").toPandas()
    pandas.to_parquet(tmp_path / "documents.parquet")
    rows = compare(spark, "op10_suffix_dedup", str(tmp_path), "documents")
    assert sum(r[3] > 0 for r in rows) == 3


def test_urls_with_mined_verdicts_and_odd_forms(spark, tmp_path):
    urls = [f"https://ads{i % 3}.example.com/de/{i}?track=1" for i in range(40)] + [f"http://www.example.com/fr/{i}" for i in range(40)]
    urls += [None, "", "no host", "://", "HTTP://WWW.Example.ORG/es/x#y?z", "http://org/", "http://a.org?b", "http://ads1.shop.net/x?track=2&&a=b=c", "http://www.shop.net//fr/", "http://ads2.example.net/de/", "x://y\n/z://com/de/"]
    spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").toPandas().to_parquet(tmp_path / "pages.parquet")
    rows = compare(spark, "op7_url_filter", str(tmp_path), "pages")
    assert {r[-1] for r in rows} == {"allow", "block"} and len(rows) == len(urls)
    assert any(r[3] is None and r[-1] == "block" for r in rows)


def test_personal_data_of_odd_forms(spark, tmp_path):
    texts = ["write to jane.miller@mail.example.org, Ms Miller of Quarnford", "Miller again, but no address", "a@b a@b.c@d.e x@y..z @q.r me@me.me.", "1.2.3.4.5.6.7.8 256.1.1.1 010.000255.0.1 1.1.1", "4111 1111 1111 1111, 4111-1111-1111-1112 and 41111111111111111111"]
    texts += ["+49 (30) 1234567 +1 2 +123456789012345678 ++4712345678", 'api_key = "abcd1234efgh" password: kurzundohne token:\tXyz98765;', "", None, "Größe über 1.2.3.4 straße", "é" * 90 + " 9.9.9.9 " + "wort" * 30]
    texts += [f"plain words number {i} about nothing in particular, twice nothing" for i in range(1500)]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").toPandas().to_parquet(tmp_path / "documents.parquet")
    rows = compare(spark, "op1_pii", str(tmp_path), "documents")
    assert len(rows) == len(texts) and any("term:" in r[-1] for r in rows) and any("secret:" in r[-1] for r in rows)
