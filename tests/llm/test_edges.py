"""Every query and the pipeline over nulls, repeated rows, empty tables and clashing extra columns."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from evsketch.llm import queries

CLASHES = "row key cid n tag v a b doc th name kept terms base w item range blob node root gone cut th2 doc2 disclosing hub bucket home size near piece start length".split()


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    full, empty = (str(tmp_path_factory.mktemp(n)) for n in ("full", "empty"))
    long = "hello world " * 30
    docs = [(1, long, "en", "s", 360), (1, long, "en", "s", 360), (None, None, None, None, None), (None, "some text that is long enough to be judged fine by all rules here", "en", None, None), (3, "", None, "s", 0)]
    frames = {
        "documents": spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long"),
        "labels": spark.createDataFrame([(1, 1, 0), (None, None, None)], "doc_id long, quality int, toxic int"),
        "pages": spark.createDataFrame([(1, "http://a.org/", None), (None, None, "<p>x</p>")], "page_id long, url string, html string"),
        "embeddings": spark.createDataFrame([(1, [1.0, 2.0], 1), (None, None, None)], "vec_id long, embedding array<float>, label int"),
    }
    for name, df in frames.items():
        df = df.withColumns({c: F.lit("clash") for c in CLASHES})
        df.write.parquet(f"{full}/{name}.parquet")
        df.limit(0).write.parquet(f"{empty}/{name}.parquet")
    return full, empty


@pytest.mark.parametrize("name", sorted(queries.QUERIES))
def test_queries(spark, tables, name):
    full, empty = tables
    assert queries.QUERIES[name](spark, full).count() == (2 if name in ("op2_html_text", "op5_embedding_dedup", "op7_url_filter") else 5)
    assert queries.QUERIES[name](spark, empty).count() == 0


def test_pipeline(spark, tables):
    full, empty = tables
    assert [r.doc_id for r in corpus_pipeline.run(spark, full).collect()] == [None]
    assert corpus_pipeline.run(spark, empty).count() == 0
