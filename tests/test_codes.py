"""Graphs above one task's size: vertices numbered by their codes, and edges of documents that need no distinct."""

import pytest
from pyspark.sql import functions as F

from stratacore.operators import peel
from stratacore.sources import graph, random_graph


def labels(df):
    return sorted(map(tuple, df.select("id", "coreness").collect()))


@pytest.mark.parametrize("kind", ["bigint", "int", "string"])
def test_vertices_are_numbered_by_codes_without_a_join(spark, monkeypatch, kind):
    edges = random_graph(spark, 80, 500, 3).select(F.col("src").cast(kind), F.col("dst").cast(kind))
    want = labels(peel.exact_coreness(edges, "local"))
    monkeypatch.setattr(peel, "NUMBERED_EDGES", 0)
    monkeypatch.setattr(peel, "LOCAL_EDGES", 0)
    with monkeypatch.context() as m:
        m.setattr(peel, "numbered", None)
        got = peel.exact_coreness(edges, "auto")
        assert got.schema["id"].dataType == edges.schema["src"].dataType and labels(got) == want
    with monkeypatch.context() as m:  # two ids with one code
        m.setattr(peel, "code", lambda end: F.least(F.col(end).cast("long"), F.lit(70)))
        assert peel.vertex_codes(edges)[1] is None and labels(peel.exact_coreness(edges, "auto")) == want
    monkeypatch.setattr(peel, "CODED_VERTICES", 10)
    assert peel.vertex_codes(edges)[1] is None and labels(peel.exact_coreness(edges, "auto")) == want


def test_words_of_documents_are_shuffled_only_where_a_document_is_there_twice(spark, tmp_path):
    rows = [(1, "a b a"), (2, "b c"), (None, "d"), (None, "e"), (3, None)]
    for k, more in enumerate([[], [(2, "c d"), (3, "a")]]):
        spark.createDataFrame(rows + more, "doc_id long, text string").write.parquet(f"{tmp_path}/{k}/documents.parquet")
    once, twice = (graph(spark, f"{tmp_path}/{k}", "doc_word") for k in (0, 1))
    assert "Exchange" not in once._jdf.queryExecution().toString()
    assert sorted(map(tuple, once.collect())) == [("d1", "wa"), ("d1", "wb"), ("d2", "wb"), ("d2", "wc")]
    assert sorted(map(tuple, twice.collect())) == [("d1", "wa"), ("d1", "wb"), ("d2", "wb"), ("d2", "wc"), ("d2", "wd"), ("d3", "wa")]
