"""Rows that share a doc_id are one document."""

from sparkgraphs.llm import line_dedup


def test_repeated_rows_are_one_document(spark):
    line = "x" * 40
    few = spark.createDataFrame([(1, line)] + [(2, line)] * 4, "doc_id long, text string")
    assert {(r.doc_id, r.text, r.n_dropped) for r in line_dedup.dedup_lines(few).collect()} == {(1, line, 0), (2, line, 0)}
    more = few.unionByName(spark.createDataFrame([(i, line) for i in (3, 4, 5)], "doc_id long, text string"))
    assert sorted((r.doc_id, r.n_dropped) for r in line_dedup.dedup_lines(more).collect()) == [(1, 1)] + [(2, 1)] * 4 + [(3, 1), (4, 1), (5, 0)]
