"""The fitting sample of skewed texts."""

from sparkgraphs.llm.common import bounded_sample


def test_sample_passes_over_long_texts(spark):
    rows = [(i, "y" * (500 if i % 2 else 10), i % 3) for i in range(20)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, label int")
    texts, labels = bounded_sample(docs.select("doc_id", "text"), docs.select("doc_id", "label"), "label", rows=20, max_bytes=100)
    assert texts == ["y" * 10] * 10 and sorted(labels) == sorted(i % 3 for i in range(0, 20, 2))
    assert bounded_sample(docs.select("doc_id", "text"), docs.select("doc_id", "label"), "label", rows=20, max_bytes=5) == ([], [])
