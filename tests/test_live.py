"""Streams that are stopped and started again."""

from sparkgraphs.stream.events import live_components


def test_labels_outlive_the_stream(spark, tmp_path):
    data, kind = str(tmp_path / "arcs"), "src bigint, dst bigint"

    def after(*arcs):
        spark.createDataFrame(arcs, kind).coalesce(1).write.mode("append").parquet(data)
        labels = live_components(spark.readStream.schema(kind).parquet(data), str(tmp_path / "run"))
        groups = {}
        for r in labels.collect():
            groups.setdefault(r.label, set()).add(r.v)
        return sorted(map(sorted, groups.values()))

    assert after((1, 2), (5, 6)) == [[1, 2], [5, 6]]
    assert after((2, 3)) == [[1, 2, 3], [5, 6]]
    assert after((6, 1), (9, 9)) == [[1, 2, 3, 5, 6], [9]]
    assert sorted(p.name for p in (tmp_path / "run" / "labels").iterdir()) == ["1", "2"]


def test_a_stream_without_arcs_has_no_labels(spark, tmp_path):
    (tmp_path / "none").mkdir()
    kind = "src bigint, dst bigint"
    assert live_components(spark.readStream.schema(kind).parquet(str(tmp_path / "none"))).collect() == []
