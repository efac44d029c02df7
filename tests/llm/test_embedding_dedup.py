"""Embedding links: repeated ids, clashing columns, and recall of planted pairs among fifty thousand vectors."""

import numpy as np

from sparkgraphs.llm import embedding_dedup


def test_an_id_joins_the_components_of_its_rows(spark):
    rng = np.random.default_rng(3)
    a, b = (rng.standard_normal(32).tolist() for _ in range(2))
    rows = [(5, a, 0), (3, a, 1), (5, b, 2), (7, b, 3), (9, [1.0] * 32, 4), (None, a, 5)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, n_links int")
    out = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in embedding_dedup.near_duplicates(df).collect() if r.vec_id is not None}
    assert out == {5: (2, 3, False), 3: (1, 3, True), 7: (1, 3, False), 9: (0, 9, True)}


def test_recall_of_planted_pairs(spark):
    """Pairs just over the threshold, where misses are likeliest; all others are far apart."""
    rng = np.random.default_rng(11)
    n, planted, dim = 50_000, 10_000, 64
    x = rng.standard_normal((n, dim)).astype(np.float32).astype(float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    for i in range(planted):  # 2i and 2i + 1 at a cosine of 0.9501 to 0.956
        other = rng.standard_normal(dim)
        other -= (other @ x[2 * i]) * x[2 * i]
        other /= np.linalg.norm(other)
        c = rng.uniform(0.9501, 0.956)
        x[2 * i + 1] = c * x[2 * i] + np.sqrt(1 - c * c) * other
    import pyarrow as pa

    table = pa.table({"vec_id": pa.array(np.arange(n)), "embedding": pa.FixedSizeListArray.from_arrays(pa.array(x.reshape(-1)), dim).cast(pa.list_(pa.float64()))})
    out = embedding_dedup.near_duplicates(spark.createDataFrame(table)).toPandas().sort_values("vec_id")
    links = out.n_links.to_numpy()
    assert (links[: 2 * planted] >= 1).mean() >= 0.9999 and (links[2 * planted :] == 0).all()
