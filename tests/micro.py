"""Hand-made graphs."""

from sparkgraphs.model.graph import Graph, from_arcs


def graph(spark, arcs, *, vertices=(), directed=False):
    weighted = bool(arcs) and len(arcs[0]) == 3
    kind = "src bigint, dst bigint" + (", w bigint" if weighted else "")
    df = spark.createDataFrame([tuple(a) for a in arcs], kind)
    ids = sorted({x for a in arcs for x in a[:2]} | set(vertices))
    return from_arcs(df, spark.createDataFrame([(v,) for v in ids], "v bigint"), directed=directed)


def empty(spark):
    return graph(spark, [])


def path(spark, n):
    return graph(spark, [(i, i + 1) for i in range(n - 1)])


def cycle(spark, n):
    return graph(spark, [(i, (i + 1) % n) for i in range(n)])


def clique(spark, n):
    return graph(spark, [(i, j) for i in range(n) for j in range(i)])


def star(spark, n):
    return graph(spark, [(0, i) for i in range(1, n)])


def bow_tie(spark):
    return graph(spark, [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4), (4, 2)])


def values(df, *columns):
    columns = columns or df.columns
    return sorted((tuple(r[c] for c in columns) for r in df.collect()), key=repr)


__all__ = ["Graph", "bow_tie", "clique", "cycle", "empty", "graph", "path", "star", "values"]
