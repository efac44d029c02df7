"""Minimum spanning forests: Boruvka rounds, after filtering; and the grouped union-find baseline."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.contract import pointer_jump, relabel_edges
from ..core.prims import prefix_cut
from ..core.rounds import Rounds, RunStats
from ..model.graph import Graph

FIELDS = ("w", "a", "b")


def boruvka(edges: DataFrame, rounds: Rounds) -> tuple[DataFrame | None, DataFrame | None]:
    """The forest (w, a, b) of edges (src, dst, w, a, b), each once, and (v, label) of its trees. The order (w, a, b) is total, so the
    forest is unique; of two vertices that pick the same edge the smaller is the root."""
    forest = label = None
    left = edges.count()
    while left:
        rank = F.struct(*FIELDS)
        both = edges.select(F.col("src").alias("v"), F.struct(*FIELDS, F.col("dst").alias("o")).alias("s")).unionByName(edges.select(F.col("dst").alias("v"), F.struct(*FIELDS, F.col("src").alias("o")).alias("s")))
        best = rounds.table(both.groupBy("v").agg(F.min("s").alias("s")).select("v", F.col("s.o").alias("p"), *[F.col(f"s.{c}").alias(c) for c in FIELDS]))
        won = rounds.table(best.select(*FIELDS).distinct())
        forest = won if forest is None else forest.unionByName(won)
        back = best.select(F.col("v").alias("p"), F.col("p").alias("pp"))
        parent = best.join(back, "p", "left").select("v", F.when((F.col("pp") == F.col("v")) & (F.col("v") < F.col("p")), F.col("v")).otherwise(F.col("p")).alias("p"))
        now = rounds.table(pointer_jump(parent, rounds).withColumnRenamed("p", "label"))
        if label is None:
            label = now
        else:
            up = now.select(F.col("v").alias("label"), F.col("label").alias("up"))
            label = rounds.table(label.join(up, "label", "left").select("v", F.coalesce("up", "label").alias("label")))
        merged = relabel_edges(edges, now).select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), *FIELDS)
        edges, seen = rounds.keep(merged.groupBy("src", "dst").agg(F.min(rank).alias("s")).select("src", "dst", "s.*"), f"boruvka{id(forest)}", arcs=F.count(F.lit(1)))
        left = seen["arcs"]
    return forest, label


def msf(g: Graph, *, method: str = "filtered", filter_steps: int = 4, prefix_factor: float = 1.5, stats: RunStats | None = None) -> DataFrame:
    """(src, dst, w), src < dst: the forest under the order (w, src, dst).

    filtered  the lightest 3n/2 edges first; then the rest without what their trees join, a few times; then all that is left
    boruvka   no filtering
    kruskal   per component by union-find in grouped Arrow batches, for components that fit a task
    """
    if method == "kruskal":
        return msf_kruskal(g, stats=stats)
    rounds = Rounds(g.spark, "msf", stats)
    edges = rounds.table(g.half().select("src", "dst", "w", F.col("src").alias("a"), F.col("dst").alias("b")))
    n, forest, step = g.vertices.count(), None, 0
    left = edges.count()
    while left:
        cut = method == "filtered" and step < filter_steps
        part = prefix_cut(edges, "w", max(1, int(prefix_factor * n)), left)[0] if cut else edges
        trees, label = boruvka(rounds.table(part) if cut else part, rounds)
        forest = trees if forest is None else forest.unionByName(trees)
        every = edges.select(F.col("src").alias("v")).unionByName(edges.select(F.col("dst").alias("v"))).distinct()
        full = every.join(label, "v", "left").select("v", F.coalesce("label", "v").alias("label"))
        edges, seen = rounds.keep(relabel_edges(edges, full), "filter", arcs=F.count(F.lit(1)))
        left, step = seen["arcs"], step + 1
    if forest is None:
        return g.half().select("src", "dst", "w")
    return forest.select(F.col("a").alias("src"), F.col("b").alias("dst"), "w")


def msf_kruskal(g: Graph, *, stats: RunStats | None = None) -> DataFrame:
    from .connectivity import hook_jump

    label = hook_jump(g, stats=stats).select(F.col("v").alias("src"), "label")
    kind = dict(g.edges.dtypes)["w"]

    def solve(rows: pd.DataFrame) -> pd.DataFrame:
        up: dict[int, int] = {}

        def root(x: int) -> int:
            while up.setdefault(x, x) != x:
                up[x] = x = up[up[x]]
            return x

        kept = []
        for e in rows.sort_values(["w", "src", "dst"]).itertuples(index=False):
            a, b = root(e.src), root(e.dst)
            if a != b:
                up[a] = b
                kept.append((e.src, e.dst, e.w))
        return pd.DataFrame(kept, columns=["src", "dst", "w"])

    return g.half().join(label, "src").groupBy("label").applyInPandas(solve, f"src bigint, dst bigint, w {kind}")


def forest_weight(forest: DataFrame) -> DataFrame:
    return forest.agg(F.count(F.lit(1)).alias("edges"), F.sum("w").alias("weight"))

