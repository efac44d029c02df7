"""Biconnected components on a breadth-first forest: preorder numbers, low and high, critical edges, components of the rest."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.depth_first import BLOCKS, PIECES, Held, blocks, pieces
from ..core.forest import leaffix, preorder
from ..core.rounds import Rounds, RunStats
from ..model.graph import Graph
from .bfs import bfs
from .connectivity import connectivity


@dataclass
class Blocks:
    """vertex_labels (v, label) and the forest (v, parent, level): an edge's block is the label of its end farther from the root."""

    graph: Graph
    vertex_labels: DataFrame
    forest: DataFrame


def biconnectivity(g: Graph, *, method: str = "hook_jump", stats: RunStats | None = None) -> Blocks:
    rounds = Rounds(g.spark, "blocks", stats)
    component = connectivity(g, method, stats=stats)
    roots = rounds.table(component.groupBy("label").agg(F.min("v").alias("v")).select("v"))
    forest = rounds.table(bfs(g, sources=roots, mode="blocked", with_parent=True, stats=stats).select("v", "parent", F.col("dist").cast("int").alias("level")))
    size = rounds.table(leaffix(forest.withColumn("size", F.lit(1).cast("bigint")), "size", "sum", rounds))
    pre = rounds.table(preorder(forest, size, rounds))
    tree = forest.where("parent IS NOT NULL").select(F.col("v").alias("child"), "parent")
    at = pre.select(F.col("v").alias("dst"), F.col("pre").alias("other"))
    loose = g.edges.select("src", "dst").join(tree.select(F.col("child").alias("src"), F.col("parent").alias("dst")), ["src", "dst"], "left_anti")
    loose = loose.join(tree.select(F.col("parent").alias("src"), F.col("child").alias("dst")), ["src", "dst"], "left_anti")
    near = loose.join(at, "dst").groupBy(F.col("src").alias("v")).agg(F.min("other").alias("lo"), F.max("other").alias("hi"))
    base = forest.join(pre, "v").join(near, "v", "left").select("v", "parent", "level", F.least("pre", "lo").alias("low"), F.greatest("pre", "hi").alias("high"))
    base = rounds.table(base)
    low, high = leaffix(base.drop("high"), "low", "min", rounds), leaffix(base.drop("low"), "high", "max", rounds)
    told = tree.join(low.withColumnRenamed("v", "child"), "child").join(high.withColumnRenamed("v", "child"), "child")
    told = told.join(pre.join(size, "v").select(F.col("v").alias("parent"), F.col("pre").alias("pp"), F.col("size").alias("ps")), "parent")
    critical = rounds.table(told.where("low >= pp AND high < pp + ps").select(F.col("parent").alias("src"), F.col("child").alias("dst")))
    both = critical.unionByName(critical.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    rest = Graph(g.vertices, rounds.table(g.edges.select("src", "dst").join(both, ["src", "dst"], "left_anti")))
    return Blocks(g, rounds.table(connectivity(rest, method, stats=stats)), forest)


def bicc_edge_labels(b: Blocks) -> DataFrame:
    """(src, dst, label_src, label_dst), src < dst: the block's smallest edge."""
    known = b.vertex_labels.join(b.forest.select("v", "level"), "v")
    a, c = known.select(F.col("v").alias("src"), F.struct("level", "label").alias("a")), known.select(F.col("v").alias("dst"), F.struct("level", "label").alias("c"))
    edges = b.graph.half().select("src", "dst").join(a, "src").join(c, "dst").select("src", "dst", F.greatest("a", "c")["label"].alias("block"))
    least = edges.groupBy("block").agg(F.min(F.struct("src", "dst")).alias("s"))
    return edges.join(least, "block").select("src", "dst", F.col("s.src").alias("label_src"), F.col("s.dst").alias("label_dst"))


def articulation_points(b: Blocks) -> DataFrame:
    """(v) in two blocks or more."""
    labels = bicc_edge_labels(b)
    block = F.struct("label_src", "label_dst").alias("block")
    return labels.select(F.col("src").alias("v"), block).unionByName(labels.select(F.col("dst").alias("v"), block)).distinct().groupBy("v").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("v")


def bridges(b: Blocks) -> DataFrame:
    """(src, dst): blocks of one edge."""
    one = bicc_edge_labels(b).groupBy("label_src", "label_dst").agg(F.count(F.lit(1)).alias("n")).where("n = 1")
    return one.select(F.col("label_src").alias("src"), F.col("label_dst").alias("dst"))


def same_block(b: Blocks, first: tuple[int, int], second: tuple[int, int]) -> bool:
    labels = bicc_edge_labels(b)
    pick = lambda e: labels.where((F.col("src") == min(e)) & (F.col("dst") == max(e))).select("label_src", "label_dst").first()
    return pick(first) == pick(second)


def bicc_bfs_check(g: Graph) -> DataFrame:
    """(v) whose removal splits its component: brute force by removal, for small graphs."""
    from .connectivity import hook_jump

    full, out = hook_jump(g), []
    parts = full.agg(F.countDistinct("label").alias("n")).first().n
    for r in g.vertices.collect():
        left = g.induced(g.vertices.where(F.col("v") != r.v))
        now = hook_jump(left).agg(F.countDistinct("label").alias("n")).first().n
        if now > parts - (g.neighbors(r.v).isEmpty()):
            out.append((r.v,))
    return g.spark.createDataFrame(out, "v bigint")


def dfs_blocks(rows: pd.DataFrame) -> pd.DataFrame:
    """(src, dst, label_src, label_dst) of the arcs (src, dst) of whole components, both ways: a depth-first search without recursion."""
    rows = rows[["src", "dst"]].sort_values(["src", "dst"]).drop_duplicates()
    held = Held()
    held.add(rows.src.to_numpy(np.int64), np.ones(len(rows), np.int64), rows.dst.to_numpy(np.int64))
    out = pa.Table.from_batches(held.blocks(), pa.schema([(c, pa.int64()) for c in ("src", "dst", "label_src", "label_dst")]))
    return out.to_pandas()


def bicc_dfs(g: Graph) -> DataFrame:
    """(src, dst, label_src, label_dst) by a depth-first search in each component, in one task: its arcs lie in memory or, if many, in mapped files."""
    from .connectivity import hook_jump

    label = hook_jump(g).select(F.col("v").alias("src"), "label")
    near = g.edges.select("src", "dst").sortWithinPartitions("src", "dst").mapInArrow(pieces, PIECES)
    whole = near.join(label, "src").repartition("label").sortWithinPartitions("label", "src", "low")
    return whole.select("label", "src", "near").mapInArrow(blocks, BLOCKS)
