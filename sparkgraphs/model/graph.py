"""Graphs as DataFrames: vertices (v) and arcs (src, dst[, w]); undirected graphs store both orientations."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..core.priority import prio
from ..core.rounds import Rounds


@dataclass
class Graph:
    vertices: DataFrame
    edges: DataFrame
    directed: bool = False
    name: str = "graph"

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @property
    def weighted(self) -> bool:
        return "w" in self.edges.columns

    def check_schema(self) -> None:
        kinds = dict(self.edges.dtypes)
        if kinds.get("src") != "bigint" or kinds.get("dst") != "bigint" or dict(self.vertices.dtypes).get("v") != "bigint":
            raise TypeError("vertices need v, edges need src and dst, all BIGINT")

    def layout(self, partitions: int | None = None) -> Graph:
        """Written once, in buckets by source and sorted: joins by source do not shuffle the edges again."""
        keep = Rounds(self.spark, self.name)
        return replace(self, vertices=keep.table(self.vertices), edges=keep.bucketed(self.edges, "src", "dst", partitions=partitions))

    def half(self) -> DataFrame:
        """Each undirected edge once."""
        return self.edges.where("src < dst")

    def transpose(self) -> Graph:
        rest = [c for c in self.edges.columns if c not in ("src", "dst")]
        return replace(self, edges=self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *rest))

    def symmetrised(self) -> Graph:
        return from_arcs(self.edges, self.vertices, directed=False, name=f"{self.name}_sym")

    def degrees(self) -> DataFrame:
        counts = self.edges.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("degree"))
        return self.vertices.select("v").join(counts, "v", "left").select("v", F.coalesce("degree", F.lit(0)).alias("degree"))

    def induced(self, keep: DataFrame) -> Graph:
        """The subgraph on the vertices of `keep` (v)."""
        ends = lambda e, c: e.join(keep.select(F.col("v").alias(c)), c, "left_semi")
        columns = self.edges.columns
        return replace(self, vertices=self.vertices.join(keep.select("v"), "v", "left_semi"), edges=ends(ends(self.edges, "src"), "dst").select(columns))

    def edge_filter(self, pred: Column | str) -> Graph:
        return replace(self, edges=self.edges.where(pred))

    def remove_edges(self, gone: DataFrame) -> Graph:
        return replace(self, edges=self.edges.join(gone.select("src", "dst"), ["src", "dst"], "left_anti").select(self.edges.columns))

    def neighbors(self, v: int) -> DataFrame:
        return self.edges.where(F.col("src") == v).select(F.col("dst").alias("v"))

    def with_weights(self, seed: int = 42, spread: int | None = None) -> Graph:
        """Uniform integers in [1, ln n), the same in both orientations."""
        import math

        n = spread or max(1, math.ceil(math.log(max(2, self.vertices.count()))) - 1)
        w = 1 + prio(seed, F.least("src", "dst"), F.greatest("src", "dst")) % n
        return replace(self, edges=self.edges.select("src", "dst", w.alias("w")))

    def map_weights(self, f: Callable[[Column], Column]) -> Graph:
        return replace(self, edges=self.edges.withColumn("w", f(F.col("w"))))


def simplify(edges: DataFrame) -> DataFrame:
    """No self-loops, no repeated arcs; of weights the least stays."""
    edges = edges.where("src <> dst")
    if "w" in edges.columns:
        return edges.groupBy("src", "dst").agg(F.min("w").alias("w"))
    return edges.select("src", "dst").distinct()


def from_arcs(arcs: DataFrame, vertices: DataFrame | None = None, *, directed: bool = False, name: str = "graph") -> Graph:
    """A simple graph of (src, dst[, w]) rows; vertices default to the endpoints."""
    rest = [c for c in arcs.columns if c == "w"]
    arcs = arcs.select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst"), *rest)
    if not directed:
        arcs = arcs.unionByName(arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *rest))
    edges = simplify(arcs)
    if vertices is None:
        ends = edges.select(F.col("src").alias("v"))
        vertices = (ends if not directed else ends.unionByName(edges.select(F.col("dst").alias("v")))).distinct()
    return Graph(vertices, edges, directed, name)
