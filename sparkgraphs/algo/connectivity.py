"""Connected components, by contraction of ball decompositions and by the methods it is compared with; spanning forests."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.contract import contract, pointer_jump, relabel_edges
from ..core.rounds import Rounds, RunStats
from ..model.graph import Graph
from .ball import ball_decompose
from .bfs import bfs

METHODS = ("contract", "hook_jump", "label_prop", "alternating", "bfs_then_rest")
#: Graphs of at most so many arcs are finished by hooking: their rounds cost more than their rows.
LOCAL_LIMIT = 4_000


def connectivity(g: Graph, method: str = "contract", *, beta: float = 0.2, seed: int = 42, local_limit: int = LOCAL_LIMIT, stats: RunStats | None = None) -> DataFrame:
    """(v, label): the smallest id of each vertex's component."""
    if method == "contract":
        return _contract(g, beta, seed, local_limit, stats, False)[0]
    return {"hook_jump": hook_jump, "label_prop": label_prop, "alternating": alternating, "bfs_then_rest": bfs_then_rest}[method](g, stats=stats)


def spanning_forest(g: Graph, *, beta: float = 0.2, seed: int = 42, local_limit: int = LOCAL_LIMIT, stats: RunStats | None = None) -> DataFrame:
    """(src, dst), src < dst: the trees that the levels of contraction grow, as edges of the graph itself."""
    return _contract(g, beta, seed, local_limit, stats, True)[1]


def _contract(g: Graph, beta: float, seed: int, local_limit: int, stats: RunStats | None, forest: bool) -> tuple[DataFrame, DataFrame | None]:
    rounds = Rounds(g.spark, "contract", stats)
    plain = g.edges.select("src", "dst")
    edges = rounds.table(plain.withColumns({"a": F.least("src", "dst"), "b": F.greatest("src", "dst")}) if forest else plain)
    label, trees, level = g.vertices.select("v", F.col("v").alias("label")), None, 0
    left = edges.count()
    while left:
        ends = edges.select(F.col("src").alias("v")).distinct()
        if left <= local_limit:
            grown, tree = hook_edges(edges, ends, rounds, forest)
        else:
            grown = rounds.table(ball_decompose(Graph(ends, edges.select("src", "dst")), beta, seed=seed + level, stats=stats))
            tree = grown.where("v <> parent").select(F.col("parent").alias("src"), F.col("v").alias("dst")).join(edges, ["src", "dst"]).select("a", "b") if forest else None
            grown = grown.select("v", F.col("center").alias("label"))
        if forest:
            part = rounds.table(tree.select(F.col("a").alias("src"), F.col("b").alias("dst")))
            trees = part if trees is None else trees.unionByName(part)
        up = grown.select(F.col("v").alias("label"), F.col("label").alias("up"))
        label = rounds.table(label.join(up, "label", "left").select("v", F.coalesce("up", "label").alias("label")))
        edges, seen = rounds.keep(contract(edges, grown), "edges", arcs=F.count(F.lit(1)))
        left, level = seen["arcs"], level + 1
    least = label.groupBy("label").agg(F.min("v").alias("least"))
    label = label.join(least, "label").select("v", F.col("least").alias("label"))
    if forest and trees is None:
        trees = g.spark.createDataFrame([], "src bigint, dst bigint")
    return label, trees


def hook_edges(edges: DataFrame, ends: DataFrame, rounds: Rounds, forest: bool) -> tuple[DataFrame, DataFrame | None]:
    """One hooking of every vertex to its smallest neighbour, jumped to roots, with the edges that hooked."""
    rest = ["a", "b"] if forest else []
    best = edges.groupBy("src").agg(F.min(F.struct("dst", *rest)).alias("s")).where("s.dst < src")
    best = rounds.table(best.select(F.col("src").alias("v"), F.col("s.dst").alias("p"), *[F.col(f"s.{c}").alias(c) for c in rest]))
    parent = ends.join(best.select("v", "p"), "v", "left").select("v", F.coalesce("p", "v").alias("p"))
    label = pointer_jump(parent, rounds).withColumnRenamed("p", "label")
    return rounds.table(label), best.select("a", "b") if forest else None


def hook_jump(g: Graph, *, stats: RunStats | None = None) -> DataFrame:
    """Hook to the smallest neighbour, jump, relabel, repeat."""
    rounds = Rounds(g.spark, "hook", stats)
    edges, label, left = g.edges.select("src", "dst"), g.vertices.select("v", F.col("v").alias("label")), 1
    while left:
        grown, _ = hook_edges(edges, edges.select(F.col("src").alias("v")).distinct(), rounds, False)
        up = grown.select(F.col("v").alias("label"), F.col("label").alias("up"))
        label = rounds.table(label.join(up, "label", "left").select("v", F.coalesce("up", "label").alias("label")))
        edges, seen = rounds.keep(relabel_edges(edges, grown).distinct(), "edges", arcs=F.count(F.lit(1)))
        left = seen["arcs"]
    return label


def label_prop(g: Graph, *, stats: RunStats | None = None) -> DataFrame:
    """The smallest label spreads, a step a round."""
    from ..core.edge_map import edge_map

    rounds = Rounds(g.spark, "label_prop", stats)
    state, seen = rounds.keep(g.vertices.select("v", F.col("v").alias("label"), F.lit(True).alias("active")), "state", active=F.count_if("active"))
    while seen["active"]:
        found = edge_map(g.edges, state.where("active").select("v", "label"), [F.min("label").alias("new")])
        lower = F.coalesce(F.col("new") < F.col("label"), F.lit(False))
        state, seen = rounds.keep(state.join(found, "v", "left").select("v", F.when(lower, F.col("new")).otherwise(F.col("label")).alias("label"), lower.alias("active")), "state", active=F.count_if("active"))
    return state.select("v", "label")


def alternating(g: Graph, *, stats: RunStats | None = None) -> DataFrame:
    """Stars to larger and to smaller neighbours in turn, until only stars are left."""
    rounds = Rounds(g.spark, "stars", stats)
    size = {"arcs": F.count(F.lit(1)), "sign": F.bit_xor(F.xxhash64("u", "m"))}
    edges, seen = rounds.keep(g.half().select(F.col("dst").alias("u"), F.col("src").alias("m")), "edges", **size)
    last = None
    while seen["arcs"] and seen["sign"] != last:
        last = seen["sign"]
        both = edges.select("u", F.col("m").alias("x")).unionByName(edges.select(F.col("m").alias("u"), F.col("u").alias("x")))
        least = both.groupBy("u").agg(F.least(F.min("x"), F.col("u")).alias("m"))
        large = both.where("x > u").join(least, "u").select(F.col("x").alias("u"), "m").where("u <> m").distinct()
        below = large.groupBy("u").agg(F.min("m").alias("low"))
        joined = large.join(below, "u")
        small = joined.select(F.col("m").alias("u"), F.col("low").alias("m")).unionByName(below.select("u", F.col("low").alias("m"))).where("u <> m").distinct()
        edges, seen = rounds.keep(small, "edges", **size)
    return g.vertices.select("v").join(edges.groupBy(F.col("u").alias("v")).agg(F.min("m").alias("m")), "v", "left").select("v", F.coalesce("m", "v").alias("label"))


def bfs_then_rest(g: Graph, *, stats: RunStats | None = None) -> DataFrame:
    """A search from the vertex of the largest degree settles the giant component; hooking does the rest."""
    hub = g.degrees().orderBy(F.desc("degree"), "v").limit(1).first()
    if hub is None:
        return g.vertices.select("v", F.col("v").alias("label"))
    giant = Rounds(g.spark, "giant").table(bfs(g, hub.v, mode="blocked", stats=stats).where("dist IS NOT NULL").select("v"))
    rest = g.induced(g.vertices.join(giant, "v", "left_anti"))
    return giant.withColumn("label", F.lit(giant.agg(F.min("v").alias("m")).first().m)).unionByName(hook_jump(rest, stats=stats))


def largest_component(g: Graph, method: str = "hook_jump") -> DataFrame:
    """(v) of the component with the most vertices; the smallest label wins ties."""
    label = connectivity(g, method)
    top = label.groupBy("label").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "label").limit(1)
    return label.join(F.broadcast(top.select("label")), "label", "left_semi").select("v")
