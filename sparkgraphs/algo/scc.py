"""Strongly connected components: trimming, one giant search, then batches of overlapping searches; and the methods compared with."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.multi_search import multi_search
from ..core.priority import SPAN, prio
from ..core.rounds import Rounds, RunStats
from ..model.graph import Graph


def _alive_edges(g: Graph, state: DataFrame) -> DataFrame:
    open_ = state.where("scc IS NULL").select("v", "label")
    a, b = open_.select(F.col("v").alias("src"), F.col("label").alias("ls")), open_.select(F.col("v").alias("dst"), F.col("label").alias("ld"))
    return g.edges.select("src", "dst").join(a, "src").join(b, "dst").where("ls = ld").select("src", "dst")


def _trim(edges: DataFrame, state: DataFrame, rounds: Rounds, most: int | None) -> tuple[DataFrame, DataFrame]:
    """Vertices without arcs in or out are components of their own, again and again."""
    r, seen = 0, {"trimmed": 1}
    while seen["trimmed"] and (most is None or r < most):
        r += 1
        both = edges.select(F.col("src").alias("v")).intersect(edges.select(F.col("dst").alias("v"))).withColumn("inner", F.lit(True))
        alone = F.col("scc").isNull() & F.col("inner").isNull()
        state, seen = rounds.keep(state.join(both, "v", "left").select("v", "label", F.when(alone, F.col("v")).otherwise(F.col("scc")).alias("scc"), alone.alias("fresh")), "trim", trimmed=F.count_if("fresh"))
        gone = state.where("scc IS NULL").select("v")
        edges = rounds.table(edges.join(gone.withColumnRenamed("v", "src"), "src", "left_semi").join(gone.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "dst"))
        state = state.drop("fresh")
    return edges, state


def _settle(state: DataFrame, f: DataFrame, b: DataFrame, rounds: Rounds) -> tuple[DataFrame, int]:
    """Vertices in both searches of a centre are done; others are split by what reached them and from which side."""
    both = f.join(b, ["v", "center"]).groupBy("v").agg(F.min("center").alias("done"))
    side = f.groupBy("v").agg(F.min("center").alias("f")).join(b.groupBy("v").agg(F.min("center").alias("b")), "v", "full")
    joined = state.join(both, "v", "left").join(side, "v", "left")
    label = F.xxhash64("label", F.coalesce("f", F.lit(-1)), F.coalesce("b", F.lit(-1)))
    scc = F.coalesce("scc", "done")
    kept, seen = rounds.keep(joined.select("v", F.when(F.col("f").isNotNull() | F.col("b").isNotNull(), label).otherwise(F.col("label")).alias("label"), scc.alias("scc")), "settle", open=F.count_if(F.col("scc").isNull()))
    return kept, seen["open"]


def scc(g: Graph, *, beta_growth: float = 1.5, trim: bool = True, max_trim_rounds: int | None = None, first_pivot: bool = True, seed: int = 42, stats: RunStats | None = None) -> DataFrame:
    """(v, label): the smallest id of each strongly connected component."""
    rounds = Rounds(g.spark, "scc", stats)
    state = rounds.table(g.vertices.select("v", F.lit(0).cast("bigint").alias("label"), F.lit(None).cast("bigint").alias("scc")))
    edges, n = g.edges.select("src", "dst"), g.vertices.count()
    if trim:
        edges, state = _trim(edges, state, rounds, max_trim_rounds)
    left = state.where("scc IS NULL").count()
    if first_pivot and left:
        into, out = edges.groupBy(F.col("dst").alias("v")).agg(F.count(F.lit(1)).alias("i")), edges.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("o"))
        pivot = state.where("scc IS NULL").join(into, "v", "left").join(out, "v", "left").orderBy(F.desc(F.coalesce("i", F.lit(0)) * F.coalesce("o", F.lit(0))), "v").limit(1).select("v")
        state, left = _search(edges, rounds.table(pivot), state, rounds)
    order, batch = prio(seed, "v"), 0
    steps = math.ceil(math.log(max(2, n)) / math.log(beta_growth)) + 1
    while left:
        bound = min(SPAN, int(SPAN * beta_growth**batch / n)) if batch < steps else SPAN
        centers = rounds.table(state.where(F.col("scc").isNull() & (order < bound)).select("v"))
        batch += 1
        if centers.isEmpty():
            continue
        edges = rounds.table(_alive_edges(g, state))
        state, left = _search(edges, centers, state, rounds)
    return _canonical(state.select("v", F.col("scc").alias("label")))


def _search(edges: DataFrame, centers: DataFrame, state: DataFrame, rounds: Rounds) -> tuple[DataFrame, int]:
    labels = state.where("scc IS NULL").select("v", "label")
    forward = multi_search(edges, centers, labels, rounds, slot="forward")
    backward = multi_search(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")), centers, labels, rounds, slot="backward")
    return _settle(state, forward, backward, rounds)


def _canonical(labels: DataFrame) -> DataFrame:
    least = labels.groupBy("label").agg(F.min("v").alias("least"))
    return labels.join(least, "label").select("v", F.col("least").alias("label"))


def scc_fwbw_trim(g: Graph, *, seed: int = 42, stats: RunStats | None = None) -> DataFrame:
    """Forward-backward with trimming: each subproblem searches from its first vertex, all subproblems at once."""
    rounds = Rounds(g.spark, "fwbw", stats)
    state = rounds.table(g.vertices.select("v", F.lit(0).cast("bigint").alias("label"), F.lit(None).cast("bigint").alias("scc")))
    left = 1
    while left:
        edges, state = _trim(rounds.table(_alive_edges(g, state)), state, rounds, None)
        rank = F.struct(prio(seed, "v"), F.col("v").alias("v"))
        centers = rounds.table(state.where("scc IS NULL").groupBy("label").agg(F.min(rank).alias("s")).select("s.v"))
        if centers.isEmpty():
            break
        state, left = _search(edges, centers, state, rounds)
    return _canonical(state.select("v", F.col("scc").alias("label")))


def scc_staged(g: Graph, *, stats: RunStats | None = None) -> DataFrame:
    """Trim, one pivot, then colouring: the largest id that reaches a vertex is its colour; a colour's root collects backwards."""
    rounds = Rounds(g.spark, "staged", stats)
    state = rounds.table(g.vertices.select("v", F.lit(0).cast("bigint").alias("label"), F.lit(None).cast("bigint").alias("scc")))
    edges, state = _trim(g.edges.select("src", "dst"), state, rounds, None)
    left = state.where("scc IS NULL").count()
    while left:
        color, seen = rounds.keep(state.where("scc IS NULL").select("v", F.col("v").alias("c"), F.lit(True).alias("moved")), "color", moved=F.count_if("moved"))
        while seen["moved"]:
            got = color.where("moved").select(F.col("v").alias("src"), "c").join(edges, "src").groupBy(F.col("dst").alias("v")).agg(F.max("c").alias("n"))
            more = F.coalesce(F.col("n") > F.col("c"), F.lit(False))
            color, seen = rounds.keep(color.join(got, "v", "left").select("v", F.when(more, F.col("n")).otherwise(F.col("c")).alias("c"), more.alias("moved")), "color", moved=F.count_if("moved"))
        labels = color.select("v", F.col("c").alias("label"))
        back = multi_search(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")), labels.where("v = label").select("v"), labels, rounds, slot="back")
        state, seen = rounds.keep(state.join(back.select("v", "center"), "v", "left").select("v", "label", F.coalesce("scc", "center").alias("scc")), "staged", open=F.count_if(F.col("scc").isNull()))
        left = seen["open"]
        edges, state = _trim(rounds.table(_alive_edges(g, state)), state, rounds, None)
        left = state.where("scc IS NULL").count()
    return _canonical(state.select("v", F.col("scc").alias("label")))


def largest_scc(g: Graph) -> DataFrame:
    """(v) of the component of the vertex with the largest product of degrees: two searches."""
    rounds = Rounds(g.spark, "largest", None)
    state = rounds.table(g.vertices.select("v", F.lit(0).cast("bigint").alias("label"), F.lit(None).cast("bigint").alias("scc")))
    into, out = g.edges.groupBy(F.col("dst").alias("v")).agg(F.count(F.lit(1)).alias("i")), g.edges.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("o"))
    pivot = rounds.table(into.join(out, "v").orderBy(F.desc(F.col("i") * F.col("o")), "v").limit(1).select("v"))
    return _search(g.edges.select("src", "dst"), pivot, state, rounds)[0].where("scc IS NOT NULL").select("v")
