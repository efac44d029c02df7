"""Low-diameter ball decomposition, and the spanner made of it."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.edge_map import edge_map
from ..core.prims import index
from ..core.priority import shift
from ..core.rounds import Rounds, RunStats
from ..model.graph import Graph

MICRO = 1_000_000
TIES = ("min_center", "arbitrary", "fractional")


def ball_decompose(g: Graph, beta: float = 0.2, *, seed: int = 42, ties: str = "min_center", permute: bool = True, stats: RunStats | None = None) -> DataFrame:
    """(v, center, parent, arrival): vertices start balls at shifted times and balls claim what they reach first.

    Ties within a round go to the smallest centre, to the smallest claiming neighbour (arbitrary), or to the exact shifted time (fractional).
    Without `permute` start times are handed out in the order of the ids.
    """
    if ties not in TIES or beta <= 0:
        raise ValueError(f"ties is one of {TIES}, beta over 0")
    rounds = Rounds(g.spark, "ball", stats)
    drawn = rounds.table(g.vertices.select("v", shift(seed, beta, "v").alias("dq")))
    if not permute:
        late = index(drawn.select((-F.col("dq")).alias("m"), F.col("v").alias("was")), ["m", "was"], "pos").select("pos", (-F.col("m")).alias("dq"))
        drawn = rounds.table(index(drawn.select("v"), ["v"], "pos").join(late, "pos").select("v", "dq"))
    top = drawn.agg(F.max("dq").alias("t")).first().t or 0
    gone = F.lit(top) - F.col("dq")
    frac = {"fractional": gone % MICRO}.get(ties, F.lit(0).cast("bigint"))
    none = F.lit(None).cast("bigint")
    state = drawn.select("v", F.expr(f"({top} - dq) div {MICRO}").alias("start"), frac.alias("frac"), none.alias("center"), none.alias("parent"), none.alias("arrival"), none.alias("cfrac"))
    state, seen = rounds.keep(state, "state", next=F.min("start"), claimed=F.count("center"))
    r = seen["next"]
    while r is not None:
        rank = {"arbitrary": ["src", "center", "cfrac"]}.get(ties, ["cfrac", "center", "src"])
        claims = edge_map(g.edges, state.where(F.col("arrival") == r - 1).select("v", "center", "cfrac"), [F.min(F.struct(*rank)).alias("claim")], live=state.where("center IS NULL"))
        own = F.struct(F.col("frac").alias("cfrac"), F.col("v").alias("center"), F.col("v").alias("src")) if ties != "arbitrary" else F.struct(F.col("v").alias("src"), F.col("v").alias("center"), F.col("frac").alias("cfrac"))
        joined = state.join(claims, "v", "left").withColumn("own", F.when(F.col("start") == r, own))
        first = F.least("claim", "own")
        got = F.col("center").isNull() & first.isNotNull()
        set_ = lambda old, new: F.when(got, new).otherwise(F.col(old)).alias(old)
        state, seen = rounds.keep(
            joined.select("v", "start", "frac", set_("center", first["center"]), set_("parent", first["src"]), set_("arrival", F.lit(r).cast("bigint")), set_("cfrac", first["cfrac"])),
            "state", new=F.count_if(F.col("arrival") == r), next=F.min(F.when(F.col("center").isNull(), F.col("start"))),
        )
        r = (r + 1) if seen["new"] and seen["next"] is not None else seen["next"]
    return state.select("v", "center", "parent", "arrival")


def spanner(g: Graph, k: int = 4, *, inter: str = "cluster_pair", seed: int = 42, stats: RunStats | None = None) -> DataFrame:
    """(src, dst), src < dst: tree edges of a decomposition with beta = ln n / 2k, and edges between balls.

    inter: one edge for each pair of adjacent balls, or (boundary_vertex) for each boundary vertex and ball next to it.
    """
    n = max(2, g.vertices.count())
    balls = Rounds(g.spark, "spanner").table(ball_decompose(g, math.log(n) / (2 * k), seed=seed, stats=stats))
    low, high = F.least("v", "parent").alias("src"), F.greatest("v", "parent").alias("dst")
    tree = balls.where("v <> parent").select(low, high)
    at = lambda c: balls.select(F.col("v").alias(c), F.col("center").alias(f"c_{c}"))
    across = g.edges.select("src", "dst").join(at("src"), "src").join(at("dst"), "dst").where("c_src <> c_dst")
    pair = F.struct(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
    groups = [F.least("c_src", "c_dst"), F.greatest("c_src", "c_dst")] if inter == "cluster_pair" else ["src", "c_dst"]
    return tree.unionByName(across.groupBy(*groups).agg(F.min(pair).alias("e")).select("e.src", "e.dst")).distinct()
