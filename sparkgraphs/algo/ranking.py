"""PageRank: one iteration, to convergence, and by deltas."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.rounds import Rounds, RunStats
from ..model.graph import Graph


def _start(g: Graph) -> tuple[DataFrame, int]:
    """(v, out, rank) with equal ranks, and the number of vertices."""
    n = g.vertices.count()
    return g.degrees().select("v", F.col("degree").alias("out"), F.lit(1.0 / max(1, n)).alias("rank")), n


def _step(g: Graph, state: DataFrame, n: int, damping: float, dangling: str, mode: str) -> DataFrame:
    """(v, out, rank, old): ranks over out-degrees are summed at the targets; push_raw shuffles every contribution."""
    parts = state.where("out > 0").select(F.col("v").alias("src"), (F.col("rank") / F.col("out")).alias("part")).join(g.edges, "src").select(F.col("dst").alias("v"), "part")
    if mode == "push_raw":
        parts = parts.repartition("v")
    sums = parts.groupBy("v").agg(F.sum("part").alias("got"))
    base = F.lit((1 - damping) / max(1, n))
    new = base + damping * F.coalesce("got", F.lit(0.0))
    joined = state.join(sums, "v", "left")
    if dangling == "redistribute":
        lost = F.broadcast(state.agg(F.coalesce(F.sum(F.when(F.col("out") == 0, F.col("rank"))), F.lit(0.0)).alias("lost")))
        joined, new = joined.crossJoin(lost), new + damping * F.col("lost") / max(1, n)
    return joined.select("v", "out", new.alias("rank"), F.col("rank").alias("old"))


def pagerank_iteration(g: Graph, ranks: DataFrame | None = None, *, damping: float = 0.85, dangling: str = "drop", mode: str = "pull") -> DataFrame:
    """(v, rank) after one iteration from `ranks` (v, rank), or from equal ranks."""
    state, n = _start(g)
    if ranks is not None:
        state = state.drop("rank").join(ranks.select("v", "rank"), "v")
    return _step(g, state, n, damping, dangling, mode).select("v", "rank")


def pagerank(g: Graph, *, damping: float = 0.85, eps: float = 1e-6, max_iter: int = 100, dangling: str = "drop", mode: str = "pull", stats: RunStats | None = None) -> DataFrame:
    """(v, rank) once an iteration changes the ranks by less than eps in sum."""
    rounds = Rounds(g.spark, "pagerank", stats)
    state, n = _start(g)
    state = rounds.table(state)
    for _ in range(max_iter):
        new = _step(g, state, n, damping, dangling, mode)
        kept, seen = rounds.keep(new, "state", residual=F.sum(F.abs(F.col("rank") - F.col("old"))))
        state = kept.drop("old")
        if (seen["residual"] or 0) < eps:
            break
    return state.select("v", "rank")


def pagerank_delta(g: Graph, *, damping: float = 0.85, eps: float = 1e-6, local_eps: float = 0.01, max_iter: int = 100, stats: RunStats | None = None) -> DataFrame:
    """(v, rank): only vertices whose change is over local_eps of their rank send it on."""
    rounds = Rounds(g.spark, "delta", stats)
    start, n = _start(g)
    base = (1 - damping) / max(1, n)
    # the first change is that of a whole iteration from equal ranks
    first = _step(g, start, n, damping, "drop", "pull").select("v", "out", "rank", (F.col("rank") - F.col("old")).alias("delta"))
    state, seen = rounds.keep(first, "state", change=F.sum(F.abs("delta")), active=F.count_if(F.abs("delta") > local_eps * F.col("rank")))
    for _ in range(max_iter):
        if not seen["active"] or (seen["change"] or 0) < eps:
            break
        moving = F.abs("delta") > local_eps * F.col("rank")
        parts = state.where(moving & (F.col("out") > 0)).select(F.col("v").alias("src"), (F.col("delta") / F.col("out")).alias("part")).join(g.edges, "src")
        sums = parts.groupBy(F.col("dst").alias("v")).agg(F.sum("part").alias("got"))
        got = damping * F.coalesce("got", F.lit(0.0))
        # what is too small to be sent waits in delta
        moved = state.select("v", "out", "rank", "delta").join(sums, "v", "left").select("v", "out", (F.col("rank") + got).alias("rank"), (got + F.when(moving, 0.0).otherwise(F.col("delta"))).alias("delta"), got.alias("got"))
        state, seen = rounds.keep(moved, "state", change=F.sum(F.abs("got")), active=F.count_if(F.abs("delta") > local_eps * F.col("rank")))
    return state.select("v", F.greatest(F.col("rank"), F.lit(base)).alias("rank"))
