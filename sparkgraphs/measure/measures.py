"""Cost and accuracy measures of runs and results."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..algo.connectivity import hook_jump
from ..core.rounds import RunStats
from ..model.graph import Graph


def graph_stats(g: Graph) -> DataFrame:
    """(graph, n, arcs, max_degree, components)"""
    top = g.edges.groupBy("src").agg(F.count(F.lit(1)).alias("k")).agg(F.max("k").alias("max_degree"))
    parts = hook_jump(g).agg(F.countDistinct("label").alias("components"))
    counts = g.vertices.agg(F.count(F.lit(1)).alias("n")).crossJoin(g.edges.agg(F.count(F.lit(1)).alias("arcs")))  # single rows
    return counts.crossJoin(top).crossJoin(parts).select(F.lit(g.name).alias("graph"), "n", "arcs", "max_degree", "components")


def degree_histogram(g: Graph) -> DataFrame:
    return g.degrees().groupBy("degree").agg(F.count(F.lit(1)).alias("vertices"))


def timed(run: Callable[[RunStats], DataFrame]) -> dict:
    """Seconds, rounds and observed totals of a run that is carried to its end."""
    stats, began = RunStats(), time.time()
    rows = run(stats).count()
    names = {k for r in stats.rounds for k in r if isinstance(r[k], int)}
    return {"seconds": time.time() - began, "rows": rows, "rounds": stats.depth, **{f"total_{n}": stats.total(n) for n in sorted(names)}}


def throughput(g: Graph, seconds: float) -> float:
    """Arcs a second."""
    return g.edges.count() / max(seconds, 1e-9)


def half_length(series: list[tuple[int, float]]) -> int | None:
    """The least size of (size, throughput) pairs that reaches half of the peak."""
    peak = max((t for _, t in series), default=0.0)
    return next((n for n, t in sorted(series) if t >= peak / 2), None)


def speedup(one: float, many: float) -> float:
    return one / max(many, 1e-9)


def live_ratio(g: Graph, frontier: DataFrame, live: DataFrame) -> DataFrame:
    """(arcs, to_live, targets, max_key): what a push writes, what of it is to open targets, how many there are, and the most contended."""
    arcs = frontier.select(F.col("v").alias("src")).join(g.edges, "src")
    marked = arcs.join(live.select(F.col("v").alias("dst"), F.lit(1).alias("open")), "dst", "left")
    per = marked.groupBy("dst").agg(F.count(F.lit(1)).alias("n"), F.max("open").alias("open"))
    return per.agg(F.sum("n").alias("arcs"), F.sum(F.when(F.col("open") == 1, F.col("n")).otherwise(0)).alias("to_live"), F.count("open").alias("targets"), F.max("n").alias("max_key"))


def shuffles(df: DataFrame) -> int:
    """Exchanges in the plan: the depth of a single-job method."""
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange")
