"""Edge maps: what a frontier's arcs send to their targets, combined at each target.

push      every message is shuffled as it is; settled targets go afterwards (the unblocked baseline)
blocked   messages are combined before the shuffle, a row for each task and target; open targets are tested below it where they are
          few enough to be broadcast (Spark checks their size and moves the test there), else on the combined rows, dealt alike
pull      open targets joined with their arcs, then with the frontier: nothing to settle afterwards
auto      pull when the frontier's arcs are over `dense` of all, else blocked

All give the same rows: one per open target that got a message. The edges of a graph that is laid out are stored by source, so the join
with a frontier does not shuffle them. Aggregates combine on the map side, so a hub is no hot key.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MODES = ("push", "blocked", "pull", "auto")


def edge_map(edges: DataFrame, frontier: DataFrame, combine: list[Column], *, live: DataFrame | None = None, message: dict[str, Column] | None = None, mode: str = "blocked", dense: float = 0.05, share: float = 0.0) -> DataFrame:
    """frontier: (v, payload...); message: columns over src, dst, w and the payload; combine: aggregates over src and the messages;
    live: (v) of open targets; share: the frontier's part of all arcs, for auto. Returns (v, aggregates)."""
    if mode not in MODES:
        raise ValueError(f"mode is one of {MODES}")
    if mode == "auto":
        mode = "pull" if live is not None and share > dense else "blocked"
    sources = frontier.withColumnRenamed("v", "src")
    targets = live.select(F.col("v").alias("dst")) if live is not None else None
    if mode == "pull" and targets is not None:
        arcs = edges.join(targets, "dst", "left_semi").join(sources, "src")
    else:
        arcs = sources.join(edges, "src")
    if message:
        arcs = arcs.withColumns(message)
    out = (arcs.repartition("dst") if mode == "push" else arcs).groupBy("dst").agg(*combine)
    if targets is not None and mode != "pull":
        out = out.join(targets, "dst", "left_semi")
    return out.withColumnRenamed("dst", "v")


def vertex_map(state: DataFrame, frontier: DataFrame, updates: dict[str, Column]) -> DataFrame:
    """`state` with columns updated for the vertices of `frontier` (v)."""
    marked = state.join(frontier.select("v", F.lit(True).alias("in_frontier")), "v", "left")
    return marked.withColumns({c: F.when(F.col("in_frontier"), x).otherwise(F.col(c)) for c, x in updates.items()}).drop("in_frontier")
