"""Breadth-first search and what is built of its levels."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.edge_map import edge_map
from ..core.rounds import Rounds, RunStats
from ..model.graph import Graph

#: Arcs of a graph whose levels one task follows in memory, about 50 bytes each.
FITS = 1 << 23


def bfs(g: Graph, source: int | None = None, *, sources: DataFrame | None = None, mode: str = "auto", with_parent: bool = False, max_depth: int | None = None, stats: RunStats | None = None) -> DataFrame:
    """(v, dist[, parent]): rounds until reached, NULL where unreachable; parents are the smallest possible, sources have none.

    Sources are one id or the (v) rows of `sources`.
    """
    rounds = Rounds(g.spark, "bfs", stats)
    size = g.edges.count() if mode == "auto" else 0
    degree = g.degrees() if mode == "auto" else g.vertices.select("v", F.lit(0).cast("bigint").alias("degree"))
    if sources is None:
        state = degree.withColumn("dist", F.when(F.col("v") == source, F.lit(0).cast("bigint")))
    else:
        state = degree.join(sources.select("v", F.lit(0).cast("bigint").alias("dist")), "v", "left")
    state = state.select("v", "degree", "dist", F.lit(None).cast("bigint").alias("parent"))
    watch = lambda d: {"frontier": F.count_if(F.col("dist") == d), "arcs": F.sum(F.when(F.col("dist") == d, F.col("degree")))}
    state, seen = rounds.keep(state, "state", **watch(0))
    depth = 0
    while seen["frontier"] and (max_depth is None or depth < max_depth):
        hit = edge_map(g.edges, state.where(F.col("dist") == depth).select("v"), [F.min("src").alias("hit")], live=state.where("dist IS NULL"), mode=mode, share=(seen["arcs"] or 0) / max(1, size))
        depth += 1
        got = F.col("hit").isNotNull()
        state, seen = rounds.keep(state.join(hit, "v", "left").select("v", "degree", F.when(got, F.lit(depth).cast("bigint")).otherwise(F.col("dist")).alias("dist"), F.when(got, F.col("hit")).otherwise(F.col("parent")).alias("parent")), "state", **watch(depth))
    return state.select("v", "dist", *["parent"] * with_parent)


def betweenness(g: Graph, source: int, *, exact_paths: bool = False, mode: str = "blocked", fits: int = 0, stats: RunStats | None = None) -> DataFrame:
    """(v, score): dependencies of the paths from one source; 0 at the source and where unreachable.

    A graph of at most `fits` arcs is followed within one task: two jobs a level cost more than the levels of a small graph of large diameter.
    """
    if fits and not exact_paths and g.edges.count() <= fits:
        rounds = Rounds(g.spark, "betweenness", stats)
        found = rounds.table(g.edges.select("src", "dst").repartition(1).mapInArrow(_dependencies(source), "v bigint, found double"))
        return g.vertices.select("v").join(found, "v", "left").select("v", F.coalesce("found", F.lit(0.0)).alias("score"))
    rounds = Rounds(g.spark, "betweenness", stats)
    paths = "decimal(38,0)" if exact_paths else "double"
    state = g.vertices.select("v", F.when(F.col("v") == source, F.lit(0)).alias("level"), F.when(F.col("v") == source, F.lit(1)).cast(paths).alias("sigma"))
    state, seen = rounds.keep(state, "state", frontier=F.count_if(F.col("level") == 0))
    level = 0
    while seen["frontier"]:
        hit = edge_map(g.edges, state.where(F.col("level") == level).select("v", "sigma"), [F.sum("sigma").cast(paths).alias("more")], live=state.where("level IS NULL"), mode=mode)
        level += 1
        got = F.col("more").isNotNull()
        state, seen = rounds.keep(state.join(hit, "v", "left").select("v", F.when(got, level).otherwise(F.col("level")).alias("level"), F.when(got, F.col("more")).otherwise(F.col("sigma")).alias("sigma")), "state", frontier=F.count_if(F.col("level") == level))
    back = g.transpose().edges if g.directed else g.edges
    state, _ = rounds.keep(state.select("v", "level", F.col("sigma").cast("double").alias("sigma"), F.lit(0.0).alias("score")), "scores")
    for depth in range(level - 1, 0, -1):
        share = edge_map(back, state.where(F.col("level") == depth).select("v", ((1 + F.col("score")) / F.col("sigma")).alias("part")), [F.sum("part").alias("part")], live=state.where(F.col("level") == depth - 1), mode=mode)
        state, _ = rounds.keep(state.join(share, "v", "left").select("v", "level", "sigma", (F.col("score") + F.coalesce(F.col("part") * F.col("sigma"), F.lit(0.0))).alias("score")), "scores", settled=F.count_if(F.col("level") == depth))
    return state.select("v", F.when(F.col("v") == source, F.lit(0.0)).otherwise(F.col("score")).alias("score"))


def _dependencies(source: int):
    """Rows (v, found) of all arcs of a graph, level by level."""

    def ranges(start: np.ndarray, size: np.ndarray) -> np.ndarray:
        ends = np.cumsum(size)
        return np.repeat(start - (ends - size), size) + np.arange(size.sum())

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if b.num_rows]
        if not parts:
            return
        src, dst = (np.concatenate([p[i] for p in parts]) for i in (0, 1))
        del parts
        ids = np.union1d(np.unique(src), np.unique(dst))
        src, dst = np.searchsorted(ids, src).astype(np.int32), np.searchsorted(ids, dst).astype(np.int32)
        size = np.bincount(src, minlength=len(ids))
        start, to = np.cumsum(size) - size, dst[np.argsort(src, kind="stable")]
        del src, dst
        level, sigma, score = np.full(len(ids), -1, np.int32), np.zeros(len(ids)), np.zeros(len(ids))
        at = np.flatnonzero(ids == source)
        level[at], sigma[at], fronts = 0, 1.0, []
        while len(at):
            fronts.append(at)
            ends, owner = to[ranges(start[at], size[at])], np.repeat(at, size[at])
            fresh = level[ends] < 0
            nxt, place = np.unique(ends[fresh], return_inverse=True)
            sigma[nxt] = np.bincount(place, weights=sigma[owner[fresh]], minlength=len(nxt))
            level[nxt] = len(fronts)
            at = nxt
        for depth in range(len(fronts) - 1, 0, -1):
            at = fronts[depth]
            ends, owner = to[ranges(start[at], size[at])], np.repeat(np.arange(len(at)), size[at])
            below = level[ends] == depth + 1
            score[at] = sigma[at] * np.bincount(owner[below], weights=(1 + score[ends[below]]) / sigma[ends[below]], minlength=len(at))
        table = pa.table({"v": ids, "found": score})
        yield from table.to_batches(max_chunksize=1 << 16)

    return solve


def effective_diameter(g: Graph, sources: list[int], **options) -> DataFrame:
    """The largest depth met from the given sources: a lower bound of the diameter."""
    out = None
    for s in sources:
        one = bfs(g, s, **options).agg(F.max("dist").alias("depth")).withColumn("source", F.lit(s).cast("bigint"))
        out = one if out is None else out.unionByName(one)
    return out.select("source", "depth")


def ego(g: Graph, v: int, hops: int) -> Graph:
    near = bfs(g, v, max_depth=hops, mode="blocked").where("dist IS NOT NULL").select("v")
    return g.induced(near)
