"""Shortest and widest paths: one relaxation loop over a semiring, by rounds of changed vertices or by buckets of values."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..core.buckets import Buckets
from ..core.contract import has_cycle
from ..core.edge_map import edge_map
from ..core.rounds import Rounds, RunStats
from ..model.graph import Graph

TOP = (1 << 63) - 1


def relax(g: Graph, source: int, start: Column, extend: Callable[[Column, Column], Column], best: str, *, bucket: Callable[[Column], Column] | None = None, cap: int | None = None, cycles: bool = False, mode: str = "blocked", dense_switch: bool = False, stats: RunStats | None = None) -> tuple[DataFrame, bool]:
    """(v, val) of the best value reaching each vertex, and whether values improve without end.

    A vertex is active from when it improves until its arcs are relaxed. Without buckets all active vertices go at once; with
    them only those of the extreme bucket, and a bucket is left when none of its vertices is active. With `dense_switch` a round whose
    active vertices are over a twentieth of all pulls: the vertices not yet settled ask along their arcs.

    Values improve without end if `cap` rounds are too few. With `cycles` each vertex also keeps the source of its best arc, and after
    4, 8, 16, ... rounds these are searched for a cycle: only one that improves its own values closes there.
    """
    n = g.vertices.count() if dense_switch else 0
    rounds = Rounds(g.spark, "relax", stats)
    pick = F.min if best == "min" else F.max
    better = (lambda a, b: a < b) if best == "min" else (lambda a, b: a > b)
    at = F.lit(0) if bucket is None else bucket(F.col("val"))
    held = Buckets(rounds, F.when(F.col("active"), at), best)
    parent = [F.lit(None).cast("bigint").alias("parent")] if cycles else []
    watch = {"active": F.count_if("active")}
    held.put(g.vertices.select("v", F.when(F.col("v") == source, start).alias("val"), (F.col("v") == source).alias("active"), *parent), **watch)
    done, check = 0, 4
    while held.id is not None:
        state = held.rows
        if cap is not None and done >= cap:
            return state.select("v", "val"), True
        if cycles and done == check:
            check *= 2
            if has_cycle(state.select("v", F.col("parent").alias("p"))):
                return state.select("v", "val"), True
        now = held.in_next
        dense = dense_switch and held.seen["active"] > n / 20
        unsettled = state.where(F.col("val").isNull() | (F.lit(True) if bucket is None else ~better(at, F.lit(held.id))))
        message = {"new": extend(F.col("val"), F.col("w") if g.weighted else F.lit(1))}
        combine = [pick(F.struct("new", "src")).alias("m")] if cycles else [pick("new").alias("new")]
        found = edge_map(g.edges, state.where(now).select("v", "val"), combine, live=unsettled if dense else None, message=message, mode="pull" if dense else mode)
        if cycles:
            found = found.select("v", "m.new", F.col("m.src").alias("from"))
        improved = F.col("new").isNotNull() & (F.col("val").isNull() | better(F.col("new"), F.col("val")))
        parent = [F.when(improved, F.col("from")).otherwise(F.col("parent")).alias("parent")] if cycles else []
        value = F.when(improved, F.col("new")).otherwise(F.col("val")).alias("val")
        held.put(state.join(found, "v", "left").select("v", value, (improved | (F.col("active") & ~now)).alias("active"), *parent), **watch)
        done += 1
    return held.rows.select("v", "val"), False


def bellman_ford(g: Graph, source: int, *, mode: str = "blocked", stats: RunStats | None = None) -> DataFrame:
    """(v, dist): least sums of weights, NULL where unreachable; -Infinity everywhere if a negative cycle is reachable.

    Such a cycle shows among the arcs of best values long before as many rounds as there are vertices have passed.
    """
    n = g.vertices.count()
    kind = dict(g.edges.dtypes).get("w", "bigint")
    negative = g.weighted and not g.edges.where(F.col("w") < 0).isEmpty()
    out, endless = relax(g, source, F.lit(0).cast(kind), lambda d, w: d + w, "min", cap=n, cycles=negative, mode=mode, stats=stats)
    if endless:
        return g.vertices.select("v", F.lit(float("-inf")).alias("dist"))
    return out.withColumnRenamed("val", "dist")


def weighted_bfs(g: Graph, source: int, *, bucket_width: int = 1, mode: str = "blocked", dense_switch: bool = True, allow_zero: bool = False, stats: RunStats | None = None) -> DataFrame:
    """(v, dist) for integral weights of 1 or more, vertices in the order of their distance; wider buckets give delta-stepping.

    With `allow_zero` weights may be 0: a bucket is then left only when no vertex in it improves any more.
    """
    least = 0 if allow_zero else 1
    if g.weighted and not g.edges.where(F.col("w") < least).isEmpty():
        raise ValueError(f"weights must be {least} or more")
    out, _ = relax(g, source, F.lit(0).cast("bigint"), lambda d, w: d + w, "min", bucket=lambda d: F.floor(d / bucket_width), mode=mode, dense_switch=dense_switch, stats=stats)
    return out.withColumnRenamed("val", "dist")


def delta_stepping(g: Graph, source: int, delta: int, **options) -> DataFrame:
    return weighted_bfs(g, source, bucket_width=delta, **options)


def widest_path(g: Graph, source: int, *, method: str = "semiring", mode: str = "blocked", stats: RunStats | None = None) -> DataFrame:
    """(v, width): the largest bottleneck of a path, NULL where unreachable, the top BIGINT at the source."""
    if method not in ("semiring", "bucket"):
        raise ValueError("method is semiring or bucket")
    out, _ = relax(g, source, F.lit(TOP), lambda d, w: F.least(d, w), "max", bucket=(lambda d: d) if method == "bucket" else None, mode=mode, stats=stats)
    return out.withColumnRenamed("val", "width")
