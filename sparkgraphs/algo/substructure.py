"""Cores, dense subgraphs, triangles."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..core.buckets import Buckets
from ..core.closing import closed, lists
from ..core.histogram import histogram
from ..core.rounds import Rounds, RunStats
from ..model.graph import Graph


def _peel(g: Graph, strategy: str, stats: RunStats | None, scan: bool = False) -> tuple[DataFrame, RunStats]:
    """(v, coreness, peeled): the round in which each vertex went."""
    stats = stats if stats is not None else RunStats()
    none = F.lit(None).cast("bigint")
    open_ = F.col("coreness").isNull()
    held = Buckets(Rounds(g.spark, "kcore", stats), F.when(open_, F.col("degree")))
    held.put(g.degrees().select("v", "degree", none.alias("coreness"), none.alias("peeled")), open=F.count(F.lit(1)))
    k = r = 0
    while held.id is not None:
        state, low = held.rows, held.id
        k = max(k, low) if not scan else k + (low > k)
        r += 1
        now = open_ & (F.col("degree") <= k)
        pairs = state.where(now).select(F.col("v").alias("src")).join(g.edges, "src").select(F.col("dst").alias("v"))
        pairs = pairs.join(state.where(open_ & (F.col("degree") > k)).select("v"), "v", "left_semi")
        lost = histogram(pairs, "v", strategy=strategy, out="lost")
        degree = F.when(F.col("lost").isNull(), F.col("degree")).otherwise(F.greatest(F.col("degree") - F.col("lost"), F.lit(k)))
        core = F.when(now, F.lit(k).cast("bigint")).otherwise(F.col("coreness"))
        gone = F.when(now, F.lit(r).cast("bigint")).otherwise(F.col("peeled"))
        held.put(state.join(lost, "v", "left").select("v", degree.alias("degree"), core.alias("coreness"), gone.alias("peeled")), open=F.count_if(open_))
    return held.rows, stats


def kcore(g: Graph, *, strategy: str = "plain", stats: RunStats | None = None) -> DataFrame:
    """(v, coreness): the lowest bucket is peeled; neighbours lose what a histogram of the removed arcs counts."""
    return _peel(g, strategy, stats)[0].select("v", "coreness")


def kcore_scan(g: Graph, *, stats: RunStats | None = None) -> DataFrame:
    """Every k is scanned for, also those without vertices."""
    return _peel(g, "plain", stats, scan=True)[0].select("v", "coreness")


def kcore_pow2(g: Graph, *, stats: RunStats | None = None) -> DataFrame:
    """(v, coreness): an upper estimate under twice the coreness, from peeling at powers of two."""
    rounds = Rounds(g.spark, "pow2", stats)
    none = F.lit(None).cast("bigint")
    state, seen = rounds.keep(g.degrees().select("v", "degree", none.alias("coreness")), "state", open=F.count(F.lit(1)), low=F.min("degree"))
    k = 0
    while seen["open"]:
        if seen["low"] > k:
            k = (1 << seen["low"].bit_length()) - 1
        now = F.col("coreness").isNull() & (F.col("degree") <= k)
        lost = histogram(state.where(now).select(F.col("v").alias("src")).join(g.edges, "src").select(F.col("dst").alias("v")), "v", out="lost")
        core = F.when(now, F.lit(k).cast("bigint")).otherwise(F.col("coreness"))
        degree = F.col("degree") - F.coalesce("lost", F.lit(0))
        state, seen = rounds.keep(state.join(lost, "v", "left").select("v", degree.alias("degree"), core.alias("coreness")), "state", open=F.count_if(F.col("coreness").isNull()), low=F.min(F.when(F.col("coreness").isNull(), F.greatest("degree", F.lit(0)))))
    return state.select("v", "coreness")


def kcore_hindex(g: Graph, *, stats: RunStats | None = None) -> DataFrame:
    """(v, coreness) as the fixpoint of h-indices of neighbours' values, from the degrees: few rounds where peeling takes many."""
    rounds = Rounds(g.spark, "hindex", stats)
    state, seen = rounds.keep(g.degrees().select("v", F.col("degree").alias("h"), F.lit(True).alias("moved")), "state", moved=F.count_if("moved"))
    while seen["moved"]:
        # neighbours' values as a histogram: a value and how many have it; the list is as long as there are different values
        seen_by = state.select(F.col("v").alias("src"), "h").join(g.edges, "src").groupBy("dst", "h").agg(F.count(F.lit(1)).alias("c"))
        lists = seen_by.groupBy(F.col("dst").alias("v")).agg(F.sort_array(F.collect_list(F.struct("h", "c")), asc=False).alias("l"))
        walk = F.aggregate("l", F.struct(F.lit(0).cast("bigint").alias("n"), F.lit(0).cast("bigint").alias("best")), lambda a, x: F.struct((a["n"] + x["c"]).alias("n"), F.greatest(a["best"], F.least(a["n"] + x["c"], x["h"])).alias("best")), lambda a: a["best"])
        new = F.coalesce(F.col("new"), F.lit(0).cast("bigint"))
        moved = new < F.col("h")
        state, seen = rounds.keep(state.join(lists.select("v", walk.alias("new")), "v", "left").select("v", F.least(new, F.col("h")).alias("h"), moved.alias("moved")), "state", moved=F.count_if("moved"))
    return state.select("v", F.col("h").alias("coreness"))


def degeneracy(g: Graph) -> DataFrame:
    return kcore_hindex(g).agg(F.coalesce(F.max("coreness"), F.lit(0).cast("bigint")).alias("degeneracy"))


def peeling_complexity(g: Graph) -> DataFrame:
    """The number of peeling rounds: all vertices of a level go at once until it is empty."""
    state, _ = _peel(g, "plain", None)
    return state.agg(F.coalesce(F.max("peeled"), F.lit(0).cast("bigint")).alias("rho"))


def degeneracy_order(g: Graph) -> DataFrame:
    """(v, coreness, peeled): any order by (peeled, v) removes vertices of degree at most the degeneracy."""
    return _peel(g, "plain", None)[0].select("v", "coreness", "peeled")


def k_core_subgraph(g: Graph, k: int) -> Graph:
    return g.induced(kcore_hindex(g).where(F.col("coreness") >= k).select("v"))


def densest_subgraph(g: Graph, *, eps: float = 0.001, stats: RunStats | None = None) -> tuple[DataFrame, float]:
    """(v) of the densest of the peeled subgraphs and its density (edges over vertices): within 2 (1 + eps) of the best."""
    rounds = Rounds(g.spark, "densest", stats)
    none = F.lit(None).cast("int")
    watch = lambda d, gone: {"n": F.count_if(gone.isNull()), "m2": F.sum(F.when(gone.isNull(), d))}
    state, seen = rounds.keep(g.degrees().select("v", "degree", none.alias("gone")), "state", **watch(F.col("degree"), F.col("gone")))
    best, best_round, r = -1.0, 0, 0
    while seen["n"]:
        density = (seen["m2"] or 0) / 2 / seen["n"]
        r += 1
        if density > best:
            best, best_round = density, r
        now = F.col("gone").isNull() & (F.col("degree") <= 2 * (1 + eps) * density)
        lost = histogram(state.where(now).select(F.col("v").alias("src")).join(g.edges, "src").select(F.col("dst").alias("v")), "v", out="lost")
        degree, gone = F.col("degree") - F.coalesce("lost", F.lit(0)), F.when(now, r).otherwise(F.col("gone"))
        state, seen = rounds.keep(state.join(lost, "v", "left").select("v", degree.alias("degree"), gone.alias("gone")), "state", **watch(F.col("degree"), F.col("gone")))
    return state.where(F.col("gone") >= best_round).select("v"), max(best, 0.0)


def densest_degeneracy(g: Graph) -> tuple[DataFrame, float]:
    """(v) of the densest suffix of the peeling rounds, and its density: the degeneracy-order 2-approximation by rounds."""
    order = Rounds(g.spark, "order").table(degeneracy_order(g).select("v", "peeled"))
    a, b = (order.select(F.col("v").alias(c), F.col("peeled").alias(f"p_{c}")) for c in ("src", "dst"))
    edges = g.half().select("src", "dst").join(a, "src").join(b, "dst").groupBy(F.least("p_src", "p_dst").alias("peeled")).agg(F.count(F.lit(1)).alias("m"))
    # one row for each round: few
    from pyspark.sql import Window

    back = Window.orderBy(F.desc("peeled")).rowsBetween(Window.unboundedPreceding, 0)
    sums = order.groupBy("peeled").agg(F.count(F.lit(1)).alias("n")).join(edges, "peeled", "left").select("peeled", F.sum("n").over(back).alias("n"), F.sum(F.coalesce("m", F.lit(0))).over(back).alias("m"))
    top = sums.select("peeled", (F.col("m") / F.col("n")).alias("d")).orderBy(F.desc("d"), "peeled").limit(1).first()
    if top is None:
        return g.vertices.select("v"), 0.0
    return order.where(F.col("peeled") >= top.peeled).select("v"), float(top.d)


METHODS = ("oriented_lists", "oriented_join", "undirected")


def triangle_count(g: Graph, *, method: str = "oriented_join") -> DataFrame:
    """(triangles): one row. Lists of larger neighbours are intersected in groups; undirected intersects whole lists and divides by 6."""
    return closed_count(lists(g.edges), method=method)


def closed_count(packed: DataFrame, *, method: str = "oriented_join") -> DataFrame:
    """triangle_count of the lists of a graph."""
    if method not in METHODS:
        raise ValueError("method is oriented_lists, oriented_join or undirected")
    found = F.coalesce(F.sum("triangles"), F.lit(0))
    return closed(packed, whole=method == "undirected").agg((found / (6 if method == "undirected" else 1)).cast("bigint").alias("triangles"))


def triangles_per_vertex(g: Graph) -> DataFrame:
    return closed_at(g.vertices, lists(g.edges))


def closed_at(vertices: DataFrame, packed: DataFrame) -> DataFrame:
    """(v, triangles) for all of `vertices` (v), of the lists of a graph."""
    found = closed(packed, at=True).groupBy("v").agg(F.sum("triangles").alias("triangles"))
    return vertices.select("v").join(found, "v", "left").select("v", F.coalesce("triangles", F.lit(0)).alias("triangles"))


def density_bounds(g: Graph) -> DataFrame:
    """The best density lies between half the degeneracy and the degeneracy."""
    return degeneracy(g).select((F.col("degeneracy") / 2).alias("low"), F.col("degeneracy").cast("double").alias("high"))


def log_rounds(n: int, eps: float) -> int:
    """The number of densest-subgraph rounds that n vertices can take at most."""
    return math.ceil(math.log(max(2, n)) / math.log(1 + eps)) + 1
