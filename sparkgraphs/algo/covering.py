"""Covering problems: independent sets, matchings, colourings, set cover."""

from __future__ import annotations

import math

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..core.buckets import Buckets
from ..core.edge_map import edge_map
from ..core.prims import index, prefix_cut
from ..core.priority import SPAN, prio
from ..core.rounds import Rounds, RunStats
from ..model.graph import Graph


def priority_dag(g: Graph, order: DataFrame) -> DataFrame:
    """Arcs from the earlier to the later end. order: (v, rank struct or number)."""
    a = order.select(F.col("v").alias("src"), F.col("rank").alias("ra"))
    b = order.select(F.col("v").alias("dst"), F.col("rank").alias("rb"))
    return g.edges.select("src", "dst").join(a, "src").join(b, "dst").where("ra < rb").select("src", "dst")


def mis(g: Graph, *, seed: int = 42, method: str = "rootset", stats: RunStats | None = None) -> DataFrame:
    """(v): the first maximal independent set of the priority order.

    rootset  vertices without undecided earlier neighbours join each round
    prefix   the same set, by prefixes of the order that double
    luby     fresh priorities each round: some maximal independent set
    """
    if method == "luby":
        return _luby(g, seed, stats)
    rounds = Rounds(g.spark, "mis", stats)
    order = rounds.table(g.vertices.select("v", F.struct(prio(seed, "v").alias("p"), F.col("v").alias("id")).alias("rank")))
    dag = rounds.table(priority_dag(g, order))
    counts = dag.groupBy(F.col("dst").alias("v")).agg(F.count(F.lit(1)).alias("ahead"))
    state = order.join(counts, "v", "left").select("v", F.col("rank.p").alias("p"), F.coalesce("ahead", F.lit(0)).alias("ahead"), F.lit(0).alias("status"))
    n = g.vertices.count()
    reach = SPAN if method == "rootset" else max(1, SPAN // max(1, n // 16))
    state, seen = rounds.keep(state, "state", open=F.count_if(F.col("status") == 0), here=F.count_if((F.col("status") == 0) & (F.col("p") < reach)))
    while seen["open"]:
        if not seen["here"]:
            reach = min(SPAN, reach * 2)
        root = (F.col("status") == 0) & (F.col("ahead") == 0) & (F.col("p") < reach)
        roots = state.where(root).select("v")
        out = rounds.table(edge_map(dag, roots, [F.count(F.lit(1)).alias("hit")], live=state.where("status = 0")).select("v"))
        lost = edge_map(dag, out, [F.count(F.lit(1)).alias("less")])
        joined = state.join(out.withColumn("out", F.lit(True)), "v", "left").join(lost, "v", "left")
        status = F.when(root, 1).when(F.col("out"), 2).otherwise(F.col("status"))
        state, seen = rounds.keep(joined.select("v", "p", (F.col("ahead") - F.coalesce("less", F.lit(0))).alias("ahead"), status.alias("status")), "state", open=F.count_if(F.col("status") == 0), here=F.count_if((F.col("status") == 0) & (F.col("p") < reach)))
    return state.where("status = 1").select("v")


def _luby(g: Graph, seed: int, stats: RunStats | None) -> DataFrame:
    rounds = Rounds(g.spark, "luby", stats)
    state, seen = rounds.keep(g.vertices.select("v", F.lit(0).alias("status")), "state", open=F.count_if(F.col("status") == 0))
    r = 0
    while seen["open"]:
        r += 1
        live = state.where("status = 0").select("v", F.struct(prio(f"{seed}.{r}", "v").alias("p"), F.col("v").alias("id")).alias("rank"))
        low = edge_map(g.edges, live, [F.min("rank").alias("low")], live=live)
        won = rounds.table(live.join(low, "v", "left").where("low IS NULL OR rank < low").select("v"))
        out = edge_map(g.edges, won, [F.count(F.lit(1)).alias("hit")], live=live)
        joined = state.join(won.withColumn("won", F.lit(True)), "v", "left").join(out, "v", "left")
        status = F.when(F.col("won"), 1).when(F.col("hit") > 0, 2).otherwise(F.col("status"))
        state, seen = rounds.keep(joined.select("v", status.alias("status")), "state", open=F.count_if(F.col("status") == 0))
    return state.where("status = 1").select("v")


def _waves(edges: DataFrame, rounds: Rounds) -> DataFrame:
    """The greedy matching of (src, dst, p) edges: an edge joins when it is the first at both ends."""
    rank = F.struct("p", "src", "dst")
    matched, left = None, edges.count()
    while left:
        best = edges.select(F.col("src").alias("v"), rank.alias("e")).unionByName(edges.select(F.col("dst").alias("v"), rank.alias("e"))).groupBy("v").agg(F.min("e").alias("e"))
        won = rounds.table(best.groupBy("e").agg(F.count(F.lit(1)).alias("ends")).where("ends = 2").select("e.src", "e.dst", "e.p"))
        matched = won if matched is None else matched.unionByName(won)
        edges, seen = rounds.keep(without_ends(edges, won), f"edges{id(rounds)}", left=F.count(F.lit(1)))
        left = seen["left"]
    return matched if matched is not None else edges


def without_ends(edges: DataFrame, won: DataFrame) -> DataFrame:
    used = won.select(F.col("src").alias("v")).unionByName(won.select(F.col("dst").alias("v")))
    columns = edges.columns
    return edges.join(used.withColumnRenamed("v", "src"), "src", "left_anti").join(used.withColumnRenamed("v", "dst"), "dst", "left_anti").select(columns)


def maximal_matching(g: Graph, *, seed: int = 42, method: str = "filtered", filter_steps: int = 4, prefix_factor: float = 1.5, stats: RunStats | None = None) -> DataFrame:
    """(src, dst): the greedy matching of the edges' priority order.

    filtered    the first 3n/2 edges are matched, then the rest is freed of their ends, a few times, then all that is left
    prefix_all  all edges are ordered and taken by doubling prefixes
    plain       waves over all edges
    """
    rounds = Rounds(g.spark, "matching", stats)
    edges = rounds.table(g.half().select("src", "dst", prio(seed, "src", "dst").alias("p")))
    if method == "plain":
        return _waves(edges, rounds).select("src", "dst")
    n, out, step = g.vertices.count(), None, 0
    size = max(1, int(prefix_factor * n) if method == "filtered" else n // 8)
    while left := edges.count():
        last = method == "filtered" and step >= filter_steps
        part, _ = (edges, None) if last else prefix_cut(edges, "p", size, left)
        got = rounds.table(_waves(rounds.table(part), rounds))
        out = got if out is None else out.unionByName(got)
        edges = rounds.table(without_ends(edges, got))
        step += 1
        size = size if method == "filtered" else size * 2
    return (out if out is not None else edges).select("src", "dst")


HEURISTICS = ("llf", "sll", "lf", "r", "ff")


def colouring_order(g: Graph, heuristic: str, seed: int, rounds: Rounds) -> DataFrame:
    """(v, rank): log-degree first, log-degree removed last, degree first, random, or by id."""
    degree = g.degrees()
    tail = [prio(seed, "v").alias("p"), F.col("v").alias("id")]
    if heuristic == "llf":
        return degree.select("v", F.struct((-F.ceil(F.log2(F.greatest("degree", F.lit(1))))).alias("k"), *tail).alias("rank"))
    if heuristic == "lf":
        return degree.select("v", F.struct((-F.col("degree")).alias("k"), *tail).alias("rank"))
    if heuristic == "r":
        return degree.select("v", F.struct(*tail).alias("rank"))
    if heuristic == "ff":
        return degree.select("v", F.struct(F.col("v").alias("id")).alias("rank"))
    if heuristic != "sll":
        raise ValueError(f"heuristic is one of {HEURISTICS}")
    state, seen = rounds.keep(degree.select("v", "degree", F.lit(None).cast("int").alias("gone")), "sll", left=F.count_if(F.col("gone").isNull()), low=F.min("degree"))
    r = 0
    while seen["left"]:
        r += 1
        bound = 1 << max(0, math.ceil(math.log2(max(1, seen["low"]))))
        now = F.col("gone").isNull() & (F.col("degree") <= bound)
        lost = edge_map(g.edges, state.where(now).select("v"), [F.count(F.lit(1)).alias("less")], live=state.where("gone IS NULL"))
        gone = F.when(now, r).otherwise(F.col("gone"))
        state, seen = rounds.keep(state.join(lost, "v", "left").select("v", F.greatest(F.col("degree") - F.coalesce("less", F.lit(0)), F.lit(0)).alias("degree"), gone.alias("gone")), "sll", left=F.count_if(F.col("gone").isNull()), low=F.min(F.when(F.col("gone").isNull(), F.col("degree"))))
    return state.select("v", F.struct((-F.col("gone")).alias("k"), *tail).alias("rank"))


#: Arcs within a prefix of the order that one task colours.
PREFIX = 1 << 21


def color(g: Graph, *, heuristic: str = "llf", seed: int = 42, method: str = "rootset", stats: RunStats | None = None) -> DataFrame:
    """(v, color): a vertex takes the smallest colour free among its earlier neighbours, once all of them are coloured.

    rootset  vertices whose earlier neighbours are coloured go each round: as many rounds as the longest path of the order
    prefix   the same colours: the order is cut where PREFIX arcs lie within a piece, and a piece is coloured in one task: about the
             root of arcs over PREFIX rounds, however long the paths are
    """
    if method not in ("rootset", "prefix"):
        raise ValueError("method is rootset or prefix")
    rounds = Rounds(g.spark, "colour", stats)
    order = rounds.table(colouring_order(g, heuristic, seed, rounds))
    if method == "prefix":
        return _color_prefixes(g, order, rounds)
    dag = rounds.table(priority_dag(g, order))
    counts = dag.groupBy(F.col("dst").alias("v")).agg(F.count(F.lit(1)).alias("ahead"))
    none = F.lit(None).cast("bigint")
    state, seen = rounds.keep(order.join(counts, "v", "left").select("v", F.coalesce("ahead", F.lit(0)).alias("ahead"), none.alias("color"), F.lit(False).alias("fresh")), "state", open=F.count_if(F.col("color").isNull()))
    while seen["open"]:
        root = F.col("color").isNull() & (F.col("ahead") == 0)
        used = edge_map(dag, state.where("color IS NOT NULL").select("v", "color"), [F.collect_set("color").alias("used")], live=state.where(root))
        free = F.array_min(F.array_except(F.sequence(F.lit(0).cast("bigint"), F.size("used").cast("bigint")), F.col("used")))
        picked = F.when(root, F.coalesce(free, F.lit(0).cast("bigint"))).otherwise(F.col("color"))
        less = edge_map(dag, state.where(root).select("v"), [F.count(F.lit(1)).alias("less")])
        state, seen = rounds.keep(state.join(used, "v", "left").join(less, "v", "left").select("v", (F.col("ahead") - F.coalesce("less", F.lit(0))).alias("ahead"), picked.alias("color"), root.alias("fresh")), "state", open=F.count_if(F.col("color").isNull()))
    return state.select("v", "color")


def _color_prefixes(g: Graph, order: DataFrame, rounds: Rounds) -> DataFrame:
    """Vertices are positions of the order here; a piece gets the colours of earlier pieces joined, and its own arcs."""
    place = rounds.table(index(order, ["rank"], "pos").select("v", "pos"))
    ends = [place.select(F.col("v").alias(c), F.col("pos").alias(p)) for c, p in (("src", "early"), ("dst", "late"))]
    dag = rounds.table(g.edges.select("src", "dst").join(ends[0], "src").join(ends[1], "dst").where("early < late").select("early", "late"))
    n, low = place.count(), 0
    done = rounds.append(place.limit(0).select("pos", F.lit(0).cast("bigint").alias("color")), "done")
    while low < n:
        left = dag.where(F.col("early") >= low)
        at = prefix_cut(left, "late", PREFIX, left.count())[1]
        high = n if at is None else at + 1
        here = dag.where((F.col("late") >= low) & (F.col("late") < high))
        used = here.where(F.col("early") < low).join(done.withColumnRenamed("pos", "early"), "early").groupBy("late").agg(F.collect_set("color").alias("used"))
        own = here.where(F.col("early") >= low).groupBy("late").agg(F.collect_list("early").alias("own"))
        piece = place.where((F.col("pos") >= low) & (F.col("pos") < high)).select("pos")
        piece = piece.join(used.withColumnRenamed("late", "pos"), "pos", "left").join(own.withColumnRenamed("late", "pos"), "pos", "left")
        got, _ = rounds.keep(piece.select("pos", "used", "own").repartition(1).sortWithinPartitions("pos").mapInArrow(_greedy(low), "pos bigint, color bigint"), "piece", coloured=F.count(F.lit(1)))
        done, low = rounds.append(got, "done"), high
    return place.join(done, "pos").select("v", "color")


def _greedy(low: int):
    """Colours rows (pos, used, own) that come in the order of pos, without a gap from `low`."""

    def solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got: list[int] = []
        for b in batches:
            began = len(got)
            for used, own in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                taken = set(used or ())
                taken.update([got[p - low] for p in own or ()])
                c = 0
                while c in taken:
                    c += 1
                got.append(c)
            yield pa.record_batch([b.column(0), pa.array(got[began:], pa.int64())], ["pos", "color"])

    return solve


def cover_from_graph(g: Graph) -> DataFrame:
    """Every vertex as the set of its neighbours: (set_id, elem_id)."""
    return g.edges.select(F.col("src").alias("set_id"), F.col("dst").alias("elem_id"))


def set_cover(instance: DataFrame, *, eps: float = 0.01, seed: int = 42, repriority: bool = True, stats: RunStats | None = None) -> DataFrame:
    """(set_id): a cover within about (1 + eps) of the harmonic bound.

    The fullest bucket of sets bids for its open elements each round, with fresh priorities (or, as the baseline, by id); a set is accepted
    if it wins about a bucket's worth of elements, or all it has.

    The instance is written once, in buckets by set, and stays. A set's degree is an upper bound: each round the open elements
    of sets bounded by over half of the fullest bucket are counted, and those truly in the fullest one bid (nobody, if all had lost
    half of their elements). Covered elements are appended to one table.
    """
    rounds = Rounds(instance.sparkSession, "cover")
    arcs = rounds.bucketed(instance.select("set_id", "elem_id").distinct(), "set_id", "elem_id")
    number = lambda d: F.floor(F.log(d.cast("double")) / math.log(1 + eps) + 1e-9)
    held = Buckets(rounds, F.when((F.col("degree") > 0) & ~F.col("taken"), number(F.col("degree"))), "max", "sets")
    held.put(arcs.groupBy("set_id").agg(F.count(F.lit(1)).alias("degree")).withColumn("taken", F.lit(False)))
    covered = rounds.append(instance.select("elem_id").limit(0), "covered")
    r, half = 1, math.floor(math.log(2) / math.log(1 + eps))
    while held.id is not None:
        low = max(held.id - half - 1, -1)
        sets = held.rows.where(held.bucket > low).select("set_id")
        own, _ = rounds.keep(sets.join(arcs, "set_id").join(covered, "elem_id", "left_anti").select("set_id", "elem_id"), "own")
        degree = own.groupBy("set_id").agg(F.count(F.lit(1)).alias("degree"))
        top = degree.agg(F.max(number(F.col("degree"))).alias("top")).where(F.col("top") > low)  # one row
        bid: Column = prio(f"{seed}.{r}", "set_id") if repriority else F.col("set_id")
        active = own.join(degree.join(F.broadcast(top), number(F.col("degree")) == F.col("top")), "set_id")
        won = active.groupBy("elem_id").agg(F.min(F.struct(bid.alias("p"), "set_id", "degree", "top")).alias("s")).groupBy("s.set_id", "s.degree", "s.top").agg(F.count(F.lit(1)).alias("won"))
        need = F.ceil(F.pow(F.lit(1.0 + eps), F.greatest(F.col("top") - 1, F.lit(0))) - 1e-9)
        won = won.select("set_id", ((F.col("won") > need) | (F.col("won") == F.col("degree"))).alias("taken"))
        won, seen = rounds.keep(won, "won", winners=F.count(F.lit(1)), sets=F.count_if("taken"))
        accepted = won.where("taken")
        if seen["sets"]:
            covered = rounds.append(own.join(accepted, "set_id", "left_semi").select("elem_id").distinct(), "covered")
        if seen["winners"]:  # else nobody bid
            r += 1
            if stats is not None:
                stats.rounds.append(seen)
        now = sets.join(degree, "set_id", "left").join(accepted, "set_id", "left")
        held.update(now.select("set_id", F.coalesce("degree", F.lit(0)).alias("degree"), F.coalesce("taken", F.lit(False)).alias("taken")), "set_id")
    return held.rows.where("taken").select("set_id")


def greedy_cover(instance: DataFrame, *, stats: RunStats | None = None) -> DataFrame:
    """The sequential greedy cover, a set a round: for small instances."""
    rounds = Rounds(instance.sparkSession, "greedy", stats)
    edges, picked = rounds.table(instance.select("set_id", "elem_id").distinct()), []
    while top := edges.groupBy("set_id").agg(F.count(F.lit(1)).alias("d")).orderBy(F.desc("d"), "set_id").limit(1).first():
        picked.append((top.set_id,))
        covered = edges.where(F.col("set_id") == top.set_id).select("elem_id")
        edges, _ = rounds.keep(edges.join(covered, "elem_id", "left_anti").select("set_id", "elem_id"), "edges", left=F.count(F.lit(1)))
    return instance.sparkSession.createDataFrame(picked, "set_id bigint")
