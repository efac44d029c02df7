"""Certificates: one row that tells whether a result has the properties its problem asks for."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..algo.bfs import bfs
from ..algo.connectivity import hook_jump
from ..algo.substructure import kcore_hindex, kcore_pow2
from ..core.rounds import Rounds
from ..model.graph import Graph, from_arcs

#: Rows (source, vertex) of a step of the stretch check; beyond it sources are parted, in at most WAYS at a time and CUTS times over.
REACH = 1 << 26
WAYS, CUTS = 16, 8
#: Arcs of a graph whose stretch is checked within tasks, each of which holds all of it; entries of the marks of sources followed together.
FITS, MARKS = 1 << 23, 1 << 23


def one(g: Graph, **values) -> DataFrame:
    kinds = {bool: "boolean", int: "bigint", float: "double"}
    return g.spark.createDataFrame([tuple(values.values())], ", ".join(f"{k} {kinds[type(v)]}" for k, v in values.items()))


def bfs_parents(g: Graph, found: DataFrame) -> DataFrame:
    """Reached vertices off the source have a parent one level up that is a neighbour; arcs skip no level."""
    found = Rounds(g.spark, "check").table(found)
    at = lambda c: found.select(F.col("v").alias(c), F.col("dist").alias(f"d_{c}"))
    up = found.where("dist > 0").select(F.col("v").alias("dst"), F.col("parent").alias("src"), "dist")
    wrong = up.join(g.edges.select("src", "dst"), ["src", "dst"], "left_anti").count() + up.join(at("src"), "src").where("d_src <> dist - 1").count()
    wrong += g.edges.join(at("src"), "src").join(at("dst"), "dst").where("d_src IS NOT NULL AND (d_dst IS NULL OR d_dst > d_src + 1)").count()
    return one(g, violations=wrong)


def distances(g: Graph, found: DataFrame) -> DataFrame:
    """No arc shortens a distance, and each but the source's is reached by a tight arc."""
    at = lambda c: found.select(F.col("v").alias(c), F.col("dist").alias(f"d_{c}"))
    arcs = g.edges.join(at("src"), "src").join(at("dst"), "dst").where("d_src IS NOT NULL")
    loose = arcs.where("d_dst IS NULL OR d_dst > d_src + w").count()
    tight = arcs.where("d_dst = d_src + w").select("dst").distinct().count()
    return one(g, loose=loose, untight=found.where("dist IS NOT NULL").count() - 1 - tight)


def ball_quality(g: Graph, balls: DataFrame, beta: float) -> DataFrame:
    """Centres are their own; balls are connected through parents; cut fraction and radius are of the promised order."""
    balls = Rounds(g.spark, "check").table(balls)
    n, m = max(2, g.vertices.count()), max(1, g.edges.count())
    own = balls.select("center").distinct().join(balls.where("v = center").select("v"), F.col("center") == F.col("v"), "left_anti").isEmpty()
    up = balls.where("v <> center").select(F.col("v").alias("dst"), F.col("parent").alias("src"), "center", "arrival")
    above = balls.select(F.col("v").alias("src"), F.col("center").alias("c"), F.col("arrival").alias("a"))
    good = up.join(above, "src").where("c = center AND a = arrival - 1").join(g.edges.select("src", "dst"), ["src", "dst"], "left_semi").count() == up.count()
    cut, radius = quality(g, balls)
    return one(g, centers_own=own, connected=good, within_bounds=cut <= 4 * beta * m and radius <= 12 * math.log(n) / beta)


def quality(g: Graph, balls: DataFrame) -> tuple[int, int]:
    """Arcs between balls, and the largest arrival after a ball's start."""
    at = lambda c: balls.select(F.col("v").alias(c), F.col("center").alias(f"c_{c}"))
    cut = g.edges.join(at("src"), "src").join(at("dst"), "dst").where("c_src <> c_dst").count()
    start = balls.where("v = center").select("center", F.col("arrival").alias("start"))
    radius = balls.join(start, "center").agg(F.max(F.col("arrival") - F.col("start")).alias("r")).first().r or 0
    return cut, radius


def stretch(g: Graph, h: Graph, pairs: DataFrame, limit: int, most: int = REACH) -> int:
    """How many of the pairs (src, dst) are farther apart than `limit` in h, whose arcs go both ways.

    Balls around all sources grow together, and a source's ball stops when its pairs are settled. Only their last two shells are held: what
    a shell meets lies in it, in the one before or in the next. Where the next step may have over `most` rows, the sources still open
    are parted and go on one part after the other.
    """
    rounds = Rounds(g.spark, "stretch")
    arcs = rounds.table(h.edges.select(F.col("src").alias("at"), F.col("dst").alias("to")))
    degree = rounds.table(arcs.groupBy("at").agg(F.count(F.lit(1)).alias("degree")))
    weigh = lambda df: df.join(degree, "at").select("src", "at", "degree")
    start = rounds.table(pairs.select("src", "dst"))
    last, seen = rounds.keep(weigh(start.select("src", F.col("src").alias("at")).distinct()), step=F.sum("degree"))
    far, waiting = 0, [(start, start.select("src", F.col("src").alias("at")).limit(0), last, seen["step"] or 0, 0, 0)]
    while waiting:
        open_, before, last, step, depth, cut = waiting.pop()
        if step > most and cut < CUTS and (parts := min(WAYS, -(-step // most))) > 1:
            of = F.pmod(F.xxhash64("src", F.lit(cut)), F.lit(parts))
            dealt = [rounds.table(df.withColumn("part", of)) for df in (open_, before, last)]
            for p in range(parts):
                mine = [df.where(F.col("part") == p).drop("part") for df in dealt]
                rows = mine[2].agg(F.sum("degree").alias("n")).first().n or 0
                waiting.append((*mine, rows, depth, cut + 1))
            continue
        while depth < limit and step:
            grown = last.join(arcs, "at").select("src", F.col("to").alias("at")).distinct()
            grown = grown.join(last.select("src", "at").unionByName(before), ["src", "at"], "left_anti")
            shell = rounds.table(weigh(grown))
            open_ = rounds.table(open_.join(shell.select("src", F.col("at").alias("dst")), ["src", "dst"], "left_anti"))
            live = open_.select("src").distinct()
            before = last.select("src", "at").join(live, "src", "left_semi")
            last, seen = rounds.keep(shell.join(live, "src", "left_semi"), step=F.sum("degree"))
            step, depth = seen["step"] or 0, depth + 1
            if step > most and cut < CUTS:
                break
        if depth < limit and step:
            waiting.append((open_, before, last, step, depth, cut))
        else:
            far += open_.count()
    return far


class Held:
    """A graph's arcs in memory, by index of their source."""

    def __init__(self, src: np.ndarray, dst: np.ndarray):
        self.ids, n = np.unique(src), len(src)
        self.first = np.searchsorted(src, self.ids, "left").astype(np.int64)
        self.degree = np.diff(np.append(self.first, n))
        # arcs go both ways, so every target is a source
        self.to = np.searchsorted(self.ids, dst).astype(np.int32)
        self.width = max(1, MARKS // max(1, len(self.ids)))
        self.seen = np.zeros(self.width * len(self.ids), np.bool_)
        self.turn = np.zeros(self.width * len(self.ids), np.int32)

    def place(self, v: np.ndarray) -> np.ndarray:
        """Indices of the ids, -1 for those without an arc."""
        if not len(self.ids):
            return np.full(len(v), -1)
        at = np.minimum(np.searchsorted(self.ids, v), len(self.ids) - 1)
        return np.where(self.ids[at] == v, at, -1)

    def far(self, src: np.ndarray, dst: np.ndarray, limit: int) -> int:
        """How many pairs, all of their sources among the first `width` of a list, are farther apart than `limit`: levels from all sources at once."""
        own = src != dst
        a, b = self.place(src[own]), self.place(dst[own])
        lost = int(np.count_nonzero((a < 0) | (b < 0)))
        a, b = a[(a >= 0) & (b >= 0)], b[(a >= 0) & (b >= 0)]
        starts, slot = np.unique(a, return_inverse=True)
        n = len(self.ids)
        want = slot.astype(np.int64) * n + b
        shell = np.arange(len(starts), dtype=np.int64) * n + starts
        self.seen[shell], met = True, [shell]
        for _ in range(limit):
            live = np.zeros(len(starts), np.bool_)
            live[want // n] = True
            shell = shell[live[shell // n]]
            if not len(shell):
                break
            v = shell % n
            size = self.degree[v]
            ends = np.cumsum(size)
            to = np.repeat(self.first[v] - (ends - size), size) + np.arange(ends[-1])
            grown = np.repeat(shell - v, size) + self.to[to]
            grown = grown[~self.seen[grown]]
            self.turn[grown] = np.arange(len(grown), dtype=np.int32)
            shell = grown[self.turn[grown] == np.arange(len(grown), dtype=np.int32)]
            self.seen[shell] = True
            met.append(shell)
            want = want[~self.seen[want]]
        self.seen[np.concatenate(met)] = False
        return lost + len(want)


def stretch_held(h: Graph, pairs: DataFrame, limit: int, fits: int = FITS) -> int | None:
    """`stretch` of a graph of at most `fits` arcs: every task holds it and follows its own sources; None if there are more."""
    spark = h.spark
    arcs, seen = Rounds(spark, "stretch").keep(h.edges.select("src", "dst"), arcs=F.count(F.lit(1)))
    if seen["arcs"] > fits:
        return None
    both = arcs.orderBy("src").toArrow()
    sent = spark.sparkContext.broadcast((both["src"].to_numpy(), both["dst"].to_numpy()))

    def follow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        both = [np.stack([b.column(0).to_numpy(), b.column(1).to_numpy()]) for b in batches]
        src, dst = np.concatenate([np.empty((2, 0), np.int64), *both], 1)
        if not len(src):
            return
        held, far = Held(*sent.value), 0
        starts = np.append(np.flatnonzero(np.append(True, src[1:] != src[:-1])), len(src))
        for i in range(0, len(starts) - 1, held.width):
            low, high = starts[i], starts[min(i + held.width, len(starts) - 1)]
            far += held.far(src[low:high], dst[low:high], limit)
        yield pa.record_batch([pa.array([far], pa.int64())], ["far"])

    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = pairs.select("src", "dst").repartition(parts, "src").sortWithinPartitions("src")
    far = dealt.mapInArrow(follow, "far bigint").agg(F.sum("far").alias("far")).first().far or 0
    sent.destroy()
    return far


def spanner(g: Graph, edges: DataFrame, k: int) -> DataFrame:
    """Edges are the graph's, components stay, and every dropped edge is stretched by O(k) at most."""
    edges = Rounds(g.spark, "check").table(edges)
    foreign = edges.join(g.edges.select("src", "dst"), ["src", "dst"], "left_anti").count()
    h = from_arcs(edges, g.vertices)
    h = Graph(h.vertices, Rounds(g.spark, "check").table(h.edges), h.directed, h.name)
    dropped = g.half().select("src", "dst").join(h.edges.select("src", "dst"), ["src", "dst"], "left_anti")
    far = stretch_held(h, dropped, 8 * k + 8)
    if far is None:
        far = stretch(g, h, dropped, 8 * k + 8)
    # edges of the graph that join the ends of all dropped ones have its components; else these are compared
    spans = foreign == far == 0 or hook_jump(h).exceptAll(hook_jump(g)).isEmpty()
    return one(g, foreign_edges=foreign, spans=spans, within_stretch=far == 0)


def forest(g: Graph, edges: DataFrame) -> DataFrame:
    """Edges n - c, all of the graph, with the graph's components: hence without a cycle."""
    edges = Rounds(g.spark, "check").table(edges)
    foreign = edges.join(g.edges.select("src", "dst"), ["src", "dst"], "left_anti").count()
    parts = hook_jump(from_arcs(edges, g.vertices)).select("label").distinct().count()
    return one(g, edges=edges.count(), foreign_edges=foreign, components=parts)


def independent(g: Graph, chosen: DataFrame) -> DataFrame:
    chosen = Rounds(g.spark, "check").table(chosen)
    mine = g.edges.join(chosen.withColumnRenamed("v", "src"), "src", "left_semi")
    inside = mine.join(chosen.withColumnRenamed("v", "dst"), "dst", "left_semi").count()
    covered = mine.select(F.col("dst").alias("v")).unionByName(chosen)
    return one(g, dependent=inside, uncovered=g.vertices.join(covered, "v", "left_anti").count())


def matching(g: Graph, edges: DataFrame) -> DataFrame:
    ends = edges.select(F.col("src").alias("v")).unionByName(edges.select(F.col("dst").alias("v")))
    twice = ends.groupBy("v").agg(F.count(F.lit(1)).alias("n")).where("n > 1").count()
    free = g.vertices.join(ends, "v", "left_anti")
    return one(g, overlaps=twice, addable=g.induced(free).half().count())


def coloring(g: Graph, colors: DataFrame) -> DataFrame:
    colors = Rounds(g.spark, "check").table(colors)
    at = lambda c: colors.select(F.col("v").alias(c), F.col("color").alias(f"c_{c}"))
    clash = g.edges.join(at("src"), "src").join(at("dst"), "dst").where("c_src = c_dst").count()
    most = g.degrees().agg(F.max("degree").alias("d")).first().d or 0
    return one(g, conflicts=clash, within_bound=(colors.agg(F.max("color").alias("c")).first().c or 0) <= most)


def cover(instance: DataFrame, chosen: DataFrame) -> DataFrame:
    """All elements are covered; the size is within 8 (1 + ln of the largest set) times the elements-over-largest-set lower bound."""
    instance, chosen = instance.distinct(), Rounds(instance.sparkSession, "check").table(chosen)
    covered = instance.join(chosen, "set_id", "left_semi").select("elem_id").distinct()
    n, left = instance.select("elem_id").distinct().count(), 0
    left = n - covered.count()
    largest = instance.groupBy("set_id").agg(F.count(F.lit(1)).alias("d")).agg(F.max("d").alias("d")).first().d or 1
    size = chosen.count()
    fine = size <= max(1, n) and size == chosen.distinct().count() and size <= max(n / largest, 1) * (1 + math.log(largest)) * 8
    return instance.sparkSession.createDataFrame([(left, fine)], "uncovered bigint, within_bound boolean")


def pow2(g: Graph) -> DataFrame:
    both = kcore_hindex(g).join(kcore_pow2(g).withColumnRenamed("coreness", "estimate"), "v")
    return both.agg(F.count(F.lit(1)).alias("vertices"), F.count_if(F.col("estimate") < F.col("coreness")).alias("too_low"), F.count_if((F.col("estimate") >= 2 * F.col("coreness")) & (F.col("coreness") > 0)).alias("too_high"))


def dense(g: Graph, chosen: DataFrame, density: float) -> DataFrame:
    """The density is that of the subgraph, and between half the degeneracy over 1.01 ... and the degeneracy."""
    sub = g.induced(chosen)
    again = sub.half().count() / max(1, chosen.count())
    top = kcore_hindex(g).agg(F.max("coreness").alias("k")).first().k or 0
    return one(g, density_holds=abs(again - density) < 1e-9, within_bounds=top / 2 / 2.01 <= density <= top)


def ranks_close(a: DataFrame, b: DataFrame, eps: float = 0.02) -> DataFrame:
    both = a.withColumnRenamed("rank", "x").join(b.withColumnRenamed("rank", "y"), "v")
    return both.agg((F.sum(F.abs(F.col("x") - F.col("y"))) < eps).alias("close"), (F.abs(F.sum("y") - 1) < eps).alias("mass_kept"))


def levels(g: Graph, source: int) -> DataFrame:
    return bfs(g, source).groupBy("dist").agg(F.count(F.lit(1)).alias("vertices"))
