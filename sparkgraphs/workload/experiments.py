"""The experiment workloads, re-expressed on the given tables: python -m sparkgraphs.workload X4 [sf_dir]

Each returns rows (dictionaries) with what the experiment compares: seconds, rounds, counters, sizes, qualities.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..algo import ball, bfs, biconnectivity, connectivity, covering, msf, ranking, relax, scc, substructure
from ..check import certificates as cert
from ..core import blocks
from ..core.histogram import STRATEGIES
from ..core.rounds import Rounds, RunStats
from ..measure import measures
from ..model import catalog
from ..model.graph import Graph, from_arcs

Rows = list[dict]
X: dict[str, Callable[[SparkSession, str], Rows]] = {}


def workload(name: str):
    def add(f):
        X[name] = f
        return f

    return add


def load(spark: SparkSession, d: str, name: str, weights: bool = False) -> Graph:
    g = catalog.load(spark, d, name)
    return (g.with_weights() if weights else g).layout()


def first(g: Graph) -> int:
    return g.vertices.agg(F.min("v").alias("m")).first().m


#: The twenty problems: each takes a weighted graph and counters, and gives a table.
PROBLEMS: dict[str, Callable[[Graph, RunStats], DataFrame]] = {
    "bfs": lambda g, s: bfs.bfs(g, first(g), stats=s),
    "weighted_bfs": lambda g, s: relax.weighted_bfs(g, first(g), stats=s),
    "bellman_ford": lambda g, s: relax.bellman_ford(g, first(g), stats=s),
    "widest_path": lambda g, s: relax.widest_path(g, first(g), stats=s),
    "betweenness": lambda g, s: bfs.betweenness(g, first(g), stats=s),
    "spanner": lambda g, s: ball.spanner(g, 4, stats=s),
    "ball_decomposition": lambda g, s: ball.ball_decompose(g, 0.2, stats=s),
    "connectivity": lambda g, s: connectivity.connectivity(g, stats=s),
    "spanning_forest": lambda g, s: connectivity.spanning_forest(g, stats=s),
    "biconnectivity": lambda g, s: biconnectivity.biconnectivity(g, stats=s).vertex_labels,
    "scc": lambda g, s: scc.scc(g, stats=s),
    "msf": lambda g, s: msf.msf(g, stats=s),
    "mis": lambda g, s: covering.mis(g, stats=s),
    "matching": lambda g, s: covering.maximal_matching(g, stats=s),
    "colouring": lambda g, s: covering.color(g, stats=s),
    "set_cover": lambda g, s: covering.set_cover(covering.cover_from_graph(g), eps=0.1, stats=s),
    "kcore": lambda g, s: substructure.kcore(g, stats=s),
    "densest": lambda g, s: substructure.densest_subgraph(g, stats=s)[0],
    "triangles": lambda g, s: substructure.triangle_count(g),
    "pagerank_iteration": lambda g, s: ranking.pagerank_iteration(g),
}


def runs(g: Graph, variants: dict[str, Callable[[RunStats], DataFrame]]) -> Rows:
    return [{"graph": g.name, "variant": k, **measures.timed(f)} for k, f in variants.items()]


#: Problems of directed graphs; the others run on graphs that hold both orientations.
DIRECTED = ("scc",)


def problems_of(g: Graph) -> dict[str, Callable[[Graph, RunStats], DataFrame]]:
    return {p: f for p, f in PROBLEMS.items() if (p in DIRECTED) == g.directed}


@workload("X1")
def every_problem(spark: SparkSession, d: str) -> Rows:
    """All problems on four whole graphs, strong components on two directed ones (seconds on this session's cores; X26 sets them against one core)."""
    out = []
    for name in ("cust_supp", "cust_part", "part_copurchase", "torus", "event_succession", "event_hot_succession"):
        g = load(spark, d, name, True)
        for p, f in problems_of(g).items():
            run = measures.timed(lambda s, f=f, g=g: f(g, s))
            out.append({"graph": name, "problem": p, **run, "arcs_per_second": measures.throughput(g, run["seconds"])})
    return out


@workload("X2")
def blocked_form(spark: SparkSession, d: str) -> Rows:
    """All problems on three graphs in blocked form against the edge list; the links of pages directed, and in both directions."""
    out = []
    for name in ("part_supp", "part_copurchase", "page_links"):
        g = load(spark, d, name, True)
        for x in (g, g.symmetrised().layout()) if g.directed else (g,):
            out += from_blocks(x, problems_of(x))
    return out


def from_blocks(g: Graph, problems: dict[str, Callable[[Graph, RunStats], DataFrame]]) -> Rows:
    """Whether problems have the same answers from difference-coded blocks as from the edge list, and the seconds of both.

    Weights are drawn again from the ends of an edge, so blocks need not hold them. Real-valued answers are compared to six places.
    """
    rounds, out = Rounds(g.spark, "from_blocks"), []
    adj = rounds.table(blocks.encode_blocks(g.edges))
    h = Graph(g.vertices, blocks.decode_blocks(adj), g.directed, f"{g.name}_blocks").with_weights().layout()
    for p, f in problems.items():
        rows, seconds = [], []
        for x in (g, h):
            began = time.time()
            rows.append(rounds.table(places(f(x, RunStats()))))
            seconds.append(time.time() - began)
        same = rows[0].exceptAll(rows[1]).isEmpty() and rows[1].exceptAll(rows[0]).isEmpty()
        out.append({"graph": g.name, "problem": p, "same": same, "seconds_edges": seconds[0], "seconds_blocks": seconds[1]})
    return out


def places(df: DataFrame, digits: int = 6) -> DataFrame:
    """Real columns rounded: sums of parts taken in another order differ in their last bits."""
    return df.select(*[F.round(c, digits).alias(c) if kind == "double" else F.col(c) for c, kind in df.dtypes])


@workload("X3")
def statistics(spark: SparkSession, d: str) -> Rows:
    """Sizes, components, degeneracy and the depth from the smallest vertex of every graph of the catalogue; cores only where arcs go both ways."""
    out = []
    for name in catalog.NAMES:
        g = load(spark, d, name)
        if g.directed:
            out.append(measures.graph_stats(g.symmetrised().layout()).first().asDict() | {"depth": bfs.effective_diameter(g, [first(g)]).first().depth})
            continue
        row = measures.graph_stats(g).first().asDict()
        out.append(row | {"degeneracy": substructure.degeneracy(g).first()[0], "depth": bfs.effective_diameter(g, [first(g)]).first().depth})
    return out


@workload("X4")
def core_histograms(spark: SparkSession, d: str) -> Rows:
    """Every histogram strategy on a graph of many shared targets and on the one with the hubs."""
    out = []
    for name in ("user_item", "cust_supp"):
        g = load(spark, d, name)
        out += runs(g, {s: lambda st, s=s, g=g: substructure.kcore(g, strategy=s, stats=st) for s in STRATEGIES})
    return out


@workload("X5")
def blocked_push(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "cust_supp", True)
    level = bfs.bfs(g, first(g)).cache()
    ratio = measures.live_ratio(g, level.where("dist = 1").select("v"), level.where("dist > 1").select("v")).first().asDict()
    return runs(g, {m: lambda s, m=m: relax.weighted_bfs(g, first(g), mode=m, stats=s) for m in ("blocked", "push")}) + [ratio]


@workload("X6")
def torus_curves(spark: SparkSession, d: str) -> Rows:
    """Arcs a second by the side of the torus, for all sides that the parts suffice for."""
    out, parts = [], catalog.read(spark, d, "part").count()
    for side in (s for s in (5, 8, 12, 18, 27) if s**3 <= parts):
        g = from_arcs(catalog.torus(spark, d, side), name=f"torus{side}").layout()
        for p in ("mis", "bfs", "betweenness", "colouring"):
            run = measures.timed(lambda s, p=p, g=g: PROBLEMS[p](g, s))
            out.append({"problem": p, "n": side**3, "arcs_per_second": measures.throughput(g, run["seconds"])})
    halves = {p: measures.half_length([(r["n"], r["arcs_per_second"]) for r in out if r["problem"] == p]) for p in ("mis", "bfs", "betweenness", "colouring")}
    return out + [{"half_length": halves}]


@workload("X7")
def widest(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "cust_supp", True)
    return runs(g, {m: lambda s, m=m: relax.widest_path(g, first(g), method=m, stats=s) for m in ("semiring", "bucket")})


@workload("X8")
def shortest(spark: SparkSession, d: str) -> Rows:
    out = []
    for name in ("cust_supp", "torus"):
        g = load(spark, d, name, True)
        out += runs(g, {"weighted_bfs": lambda s, g=g: relax.weighted_bfs(g, first(g), stats=s), "bellman_ford": lambda s, g=g: relax.bellman_ford(g, first(g), stats=s), "delta_3": lambda s, g=g: relax.delta_stepping(g, first(g), 3, stats=s)})
    return out


@workload("X9")
def spanners(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "torus")
    return [{"k": k, "inter": i, "edges": ball.spanner(g, k, inter=i).count(), "of": g.half().count()} for k in (1, 2, 4, 8) for i in ("cluster_pair", "boundary_vertex")]


@workload("X10")
def decompositions(spark: SparkSession, d: str) -> Rows:
    out = []
    for name in ("order_part_h1", "torus"):
        g = load(spark, d, name)
        m = g.edges.count()
        for beta in (0.05, 0.1, 0.2, 0.5):
            for permute in (True, False):
                stats = RunStats()
                cut, radius = cert.quality(g, ball.ball_decompose(g, beta, permute=permute, stats=stats).cache())
                out.append({"graph": name, "beta": beta, "permuted": permute, "cut_fraction": cut / m, "radius": radius, "rounds": stats.depth})
    return out


@workload("X11")
def components(spark: SparkSession, d: str) -> Rows:
    out = []
    for name in ("order_part_h1", "conversation_chain"):
        g = load(spark, d, name)
        out += runs(g, {m: lambda s, m=m, g=g: connectivity.connectivity(g, m, stats=s) for m in connectivity.METHODS})
    return out


@workload("X12")
def forests(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "order_part_h1")
    return runs(g, {"connectivity": lambda s: connectivity.connectivity(g, stats=s), "forest": lambda s: connectivity.spanning_forest(g, stats=s)})


@workload("X13")
def blocks_of_graphs(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "cust_part_urgent")
    return runs(g, {"connectivity": lambda s: connectivity.hook_jump(g, stats=s), "biconnectivity": lambda s: biconnectivity.biconnectivity(g, stats=s).vertex_labels, "depth_first": lambda s: biconnectivity.bicc_dfs(g)})


@workload("X14")
def strong_components(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "event_hot_succession")
    variants = {f"growth_{b}": lambda s, b=b: scc.scc(g, beta_growth=b, stats=s) for b in (1.1, 1.5, 2.0)}
    variants |= {"no_trim": lambda s: scc.scc(g, trim=False, stats=s), "no_pivot": lambda s: scc.scc(g, first_pivot=False, stats=s), "fwbw": lambda s: scc.scc_fwbw_trim(g, stats=s), "staged": lambda s: scc.scc_staged(g, stats=s), "largest": lambda s: scc.largest_scc(g)}
    return runs(g, variants)


@workload("X15")
def spanning_trees(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "user_item", True)
    return runs(g, {"filtered": lambda s: msf.msf(g, stats=s), **{f"filter_{k}": lambda s, k=k: msf.msf(g, filter_steps=k, stats=s) for k in (1, 2)}, "boruvka": lambda s: msf.msf(g, method="boruvka", stats=s), "kruskal": lambda s: msf.msf(g, method="kruskal", stats=s)})


@workload("X16")
def independent_sets(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "torus")
    return runs(g, {m: lambda s, m=m: covering.mis(g, method=m, stats=s) for m in ("rootset", "prefix", "luby")})


@workload("X17")
def matchings(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "cust_part")
    return runs(g, {m: lambda s, m=m: covering.maximal_matching(g, method=m, stats=s) for m in ("filtered", "prefix_all", "plain")})


@workload("X18")
def colourings(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "user_item")
    most = g.degrees().agg(F.max("degree")).first()[0]
    return [{"heuristic": h, "colours": covering.color(g, heuristic=h).agg(F.max("color") + 1).first()[0], "max_degree": most} for h in ("llf", "sll", "lf", "r")]


@workload("X19")
def covers(spark: SparkSession, d: str) -> Rows:
    sets = covering.cover_from_graph(load(spark, d, "torus"))
    out = []
    for eps in (0.01, 0.1, 0.5):
        for fresh in (True, False):
            stats = RunStats()
            out.append({"eps": eps, "fresh_priorities": fresh, "sets": covering.set_cover(sets, eps=eps, repriority=fresh, stats=stats).count(), "rounds": stats.depth})
    return out


@workload("X20")
def dense_parts(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "user_item")
    return [{"variant": n, "density": f()[1]} for n, f in (("eps_0.001", lambda: substructure.densest_subgraph(g)), ("eps_0", lambda: substructure.densest_subgraph(g, eps=0.0)), ("degeneracy", lambda: substructure.densest_degeneracy(g)))]


@workload("X21")
def triangles(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "part_copurchase")
    return [{"method": m, "triangles": substructure.triangle_count(g, method=m).first()[0], **measures.timed(lambda s, m=m: substructure.triangle_count(g, method=m))} for m in ("oriented_join", "oriented_lists", "undirected")]


@workload("X22")
def ranks(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "cust_supp")
    return runs(g, {"pull": lambda s: ranking.pagerank(g, stats=s), "push_raw": lambda s: ranking.pagerank(g, mode="push_raw", stats=s), "delta": lambda s: ranking.pagerank_delta(g, stats=s)})


@workload("X23")
def dense_switch(spark: SparkSession, d: str) -> Rows:
    """Weighted search with and without pulling in rounds of large frontiers, and the modes of the search by levels."""
    g = load(spark, d, "cust_supp", True)
    weighted = {f"weighted_{'switch' if on else 'push'}": lambda s, on=on: relax.weighted_bfs(g, first(g), dense_switch=on, stats=s) for on in (True, False)}
    return runs(g, weighted | {m: lambda s, m=m: bfs.bfs(g, first(g), mode=m, stats=s) for m in ("auto", "blocked", "pull", "push")})


@workload("X24")
def directed_and_symmetric(spark: SparkSession, d: str) -> Rows:
    g = load(spark, d, "event_succession")
    return [r for h in (g, load(spark, d, "event_succession_sym")) for r in runs(h, {"bfs": lambda s, h=h: bfs.bfs(h, first(h), stats=s), "betweenness": lambda s, h=h: bfs.betweenness(h, first(h), stats=s), "pagerank": lambda s, h=h: ranking.pagerank(h, stats=s)})]


@workload("X25")
def approximate_cores(spark: SparkSession, d: str) -> Rows:
    return [cert.pow2(load(spark, d, "user_item")).first().asDict()]


def ratios(one: Rows, many: Rows, cores: int) -> Rows:
    """Seconds of the same problems on one core and on `cores`, and how many times faster the latter are."""
    key = lambda r: (r["graph"], r["problem"])
    fast = {key(r): r["seconds"] for r in many}
    return [{"graph": g, "problem": p, "one_core": s, "cores": cores, "all_cores": fast[g, p], "speedup": s / fast[g, p]} for (g, p), s in ((key(r), r["seconds"]) for r in one) if (g, p) in fast]


def on_cores(name: str, d: str, cores: int) -> Rows:
    """The rows of an experiment from a process of its own on local[cores]: a session keeps the cores it was started with."""
    run = subprocess.run([sys.executable, "-m", "sparkgraphs.workload", name, d], env={**os.environ, "BENCH_CPUS": str(cores)}, stdout=subprocess.PIPE, text=True, check=True)
    return [json.loads(line) for line in run.stdout.splitlines() if line.startswith("{")]


@workload("X26")
def speedup(spark: SparkSession, d: str) -> Rows:
    """All problems of X1 on one core and on all of this session's: two more processes, one after the other, on this machine."""
    cores = spark.sparkContext.defaultParallelism
    return ratios(on_cores("X1", d, 1), on_cores("X1", d, cores), cores)
