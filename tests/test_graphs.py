import math

import micro
import pytest
from micro import values
from pyspark.sql import functions as F

from sparkgraphs.algo import ball, bfs, biconnectivity, connectivity, covering, msf, ranking, relax, scc, substructure
from sparkgraphs.check import certificates as cert
from sparkgraphs.core import blocks
from sparkgraphs.core.histogram import STRATEGIES, histogram
from sparkgraphs.core.prims import index, scan
from sparkgraphs.core.rounds import RunStats
from sparkgraphs.measure import measures


@pytest.mark.parametrize("mode", ["auto", "push", "blocked", "pull"])
def test_bfs_modes(spark, mode):
    g = micro.graph(spark, [(0, 1), (1, 2), (0, 3), (3, 2), (7, 8)], vertices=[9])
    assert values(bfs.bfs(g, 0, mode=mode, with_parent=True)) == [(0, 0, None), (1, 1, 0), (2, 2, 1), (3, 1, 0), (7, None, None), (8, None, None), (9, None, None)]


def test_bfs_counts_rounds_and_stops_at_depth(spark):
    stats = RunStats()
    assert dict(values(bfs.bfs(micro.path(spark, 5), 0, max_depth=2, mode="blocked", stats=stats)))[4] is None
    assert stats.depth == 3 and stats.total("frontier") == 3


def test_empty_graph(spark):
    g = micro.empty(spark)
    for f in (substructure.kcore, covering.mis, covering.maximal_matching, connectivity.connectivity, connectivity.spanning_forest, covering.color, ranking.pagerank, substructure.triangle_count):
        assert f(g).count() in (0, 1)
    assert bfs.bfs(g, 0).count() == 0


def test_weighted_paths(spark):
    g = micro.graph(spark, [(0, 1, 4), (0, 2, 1), (2, 1, 2), (1, 3, 5)], vertices=[9])
    want = [(0, 0), (1, 3), (2, 1), (3, 8), (9, None)]
    for f in (relax.weighted_bfs, relax.bellman_ford, lambda g, s: relax.delta_stepping(g, s, 3), lambda g, s: relax.bellman_ford(g, s, mode="push")):
        assert values(f(g, 0)) == want
    widths = [(0, relax.TOP), (1, 4), (2, 2), (3, 4), (9, None)]
    assert values(relax.widest_path(g, 0)) == values(relax.widest_path(g, 0, method="bucket")) == widths
    with pytest.raises(ValueError):
        relax.weighted_bfs(micro.graph(spark, [(0, 1, 0)]), 0)


def test_negative_weights_and_cycles(spark):
    g = micro.graph(spark, [(0, 1, 4), (1, 2, -3), (0, 2, 2)], directed=True)
    assert values(relax.bellman_ford(g, 0)) == [(0, 0), (1, 4), (2, 1)]
    loop = micro.graph(spark, [(0, 1, 1), (1, 2, -3), (2, 1, 1), (5, 6, 1)], directed=True)
    assert all(r.dist == -math.inf for r in relax.bellman_ford(loop, 0).collect())
    assert dict(values(relax.bellman_ford(loop, 5)))[6] == 1  # the cycle is not reachable


def test_betweenness_of_a_path_and_a_diamond(spark):
    assert values(bfs.betweenness(micro.path(spark, 4), 0)) == [(0, 0.0), (1, 2.0), (2, 1.0), (3, 0.0)]
    diamond = micro.graph(spark, [(0, 1), (0, 2), (1, 3), (2, 3)])
    assert values(bfs.betweenness(diamond, 0, exact_paths=True)) == [(0, 0.0), (1, 0.5), (2, 0.5), (3, 0.0)]


@pytest.mark.parametrize("method", connectivity.METHODS)
def test_components(spark, method):
    g = micro.graph(spark, [(1, 2), (2, 3), (5, 6), (6, 7), (7, 5)], vertices=[9])
    assert values(connectivity.connectivity(g, method, **({"local_limit": 0} if method == "contract" else {}))) == [(1, 1), (2, 1), (3, 1), (5, 5), (6, 5), (7, 5), (9, 9)]


def test_spanning_forest_and_spanner(spark):
    g = micro.clique(spark, 7)
    assert values(cert.forest(g, connectivity.spanning_forest(g, local_limit=0))) == [(6, 0, 1)]
    for inter in ("cluster_pair", "boundary_vertex"):
        assert values(cert.spanner(g, ball.spanner(g, 2, inter=inter), 2)) == [(0, True, True)]


@pytest.mark.parametrize("ties", ball.TIES)
def test_balls(spark, ties):
    g = micro.cycle(spark, 12)
    for permute in (True, False):
        assert values(cert.ball_quality(g, ball.ball_decompose(g, 0.3, ties=ties, permute=permute), 0.9)) == [(True, True, True)]


def test_blocks_of_a_bow_tie(spark):
    """Two triangles that share a vertex stay two blocks."""
    b = biconnectivity.biconnectivity(micro.bow_tie(spark))
    assert values(biconnectivity.articulation_points(b)) == [(2,)] == values(biconnectivity.bicc_bfs_check(micro.bow_tie(spark)))
    assert len({r[2:] for r in values(biconnectivity.bicc_edge_labels(b))}) == 2
    assert values(biconnectivity.bicc_edge_labels(b)) == values(biconnectivity.bicc_dfs(micro.bow_tie(spark)))
    assert biconnectivity.bridges(b).count() == 0 and biconnectivity.same_block(b, (0, 1), (2, 1))


def test_bridges_of_a_path(spark):
    assert biconnectivity.bridges(biconnectivity.biconnectivity(micro.path(spark, 4))).count() == 3


@pytest.mark.parametrize("f", [scc.scc, scc.scc_fwbw_trim, scc.scc_staged, lambda g: scc.scc(g, trim=False), lambda g: scc.scc(g, first_pivot=False, beta_growth=2.0)])
def test_strong_components(spark, f):
    g = micro.graph(spark, [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4), (4, 5), (5, 3), (5, 6)], directed=True)
    assert values(f(g)) == [(0, 0), (1, 0), (2, 0), (3, 3), (4, 3), (5, 3), (6, 6)]


@pytest.mark.parametrize("method", ["filtered", "boruvka", "kruskal"])
def test_msf_with_equal_weights(spark, method):
    g = micro.graph(spark, [(i, (i + 1) % 6, 1) for i in range(6)])
    assert values(msf.msf(g, method=method)) == [(0, 1, 1), (0, 5, 1), (1, 2, 1), (2, 3, 1), (3, 4, 1)]


def test_independent_sets_agree(spark):
    g = micro.cycle(spark, 9)
    assert values(covering.mis(g)) == values(covering.mis(g, method="prefix"))
    assert values(cert.independent(g, covering.mis(g, method="luby"))) == [(0, 0)]
    assert covering.mis(micro.clique(spark, 6)).count() == 1


def test_matchings_agree(spark):
    g = micro.clique(spark, 6)
    found = [values(covering.maximal_matching(g, method=m)) for m in ("filtered", "prefix_all", "plain")]
    assert found[0] == found[1] == found[2] and len(found[0]) == 3
    assert values(cert.matching(g, covering.maximal_matching(g))) == [(0, 0)]


@pytest.mark.parametrize("heuristic", covering.HEURISTICS)
def test_colours(spark, heuristic):
    assert covering.color(micro.clique(spark, 5), heuristic=heuristic).select("color").distinct().count() == 5
    star = micro.star(spark, 8)
    assert values(cert.coloring(star, covering.color(star, heuristic=heuristic))) == [(0, True)]


def test_cover_makes_progress_on_small_sets(spark):
    sets = spark.createDataFrame([(s, e) for s in range(4) for e in range(5)] + [(9, 7)], "set_id bigint, elem_id bigint")
    assert covering.set_cover(sets, eps=0.01).count() == 2 == covering.greedy_cover(sets).count()
    assert covering.set_cover(sets, eps=0.01, repriority=False).count() == 2


@pytest.mark.parametrize("strategy", STRATEGIES)
def test_cores(spark, strategy):
    g = micro.graph(spark, [(0, 1), (1, 2), (2, 0), (2, 3), (3, 4)], vertices=[8])
    want = [(0, 2), (1, 2), (2, 2), (3, 1), (4, 1), (8, 0)]
    assert values(substructure.kcore(g, strategy=strategy)) == want == values(substructure.kcore_hindex(g)) == values(substructure.kcore_scan(g))


def test_peeling_and_density(spark):
    k6 = micro.clique(spark, 6)
    assert values(substructure.degeneracy(k6)) == [(5,)] and values(substructure.peeling_complexity(k6)) == [(1,)]
    # a regular graph is peeled at once also with eps = 0
    assert substructure.densest_subgraph(micro.cycle(spark, 8), eps=0.0)[1] == 1.0
    barbell = micro.graph(spark, [(i, j) for i in range(5) for j in range(i)] + [(4, 5), (5, 6), (6, 7)])
    assert substructure.densest_subgraph(barbell)[1] == 2.0 == substructure.densest_degeneracy(barbell)[1]
    assert substructure.k_core_subgraph(barbell, 4).vertices.count() == 5


@pytest.mark.parametrize("method", ["oriented_join", "oriented_lists", "undirected"])
def test_triangles_of_equal_degrees(spark, method):
    assert values(substructure.triangle_count(micro.clique(spark, 6), method=method)) == [(20,)]
    assert values(substructure.triangle_count(micro.star(spark, 6), method=method)) == [(0,)]


def test_triangles_per_vertex(spark):
    assert values(substructure.triangles_per_vertex(micro.bow_tie(spark))) == [(0, 1), (1, 1), (2, 2), (3, 1), (4, 1)]


def test_pagerank(spark):
    ring = ranking.pagerank(micro.cycle(spark, 5))
    assert all(abs(r.rank - 0.2) < 1e-9 for r in ring.collect())
    tail = micro.graph(spark, [(0, 1), (1, 2)], directed=True)
    assert abs(ranking.pagerank(tail, dangling="redistribute").agg(F.sum("rank")).first()[0] - 1) < 1e-6
    g = micro.bow_tie(spark)
    assert values(cert.ranks_close(ranking.pagerank(g), ranking.pagerank_delta(g, local_eps=1e-4))) == [(True, True)]
    assert values(ranking.pagerank_iteration(g)) == values(ranking.pagerank_iteration(g, mode="push_raw"))


def test_blocked_adjacency(spark):
    g = micro.star(spark, 200)
    adj = blocks.encode_blocks(g.edges, 16)
    assert adj.where("src = 0").count() == 13 and values(blocks.decode_blocks(adj)) == values(g.edges)
    assert blocks.decode_blocks(blocks.nbr_pack(adj, lambda x: x % 2 == 0)).where("src = 0").count() == 99
    assert values(blocks.nbr_intersect_count(adj, spark.createDataFrame([(1, 2), (0, 1)], "src bigint, dst bigint"))) == [(0, 1, 0), (1, 2, 1)]


def test_scan_and_index(spark):
    df = spark.range(100).select((F.col("id") * 37 % 101).alias("k"), F.col("id").alias("x"))
    total, want = 0, {}
    for k, x in sorted((r.k, r.x) for r in df.collect()):
        want[k], total = total, total + x
    assert {r.k: r["scan"] for r in scan(df, ["k"], "x").collect()} == want
    assert [r.pos for r in index(df, ["k"]).orderBy("k").collect()] == list(range(100))


def test_histogram_strategies_agree(spark):
    df = spark.range(1000).select(F.when(F.col("id") % 3 == 0, 0).otherwise(F.col("id") % 50).alias("k"))
    assert len({tuple(values(histogram(df, "k", strategy=s))) for s in STRATEGIES}) == 1


def test_simplification(spark):
    g = micro.graph(spark, [(0, 1), (1, 0), (0, 1), (2, 2)])
    assert values(g.edges) == [(0, 1), (1, 0)]


def test_partition_counts_do_not_matter(spark):
    g = micro.bow_tie(spark)
    assert values(connectivity.spanning_forest(g.layout(1))) == values(connectivity.spanning_forest(g.layout(13)))


def test_measures(spark):
    assert measures.half_length([(1, 1.0), (8, 5.0), (64, 9.0)]) == 8 and measures.speedup(6, 2) == 3
    run = measures.timed(lambda s: bfs.bfs(micro.path(spark, 4), 0, mode="blocked", stats=s))
    assert run["rounds"] == 5 and run["total_frontier"] == 4
    g = micro.star(spark, 5)
    assert values(measures.live_ratio(g, g.vertices, g.vertices.where("v = 0"))) == [(8, 4, 1, 4)]


@pytest.mark.parametrize("group,step,batch", [(1 << 21, 1 << 22, 4096), (3, 2, 2), (40, 7, 3)])
def test_triangles_meet_in_groups(spark, monkeypatch, group, step, batch):
    """Lists cut into many groups, a hub among them, repeated arcs and loops: against all triples; wedges are no rows of a join."""
    from sparkgraphs.core import closing

    for name, value in (("GROUP", group), ("STEP", step), ("BATCH", batch)):
        monkeypatch.setattr(closing, name, value)
    arcs = {(i, (i * i + 3 * j) % 40) for i in range(40) for j in range(4)} | {(0, i) for i in range(1, 40)} | {(-5, 10**15), (-5, 7), (7, 10**15)}
    near = {v: {b for a, b in arcs if a == v} | {a for a, b in arcs if b == v} for v in {x for e in arcs for x in e}}
    found = [(a, b, c) for a in near for b in near[a] for c in near[a] & near[b] if a < b < c]
    packed = closing.lists(spark.createDataFrame([e for a, b in arcs for e in ((a, b), (b, a), (a, b))], "src bigint, dst bigint"))
    assert found and (group > 100 or packed.select("grp").distinct().count() > 2)
    for method in substructure.METHODS:
        count = substructure.closed_count(packed, method=method)
        assert values(count) == [(len(found),)] and "Join" not in count._jdf.queryExecution().executedPlan().toString()
    want = sorted(((v, sum(v in t for t in found)) for v in near), key=repr)
    assert values(substructure.closed_at(packed, packed)) == want
