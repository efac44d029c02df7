"""Workload helpers on hand-made graphs."""

from micro import bow_tie, clique, graph

from sparkgraphs.workload import experiments as x


def test_problems_are_those_of_the_direction(spark):
    assert set(x.problems_of(graph(spark, [(0, 1)], directed=True))) == set(x.DIRECTED)
    assert set(x.problems_of(clique(spark, 3))) == set(x.PROBLEMS) - set(x.DIRECTED) and len(x.PROBLEMS) == 20


def test_blocks_give_the_answers_of_the_edge_list(spark):
    g = bow_tie(spark).with_weights().layout()
    problems = {p: x.PROBLEMS[p] for p in ("bfs", "bellman_ford", "kcore", "triangles", "pagerank_iteration")}
    rows = x.from_blocks(g, problems)
    assert [r["problem"] for r in rows] == list(problems) and all(r["same"] for r in rows)


def test_a_wrong_answer_is_noticed(spark):
    g = bow_tie(spark).with_weights().layout()
    by_name = {"name": lambda h, s: h.vertices.selectExpr("v", f"'{h.name}' AS name")}
    assert not x.from_blocks(g, by_name)[0]["same"]


def test_speedups_are_of_the_same_problem_and_graph():
    row = lambda g, p, s: {"graph": g, "problem": p, "seconds": s}
    found = x.ratios([row("a", "bfs", 8.0), row("b", "bfs", 3.0)], [row("b", "bfs", 1.5), row("a", "bfs", 2.0), row("a", "mis", 1.0)], 4)
    assert [(r["graph"], r["speedup"]) for r in found] == [("a", 4.0), ("b", 2.0)]
