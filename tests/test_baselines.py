"""Sequential comparison points: the greedy spanner and ball growing, next to the methods that replace them."""

import math
from collections import deque

import micro
from micro import values

from sparkgraphs.algo import ball
from sparkgraphs.check import certificates as cert


def neighbours(edges):
    out = {}
    for a, b in edges:
        out.setdefault(a, set()).add(b)
        out.setdefault(b, set()).add(a)
    return out


def reach(adj, start, most):
    dist, queue = {start: 0}, deque([start])
    while queue:
        v = queue.popleft()
        if dist[v] < most:
            for w in adj.get(v, ()):
                if w not in dist:
                    dist[w] = dist[v] + 1
                    queue.append(w)
    return dist


def greedy_spanner(edges, k):
    """An edge is kept if its ends are farther apart than 2k - 1 without it."""
    kept = []
    for a, b in sorted(edges):
        if b not in reach(neighbours(kept), a, 2 * k - 1):
            kept.append((a, b))
    return kept


def grown_balls(edges, beta):
    """Balls one after another: each grows until its boundary is at most beta of its inner edges."""
    adj, owner = neighbours(edges), {}
    for start in sorted(adj):
        if start in owner:
            continue
        radius = 0
        while True:
            open_ = {v: {w for w in ws if w not in owner} for v, ws in adj.items() if v not in owner}
            dist = reach(open_, start, radius)
            inner = sum(w in dist for v in dist for w in open_[v]) // 2
            edge = sum(w not in dist for v in dist for w in open_[v])
            if edge <= beta * max(1, inner):
                break
            radius += 1
        owner |= dict.fromkeys(dist, start)
    return owner


def lattice(side):
    return [(x * side + y, a * side + b) for x in range(side) for y in range(side) for a, b in ((x + 1, y), (x, y + 1)) if a < side and b < side]


def test_spanner_next_to_the_greedy_one(spark):
    edges = lattice(7)
    g = micro.graph(spark, edges)
    greedy = greedy_spanner(edges, 2)
    assert values(cert.spanner(g, spark.createDataFrame(greedy, "src bigint, dst bigint"), 2)) == [(0, True, True)]
    found = values(ball.spanner(g, 2))
    n = 49
    assert n - 1 <= len(found) <= len(edges) and len(greedy) <= 2 * n ** (1 + 1 / 2)


def test_balls_next_to_sequential_growing(spark):
    edges = lattice(8)
    owner = grown_balls(edges, 0.5)
    cut = sum(owner[a] != owner[b] for a, b in edges)
    assert cut <= 0.5 * len(edges) + 1
    balls = ball.ball_decompose(micro.graph(spark, edges), 0.2)
    center = {r.v: r.center for r in balls.collect()}
    assert sum(center[a] != center[b] for a, b in edges) <= 4 * 0.2 * len(edges)
    start = {r.v: r.arrival for r in balls.collect() if r.v == r.center}
    assert max(r.arrival - start[r.center] for r in balls.collect()) <= 12 * math.log(64) / 0.2
