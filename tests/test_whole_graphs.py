"""The queries on whole-table graphs against brute force on the smallest tables."""

import hashlib
import math
from collections import defaultdict

import pytest
from micro import values

from sparkgraphs.model import catalog
from sparkgraphs.queries import QUERIES, WHOLE

SLICES = ("cust_part_urgent", "event_hot_succession", "order_part_h1")


def prio(text):
    return int(hashlib.md5(f"42:{text}".encode()).hexdigest()[:12], 16)


def near_of(arcs):
    near = defaultdict(set)
    for a, b in arcs:
        near[a].add(b)
    return near


@pytest.fixture(scope="module")
def arcs_of(spark, sf):
    held = {}
    return lambda name: held.setdefault(name, sorted((r.src, r.dst) for r in catalog.load(spark, sf, name).edges.collect()))


def cores(arcs):
    near, core, k = near_of(arcs), {}, 0
    while near:
        v = min(near, key=lambda x: len(near[x]))
        k = max(k, len(near[v]))
        core[v] = k
        for u in near.pop(v):
            near[u].discard(v)
    return sorted(core.items(), key=repr)


def colours(arcs):
    near, got = near_of(arcs), {}
    for v in sorted(near, key=lambda x: (-math.ceil(math.log2(max(1, len(near[x])))), prio(x), x)):
        taken = {got.get(u) for u in near[v]}
        got[v] = next(c for c in range(len(taken) + 1) if c not in taken)
    return sorted(got.items(), key=repr)


def matching(arcs):
    used, got = set(), []
    for _, a, b in sorted((prio(f"{a}-{b}"), a, b) for a, b in arcs if a < b):
        if a not in used and b not in used:
            used |= {a, b}
            got.append((a, b))
    return sorted(got, key=repr)


def forest(arcs):
    up, got = {}, []

    def root(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    spread = max(1, math.ceil(math.log(len({a for a, _ in arcs}))) - 1)
    for w, a, b in sorted((1 + prio(f"{a}-{b}") % spread, a, b) for a, b in arcs if a < b):
        if root(a) != root(b):
            up[root(a)] = root(b)
            got.append((a, b, w))
    return sorted(got, key=repr)


def strong(arcs):
    def reach(near, v):
        seen, left = {v}, [v]
        while left:
            for u in near[left.pop()] - seen:
                seen.add(u)
                left.append(u)
        return seen

    out, into = near_of(arcs), near_of([(b, a) for a, b in arcs])
    return sorted(((v, min(reach(out, v) & reach(into, v))) for v in {x for e in arcs for x in e}), key=repr)


BRUTE = {"kcore": cores, "color_llf": colours, "matching": matching, "msf": forest, "scc": strong}


@pytest.mark.parametrize("name", [n for n in WHOLE if n.startswith(tuple(BRUTE))])
def test_whole_graph_queries_against_brute_force(spark, sf, arcs_of, name):
    solve = next(f for k, f in BRUTE.items() if name.startswith(k))
    assert values(QUERIES[f"{name}_whole"](spark, sf)) == solve(arcs_of(WHOLE[name][0]))


def test_whole_balls(spark, sf, arcs_of):
    assert values(QUERIES["ball_decompose_quality_whole"](spark, sf)) == [(True, True, True)]
    dq = {v: math.floor(-math.log((prio(v) + 1) / float(1 << 48)) / 0.2 * 1e6) for v in {a for a, _ in arcs_of("cust_part")}}
    near, center, r, wait = near_of(arcs_of("cust_part")), {}, 0, {v: (max(dq.values()) - q) // 1_000_000 for v, q in dq.items()}
    while len(center) < len(dq):
        claims = {v: min([center[u] for u in near[v] if u in center] + [v] * (wait[v] == r), default=None) for v in dq if v not in center}
        center.update({v: c for v, c in claims.items() if c is not None})
        r += 1
    assert values(QUERIES["ball_decompose_centers_whole"](spark, sf)) == sorted(center.items(), key=repr)


def test_whole_blocks(spark, sf, arcs_of):
    labels = values(QUERIES["bicc_edge_labels_whole"](spark, sf))
    assert labels == values(QUERIES["bicc_dfs_whole"](spark, sf)) and len(labels) == len(arcs_of("order_part")) // 2
    blocks = defaultdict(set)
    for a, b, *label in labels:
        blocks[a].add(tuple(label))
        blocks[b].add(tuple(label))
    want = sorted(((v,) for v, held in blocks.items() if len(held) > 1), key=repr)
    assert want and values(QUERIES["articulation_points_whole"](spark, sf)) == want


def test_whole_queries_are_on_no_slice():
    assert len(WHOLE) == 17 and not [g for g, *_ in WHOLE.values() if g.startswith(SLICES)]
