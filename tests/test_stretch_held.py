import micro
import numpy as np
import pytest
from micro import values

from sparkgraphs.check import certificates as cert


@pytest.mark.parametrize("marks", [1 << 23, 100, 1])
def test_stretch_in_memory_against_brute_force(monkeypatch, marks):
    """A ring of 40, whole, cut once, cut to pieces and without arcs; pairs of any two vertices, also of those without an arc."""
    monkeypatch.setattr(cert, "MARKS", marks)
    pairs = np.array([(a, b) for a in range(0, 40, 3) for b in range(40)])
    for gone in (set(), {4}, {4, 20, 21}, set(range(40))):
        near = {v: [(v + 1) % 40] * (v not in gone) + [(v - 1) % 40] * ((v - 1) % 40 not in gone) for v in range(40)}
        arcs = np.array(sorted((a, b) for a in near for b in near[a]), np.int64).reshape(-1, 2)
        held = cert.Held(arcs[:, 0], arcs[:, 1])
        for limit in (1, 19, 39):
            reach = {}
            for a in near:
                got = {a}
                for _ in range(limit):
                    got |= {y for x in got for y in near[x]}
                reach[a] = got
            found, starts = 0, [*range(0, len(pairs), 40), len(pairs)]
            for i in range(0, len(starts) - 1, held.width):
                part = pairs[starts[i] : starts[min(i + held.width, len(starts) - 1)]]
                found += held.far(part[:, 0], part[:, 1], limit)
            assert found == sum(b not in reach[a] for a, b in pairs.tolist())
            assert not held.seen.any()


def test_stretch_of_a_graph_that_fits_takes_no_job_a_level(spark, monkeypatch):
    g = micro.cycle(spark, 40)
    assert cert.stretch_held(g, g.half(), 1, fits=79) is None
    assert cert.stretch_held(g, g.half().limit(0), 1) == 0
    monkeypatch.setattr(cert, "stretch", None)
    assert values(cert.spanner(g, g.half().where("NOT (src = 4 AND dst = 5)"), 4)) == [(0, True, True)]
    assert values(cert.spanner(g, g.half().where("NOT (src = 4 AND dst = 5)"), 3)) == [(0, True, False)]
