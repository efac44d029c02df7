"""The stretch certificate looks at every dropped edge."""

import micro
from micro import values
from pyspark.sql import functions as F

from sparkgraphs.check import certificates as cert
from sparkgraphs.model.graph import from_arcs


def test_stretch_of_every_dropped_edge_is_checked(spark):
    """A ring of 300 without one edge off the 64 vertices that were once the sample."""
    g = micro.cycle(spark, 300)
    sample = {r.v for r in g.vertices.orderBy(F.xxhash64("v")).limit(64).collect()}
    gone = next(i for i in range(299) if not {i, i + 1} & sample)
    left = g.half().where(f"NOT (src = {gone} AND dst = {gone + 1})")
    assert values(cert.spanner(g, left, 2)) == [(0, True, False)]


def test_stretch_by_blocks_of_sources(spark):
    g = micro.cycle(spark, 12)
    h = from_arcs(g.half().where("NOT (src = 4 AND dst = 5)"), g.vertices)
    assert [cert.stretch(g, h, g.half(), limit, 72) for limit in (10, 11)] == [1, 0]
