from glob import glob

import pytest
from micro import values
from pyspark.sql import functions as F

from sparkgraphs.core import closing
from sparkgraphs.core.rounds import Rounds, shared_dir
from sparkgraphs.model import catalog
from sparkgraphs.queries import QUERIES


@pytest.mark.parametrize("query", ["triangles_undirected", "triangles_per_vertex"])
def test_arcs_are_shuffled_a_slice_at_a_time_and_lists_written_once(spark, sf, monkeypatch, query):
    """All arcs lay in one shuffle, beside two copies of the lists."""
    want = values(QUERIES[query](spark, sf))
    arcs, n = catalog.both_ways(spark, sf, "part_copurchase")
    assert n == arcs.count() > 15_000
    written, append = [], Rounds.append
    monkeypatch.setattr(closing, "SLICE", 5000)
    monkeypatch.setattr(Rounds, "append", lambda self, df, name: written.append(df.agg(F.sum("n")).first()[0] or 0) or append(self, df, name))
    assert values(QUERIES[query](spark, sf)) == want
    assert len(written) == -(-n // 5000) and max(written) < n / 2 and sum(written) == arcs.distinct().count()


def test_what_arcs_are_made_of_is_gone_when_the_lists_are_written(spark, sf):
    """Baskets lay beside the lists and their copies to the end."""
    left = lambda: set(glob(f"{shared_dir(spark).removeprefix('file:')}/baskets-*"))
    before = left()
    assert values(QUERIES["triangles_per_vertex"](spark, sf))
    assert left() == before
