import random

import numpy as np
import pyarrow as pa
import pytest
from micro import values
from pyspark.sql import functions as F

from sparkgraphs.core import closing
from sparkgraphs.model import catalog
from sparkgraphs.queries import QUERIES


def test_a_row_for_each_membership_is_shuffled_not_one_for_each_arc(spark, sf, monkeypatch):
    """Each arc of each order was a row that was shuffled and sorted."""
    members = catalog.cliques(spark, sf, "part_copurchase")[0].agg(F.sum(F.size("l"))).first()[0]
    arcs = catalog.both_ways(spark, sf, "part_copurchase")[1]
    sent, kind = [], type(spark.range(1))
    deal = kind.repartition
    monkeypatch.setattr(kind, "repartition", lambda self, n, *cols: (sent.append(self.count()) if n == "src" else None, deal(self, n, *cols))[1])
    assert values(QUERIES["triangles_undirected"](spark, sf)) == values(QUERIES["triangles"](spark, sf))
    assert sent == [members, members] and members < arcs / 2


@pytest.mark.parametrize("slices", [1, 3])
def test_lists_of_cliques_in_slices_and_pieces(monkeypatch, slices):
    monkeypatch.setattr(closing, "PIECE", 3)
    monkeypatch.setattr(closing, "STEP", 40)
    draw, want = random.Random(slices), {}
    cliques = [sorted(draw.sample(range(-20, 40), draw.choice([1, 2, 5, 17]))) for _ in range(60)]
    for c in cliques:
        for v in c:
            if len(c) > 1:
                want.setdefault(v, set()).update(set(c) - {v})
    batches, got = pa.table({"l": pa.array(cliques, pa.list_(pa.int64()))}).to_batches(max_chunksize=7), {}
    for i in range(slices):
        rows = pa.Table.from_batches(closing._others(slices, i, iter(batches))).sort_by("src").combine_chunks()
        assert max(map(len, rows.column("near").to_pylist())) <= 3 * 8
        for b in closing._pack_pieces(rows.to_batches(max_chunksize=5)):
            for v, n, near in zip(*(c.to_pylist() for c in b.columns), strict=True):
                assert v not in got and n == len(closing.unpack(near))
                got[v] = set(closing.unpack(near).tolist())
    assert got == want


def test_members_of_an_order_that_batches_cut():
    draw = random.Random(5)
    rows = sorted((draw.randrange(12), draw.randrange(8)) for _ in range(90))
    o, src = np.array(rows, np.int64).T
    batches = pa.table({"o": o, "src": src}).to_batches(max_chunksize=4)
    got = [x for b in catalog._sets(iter(batches)) for x in b.column(0).to_pylist()]
    assert got == [sorted({s for k, s in rows if k == q}) for q in sorted({k for k, _ in rows})]
