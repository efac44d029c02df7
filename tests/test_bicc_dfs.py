import time

import pandas as pd

from sparkgraphs.algo import biconnectivity


def test_depth_first_blocks_of_a_long_path():
    """Each block was looked for from the start of all edges held: 40000 edges took minutes."""
    n, began = 40_000, time.time()
    got = biconnectivity.dfs_blocks(pd.DataFrame([e for i in range(n) for e in ((i, i + 1), (i + 1, i))], columns=["src", "dst"]))
    assert len(got) == n and (got.src == got.label_src).all() and time.time() - began < 20


def test_depth_first_blocks_of_a_long_cycle():
    """A block's label was looked for again for each of its edges."""
    n, began = 40_000, time.time()
    got = biconnectivity.dfs_blocks(pd.DataFrame([e for i in range(n) for e in ((i, (i + 1) % n), ((i + 1) % n, i))], columns=["src", "dst"]))
    assert len(got) == n and set(zip(got.label_src, got.label_dst, strict=True)) == {(0, 1)} and time.time() - began < 20
