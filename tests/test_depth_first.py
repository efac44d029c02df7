import random
import tracemalloc

import pandas as pd
import pyarrow as pa
import pytest

from sparkgraphs.algo import biconnectivity
from sparkgraphs.core import depth_first


def both(edges):
    return pd.DataFrame(sorted({x for a, b in edges for x in ((a, b), (b, a))}), columns=["src", "dst"])


def test_depth_first_blocks_take_arrays_not_objects():
    """Lists, dictionaries and tuples of a component took about 700 bytes an edge, and so more than a task has at 1 GB."""
    n = 30_000
    rows = both([e for i in range(n) for e in ((i, (i + 1) % n), (i, (i * 7 + 3) % n)) if e[0] != e[1]])
    tracemalloc.start()
    got = biconnectivity.dfs_blocks(rows)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(got) == len(rows) // 2 and most < 250 * len(got)


def by_hand(edges):
    """Edges that meet in x are of one block if their other ends are connected without x."""
    near = {}
    for a, b in edges:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    top = {e: e for e in edges}

    def find(e):
        while top[e] != e:
            e = top[e]
        return e

    for x in near:
        seen = {x}
        for a in sorted(near[x]):
            todo = [a] if a not in seen else []
            seen.update(todo)
            reached = set(todo)
            while todo:
                for u in near[todo.pop()] - seen:
                    seen.add(u)
                    reached.add(u)
                    todo.append(u)
            mine = sorted((min(x, u), max(x, u)) for u in near[x] & reached)
            for e in mine[1:]:
                p, q = sorted((find(mine[0]), find(e)))
                top[q] = p
    return sorted((*e, *find(e)) for e in edges)


def labelled(edges):
    near = {}
    for a, b in edges:
        near.setdefault(a, []).append(b)
        near.setdefault(b, []).append(a)
    label = {}
    for r in sorted(near):
        todo = [r] if r not in label else []
        label.update({x: r for x in todo})
        while todo:
            for u in near[todo.pop()]:
                if u not in label:
                    label[u] = r
                    todo.append(u)
    return label


@pytest.mark.parametrize("small", [False, True])
@pytest.mark.parametrize("seed", range(4))
def test_components_in_batches_and_pieces_and_mapped_files(monkeypatch, small, seed):
    if small:
        for name, value in (("LARGE", 64), ("TOGETHER", 20), ("PART", 7), ("PIECE", 3)):
            monkeypatch.setattr(depth_first, name, value)
    draw = random.Random(seed)
    ids = draw.sample(range(-(10**12), 10**12), 120)
    edges = sorted({tuple(sorted(draw.sample(ids[k : k + draw.choice([4, 30])], 2))) for k in [draw.randrange(90) for _ in range(110)]})
    hub = ids[0]
    edges = sorted({*edges, *(tuple(sorted((hub, x))) for x in ids[1:25])})
    rows, label = both(edges), labelled(edges)
    arcs = pa.RecordBatch.from_pandas(rows, preserve_index=False)
    cut = [arcs.slice(i, 9) for i in range(0, arcs.num_rows, 9)]
    lists = pa.Table.from_batches(depth_first.pieces(cut)).to_pandas()
    lists["label"] = lists.src.map(label)
    lists = pa.Table.from_pandas(lists.sort_values(["label", "src", "low"])[["label", "src", "near"]], preserve_index=False)
    got = pa.Table.from_batches(depth_first.blocks(lists.to_batches(5)), pa.schema([(c, pa.int64()) for c in ("src", "dst", "label_src", "label_dst")]))
    assert len(set(label.values())) > 1
    assert sorted(map(tuple, got.to_pandas().itertuples(index=False))) == by_hand(edges)
