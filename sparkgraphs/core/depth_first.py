"""Depth-first search of whole components in a task, on arrays: an arc is one index, and what is larger than LARGE lies in a mapped file without a name.

Neighbours come as pieces of lists, sorted by component and vertex. Small components are searched together. The search itself only numbers the
vertices and notes their parents; the rest goes by columns over a part of the arcs at a time.
"""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bytes of an array that a task has in memory; larger ones are mapped files.
LARGE = 1 << 24
#: Arcs of small components that are searched together.
TOGETHER = 1 << 20
#: Arcs at a time where work goes by columns.
PART = 1 << 16
#: Arcs of a piece of a list at most.
PIECE = 1 << 10

BLOCKS = "src bigint, dst bigint, label_src bigint, label_dst bigint"
PIECES = "src bigint, low bigint, near binary"


def _folder() -> str | None:
    """Spark's own local folder in an executor."""
    first = os.environ.get("SPARK_LOCAL_DIRS", "").split(",")[0]
    return first if os.path.isdir(first) else None


def room(n: int, kind: type) -> np.ndarray:
    if n * np.dtype(kind).itemsize <= LARGE:
        return np.empty(n, kind)
    with tempfile.TemporaryFile(dir=_folder()) as f:
        return np.memmap(f, kind, "w+", shape=(n,))


def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(src, low, near) of rows (src, dst) that come sorted: neighbours as int64, the first also in `low`. A list may come in several pieces."""
    for b in batches:
        if not b.num_rows:
            continue
        src, dst = b.column(0).to_numpy(), np.ascontiguousarray(b.column(1).to_numpy(), "<i8")
        at, new = np.arange(len(src)), np.ones(len(src), bool)
        new[1:] = src[1:] != src[:-1]
        new |= (at - np.maximum.accumulate(np.where(new, at, 0))) % PIECE == 0
        starts = np.flatnonzero(new)
        ends = (8 * np.append(starts, len(src))).astype(np.int32)
        near = pa.Array.from_buffers(pa.binary(), len(starts), [None, pa.py_buffer(ends), pa.py_buffer(dst)])
        yield pa.record_batch([pa.array(src[starts]), pa.array(dst[starts]), near], ["src", "low", "near"])


def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(src, dst, label_src, label_dst), src < dst, of whole components given as (label, src, near), sorted by label, src and the first of `near`."""
    held, last = Held(), None
    for b in batches:
        if not b.num_rows:
            continue
        label, src, near = b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2)
        wide = 8 if pa.types.is_large_binary(near.type) else 4
        cut = np.frombuffer(near.buffers()[1], f"<i{wide}", len(near) + 1, wide * near.offset) // 8
        to = np.frombuffer(near.buffers()[2], "<i8", int(cut[-1]))
        new = np.ones(len(label), bool)
        new[0], new[1:] = label[0] != last, label[1:] != label[:-1]
        begin, last = 0, label[-1]
        for c in np.flatnonzero(new).tolist():
            if held.arcs + int(cut[c] - cut[begin]) >= TOGETHER:
                held.add(src[begin:c], np.diff(cut[begin : c + 1]), to[cut[begin] : cut[c]])
                yield from held.blocks()
                held, begin = Held(), c
        held.add(src[begin:], np.diff(cut[begin:]), to[cut[begin] :])
    yield from held.blocks()


class Held:
    """The arcs of whole components, by source: those of a component ascending."""

    def __init__(self) -> None:
        self.arcs, self.src, self.size = 0, [], []
        self.raw = tempfile.SpooledTemporaryFile(LARGE, dir=_folder())

    def add(self, src: np.ndarray, size: np.ndarray, to: np.ndarray) -> None:
        self.src.append(src.copy())
        self.size.append(size.astype(np.int32))
        self.raw.write(to.tobytes())
        self.arcs += len(to)

    def blocks(self) -> Iterator[pa.RecordBatch]:
        if not self.arcs:
            return
        self._index()
        head, number = self._heads(), self.number
        # of each block the first arc, which is its smallest edge
        first_src, first_dst = self.up, self.spare
        for a, b in reversed(list(self._parts())):
            s, d = self._half(a, b)
            block = head[np.maximum(number[s], number[d])][::-1]
            first_src[block], first_dst[block] = s[::-1], d[::-1]
        for a, b in self._parts():
            s, d = self._half(a, b)
            block = head[np.maximum(number[s], number[d])]
            if len(s):
                yield pa.record_batch([pa.array(np.asarray(self.ids[x])) for x in (s, d, first_src[block], first_dst[block])], ["src", "dst", "label_src", "label_dst"])

    def _index(self) -> None:
        """The vertices' ids, where each one's arcs end, and the arcs as indices."""
        src, size, self.src, self.size = np.concatenate(self.src), np.concatenate(self.size), [], []
        starts = np.flatnonzero(np.append(True, src[1:] != src[:-1]))
        self.ids = src[starts]
        n = self.n = len(self.ids)
        self.kind = np.int32 if n < 1 << 31 else np.int64
        self.end = room(n, np.int64)
        np.cumsum(np.add.reduceat(size, starts, dtype=np.int64), out=self.end)
        by_id = None if (self.ids[1:] > self.ids[:-1]).all() else np.argsort(self.ids)
        self.to = room(self.arcs, self.kind)
        self.raw.seek(0)
        for a, b in self._parts():
            found = np.searchsorted(self.ids, np.frombuffer(self.raw.read(8 * (b - a)), "<i8"), sorter=by_id)
            self.to[a:b] = found if by_id is None else by_id[found]
        self.raw.close()

    def _heads(self) -> np.ndarray:
        """Of each vertex, by its number, the number at which the block of the edge to its parent begins."""
        n, kind = self.n, self.kind
        self.number, self.up, self.spare = room(n, kind), room(n, kind), room(n, kind)
        self._search()
        above, low, number = self.spare, room(n, kind), self.number
        for a in range(0, n, PART):
            here = slice(a, min(n, a + PART))
            low[here] = np.arange(here.start, here.stop)
            up = self.up[here]
            above[number[here]] = np.where(up < 0, -1, number[up])
        for a, b in self._parts():
            v, starts = self._owners(a, b)
            mine = number[v]
            low[mine] = np.minimum(low[mine], np.minimum.reduceat(number[self.to[a:b]], starts))
        # the arc to the parent counts as well: it takes nothing from low[k] >= p
        lows, ups = memoryview(low), memoryview(above)
        for k in range(n - 1, 0, -1):
            p = ups[k]
            if p >= 0 and lows[k] < lows[p]:
                lows[p] = lows[k]
        for k in range(n):
            p = ups[k]
            lows[k] = k if p < 0 or lows[k] >= p else lows[p]
        return low

    def _search(self) -> None:
        """Numbers in the order of a depth-first search from each component's smallest vertex, and the parents (-1 for roots)."""
        self.number[:] = -1
        next_arc = room(self.n, np.int64)
        next_arc[0], next_arc[1:] = 0, self.end[:-1]
        number, up, at, end, to = (memoryview(x) for x in (self.number, self.up, next_arc, self.end, self.to))
        count = 0
        for root in range(self.n):
            if number[root] >= 0:
                continue
            number[root], up[root], v = count, -1, root
            count += 1
            while v >= 0:
                i, last = at[v], end[v]
                while i < last:
                    u = to[i]
                    i += 1
                    if number[u] < 0:
                        at[v] = i
                        number[u], up[u], v = count, v, u
                        count += 1
                        break
                else:
                    at[v] = last
                    v = up[v]

    def _parts(self) -> Iterator[tuple[int, int]]:
        for a in range(0, self.arcs, PART):
            yield a, min(self.arcs, a + PART)

    def _owners(self, a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        """The vertices that the arcs a to b leave, and where those of each begin among them."""
        low, high = np.searchsorted(self.end, [a, b - 1], "right")
        return np.arange(low, high + 1), np.append(a, self.end[low:high]) - a

    def _half(self, a: int, b: int) -> tuple[np.ndarray, np.ndarray]:
        """Both ends of those of the arcs a to b that lead to a larger vertex."""
        v, starts = self._owners(a, b)
        s, d = np.repeat(v, np.diff(np.append(starts, b - a))), np.asarray(self.to[a:b])
        up = s < d
        return s[up], d[up]
