"""Closed wedges in groups of bounded size: neighbour lists meet in a task without a row for each wedge.

Every vertex has one packed list of its neighbours. Vertices are cut by id into groups of about GROUP arcs; a task holds the lists of a group
and lets those of all neighbours of the group stream by, each once. So a list is shuffled once for each group that it has
neighbours in (few where ids have locality, at most all groups), and wedges are never rows.

On disk there is at a time one slice of the arcs, or the packed lists and their copies for the groups: shuffles are let go as soon as
what they gave is written.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .prims import scan
from .rounds import Rounds, release

#: Arcs of the lists that a task holds; a vertex with more is a group of its own.
GROUP = 1 << 21
#: Arcs that are shuffled at a time to be packed.
SLICE = 1 << 24
#: Rows of a batch handed to Spark.
BATCH = 4096
#: Elements that one step of a comparison gathers at most, but for a single list.
STEP = 1 << 22
#: Ids of a row that is sent to be packed.
PIECE = 1 << 10

PACKED = "v bigint, n bigint, near binary"


def pack(ids: np.ndarray) -> bytes:
    """Ascending ids as their first and the differences, in as few bytes as the largest takes."""
    if not len(ids):
        return b""
    gaps = np.diff(ids)
    widest = int(gaps.max()) if len(gaps) else 0
    width = 1 if widest < 1 << 8 else 2 if widest < 1 << 16 else 4 if widest < 1 << 32 else 8
    return bytes([width]) + ids[:1].tobytes() + gaps.astype(f"<u{width}").tobytes()


def unpack(data: bytes) -> np.ndarray:
    if not data:
        return np.empty(0, np.int64)
    out = np.empty(1 + (len(data) - 9) // data[0], np.int64)
    out[0] = np.frombuffer(data, "<i8", 1, 1)[0]
    out[1:] = np.frombuffer(data, f"<u{data[0]}", offset=9)
    return np.cumsum(out, out=out)


def _pack_sorted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(v, n, near) of rows (src, dst) that come sorted, repeated ones among them."""

    def rows(both: np.ndarray) -> pa.RecordBatch:
        src, dst = both
        new = np.ones(len(src), bool)
        new[1:] = (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])
        src, dst = src[new], dst[new]
        ends = np.append(np.flatnonzero(src[1:] != src[:-1]) + 1, len(src))
        starts = np.concatenate([[0], ends[:-1]])
        near = [pack(dst[a:b]) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
        return pa.record_batch([pa.array(src[starts]), pa.array(ends - starts), pa.array(near, pa.binary())], ["v", "n", "near"])

    held: list[np.ndarray] = [np.empty((2, 0), np.int64)]
    for b in batches:
        if not b.num_rows:
            continue
        both = np.stack([b.column(0).to_numpy(), b.column(1).to_numpy()])
        cut = int(np.searchsorted(both[0], both[0, -1]))
        if cut or (held[-1].size and held[-1][0, -1] != both[0, 0]):  # a list is complete
            done = np.concatenate([*held, both[:, :cut]], 1)
            if done.size:
                yield rows(done)
            held = []
        held.append(both[:, cut:])
    done = np.concatenate(held, 1)
    if done.size:
        yield rows(done)


def _flat(rows: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The int64 values of lists, or of binary rows, one after another, and where each list ends, after a 0."""
    if pa.types.is_list(rows.type) or pa.types.is_large_list(rows.type):
        ends = rows.offsets.to_numpy().astype(np.int64)
        return rows.values.to_numpy()[ends[0] : ends[-1]], ends - ends[0]
    wide = 8 if pa.types.is_large_binary(rows.type) else 4
    ends = np.frombuffer(rows.buffers()[1], f"<i{wide}", len(rows) + 1, wide * rows.offset).astype(np.int64) // 8
    return np.frombuffer(rows.buffers()[2], "<i8", int(ends[-1]))[ends[0] :], ends - ends[0]


def _others(slices: int, i: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(src, near) of cliques, lists of distinct ids: a row for each member of slice i, with the other members as int64, in pieces of PIECE at most."""
    for b in batches:
        ids, ends = _flat(b.column(0))
        size = np.diff(ends)
        first, many = np.repeat(ends[:-1], size), np.repeat(size, size)
        mine = np.flatnonzero(((ids.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)) % np.uint64(slices) == i)
        for part in _slices(mine, many[mine]):
            n = many[part]
            stop = np.cumsum(n)
            place = np.repeat(first[part] - (stop - n), n)
            place += np.arange(len(place))
            other = place != np.repeat(part, n)
            near = np.ascontiguousarray(ids[place[other]], "<i8")
            n = n - 1
            cuts = -(-n // PIECE)
            k = np.arange(int(cuts.sum())) - np.repeat(np.cumsum(cuts) - cuts, cuts)
            to = np.append(0, np.cumsum(np.minimum(PIECE, np.repeat(n, cuts) - k * PIECE)))
            rows = pa.Array.from_buffers(pa.binary(), len(k), [None, pa.py_buffer((8 * to).astype(np.int32)), pa.py_buffer(near)])
            yield pa.record_batch([pa.array(np.repeat(ids[part], cuts)), rows], ["src", "near"])


def _pack_pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(v, n, near) of rows (src, near) that come sorted by src, with ids in any order and repeated ones among them."""

    def arcs() -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        for b in batches:
            if not b.num_rows:
                continue
            src, (dst, ends) = b.column(0).to_numpy(), _flat(b.column(1))
            both = np.stack([np.repeat(src, np.diff(ends)), dst])
            cut = int(np.searchsorted(both[0], both[0, -1]))
            if cut or (held and held[-1][0, -1] != both[0, 0]):
                yield ordered([*held, both[:, :cut]])
                held = []
            held.append(both[:, cut:])
        if held:
            yield ordered(held)

    def ordered(parts: list[np.ndarray]) -> pa.RecordBatch:
        src, dst = np.concatenate(parts, 1)
        order = np.lexsort((dst, src))
        return pa.record_batch([pa.array(src[order]), pa.array(dst[order])], ["src", "dst"])

    yield from _pack_sorted(arcs())


def lists_of_cliques(cliques: DataFrame, arcs: int = 0) -> DataFrame:
    """`lists` of the graph whose edges join the members of each clique (l: array of distinct bigints); `arcs` both ways, repeated ones counted.

    A member is sent with all others at once: a row for each membership, not for each arc.
    """
    slices = max(1, -(-arcs // SLICE))

    def slice_of(i: int) -> DataFrame:
        pieces = cliques.select("l").mapInArrow(partial(_others, slices, i), "src bigint, near binary")
        return pieces.repartition("src").sortWithinPartitions("src").mapInArrow(_pack_pieces, PACKED)

    return _written(cliques.sparkSession, slices, slice_of)


def lists(arcs: DataFrame, rows: int = 0) -> DataFrame:
    """(v, n, near, grp): the packed neighbours of each vertex, written. `arcs` (src, dst) may repeat rows and hold loops; each edge comes both ways.

    If they are many (`rows` of them), arcs are made anew for each slice of the vertices, so that only a slice is shuffled at a time.
    """
    slices = max(1, -(-rows // SLICE))

    def slice_of(i: int) -> DataFrame:
        mine = arcs.where("src <> dst").select("src", "dst").where(F.pmod(F.xxhash64("src"), F.lit(slices)) == i)
        return mine.repartition("src").sortWithinPartitions("src", "dst").mapInArrow(_pack_sorted, PACKED)

    return _written(arcs.sparkSession, slices, slice_of)


def _written(spark: SparkSession, slices: int, slice_of: Callable[[int], DataFrame]) -> DataFrame:
    rounds = Rounds(spark, "lists")
    for i in range(slices):
        packed = rounds.append(slice_of(i), "packed")
        release(spark)
    # one row for each group
    cuts = np.array([r.low for r in groups(packed).groupBy("grp").agg(F.min("v").alias("low")).orderBy("low").collect()], np.int64)

    def label(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.append_column("grp", pa.array(np.searchsorted(cuts, b.column(0).to_numpy(), "right") - 1))

    return packed.mapInArrow(label, f"{PACKED}, grp bigint")


def groups(packed: DataFrame) -> DataFrame:
    """(v, grp): vertices in the order of their ids, cut at every GROUP arcs."""
    return scan(packed.select("v", "n"), ["v"], "n", "sum", "before").select("v", F.expr(f"before div {GROUP}").alias("grp"))


def closed(table: DataFrame, *, whole: bool = False, at: bool = False) -> DataFrame:
    """(v, triangles) partial counts of what `lists` gave, to be summed by v; v is null unless `at`.

    Each triangle is found once, from its smallest id, and counted for all three vertices if `at`; with `whole` lists are compared as they
    are, and each triangle is found six times.
    """
    spark = table.sparkSession
    # one row for each group
    cuts = np.array([r.low for r in table.groupBy("grp").agg(F.min("v").alias("low")).orderBy("low").collect()], np.int64)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Own lists (kind 0) go to the vertex's group, and as guests (kind 1) to the other groups of the neighbours that ask for them."""
        for b in batches:
            for part in (b.slice(i, BATCH) for i in range(0, b.num_rows, BATCH)):
                out: tuple[list, ...] = ([], [], [], [])
                for v, data in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    near = unpack(data)
                    split = int(np.searchsorted(near, v))
                    data, asked = (data, near) if whole else (pack(near[split:]), near[:split])
                    own = int(np.searchsorted(cuts, v, "right")) - 1
                    if not data:
                        continue
                    guests = np.unique(np.searchsorted(cuts, asked, "right") - 1).tolist()
                    for g, kind in [(own, 0), *((g, 1) for g in guests if g != own)]:
                        for column, x in zip(out, (g, kind, v, data), strict=True):
                            column.append(x)
                yield pa.record_batch([pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int32(), pa.int64(), pa.binary()), strict=True)], ["g", "kind", "v", "near"])

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, own, held = None, [], None
        for b in batches:
            for g, kind, v, data in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                if g != group:
                    if group is not None:
                        yield (held or Held(own, at)).rows()
                    group, own, held = g, [], None
                if kind == 0:
                    own.append((v, unpack(data)))
                    continue
                held = held or Held(own, at)
                held.guest(v, unpack(data))
        if group is not None:
            yield (held or Held(own, at)).rows()

    n = max(len(cuts), int(spark.conf.get("spark.sql.shuffle.partitions")))
    dealt = table.select("v", "near").mapInArrow(deal, "g bigint, kind int, v bigint, near binary")
    return dealt.repartition(n, "g").sortWithinPartitions("g", "kind", "v").mapInArrow(meet, "v bigint, triangles bigint")


class Held:
    """The lists of a group, as indices of the ids in them."""

    def __init__(self, own: list[tuple[int, np.ndarray]], at: bool):
        self.at, self.total = at, 0
        self.v = np.array([v for v, _ in own], np.int64)
        self.size = np.array([len(x) for _, x in own], np.int64)
        self.start = np.cumsum(self.size) - self.size
        flat = np.concatenate([x for _, x in own]) if own else np.empty(0, np.int64)
        self.ids = np.unique(flat)
        self.to = np.searchsorted(self.ids, flat).astype(np.int32)
        self.each = np.split(self.to, self.start[1:]) if own else []
        holder = np.repeat(np.arange(len(own), dtype=np.int32), self.size)
        order = np.argsort(self.to, kind="stable")
        self.holder = holder[order]
        self.first = np.searchsorted(self.to[order], np.arange(len(self.ids) + 1))
        # ascending, since lists and what they hold are
        self.key = holder.astype(np.int64) * max(1, len(self.ids)) + self.to
        self.mark = np.zeros(len(self.ids), np.bool_)
        self.of_own, self.of_id = np.zeros(len(own), np.int64), np.zeros(len(self.ids), np.int64)
        self.of_guest: list[tuple[int, int]] = []
        for v, near in own:
            self.guest(v, near)

    def guest(self, v: int, near: np.ndarray) -> None:
        """Counts, for each list of the group that holds v, what it has in common with the list of v: the shorter of the two is looked up in the other."""
        j = int(np.searchsorted(self.ids, v))
        if j == len(self.ids) or self.ids[j] != v:
            return
        k = np.searchsorted(self.ids, near)
        k[k == len(self.ids)] = 0
        k = k[self.ids[k] == near]
        if not len(k):
            return
        askers = self.holder[self.first[j] : self.first[j + 1]]
        long = self.size[askers] > 16 * len(k)
        found = self._marked(askers[~long], k) + self._looked_up(askers[long], k)
        self.total += found
        if self.at and found:
            self.of_guest.append((v, found))

    def _marked(self, askers: np.ndarray, k: np.ndarray) -> int:
        self.mark[k], found = True, 0
        for part in _slices(askers, self.size[askers]):
            # whole lists are copied: faster than an index for each element
            to = np.concatenate([self.each[j] for j in part.tolist()])
            hit = self.mark.take(to)
            found += int(np.count_nonzero(hit))
            if self.at:
                size = self.size[part]
                ends = np.cumsum(size)
                self.of_own[part] += np.add.reduceat(hit, ends - size, dtype=np.int64)
                np.add.at(self.of_id, to[hit], 1)
        self.mark[k] = False
        return found

    def _looked_up(self, askers: np.ndarray, k: np.ndarray) -> int:
        found = 0
        for part in _slices(askers, np.full(len(askers), len(k))):
            want = (part.astype(np.int64)[:, None] * len(self.ids) + k[None, :]).ravel()
            place = np.searchsorted(self.key, want)
            place[place == len(self.key)] = 0
            hit = (self.key[place] == want).reshape(len(part), len(k))
            found += int(np.count_nonzero(hit))
            if self.at:
                self.of_own[part] += hit.sum(1)
                self.of_id[k] += hit.sum(0)
        return found

    def rows(self) -> pa.RecordBatch:
        if self.at:
            g = np.array(self.of_guest, np.int64).reshape(-1, 2)
            v, n = np.concatenate([self.v, self.ids, g[:, 0]]), np.concatenate([self.of_own, self.of_id, g[:, 1]])
            return pa.record_batch([pa.array(v[n > 0]), pa.array(n[n > 0])], ["v", "triangles"])
        return pa.record_batch([pa.array([None], pa.int64()), pa.array([self.total], pa.int64())], ["v", "triangles"])


def _slices(askers: np.ndarray, cost: np.ndarray) -> Iterator[np.ndarray]:
    """The askers in runs that cost STEP at most, or one alone."""
    at = 0
    ends = np.cumsum(cost)
    while at < len(askers):
        to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + STEP, "right")))
        yield askers[at:to]
        at = to

