"""N-gram Jaccard join by universe partition and pigeonhole.

Sets of word n-grams of similarity t or more differ in at most H = (1-t)/(1+t) * (|x|+|y|) members. Sizes fall into bands whose
starts differ by the factor 1/t^2; a set is indexed in its own band and, if smaller partners may lie there, in the band below. In a band
the universe (of hashes) is cut into segments; partners agree in one of any choice of segments that covers H + 1 units, where a segment
compared exactly covers one unit, and one compared up to one deletion covers two.

Allocation: bands of 2 to 4 units use one-deletion neighbourhoods of few long segments, others exact segments with some to spare. In
the latter a set asks for the segments whose lists cost least: all lists are counted, and the `spare` longest ones (which chance or
a passage common to many makes long) are left to others (`passive`). Every such choice covers H + 1 units, so no link is lost.

Equal sets are one node from the start, named by 64 bits of their digest; copies cost a row each and nothing more. Signatures are
counted first, pre-aggregated, and only those that two nodes share and one asks for are joined back (adaptive execution splits a
hot signature in that join). Pairs of short lists are verified in groups, where each set is built once, and pairs connected by
then are not compared again.

Nodes of long lists are verified by rarity: their n-grams are counted among themselves, a node with over (1-t) of its n-grams
in no other node has no partner and is gone, and of the others only the rarest n-grams that a partner must meet (the prefix) are
listed. Short prefix lists are paired under bounds of size and position. In a long one all are compared with one leader; copies
of one another are connected by that. If a list still holds several components, its nodes outside the largest one are compared in
blocks with all of the list, by matrix products that emit a spanning forest. The components of all links are the result. All comparisons are
exact on 64-bit hashes of n-grams.

Defined cases: null texts and texts without words have an empty set and are linked with nothing; texts of fewer than n words have
their whole word sequence as one n-gram; equal texts are linked; rows that share a doc_id are one document, which has the links of
each of its rows; rows without doc_id have no component; empty tables give empty results; extra columns are ignored.
"""

from __future__ import annotations

import bisect
import hashlib
import math
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Stages, bounded_batches, map_arrow, release, streamed_groups, table
from .components import components
from .token_counts import Memo

BLOCK_DOCS, BLOCK_SHINGLES = 512, 1 << 18
#: Up to so many sets of one list are paired; longer lists have leaders and blocks.
SMALL_LIST = 32
#: A verification group holds about so many pairs with one leader.
LEADER_PAIRS = 4096
U = np.uint64
#: Odd multipliers of the mixing functions (fixed values).
M1, M2, M3 = U(0x9E3779B97F4A7C15), U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB)


@np.errstate(over="ignore")
def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(30))) * M2
    x = (x ^ (x >> U(27))) * M3
    return x ^ (x >> U(31))


class Shingler:
    """Texts to sorted arrays of 64-bit n-gram hashes."""

    def __init__(self, n: int):
        self.n = n
        self.words = Memo(xxhash.xxh64_intdigest, 1 << 18)

    @np.errstate(over="ignore")
    def shingles(self, text: bytes | None) -> np.ndarray:
        words = text.lower().split() if text else []
        if not words:
            return np.zeros(0, U)
        h = np.fromiter(map(self.words.__getitem__, words), U, len(words))
        n = min(self.n, len(words))
        out = np.full(len(words) - n + 1, n, U)
        for i in range(n):
            out = mix(out * M1 + h[i : len(words) - n + 1 + i])
        return np.unique(out)


class Bands:
    """Size bands for a similarity of percent / 100, and how each cuts the universe."""

    def __init__(self, percent: int):
        self.percent, self._starts, self._plans = percent, [1], {}

    def _extend(self, count: int) -> None:
        p2, starts = self.percent**2, self._starts
        while len(starts) < count:
            starts.append(max(starts[-1] + 1, -(-starts[-1] * 10_000 // p2)))

    def start(self, band: int) -> int:
        self._extend(band + 1)
        return self._starts[band]

    def of(self, size: int) -> list[int]:
        """The set's own band and, if smaller partners may lie there, the one below."""
        while self._starts[-1] <= size:
            self._extend(len(self._starts) + 16)
        own = bisect.bisect_right(self._starts, size) - 1
        return [own, own - 1] if own and -(-size * self.percent // 100) < self._starts[own] else [own]

    @np.errstate(over="ignore")
    def plan(self, band: int) -> tuple[np.ndarray, np.ndarray, int, bool]:
        """Segment starts, salts, number of spare segments, and whether segments are compared up to one deletion. Short segments are
        more often shared by chance or through a common passage, so bands of such have more to spare."""
        if band not in self._plans:
            most = self.start(band + 1) - 1
            units = (100 - self.percent) * (most + most * 100 // self.percent) // (100 + self.percent) + 1
            halves = (units + 1) // 2
            # deletions list every member once more: worth it for sets of a few units, whose exact segments would be few and long lists
            deletions = 1 < units <= 4
            m, spare = (halves, 0) if deletions else (units, 0)
            if not deletions and units > 1:
                spare = 2 + math.ceil(units * min(0.3, 1.2 * units / most))
                m = units + spare
            edges = np.array([(i << 64) // m for i in range(m)], U)
            self._plans[band] = edges, mix(np.arange(m, dtype=U) * M1 + U(band) * M2 + U(1)), spare, deletions
        return self._plans[band]

    @np.errstate(over="ignore")
    def signatures(self, hashes: np.ndarray, band: int) -> tuple[np.ndarray, int]:
        """The signatures of a set (sorted hashes) in a band, and how many of them it need not ask for."""
        edges, salt, spare, deletions = self.plan(band)
        at = np.searchsorted(hashes, edges)
        ends = np.append(at[1:], len(hashes))
        sizes = ends - at
        run = np.concatenate([np.zeros(1, U), np.cumsum(hashes, dtype=U)])
        sums = run[ends] - run[at]
        name = lambda total, size, salt: mix(mix(total ^ salt) + size.astype(U))
        sig = name(sums, sizes, salt)
        if deletions:
            seg = np.repeat(np.arange(len(sizes)), sizes)
            sig = np.concatenate([sig, np.unique(name(sums[seg] - hashes, sizes[seg] - 1, salt[seg]))])
        return sig, spare


def linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """Whether two sorted arrays of distinct hashes have a similarity of percent / 100 or more."""
    if min(len(a), len(b)) * 100 < percent * max(len(a), len(b)):
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


class Forest:
    def __init__(self):
        self.up: dict[int, int] = {}

    def root(self, x: int) -> int:
        while (p := self.up.setdefault(x, x)) != x:
            self.up[x] = x = self.up.setdefault(p, p)
        return x

    def join(self, a: int, b: int) -> bool:
        a, b = self.root(a), self.root(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def block_links(left: list[tuple[int, np.ndarray]], right: list[tuple[int, np.ndarray]] | None, percent: int) -> list[tuple[int, int]]:
    """A spanning forest of the links within `left`, or between `left` and `right`: intersections by matrix products."""
    rows = left + (right or [])
    if len(rows) < 2:
        return []
    sizes = np.array([len(s) for _, s in rows], np.int64)
    owner = np.repeat(np.arange(len(rows)), sizes)
    values, inverse, counts = np.unique(np.concatenate([s for _, s in rows]), return_inverse=True, return_counts=True)
    shared = np.flatnonzero(counts > 1)
    place = np.full(len(values), -1, np.int64)
    place[shared] = np.arange(len(shared))
    column = place[inverse]
    owner, column = owner[column >= 0], column[column >= 0]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    both = np.zeros((len(rows), len(rows)), np.float32)
    for lo in range(0, len(shared), 2048):
        i, j = np.searchsorted(column, [lo, lo + 2048])
        part = np.zeros((len(rows), min(2048, len(shared) - lo)), np.float32)
        part[owner[i:j], column[i:j] - lo] = 1
        both += part @ part.T
    inter = both.astype(np.int64)
    link = 100 * inter >= percent * (sizes[:, None] + sizes[None, :] - inter)
    np.fill_diagonal(link, False)
    if right is not None:
        k = len(left)
        link[:k, :k] = False
        link[k:, k:] = False
    label = np.arange(len(rows))
    while True:  # smallest label among neighbours, then shortcuts
        new = np.minimum(label, np.where(link, label[None, :], len(rows)).min(1))
        new = new[new]
        if (new == label).all():
            break
        label = new
    return [(rows[r][0], rows[i][0]) for i, r in enumerate(label.tolist()) if r != i]


#: What a row of signature_rows tells in `spare`: an index-only signature, or a document; else how many a set need not ask for.
INDEX_ONLY, DOCUMENT = -1, -2
SEEN = 1 << 17
NODE_ROWS = "sig long, node long, spare int, n int, doc long"


def node_of(hashes: np.ndarray, doc: int | None) -> int:
    """The 64-bit name of a set; an empty one is its document's own."""
    if not len(hashes):
        return int(mix(np.array([doc or 0], np.int64).view(U) ^ M3).view(np.int64)[0])
    return int.from_bytes(hashlib.blake2b(hashes.tobytes(), digest_size=8).digest(), "little", signed=True)


def signature_rows(docs: DataFrame, n: int, percent: int, key: str, text: str, documents: bool) -> DataFrame:
    """A row for each signature of each node, of equal sets in a task once; with `documents` also one for each row of `docs`, dealt by its id."""

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler, bands, seen = Shingler(n), Bands(percent), {}
        for b in batches:
            ids = b.column(0).to_pylist()
            sigs, owners, counts, spares, widths, nodes, sizes = [], [], [], [], [], [], []
            for i, t in zip(ids, b.column(1).to_pylist(), strict=True):
                s = shingler.shingles(t)
                node = node_of(s, i)
                sizes.append(len(s))
                nodes.append(node)
                if not len(s) or i is None or node in seen:
                    continue
                if len(seen) >= SEEN:
                    seen.clear()
                seen[node] = None
                for own, band in enumerate(bands.of(len(s))):
                    sig, spare = bands.signatures(s, band)
                    sigs.append(sig)
                    owners.append(node)
                    counts.append(len(sig))
                    spares.append(INDEX_ONLY if own else spare)
                    widths.append(len(s))
            if documents:
                here = mix(np.array([i or 0 for i in ids], np.int64).view(U) ^ M1).view(np.int64)
                kind = np.full(len(ids), DOCUMENT, np.int32)
                yield pa.RecordBatch.from_pydict({"sig": pa.array(here), "node": pa.array(nodes, pa.int64()), "spare": pa.array(kind), "n": pa.array(sizes, pa.int32()), "doc": pa.array(ids, pa.int64())})
            if not sigs:
                continue
            each = lambda values, kind: np.repeat(np.array(values, kind), counts)
            columns = {"sig": np.concatenate(sigs).view(np.int64), "node": each(owners, np.int64), "spare": each(spares, np.int32), "n": each(widths, np.int32)}
            for at in range(0, len(columns["sig"]), 50_000):
                part = {k: pa.array(v[at : at + 50_000]) for k, v in columns.items()}
                yield pa.RecordBatch.from_pydict(part | {"doc": pa.nulls(len(part["sig"]), pa.int64())})

    return map_arrow(docs.select(F.col(key).cast("long").alias("doc"), F.col(text).cast("binary").alias("t")), body, NODE_ROWS)


def sets_of(docs: DataFrame, wanted: DataFrame, n: int, key: str, text: str) -> DataFrame:
    """(node, n, long, s): the sets of the nodes in `wanted` (doc, node, long), built from the texts of the documents named there."""
    # what is wanted grows with the corpus, so it is never broadcast: one shuffle of the texts at every size
    joined = docs.select(F.col(key).cast("long").alias("doc"), F.col(text).cast("binary").alias("t")).join(wanted.hint("merge"), "doc")

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(n)
        for b in batches:
            sets = [shingler.shingles(t) for t in b.column("t").to_pylist()]
            # another row of the same document may hold another text
            own = [i for i, (s, d, node) in enumerate(zip(sets, b.column("doc").to_pylist(), b.column("node").to_pylist(), strict=True)) if node_of(s, d) == node]
            sets = [sets[i].view(np.int64) for i in own]
            sizes = np.array([len(s) for s in sets], np.int32)
            offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate([np.zeros(0, np.int64), *sets])))
            at = pa.array(own, pa.int64())
            yield pa.RecordBatch.from_arrays([b.column("node").take(at), pa.array(sizes), b.column("long").take(at), lists], names=["node", "n", "long", "s"])

    return map_arrow(joined.select("doc", "t", "node", "long"), body, "node long, n int, long boolean, s array<long>")


def as_set(column: pa.ChunkedArray, i: int) -> np.ndarray:
    return column[i].values.to_numpy(zero_copy_only=False).view(U)


LINKS = "a long, b long"


def link_batch(links: list[tuple[int, int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({"a": pa.array([x for x, _ in links], pa.int64()), "b": pa.array([y for _, y in links], pa.int64())})


def pair_links(sets: DataFrame, pairs: DataFrame, percent: int) -> DataFrame:
    """Links among listed pairs. sets: (grp, node, s); pairs: (grp, a, b)."""
    none = F.lit(None)
    rows = sets.select("grp", F.lit(0).alias("kind"), F.col("node").alias("a"), none.cast("long").alias("b"), "s").unionByName(pairs.select("grp", F.lit(1).alias("kind"), "a", "b", none.cast("array<long>").alias("s")))

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, g in streamed_groups(batches, ["grp"]):
            kind, a, b, s = g["kind"].to_pylist(), g["a"].to_pylist(), g["b"].to_pylist(), g["s"]
            own: dict[int, np.ndarray] = {}
            forest, out = Forest(), []
            for i, k in enumerate(kind):
                if k == 0:
                    own[a[i]] = as_set(s, i)
                elif forest.root(a[i]) != forest.root(b[i]) and linked(own[a[i]], own[b[i]], percent):
                    forest.join(a[i], b[i])
                    out.append((a[i], b[i]))
            if out:
                yield link_batch(out)

    return map_arrow(rows.repartition("grp").sortWithinPartitions("grp", "kind"), body, LINKS)


def block_rows(sets: DataFrame) -> DataFrame:
    """sets: (grp, main, blocks, rest, node, s). Nodes outside the main component (of `rest` blocks) meet one another (kind 0) and those
    of the main component (kind 1, of `blocks` blocks), which are connected already and do not meet each other."""
    mine = F.when(F.col("main"), F.pmod(F.xxhash64("node"), F.col("blocks"))).otherwise(F.pmod(F.xxhash64("node"), F.col("rest")))
    upto = lambda c: F.sequence(F.lit(0).cast("long"), F.col(c) - 1)
    none = F.array().cast("array<struct<kind:int,i:bigint,j:bigint,left:boolean>>")
    place = lambda kind, i, j, left: F.struct(F.lit(kind).alias("kind"), i.alias("i"), j.alias("j"), left.alias("left"))
    me = F.col("mine")
    inner = F.transform(upto("rest"), lambda x: place(0, F.least(me, x), F.greatest(me, x), me <= x))
    outer = F.when(F.col("blocks") > 0, F.transform(upto("blocks"), lambda x: place(1, x, me, F.lit(False)))).otherwise(none)
    places = F.when(F.col("main"), F.transform(upto("rest"), lambda x: place(1, me, x, F.lit(True)))).otherwise(F.concat(inner, outer))
    return sets.withColumn("mine", mine).select("grp", "node", "s", F.explode(places).alias("p")).select("grp", "p.kind", "p.i", "p.j", "p.left", "node", "s")


def cluster_links(sets: DataFrame, percent: int) -> DataFrame:
    """Links between the components of clusters, block by block."""

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (_, kind, i, j), g in streamed_groups(batches, ["grp", "kind", "i", "j"]):
            nodes, left, s = g["node"].to_pylist(), g["left"].to_pylist(), g["s"]
            rows = [(d, as_set(s, k)) for k, d in enumerate(nodes)]
            if kind == 0 and i == j:
                out = block_links(rows, None, percent)
            else:
                out = block_links([r for r, x in zip(rows, left, strict=True) if x], [r for r, x in zip(rows, left, strict=True) if not x], percent)
            if out:
                yield link_batch(out)

    keys = ["grp", "kind", "i", "j"]
    return map_arrow(block_rows(sets).repartition(*keys).sortWithinPartitions(*keys), body, LINKS)


def listed_pairs(lists: DataFrame, key: str, percent: int, possible: Callable[[Column, Column], Column] | None = None) -> DataFrame:
    """(a, b, grp) of lists (key, passive, node, n[, pos]) of at most SMALL_LIST rows: pairs of which one asks and whose sizes fit.

    A list is verified in the group of its first node; the lists of a long text are dealt to several groups.
    """
    rest = [c for c in ("pos",) if c in lists.columns]
    each = lists.groupBy(key).agg(F.sort_array(F.collect_list(F.struct("passive", "node", "n", *rest))).alias("l"))
    fits = lambda x, y: F.least(x["n"], y["n"]) * 100 >= F.greatest(x["n"], y["n"]) * percent
    good = (lambda x, y: fits(x, y) & possible(x, y)) if possible else fits
    pair = lambda x, y: F.struct(F.least(x["node"], y["node"]).alias("a"), F.greatest(x["node"], y["node"]).alias("b"))
    after = lambda x, i: F.transform(F.filter(F.slice("l", i + 2, F.size("l")), lambda y: good(x, y)), lambda y: pair(x, y))
    # those that ask come first, and are paired with all behind them
    pairs = F.flatten(F.transform(F.filter("l", lambda x, i: ~x["passive"]), after))
    first = F.col("l")[0]
    grp = F.xxhash64(first["node"], F.pmod(F.col(key), (F.floor(first["n"] / 512) + 1).cast("long")))
    return each.select(grp.alias("grp"), F.explode(pairs).alias("p")).select("p.a", "p.b", "grp")


def prefix_lists(sets: DataFrame, percent: int) -> DataFrame:
    """(h, node, n, pos): of each node its rarest n-grams, as many as any partner must meet one of; pos is their place in the order of rarity.

    N-grams are counted among these nodes. Those met once take the first places and are not listed.
    """
    tokens = sets.select("node", "n", F.explode("s").alias("h"))
    counts = sets.select(F.explode("s").alias("h")).groupBy("h").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
    known = tokens.join(counts, "h").groupBy("node", "n").agg(F.sort_array(F.collect_list(F.struct("df", "h"))).alias("l"))
    alone = F.col("n") - F.size("l")
    most = F.col("n") - F.expr(f"(n * {percent} + 99) div 100").cast("int") + 1
    listed = known.select("node", "n", alone.alias("alone"), F.slice("l", 1, F.greatest(most - alone, F.lit(0))).alias("l"))
    return listed.select("node", "n", "alone", F.posexplode("l").alias("at", "x")).select(F.col("x.h").alias("h"), "node", "n", (F.col("alone") + F.col("at")).alias("pos"))


def unsettled_blocks(long: DataFrame, linked_so_far: DataFrame, percent: int, stages: Stages) -> DataFrame | None:
    """(grp, main, blocks, rest, node) of long lists (h, node, n) that still hold several components."""
    parts = components(linked_so_far, stages).select(F.col("v").alias("node"), "component")
    held = stages.keep(long.select("h", "node", "n").join(parts, "node", "left").select("h", "node", "n", F.coalesce("component", "node").alias("part")))
    open_ = stages.keep(held.groupBy("h").agg(F.min("part").alias("lo"), F.max("part").alias("hi"), F.min("node").alias("head")).where("lo < hi").select("h", "head"))
    if open_.isEmpty():
        return None
    left = stages.keep(held.join(open_, "h"))
    clusters = components(left.select(F.col("node").alias("a"), F.col("head").alias("b")), stages)
    # within a cluster only sets of about one size can be linked: it is split by bands of the factor t, and a set goes to its own
    # band and the one below, where a smaller partner may be
    band = F.floor(F.log(F.col("n").cast("double")) / math.log(100 / percent * 1.0001))
    sized = clusters.withColumnRenamed("v", "node").join(left.select("node", "n", "part").distinct(), "node")
    sized = stages.keep(sized.select("node", "n", "part", "component", F.explode(F.array(band, band - 1)).alias("band")).select("node", "n", "part", F.xxhash64("component", "band").alias("grp")))
    parts_of = sized.groupBy("grp", "part").agg(F.count(F.lit(1)).alias("c"), F.sum("n").alias("mass"))
    pieces = lambda c, m: F.greatest(F.ceil(c / BLOCK_DOCS), F.ceil(m / BLOCK_SHINGLES)).cast("long")
    totals = parts_of.groupBy("grp").agg(F.max(F.struct("c", "part", "mass")).alias("top"), F.sum("c").alias("c"), F.sum("mass").alias("mass")).where("c > top.c")
    totals = totals.select("grp", F.col("top.part").alias("main_part"), pieces(F.col("top.c"), F.col("top.mass")).alias("blocks"), pieces(F.col("c") - F.col("top.c"), F.col("mass") - F.col("top.mass")).alias("rest"))
    return sized.join(totals, "grp").select("grp", (F.col("part") == F.col("main_part")).alias("main"), "blocks", "rest", "node")


def similar_documents(docs: DataFrame, *, n: int = 5, percent: int = 80, key: str = "doc_id", text: str = "text", stages: Stages | None = None) -> DataFrame:
    """(doc, n_shingles, component) of every row of `docs`."""
    spark = docs.sparkSession
    stages = stages or Stages(spark, "ngrams")
    bounded_batches(spark)
    # signatures that several nodes share and one of them asks for
    counted = signature_rows(docs, n, percent, key, text, documents=False).groupBy("sig").agg(F.min("node").alias("lo"), F.max("node").alias("hi"), F.max("spare").alias("asked"), F.count(F.lit(1)).alias("c"))
    alive = stages.keep(counted.where("lo < hi AND asked >= 0").select("sig", "c"))
    release(spark)
    rows = signature_rows(docs, n, percent, key, text, documents=True).join(alive.hint("shuffle_hash"), "sig", "left")
    table_of = stages.keep(rows.where(f"spare = {DOCUMENT} OR c IS NOT NULL"))
    release(spark)
    names = table_of.where(f"spare = {DOCUMENT}").select("doc", "node", "n")
    classes = stages.keep(names.where("doc IS NOT NULL").groupBy("node").agg(F.min("doc").alias("rep"), F.count(F.lit(1)).alias("copies")))
    # a set asks for all of its own signatures but the `spare` longest lists
    lists = table_of.where(f"spare > {DOCUMENT}").groupBy("sig", "node").agg(F.max("spare").alias("spare"), F.max("n").alias("n"), F.max("c").alias("c"))
    mine = Window.partitionBy("node", F.col("spare") >= 0).orderBy(F.desc("c"), "sig")
    asked = stages.keep(lists.withColumn("passive", (F.col("spare") < 0) | (F.row_number().over(mine) <= F.col("spare"))).select("sig", "node", "n", "passive"))
    lengths = asked.groupBy("sig").agg(F.count(F.lit(1)).alias("c"), F.count_if(~F.col("passive")).alias("asking")).where("c > 1 AND asking > 0").select("sig", "c")
    shared = stages.keep(asked.join(lengths, "sig"))
    release(spark)
    wanted = shared.groupBy("node").agg((F.max("c") > SMALL_LIST).alias("long")).join(classes, "node").select(F.col("rep").alias("doc"), "node", "long")
    wanted = stages.keep(wanted)
    sets = stages.keep(sets_of(docs, wanted, n, key, text))
    if sets.count() > wanted.count():  # a document repeated with its text
        sets = stages.keep(sets.dropDuplicates(["node"]))
    release(spark)
    pairs = listed_pairs(shared.where(F.col("c") <= SMALL_LIST), "sig", percent)
    rare = stages.keep(prefix_lists(sets.where("long"), percent))
    rare = stages.keep(rare.join(rare.groupBy("h").agg(F.count(F.lit(1)).alias("c"), F.min(F.struct("pos", "node", "n")).alias("leader")).where("c > 1"), "h"))
    # behind a pair's first common n-gram (which both list) there must be enough left of both for the overlap it needs
    enough = lambda x, y: (F.least(x["n"] - x["pos"], y["n"] - y["pos"]) * (100 + percent)) >= (x["n"] + y["n"]) * percent
    short = listed_pairs(rare.where(F.col("c") <= SMALL_LIST).withColumn("passive", F.lit(False)), "h", percent, enough)
    long = rare.where(F.col("c") > SMALL_LIST)
    lead = F.col("leader.node")
    star = long.where((F.col("node") != lead) & (F.least("n", "leader.n") * 100 >= F.greatest("n", "leader.n") * percent))
    star = star.select(F.least("node", lead).alias("a"), F.greatest("node", lead).alias("b"), F.xxhash64(lead, F.pmod(F.xxhash64("node"), F.ceil(F.col("c") / LEADER_PAIRS))).alias("grp"))
    found = reduce(DataFrame.unionByName, (pairs, short, star)).groupBy("a", "b").agg(F.min("grp").alias("grp"))
    pairs = stages.keep(found)
    members = pairs.select(F.col("a").alias("node"), "grp").unionByName(pairs.select(F.col("b").alias("node"), "grp")).distinct()
    links = stages.keep(pair_links(sets.select("node", "s").join(members, "node"), pairs, percent))
    release(spark)
    blocks = unsettled_blocks(long, links, percent, stages)
    if blocks is not None:
        links = links.unionByName(stages.keep(cluster_links(sets.select("node", "s").join(blocks, "node"), percent)))
    # the rows of one document
    several = names.where("doc IS NOT NULL").groupBy("doc").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo < hi").select("doc", "lo")
    links = links.unionByName(names.join(several, "doc").select(F.col("lo").alias("a"), F.col("node").alias("b")).where("a <> b"))
    groups = components(links, stages).select(F.col("v").alias("node"), F.col("component").alias("root"))
    reach = stages.keep(classes.join(groups, "node", "left").select("node", "rep", "copies", F.coalesce("root", "node").alias("root"), F.col("root").isNotNull().alias("linked")))
    least = reach.where("linked").groupBy("root").agg(F.min("rep").alias("least"))
    told = reach.where("linked").join(least, "root").select("node", F.col("least").alias("component"))
    told = stages.keep(told.unionByName(reach.where("NOT linked AND copies > 1").select("node", F.col("rep").alias("component"))))
    out = names.join(told, "node", "left")
    return out.select("doc", F.col("n").cast("long").alias("n_shingles"), F.when(F.col("doc").isNotNull(), F.coalesce("component", "doc")).alias("component"))


def keep_one_of_each(docs: DataFrame, *, n: int = 5, percent: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """`docs` without those that a smaller doc_id reaches by links."""
    stages = Stages(docs.sparkSession, "ngrams")
    found = similar_documents(docs, n=n, percent=percent, key=key, text=text, stages=stages)
    gone = stages.keep(found.where("doc <> component").select(F.col("doc").alias(key)).distinct())  # if small, Spark broadcasts it by its size
    return docs.join(gone, key, "left_anti").select(*docs.columns)


def op3_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return similar_documents(docs, n=3, percent=90).select(F.col("doc").alias("doc_id"), "n_shingles", F.col("component").alias("component_id"))
