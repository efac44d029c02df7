"""Embedding near-duplicates with randomised-rotation binary codes.

A vector is scaled to length 1 and turned by seeded random rotations; the signs of its coordinates are its code. The code and, for
the first rotation, the correction factor <code/sqrt(D), rotated vector> are computed once and stored: code and factor give an
unbiased estimate of an inner product with an error of about sqrt((1-f^2)/(f^2 (D-1))) per standard deviation.

Slices of the codes index the vectors: `tables` slices of `bits` signs each. A pair at the threshold agrees in a slice with a
probability that is known, so that with the number of tables chosen here a pair is missed with a probability under `miss`
(1e-6); bits grow with the logarithm of the number of vectors, so lists keep their length.

Lists hold stored codes only. Two codes of a pair at the threshold agree in a number of signs that is binomial; rows with a
partner in their list within `sigmas` standard deviations of it are candidates, and only for those are the vectors fetched. In a list
the estimates of all candidate pairs are then a matrix product; pairs whose upper confidence bound (`sigmas` standard deviations)
reaches the threshold are recomputed in double precision, which alone decides. A pair is counted in the first table in which it meets.

Lists are cut into blocks and compared block by block; a block emits candidate rows, counts and a spanning forest, never its pairs.
Equal vectors are one class and count with their number.

Defined cases: vectors that are null, empty, zero or hold null or non-finite components link with nothing and are their own component; vectors of
different lengths never link; rows that share a vec_id are compared as one vector each, their counts are summed for that id, and the id
joins the components of all its rows; rows without vec_id link with nothing; an empty table gives an empty result; extra
columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Stages, bounded_batches, map_arrow, streamed_groups, table
from .components import components

MISS, SIGMAS, BLOCK, LIST = 1e-6, 6.0, 512, 256


class Rotations:
    """Seeded random orthogonal matrices of one dimension, enough for `bits` signs."""

    def __init__(self, dim: int, bits: int, seed: int):
        rng = np.random.default_rng([seed, dim])
        self.dim, self.bits = dim, bits
        turns = []
        for _ in range(-(-bits // dim)):
            q, r = np.linalg.qr(rng.standard_normal((dim, dim)))
            turns.append(q * np.sign(np.diag(r)))
        self.turns = np.concatenate(turns, 1)

    def codes(self, unit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Signs (rows x bits) and the correction factors of the first rotation."""
        turned = unit @ self.turns
        factor = np.abs(turned[:, : self.dim]).sum(1) / math.sqrt(self.dim)
        return turned[:, : self.bits] >= 0, factor


def plan_tables(rows: int, threshold: float, *, miss: float = MISS, per_list: int = LIST) -> tuple[int, int]:
    """(bits, tables): lists of about `per_list` vectors, a chance under `miss` that a pair at the threshold meets in none."""
    bits = min(62, max(4, round(math.log2(max(2, rows) / per_list))))
    agree = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, max(1, math.ceil(math.log(miss) / math.log1p(-agree)))


def block_counts(a: dict, b: dict | None, t: int, threshold: float, sigmas: float) -> tuple[np.ndarray, np.ndarray]:
    """Links of each row (classes weighted) counted in table t, and a label shared by linked rows, over the rows of a then b."""
    n = len(a["id"])
    rows = a if b is None else {k: np.concatenate([a[k], b[k]]) for k in a}
    dim = rows["unit"].shape[1]
    signs, unit, f = rows["signs"], rows["unit"], rows["factor"]
    # estimate of <x, y> from x's code and y itself, in both directions; the better one's bound is used
    est = (np.where(signs, 1.0, -1.0).astype(np.float32) @ rows["turned"].T.astype(np.float32)) / (math.sqrt(dim) * f[:, None])
    err = sigmas * np.sqrt(np.maximum(1 - f * f, 0) / (f * f * max(1, dim - 1)))[:, None]
    bound = np.minimum(est + err, (est + err).T)
    maybe = bound >= threshold - 1e-4
    np.fill_diagonal(maybe, False)
    if b is not None:
        maybe[:n, :n] = False
        maybe[n:, n:] = False
    if maybe.mean() > 0.05:
        link = maybe & (unit @ unit.T >= threshold)
    else:
        i, j = np.nonzero(np.triu(maybe))
        link = np.zeros_like(maybe)
        for at in range(0, len(i), 1 << 16):
            p, q = i[at : at + (1 << 16)], j[at : at + (1 << 16)]
            link[p, q] = np.einsum("ij,ij->i", unit[p], unit[q]) >= threshold
        link |= link.T
    label = np.arange(len(rows["id"]))
    if not link.any():
        return np.zeros(len(label), np.int64), label
    first = link.copy()
    for s in range(t):
        key = rows["lists"][:, s]
        first &= key[:, None] != key[None, :]
    counts = first @ rows["n"]
    while True:
        new = np.minimum(label, np.where(link, label[None, :], len(label)).min(1))
        new = new[new]
        if (new == label).all():
            return counts, label
        label = new


def units(v: np.ndarray) -> np.ndarray:
    """Rows of length 1; scaled first, so that very large and very small components do no harm."""
    v = v / np.abs(v).max(1, keepdims=True)
    return v / np.sqrt((v * v).sum(1, keepdims=True))


def unpacked(codes: pa.ChunkedArray, bits: int) -> np.ndarray:
    """Stored codes as rows of signs."""
    whole = np.frombuffer(b"".join(codes.to_pylist()), np.uint8).reshape(len(codes), -1)
    return np.unpackbits(whole, axis=1, count=bits).astype(bool)


def near_duplicates(vectors: DataFrame, *, threshold: float = 0.95, key: str = "vec_id", vector: str = "embedding", seed: int = 17, miss: float = MISS, sigmas: float = SIGMAS, block: int = BLOCK, stages: Stages | None = None) -> DataFrame:
    """(key, n_links, component_id, kept) of each distinct key."""
    spark = vectors.sparkSession
    stages = stages or Stages(spark, "vectors")
    bounded_batches(spark, 4_000)
    x = F.col("x")
    usable = x.isNotNull() & (F.size(x) > 0) & F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & F.exists(x, lambda c: c != 0)
    raw = vectors.select(F.col(key).cast("long").alias("id"), F.col(vector).alias("x"))
    ids = raw.select("id").distinct()
    good = raw.where(F.coalesce(usable, F.lit(False)) & F.col("id").isNotNull())
    # hashing first keeps the pre-aggregation of equal vectors small
    marked = good.withColumns({"h1": F.xxhash64("x"), "h2": F.xxhash64(F.lit(7), "x")})
    classes = marked.groupBy("h1", "h2").agg(F.min("id").alias("rep"), F.first("x").alias("x"), F.count(F.lit(1)).alias("n"))
    classes = stages.keep(classes.withColumn("node", F.monotonically_increasing_id()))
    size = classes.agg(F.count(F.lit(1)).alias("classes"), F.coalesce(F.sum("n"), F.lit(0)).alias("rows")).first()
    bits, tables = plan_tables(size.classes, threshold, miss=miss)
    apart = math.acos(threshold) / math.pi

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rotations: dict[int, Rotations] = {}
        power = 1 << np.arange(bits, dtype=np.int64)
        for b in batches:
            vectors = b.column("x").to_pylist()
            for dim in sorted({len(v) for v in vectors}):
                own = [i for i, v in enumerate(vectors) if len(v) == dim]
                turn = rotations.setdefault(dim, Rotations(dim, max(dim, bits * tables), seed))
                signs, factor = turn.codes(units(np.array([vectors[i] for i in own], float)))
                slices = signs[:, : bits * tables].reshape(len(own), tables, bits) @ power
                packed = np.packbits(signs, axis=1)
                offsets = pa.array(np.arange(len(own) + 1, dtype=np.int32) * tables)
                yield pa.RecordBatch.from_pydict({
                    "node": b.column("node").take(pa.array(own)), "dim": pa.array([dim] * len(own), pa.int32()), "code": pa.array([r.tobytes() for r in packed], pa.binary()),
                    "factor": pa.array(factor), "lists": pa.ListArray.from_arrays(offsets, pa.array(slices.reshape(-1))),
                })

    codes = stages.keep(map_arrow(classes.select("node", "x"), coded, "node long, dim int, code binary, factor double, lists array<long>"))
    listed = codes.select("dim", F.posexplode("lists").alias("t", "list"), "node", "code")
    sizes = codes.select("dim", F.posexplode("lists").alias("t", "list")).groupBy("dim", "t", "list").agg(F.count(F.lit(1)).alias("c"))
    # lists of more than a block are few: at most rows x tables / block, so they are looked up by a shuffle only if large
    long_lists = stages.keep(sizes.where(F.col("c") > block).select("dim", "t", "list", F.ceil(F.col("c") / block).cast("long").alias("blocks")))
    spread = listed.join(long_lists, ["dim", "t", "list"], "left").withColumn("blocks", F.coalesce("blocks", F.lit(1).cast("long")))
    mine = F.when(F.col("blocks") == 1, F.lit(0).cast("long")).otherwise(F.pmod(F.xxhash64("node"), F.col("blocks")))
    pieces = spread.withColumn("mine", mine).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    pieces = pieces.select("dim", "t", "list", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "mine", "node", "code")
    keys = ["dim", "t", "list", "i", "j"]
    places = "dim int, t int, list long, i long, j long, mine long, node long"

    def candidates(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []
        rows = 0
        for (dim, *_), g in streamed_groups(batches, keys):
            if g.num_rows < 2:
                continue
            every = max(dim, bits * tables)
            least = every * (1 - apart) - sigmas * math.sqrt(every * apart * (1 - apart))
            signs = np.where(unpacked(g["code"], every), np.float32(1), np.float32(-1))
            near = signs @ signs.T >= 2 * least - every
            side = g["mine"].to_numpy()
            if len(set(side.tolist())) > 1:
                near &= side[:, None] != side[None, :]
            np.fill_diagonal(near, False)
            at = np.flatnonzero(near.any(1))
            if len(at):
                held.append(g.select([*keys, "mine", "node"]).take(pa.array(at)))
                rows += len(at)
            if rows > 20_000:
                yield from pa.concat_tables(held).combine_chunks().to_batches()
                held, rows = [], 0
        if held:
            yield from pa.concat_tables(held).combine_chunks().to_batches()

    near = stages.keep(map_arrow(pieces.repartition(*keys).sortWithinPartitions(*keys), candidates, places))
    fetched = near.join(codes.select("node", "code", "factor"), "node").join(classes.select("node", "n", "x"), "node")

    def compared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rotations: dict[int, Rotations] = {}
        power = 1 << np.arange(bits, dtype=np.int64)
        for (dim, t, _, i, j), g in streamed_groups(batches, keys):
            every = max(dim, bits * tables)
            turn = rotations.setdefault(dim, Rotations(dim, dim, seed))
            unit = units(g["x"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, dim).astype(float))
            signs = unpacked(g["code"], every)
            side = g["mine"].to_numpy()
            rows = {
                "id": g["node"].to_numpy(), "n": g["n"].to_numpy(), "unit": unit, "signs": signs[:, :dim], "factor": g["factor"].to_numpy(),
                "turned": unit @ turn.turns, "lists": signs[:, : bits * tables].reshape(len(unit), tables, bits) @ power,
            }
            if i == j:
                counts, label = block_counts(rows, None, t, threshold, sigmas)
            else:
                order = np.argsort(side != i, kind="stable")
                rows = {k: x[order] for k, x in rows.items()}
                cut = int((side == i).sum())
                if cut in (0, len(side)):
                    continue
                counts, label = block_counts({k: x[:cut] for k, x in rows.items()}, {k: x[cut:] for k, x in rows.items()}, t, threshold, sigmas)
            at = np.flatnonzero((counts > 0) | (label != np.arange(len(label))))
            if len(at):
                yield pa.RecordBatch.from_pydict({"node": pa.array(rows["id"][at]), "links": pa.array(counts[at].astype(np.int64)), "to": pa.array(rows["id"][label[at]])})

    found = stages.keep(map_arrow(fetched.repartition(*keys).sortWithinPartitions(*keys), compared, "node long, links long, to long"))
    counts = found.groupBy("node").agg(F.sum("links").alias("links"))
    known = classes.select("h1", "h2", "node", "rep", "n")
    # a class of over a thousandth of all rows: there are a thousand at most
    big = F.col("n") > size.rows / 1000 + 1
    each = marked.select("id", "h1", "h2")
    hot = F.broadcast(known.where(big))
    held = each.join(hot, ["h1", "h2"]).unionByName(each.join(hot.select("h1", "h2"), ["h1", "h2"], "left_anti").join(known.where(~big), ["h1", "h2"]))
    held = stages.keep(held.select("id", "node", "n"))
    # the rows of one id
    several = held.groupBy("id").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo < hi").select("id", "lo")
    joined = held.join(several, "id").select(F.col("lo").alias("a"), F.col("node").alias("b"))
    groups = components(found.select(F.col("node").alias("a"), F.col("to").alias("b")).unionByName(joined), stages).withColumnRenamed("v", "node")
    reach = known.select("node", "rep").join(groups, "node", "left").select("node", "rep", F.coalesce("component", "node").alias("root"))
    reach = stages.keep(reach)
    least = reach.groupBy("root").agg(F.min("rep").alias("component"))
    told = stages.keep(reach.join(least, "root").join(counts, "node", "left").select("node", "component", F.coalesce("links", F.lit(0)).alias("links")))
    per_id = held.join(told, "node").groupBy("id").agg(F.sum(F.col("links") + F.col("n") - 1).alias("links"), F.min("component").alias("component"))
    out = ids.join(per_id, "id", "left").select(F.col("id").alias(key), F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    return out.withColumn("kept", F.col(key) == F.col("component_id"))


def op1_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "embeddings"))


OP1_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, list_transform(embedding, lambda c: c::DOUBLE) AS x FROM embeddings),
u AS (
  SELECT vec_id, x, sqrt(list_inner_product(x, x)) AS len FROM v
  WHERE x IS NOT NULL AND len(x) > 0 AND len(list_filter(x, lambda c: c IS NULL OR NOT isfinite(c))) = 0),
w AS (SELECT * FROM u WHERE len > 0),
e AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM w a JOIN w b ON a.vec_id <> b.vec_id AND len(a.x) = len(b.x)
  WHERE list_inner_product(a.x, b.x) / (a.len * b.len) >= 0.95),
r(v, c) AS (
  SELECT vec_id, vec_id FROM embeddings
  UNION
  SELECT e.b, r.c FROM r JOIN e ON e.a = r.v WHERE r.c < e.b)
SELECT v.vec_id, coalesce(n.n, 0) AS n_links, c.c AS component_id, c.c = v.vec_id AS kept
FROM (SELECT vec_id FROM embeddings) v LEFT JOIN (SELECT a, count(*) AS n FROM e GROUP BY a) n ON n.a = v.vec_id
JOIN (SELECT v, min(c) AS c FROM r GROUP BY v) c ON c.v = v.vec_id
"""
