"""Blocked adjacency: sorted neighbour lists cut in rows of at most B entries, difference-coded; and the neighbour primitives.

A hub is many rows, so work on it spreads over tasks. The first delta is relative to the source.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SIZE = 64


def encode_blocks(edges: DataFrame, size: int = SIZE) -> DataFrame:
    """(src, block_no, first, last, deltas)"""
    place = F.row_number().over(Window.partitionBy("src").orderBy("dst")) - 1
    rows = edges.select("src", "dst", F.floor(place / size).cast("int").alias("block_no"))
    lists = rows.groupBy("src", "block_no").agg(F.sort_array(F.collect_list("dst")).alias("l"))
    before = F.concat(F.array("src"), F.slice("l", 1, F.size("l") - 1))
    return lists.select("src", "block_no", F.element_at("l", 1).alias("first"), F.element_at("l", -1).alias("last"), F.zip_with("l", before, lambda a, b: a - b).alias("deltas"))


def neighbours(adj: DataFrame) -> DataFrame:
    """(src, block_no, nbrs): lists decoded by a running sum."""
    start = F.array().cast("array<bigint>")
    walk = F.aggregate("deltas", F.struct(F.col("src").alias("at"), start.alias("l")), lambda a, d: F.struct((a["at"] + d).alias("at"), F.concat(a["l"], F.array(a["at"] + d)).alias("l")), lambda a: a["l"])
    return adj.select("src", "block_no", walk.alias("nbrs"))


def decode_blocks(adj: DataFrame) -> DataFrame:
    return neighbours(adj).select("src", F.explode("nbrs").alias("dst"))


def nbr_map(adj: DataFrame, f) -> DataFrame:
    return neighbours(adj).select("src", "block_no", F.transform("nbrs", f).alias("mapped"))


def nbr_map_reduce(adj: DataFrame, f, zero: Column, plus, again=F.sum) -> DataFrame:
    """(src, value): neighbours mapped and folded in each block, then over the blocks."""
    return neighbours(adj).select("src", F.aggregate(F.transform("nbrs", f), zero, plus).alias("value")).groupBy("src").agg(again("value").alias("value"))


def nbr_filter(adj: DataFrame, pred) -> DataFrame:
    return neighbours(adj).select("src", "block_no", F.filter("nbrs", pred).alias("nbrs"))


def nbr_pack(adj: DataFrame, pred, size: int = SIZE) -> DataFrame:
    """The adjacency of the neighbours that stay, blocked anew."""
    return encode_blocks(nbr_filter(adj, pred).select("src", F.explode("nbrs").alias("dst")), size)


def nbr_intersect_count(adj: DataFrame, pairs: DataFrame) -> DataFrame:
    """(src, dst, common) for the pairs: only blocks whose ranges overlap are intersected."""
    lists = neighbours(adj).join(adj.select("src", "block_no", "first", "last"), ["src", "block_no"])
    a = lists.select("src", F.col("nbrs").alias("la"), F.col("first").alias("fa"), F.col("last").alias("za"))
    b = lists.select(F.col("src").alias("dst"), F.col("nbrs").alias("lb"), F.col("first").alias("fb"), F.col("last").alias("zb"))
    met = pairs.join(a, "src").join(b, "dst").where("fa <= zb AND fb <= za")
    counts = met.groupBy("src", "dst").agg(F.sum(F.size(F.array_intersect("la", "lb"))).alias("common"))
    return pairs.select("src", "dst").join(counts, ["src", "dst"], "left").select("src", "dst", F.coalesce("common", F.lit(0)).alias("common"))
