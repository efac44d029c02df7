"""Connected components of link tables by alternating stars: larger neighbours go to a vertex's smallest, then smaller ones do.

A round is two written tables in the shared folder with its counters observed as they are written; the number of rounds grows with the
logarithm of a component's size. Minima are pre-aggregated before they are shuffled, so a vertex with very many links is no hot key
there; joins on vertices are plain shuffle joins that adaptive execution can split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from .common import Stages


def _files(rows: int | None) -> int | None:
    return max(1, min(64, rows // 50_000 + 1)) if rows is not None and rows < 3_000_000 else None


def _written(stages: Stages, stars: DataFrame, last: int | None = None) -> tuple[DataFrame, int, int]:
    """The written table (u, m), its number of rows and a sum that depends on its rows alone. last: rows before; small tables go to few files."""
    watch = Observation()
    seen = stars.observe(watch, F.count(F.lit(1)).alias("rows"), F.coalesce(F.bit_xor(F.xxhash64("u", "m")), F.lit(0)).alias("sign"))
    kept = stages.keep(seen, _files(last))
    return kept, watch.get["rows"], watch.get["sign"]


def components(links: DataFrame, stages: Stages, a: str = "a", b: str = "b") -> DataFrame:
    """(v, component): the smallest vertex reachable, for every vertex that has a link."""
    first = links.select(F.greatest(a, b).cast("long").alias("u"), F.least(a, b).cast("long").alias("m")).where("u > m").distinct()
    edges, rows, sign = _written(stages, first)
    last = None
    while rows and sign != last:
        last = sign
        both = edges.unionByName(edges.select(F.col("m").alias("u"), F.col("u").alias("m")))
        # written, so that the join below has a plain shuffle on both sides, which adaptive execution splits at a hub
        least = stages.keep(both.groupBy("u").agg(F.least(F.min("m"), F.col("u")).alias("low")), _files(rows))
        large = both.where("m > u").join(least, "u").select(F.col("m").alias("u"), F.col("low").alias("m")).distinct()
        below = large.groupBy("u").agg(F.min("m").alias("low"))
        # a hub of the next round is the smallest of its neighbours: what it hands down is written once
        small = large.join(below, "u").where("m > low").select(F.col("m").alias("u"), F.col("low").alias("m")).unionByName(below.select("u", F.col("low").alias("m")))
        edges, rows, sign = _written(stages, small.distinct(), rows)
    return edges.groupBy(F.col("u").alias("v")).agg(F.min("m").alias("component")).unionByName(edges.select(F.col("m").alias("v"), F.col("m").alias("component")).distinct())
