"""Overlapping searches: many centres at once, each within its own subproblem, as (v, center) pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .rounds import Rounds


def multi_search(edges: DataFrame, centers: DataFrame, labels: DataFrame, rounds: Rounds, *, slot: str = "pairs") -> DataFrame:
    """(v, center): what each centre reaches over arcs between vertices of its label. centers: (v); labels: (v, label).

    Pairs are spread by vertex. A round joins the newest pairs only and drops those known.
    """
    own = edges.join(labels.select(F.col("v").alias("src"), F.col("label").alias("ls")), "src").join(labels.select(F.col("v").alias("dst"), F.col("label").alias("ld")), "dst").where("ls = ld").select("src", "dst")
    own = rounds.table(own)
    pairs, seen = rounds.keep(centers.select("v", F.col("v").alias("center"), F.lit(True).alias("new")), slot, new=F.count_if("new"))
    while seen["new"]:
        found = pairs.where("new").select(F.col("v").alias("src"), "center").join(own, "src").select(F.col("dst").alias("v"), "center").distinct()
        fresh = found.join(pairs, ["v", "center"], "left_anti").select("v", "center", F.lit(True).alias("new"))
        pairs, seen = rounds.keep(pairs.withColumn("new", F.lit(False)).unionByName(fresh), slot, new=F.count_if("new"))
    return pairs.select("v", "center")


def estimate(edges: DataFrame, frontier: DataFrame, labels: DataFrame) -> DataFrame:
    """(bound): how many pairs a round can add at most: neighbours of the same label times centres held."""
    held = frontier.groupBy("v").agg(F.count(F.lit(1)).alias("c")).withColumnRenamed("v", "src")
    a, b = labels.select(F.col("v").alias("src"), F.col("label").alias("ls")), labels.select(F.col("v").alias("dst"), F.col("label").alias("ld"))
    return edges.join(held, "src").join(a, "src").join(b, "dst").where("ls = ld").agg(F.coalesce(F.sum("c"), F.lit(0)).alias("bound"))
