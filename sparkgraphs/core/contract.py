"""Contraction and pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .rounds import Rounds


def pointer_jump(parents: DataFrame, rounds: Rounds | None = None) -> DataFrame:
    """(v, p) with every p its tree's root: chains halve a round."""
    rounds = rounds or Rounds(parents.sparkSession, "jump")
    parents, seen = parents.select("v", "p"), {"moved": 1}
    while seen["moved"]:
        up = parents.select(F.col("v").alias("p"), F.col("p").alias("pp"))
        jumped = parents.join(up, "p", "left").select("v", F.coalesce("pp", "p").alias("p"), (F.coalesce("pp", "p") != F.col("p")).alias("moved"))
        kept, seen = rounds.keep(jumped, "jump", moved=F.count_if("moved"))
        parents = kept.drop("moved")
    return parents


def has_cycle(parents: DataFrame, rounds: Rounds | None = None) -> bool:
    """Whether some vertex of (v, p), p NULL at roots, never comes to a root: pointers double, and those that came to one go."""
    rounds = rounds or Rounds(parents.sparkSession, "cycle")
    ways, seen = rounds.keep(parents.where("p IS NOT NULL").select("v", "p"), "ways", left=F.count(F.lit(1)))
    reach, longest = 1, seen["left"]
    while seen["left"]:
        if reach > longest:
            return True
        up = ways.select(F.col("v").alias("p"), F.col("p").alias("pp"))
        ways, seen = rounds.keep(ways.join(up, "p").select("v", F.col("pp").alias("p")), "ways", left=F.count(F.lit(1)))
        reach *= 2
    return False


def relabel_edges(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """Ends replaced by their labels (v, label); arcs within a label go."""
    a, b = (labels.select(F.col("v").alias(c), F.col("label").alias(f"new_{c}")) for c in ("src", "dst"))
    rest = [c for c in edges.columns if c not in ("src", "dst")]
    return edges.join(a, "src").join(b, "dst").where("new_src <> new_dst").select(F.col("new_src").alias("src"), F.col("new_dst").alias("dst"), *rest)


def contract(edges: DataFrame, labels: DataFrame) -> DataFrame:
    """The edges between labels, once each; of other columns the smallest struct stays."""
    out = relabel_edges(edges, labels)
    rest = [c for c in out.columns if c not in ("src", "dst")]
    if not rest:
        return out.distinct()
    return out.groupBy("src", "dst").agg(F.min(F.struct(*rest)).alias("s")).select("src", "dst", "s.*")
