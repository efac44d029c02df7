"""Prefixes down and sums up rooted forests given as (v, parent, level); roots have no parent and level 0."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .rounds import Rounds


def leaffix(forest: DataFrame, column: str, agg: str = "sum", rounds: Rounds | None = None) -> DataFrame:
    """(v, column) with every subtree's sum, min or max, level by level from the leaves."""
    rounds = rounds or Rounds(forest.sparkSession, "leaffix")
    plus = {"sum": lambda a, b: a + F.coalesce(b, F.lit(0)), "min": F.least, "max": F.greatest}[agg]
    pick = {"sum": F.sum, "min": F.min, "max": F.max}[agg]
    state = forest.select("v", "parent", "level", column)
    depth = state.agg(F.max("level").alias("d")).first().d or 0
    for level in range(depth, 0, -1):
        up = state.where(F.col("level") == level).groupBy(F.col("parent").alias("v")).agg(pick(column).alias("from_below"))
        state, _ = rounds.keep(state.join(up, "v", "left").select("v", "parent", "level", F.when(F.col("from_below").isNull(), F.col(column)).otherwise(plus(F.col(column), F.col("from_below"))).alias(column)), f"leaffix_{column}", touched=F.count_if(F.col("level") == level - 1))
    return state.select("v", column)


def rootfix(forest: DataFrame, column: str, extend: Column, start: Column, rounds: Rounds | None = None) -> DataFrame:
    """(v, column) from the roots down; `extend` is over the vertex's columns and above (the parent's value)."""
    rounds = rounds or Rounds(forest.sparkSession, "rootfix")
    depth = forest.agg(F.max("level").alias("d")).first().d or 0
    state = forest.withColumn(column, F.when(F.col("level") == 0, start))
    for level in range(1, depth + 1):
        above = state.where(F.col("level") == level - 1).select(F.col("v").alias("parent"), F.col(column).alias("above"))
        joined = state.join(above, "parent", "left").withColumn(column, F.when(F.col("level") == level, extend).otherwise(F.col(column)))
        state, _ = rounds.keep(joined.select(*forest.columns, column), f"rootfix_{column}", touched=F.count_if(F.col("level") == level))
    return state.select("v", column)


def preorder(forest: DataFrame, sizes: DataFrame, rounds: Rounds | None = None) -> DataFrame:
    """(v, pre): numbers within each tree, siblings in the order of their ids."""
    earlier = F.sum("size").over(Window.partitionBy("parent").orderBy("v").rowsBetween(Window.unboundedPreceding, -1))
    told = forest.join(sizes, "v").withColumn("offset", F.when(F.col("level") > 0, 1 + F.coalesce(earlier, F.lit(0))).otherwise(F.lit(0)).cast("bigint"))
    return rootfix(told.select("v", "parent", "level", "offset"), "pre", F.col("above") + F.col("offset"), F.lit(0).cast("bigint"), rounds)
