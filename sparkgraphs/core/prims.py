"""Sequence primitives without a one-partition window: range-partition, scan locally, add the totals before each partition."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .rounds import Rounds

OPS = {"sum": (F.sum, lambda a, b: a + b, 0), "max": (F.max, F.greatest, None), "min": (F.min, F.least, None)}


def scan(df: DataFrame, order: list[str], value: str, op: str = "sum", out: str = "scan") -> DataFrame:
    """`df` with the exclusive running `op` of `value` in the order of `order` (a total order): two levels, so that no task sees it all."""
    agg, plus, zero = OPS[op]
    rounds = Rounds(df.sparkSession, "scan")
    dealt = rounds.table(df.repartitionByRange(*order).withColumn("pid", F.spark_partition_id()))
    # one row for each partition
    parts = dealt.groupBy("pid").agg(agg(value).alias("t"), F.count(F.lit(1)).alias("c"))
    before = parts.select("pid", agg("t").over(Window.orderBy("pid").rowsBetween(Window.unboundedPreceding, -1)).alias("base"))
    local = agg(value).over(Window.partitionBy("pid").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1))
    both = dealt.withColumn("here", local).join(F.broadcast(before), "pid")
    value_of = F.when(F.col("here").isNull(), F.col("base")).when(F.col("base").isNull(), F.col("here")).otherwise(plus(F.col("base"), F.col("here")))
    return both.withColumn(out, F.coalesce(value_of, F.lit(zero)) if zero is not None else value_of).drop("pid", "here", "base")


def index(df: DataFrame, order: list[str], out: str = "pos") -> DataFrame:
    """`df` with each row's position from 0."""
    return scan(df.withColumn("one", F.lit(1).cast("bigint")), order, "one", "sum", out).drop("one")


def reduce(df: DataFrame, expr: Column) -> DataFrame:
    return df.agg(expr.alias("value"))


def filter_ordered(df: DataFrame, pred: Column | str) -> DataFrame:
    return df.where(pred)


def prefix_cut(edges: DataFrame, key: str, size: int, total: int) -> tuple[DataFrame, object]:
    """The edges up to about the `size`-th smallest key (all of equal keys), and the key at which it was cut."""
    if size >= total:
        return edges, None
    at = edges.agg(F.percentile_approx(key, size / total, 1000).alias("k")).first().k
    return edges.where(F.col(key) <= F.lit(at)), at
