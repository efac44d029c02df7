"""Relational operators that derive graphs from tables or consume results."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..core.rounds import Rounds


def scan_edges(df: DataFrame, src: str, dst: str, pred: Column | str | None = None) -> DataFrame:
    """Distinct (src, dst); predicate and columns reach the scan."""
    return (df.where(pred) if pred is not None else df).select(F.col(src).alias("src"), F.col(dst).alias("dst")).distinct()


def tag_ids(df: DataFrame, left: str, right: str) -> DataFrame:
    """Ids of two sides that never meet: even and odd."""
    return df.select((2 * F.col(left)).alias("src"), (2 * F.col(right) + 1).alias("dst"))


def join(a: DataFrame, b: DataFrame, on: Column, strategy: str = "auto", how: str = "inner") -> DataFrame:
    """An equi-join with a strategy: broadcast (of a side whose size the caller has checked), shuffle_hash, merge, or auto."""
    return a.join(b if strategy == "auto" else b.hint(strategy), on, how)


def range_join(points: DataFrame, ranges: DataFrame, at: str, low: str, high: str, bin_size: float) -> DataFrame:
    """Rows with low <= at < high: an equi-join on bins and a residual, instead of a nested loop."""
    binned = points.withColumn("bin", F.floor(F.col(at) / bin_size))
    cut = ranges.withColumn("bin", F.explode(F.sequence(F.floor(F.col(low) / bin_size), F.ceil(F.col(high) / bin_size))))
    return binned.join(cut, "bin").where((F.col(at) >= F.col(low)) & (F.col(at) < F.col(high))).drop("bin")


def interval_join(a: DataFrame, b: DataFrame, key: str, ta: str, tb: str, seconds: int) -> DataFrame:
    """Pairs of one key where b follows a within so many seconds: time slots make it an equi-join, so long histories are split."""
    slot = lambda c: F.floor(F.unix_micros(c) / (seconds * 1_000_000))
    left = a.withColumn("slot", F.explode(F.array(slot(ta), slot(ta) + 1)))
    gap = F.unix_micros(tb) - F.unix_micros(ta)
    return left.join(b.withColumn("slot", slot(tb)), [key, "slot"]).where((gap > 0) & (gap <= seconds * 1_000_000)).drop("slot")


def asof_join(left: DataFrame, right: DataFrame, key: str, tl: str, tr: str, carry: str, order: str) -> DataFrame:
    """`left` with the last `carry` of `right` strictly before it, by key: one shuffle, no pairs."""
    a = left.select(key, F.col(tl).alias("t"), F.lit(1).alias("side"), F.struct(*left.columns).alias("row"), F.lit(None).cast(right.schema[carry].dataType).alias("c"), F.col(order).alias("o"))
    b = right.select(key, F.col(tr).alias("t"), F.lit(2).alias("side"), F.lit(None).cast(left.select(F.struct(*left.columns)).schema[0].dataType).alias("row"), F.col(carry).alias("c"), F.col(order).alias("o"))
    w = Window.partitionBy(key).orderBy("t", "side", "o").rowsBetween(Window.unboundedPreceding, -1)
    return a.unionByName(b).withColumn(f"last_{carry}", F.last("c", ignorenulls=True).over(w)).where("side = 1").select("row.*", f"last_{carry}")


def rank_within(df: DataFrame, group: str, order: Column, tie: str) -> DataFrame:
    w, unique = Window.partitionBy(group).orderBy(order), Window.partitionBy(group).orderBy(order, tie)
    return df.select("*", F.row_number().over(unique).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("drk"), F.ntile(4).over(unique).alias("quarter"), F.round(F.percent_rank().over(w), 9).alias("prk"), F.round(F.cume_dist().over(w), 9).alias("cd"))


def range_frame(df: DataFrame, key: str, at: str, seconds: int) -> DataFrame:
    """How many rows of the key lie in the seconds up to each row."""
    w = Window.partitionBy(key).orderBy(F.unix_micros(at)).rangeBetween(-seconds * 1_000_000, 0)
    return df.withColumn("in_range", F.count(F.lit(1)).over(w))


def topk_by(df: DataFrame, group: str, order: list[Column], k: int) -> DataFrame:
    return df.withColumn("place", F.row_number().over(Window.partitionBy(group).orderBy(*order))).where(F.col("place") <= k)


def page(df: DataFrame, order: list[Column], offset: int, rows: int) -> DataFrame:
    return df.orderBy(*order).offset(offset).limit(rows)


def symdiff(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.exceptAll(b).unionByName(b.exceptAll(a)).distinct()


def json_edges(df: DataFrame, v: str, props: str, path: str) -> DataFrame:
    return df.select(F.col(v).alias("v"), F.get_json_object(props, path).cast("bigint").alias("item"))


def extract_links(df: DataFrame, key: str, html: str) -> DataFrame:
    """(key, link): the distinct relative links of each page."""
    return df.select(key, F.explode(F.array_distinct(F.regexp_extract_all(html, F.lit('href="(/[^"]+)"'), 1))).alias("link"))


def recursive_reach(edges: DataFrame) -> DataFrame:
    """(v, dist) of what the smallest source reaches: a recursion in SQL, a statement a round, until no new vertex appears."""
    spark, rounds = edges.sparkSession, Rounds(edges.sparkSession, "recursive")
    arcs = rounds.table(edges.select("src", "dst"))
    reached, seen = rounds.keep(spark.sql("SELECT min(src) AS v, CAST(0 AS BIGINT) AS dist FROM {arcs} HAVING min(src) IS NOT NULL", arcs=arcs), "reached", new=F.count(F.lit(1)))
    depth = 0
    while seen["new"]:
        depth += 1
        step = """SELECT v, dist FROM {reached} UNION ALL
            SELECT DISTINCT a.dst, CAST({depth} AS BIGINT) FROM {reached} r JOIN {arcs} a ON a.src = r.v LEFT ANTI JOIN {reached} k ON k.v = a.dst WHERE r.dist = {depth} - 1"""
        reached, seen = rounds.keep(spark.sql(step, reached=reached, arcs=arcs, depth=depth), "reached", new=F.count_if(F.col("dist") == depth))
    return reached
