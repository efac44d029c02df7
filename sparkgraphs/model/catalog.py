"""The graphs derived from the given tables, in Spark and in SQL."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..core.rounds import Rounds, release
from .graph import Graph, from_arcs


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _arcs(spark: SparkSession, d: str, name: str) -> tuple[DataFrame, bool]:
    """(src, dst) rows and whether they are directed."""
    t = lambda n: read(spark, d, n)
    even, odd = (lambda c: (2 * F.col(c)).cast("bigint")), (lambda c: (2 * F.col(c) + 1).cast("bigint"))
    pair = lambda df, a, b: df.select(a.alias("src"), b.alias("dst"))
    line = lambda: t("orders").join(t("lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    if name == "cust_supp":
        return pair(line(), even("o_custkey"), odd("l_suppkey")), False
    if name == "part_supp":
        return pair(t("lineitem"), even("l_partkey"), odd("l_suppkey")), False
    if name == "cust_part":
        return pair(line(), even("o_custkey"), odd("l_partkey")), False
    if name == "order_part":
        return pair(t("lineitem"), even("l_orderkey"), odd("l_partkey")), False
    if name == "part_copurchase":
        x = _baskets(spark, d).select("l", F.explode("l").alias("src"))
        return x.select("src", F.explode(F.filter("l", lambda q: q > F.col("src"))).alias("dst")), False
    if name in ("event_succession", "event_succession_sym"):
        # the succession is over all events; days are followed in parallel and joined at their ends
        e = t("events").select("user_id", "ts", "event_id", F.to_date("ts").alias("day"))
        w = Window.partitionBy("day").orderBy("ts", "event_id")
        inner = e.select(F.col("user_id").alias("src"), F.lead("user_id").over(w).alias("dst"))
        ends = e.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
        between = ends.select(F.col("last").alias("src"), F.lead("first").over(Window.orderBy("day")).alias("dst"))  # one row a day
        return inner.where("dst IS NOT NULL").unionByName(between.where("dst IS NOT NULL")), name == "event_succession"
    if name in ("event_hot_succession", "event_hot_succession_sym"):
        e = t("events").where("value > 200")
        w = Window.partitionBy(F.to_date("ts")).orderBy("ts", "event_id")
        return e.select(F.col("user_id").alias("src"), F.lead("user_id").over(w).alias("dst")).where("dst IS NOT NULL"), name == "event_hot_succession"
    if name == "order_part_h1":
        return pair(t("lineitem").where("l_shipdate >= '2000-01-01' AND l_shipdate < '2000-07-01'"), even("l_orderkey"), odd("l_partkey")), False
    if name == "cust_part_urgent":
        return pair(line().where("o_orderpriority = '1-URGENT' AND l_quantity >= 48"), even("o_custkey"), odd("l_partkey")), False
    if name == "conversation_chain":
        c = t("conversations").select((F.col("conv_id") * 100 + F.col("turn")).alias("src"))
        return c.join(c.select(F.col("src").alias("dst"), (F.col("src") - 1).alias("src")), "src").select("src", "dst"), False
    if name == "duplicate_docs":
        lines = t("documents").select("doc_id", F.explode(F.array_distinct(F.filter(F.split("text", "\n"), lambda x: F.char_length(x) > 40))).alias("line"))
        hubs = lines.groupBy(F.md5("line").alias("h")).agg(F.min("doc_id").alias("src"), F.count(F.lit(1)).alias("n")).where("n > 1")
        return lines.select(F.md5("line").alias("h"), F.col("doc_id").alias("dst")).join(hubs, "h").select("src", "dst"), False
    if name.startswith("torus"):
        return torus(spark, d, int(name[5:]) if len(name) > 5 else None), False
    if name == "page_links":
        p = t("pages").select((2 * F.col("page_id")).alias("src"), F.explode(F.array_distinct(F.array_union(F.regexp_extract_all("html", F.lit('href="(/[^"]+)"'), 1), F.array(F.parse_url("url", F.lit("HOST")))))).alias("to"))
        return p.select("src", (2 * F.conv(F.substring(F.md5("to"), 1, 12), 16, 10).cast("bigint") + 1).alias("dst")), True
    if name == "user_item":
        e = t("events").where("event_type = 'purchase'")
        return e.select((2 * F.col("user_id")).alias("src"), (2 * F.get_json_object("props", "$.k").cast("bigint") + 1).alias("dst")), False
    if name == "geo_tree":
        r, n = t("nation").select((F.col("n_nationkey") * 4 + 1).cast("bigint").alias("src"), (F.col("n_regionkey") * 4).cast("bigint").alias("dst")), lambda df, k, c, tag: df.select((F.col(k) * 4 + tag).cast("bigint").alias("src"), (F.col(c) * 4 + 1).cast("bigint").alias("dst"))
        return r.unionByName(n(t("customer"), "c_custkey", "c_nationkey", 2)).unionByName(n(t("supplier"), "s_suppkey", "s_nationkey", 3)), False
    raise KeyError(name)


def _baskets(spark: SparkSession, d: str) -> DataFrame:
    """(l): the parts of each order, ascending."""
    x = read(spark, d, "lineitem").select(F.col("l_orderkey").cast("bigint").alias("o"), F.col("l_partkey").cast("bigint").alias("src")).where("o IS NOT NULL AND src IS NOT NULL")
    return x.repartition("o").sortWithinPartitions("o", "src").mapInArrow(_sets, "l array<bigint>")


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(l): the distinct members of each o, of rows (o, src) that come sorted."""

    def rows(parts: list[np.ndarray]) -> pa.RecordBatch:
        o, src = np.concatenate(parts, 1)
        new = np.append(True, (o[1:] != o[:-1]) | (src[1:] != src[:-1]))
        o, src = o[new], src[new]
        ends = np.append(np.flatnonzero(np.append(True, o[1:] != o[:-1])), len(o)).astype(np.int32)
        return pa.record_batch([pa.ListArray.from_arrays(ends, src)], ["l"])

    held: list[np.ndarray] = []
    for b in batches:
        if not b.num_rows:
            continue
        both = np.stack([b.column(0).to_numpy(), b.column(1).to_numpy()])
        cut = int(np.searchsorted(both[0], both[0, -1]))
        if cut or (held and held[-1][0, -1] != both[0, 0]):  # an order is complete
            yield rows([*held, both[:, :cut]])
            held = []
        held.append(both[:, cut:])
    if held:
        yield rows(held)


def torus_side(n: int) -> int:
    """The largest side whose cube is at most n."""
    side = 1
    while (side + 1) ** 3 <= n:
        side += 1
    return side


def torus(spark: SparkSession, sf_dir: str, side: int | None = None) -> DataFrame:
    """Arcs of the 3-D torus over the first side^3 part keys; each vertex names its three successors."""
    parts = read(spark, sf_dir, "part").select(F.col("p_partkey").cast("bigint").alias("src"))
    side = side or torus_side(parts.count())
    x, y, z = F.col("src") % side, F.expr(f"(src div {side}) % {side}"), F.expr(f"src div {side * side}")
    step = [((x + 1) % side, y, z), (x, (y + 1) % side, z), (x, y, (z + 1) % side)]
    return parts.where(F.col("src") < side**3).select("src", F.explode(F.array(*[a + b * side + c * side * side for a, b, c in step])).alias("dst"))


NAMES = (
    "cust_supp", "part_supp", "cust_part", "order_part", "part_copurchase", "event_succession", "event_hot_succession", "order_part_h1",
    "cust_part_urgent", "conversation_chain", "duplicate_docs", "torus", "page_links", "user_item", "geo_tree",
    "event_succession_sym", "event_hot_succession_sym",
)


def load(spark: SparkSession, sf_dir: str, name: str, *, layout: bool = False) -> Graph:
    arcs, directed = _arcs(spark, sf_dir, name)
    g = from_arcs(arcs, directed=directed, name=name)
    return g.layout() if layout else g


#: Graphs whose edges join the members of each of some sets.
CLIQUES = ("part_copurchase",)


def cliques(spark: SparkSession, sf_dir: str, name: str, rounds: Rounds | None = None) -> tuple[DataFrame, int]:
    """(l), written: the sets of two members or more that make a graph of CLIQUES, and how many arcs they give, both ways and with repeated ones."""
    if name not in CLIQUES:
        raise ValueError(f"{name} is not made of sets")
    many = _baskets(spark, sf_dir).where("size(l) > 1")
    written, seen = (rounds or Rounds(spark, "baskets")).keep(many, arcs=F.sum(F.size("l").cast("bigint") * (F.size("l") - 1)))
    del many
    release(spark)
    return written, seen["arcs"] or 0


def both_ways(spark: SparkSession, sf_dir: str, name: str, rounds: Rounds | None = None) -> tuple[DataFrame, int]:
    """(src, dst) of an undirected graph in both directions, as they come (rows may repeat), and how many, 0 where they are not counted.

    Baskets are written before (by `rounds`, if given, which may delete them later), so that arcs can be made from them more than once.
    """
    if name in CLIQUES:
        written, n = cliques(spark, sf_dir, name, rounds)
        each = written.select("l", F.explode("l").alias("src"))
        return each.select("src", F.explode("l").alias("dst")).where("src <> dst"), n
    arcs, directed = _arcs(spark, sf_dir, name)
    if directed:
        raise ValueError(f"{name} is directed")
    src, dst = F.col("src").cast("bigint"), F.col("dst").cast("bigint")
    ends = F.array(F.struct(src.alias("src"), dst.alias("dst")), F.struct(dst.alias("src"), src.alias("dst")))
    return arcs.select(F.inline(ends)), 0


def embedding_knn(spark: SparkSession, sf_dir: str, k: int = 5, block: int = 1024) -> Graph:
    """G14: each vector's k nearest by cosine, with w = 1 - cosine; exact, a block of queries against all rows."""
    import numpy as np
    import pandas as pd

    rows = read(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("bigint").alias("v"), F.col("embedding").cast("array<double>").alias("x"))
    blocks = max(1, -(-rows.count() // block))
    side = rows.withColumn("b", F.pmod(F.xxhash64("v"), F.lit(blocks)))
    left, right = side.withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select(F.col("b").alias("i"), "j", "v", "x"), side.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).select("i", F.col("b").alias("j"), "v", "x")

    def near(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        if a.empty or b.empty:
            return pd.DataFrame({"src": [], "dst": [], "w": []})
        unit = lambda c: (lambda m: m / np.linalg.norm(m, axis=1, keepdims=True))(np.stack(c.to_numpy()))
        sim = unit(a.x) @ unit(b.x).T
        sim[a.v.to_numpy()[:, None] == b.v.to_numpy()[None, :]] = -2
        top = np.argsort(-sim, 1, kind="stable")[:, :k]
        return pd.DataFrame({"src": np.repeat(a.v.to_numpy(), top.shape[1]), "dst": b.v.to_numpy()[top].ravel(), "w": np.round(1 - np.take_along_axis(sim, top, 1), 9).ravel()})

    found = left.groupBy("i", "j").cogroup(right.groupBy("i", "j")).applyInPandas(near, "src bigint, dst bigint, w double").where("w < 2.5")
    best = found.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy("w", "dst"))).where(F.col("r") <= k)
    return from_arcs(best.select("src", "dst", "w"), name="embedding_knn")


#: The same arcs in SQL: (src, dst), in one direction for undirected graphs.
SQL = {
    "cust_supp": "SELECT 2 * o_custkey AS src, 2 * l_suppkey + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "part_supp": "SELECT 2 * l_partkey AS src, 2 * l_suppkey + 1 AS dst FROM lineitem",
    "cust_part": "SELECT 2 * o_custkey AS src, 2 * l_partkey + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "order_part": "SELECT 2 * l_orderkey AS src, 2 * l_partkey + 1 AS dst FROM lineitem",
    "part_copurchase": "SELECT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey",
    "event_succession": "SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events QUALIFY dst IS NOT NULL",
    "event_hot_succession": "SELECT user_id AS src, lead(user_id) OVER (PARTITION BY ts::DATE ORDER BY ts, event_id) AS dst FROM events WHERE value > 200 QUALIFY dst IS NOT NULL",
    "order_part_h1": "SELECT 2 * l_orderkey AS src, 2 * l_partkey + 1 AS dst FROM lineitem WHERE l_shipdate >= '2000-01-01' AND l_shipdate < '2000-07-01'",
    "cust_part_urgent": "SELECT 2 * o_custkey AS src, 2 * l_partkey + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderpriority = '1-URGENT' AND l_quantity >= 48",
    "conversation_chain": "SELECT a.conv_id * 100 + a.turn AS src, a.conv_id * 100 + a.turn + 1 AS dst FROM conversations a JOIN conversations b ON a.conv_id * 100 + a.turn + 1 = b.conv_id * 100 + b.turn",
    "page_links": """SELECT 2 * page_id AS src, 2 * ('0x' || substr(md5(t), 1, 12))::BIGINT + 1 AS dst FROM (
        SELECT page_id, unnest(list_append(regexp_extract_all(html, 'href="(/[^"]+)"', 1), regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1))) AS t FROM pages)""",
    "user_item": "SELECT 2 * user_id AS src, 2 * (props::JSON ->> '$.k')::BIGINT + 1 AS dst FROM events WHERE event_type = 'purchase'",
    "geo_tree": """SELECT n_nationkey * 4 + 1 AS src, n_regionkey * 4 AS dst FROM nation UNION ALL SELECT c_custkey * 4 + 2, c_nationkey * 4 + 1 FROM customer
        UNION ALL SELECT s_suppkey * 4 + 3, s_nationkey * 4 + 1 FROM supplier""",
    "duplicate_docs": """WITH l AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) > 40),
        h AS (SELECT line, min(doc_id) AS hub FROM l GROUP BY line HAVING count(*) > 1) SELECT hub AS src, doc_id AS dst FROM l JOIN h USING (line)""",
    "torus": """WITH s AS (SELECT max(k) AS side FROM range(1, 200) r(k) WHERE k * k * k <= (SELECT count(*) FROM part)),
        c AS (SELECT p_partkey AS p, p_partkey % side AS x, (p_partkey // side) % side AS y, p_partkey // (side * side) AS z, side FROM part, s WHERE p_partkey < side * side * side)
        SELECT p AS src, (x + 1) % side + y * side + z * side * side AS dst FROM c UNION ALL SELECT p, x + (y + 1) % side * side + z * side * side FROM c
        UNION ALL SELECT p, x + y * side + (z + 1) % side * side * side FROM c""",
}


def sql_arcs(name: str) -> str:
    """CTEs e (src, dst), simple and in both directions unless directed, and v (v)."""
    base = SQL[name.removesuffix("_sym")]
    directed = name in ("event_succession", "event_hot_succession", "page_links")
    both = "" if directed else " UNION ALL SELECT dst, src FROM arcs"
    return f"""arcs AS (SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM ({base}) WHERE src <> dst),
e AS MATERIALIZED (SELECT DISTINCT src, dst FROM (SELECT src, dst FROM arcs{both})),
v AS MATERIALIZED (SELECT src AS v FROM e UNION SELECT dst FROM e)"""
