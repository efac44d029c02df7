"""Registered operator queries over the given tables."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..algo.bfs import ego
from ..core import blocks, forest
from ..core.contract import contract, pointer_jump
from ..core.histogram import histogram
from ..core.prims import index, prefix_cut, scan
from ..core.priority import prio, prio_sql
from ..core.rounds import shared_dir
from ..model import catalog
from ..model.graph import Graph
from ..queries import arcs, on, query, source
from ..sources import edges as io
from ..stream import events as live
from . import relational as rel

T = catalog.read
S = SparkSession


def op(name: str, sql: str | None = None):
    return query(f"op_{name}", sql)


def line(spark: S, d: str) -> DataFrame:
    return T(spark, d, "orders").join(T(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))


def nation_sales(spark: S, d: str) -> DataFrame:
    return T(spark, d, "customer").join(T(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"))


# scans, sources, sinks

op("scan_edges", "SELECT DISTINCT l_partkey AS src, l_suppkey AS dst FROM lineitem WHERE l_shipdate >= '2000-01-01' AND l_shipdate < '2000-04-01'")(
    lambda s, d: rel.scan_edges(T(s, d, "lineitem"), "l_partkey", "l_suppkey", "l_shipdate >= '2000-01-01' AND l_shipdate < '2000-04-01'"))


@op("sink_roundtrip", f"WITH {arcs('cust_part_urgent')} SELECT unnest(['parquet', 'json', 'csv', 'orc']) AS fmt, (SELECT count(*) FROM e) AS n, (SELECT sum(src + 3 * dst)::BIGINT FROM e) AS total")
def sink_roundtrip(spark: S, sf_dir: str) -> DataFrame:
    g, out = catalog.load(spark, sf_dir, "cust_part_urgent"), None
    for fmt in io.FORMATS:
        path = f"{shared_dir(spark)}/sink-{uuid.uuid4().hex[:12]}"
        io.write_result(g.edges, path, fmt)
        got = io.read_edges(spark, path, fmt=fmt).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("src") + 3 * F.col("dst")).alias("total")).withColumn("fmt", F.lit(fmt))
        out = got if out is None else out.unionByName(got)
    return out


@op("torus_source", catalog.SQL["torus"])
def torus_source(spark: S, sf_dir: str) -> DataFrame:
    """Arcs of the torus over the part keys: the data source makes them, the parts say which there are."""
    parts = T(spark, sf_dir, "part").select(F.col("p_partkey").cast("bigint").alias("src"))
    spark.dataSource.register(io.TorusSource)
    return parts.join(spark.read.format("torus").option("side", catalog.torus_side(parts.count())).load(), "src").select("src", "dst")


# projections and filters

op("project_rename", "SELECT 2 * l_partkey AS src, 2 * l_suppkey + 1 AS dst FROM lineitem")(lambda s, d: rel.tag_ids(T(s, d, "lineitem"), "l_partkey", "l_suppkey"))
op("filter_compound", "SELECT o_orderkey, l_linenumber, l_quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE (o_orderpriority IN ('1-URGENT', '2-HIGH') OR l_quantity BETWEEN 10 AND 12) AND l_returnflag LIKE 'R%' AND o_orderstatus IS NOT NULL")(
    lambda s, d: line(s, d).where((F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") | F.col("l_quantity").between(10, 12)) & F.col("l_returnflag").like("R%") & F.col("o_orderstatus").isNotNull()).select("o_orderkey", "l_linenumber", "l_quantity"))
op("induced_subgraph", f"WITH {arcs('duplicate_docs')}, k AS (SELECT doc_id FROM labels WHERE quality = 1) SELECT src, dst FROM e WHERE src IN (SELECT * FROM k) AND dst IN (SELECT * FROM k)")(
    lambda s, d: catalog.load(s, d, "duplicate_docs").induced(T(s, d, "labels").where("quality = 1").select(F.col("doc_id").alias("v"))).edges)
op("ego_network", f"WITH {arcs('cust_part_urgent')}, o AS (SELECT min(v) AS o FROM v), a AS (SELECT o AS v FROM o UNION SELECT dst FROM e, o WHERE src = o), b AS (SELECT v FROM a UNION SELECT dst FROM e JOIN a ON src = a.v) SELECT src, dst FROM e WHERE src IN (SELECT v FROM b) AND dst IN (SELECT v FROM b)")(
    on("cust_part_urgent", lambda g: ego(g, source(g), 2).edges))

# joins

for _s in ("broadcast", "shuffle_hash", "merge"):
    op(f"join_{'sort_merge' if _s == 'merge' else _s}", "SELECT s_suppkey, n_name, s_acctbal FROM supplier JOIN nation ON s_nationkey = n_nationkey")(
        lambda s, d, k=_s: rel.join(T(s, d, "supplier"), T(s, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey"), k).select("s_suppkey", "n_name", "s_acctbal"))
op("join_nested_loop", "SELECT c_custkey, s_suppkey FROM customer JOIN supplier ON c_nationkey = s_nationkey AND c_acctbal < s_acctbal WHERE c_nationkey = 3")(
    lambda s, d: T(s, d, "customer").where("c_nationkey = 3").join(T(s, d, "supplier"), (F.col("c_nationkey") == F.col("s_nationkey")) & (F.col("c_acctbal") < F.col("s_acctbal"))).select("c_custkey", "s_suppkey"))
op("join_nested_loop_whole", "SELECT c_custkey, n_nationkey FROM customer JOIN nation ON c_nationkey < n_nationkey")(
    lambda s, d: rel.join(T(s, d, "customer"), T(s, d, "nation"), F.col("c_nationkey") < F.col("n_nationkey"), "broadcast").select("c_custkey", "n_nationkey"))
op("join_cross", "SELECT r_name, event_type FROM region, (SELECT DISTINCT event_type FROM events)")(lambda s, d: T(s, d, "region").crossJoin(F.broadcast(T(s, d, "events").select("event_type").distinct())).select("r_name", "event_type"))
for _h, _n in (("left_semi", "IN"), ("left_anti", "NOT IN")):
    op(f"join_{_h[5:]}", f"SELECT c_custkey FROM customer WHERE c_custkey {_n} (SELECT o_custkey FROM orders)")(
        lambda s, d, h=_h: T(s, d, "customer").join(T(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), h).select("c_custkey"))
op("join_outer", "SELECT o_orderkey AS v, count(l_orderkey) AS degree FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey")(
    lambda s, d: T(s, d, "orders").join(T(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left").groupBy(F.col("o_orderkey").alias("v")).agg(F.count("l_orderkey").alias("degree")))
op("join_full", "SELECT coalesce(c_nationkey, s_nationkey) AS k, c, t FROM (SELECT c_nationkey, count(*) AS c FROM customer WHERE c_acctbal > 9000 GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS t FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) ON c_nationkey = s_nationkey")(
    lambda s, d: T(s, d, "customer").where("c_acctbal > 9000").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("c")).join(T(s, d, "supplier").where("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("t")), "k", "full"))
op("join_self", f"WITH {arcs('cust_part_urgent')} SELECT a.dst AS x, b.dst AS y, count(*) AS wedges FROM e a JOIN e b ON a.src = b.src AND a.dst < b.dst GROUP BY ALL")(
    lambda s, d: (lambda e: e.select("src", F.col("dst").alias("x")).join(e.select("src", F.col("dst").alias("y")), "src").where("x < y").groupBy("x", "y").agg(F.count(F.lit(1)).alias("wedges")))(catalog.load(s, d, "cust_part_urgent").edges))
op("join_range", "WITH r AS (SELECT i AS bucket, i * 7.5 AS low, (i + 1) * 7.5 AS high FROM range(8) t(i)) SELECT l_orderkey, l_linenumber, l_quantity, bucket FROM lineitem JOIN r ON l_quantity >= low AND l_quantity < high")(
    lambda s, d: rel.range_join(T(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity"), s.range(8).select(F.col("id").alias("bucket"), (F.col("id") * 7.5).alias("low"), ((F.col("id") + 1) * 7.5).alias("high")), "l_quantity", "low", "high", 5.0).select("l_orderkey", "l_linenumber", "l_quantity", "bucket"))


def _two(s: S, d: str, a: str, b: str) -> tuple[DataFrame, DataFrame]:
    e = T(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.where(F.col("event_type") == a).select("user_id", F.col("event_id").alias("a_id"), F.col("ts").alias("ta")), e.where(F.col("event_type") == b).select("user_id", F.col("event_id").alias("b_id"), F.col("ts").alias("tb"))


CLICKS = "SELECT a.user_id, a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"
op("join_interval", CLICKS)(lambda s, d: rel.interval_join(*_two(s, d, "click", "purchase"), "user_id", "ta", "tb", 3600).select("user_id", "a_id", "b_id"))
op("join_asof", "SELECT p.event_id AS b_id, v.event_id AS last_a_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts > v.ts")(
    lambda s, d: (lambda v, p: rel.asof_join(p.withColumnRenamed("b_id", "id"), v.withColumnRenamed("a_id", "a_id").withColumn("id", F.col("a_id")), "user_id", "tb", "ta", "a_id", "id").select(F.col("id").alias("b_id"), "last_a_id"))(*_two(s, d, "view", "purchase")))
op("join_triangle", f"WITH {arcs('event_succession_sym')} SELECT a.src AS a, a.dst AS b, b.dst AS c FROM e a JOIN e b ON a.dst = b.src AND a.src < a.dst AND b.src < b.dst JOIN e c ON c.src = a.src AND c.dst = b.dst")(
    on("event_succession_sym", lambda g: (lambda e: e.select(F.col("src").alias("a"), F.col("dst").alias("b")).join(e.select(F.col("src").alias("b"), F.col("dst").alias("c")), "b").join(e.select(F.col("src").alias("a"), F.col("dst").alias("c")), ["a", "c"], "left_semi").select("a", "b", "c"))(g.half())))

# aggregations

op("agg_hash", "SELECT l_suppkey, count(*) AS n, sum(l_quantity) AS quantity, strftime(min(l_shipdate), '%Y-%m-%d') AS first, max(l_discount) AS top FROM lineitem GROUP BY l_suppkey")(
    lambda s, d: T(s, d, "lineitem").groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"), F.date_format(F.min("l_shipdate"), "yyyy-MM-dd").alias("first"), F.max("l_discount").alias("top")))
op("agg_sort", "SELECT l_orderkey, array_to_string(list_sort(list(l_partkey)), ',') AS parts FROM lineitem GROUP BY l_orderkey")(
    lambda s, d: T(s, d, "lineitem").groupBy("l_orderkey").agg(F.array_join(F.sort_array(F.collect_list("l_partkey")).cast("array<string>"), ",").alias("parts")))
for _s in ("local_first", "raw"):
    op(f"agg_{'partial_final' if _s == 'local_first' else 'unshared'}", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey")(lambda s, d, k=_s: histogram(T(s, d, "lineitem").select("l_suppkey"), "l_suppkey", strategy=k))
op("salted_agg", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey")(lambda s, d: histogram(T(s, d, "lineitem").select("l_suppkey"), "l_suppkey", strategy="heavy_light"))
op("agg_distinct", "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY l_suppkey")(lambda s, d: T(s, d, "lineitem").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders")))
op("agg_approx_distinct", "SELECT true AS close")(
    lambda s, d: T(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.countDistinct("l_partkey").alias("b"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("c")).select(((F.abs(F.col("a") - F.col("b")) < 0.1 * F.col("b")) & (F.abs(F.col("c") - F.col("b")) < 0.1 * F.col("b"))).alias("close")))
op("agg_percentile", "SELECT quantile_cont(l_quantity, 0.5) AS half, quantile_cont(l_extendedprice, 0.9) AS top FROM lineitem")(lambda s, d: T(s, d, "lineitem").agg(F.percentile("l_quantity", 0.5).alias("half"), F.percentile("l_extendedprice", 0.9).alias("top")))
NS = "FROM customer JOIN orders ON c_custkey = o_custkey"
GROUPING = {"rollup": "ROLLUP (c_nationkey, c_mktsegment)", "cube": "CUBE (c_nationkey, c_mktsegment)", "grouping_sets": "GROUPING SETS ((c_nationkey), (c_mktsegment), ())"}
for _k, _v in GROUPING.items():
    def _grouped(s: S, d: str, k: str = _k) -> DataFrame:
        df = nation_sales(s, d)
        if k == "grouping_sets":
            g = df.groupingSets([[F.col("c_nationkey")], [F.col("c_mktsegment")], []], "c_nationkey", "c_mktsegment")
        else:
            g = getattr(df, k)("c_nationkey", "c_mktsegment")
        return g.agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("gid")).select("c_nationkey", "c_mktsegment", "n", "gid")

    op(_k, f"SELECT c_nationkey, c_mktsegment, count(*) AS n, grouping_id(c_nationkey, c_mktsegment) AS gid {NS} GROUP BY {_v}")(_grouped)
op("pivot", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase, count(*) FILTER (event_type = 'view') AS \"view\" FROM events GROUP BY user_id")(
    lambda s, d: T(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "purchase", "view"]).agg(F.count(F.lit(1))).na.fill(0))
op("unpivot", "SELECT s_suppkey, k, x FROM (SELECT s_suppkey, s_nationkey::DOUBLE AS nation, s_acctbal AS balance FROM supplier) UNPIVOT (x FOR k IN (nation, balance))")(
    lambda s, d: T(s, d, "supplier").select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance")).unpivot("s_suppkey", ["nation", "balance"], "k", "x"))
op("agg_filter_clause", "SELECT o_custkey, count(*) FILTER (o_totalprice > 1000) AS large, count(*) FILTER (o_orderstatus = 'F') AS done FROM orders GROUP BY o_custkey")(lambda s, d: T(s, d, "orders").groupBy("o_custkey").agg(F.count_if(F.col("o_totalprice") > 1000).alias("large"), F.count_if(F.col("o_orderstatus") == "F").alias("done")))
op("min_by_struct", "SELECT l_partkey, arg_min(l_suppkey, (l_extendedprice, l_suppkey)) AS cheapest FROM lineitem GROUP BY l_partkey")(lambda s, d: T(s, d, "lineitem").groupBy("l_partkey").agg(F.min_by("l_suppkey", F.struct("l_extendedprice", "l_suppkey")).alias("cheapest")))

# windows and order

op("window_rank", "WITH t AS (SELECT c_nationkey AS nation, c_custkey AS v, floor(c_acctbal / 100)::BIGINT AS degree FROM customer) SELECT nation, v, degree, row_number() OVER (PARTITION BY nation ORDER BY degree DESC, v) AS rn, rank() OVER w AS rk, dense_rank() OVER w AS drk, ntile(4) OVER (PARTITION BY nation ORDER BY degree DESC, v) AS quarter, round(percent_rank() OVER w, 9) AS prk, round(cume_dist() OVER w, 9) AS cd FROM t WINDOW w AS (PARTITION BY nation ORDER BY degree DESC)")(
    lambda s, d: rel.rank_within(T(s, d, "customer").select(F.col("c_nationkey").alias("nation"), F.col("c_custkey").alias("v"), F.floor(F.col("c_acctbal") / 100).alias("degree")), "nation", F.desc("degree"), "v"))
op("window_lag_lead", f"WITH {arcs('event_succession')} SELECT src, dst FROM e")(lambda s, d: catalog.load(s, d, "event_succession").edges)
op("window_scan", "SELECT s_suppkey, coalesce(sum(s_nationkey) OVER (ORDER BY s_suppkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS scan FROM supplier")(lambda s, d: scan(T(s, d, "supplier").select("s_suppkey", F.col("s_nationkey").cast("bigint").alias("x")), ["s_suppkey"], "x").select("s_suppkey", "scan"))
op("window_index", "SELECT c_custkey, row_number() OVER (ORDER BY c_acctbal, c_custkey) - 1 AS pos FROM customer")(lambda s, d: index(T(s, d, "customer").select("c_custkey", "c_acctbal"), ["c_acctbal", "c_custkey"]).select("c_custkey", "pos"))
op("window_suffix", "SELECT c_nationkey, c_custkey, sum(c_custkey) OVER (PARTITION BY c_nationkey ORDER BY c_custkey DESC ROWS UNBOUNDED PRECEDING) AS suffix FROM customer")(
    lambda s, d: T(s, d, "customer").select("c_nationkey", "c_custkey", F.sum("c_custkey").over(Window.partitionBy("c_nationkey").orderBy(F.desc("c_custkey")).rowsBetween(Window.unboundedPreceding, 0)).alias("suffix")))
op("window_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS in_range FROM events")(lambda s, d: rel.range_frame(T(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")), "user_id", "ts", 3600).select("event_id", "in_range"))
op("window_first_last_nth", "SELECT DISTINCT user_id, first_value(event_type) OVER w AS first, last_value(event_type) OVER w AS last, nth_value(event_type, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")(
    lambda s, d: (lambda w: T(s, d, "events").select("user_id", F.first("event_type").over(w).alias("first"), F.last("event_type").over(w).alias("last"), F.nth_value("event_type", 2).over(w).alias("second")).distinct())(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
op("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")(lambda s, d: T(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10))
op("topk_group", "SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS place FROM orders QUALIFY place <= 3")(lambda s, d: rel.topk_by(T(s, d, "orders"), "o_custkey", [F.desc("o_totalprice"), F.col("o_orderkey")], 3).select("o_custkey", "o_orderkey", "place"))
op("sort_limit_offset", "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal, c_custkey LIMIT 20 OFFSET 40")(lambda s, d: rel.page(T(s, d, "customer").select("c_custkey", "c_acctbal"), [F.col("c_acctbal"), F.col("c_custkey")], 40, 20))

# sets

A, B = "SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 8000", "SELECT s_nationkey AS k FROM supplier WHERE s_acctbal > 4000"
_ab = lambda s, d: (T(s, d, "customer").where("c_acctbal > 8000").select(F.col("c_nationkey").alias("k")), T(s, d, "supplier").where("s_acctbal > 4000").select(F.col("s_nationkey").alias("k")))
for _n, _q, _f in (
    ("union", f"{A} UNION {B}", lambda a, b: a.union(b).distinct()), ("union_all", f"{A} UNION ALL {B}", lambda a, b: a.unionByName(b)),
    ("intersect", f"{A} INTERSECT {B}", lambda a, b: a.intersect(b)), ("intersect_all", f"{A} INTERSECT ALL {B}", lambda a, b: a.intersectAll(b)),
    ("except", f"{A} EXCEPT {B}", lambda a, b: a.subtract(b)), ("except_all", f"{A} EXCEPT ALL {B}", lambda a, b: a.exceptAll(b)),
    ("symdiff", f"({A} EXCEPT ALL {B}) UNION ({B} EXCEPT ALL {A})", rel.symdiff),
):
    op(_n, _q)(lambda s, d, f=_f: f(*_ab(s, d)))

# functions

op("string_fns", "SELECT page_id, upper(substr(url, 1, 5)) AS head, length(html) AS n, list_aggregate(string_split(url, '/'), 'count') AS parts, regexp_extract(url, '^([a-z]+):', 1) AS scheme FROM pages")(
    lambda s, d: T(s, d, "pages").select("page_id", F.upper(F.substring("url", 1, 5)).alias("head"), F.length("html").alias("n"), F.size(F.split("url", "/")).alias("parts"), F.regexp_extract("url", "^([a-z]+):", 1).alias("scheme")))
op("url_fns", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/]+([^?#]*)', 1) AS path FROM pages")(lambda s, d: T(s, d, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PATH")).alias("path")))
op("extract_links", """SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="(/[^"]+)"', 1)) AS link FROM pages""")(lambda s, d: rel.extract_links(T(s, d, "pages"), "page_id", "html"))
op("date_fns", "SELECT strftime(l_shipdate, '%Y-%m') AS month, count(*) AS n, max(dayofweek(l_shipdate) + 1) AS day, max(datediff('day', DATE '2000-01-01', l_shipdate::DATE)) AS days FROM lineitem GROUP BY 1")(
    lambda s, d: T(s, d, "lineitem").groupBy(F.date_format("l_shipdate", "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.max(F.dayofweek("l_shipdate")).alias("day"), F.max(F.datediff(F.col("l_shipdate").cast("date"), F.lit("2000-01-01").cast("date"))).alias("days")))
op("math_fns", "SELECT p_partkey, floor(ln(p_partkey + 1) / ln(1.01) + 1e-9)::BIGINT AS bucket, p_partkey % 12 AS x, ceil(log2(p_partkey + 1))::BIGINT AS l, greatest(p_size, 10) AS g FROM part")(
    lambda s, d: T(s, d, "part").select("p_partkey", F.floor(F.log(F.col("p_partkey") + 1) / F.log(F.lit(1.01)) + 1e-9).alias("bucket"), F.pmod("p_partkey", F.lit(12)).alias("x"), F.ceil(F.log2(F.col("p_partkey") + 1)).alias("l"), F.greatest("p_size", F.lit(10)).alias("g")))
op("array_fns", "WITH l AS (SELECT l_orderkey AS v, list_sort(list(DISTINCT l_partkey)) AS n FROM lineitem GROUP BY 1) SELECT v, len(n) AS k, array_to_string(n[1:3], ',') AS head, list_sum(list_transform(n, lambda x: x * 2))::BIGINT AS doubled, len(list_filter(n, lambda x: x % 2 = 0)) AS evens FROM l")(
    lambda s, d: T(s, d, "lineitem").groupBy(F.col("l_orderkey").alias("v")).agg(F.array_sort(F.collect_set("l_partkey")).alias("n")).select("v", F.size("n").alias("k"), F.array_join(F.slice("n", 1, 3).cast("array<string>"), ",").alias("head"), F.aggregate(F.transform("n", lambda x: x * 2), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("doubled"), F.size(F.filter("n", lambda x: x % 2 == 0)).alias("evens")))
op("map_fns", "SELECT l_orderkey AS v, count(*) AS pairs, max(q) AS top FROM (SELECT l_orderkey, l_partkey, sum(l_quantity) AS q FROM lineitem GROUP BY ALL) GROUP BY 1")(
    lambda s, d: T(s, d, "lineitem").groupBy("l_orderkey", "l_partkey").agg(F.sum("l_quantity").alias("q")).groupBy(F.col("l_orderkey").alias("v")).agg(F.map_from_entries(F.collect_list(F.struct("l_partkey", "q"))).alias("m")).select("v", F.size("m").cast("bigint").alias("pairs"), F.array_max(F.map_values("m")).alias("top")))
op("json_fns", "SELECT user_id AS v, (props::JSON ->> '$.k')::BIGINT AS item FROM events")(lambda s, d: rel.json_edges(T(s, d, "events"), "user_id", "props", "$.k"))
op("bits_hash", f"SELECT c_custkey, {prio_sql(7, 'c_custkey')} AS p, xor(c_custkey, 255) AS x, bit_count(c_custkey) AS ones FROM customer")(lambda s, d: T(s, d, "customer").select("c_custkey", prio(7, "c_custkey").alias("p"), F.col("c_custkey").bitwiseXOR(255).alias("x"), F.bit_count("c_custkey").alias("ones")))


@op("recursive_sql", "WITH RECURSIVE a AS (SELECT DISTINCT user_id AS src, lead(user_id) OVER (PARTITION BY ts::DATE ORDER BY ts, event_id) AS dst FROM events WHERE value > 200), r(v, d) AS (SELECT (SELECT min(src) FROM a), 0 UNION SELECT dst, d + 1 FROM r JOIN a ON src = v WHERE d < 8 AND dst IS NOT NULL) SELECT v, min(d) AS dist FROM r GROUP BY v")
def recursive_sql(spark: S, sf_dir: str) -> DataFrame:
    T(spark, sf_dir, "events").createOrReplaceTempView("recursive_events")
    return spark.sql("""WITH RECURSIVE a AS (SELECT DISTINCT user_id AS src, lead(user_id) OVER (PARTITION BY to_date(ts) ORDER BY ts, event_id) AS dst FROM recursive_events WHERE value > 200),
        r(v, d) AS (SELECT min(src), 0 FROM a UNION ALL SELECT DISTINCT dst, d + 1 FROM r JOIN a ON src = v WHERE d < 8 AND dst IS NOT NULL) SELECT v, min(d) AS dist FROM r GROUP BY v""")


@op("recursive_sql_whole", f"""WITH RECURSIVE {arcs('event_succession')}, r(v, d) USING KEY (v) AS (
  SELECT min(src), 0::BIGINT FROM e UNION
  SELECT e.dst, min(r.d) + 1 FROM r JOIN e ON r.v = e.src WHERE NOT EXISTS (SELECT 1 FROM recurring.r k WHERE k.v = e.dst) GROUP BY e.dst)
SELECT v, d AS dist FROM r WHERE v IS NOT NULL""")
def recursive_sql_whole(spark: S, sf_dir: str) -> DataFrame:
    return rel.recursive_reach(catalog.load(spark, sf_dir, "event_succession").edges)


# graph primitives

@op("prefix_cut", "SELECT true AS holds")
def cut(spark: S, sf_dir: str) -> DataFrame:
    df = T(spark, sf_dir, "lineitem").select(F.col("l_quantity").cast("bigint").alias("w"))
    n = df.count()
    part, at = prefix_cut(df, "w", n // 3, n)
    return part.agg((F.count(F.lit(1)) >= n // 3).alias("enough"), (F.max("w") <= at).alias("below")).select((F.col("enough") & F.col("below")).alias("holds"))


op("pointer_jump", "SELECT n_nationkey * 4 + 1 AS v, n_regionkey * 4 AS p FROM nation UNION ALL SELECT r_regionkey * 4, r_regionkey * 4 FROM region UNION ALL SELECT c_custkey * 4 + 2, n_regionkey * 4 FROM customer JOIN nation ON c_nationkey = n_nationkey UNION ALL SELECT s_suppkey * 4 + 3, n_regionkey * 4 FROM supplier JOIN nation ON s_nationkey = n_nationkey")(
    lambda s, d: pointer_jump(_geo(s, d).select("v", F.coalesce("parent", "v").alias("p"))))


def _geo(s: S, d: str) -> DataFrame:
    """(v, parent, level) of the region, nation, customer and supplier trees."""
    up, _ = catalog._arcs(s, d, "geo_tree")
    top = T(s, d, "region").select((F.col("r_regionkey") * 4).cast("bigint").alias("v"), F.lit(None).cast("bigint").alias("parent"), F.lit(0).alias("level"))
    return up.select(F.col("src").alias("v"), F.col("dst").alias("parent"), F.when(F.col("src") % 4 == 1, 1).otherwise(2).alias("level")).unionByName(top)


op("contract", "WITH x AS (SELECT DISTINCT least(a.c_nationkey, b.s_nationkey) AS p, greatest(a.c_nationkey, b.s_nationkey) AS q FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer a ON c_custkey = o_custkey JOIN supplier b ON s_suppkey = l_suppkey WHERE a.c_nationkey <> b.s_nationkey) SELECT p::BIGINT AS src, q::BIGINT AS dst FROM x UNION SELECT q, p FROM x")(
    lambda s, d: contract(catalog.load(s, d, "cust_supp").edges, T(s, d, "customer").select((2 * F.col("c_custkey")).alias("v"), F.col("c_nationkey").cast("bigint").alias("label")).unionByName(T(s, d, "supplier").select((2 * F.col("s_suppkey") + 1).alias("v"), F.col("s_nationkey").cast("bigint").alias("label")))))
op("rootfix", "SELECT n_nationkey * 4 + 1 AS v, 1 AS depth FROM nation UNION ALL SELECT r_regionkey * 4, 0 FROM region UNION ALL SELECT c_custkey * 4 + 2, 2 FROM customer UNION ALL SELECT s_suppkey * 4 + 3, 2 FROM supplier")(lambda s, d: forest.rootfix(_geo(s, d), "depth", F.col("above") + 1, F.lit(0)))
op("leaffix", "WITH c AS (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1), t AS (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1), z AS (SELECT n_nationkey, n_regionkey, 1 + coalesce(c.n, 0) + coalesce(t.n, 0) AS size FROM nation LEFT JOIN c ON c.k = n_nationkey LEFT JOIN t ON t.k = n_nationkey) SELECT n_nationkey * 4 + 1 AS v, size FROM z UNION ALL SELECT r_regionkey * 4, 1 + coalesce(sum(size), 0)::BIGINT FROM region LEFT JOIN z ON n_regionkey = r_regionkey GROUP BY r_regionkey UNION ALL SELECT c_custkey * 4 + 2, 1 FROM customer UNION ALL SELECT s_suppkey * 4 + 3, 1 FROM supplier")(
    lambda s, d: forest.leaffix(_geo(s, d).withColumn("size", F.lit(1).cast("bigint")), "size"))

# neighbour lists

op("blocks_roundtrip", f"WITH {arcs('part_supp')} SELECT src, dst FROM e")(on("part_supp", lambda g: blocks.decode_blocks(blocks.encode_blocks(g.edges))))
op("nbr_map_reduce", f"WITH {arcs('part_supp')} SELECT src, sum(dst * 2)::BIGINT AS value FROM e GROUP BY src")(on("part_supp", lambda g: blocks.nbr_map_reduce(blocks.encode_blocks(g.edges), lambda x: x * 2, F.lit(0).cast("bigint"), lambda a, x: a + x)))
op("nbr_map", f"WITH {arcs('part_supp')} SELECT src, dst + 1 AS x FROM e")(on("part_supp", lambda g: blocks.nbr_map(blocks.encode_blocks(g.edges), lambda x: x + 1).select("src", F.explode("mapped").alias("x"))))
op("nbr_filter", f"WITH {arcs('part_supp')} SELECT src, dst FROM e WHERE dst % 3 = 0")(on("part_supp", lambda g: blocks.nbr_filter(blocks.encode_blocks(g.edges), lambda x: x % 3 == 0).select("src", F.explode("nbrs").alias("dst"))))
op("nbr_pack", f"WITH {arcs('part_supp')}, k AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS i FROM e WHERE dst % 3 = 0) SELECT src, (i // 64)::INT AS block_no, min(dst) AS first, max(dst) AS last, count(*) AS n FROM k GROUP BY ALL")(
    on("part_supp", lambda g: blocks.nbr_pack(blocks.encode_blocks(g.edges), lambda x: x % 3 == 0).select("src", "block_no", "first", "last", F.size("deltas").cast("bigint").alias("n"))))
op("nbr_intersect", f"WITH {arcs('event_succession_sym')} SELECT p.src, p.dst, count(b.dst) AS common FROM (SELECT src, dst FROM e WHERE src < dst) p LEFT JOIN e a ON a.src = p.src LEFT JOIN e b ON b.src = p.dst AND b.dst = a.dst GROUP BY ALL")(
    on("event_succession_sym", lambda g: blocks.nbr_intersect_count(blocks.encode_blocks(g.edges), g.half())))

# streams: replays of the events table

_ev = lambda s, d, by="ts": live.event_source(s, live.replayable(s, d, by))
HOURS = "(SELECT unnest(range(0, {n})) AS i), events"
op("stream_tumbling", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, user_id, count(*) AS n FROM events GROUP BY ALL")(lambda s, d: live.run(live.windows(_ev(s, d), "tumbling"), "complete").select("start", "user_id", "n"))
op("stream_sliding", "SELECT time_bucket(INTERVAL 15 MINUTE, ts) - i * INTERVAL 15 MINUTE AS start, user_id, count(*) AS n FROM events, range(4) t(i) GROUP BY ALL")(lambda s, d: live.run(live.windows(_ev(s, d), "sliding"), "complete").select("start", "user_id", "n"))
op("stream_session", "WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), k AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM g) SELECT min(ts) AS start, user_id, count(*) AS n FROM k GROUP BY user_id, session")(
    lambda s, d: live.run(live.windows(_ev(s, d), "session"), "complete").select("start", "user_id", "n"))
op("stream_dedup", "SELECT event_id, user_id FROM events")(lambda s, d: live.run(live.dedup(_ev(s, d).withColumn("twice", F.explode(F.array(F.lit(1), F.lit(2))))).select("event_id", "user_id")))
op("stream_join_stream", CLICKS.replace("AS a_id", "AS click_id").replace("AS b_id", "AS purchase_id"))(lambda s, d: live.run(live.click_to_purchase(_ev(s, d))))
op("stream_join_static", "SELECT event_id, user_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")(lambda s, d: live.run(live.with_customers(_ev(s, d), T(s, d, "customer"))))
op("stream_stateful_succession", "SELECT user_id, src, event_id AS dst FROM (SELECT user_id, event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS src FROM events) WHERE src IS NOT NULL")(lambda s, d: live.run(live.succession(_ev(s, d))))
op("stream_cc", "SELECT count(*) AS vertices, 1::BIGINT AS components FROM (SELECT DISTINCT 2 * user_id AS v FROM events UNION SELECT DISTINCT 2 * (event_id % 7) + 1 FROM events)")(
    lambda s, d: live.live_components(_ev(s, d).select((2 * F.col("user_id")).alias("src"), (2 * (F.col("event_id") % 7) + 1).alias("dst"))).agg(F.count(F.lit(1)).alias("vertices"), F.countDistinct("label").alias("components")))


@op("stream_watermark_late", "SELECT true AS dropped")
def watermark_late(spark: S, sf_dir: str) -> DataFrame:
    """Rows of the first day come in again at the end: they are past the watermark and change no window."""
    path = live.replayable(spark, sf_dir)
    events = spark.read.parquet(path)
    events.where(F.to_date("ts") == events.agg(F.min(F.to_date("ts")).alias("d")).first().d).coalesce(1).write.mode("append").parquet(path)
    got = live.run(live.windows(live.event_source(spark, path), "tumbling"), "append")
    want = events.groupBy(F.window("ts", "1 hour").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")
    return got.select("start", "user_id", "n").exceptAll(want).agg((F.count(F.lit(1)) == 0).alias("dropped"))


# functions in Python, over Arrow

@op("udf_arrow", "SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(list_transform(a.embedding, lambda x: x::DOUBLE), list_transform(b.embedding, lambda x: x::DOUBLE)), 6) AS cosine FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def udf_arrow(spark: S, sf_dir: str) -> DataFrame:
    import numpy as np

    @F.pandas_udf("double")
    def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
        x, y = np.stack(a.to_numpy()).astype(float), np.stack(b.to_numpy()).astype(float)
        return pd.Series((x * y).sum(1) / np.linalg.norm(x, axis=1) / np.linalg.norm(y, axis=1))

    e = T(spark, sf_dir, "embeddings")
    both = e.select(F.col("vec_id").alias("a"), F.col("embedding").alias("x")).join(e.select((F.col("vec_id") - 1).alias("a"), F.col("vec_id").alias("b"), F.col("embedding").alias("y")), "a")
    return both.select("a", "b", F.round(cosine("x", "y"), 6).alias("cosine"))


@op("udf_grouped", "SELECT s_suppkey, s_nationkey, round(coalesce((s_acctbal - avg(s_acctbal) OVER w) / nullif(stddev_pop(s_acctbal) OVER w, 0), 0), 6) AS score FROM supplier WINDOW w AS (PARTITION BY s_nationkey)")
def udf_grouped(spark: S, sf_dir: str) -> DataFrame:
    """Standard scores within a nation, a group of suppliers a call: for groups that are known to be small."""

    def scores(group: pd.DataFrame) -> pd.DataFrame:
        spread = group.s_acctbal.std(ddof=0)
        return group[["s_suppkey", "s_nationkey"]].assign(score=((group.s_acctbal - group.s_acctbal.mean()) / spread).round(6) if spread else 0.0)

    return T(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal").groupBy("s_nationkey").applyInPandas(scores, "s_suppkey bigint, s_nationkey int, score double")


@op("udaf_pandas", "SELECT c_nationkey, round((2 * sum(i * x) / (count(*) * sum(x)) - (count(*) + 1) / count(*)), 6) AS gini FROM (SELECT c_nationkey, c_custkey + 1 AS x, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS i FROM customer) GROUP BY c_nationkey")
def udaf_pandas(spark: S, sf_dir: str) -> DataFrame:
    @F.pandas_udf("double")
    def gini(x: pd.Series) -> float:
        x = x.sort_values().to_numpy(float)
        n = len(x)
        return float(2 * ((pd.RangeIndex(1, n + 1).to_numpy() * x).sum()) / (n * x.sum()) - (n + 1) / n)

    return T(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.round(gini(F.col("c_custkey") + 1), 6).alias("gini"))


@op("udtf", catalog.SQL["torus"])
def udtf(spark: S, sf_dir: str) -> DataFrame:
    """Arcs of the torus over the part keys: a table function is called for each part."""
    @F.udtf(returnType="dst bigint")
    class Successors:
        def eval(self, at: int, side: int):
            x, y, z = at % side, at // side % side, at // side**2
            yield (x + 1) % side + y * side + z * side**2,
            yield x + (y + 1) % side * side + z * side**2,
            yield x + y * side + (z + 1) % side * side**2,

    parts = T(spark, sf_dir, "part").select(F.col("p_partkey").cast("bigint").alias("src"))
    side = catalog.torus_side(parts.count())
    return parts.where(F.col("src") < side**3).lateralJoin(Successors(F.col("src").outer(), F.lit(side))).select("src", "dst")


def edge_list_equals_blocks(g: Graph) -> DataFrame:
    """The same graph once more through its blocked adjacency."""
    return Graph(g.vertices, blocks.decode_blocks(blocks.encode_blocks(g.edges)), g.directed, g.name).edges
