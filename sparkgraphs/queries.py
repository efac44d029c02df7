"""Registered graph queries: each with the SQL that recomputes it from the tables, where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .algo import ball, bfs, biconnectivity, connectivity, covering, msf, ranking, relax, scc, substructure
from .check import certificates as cert
from .core.closing import lists, lists_of_cliques
from .core.priority import prio_sql
from .core.rounds import Rounds, RunStats
from .measure import measures
from .model import catalog
from .model.graph import Graph, from_arcs

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def on(graph: str, f: Callable[[Graph], DataFrame], *, weights: bool = False) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = catalog.load(spark, sf_dir, graph)
        return f((g.with_weights() if weights else g).layout())

    return run


def on_lists(graph: str, f: Callable[[DataFrame], DataFrame]) -> Query:
    """`f` of the packed neighbour lists, made of the arcs as they come: simple arcs are not written before, and what arcs were made of is deleted."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rounds = Rounds(spark, "baskets")
        packed = lists_of_cliques(*catalog.cliques(spark, sf_dir, graph, rounds)) if graph in catalog.CLIQUES else lists(*catalog.both_ways(spark, sf_dir, graph, rounds))
        rounds.delete(rounds.root)
        return f(packed)

    return run


def source(g: Graph) -> int:
    return g.vertices.agg(F.min("v").alias("m")).first().m


def rounded(df: DataFrame, column: str, places: int = 9) -> DataFrame:
    return df.withColumn(column, F.round(column, places))


# --- SQL forms -----------------------------------------------------------------------------------------------------------------

W = f"""n AS (SELECT greatest(1, ceil(ln(count(*)))::BIGINT - 1) AS spread FROM v),
ew AS MATERIALIZED (SELECT src, dst, 1 + {prio_sql(42, "least(src, dst) || '-' || greatest(src, dst)")} % spread AS w FROM e, n)"""


def bfs_sql(graph: str) -> str:
    return f"""WITH RECURSIVE {catalog.sql_arcs(graph)},
r(v, d) USING KEY (v) AS (
  SELECT min(v), 0::BIGINT FROM v UNION
  SELECT e.dst, min(r.d) + 1 FROM r JOIN e ON r.v = e.src WHERE NOT EXISTS (SELECT 1 FROM recurring.r k WHERE k.v = e.dst) GROUP BY e.dst)
SELECT v.v, r.d AS dist FROM v LEFT JOIN r ON r.v = v.v"""


def relax_sql(graph: str, start: str, extend: str, agg: str, worse: str, out: str) -> str:
    return f"""WITH RECURSIVE {catalog.sql_arcs(graph)}, {W},
r(v, d) USING KEY (v) AS (
  SELECT min(v), {start} FROM v UNION
  SELECT * FROM (SELECT ew.dst AS v, {agg}({extend}) AS d FROM r JOIN ew ON ew.src = r.v GROUP BY ew.dst) c
  WHERE NOT EXISTS (SELECT 1 FROM recurring.r k WHERE k.v = c.v AND k.d {worse} c.d))
SELECT v.v, r.d AS {out} FROM v LEFT JOIN r ON r.v = v.v"""


def dist_sql(graph: str) -> str:
    return relax_sql(graph, "0::BIGINT", "r.d + ew.w", "min", "<=", "dist")


def label_cte(name: str = "cc", edges: str = "e") -> str:
    return f"""{name}(v, label) USING KEY (v) AS (
  SELECT v, v FROM v UNION
  SELECT * FROM (SELECT {edges}.dst AS v, min({name}.label) AS label FROM {name} JOIN {edges} ON {edges}.src = {name}.v GROUP BY {edges}.dst) c
  WHERE EXISTS (SELECT 1 FROM recurring.{name} k WHERE k.v = c.v AND k.label > c.label))"""


def cc_sql(graph: str) -> str:
    return f"WITH RECURSIVE {catalog.sql_arcs(graph)}, {label_cte()} SELECT v, label FROM cc"


def core_sql(graph: str) -> str:
    return f"""WITH RECURSIVE {catalog.sql_arcs(graph)},
r(v, h) USING KEY (v) AS (
  SELECT src, count(*) FROM e GROUP BY src UNION
  SELECT c.v, c.h FROM (
    SELECT v, max(least(n, h)) AS h FROM (
      SELECT e.src AS v, k.h, row_number() OVER (PARTITION BY e.src ORDER BY k.h DESC) AS n FROM e JOIN recurring.r k ON k.v = e.dst) x GROUP BY v) c
  JOIN recurring.r o ON o.v = c.v WHERE c.h < o.h AND EXISTS (SELECT 1 FROM r))"""


BETWEEN = """d(s, v, l, g) AS (
  SELECT v, v, 0, 1.0::DOUBLE FROM v UNION ALL
  SELECT s, w, l, g FROM (SELECT d.s, e.dst AS w, d.l + 1 AS l, sum(d.g) AS g FROM d JOIN e ON e.src = d.v JOIN dist ON dist.s = d.s AND dist.v = e.dst AND dist.l = d.l + 1 GROUP BY ALL) x),
dist(s, v, l) USING KEY (s, v) AS (
  SELECT v, v, 0 FROM v UNION
  SELECT dist.s, e.dst, min(dist.l) + 1 FROM dist JOIN e ON e.src = dist.v WHERE NOT EXISTS (SELECT 1 FROM recurring.dist k WHERE k.s = dist.s AND k.v = e.dst) GROUP BY dist.s, e.dst)"""


def between_sql(graph: str) -> str:
    parts = BETWEEN.split("dist(s, v, l) USING")
    return f"""WITH RECURSIVE {catalog.sql_arcs(graph)},
dist(s, v, l) USING{parts[1]},
{parts[0].rstrip().rstrip(",")},
o AS (SELECT min(v) AS o FROM v),
f AS (SELECT d.* FROM d, o WHERE d.s = o.o)
SELECT v.v, round(coalesce(x.score, 0), 6) AS score FROM v LEFT JOIN (
  SELECT a.v, sum(a.g * b.g / t.g) AS score FROM f a JOIN d b ON b.s = a.v JOIN f t ON t.v = b.v AND t.l = a.l + b.l, o
  WHERE b.v <> a.v AND a.v <> o.o GROUP BY a.v) x ON x.v = v.v"""


PAGERANK_SQL = """WITH RECURSIVE {arcs}, deg AS (SELECT src AS v, count(*) AS k FROM e GROUP BY src), n AS (SELECT count(*) AS n FROM v),
p(i, v, r) AS (
  SELECT 0, v, 1.0::DOUBLE / n FROM v, n UNION ALL
  SELECT i + 1, v, 0.15 / n + 0.85 * coalesce(got, 0) FROM (
    SELECT p.i, e.dst AS v, sum(p.r / deg.k) AS got FROM p JOIN deg ON deg.v = p.v JOIN e ON e.src = p.v WHERE p.i < {times} GROUP BY ALL) x, n)
SELECT v, round(r, 9) AS rank FROM p WHERE i = {times}"""

TRIANGLES_SQL = "SELECT a.src AS a, a.dst AS b, b.dst AS c FROM e a JOIN e b ON a.dst = b.src AND a.src < a.dst AND b.src < b.dst JOIN e c ON c.src = a.src AND c.dst = b.dst"

MIS_SQL = f"""WITH RECURSIVE {{arcs}}, pr AS (SELECT v, {prio_sql(42, 'v')} AS p FROM v),
dag AS MATERIALIZED (SELECT e.src, e.dst FROM e JOIN pr a ON a.v = e.src JOIN pr b ON b.v = e.dst WHERE (a.p, a.v) < (b.p, b.v)),
r(v, st) USING KEY (v) AS (
  SELECT v, 0 FROM v UNION
  SELECT x.v, CASE WHEN hit > 0 THEN 2 ELSE 1 END FROM (
    SELECT v.v, count(k1.v) AS hit, count(dag.src) - count(k1.v) - count(k2.v) AS open FROM v LEFT JOIN dag ON dag.dst = v.v
    LEFT JOIN (SELECT v FROM recurring.r WHERE st = 1) k1 ON k1.v = dag.src LEFT JOIN (SELECT v FROM recurring.r WHERE st = 2) k2 ON k2.v = dag.src GROUP BY v.v) x
  JOIN recurring.r o ON o.v = x.v AND o.st = 0 WHERE (hit > 0 OR open = 0) AND EXISTS (SELECT 1 FROM r))
SELECT v FROM r WHERE st = 1"""

MATCHING_SQL = f"""WITH RECURSIVE {{arcs}},
h AS MATERIALIZED (SELECT row_number() OVER (ORDER BY p, src, dst) AS i, src, dst FROM (SELECT src, dst, {prio_sql(42, "src || '-' || dst")} AS p FROM e WHERE src < dst)),
adj AS MATERIALIZED (SELECT DISTINCT a.i AS i, b.i AS j FROM h a JOIN h b ON (a.src = b.src OR a.dst = b.dst OR a.src = b.dst OR a.dst = b.src) AND b.i < a.i),
r(i, st) USING KEY (i) AS (
  SELECT i, 0 FROM h UNION
  SELECT x.i, CASE WHEN hit > 0 THEN 2 ELSE 1 END FROM (
    SELECT h.i, count(k1.i) AS hit, count(adj.j) - count(k1.i) - count(k2.i) AS open FROM h LEFT JOIN adj ON adj.i = h.i
    LEFT JOIN (SELECT i FROM recurring.r WHERE st = 1) k1 ON k1.i = adj.j LEFT JOIN (SELECT i FROM recurring.r WHERE st = 2) k2 ON k2.i = adj.j GROUP BY h.i) x
  JOIN recurring.r o ON o.i = x.i AND o.st = 0 WHERE (hit > 0 OR open = 0) AND EXISTS (SELECT 1 FROM r))
SELECT src, dst FROM h JOIN r USING (i) WHERE st = 1"""

COLOR_SQL = f"""WITH RECURSIVE {{arcs}},
pr AS (SELECT v, -ceil(log2(greatest(k, 1))) AS k, {prio_sql(42, 'v')} AS p FROM (SELECT v.v, count(e.src) AS k FROM v LEFT JOIN e ON e.src = v.v GROUP BY v.v)),
dag AS MATERIALIZED (SELECT e.src, e.dst FROM e JOIN pr a ON a.v = e.src JOIN pr b ON b.v = e.dst WHERE (a.k, a.p, a.v) < (b.k, b.p, b.v)),
r(v, c) USING KEY (v) AS (
  SELECT v, -1::BIGINT FROM v UNION
  SELECT x.v, list_min(list_filter(range(0, len(x.used) + 1), lambda y: NOT list_contains(x.used, y))) FROM (
    SELECT v.v, coalesce(list(DISTINCT k.c) FILTER (WHERE k.c >= 0), []) AS used, count(dag.src) - count(k.v) AS open FROM v LEFT JOIN dag ON dag.dst = v.v
    LEFT JOIN (SELECT v, c FROM recurring.r WHERE c >= 0) k ON k.v = dag.src GROUP BY v.v) x
  JOIN recurring.r o ON o.v = x.v AND o.c = -1 WHERE open = 0 AND EXISTS (SELECT 1 FROM r))
SELECT v, c AS color FROM r"""

MSF_SQL = f"""WITH RECURSIVE {{arcs}}, {W},
h AS MATERIALIZED (SELECT row_number() OVER (ORDER BY w, src, dst) AS i, src, dst, w FROM ew WHERE src < dst),
b AS MATERIALIZED (SELECT src, dst, i FROM h UNION ALL SELECT dst, src, i FROM h),
r(s, v, i) USING KEY (s, v) AS (
  SELECT v, v, 0::BIGINT FROM v UNION
  SELECT * FROM (SELECT r.s, b.dst AS v, min(greatest(r.i, b.i)) AS i FROM r JOIN b ON b.src = r.v GROUP BY r.s, b.dst) c
  WHERE NOT EXISTS (SELECT 1 FROM recurring.r k WHERE k.s = c.s AND k.v = c.v AND k.i <= c.i))
SELECT h.src, h.dst, h.w FROM h JOIN r ON r.s = h.src AND r.v = h.dst WHERE r.i = h.i"""

SCC_SQL = """WITH RECURSIVE {arcs}, t(s, v) AS (SELECT v, v FROM v UNION SELECT t.s, e.dst FROM t JOIN e ON e.src = t.v)
SELECT a.s AS v, min(a.v) AS label FROM t a JOIN t b ON b.s = a.v AND b.v = a.s GROUP BY a.s"""

BALL_SQL = f"""WITH RECURSIVE {{arcs}}, dq AS (SELECT v, floor(-ln(({prio_sql(42, 'v')} + 1) / 281474976710656.0) / 0.2 * 1e6)::BIGINT AS q FROM v),
st AS (SELECT v, (max(q) OVER () - q) // 1000000 AS s FROM dq),
r(c, v, l) USING KEY (c, v) AS (
  SELECT v, v, 0::BIGINT FROM v UNION
  SELECT r.c, e.dst, min(r.l) + 1 FROM r JOIN e ON e.src = r.v WHERE NOT EXISTS (SELECT 1 FROM recurring.r k WHERE k.c = r.c AND k.v = e.dst) GROUP BY r.c, e.dst)
SELECT r.v, min((st.s + r.l, r.c))[2] AS center FROM r JOIN st ON st.v = r.c GROUP BY r.v"""
BALL_SQL = BALL_SQL.replace("min((st.s + r.l, r.c))[2]", "arg_min(r.c, (st.s + r.l) * 100000000 + r.c)")

BLOCK_CTES = """h AS MATERIALIZED (SELECT src, dst FROM e WHERE src < dst),
g(x, y, z) AS (
  SELECT a.src, a.dst, a.dst FROM e a UNION
  SELECT g.x, g.y, e.dst FROM g JOIN e ON e.src = g.z WHERE e.dst <> g.x),
same AS MATERIALIZED (
  SELECT DISTINCT least(g.x, g.y) AS a, greatest(g.x, g.y) AS b, least(g.x, n.dst) AS c, greatest(g.x, n.dst) AS d FROM g JOIN e n ON n.src = g.x AND n.dst = g.z),
r(src, dst, ls, ld) USING KEY (src, dst) AS (
  SELECT src, dst, src, dst FROM h UNION
  SELECT * FROM (SELECT same.c AS src, same.d AS dst, min((r.ls, r.ld))[1] AS ls, min((r.ls, r.ld))[2] AS ld FROM r JOIN same ON same.a = r.src AND same.b = r.dst GROUP BY same.c, same.d) q
  WHERE EXISTS (SELECT 1 FROM recurring.r k WHERE k.src = q.src AND k.dst = q.dst AND (k.ls, k.ld) > (q.ls, q.ld)))"""
BLOCK_CTES = BLOCK_CTES.replace("min((r.ls, r.ld))[1]", "min(row(r.ls, r.ld))[1]").replace("min((r.ls, r.ld))[2]", "min(row(r.ls, r.ld))[2]")


def blocks_sql(graph: str, tail: str) -> str:
    return f"WITH RECURSIVE {catalog.sql_arcs(graph)}, {BLOCK_CTES} {tail}"


def densest_sql(graph: str, eps: float) -> str:
    return f"""WITH RECURSIVE {catalog.sql_arcs(graph)},
r(i, v) AS (
  SELECT 1, v FROM v UNION ALL
  SELECT x.i + 1, x.v FROM (
    SELECT a.i, a.v, count(b.v) AS k, sum(count(b.v)) OVER () / 2.0 / count(*) OVER () AS d FROM r a LEFT JOIN e ON e.src = a.v LEFT JOIN r b ON b.v = e.dst GROUP BY a.i, a.v) x
  WHERE k > 2 * (1 + {eps}) * d)
SELECT round(max(m / n), 9) AS density FROM (
  SELECT a.i, count(DISTINCT a.v) AS n, count(b.v) / 2.0 AS m FROM r a LEFT JOIN e ON e.src = a.v LEFT JOIN r b ON b.v = e.dst AND b.i = a.i GROUP BY a.i)"""


def arcs(graph: str) -> str:
    return catalog.sql_arcs(graph)


# --- shortest paths ------------------------------------------------------------------------------------------------------------

for _name, _graph, _mode in (
    ("bfs_cust_supp", "cust_supp", "auto"), ("bfs_part_copurchase", "part_copurchase", "auto"), ("bfs_torus", "torus", "auto"),
    ("bfs_directed_events", "event_succession", "auto"), ("bfs_push", "cust_part", "push"), ("bfs_pull", "cust_part", "pull"), ("bfs_blocked", "cust_part", "blocked"),
):
    query(_name, bfs_sql(_graph))(on(_graph, lambda g, m=_mode: bfs.bfs(g, source(g), mode=m)))

query("bfs_parents_valid", "SELECT 0::BIGINT AS violations")(on("cust_supp", lambda g: cert.bfs_parents(g, bfs.bfs(g, source(g), with_parent=True))))
query("wbfs_cust_supp", dist_sql("cust_supp"))(on("cust_supp", lambda g: relax.weighted_bfs(g, source(g)), weights=True))
query("wbfs_unblocked", dist_sql("part_supp"))(on("part_supp", lambda g: relax.weighted_bfs(g, source(g), mode="push"), weights=True))
query("wbfs_delta_step", dist_sql("cust_supp"))(on("cust_supp", lambda g: relax.delta_stepping(g, source(g), 3), weights=True))
query("bellman_ford_blocked", dist_sql("cust_part"))(on("cust_part", lambda g: relax.bellman_ford(g, source(g)), weights=True))
query("bellman_ford_unblocked", dist_sql("torus"))(on("torus", lambda g: relax.bellman_ford(g, source(g), mode="push"), weights=True))


@query(
    "bellman_ford_real",
    f"""WITH RECURSIVE a AS (SELECT 2 * o_custkey AS src, 2 * l_suppkey + 1 AS dst, min((l_extendedprice * 100)::BIGINT / 100.0) AS w FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL),
ew AS MATERIALIZED (SELECT src, dst, w::DOUBLE AS w FROM a UNION ALL SELECT dst, src, w FROM a), v AS (SELECT DISTINCT src AS v FROM ew),
{relax_sql("cust_supp", "0::DOUBLE", "r.d + ew.w", "min", "<=", "dist").split("spread AS w FROM e, n),")[1].replace("SELECT v.v, r.d AS dist", "SELECT v.v, round(r.d, 4) AS dist")}""",
)
def bellman_ford_real(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = catalog.read(spark, sf_dir, "orders").join(catalog.read(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    g = from_arcs(line.select((2 * F.col("o_custkey")).alias("src"), (2 * F.col("l_suppkey") + 1).alias("dst"), (F.round(F.col("l_extendedprice") * 100).cast("bigint") / 100.0).cast("double").alias("w"))).layout()
    return rounded(relax.bellman_ford(g, source(g)), "dist", 4)


@query("bellman_ford_negative_cycle", "SELECT n_nationkey::BIGINT AS v, '-inf'::DOUBLE AS dist FROM nation")
def bellman_ford_negative_cycle(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A ring of all nations with arcs of weight -1: every vertex gets -Infinity."""
    n = catalog.read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("bigint").alias("src"))
    ring = n.select("src", ((F.col("src") + 1) % n.count()).alias("dst"), F.lit(-1).cast("bigint").alias("w"))
    g = from_arcs(ring, directed=True).layout()
    return relax.bellman_ford(g, source(g))


WIDEST = relax_sql("cust_supp", "9223372036854775807::BIGINT", "least(r.d, ew.w)", "max", ">=", "width")
query("widest_semiring", WIDEST)(on("cust_supp", lambda g: relax.widest_path(g, source(g)), weights=True))
query("widest_bucket", WIDEST)(on("cust_supp", lambda g: relax.widest_path(g, source(g), method="bucket"), weights=True))
query("betweenness_events_sym", between_sql("event_succession_sym"))(on("event_succession_sym", lambda g: rounded(bfs.betweenness(g, source(g)), "score", 6)))
#: On a graph without weights the scores add up to the inner vertices of a shortest path to each vertex.
query("betweenness_torus", f"SELECT count(*) AS vertices, sum(CASE WHEN dist > 0 THEN dist - 1 ELSE 0 END)::BIGINT AS inner_vertices FROM ({bfs_sql('torus')})")(
    on("torus", lambda g: bfs.betweenness(g, source(g), fits=bfs.FITS).agg(F.count(F.lit(1)).alias("vertices"), F.round(F.sum("score")).cast("bigint").alias("inner_vertices")))
)
query("betweenness_directed", between_sql("event_succession"))(on("event_succession", lambda g: rounded(bfs.betweenness(g, source(g), exact_paths=True), "score", 6)))

# --- decompositions, connectivity ----------------------------------------------------------------------------------------------

query("ball_decompose_centers", BALL_SQL.format(arcs=arcs("cust_part_urgent")))(on("cust_part_urgent", lambda g: ball.ball_decompose(g).select("v", "center")))
query("ball_decompose_quality", "SELECT true AS centers_own, true AS connected, true AS within_bounds")(on("cust_part_urgent", lambda g: cert.ball_quality(g, ball.ball_decompose(g), 0.2)))
query("ball_decompose_fractional", "SELECT true AS centers_own, true AS connected, true AS within_bounds")(on("order_part_h1", lambda g: cert.ball_quality(g, ball.ball_decompose(g, ties="fractional"), 0.2)))
for _k in (4, 8):
    query(f"spanner_k{_k}_quality", "SELECT 0::BIGINT AS foreign_edges, true AS spans, true AS within_stretch")(on("torus", lambda g, k=_k: cert.spanner(g, ball.spanner(g, k), k)))
query("spanner_boundary_quality", "SELECT 0::BIGINT AS foreign_edges, true AS spans, true AS within_stretch")(on("torus", lambda g: cert.spanner(g, ball.spanner(g, 4, inter="boundary_vertex"), 4)))
for _name, _graph, _method in (
    ("cc_contract", "order_part_h1", "contract"), ("cc_label_prop", "conversation_chain", "label_prop"), ("cc_hook_jump", "duplicate_docs", "hook_jump"),
    ("cc_alternating", "cust_part_urgent", "alternating"), ("cc_bfs_then_rest", "order_part_h1", "bfs_then_rest"),
):
    query(_name, cc_sql(_graph))(on(_graph, lambda g, m=_method: connectivity.connectivity(g, m)))
query("largest_component", f"WITH RECURSIVE {arcs('order_part_h1')}, {label_cte()}, t AS (SELECT label FROM cc GROUP BY label ORDER BY count(*) DESC, label LIMIT 1) SELECT v FROM cc JOIN t USING (label)")(on("order_part_h1", connectivity.largest_component))
query("spanning_forest_cert", f"WITH RECURSIVE {arcs('order_part_h1')}, {label_cte()} SELECT count(*) - count(DISTINCT label) AS edges, 0::BIGINT AS foreign_edges, count(DISTINCT label) AS components FROM cc")(on("order_part_h1", lambda g: cert.forest(g, connectivity.spanning_forest(g))))
query("bicc_edge_labels", blocks_sql("cust_part_urgent", "SELECT src, dst, ls AS label_src, ld AS label_dst FROM r"))(on("cust_part_urgent", lambda g: biconnectivity.bicc_edge_labels(biconnectivity.biconnectivity(g))))
query("bicc_dfs", blocks_sql("cust_part_urgent", "SELECT src, dst, ls AS label_src, ld AS label_dst FROM r"))(on("cust_part_urgent", biconnectivity.bicc_dfs))
query("articulation_points", blocks_sql("cust_part_urgent", "SELECT v FROM (SELECT DISTINCT unnest([src, dst]) AS v, ls, ld FROM r) GROUP BY v HAVING count(*) > 1"))(on("cust_part_urgent", lambda g: biconnectivity.articulation_points(biconnectivity.biconnectivity(g))))
query("bridges", f"WITH {arcs('geo_tree')} SELECT src, dst FROM e WHERE src < dst")(on("geo_tree", lambda g: biconnectivity.bridges(biconnectivity.biconnectivity(g))))
for _name, _f in (("scc_hot_events", scc.scc), ("scc_fwbw_trim", scc.scc_fwbw_trim), ("scc_staged", scc.scc_staged), ("scc_no_trim", lambda g: scc.scc(g, trim=False, first_pivot=False, beta_growth=2.0))):
    query(_name, SCC_SQL.format(arcs=arcs("event_hot_succession")))(on("event_hot_succession", _f))
query("scc_page_links", f"WITH {arcs('page_links')} SELECT v, v AS label FROM v")(on("page_links", scc.scc))
query("largest_scc", f"WITH s AS ({SCC_SQL.format(arcs=arcs('event_succession'))}), t AS (SELECT label FROM s GROUP BY label ORDER BY count(*) DESC LIMIT 1) SELECT v FROM s JOIN t USING (label)")(on("event_succession", scc.largest_scc))

# --- forests and covers --------------------------------------------------------------------------------------------------------

query("msf_edges", MSF_SQL.format(arcs=arcs("event_hot_succession_sym")))(on("event_hot_succession_sym", msf.msf, weights=True))
query("msf_boruvka", MSF_SQL.format(arcs=arcs("cust_part_urgent")))(on("cust_part_urgent", lambda g: msf.msf(g, method="boruvka"), weights=True))
query("msf_kruskal", MSF_SQL.format(arcs=arcs("cust_part_urgent")))(on("cust_part_urgent", lambda g: msf.msf(g, method="kruskal"), weights=True))
query("msf_weight", f"SELECT count(*) AS edges, sum(w)::BIGINT AS weight FROM ({MSF_SQL.format(arcs=arcs('user_item'))})")(on("user_item", lambda g: msf.forest_weight(msf.msf(g)), weights=True))
query("mis_rootset", MIS_SQL.format(arcs=arcs("event_succession_sym")))(on("event_succession_sym", covering.mis))
query("mis_prefix", MIS_SQL.format(arcs=arcs("torus")))(on("torus", lambda g: covering.mis(g, method="prefix")))
query("mis_luby_cert", "SELECT 0::BIGINT AS dependent, 0::BIGINT AS uncovered")(on("torus", lambda g: cert.independent(g, covering.mis(g, method="luby"))))
query("matching_filtered", MATCHING_SQL.format(arcs=arcs("cust_part_urgent")))(on("cust_part_urgent", covering.maximal_matching))
query("matching_prefix_all", MATCHING_SQL.format(arcs=arcs("order_part_h1")))(on("order_part_h1", lambda g: covering.maximal_matching(g, method="prefix_all")))
query("matching_greedy", MATCHING_SQL.format(arcs=arcs("cust_part_urgent")))(on("cust_part_urgent", lambda g: covering.maximal_matching(g, method="plain")))
query("color_llf", COLOR_SQL.format(arcs=arcs("cust_part_urgent")))(on("cust_part_urgent", covering.color))
for _h in ("sll", "lf", "r"):
    query(f"color_{_h}_cert", "SELECT 0::BIGINT AS conflicts, true AS within_bound")(on("torus", lambda g, h=_h: cert.coloring(g, covering.color(g, heuristic=h))))
query("set_cover_cert", "SELECT 0::BIGINT AS uncovered, true AS within_bound")(on("user_item", lambda g: cert.cover(covering.cover_from_graph(g), covering.set_cover(covering.cover_from_graph(g)))))
query("set_cover_order_part", "SELECT 0::BIGINT AS uncovered, true AS within_bound")(on("order_part", lambda g: cert.cover(_sets(g), covering.set_cover(_sets(g), eps=0.1))))
query("set_cover_id_priority", "SELECT 0::BIGINT AS uncovered, true AS within_bound")(on("user_item", lambda g: cert.cover(_sets(g), covering.set_cover(_sets(g), repriority=False, eps=0.1))))


@query("set_cover_rounds")
def set_cover_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(priorities, rounds, sets) of the cover of users by what they bought, with fresh priorities and with ids. Rounds have no SQL."""
    g, out = catalog.load(spark, sf_dir, "user_item").layout(), []
    for fresh in (True, False):
        stats = RunStats()
        sets = covering.set_cover(covering.cover_from_graph(g), eps=0.1, repriority=fresh, stats=stats).count()
        out.append(("fresh" if fresh else "ids", stats.depth, sets))
    return spark.createDataFrame(out, "priorities string, rounds bigint, sets bigint")


def _sets(g: Graph) -> DataFrame:
    return g.edges.where("src % 2 = 0").select(F.col("src").alias("set_id"), F.col("dst").alias("elem_id"))


# --- substructure, ranking, statistics -----------------------------------------------------------------------------------------

query("kcore", core_sql("cust_part_urgent") + " SELECT v, h AS coreness FROM r")(on("cust_part_urgent", substructure.kcore))
query("kcore_hindex", core_sql("cust_supp") + " SELECT v, h AS coreness FROM r")(on("cust_supp", substructure.kcore_hindex))
for _s in ("plain", "heavy_light", "local_first", "raw"):
    query(f"kcore_hist_{_s}", core_sql("user_item") + " SELECT v, h AS coreness FROM r")(on("user_item", lambda g, s=_s: substructure.kcore(g, strategy=s)))
query("kcore_scan", core_sql("duplicate_docs") + " SELECT v, h AS coreness FROM r")(on("duplicate_docs", substructure.kcore_scan))
query("kcore_pow2", f"WITH c AS ({core_sql('user_item')} SELECT v, h FROM r) SELECT count(*) AS vertices, 0::BIGINT AS too_low, 0::BIGINT AS too_high FROM c")(on("user_item", cert.pow2))
query("degeneracy", core_sql("cust_supp") + " SELECT max(h) AS degeneracy FROM r")(on("cust_supp", substructure.degeneracy))
query("peel_rounds", "SELECT 1::BIGINT AS rho")(on("torus", substructure.peeling_complexity))
for _e in (0.001, 0.0):
    query(f"densest_density_{'eps' if _e else 'exact'}", densest_sql("event_succession_sym", _e))(on("event_succession_sym", lambda g, e=_e: g.spark.createDataFrame([(round(substructure.densest_subgraph(g, eps=e)[1], 9),)], "density double")))
query("densest_peel", "SELECT true AS density_holds, true AS within_bounds")(on("user_item", lambda g: cert.dense(g, *substructure.densest_subgraph(g))))
query("densest_degeneracy", "SELECT true AS density_holds, true AS within_bounds")(on("user_item", lambda g: cert.dense(g, *substructure.densest_degeneracy(g))))
for _m in ("oriented_join", "oriented_lists", "undirected"):
    query("triangles" if _m == "oriented_join" else f"triangles_{_m}", f"WITH {arcs('part_copurchase')} SELECT count(*) AS triangles FROM ({TRIANGLES_SQL})")(on_lists("part_copurchase", lambda t, m=_m: substructure.closed_count(t, method=m)))
query("triangles_per_vertex", f"WITH {arcs('part_copurchase')}, t AS ({TRIANGLES_SQL}) SELECT v.v, count(x.v) AS triangles FROM v LEFT JOIN (SELECT unnest([a, b, c]) AS v FROM t) x ON x.v = v.v GROUP BY v.v")(on_lists("part_copurchase", lambda t: substructure.closed_at(t, t)))
query("pagerank_iter1", PAGERANK_SQL.format(arcs=arcs("cust_supp"), times=1))(on("cust_supp", lambda g: rounded(ranking.pagerank_iteration(g), "rank")))
query("pagerank_20", PAGERANK_SQL.format(arcs=arcs("event_succession_sym"), times=20))(on("event_succession_sym", lambda g: rounded(ranking.pagerank(g, eps=0.0, max_iter=20), "rank")))
query("pagerank_converged", PAGERANK_SQL.format(arcs=arcs("event_succession_sym"), times=60).replace("round(r, 9)", "round(r, 8)"))(
    on("event_succession_sym", lambda g: rounded(ranking.pagerank(g, eps=1e-12, max_iter=60), "rank", 8))
)
query("pagerank_push_raw", PAGERANK_SQL.format(arcs=arcs("cust_supp"), times=1))(on("cust_supp", lambda g: rounded(ranking.pagerank_iteration(g, mode="push_raw"), "rank")))
query("pagerank_delta_cert", "SELECT true AS close, true AS mass_kept")(on("event_succession_sym", lambda g: cert.ranks_close(ranking.pagerank(g), ranking.pagerank_delta(g))))
query("pagerank_directed_mass", "SELECT true AS mass_kept")(on("page_links", lambda g: ranking.pagerank(g, dangling="redistribute", max_iter=30).agg((F.abs(F.sum("rank") - 1) < 1e-6).alias("mass_kept"))))

# --- whole-table graphs --------------------------------------------------------------------------------------------------------

#: Queries named above on slices, here on all rows of their tables: graph, method, SQL where it ends in time, whether weighted.
WHOLE: dict[str, tuple] = {
    "kcore": ("cust_supp", substructure.kcore, core_sql("cust_supp") + " SELECT v, h AS coreness FROM r", False),
    "color_llf": ("part_copurchase", lambda g: covering.color(g, method="prefix"), None, False),
    "matching_filtered": ("cust_part", covering.maximal_matching, None, False),
    "matching_greedy": ("cust_part", lambda g: covering.maximal_matching(g, method="plain"), None, False),
    "matching_prefix_all": ("part_copurchase", lambda g: covering.maximal_matching(g, method="prefix_all"), None, False),
    "msf_edges": ("event_succession_sym", msf.msf, MSF_SQL.format(arcs=arcs("event_succession_sym")), True),
    "msf_boruvka": ("cust_part", lambda g: msf.msf(g, method="boruvka"), None, True),
    "msf_kruskal": ("cust_part", lambda g: msf.msf(g, method="kruskal"), None, True),
    "ball_decompose_centers": ("cust_part", lambda g: ball.ball_decompose(g).select("v", "center"), None, False),
    "ball_decompose_quality": ("cust_part", lambda g: cert.ball_quality(g, ball.ball_decompose(g), 0.2), "SELECT true AS centers_own, true AS connected, true AS within_bounds", False),
    "bicc_edge_labels": ("order_part", lambda g: biconnectivity.bicc_edge_labels(biconnectivity.biconnectivity(g)), None, False),
    "bicc_dfs": ("order_part", biconnectivity.bicc_dfs, None, False),
    "articulation_points": ("order_part", lambda g: biconnectivity.articulation_points(biconnectivity.biconnectivity(g)), None, False),
    "scc_hot_events": ("event_succession", scc.scc, SCC_SQL.format(arcs=arcs("event_succession")), False),
    "scc_fwbw_trim": ("event_succession", scc.scc_fwbw_trim, SCC_SQL.format(arcs=arcs("event_succession")), False),
    "scc_staged": ("event_succession", scc.scc_staged, SCC_SQL.format(arcs=arcs("event_succession")), False),
    "scc_no_trim": ("event_succession", lambda g: scc.scc(g, trim=False, first_pivot=False, beta_growth=2.0), SCC_SQL.format(arcs=arcs("event_succession")), False),
}
for _name, (_graph, _f, _sql, _weights) in WHOLE.items():
    query(f"{_name}_whole", _sql)(on(_graph, _f, weights=_weights))

STATS_SQL = """SELECT '{name}' AS graph, (SELECT count(*) FROM v) AS n, (SELECT count(*) FROM e) AS arcs, (SELECT max(k) FROM (SELECT count(*) AS k FROM e GROUP BY src)) AS max_degree, (SELECT count(DISTINCT label) FROM cc) AS components"""
for _g in ("cust_supp", "order_part_h1", "conversation_chain", "geo_tree", "torus"):
    query(f"graph_stats_{_g}", f"WITH RECURSIVE {arcs(_g)}, {label_cte()} {STATS_SQL.format(name=_g)}")(on(_g, measures.graph_stats))
query("degree_histogram", f"WITH {arcs('cust_supp')} SELECT degree, count(*) AS vertices FROM (SELECT src, count(*) AS degree FROM e GROUP BY src) GROUP BY degree")(on("cust_supp", measures.degree_histogram))
query("torus_stats", f"WITH {arcs('torus')} SELECT min(k) AS low, max(k) AS high, count(*) AS n FROM (SELECT src, count(*) AS k FROM e GROUP BY src)")(on("torus", lambda g: g.degrees().agg(F.min("degree").alias("low"), F.max("degree").alias("high"), F.count(F.lit(1)).alias("n"))))
query("effective_diameter", f"SELECT min_v AS source, depth FROM (SELECT (SELECT min(v) FROM ({bfs_sql('torus')})) AS min_v, max(dist) AS depth FROM ({bfs_sql('torus')}))")(on("torus", lambda g: bfs.effective_diameter(g, [source(g)])))
