"""Line deduplication: explode normalised lines, hash, count documents per hash, drop lines over the threshold, reassemble.

A line's key is the line without white space at both ends, A-Z lower-cased; 128-bit digests of keys are shuffled, not lines. A
document contributes each key once, before the shuffle. Keys found in `min_docs` documents or more lose their lines everywhere but
in the largest doc_id that holds them.

Defined cases: null and empty texts are one empty line; rows that share a doc_id count as one document and keep or lose
a line together, rows without doc_id count as none; ties cannot arise, as doc_ids order the holders; empty tables give empty results; columns named n_lines or
n_dropped in the input are replaced; all other columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Stages, table

MIN_DOCS, MIN_CHARS = 5, 40
BLANKS = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def ascii_lower(text: Column) -> Column:
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, UPPER, LOWER))


def split_lines(text: str) -> Column:
    return F.split(F.coalesce(F.col(text), F.lit("")), "\n", -1)


def line_digest(line: Column) -> Column:
    return F.unhex(F.md5(ascii_lower(F.btrim(line, F.lit(BLANKS)))))


def dedup_lines(docs: DataFrame, *, key: str = "doc_id", text: str = "text", min_docs: int = MIN_DOCS, min_chars: int = MIN_CHARS, stages: Stages | None = None) -> DataFrame:
    """`docs` with the text that is left, n_lines (before) and n_dropped."""
    stages = stages or Stages(docs.sparkSession, "lines")
    long_enough = lambda x: F.char_length(F.btrim(x, F.lit(BLANKS))) >= min_chars
    held = docs.select(
        F.col(key).alias("k"),
        F.explode(F.array_distinct(F.transform(F.filter(split_lines(text), long_enough), line_digest))).alias("h"),
    )
    held = stages.keep(held)  # read three times: by keys, by frequent keys, by the rest
    common = stages.keep(held.distinct().groupBy("h").agg(F.count("k").alias("n"), F.max("k").alias("keeper")).where(F.col("n") >= min_docs))
    # A key with over a thousandth of the rows that match any is joined by broadcast: there are at most a thousand of those.
    total = F.broadcast(common.agg((F.sum("n") / 1000).alias("least")))
    ranked = common.crossJoin(total)
    hot = F.broadcast(ranked.where("n > least").select("h", "keeper"))
    cold = ranked.where("n <= least").select("h", "keeper")
    losing = (
        held.join(hot, "h").select("k", "h", "keeper")
        .unionByName(held.join(hot.select("h"), "h", "left_anti").join(cold, "h").select("k", "h", "keeper"))
        .where("k < keeper")
        .groupBy("k").agg(F.collect_set("h").alias("gone"))
    )
    lines = split_lines(text)
    kept = F.filter(lines, lambda x: ~(long_enough(x) & F.array_contains(F.col("gone"), line_digest(x))))
    own = [c for c in docs.columns if c not in ("n_lines", "n_dropped")]
    joined = docs.select(*own).join(losing.withColumnRenamed("k", "losing_key"), F.col(key) == F.col("losing_key"), "left")
    joined = joined.withColumn("kept_lines", F.when(F.col("gone").isNotNull(), kept))
    whole = F.coalesce(F.array_join("kept_lines", "\n"), F.col(text), F.lit(""))
    return joined.select(
        *[whole.alias(c) if c == text else F.col(c) for c in own],
        F.size(lines).cast("long").alias("n_lines"),
        F.when(F.col("gone").isNull(), F.lit(0)).otherwise(F.size(lines) - F.size("kept_lines")).cast("long").alias("n_dropped"),
    )


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return docs.select("doc_id", "n_lines", "n_dropped", F.sha2("text", 256).alias("kept_sha256"))


OP7_SQL = """
WITH lines AS (
  SELECT doc_id, generate_subscripts(ls, 1) AS pos, unnest(ls) AS line
  FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents)),
keyed AS (
  SELECT doc_id, pos, line,
         translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM lines),
common AS (
  SELECT key, max(doc_id) AS keeper FROM keyed WHERE length(key) >= 40 GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
marked AS (
  SELECT k.doc_id, k.pos, k.line, coalesce(k.doc_id <> c.keeper, false) AS gone FROM keyed k LEFT JOIN common c ON k.key = c.key)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
