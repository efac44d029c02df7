"""Streams of events: windows, late rows, duplicates, joins, succession arcs, live components."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..core.rounds import Rounds, shared_dir

SCHEMA = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def event_source(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A file stream of events of a fixed schema, so many files a trigger; `path` is a folder."""
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).parquet(path)


def replayable(spark: SparkSession, sf_dir: str, order: str = "ts", parts: int = 4) -> str:
    """A folder in the shared space with the events in files that follow the time."""
    path = f"{shared_dir(spark)}/events-{uuid.uuid4().hex[:12]}"
    events = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    # a file stream takes files by the time they were written, so the parts are written one after the other
    cuts = events.agg(F.percentile_approx(F.unix_micros(order), [i / parts for i in range(1, parts)], 10_000).alias("c")).first().c or []
    at, place = F.unix_micros(order), F.lit(0)
    for c in cuts:
        place = place + (at > c).cast("int")
    for i in range(len(cuts) + 1):
        events.where(place == i).coalesce(1).sortWithinPartitions(order).write.mode("append").parquet(path)
    return path


def run(stream: DataFrame, mode: str = "append") -> DataFrame:
    """The stream's result once all files there are have been taken: written to the shared folder, or (update, complete) held in a table of it."""
    spark = stream.sparkSession
    root = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex[:12]}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{root}/state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{root}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{root}/out")

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{root}/batch/{number:06d}")

    query = writer.foreachBatch(put).start()
    query.awaitTermination()
    last = query.lastProgress["batchId"] if query.lastProgress else 0
    return spark.read.schema(stream.schema).parquet(f"{root}/batch/{last:06d}")


def windows(events: DataFrame, kind: str) -> DataFrame:
    """(start, end, user_id, n): tumbling hours, hours that slide by 15 minutes, or sessions with gaps under 30 minutes."""
    slot = {"tumbling": F.window("ts", "1 hour"), "sliding": F.window("ts", "1 hour", "15 minutes"), "session": F.session_window("ts", "30 minutes")}[kind]
    return events.withWatermark("ts", "2 hours").groupBy(slot.alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


def dedup(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "2 hours").dropDuplicatesWithinWatermark(["event_id"])


def click_to_purchase(events: DataFrame) -> DataFrame:
    """(user_id, click_id, purchase_id): purchases within an hour after a click, stream with stream."""
    clicks = events.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("event_id").alias("click_id"), F.col("ts").alias("tc")).withWatermark("tc", "2 hours")
    buys = events.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("tp")).withWatermark("tp", "2 hours")
    return clicks.join(buys, F.expr("u = user_id AND tp > tc AND tp <= tc + interval 1 hour")).select("user_id", "click_id", "purchase_id")


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    return events.join(customers, events.user_id == customers.c_custkey).select("event_id", "user_id", "c_mktsegment")


def last_pairs(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    """Arcs from each event of a user to the user's next: the last one waits in the state."""
    held = list(state.get) if state.exists else None
    rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
    ids = ([held[0]] if held else []) + rows.event_id.tolist()
    state.update((ids[-1],))
    yield pd.DataFrame({"user_id": [key[0]] * (len(ids) - 1), "src": ids[:-1], "dst": ids[1:]})


def succession(events: DataFrame) -> DataFrame:
    """(user_id, src, dst): succession arcs per user, kept up over triggers; files must follow the time."""
    return events.groupBy("user_id").applyInPandasWithState(last_pairs, "user_id bigint, src bigint, dst bigint", "last bigint", "append", "NoTimeout")


def live_components(arcs: DataFrame, folder: str | None = None) -> DataFrame:
    """(v, label) of all arcs that came: each batch joins the labels stored by the one before, by a contraction of both.

    Labels lie in `folder` (a new one in the shared folder if not given) beside the stream's checkpoint, under the number of their
    batch: a restarted stream goes on from them, and a batch that is run again writes the same table again.
    """
    from ..algo.connectivity import hook_jump
    from ..model.graph import from_arcs

    spark = arcs.sparkSession
    rounds = Rounds(spark, "live")
    folder = folder or rounds.root
    labels = spark._jvm.org.apache.hadoop.fs.Path(f"{folder}/labels")
    files = labels.getFileSystem(spark._jsc.hadoopConfiguration())
    read = lambda number: spark.read.schema("v bigint, label bigint").parquet(f"{folder}/labels/{number}")

    def fold(batch: DataFrame, number: int) -> None:
        fresh = batch.select("src", "dst")
        if number:
            fresh = fresh.unionByName(read(number - 1).select(F.col("v").alias("src"), F.col("label").alias("dst")))
        # loops keep vertices that are alone
        ends = fresh.select(F.col("src").alias("v")).unionByName(fresh.select(F.col("dst").alias("v"))).distinct()
        hook_jump(from_arcs(fresh, ends)).select("v", "label").write.mode("overwrite").parquet(f"{folder}/labels/{number}")
        if number > 1:
            rounds.delete(f"{folder}/labels/{number - 2}")

    query = arcs.writeStream.foreachBatch(fold).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    # a batch's number is its folder's name: two at most
    numbers = [int(f.getPath().getName()) for f in files.listStatus(labels)] if files.exists(labels) else []
    return read(max(numbers)) if numbers else spark.createDataFrame([], "v bigint, label bigint")
