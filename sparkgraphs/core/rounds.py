"""Rounds: every iterative method writes its state once a round to the shared folder and counts as it writes.

A written state cuts the lineage and survives lost executors; the counters of a round come from observed metrics of that same job, so a
round is one action. States of a slot replace each other; the older one is deleted when the newer one stands.
"""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import time
import uuid
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Observation, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: the session's spark.checkpoint.dir; on one machine a new one where none is set."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base and not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    if not base:
        base = tempfile.mkdtemp(prefix="graph-rounds-")
        spark.sparkContext.setCheckpointDir(base)
        atexit.register(shutil.rmtree, base, True)
    return base


def release(spark: SparkSession) -> None:
    """Lets Spark drop the shuffle files of jobs that are done and no longer referred to, instead of at some later collection.

    Spark's own threads refer to the last job until another one runs, so a job of one row goes before.
    """
    gc.collect()
    spark.range(0, 1, 1, 1).toArrow()
    gc.collect()
    spark._jvm.System.gc()


@dataclass
class RunStats:
    """Counters of a run: one entry a round, with whatever the method observed."""

    rounds: list[dict] = field(default_factory=list)

    @property
    def depth(self) -> int:
        return len(self.rounds)

    def total(self, name: str) -> int:
        return sum(r.get(name) or 0 for r in self.rounds)


class Rounds:
    """The written states of one run."""

    def __init__(self, spark: SparkSession, tag: str, stats: RunStats | None = None):
        self.spark, self.root = spark, f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex[:12]}"
        self.stats = stats if stats is not None else RunStats()
        self.slots: dict[str, str] = {}
        self.count = 0

    def keep(self, df: DataFrame, slot: str | None = None, **counters: Column) -> tuple[DataFrame, dict]:
        """Writes `df` and reads it back; returns it with the observed counters. A slot's former table is deleted."""
        began, self.count = time.time(), self.count + 1
        path = f"{self.root}/{self.count}"
        seen: dict = {}
        if counters:
            watch = Observation()
            df.observe(watch, *(c.alias(n) for n, c in counters.items())).write.parquet(path)
            seen = watch.get
            self.stats.rounds.append({**seen, "seconds": time.time() - began})
        else:
            df.write.parquet(path)
        if slot:
            if slot in self.slots:
                self.delete(self.slots[slot])
            self.slots[slot] = path
        return self.spark.read.schema(df.schema).parquet(path), seen

    def table(self, df: DataFrame) -> DataFrame:
        return self.keep(df)[0]

    def append(self, df: DataFrame, name: str) -> DataFrame:
        """Adds rows to a table that grows over the rounds, and reads all of it."""
        path = f"{self.root}/{name}"
        df.write.mode("append").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def bucketed(self, df: DataFrame, key: str, *order: str, partitions: int | None = None) -> DataFrame:
        """Writes `df` in buckets by `key`, a file each, under the run's own folder; the table's name goes with the session."""
        self.count += 1
        n = partitions or int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        name = f"by_{key}_{uuid.uuid4().hex[:16]}"
        dealt = df.repartition(n, key)
        dealt.write.format("parquet").bucketBy(n, key).sortBy(key, *order).option("path", f"{self.root}/{self.count}").saveAsTable(name)
        return self.spark.table(name)

    def delete(self, path: str) -> None:
        where = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(where, True)
