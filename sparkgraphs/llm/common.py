"""Shared plumbing: table access, stage tables, bounded Arrow batches, hot keys, streamed groups."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import gc
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..core.rounds import release  # noqa: F401

TOKENIZER_ROWS = 512


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bounded_batches(spark: SparkSession, rows: int = TOKENIZER_ROWS) -> None:
    """Arrow batches of few rows, so that a run of very long texts stays small in a Python worker."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or the context's own, or (on one machine, where neither is set) a new one."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base and not spark.sparkContext.master.startswith("local["):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    if not base:
        base = tempfile.mkdtemp(prefix="llm-shared-")
        spark.sparkContext.setCheckpointDir(base)
        atexit.register(shutil.rmtree, base, True)
    return base


class Stages:
    """Parquet tables of one run in the shared folder: they cut lineage, are written once, and outlive executors."""

    def __init__(self, spark: SparkSession, tag: str):
        self.spark, self.root = spark, f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex[:12]}"
        self.count = 0

    def keep(self, df: DataFrame, parts: int | None = None) -> DataFrame:
        self.count += 1
        path = f"{self.root}/{self.count}"
        (df.coalesce(parts) if parts else df).write.parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, number: int) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{number}")
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string")) % 4 == 2


def bounded_sample(docs: DataFrame, labelled: DataFrame, label: str, *, rows: int, max_bytes: int) -> tuple[list, list]:
    """Texts and labels of at most `rows` rows and `max_bytes` of text, for fitting: (doc_id, label) rows in the order of a hash of their id.

    A text that would overflow what is left of `max_bytes` is passed over, and the next ones are tried.
    """
    spark = docs.sparkSession
    kind = labelled.schema[label].dataType.simpleString()
    ids = labelled.select("doc_id", label).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows).collect()
    if not ids:
        return [], []
    places = spark.createDataFrame([(r[0], r[1], i) for i, r in enumerate(ids)], f"doc_id long, label {kind}, place int")
    taken = docs.select("doc_id", "text").join(F.broadcast(places), "doc_id")
    total, chosen = 0, []
    for r in sorted(taken.groupBy("place").agg(F.sum(F.coalesce(F.octet_length("text"), F.lit(0))).alias("n")).collect()):
        if total + r.n <= max_bytes:
            total += r.n
            chosen.append((r.place,))
    if not chosen:
        return [], []
    got = taken.join(F.broadcast(spark.createDataFrame(chosen, "place int")), "place").select("place", "text", "label").toArrow().sort_by("place")
    return got["text"].to_pylist(), got["label"].to_pylist()


def hot_values(df: DataFrame, column: str, share: int = 1000) -> DataFrame:
    """Values that hold more than 1/share of the rows: at most `share` of them whatever the size of the input."""
    counts = df.groupBy(column).agg(F.count(F.lit(1)).alias("n_rows"))
    total = df.agg((F.count(F.lit(1)) / share).alias("least"))
    return counts.crossJoin(F.broadcast(total)).where("n_rows > least").select(column)


def batches_of(columns: dict[str, list], schema: pa.Schema, rows: int = 20_000) -> Iterator[pa.RecordBatch]:
    size = len(next(iter(columns.values()), []))
    for at in range(0, size, rows):
        yield pa.RecordBatch.from_arrays([pa.array(columns[f.name][at : at + rows], type=f.type) for f in schema], schema=schema)


def streamed_groups(batches: Iterable[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[tuple, pa.Table]]:
    """Groups of rows already clustered by `keys` in a partition, one at a time."""
    held: list[pa.RecordBatch] = []
    current: tuple | None = None
    for batch in batches:
        if not batch.num_rows:
            continue
        values = list(zip(*(batch.column(k).to_pylist() for k in keys), strict=True))
        start = 0
        for i in range(1, len(values) + 1):
            if i == len(values) or values[i] != values[start]:
                if current is not None and values[start] != current:
                    yield current, pa.Table.from_batches(held)
                    held = []
                current = values[start]
                held.append(batch.slice(start, i - start))
                start = i
    if current is not None:
        yield current, pa.Table.from_batches(held)


def trim() -> None:
    """Gives memory that a task has freed back to the system: workers are reused and would else keep it."""
    gc.collect()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def map_arrow(df: DataFrame, body: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    def trimmed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from body(batches)
        trim()

    return df.mapInArrow(trimmed, schema)
