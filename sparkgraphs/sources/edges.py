"""Edge readers and result writers, and a data source that makes torus arcs."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

FORMATS = ("parquet", "json", "csv", "orc")


def read_edges(spark: SparkSession, path: str, src: str = "src", dst: str = "dst", w: str | None = None, fmt: str = "parquet") -> DataFrame:
    """(src, dst[, w]) of a file; text files hold white-space separated lines, # starts a comment."""
    if fmt == "text":
        parts = spark.read.text(path).where("value NOT LIKE '#%'").select(F.split(F.trim("value"), r"\s+").alias("p"))
        return parts.select(*[F.col("p")[i].cast("bigint" if i < 2 else "double").alias(c) for i, c in enumerate(["src", "dst"] + ["w"] * bool(w))])
    names = [(src, "src"), (dst, "dst")] + ([(w, "w")] if w else [])
    reader = spark.read.format(fmt)
    if fmt in ("csv", "json"):
        reader = reader.schema(", ".join(f"{a} {'bigint' if b != 'w' else 'double'}" for a, b in names))
    if fmt == "csv":
        reader = reader.option("header", True)
    return reader.load(path).select(*[F.col(a).alias(b) for a, b in names])


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst) of text lines that name a vertex and then its neighbours."""
    parts = spark.read.text(path).where("value <> ''").select(F.split(F.trim("value"), r"\s+").alias("p"))
    return parts.select(F.col("p")[0].cast("bigint").alias("src"), F.explode(F.slice("p", 2, F.size("p"))).cast("bigint").alias("dst"))


def write_result(df: DataFrame, path: str, fmt: str = "parquet", partition_by: str | None = None) -> None:
    writer = df.write.format(fmt).mode("overwrite")
    if fmt == "csv":
        writer = writer.option("header", True)
    (writer.partitionBy(partition_by) if partition_by else writer).save(path)


def write_graph(df: DataFrame, name: str, buckets: int) -> None:
    """A table bucketed and sorted by source: joins on it need no exchange of the arcs."""
    df.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(name)


class Slab(InputPartition):
    def __init__(self, x: int):
        self.x = x


class TorusReader(DataSourceReader):
    def __init__(self, side: int):
        self.side = side

    def partitions(self) -> list[InputPartition]:
        return [Slab(z) for z in range(self.side)]

    def read(self, slab: Slab) -> Iterator[tuple[int, int]]:
        n, z = self.side, slab.x
        for y in range(n):
            for x in range(n):
                at = x + y * n + z * n * n
                yield at, (x + 1) % n + y * n + z * n * n
                yield at, x + (y + 1) % n * n + z * n * n
                yield at, x + y * n + (z + 1) % n * n * n


class TorusSource(DataSource):
    """spark.read.format("torus").option("side", n): the arcs of a 3-D torus, a slab a partition."""

    @classmethod
    def name(cls) -> str:
        return "torus"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> DataSourceReader:
        return TorusReader(int(self.options.get("side", 3)))
