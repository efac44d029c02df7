"""Counting by key: map-side combining is what removes contention; the other strategies are its ablations and its help under skew."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Keys that a task of local_first holds before it hands them on.
HELD = 1 << 18
STRATEGIES = ("plain", "heavy_light", "local_first", "raw")


def histogram(pairs: DataFrame, key: str, agg: Column | None = None, again: Column | None = None, *, strategy: str = "plain", out: str = "n", salts: int = 32, share: int = 1000) -> DataFrame:
    """(key, out). `agg` reduces rows, `again` reduces what `agg` gave (default: counts and their sum).

    plain        partial and final aggregation
    heavy_light  keys that a sample shows to hold over 1/share of the rows (at most `share` of them, broadcast) are salted
    local_first  an explicit count within each task before the shuffle
    raw          every pair is shuffled: the counter-per-pair baseline
    """
    if strategy == "local_first" and agg is not None:
        raise ValueError("local_first counts")
    agg = F.count(F.lit(1)) if agg is None else agg
    again = F.sum(out) if again is None else again
    if strategy == "plain":
        return pairs.groupBy(key).agg(agg.alias(out))
    if strategy == "raw":
        return pairs.repartition(key).groupBy(key).agg(agg.alias(out))
    if strategy == "local_first":
        return local_counts(pairs, key, out).groupBy(key).agg(F.sum(out).alias(out))
    if strategy != "heavy_light":
        raise ValueError(f"strategy is one of {STRATEGIES}")
    sample = pairs.select(key).sample(0.1, 5)
    total = sample.agg((F.count(F.lit(1)) / share).alias("least"))
    heavy = F.broadcast(sample.groupBy(key).agg(F.count(F.lit(1)).alias("c")).crossJoin(F.broadcast(total)).where("c > least").select(key))
    salted = pairs.join(heavy, key, "left_semi").groupBy(key, F.floor(F.rand(3) * salts).alias("salt")).agg(agg.alias(out)).groupBy(key).agg(again.alias(out))
    return salted.unionByName(pairs.join(heavy, key, "left_anti").groupBy(key).agg(agg.alias(out)))


def local_counts(pairs: DataFrame, key: str, out: str) -> DataFrame:
    """(key, out) counted within each task, without a shuffle: a key comes once for each HELD distinct keys of a task."""
    kind = pairs.schema[key].dataType.simpleString()

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.Table | None = None
        for b in batches:
            one = pa.table({key: b.column(0), out: pa.repeat(pa.scalar(1, pa.int64()), b.num_rows)})
            held = one if held is None else pa.concat_tables([held, one])
            if held.num_rows > HELD:
                held = held.group_by(key).aggregate([(out, "sum")]).rename_columns([key, out])
                if held.num_rows > HELD // 2:
                    yield from held.to_batches()
                    held = None
        if held is not None:
            yield from held.group_by(key).aggregate([(out, "sum")]).rename_columns([key, out]).to_batches()

    return pairs.select(key).mapInArrow(body, f"`{key}` {kind}, `{out}` bigint")
