"""Buckets: rows held by the value of a key that changes, taken a bucket at a time in the order of their numbers.

The table of all rows is a written state and the number of the next bucket is observed as it is written, so extracting a bucket costs
no job of its own and an update is one. Rows whose bucket is NULL lie in none.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .rounds import Rounds


class Buckets:
    def __init__(self, rounds: Rounds, bucket: Column, order: str = "min", slot: str = "state"):
        if order not in ("min", "max"):
            raise ValueError("order is min or max")
        self.rounds, self.bucket, self.slot = rounds, bucket, slot
        self.pick = F.min if order == "min" else F.max
        self.rows: DataFrame | None = None
        self.seen: dict = {}

    def put(self, rows: DataFrame, **counters: Column) -> Buckets:
        """Makes the buckets of `rows`, in place of those held so far."""
        self.rows, self.seen = self.rounds.keep(rows, self.slot, bucket=self.pick(self.bucket), **counters)
        return self

    def update(self, changes: DataFrame, key: str, **counters: Column) -> Buckets:
        """Moves rows: `changes` (key, columns) has each key at most once, its columns take the place of the row's own."""
        new = [c for c in changes.columns if c != key]
        moved = changes.select(key, F.lit(True).alias("moved"), *[F.col(c).alias(f"new_{c}") for c in new])
        kept = [F.when(F.col("moved"), F.col(f"new_{c}")).otherwise(F.col(c)).alias(c) if c in new else F.col(c) for c in self.rows.columns]
        return self.put(self.rows.join(moved, key, "left").select(*kept), **counters)

    @property
    def id(self):
        """The number of the next bucket, None when all are empty."""
        return self.seen["bucket"]

    @property
    def in_next(self) -> Column:
        return F.coalesce(self.bucket == F.lit(self.id), F.lit(False))

    def next(self) -> tuple[object, DataFrame]:
        """The number and the rows of the next bucket; they stay in it until an update moves them."""
        return self.id, self.rows.where(self.in_next)
