"""Benchmark decontamination by pigeonhole edit matching.

An item of n normalised characters may be off by floor(error_rate * n) edits. It is cut into one piece more than that, so a passage
within the budget holds one piece unchanged. One automaton of all pieces finds the hits in a text in a single pass; each
hit names a small window, which bit-parallel edit distance (one machine-word-like integer per item) verifies.

The items are broadcast: a benchmark is a fixed set, checked against `max_items_bytes`; beyond that they are taken in slices.

Defined cases: normalisation lower-cases, keeps letters and digits and puts one blank between words, so an item or text without
any is null-like and matches nothing; items too short for an edit match as whole words, exactly; items of fewer than `min_chars`
normalised characters (by default none) match nothing; texts of any length are searched whole; repeated items and rows each count; empty tables give no hits; extra columns of the documents pass through `drop_contaminated`.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_batches, map_arrow, table

ERROR_RATE, MIN_CHARS, MAX_ITEMS_BYTES = 0.05, 1, 64 << 20
RUN = re.compile(r"[^\W_]+")


def normalise(text: str | None) -> str:
    return " ".join(RUN.findall(text.lower())) if text else ""


def best_match(pattern: str, text: str, budget: int, masks: dict[str, int] | None = None) -> int:
    """The least edit distance of `pattern` to any part of `text`, or budget + 1: bit-parallel columns in one integer."""
    m = len(pattern)
    if masks is None:
        masks = pattern_masks(pattern)
    full, high = (1 << m) - 1, 1 << (m - 1)
    up, down, score, best = full, 0, m, m
    for c in text:
        eq = masks.get(c, 0)
        across = eq | down
        diag = ((((eq & up) + up) ^ up) | eq) & full
        right = (down | ~(diag | up)) & full
        left = up & diag
        if right & high:
            score += 1
        elif left & high:
            score -= 1
            if score < best:
                best = score
                if not best:
                    return 0
        right, left = (right << 1) & full, (left << 1) & full
        up = (left | ~(across | right)) & full
        down = right & across
    return min(best, budget + 1)


def pattern_masks(pattern: str) -> dict[str, int]:
    masks: dict[str, int] = {}
    for i, c in enumerate(pattern):
        masks[c] = masks.get(c, 0) | 1 << i
    return masks


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Overlapping windows as one: each character is read once an item."""
    out: list[tuple[int, int]] = []
    for lo, hi in sorted(spans):
        if out and lo <= out[-1][1]:
            out[-1] = out[-1][0], max(hi, out[-1][1])
        else:
            out.append((lo, hi))
    return out


class ItemMatcher:
    def __init__(self, items: list[tuple[int, str | None]], error_rate: float = ERROR_RATE, min_chars: int = MIN_CHARS):
        self.items: list[tuple[int, str, int, dict[str, int]]] = []
        where: dict[str, list[tuple[int, int]]] = {}
        for ident, raw in items:
            text = normalise(raw)
            if len(text) < min_chars:
                continue
            budget = int(error_rate * len(text))
            if not budget:  # whole words: normalised texts are searched with a blank at both ends
                text = f" {text} "
            k, n = len(self.items), len(text)
            self.items.append((ident, text, budget, pattern_masks(text)))
            for p in range(budget + 1):
                lo, hi = p * n // (budget + 1), (p + 1) * n // (budget + 1)
                where.setdefault(text[lo:hi], []).append((k, lo))
        self.automaton = ahocorasick.Automaton()
        for piece, places in where.items():
            self.automaton.add_word(piece, (len(piece), places))
        if where:
            self.automaton.make_automaton()

    def matches(self, text: str) -> list[tuple[int, int]]:
        """(item, least distance) of the items that a normalised text holds within their budgets."""
        windows: dict[int, list[tuple[int, int]]] = {}
        if not self.items or not text:
            return []
        text = f" {text} "
        for end, (size, places) in self.automaton.iter(text):
            for k, lo in places:
                start = end - size + 1 - lo
                windows.setdefault(k, []).append((start - self.items[k][2], start + len(self.items[k][1]) + self.items[k][2]))
        found = []
        for k, spans in windows.items():
            ident, item, budget, masks = self.items[k]
            best = budget + 1
            for lo, hi in merged(spans):
                best = min(best, best_match(item, text[max(0, lo) : hi], budget, masks))
                if best == 0:
                    break
            if best <= budget:
                found.append((ident, best))
        return sorted(found)


def slices_of(benchmark: DataFrame, item: str, text: str, most: int) -> Iterator[list[tuple[int, str]]]:
    held, size = [], 0
    for r in benchmark.select(F.col(item).alias("i"), F.col(text).alias("t")).where("t is not null").toLocalIterator():
        held.append((r.i, r.t))
        size += len(r.t)
        if size > most:
            yield held
            held, size = [], 0
    if held:
        yield held


def contaminated(docs: DataFrame, benchmark: DataFrame, *, key: str = "doc_id", text: str = "text", item: str = "item_id", item_text: str = "text", error_rate: float = ERROR_RATE, min_chars: int = MIN_CHARS, max_items_bytes: int = MAX_ITEMS_BYTES) -> DataFrame:
    """(key, item_id, distance) of every document and item within the item's budget."""
    spark = docs.sparkSession
    bounded_batches(spark)
    kind = docs.select(key).schema[0].dataType.simpleString()
    out = None
    for part in slices_of(benchmark, item, item_text, max_items_bytes):
        shared = spark.sparkContext.broadcast(part)

        def body(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            matcher = ItemMatcher(shared.value, error_rate, min_chars)
            for b in batches:
                at, ids, dist = [], [], []
                for row, t in enumerate(b.column(1).to_pylist()):
                    for i, d in matcher.matches(normalise(t)):
                        at.append(row)
                        ids.append(i)
                        dist.append(d)
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at, pa.int64())), pa.array(ids, pa.int64()), pa.array(dist, pa.int32())], names=["k", "item_id", "distance"])

        hits = map_arrow(docs.select(F.col(key).alias("k"), text), body, f"k {kind}, item_id long, distance int")
        out = hits if out is None else out.unionByName(hits)
    if out is None:
        out = spark.createDataFrame([], f"k {kind}, item_id long, distance int")
    return out.withColumnRenamed("k", key)


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, *, text: str = "text", item: str = "item_id", item_text: str = "text", error_rate: float = ERROR_RATE, min_chars: int = MIN_CHARS, max_items_bytes: int = MAX_ITEMS_BYTES) -> DataFrame:
    """`docs` without the rows that hold an item: one pass, nothing shuffled."""
    spark = docs.sparkSession
    bounded_batches(spark)
    schema = docs.schema
    for part in slices_of(benchmark, item, item_text, max_items_bytes):
        shared = spark.sparkContext.broadcast(part)

        def body(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            matcher = ItemMatcher(shared.value, error_rate, min_chars)
            for b in batches:
                yield b.filter(pa.array([not matcher.matches(normalise(t)) for t in b.column(text).to_pylist()], pa.bool_()))

        docs = docs.mapInArrow(body, schema)
    return docs


def op6_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, item_id, distance) of each benchmark passage found in a document."""
    return contaminated(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))
