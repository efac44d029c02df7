"""Token counts by heap-and-linked-list byte-pair merging.

The count of a word is its number of initial byte symbols minus the merges done; identifiers are never formed.
Words repeat, so a bounded per-worker memo holds the counts of white-space chunks and of words; a miss runs the merge.

Defined cases: null and empty texts have 0 bytes and 0 tokens; texts of any length are counted whole; repeated rows are
counted row by row; an empty table gives an empty result; extra columns of the input are ignored.
"""

from __future__ import annotations

import heapq
import json
import unicodedata
from collections.abc import Callable, Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_batches, map_arrow, table

MEMO_ENTRIES = 1 << 19
#: str.split() also splits at these, which are not white space for the tokenizer.
SEPARATORS = ("\x1c", "\x1d", "\x1e", "\x1f")
WHITE = regex.compile(r"[\t-\r \x85\xa0  -     　]+")


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte in byte-level vocabularies: printable Latin-1 stays, the rest follow from 256."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(spare)) for b in range(256)]


def merges_left(symbols: list[str], rank: dict[tuple[str, str], int]) -> list[str]:
    """The symbols after all merges: always the adjacent pair of lowest rank, the leftmost of equals."""
    n = len(symbols)
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = [(r, i, symbols[i], symbols[i + 1]) for i in range(n - 1) if (r := rank.get((symbols[i], symbols[i + 1]))) is not None]
    heapq.heapify(heap)
    alive: list[str | None] = list(symbols)
    while heap:
        _, i, left, right = heapq.heappop(heap)
        j = after[i]
        if alive[i] != left or j >= n or alive[j] != right:
            continue
        alive[i], alive[j] = left + right, None
        k = after[i] = after[j]
        if k < n:
            before[k] = i
            if (r := rank.get((alive[i], alive[k]))) is not None:
                heapq.heappush(heap, (r, i, alive[i], alive[k]))
        if (p := before[i]) >= 0 and (r := rank.get((alive[p], alive[i]))) is not None:
            heapq.heappush(heap, (r, p, alive[p], alive[i]))
    return [x for x in alive if x is not None]


class Memo(dict):
    """A dictionary that computes what it lacks and starts anew when full."""

    def __init__(self, compute: Callable, entries: int = MEMO_ENTRIES):
        super().__init__()
        self.compute, self.entries = compute, entries

    def __missing__(self, key):
        value = self.compute(key)
        if len(self) >= self.entries:
            self.clear()
        self[key] = value
        return value


class WordPairCounter:
    """Counts for a BPE vocabulary with word ends, white space dropped, lower case (the .json named in `path`)."""

    def __init__(self, path: str, entries: int = MEMO_ENTRIES):
        spec = json.load(open(path, encoding="utf-8"))
        self.rank = {(a, b): i for i, (a, b) in enumerate(m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"])}
        self.suffix = spec["model"]["end_of_word_suffix"] or ""
        self.symbols = byte_symbols()
        self.pieces = regex.compile(spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        special = sorted((t["content"] for t in spec["added_tokens"]), key=len, reverse=True)
        self.special = regex.compile("|".join(map(regex.escape, special))) if special else None
        self.marks = [s[:2] for s in special]
        self.words = Memo(self._word, entries)
        self.chunks = Memo(self._chunk, entries)

    def _word(self, word: str) -> int:
        symbols = [self.symbols[b] for b in word.encode("utf-8")]
        symbols[-1] += self.suffix
        return len(merges_left(symbols, self.rank))

    def _chunk(self, chunk: str) -> int:
        if chunk.isascii():
            chunk = chunk.lower()
        else:
            chunk = "".join(c.lower() for c in unicodedata.normalize("NFC", chunk))
        return sum(self.words[w] for w in self.pieces.findall(chunk))

    def _plain(self, text: str) -> int:
        chunks = text.split() if not any(s in text for s in SEPARATORS) else [c for c in WHITE.split(text) if c]
        return sum(map(self.chunks.__getitem__, chunks))

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if self.special and any(m in text for m in self.marks):
            return sum(map(self._plain, self.special.split(text))) + len(self.special.findall(text))
        return self._plain(text)


def token_counts(docs: DataFrame, tokenizer: str, *, limit: int = 2048, text: str = "text", key: str = "doc_id", entries: int = MEMO_ENTRIES) -> DataFrame:
    """One row per row of `docs`: key, n_bytes, n_tokens, over_limit. `tokenizer`: path of the vocabulary on every executor."""
    bounded_batches(docs.sparkSession)

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = WordPairCounter(tokenizer, entries)
        for b in batches:
            counts = pa.array([counter.count(t) for t in b.column(2).to_pylist()], pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), counts], names=["k", "n_bytes", "n_tokens"])

    kind = docs.select(key).schema[0].dataType.simpleString()
    slim = docs.select(F.col(key).alias("k"), F.coalesce(F.octet_length(text), F.lit(0)).cast("long").alias("n_bytes"), F.col(text).alias("t"))
    return map_arrow(slim, body, f"k {kind}, n_bytes long, n_tokens long").select(F.col("k").alias(key), "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
