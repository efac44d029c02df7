"""Language identification with string kernels.

The kernel of two texts is the number of character n-grams (n = 1, 2, 3) present in both, over the geometric mean of their numbers
(a blended-spectrum presence kernel). Landmark texts span a Nyström feature space; one-versus-rest kernel ridge regression is fitted
in it. Since the kernel is linear in the presence vector, landmarks and regression fold into one matrix, and a batch of texts is
scored by a product of its presence matrix with that.

Fitting uses at most `FIT_ROWS` rows and `FIT_BYTES` of text outside the held-out quarter, in the order of a hash of the id; every
text is scored whole.

Characters are lower-cased; a letter of any script is its own code point, and all that is no letter is one symbol. N-grams are named by
a hash of 20 bits, of each length apart.

Defined cases: null texts and texts without a letter are `und` with score 0; without any fitting rows all are; ties go to the first
language in code order; repeated rows are scored alike; an empty table gives an empty result; extra columns pass through, but for
those named like the new ones, which are replaced.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_batches, bounded_sample, held_out, map_arrow, table

FIT_ROWS, FIT_BYTES, LANDMARKS = 4_000, 24 << 20, 240
BITS = 20
SIZE = 1 << BITS
#: Odd multipliers of the hash, one for each place in an n-gram, and one for each length (fixed values).
PLACES, LENGTHS = (0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D), (0x27D4EB2F, 0x165667B1, 0x2C1B3C6D)


@functools.cache
def letters() -> np.ndarray:
    """Whether each code point is a letter."""
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)


class Presence:
    """Turns texts into sets of n-gram codes."""

    def __init__(self):
        self.flags = np.zeros(SIZE, np.uint8)

    def symbols(self, text: str) -> np.ndarray:
        """Code points of letters, 1 for anything else."""
        points = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
        return np.where(letters()[points], points, np.uint32(1))

    @np.errstate(over="ignore")
    def codes(self, text: str) -> list[np.ndarray]:
        s = self.symbols(text)
        out, mixed = [], np.zeros(len(s), np.uint32)
        for n, (place, length) in enumerate(zip(PLACES, LENGTHS, strict=True)):
            if len(s) <= n:
                break
            mixed = mixed[: len(s) - n] + s[n:] * np.uint32(place)
            h = (mixed ^ (mixed >> np.uint32(15))) * np.uint32(length)
            out.append((h ^ (h >> np.uint32(13))) >> np.uint32(32 - BITS))
        return out

    def mark(self, text: str, columns: np.ndarray) -> tuple[np.ndarray, int, bool]:
        """Which of `columns` are present, the number of distinct n-grams, and whether there is a letter."""
        parts, flags = self.codes(text), self.flags
        for p in parts:
            flags[p] = 1
        row, n, letter = flags[columns], int(np.count_nonzero(flags)), any(map(str.isalpha, text))
        for p in parts:
            flags[p] = 0
        return row, n, letter


class KernelModel:
    """languages, the columns (n-gram codes) the landmarks hold, and for each its contribution to each language's value."""

    def __init__(self, languages: list[str], columns: np.ndarray, matrix: np.ndarray):
        self.languages, self.columns, self.matrix = languages, columns, matrix
        self.presence = Presence()

    def __reduce__(self):
        return KernelModel, (self.languages, self.columns, self.matrix)

    def values(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """The regression's value of each text and language, and whether the text has a letter."""
        rows = np.zeros((len(texts), len(self.columns)), np.float32)
        sizes, letters = np.ones(len(texts)), np.zeros(len(texts), bool)
        for i, t in enumerate(texts):
            if t:
                rows[i], sizes[i], letters[i] = self.presence.mark(t, self.columns)
        return (rows @ self.matrix) / np.sqrt(sizes)[:, None], letters

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        if not self.languages:
            return ["und"] * len(texts), [0.0] * len(texts)
        values, letters = self.values(texts)
        best = values.argmax(1)
        odds = np.exp(6 * (values - values.max(1, keepdims=True)))
        share = 1 / odds.sum(1)
        return [self.languages[k] if ok else "und" for k, ok in zip(best, letters, strict=True)], [float(p) if ok else 0.0 for p, ok in zip(share, letters, strict=True)]


def fit_kernel_model(texts: list[str], langs: list[str], *, landmarks: int = LANDMARKS, ridge: float = 1e-2, seed: int = 11) -> KernelModel:
    kept = [(t, y) for t, y in zip(texts, langs, strict=True) if t and y is not None]
    languages = sorted({y for _, y in kept})
    if not kept:
        return KernelModel([], np.zeros(0, np.int64), np.zeros((0, 0), np.float32))
    presence, rng = Presence(), np.random.default_rng(seed)
    sets = [np.unique(np.concatenate(presence.codes(t))) for t, _ in kept]
    picked: list[int] = []  # an equal share of landmarks for each language
    for y in languages:
        own = [i for i, (_, z) in enumerate(kept) if z == y]
        picked += rng.permutation(own)[: max(1, landmarks // len(languages))].tolist()
    columns = np.unique(np.concatenate([sets[i] for i in picked]))
    place = np.full(SIZE, -1, np.int64)
    place[columns] = np.arange(len(columns))
    dense = lambda ids: np.stack([np.bincount(p[p >= 0], minlength=len(columns)) for p in (place[sets[i]] for i in ids)]).astype(np.float32)
    land = dense(picked) / np.sqrt([len(sets[i]) for i in picked])[:, None].astype(np.float32)
    vals, vecs = np.linalg.eigh(land @ land.T)
    root = vecs @ np.diag(1 / np.sqrt(np.maximum(vals, 1e-4))) @ vecs.T
    gram, target = np.zeros((len(picked), len(picked))), np.zeros((len(picked), len(languages)))
    for at in range(0, len(kept), 500):
        ids = range(at, min(at + 500, len(kept)))
        phi = (dense(ids) @ land.T) / np.sqrt([max(1, len(sets[i])) for i in ids])[:, None] @ root
        y = np.array([[float(kept[i][1] == c) for c in languages] for i in ids])
        gram += phi.T @ phi
        target += phi.T @ y
    weights = np.linalg.solve(gram + ridge * len(kept) / len(picked) * np.eye(len(picked)), target)
    return KernelModel(languages, columns, (land.T @ (root @ weights)).astype(np.float32))


def identify_language(docs: DataFrame, model: KernelModel, *, text: str = "text", keep_text: bool = True) -> DataFrame:
    """`docs` with lang_pred and score."""
    spark = docs.sparkSession
    bounded_batches(spark, 256)
    slim = docs.drop("lang_pred", "score")
    fields = [f for f in slim.schema if keep_text or f.name != text]
    shared = spark.sparkContext.broadcast(model)

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fitted = shared.value
        for b in batches:
            langs, scores = fitted.predict(b.column(text).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(f.name) for f in fields] + [pa.array(langs, pa.string()), pa.array(scores, pa.float64())], names=[f.name for f in fields] + ["lang_pred", "score"])

    return map_arrow(slim, body, ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in fields] + ["lang_pred string", "score double"]))


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    learn = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id"))).select("doc_id", "lang")
    model = fit_kernel_model(*bounded_sample(docs, learn, "lang", rows=FIT_ROWS, max_bytes=FIT_BYTES))
    out = identify_language(docs.select("doc_id", "text"), model, keep_text=False)
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
