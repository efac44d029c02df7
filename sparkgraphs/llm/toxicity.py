"""Toxic spans by a linear-chain conditional random field.

Fitting uses at most `fit_rows` labelled rows and `fit_bytes` of their text, taken in the order of a hash of the id (a documented
bound; scoring covers all texts). Document labels become token labels by weak supervision: words are picked greedily that explain
labelled documents not explained so far and hardly occur in clean ones; their occurrences in toxic documents are the toxic tokens.
The field has two states, an emission weight per known word or word beginning, a bias for all other words, and a transition matrix, fitted by
gradient ascent of its likelihood on token windows. In a text, runs of unknown words are powers of one matrix, so
forward-backward costs a step per known word and is exact for texts of any length. Offsets are those of the text itself. Marginals give offending spans and, through a logistic function fitted
on the same rows, document scores.

Defined cases: null and empty texts have no spans and the score of a text without known words; labels other than 0 and 1, null ids
and labels without a document are left out of fitting; a document labelled twice counts as toxic if any label says so; without
toxic labels every score is next to 0; repeated rows are scored alike; extra columns pass
through, but for those named like the new ones, which are replaced.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_batches, bounded_sample, held_out, map_arrow, table
from .token_counts import Memo

FIT_ROWS, FIT_BYTES, THRESHOLD = 6_000, 32 << 20, 0.3
WORD = re.compile(r"[^\W\d_]+")
#: Lengths of the word beginnings that may serve as features, the longest first.
PREFIXES = (6, 5, 4)
SPANS = "array<struct<start:int,end:int,word:string,p:double>>"


@dataclass
class SpanField:
    """The fitted field. weights: feature (word or beginning) to emission of the toxic state; bias: that of other words;
    trans[i][j]: log potential of i, j."""

    weights: dict[str, float] = field(default_factory=dict)
    bias: float = -8.0
    trans: tuple = ((0.0, 0.0), (0.0, 0.0))
    logistic: tuple = (-8.0, 0.0, 0.0)

    def __post_init__(self):
        t, e = np.exp(np.array(self.trans)), np.array([1.0, math.exp(self.bias)])
        self.step = t * e[None, :]
        self.powers = Memo(self._power, 1 << 12)
        self.enter = {f: ((t * np.array([1.0, math.exp(x)])[None, :]).tolist(), math.exp(x)) for f, x in self.weights.items()}
        self.feature = Memo(lambda w: next((f for f in word_features(w.lower()) if f in self.weights), None), 1 << 16)

    def _power(self, gap: int) -> list[list[float]]:
        """The step matrix to the power of `gap`, normalised: common factors do not matter."""
        if gap < 2:
            return (self.step / self.step.max()).tolist() if gap else np.eye(2).tolist()
        half, rest = np.array(self.powers[gap // 2]), np.array(self.powers[gap % 2])
        power = half @ half @ rest
        return (power / power.max()).tolist()

    def __reduce__(self):
        return SpanField, (self.weights, self.bias, self.trans, self.logistic)

    def marginals(self, words: list[str]) -> list[tuple[int, float]]:
        """(position, probability of the toxic state) of each known word."""
        marks = list(map(self.feature.__getitem__, words))
        if not any(marks):
            return []
        at = [i for i, f in enumerate(marks) if f]
        first = np.exp(self.bias)
        forward, a, last = [], None, -1
        for i in at:
            m, e = self.enter[marks[i]]
            if i == 0:
                a = (1.0, e)
            else:
                a = self._through((1.0, first), i - last - 2) if last < 0 else self._through(a, i - last - 1)
                a = (a[0] * m[0][0] + a[1] * m[1][0], a[0] * m[0][1] + a[1] * m[1][1])
            s = a[0] + a[1]
            a = (a[0] / s, a[1] / s)
            forward.append(a)
            last = i
        out, b, nxt = [], (1.0, 1.0), len(words)
        for k in range(len(at) - 1, -1, -1):
            i = at[k]
            p = self.powers[nxt - i - 1]
            b = (p[0][0] * b[0] + p[0][1] * b[1], p[1][0] * b[0] + p[1][1] * b[1])
            f = forward[k]
            x, y = f[0] * b[0], f[1] * b[1]
            out.append((i, y / (x + y)))
            m, _ = self.enter[marks[i]]
            b = (m[0][0] * b[0] + m[0][1] * b[1], m[1][0] * b[0] + m[1][1] * b[1])
            s = b[0] + b[1]
            b, nxt = (b[0] / s, b[1] / s), i
        return out[::-1]

    def _through(self, a: tuple, gap: int) -> tuple:
        p = self.powers[gap]
        return a[0] * p[0][0] + a[1] * p[1][0], a[0] * p[0][1] + a[1] * p[1][1]

    def score(self, marginals: list[tuple[int, float]]) -> float:
        total, most = sum(p for _, p in marginals), max((p for _, p in marginals), default=0.0)
        z = self.logistic[0] + self.logistic[1] * math.log1p(total) + self.logistic[2] * most
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def word_features(word: str) -> list[str]:
    """A word itself and its beginnings: inflected and compounded forms share those."""
    return ["=" + word, *(word[:n] for n in PREFIXES if len(word) > n)]


def telling_features(texts: list[list[str]], labels: list[int], most: int = 200) -> list[str]:
    """Features that explain toxic documents: greedily, each the best for those not yet explained, charged for clean documents.

    Features that merely come with a chosen one (through copies of a document) have nothing left to explain and are not taken.
    """
    left = [{f for w in set(t) for f in word_features(w)} for t, y in zip(texts, labels, strict=True) if y]
    toxic = Counter(f for s in left for f in s)
    usual = {f for f, n in toxic.items() if n >= 2}
    clean: Counter = Counter()  # documents by word: an upper bound for beginnings
    for w, n in Counter(w for t, y in zip(texts, labels, strict=True) if not y for w in set(t)).items():
        for f in word_features(w):
            if f in usual:
                clean[f] += n
    gain, found = Counter(toxic), []
    rank = lambda f: (gain[f] - 2 * clean[f], len(f), f)
    least = max(2, 0.003 * len(left))
    while left and usual and len(found) < most:
        best = max(usual, key=rank)
        if gain[best] - 2 * clean[best] < least:
            break
        found.append(best)
        usual.discard(best)
        for s in left:
            if best in s:
                gain.subtract(s)
        left = [s for s in left if best not in s]
    # explained documents hold further telling words: those about as frequent as the chosen ones, if not forms of them
    if found:
        wide = 0.2 * sorted(toxic[f] for f in found)[len(found) // 2]
        stem = lambda f: f.lstrip("=")
        for f in sorted(usual, key=lambda f: (-toxic[f], -len(f), f)):
            if toxic[f] < max(3, wide) or len(found) >= most:
                break
            if toxic[f] > 20 * clean[f] and not any((stem(g).startswith(stem(f)) or stem(f).startswith(stem(g))) and toxic[f] <= 1.1 * toxic[g] for g in found):
                found.append(f)
    return found


def fit_field(texts: list[list[str]], labels: list[int], *, width: int = 16, windows: int = 4_000, steps: int = 80, rate: float = 0.3, l2: float = 1e-3, seed: int = 7) -> SpanField:
    rng = np.random.default_rng(seed)
    positives = sum(labels)
    if not positives:
        return SpanField(logistic=(-30.0, 0.0, 0.0))
    chosen = telling_features(texts, labels)
    model = SpanField({f: 0.0 for f in chosen})
    counts = Counter(w for t in texts for w in t)
    common = [w for w, _ in counts.most_common(200) if not model.feature[w]]
    index = {f: i + 1 for i, f in enumerate(chosen)} | {w: i + 1 + len(chosen) for i, w in enumerate(common)}
    n_toxic = len(chosen)
    xs, ys = [], []
    for k in rng.permutation(len(texts)):
        t, y = texts[k], labels[k]
        if len(xs) >= windows:
            break
        ids = [index.get(model.feature[w] or w, 0) for w in t]
        toxic_at = [i for i, k in enumerate(ids) if 0 < k <= n_toxic]
        centres = toxic_at[:4] + ([int(rng.integers(len(ids)))] if ids else [])
        for c in centres:
            lo = max(0, c - width // 2)
            x = ids[lo : lo + width]
            xs.append(x + [-1] * (width - len(x)))
            ys.append([int(bool(y) and 0 < k <= n_toxic) for k in x] + [0] * (width - len(x)))
    x, y = np.array(xs).reshape(-1, width), np.array(ys).reshape(-1, width)
    live = x >= 0
    x = np.where(live, x, 0)
    n = len(x)
    w, a = np.zeros(len(index) + 1), np.zeros((2, 2))
    w[0] = -3.0
    state = [np.zeros_like(w), np.zeros_like(w), np.zeros_like(a), np.zeros_like(a)]
    for step in range(1, steps + 1):
        e1 = np.where(live, np.exp(np.clip(w[x] + (x > 0) * w[0], -30, 30)), 1.0)
        e = np.stack([np.ones_like(e1), e1], -1)
        t = np.exp(a)
        f, b = np.zeros((n, width, 2)), np.ones((n, width, 2))
        f[:, 0] = e[:, 0] / e[:, 0].sum(-1, keepdims=True)
        for i in range(1, width):
            nxt = (f[:, i - 1] @ t) * e[:, i]
            f[:, i] = np.where(live[:, i, None], nxt / nxt.sum(-1, keepdims=True), f[:, i - 1])
        for i in range(width - 2, -1, -1):
            nxt = (e[:, i + 1] * b[:, i + 1]) @ t.T
            b[:, i] = np.where(live[:, i + 1, None], nxt / nxt.sum(-1, keepdims=True), 1.0)
        p = f * b
        p1 = np.where(live, p[..., 1] / p.sum(-1), 0.0)
        both = live[:, 1:]
        pair = f[:, :-1, :, None] * t[None, None] * (e[:, 1:] * b[:, 1:])[:, :, None, :]
        pair = pair / pair.sum((-1, -2), keepdims=True) * both[..., None, None]
        seen = np.zeros((2, 2))
        for i in (0, 1):
            for j in (0, 1):
                seen[i, j] = ((y[:, :-1] == i) & (y[:, 1:] == j) & both).sum()
        diff = (y - p1) * live
        gw = np.bincount(x.ravel(), diff.ravel(), minlength=len(w))
        gw[0] = diff.sum()  # the bias is shared by all words
        gw, ga = gw / n - l2 * w * (np.arange(len(w)) > 0), (seen - pair.sum((0, 1))) / n - l2 * a
        for k, (g, v) in enumerate(((gw, w), (ga, a))):
            m1, m2 = state[2 * k], state[2 * k + 1]
            m1 += 0.1 * (g - m1)
            m2 += 0.01 * (g * g - m2)
            v += rate * (m1 / (1 - 0.9**step)) / (np.sqrt(m2 / (1 - 0.99**step)) + 1e-8)
    weights = {f: float(np.clip(w[i] + w[0], -30, 30)) for f, i in index.items() if i <= n_toxic}
    model = SpanField(weights, float(np.clip(w[0], -30, 30)), tuple(map(tuple, a.tolist())))
    rows = np.array([[1.0, math.log1p(sum(p for _, p in m)), max((p for _, p in m), default=0.0)] for m in map(model.marginals, texts)])
    target, theta = np.array(labels, float), np.zeros(3)
    for _ in range(50):  # Newton's method with a small ridge
        q = 1 / (1 + np.exp(-np.clip(rows @ theta, -30, 30)))
        hess = rows.T @ (rows * (q * (1 - q))[:, None]) + 1e-2 * np.eye(3)
        theta = theta + np.linalg.solve(hess, rows.T @ (target - q) - 1e-2 * theta)
    model.logistic = tuple(theta.tolist())
    return model


def fit_rows(docs: DataFrame, labels: DataFrame, *, rows: int = FIT_ROWS, max_bytes: int = FIT_BYTES) -> tuple[list[list[str]], list[int]]:
    """The bounded sample: labelled rows outside the held-out quarter, in the order of a hash of their id."""
    seed = (
        labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
        .groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    )
    texts, toxic = bounded_sample(docs, seed, "toxic", rows=rows, max_bytes=max_bytes)
    same: dict[str, str] = {}  # one object for each word
    return [[same.setdefault(w, w) for w in map(str.lower, WORD.findall(t or ""))] for t in texts], toxic


def score_toxicity(docs: DataFrame, model: SpanField, *, text: str = "text", threshold: float = THRESHOLD, spans: bool = True, keep_text: bool = True) -> DataFrame:
    """`docs` with score, predicted and (`spans`) toxic_spans: character offsets, word and marginal of each toxic token."""
    bounded_batches(docs.sparkSession)
    new = ["score", "predicted"] + ["toxic_spans"] * spans
    slim = docs.drop(*new)
    fields = [f for f in slim.schema if keep_text or f.name != text]
    kind = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("word", pa.string()), ("p", pa.float64())]))

    def body(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blank = model.score([])
        for b in batches:
            scores, found = [], []
            for t in b.column(text).to_pylist():
                words = WORD.findall(t) if t else []
                marks = model.marginals(words)
                if not marks:
                    scores.append(blank)
                    found.append([])
                    continue
                scores.append(model.score(marks))
                if spans:
                    places = [m.span() for m in WORD.finditer(t)]
                    found.append([{"start": places[i][0], "end": places[i][1], "word": words[i].lower(), "p": p} for i, p in marks if p >= 0.5])
            columns = [b.column(f.name) for f in fields]
            columns += [pa.array(scores, pa.float64()), pa.array([int(s >= threshold) for s in scores], pa.int32())]
            columns += [pa.array(found, kind)] if spans else []
            yield pa.RecordBatch.from_arrays(columns, names=[f.name for f in fields] + new)

    schema = [f"`{f.name}` {f.dataType.simpleString()}" for f in fields] + ["score double", "predicted int"] + [f"toxic_spans {SPANS}"] * spans
    return map_arrow(slim, body, ", ".join(schema))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit_field(*fit_rows(docs, table(spark, sf_dir, "labels")))
    scored = score_toxicity(docs, model, spans=False, keep_text=False)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")
