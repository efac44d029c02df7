"""Offsets, powers, kernels, windows and archive files, each against a plain form of itself."""

import math
import random
import re
from pathlib import Path

import numpy as np

from sparkgraphs.llm import decontaminate, language_id, toxicity, warc


def test_offsets_are_those_of_the_text(spark):
    field = toxicity.SpanField({"=vile": 9.0}, -3.0, ((0.0, 0.0), (0.0, 0.0)), (0.0, 1.0, 1.0))
    text = "İİ vile x VILE"
    row = toxicity.score_toxicity(spark.createDataFrame([(1, text)], "doc_id long, text string"), field).first()
    assert [(text[s.start : s.end], s.word) for s in row.toxic_spans] == [("vile", "vile"), ("VILE", "vile")]


def test_long_runs_of_unknown_words_are_exact():
    field = toxicity.SpanField({"=bad": 1.5}, -0.02, ((0.01, -0.02), (-0.015, 0.012)))
    words = ["u"] * 400 + ["bad"] + ["u"] * 700 + ["bad"] + ["u"] * 300
    t, e = np.exp(np.array(field.trans)), [np.array([1, math.exp(field.weights.get("=" + w, field.bias))]) for w in words]
    f, b = [e[0] / e[0].sum()], [np.ones(2)]
    for x in e[1:]:
        f.append((f[-1] @ t) * x)
        f[-1] = f[-1] / f[-1].sum()
    for x in e[:0:-1]:
        b.append(t @ (x * b[-1]))
        b[-1] = b[-1] / b[-1].sum()
    p = [x * y for x, y in zip(f, b[::-1], strict=True)]
    assert np.allclose([q for _, q in field.marginals(words)], [p[i][1] / p[i].sum() for i in (400, 1101)], atol=1e-9)


def test_toxicity_ranks_held_out_documents(spark):
    """The area under the curve on the quarter that fitting never sees (about a tenth of the toxic labels are on texts without a toxic word)."""
    sf = "/root/testdata/sf0.1"
    out = toxicity.op5_toxicity(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet").groupBy("doc_id").max("toxic").withColumnRenamed("max(toxic)", "toxic"), "doc_id")
    rows = out.where("held_out AND toxic IS NOT NULL").select("score", "toxic").collect()
    good, bad = ([r.score for r in rows if r.toxic == k] for k in (0, 1))
    wins = sum((x < y) + (x == y) / 2 for x in good for y in bad)
    assert len(bad) >= 50 and wins / (len(good) * len(bad)) > 0.9


def test_kernel_model_against_explicit_kernels():
    random.seed(5)
    alphabets = {"aa": "abcdeé", "bb": "абвгде", "cc": "ႠႡႢ𐐨𐐩漢"}
    texts = ["".join(random.choices(alphabets[y] + "  ", k=random.randint(8, 60))) for y in alphabets for _ in range(12)]
    langs = [y for y in alphabets for _ in range(12)]
    model = language_id.fit_kernel_model(texts, langs, landmarks=36, ridge=0.5)
    grams = lambda t: {g for n in (1, 2, 3) for i in range(len(t) - n + 1) for g in [t[i : i + n]]}
    sets = [grams("".join(c if c.isalpha() else " " for c in t.lower())) for t in texts]
    k = np.array([[len(x & y) / math.sqrt(len(x) * len(y)) for y in sets] for x in sets])
    # with all texts as landmarks the features are those of the kernel's square root
    vals, vecs = np.linalg.eigh(k)
    root = vecs @ np.diag(1 / np.sqrt(np.maximum(vals, 1e-4))) @ vecs.T
    phi = k @ root
    y = np.array([[float(z == c) for c in sorted(alphabets)] for z in langs])
    want = phi @ np.linalg.solve(phi.T @ phi + 0.5 * np.eye(len(texts)), phi.T @ y)
    assert np.abs(model.values(texts)[0] - want).max() < 2e-3
    assert model.predict(["𐐨𐐩漢", "漢", "вгд"])[0] == ["cc", "cc", "bb"]


def test_decontamination_against_brute_force(spark):
    """Every document and item by plain dynamic programming, short items included."""

    def least(p, t):
        row = [0] * (len(t) + 1)
        for i in range(1, len(p) + 1):
            new = [i]
            for j in range(1, len(t) + 1):
                new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (p[i - 1] != t[j - 1])))
            row = new
        return min(row)

    random.seed(8)
    words = ["alpha", "beta", "gamma", "delta", "eps", "zeta"]
    items = [" ".join(random.choices(words, k=k)) for k in (1, 2, 3, 5, 8, 12, 12)]
    texts = [None, "", "..."]
    for item in items:
        spoiled = list(item)
        spoiled[random.randrange(len(spoiled))] = "q"
        texts += [f"x {item.upper()}, y", f"{''.join(spoiled)} z " * 2, f"pre{item}"]
    texts += [" ".join(random.choices(words, k=40)) for _ in range(6)]
    want = set()
    for d, t in enumerate(texts):
        text = decontaminate.normalise(t)
        for i, item in enumerate(items):
            budget = int(decontaminate.ERROR_RATE * len(item))
            exact = re.search(rf"(?<!\S){re.escape(item)}(?!\S)", text) is not None
            if exact if not budget else least(item, text) <= budget:
                want.add((d, i, 0 if not budget else least(item, text)))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = {(r.doc_id, r.item_id, r.distance) for r in decontaminate.contaminated(df, bench).collect()}
    assert {(d, i) for d, i, _ in got} == {(d, i) for d, i, _ in want}
    assert {r.doc_id for r in decontaminate.drop_contaminated(df, bench).collect()} == set(range(len(texts))) - {d for d, _, _ in want}


def test_archive_files_are_bounded(spark, tmp_path):
    """Huge pages between many small ones, repeated rows and a null id: files hold at most twice the bytes asked for, or one record."""
    rows = [(i, f"http://h/{i}", "x" * (200_000 if i % 50 == 0 else 100) + str(i)) for i in range(400)] + [(7, "u", "same"), (7, "u", "same"), (None, "n", "same")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)
    path = tmp_path / "warc"
    warc.write_warc(warc.resolve_revisits(pages), str(path), file_bytes=64 << 10)
    for f in path.rglob("part-*"):
        records = list(warc.parse_warc(f.read_bytes()))
        assert f.stat().st_size <= 2 * (64 << 10) + 2048 or len(records) == 1
    out = warc.read_warc(spark, str(path))
    assert out.count() == len(rows) and out.where("record_type = 'revisit'").count() == 0 or out.where("record_type = 'revisit'").first().record_id == "<urn:x-page:null>"
