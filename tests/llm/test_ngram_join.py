"""The n-gram join against brute force: repeated ids, hubs, large groups of near copies, passages."""

import random

import pytest

from sparkgraphs.llm import ngram_join


def brute(rows, n, percent):
    """(component by doc_id) of (doc_id, text) rows: every pair of sets is compared."""
    sets = []
    for _, t in rows:
        w = (t or "").lower().split()
        sets.append({tuple(w[k : k + n]) for k in range(max(1, len(w) - n + 1))} if w else set())
    forest = ngram_join.Forest()
    for i, x in enumerate(sets):
        forest.root(rows[i][0])
        for j in range(i):
            both = len(x & sets[j])
            if both and 100 * both >= percent * (len(x) + len(sets[j]) - both):
                forest.join(rows[i][0], rows[j][0])
    return sets, {d: forest.root(d) for d, _ in rows}


def check(spark, rows, n=5, percent=80):
    df = spark.createDataFrame(rows, "doc_id long, text string")
    sets, component = brute(rows, n, percent)
    out = sorted((r.doc, r.n_shingles, r.component) for r in ngram_join.similar_documents(df, n=n, percent=percent).collect())
    assert out == sorted((d, len(s), component[d]) for (d, _), s in zip(rows, sets, strict=True))
    return component


def words(rng, size, vocabulary=500):
    return [f"w{rng.randrange(vocabulary)}" for _ in range(size)]


def edited(rng, base, edits):
    copy = list(base)
    for k in range(edits):
        copy[rng.randrange(len(copy))] = f"x{rng.random()}"
    return copy


def test_rows_that_share_a_doc_id_are_one_document(spark):
    rng = random.Random(1)
    a, b = words(rng, 60), words(rng, 60)
    rows = [(5, " ".join(a)), (3, " ".join(a)), (5, " ".join(b)), (7, " ".join([*b, "more"])), (9, None), (9, " ".join(a)), (8, ""), (5, " ".join(a))]
    component = check(spark, rows)
    assert component == {5: 3, 3: 3, 7: 3, 9: 3, 8: 8}
    assert {r.doc_id for r in ngram_join.keep_one_of_each(spark.createDataFrame(rows, "doc_id long, text string")).collect()} == {3, 8}


@pytest.mark.parametrize("small,n,percent", [(3, 5, 80), (32, 3, 90)])
def test_groups_of_near_copies_and_common_passages(spark, monkeypatch, small, n, percent):
    """Lists longer than `small` take the way by rarity, leaders and blocks."""
    monkeypatch.setattr(ngram_join, "SMALL_LIST", small)
    monkeypatch.setattr(ngram_join, "BLOCK_DOCS", 4)
    monkeypatch.setattr(ngram_join, "LEADER_PAIRS", 8)
    rng = random.Random(small)
    texts = []
    base = words(rng, 150)
    texts += [edited(rng, base, rng.randint(0, 6)) for _ in range(50)]  # copies of copies: some reach others only through third ones
    passage = words(rng, 60)
    texts += [words(rng, rng.randint(8, 40)) + passage + words(rng, rng.randint(8, 40)) for _ in range(40)]  # dissimilar: the passage is not enough
    texts += [words(rng, 3) + passage + words(rng, rng.randint(2, 9)) for _ in range(30)]  # at the edge of being similar
    chain = words(rng, 100)
    for _ in range(12):
        chain = chain[2:] + words(rng, 2)
        texts.append(list(chain))
    texts += [words(rng, s) for s in (1, 2, 4, 5, 6, 400) for _ in range(3)]
    rows = [(i, " ".join(t)) for i, t in enumerate(texts)] + [(1000 + i, " ".join(texts[i]).upper()) for i in range(0, 60, 7)]
    rng.shuffle(rows)
    assert len(set(check(spark, rows, n, percent).values())) > 40


def test_nulls_and_extra_columns(spark):
    df = spark.createDataFrame([(None, "a b c d e f", 1), (1, "a b c d e f", 2), (2, "A B c d e f", 3), (3, None, 4)], "doc_id long, text string, component long")
    out = sorted(((r.doc, r.component) for r in ngram_join.similar_documents(df).collect()), key=repr)
    assert out == sorted([(None, None), (1, 1), (2, 1), (3, 3)], key=repr)
    assert ngram_join.keep_one_of_each(df).columns == df.columns
