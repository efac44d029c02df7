import hashlib
import json
import random
from collections import defaultdict

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from sparkgraphs.llm import bpe_codec, decontaminate, embedding_dedup, language_id, line_dedup, ngram_join, surrogates, token_counts, toxicity, warc
from sparkgraphs.llm.components import components
from sparkgraphs.llm.common import Stages

TEXTS = ["a  b", "<|endoftext|> hi<|endoftext|>", "don't  we'll \n\n x\t y ", " lead", "tail ", "Ünï İstanbul ΑΣ é 123 4½²", "日本語 text!!! ...", "a\x1cb", "", None, "\n", " \n a", "foo\n bar", "word " * 3000]


def docs(spark, texts, **extra):
    rows = [(i, t, *(v for v in extra.values())) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string" + "".join(f", {k} string" for k in extra))


def got(df, *columns):
    return sorted((tuple(r[c] for c in columns) for r in df.collect()), key=repr)


def test_token_counts_match_the_library(spark):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    out = {r.doc_id: r for r in token_counts.token_counts(docs(spark, TEXTS, n_tokens="clash"), path, entries=64).collect()}
    for i, t in enumerate(TEXTS):
        assert out[i].n_tokens == len(library.encode(t or "", add_special_tokens=False).ids) and out[i].n_bytes == len((t or "").encode())
    assert out[len(TEXTS) - 1].over_limit
    assert token_counts.token_counts(docs(spark, []), path).count() == 0


def test_codec_matches_the_library_with_any_lexicon(spark):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    for lexicon in (None, bpe_codec.compile_lexicon({})):
        for r in bpe_codec.encode_decode(docs(spark, TEXTS, bpe_ids="clash"), path, lexicon=lexicon, entries=64).collect():
            ids = library.encode(TEXTS[r.doc_id] or "", add_special_tokens=False).ids
            assert r.bpe_ids == ids and r.bpe_text == library.decode(ids, skip_special_tokens=False)
    assert bpe_codec.encode_decode(docs(spark, []), path).count() == 0


def test_lexicon_is_minimal_and_exact():
    words = {w: [i, i + 1] for i, w in enumerate(["tap", "taps", "top", "tops", "é", "日本"])}
    lexicon = bpe_codec.MappedLexicon(bpe_codec.compile_lexicon(words))
    assert all(lexicon.ids(w.encode()) == ids for w, ids in words.items()) and lexicon.ids(b"ta") is None and lexicon.ids(b"tapsx") is None
    assert lexicon.n_states == 4 + 2 + 6 - 1 - 0 - 1 or lexicon.n_states < sum(len(w.encode()) for w in words)


def test_short_merging_equals_heap_merging():
    rank = {(a, b): i for i, (a, b) in enumerate([("a", "b"), ("ab", "a"), ("b", "a"), ("ab", "ab"), ("c", "c"), ("cc", "c")])}
    random.seed(3)
    for _ in range(300):
        s = [random.choice("abc") for _ in range(random.randint(1, 14))]
        assert bpe_codec.merged_short(list(s), rank) == token_counts.merges_left(list(s), rank)


def test_line_dedup(spark):
    long = "x" * 40
    texts = [f" {long.upper()}\t\nown line {i}" for i in range(5)] + [None, "", f"{long}\n{long}", "short\nshort"]
    out = {r.doc_id: r for r in line_dedup.dedup_lines(docs(spark, texts, n_lines="clash", source="s")).collect()}
    assert [out[i].text for i in range(4)] == [f"own line {i}" for i in range(4)] and out[4].text == "own line 4"
    assert out[7].text == f"{long}\n{long}" and out[7].n_dropped == 0 and out[7].source == "s"  # the largest doc_id keeps all of them
    assert (out[5].text, out[5].n_lines, out[6].n_lines, out[8].n_lines) == ("", 1, 1, 2)
    assert line_dedup.dedup_lines(docs(spark, [])).count() == 0


def test_warc_round_trip(spark, tmp_path):
    nasty = "\r\n\r\nWARC/1.1\r\nContent-Length: 3\r\n\r\nabc"
    rows = [(1, "http://a/", "same"), (2, "http://b/\r\nX: y", "same"), (3, None, "same"), (4, "http://d/", nasty), (5, "http://e/", None), (6, "http://f/", "é" * 5000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    path = str(tmp_path / "warc")
    warc.write_warc(warc.resolve_revisits(pages), path, date="2020-01-01T00:00:00Z")
    out = {r.record_id: r for r in warc.read_warc(spark, path).collect()}
    kinds = {i: out[f"<urn:x-page:{i}>"] for i in range(1, 7)}
    assert [kinds[i].record_type for i in range(1, 7)] == ["revisit", "revisit", "response", "response", "response", "response"]
    assert kinds[1].refers_to == "<urn:x-page:3>" and kinds[1].payload is None and kinds[1].payload_bytes == 4
    assert bytes(kinds[4].payload).decode() == nasty and kinds[6].payload_bytes == 10000 and "\r" not in kinds[2].target_uri
    empty = str(tmp_path / "none")
    warc.write_warc(warc.resolve_revisits(pages.limit(0)), empty)
    assert warc.read_warc(spark, empty).count() == 0


@pytest.mark.parametrize("n,percent", [(3, 90), (5, 80)])
def test_ngram_join_against_brute_force(spark, n, percent):
    random.seed(n)
    vocabulary = [f"w{i}" for i in range(400)]
    texts = [None, "", "  \n", "one two", "One TWO", "a", "a"]
    for size in (6, 12, 30, 90, 300):
        base = [random.choice(vocabulary) for _ in range(size)]
        for _ in range(8):
            copy = list(base)
            for _ in range(random.randint(0, max(1, size // 25))):
                copy[random.randrange(size)] = random.choice(vocabulary)
            texts.append(" ".join(copy))
    base = [random.choice(vocabulary) for _ in range(120)]  # a group larger than SMALL_LIST
    for i in range(50):
        copy = list(base)
        copy[random.randrange(120)] = f"x{i}"
        texts.append(" ".join(copy))
    sets = {}
    for i, t in enumerate(texts):
        w = (t or "").lower().split()
        sets[i] = {tuple(w[k : k + n]) for k in range(max(1, len(w) - n + 1))} if w else set()
    forest = ngram_join.Forest()
    for i in sets:
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both and 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                forest.join(i, j)
    out = ngram_join.similar_documents(docs(spark, texts, component="clash"), n=n, percent=percent)
    assert got(out, "doc", "n_shingles", "component") == sorted(((i, len(s), forest.root(i)) for i, s in sets.items()), key=repr)
    kept = ngram_join.keep_one_of_each(docs(spark, texts), n=n, percent=percent)
    assert {r.doc_id for r in kept.collect()} == {forest.root(i) for i in sets}


def test_ngram_join_of_nothing(spark):
    assert ngram_join.similar_documents(docs(spark, [])).count() == 0


def test_blocks_between_two_sides():
    rng = np.random.default_rng(1)
    base = np.unique(rng.integers(0, 1 << 60, 50, dtype=np.uint64))
    near = np.sort(np.append(base[1:], np.uint64(7)))
    assert ngram_join.block_links([(1, base)], [(2, near)], 90) == [(1, 2)]
    assert ngram_join.block_links([(1, base), (3, near)], [(2, rng.integers(0, 9, 3, dtype=np.uint64))], 90) == []  # pairs within a side are others' work


def test_embedding_links_against_brute_force(spark):
    rng = np.random.default_rng(5)
    rows = []
    for c in range(12):
        centre = rng.standard_normal(32)
        rows += [(centre + rng.standard_normal(32) * s).tolist() for s in (0.01, 0.1, 0.2, 0.25, 0.3, 1.0)]
    rows += [rows[0], rows[0], [0.0] * 32, None, [float("nan")] + [1.0] * 31, [None] + [1.0] * 31, [1.0] * 16, []]
    x = [None if r is None or len(r) != 32 or None in r or not np.isfinite(r).all() or not np.any(r) else np.array(r) / np.linalg.norm(r) for r in rows]
    forest, links = ngram_join.Forest(), defaultdict(int)
    for i in range(len(rows)):
        for j in range(i):
            if x[i] is not None and x[j] is not None and x[i] @ x[j] >= 0.95:
                forest.join(i, j)
                links[i] += 1
                links[j] += 1
    df = spark.createDataFrame([(i, r) for i, r in enumerate(rows)], "vec_id long, embedding array<double>")
    want = [(i, links[i], forest.root(i), forest.root(i) == i) for i in range(len(rows))]
    for block in (512, 7):
        assert got(embedding_dedup.near_duplicates(df, block=block), "vec_id", "n_links", "component_id", "kept") == sorted(want, key=repr)
    assert embedding_dedup.near_duplicates(df.limit(0)).count() == 0


def test_estimates_are_unbiased():
    rng = np.random.default_rng(2)
    u = rng.standard_normal((400, 64))
    u /= np.linalg.norm(u, axis=1, keepdims=True)
    errors = []
    for seed in range(30):
        turn = embedding_dedup.Rotations(64, 64, seed)
        signs, factor = turn.codes(u)
        est = np.where(signs, 1.0, -1.0) @ (u @ turn.turns[:, :64]).T / 8.0 / factor[:, None]
        errors.append(est - u @ u.T)
    assert abs(np.mean(errors)) < 1e-3 and np.abs(errors).max() < 1.0


def test_field_marginals_are_exact():
    import itertools
    import math

    field = toxicity.SpanField({"=bad": 1.0, "wors": 0.5}, -2.0, ((0.1, -0.3), (-0.2, 0.6)))
    words = ["fine", "bad", "ok", "ok", "worse", "bad", "end"]
    t = np.exp(np.array(field.trans))
    e = [np.array([1, math.exp(field.weights.get(field.feature[w], field.bias))]) for w in words]
    total, mass = 0.0, np.zeros(len(words))
    for s in itertools.product((0, 1), repeat=len(words)):
        p = e[0][s[0]] * math.prod(t[s[i - 1]][s[i]] * e[i][s[i]] for i in range(1, len(words)))
        total, mass = total + p, mass + p * np.array(s)
    assert np.allclose([p for _, p in field.marginals(words)], [mass[i] / total for i in (1, 4, 5)])


def test_toxic_spans(spark):
    random.seed(1)
    clean = [f"w{i}" for i in range(80)]
    texts, labels = [], []
    for i in range(400):
        words = random.choices(clean, k=20)
        if i % 5 == 0:
            words[7], words[12] = random.sample(["vile", "nasty", "rotten"], 2)
        texts.append(" ".join(words))
        labels.append(int(i % 5 == 0))
    model = toxicity.fit_field([t.split() for t in texts], labels)
    out = toxicity.score_toxicity(docs(spark, ["a vile and Rotten w1", "w1 w2", "", None], score="clash"), model).orderBy("doc_id").collect()
    assert [r.predicted for r in out] == [1, 0, 0, 0] and [(s.start, s.end, s.word) for s in out[0].toxic_spans] == [(2, 6, "vile"), (11, 17, "rotten")]
    nothing = toxicity.fit_field([], [])
    assert toxicity.score_toxicity(docs(spark, ["x"]), nothing).first().predicted == 0


def test_edit_matching(spark):
    item = "The quick brown fox jumps over the lazy dog while seven wizards mix potions"
    off = item.replace("quick", "quack").replace("wizards", "wizard")
    bench = spark.createDataFrame([(1, item), (2, None), (3, "short"), (1, item)], "item_id long, text string")
    df = docs(spark, ["before, " + item.upper() + "!", "x " + off + " y", "the quick brown fox only", None, ""], distance="clash")
    assert got(decontaminate.contaminated(df, bench).distinct(), "doc_id", "item_id", "distance") == [(0, 1, 0), (1, 1, 2)]
    assert [r.doc_id for r in decontaminate.drop_contaminated(df, bench).orderBy("doc_id").collect()] == [2, 3, 4]
    assert decontaminate.drop_contaminated(df, bench.limit(0)).count() == 5 and decontaminate.contaminated(df.limit(0), bench).count() == 0


def test_bit_parallel_distance():
    def plain(p, t):
        row = [0] * (len(t) + 1)
        for i in range(1, len(p) + 1):
            new = [i]
            for j in range(1, len(t) + 1):
                new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (p[i - 1] != t[j - 1])))
            row = new
        return min(row)

    random.seed(4)
    for _ in range(200):
        p, t = ("".join(random.choices("ab c", k=random.randint(lo, 20))) for lo in (1, 0))
        assert decontaminate.best_match(p, t, 98) == plain(p, t)


def test_languages(spark):
    words = {"aa": ["kala", "mana", "tala"], "bb": ["ßtor", "çrek", "öpfe"], "cc": ["xyz", "zyx", "yxq"]}
    random.seed(2)
    texts = [(" ".join(random.choices(words[y], k=12)), y) for y in words for _ in range(60)]
    model = language_id.fit_kernel_model([t for t, _ in texts], [y for _, y in texts], landmarks=30)
    out = language_id.identify_language(docs(spark, ["kala mana tala", "ßtor çrek öpfe", "xyz zyx", "123 !", "", None, "𝔸 kala mana"], score="clash"), model).orderBy("doc_id").collect()
    assert [r.lang_pred for r in out] == ["aa", "bb", "cc", "und", "und", "und", "aa"] and out[3].score == 0.0
    assert language_id.identify_language(docs(spark, ["abc"]), language_id.fit_kernel_model([], [])).first().lang_pred == "und"


def test_surrogates(spark):
    texts = ["call +1 (988) 555-2485 or +1-988-555-2485, a.b42@Mail8.example.com and card 4041894974608795", "4041894974608795 again; Mr. John Smith, Frau Müller", None, "", "clean 4.0 text", "4041894974608795 again; Mr. John Smith, Frau Müller"]
    out = {r.doc_id: r for r in surrogates.replace_entities(docs(spark, texts, kinds="clash"), "key").collect()}
    assert out[2].text is None and out[3].text == "" and out[4].text == texts[4] and out[4].n_entities == 0
    assert not any(x in out[0].text for x in ("2485", "a.b42", "4041894974608795")) and out[0].n_entities == 4
    a, b = out[0].text.split("call ")[1].split(" or ")
    assert [c for c in a if c.isdigit()] == [c for c in b.split(",")[0] if c.isdigit()]  # one number in two formats
    card = out[1].text.split()[0]
    assert card in out[0].text and card[0] == "4" and sum(int(d) if i % 2 else sum(divmod(2 * int(d), 10)) for i, d in enumerate(card)) % 10 == 0
    assert out[1].text == out[5].text and out[1].text.split("; ")[1].startswith("Mr. ")
    other = surrogates.replace_entities(docs(spark, texts), "another key").where("doc_id = 1").first().text
    assert other != out[1].text and surrogates.replace_entities(docs(spark, []), "key").count() == 0


def test_surrogates_stay_distinct(spark):
    """Two-letter local parts leave so few surrogates that draws collide; each still gets its own."""
    texts = [f"{a}{b}@c.org" for a in "abcdefghij" for b in "aeiou"]
    out = surrogates.replace_entities(docs(spark, texts), "key").collect()
    assert len({r.text for r in out}) == len(texts) and not {r.text for r in out} & set(texts)


def test_components_of_chains_and_stars(spark):
    links = [(i, i + 1) for i in range(20, 60)] + [(100, i) for i in range(101, 140)] + [(7, 7)]
    out = dict(got(components(spark.createDataFrame(links, "a long, b long"), Stages(spark, "t")), "v", "component"))
    assert {out[i] for i in range(20, 61)} == {20} and {out[i] for i in range(100, 140)} == {100} and 7 not in out


def test_pipeline_against_its_stages(spark, sf):
    import corpus_pipeline

    final = corpus_pipeline.run(spark, sf)
    docs_in = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs_out = stage(spark, docs_in, sf)
        assert docs_out.columns == docs_in.columns, name
        docs_in = docs_out
    rows = {r.doc_id: r for r in final.collect()}
    assert set(rows) == {r.doc_id for r in docs_in.collect()} and all(r.round_trip and r.n_tokens == len(r.bpe_ids) for r in rows.values())
    assert final.join(docs_in.select("doc_id", F.col("text").alias("t")), "doc_id").where("text <> t").count() == 0
    assert json.dumps(sorted(rows)) and hashlib
