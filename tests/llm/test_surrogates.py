"""Surrogates: nothing real is left in any script, one person keeps one surname, distinct entities stay distinct."""

import re
import unicodedata

from sparkgraphs.llm import surrogates

NAMES = ["Łšč Čžř", "Աննա Հակոբյան", "ანა ბერიძე", "محمد علي", "王小明", "Ñuño Ömer", "Αλέξης Παππάς", "Иван Петров", "דוד כהן", "สมชาย", "Jürgen"]


def rewritten(spark, texts, key="key"):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return [r.text for r in surrogates.replace_entities(df, key).orderBy("doc_id").collect()]


def scripts(text):
    return [unicodedata.name(c).split()[0] for c in text if c.isalpha()]


def test_no_real_name_survives_in_any_script(spark):
    for name, new in zip(NAMES, rewritten(spark, [f"Dear Mr. {n}, hello" for n in NAMES]), strict=True):
        got = re.fullmatch(r"Dear Mr\. (.*), hello", new)[1]
        assert len(got.split()) == len(name.split()) and not {*name.split()} & {*got.split()}, (name, got)
        assert {*scripts(got)} <= {*scripts(name)} | {"LATIN"}, (name, got)
        assert all(a.isupper() == b.isupper() for a, b in zip((w[0] for w in name.split()), (w[0] for w in got.split()), strict=True))
        last, new_last = name.split()[-1], got.split()[-1]
        assert len(last) == len(new_last) and all(a != b or a in "aeiou" or a.isascii() for a, b in zip(last.lower(), new_last.lower(), strict=True)) or last.isascii()


def test_one_person_keeps_one_surname(spark):
    one, two, other = rewritten(spark, ["Mr. Smith and Mr. John Smith", "Mrs SMITH? no, Mr John Smith", "Mrs. Mary Jones"])
    a, b, c = re.fullmatch(r"Mr\. (\w+) and Mr\. (\w+) (\w+)", one).groups()
    assert a == c != "Smith" and b in surrogates.MALE_NAMES
    assert two == f"Mrs SMITH? no, Mr {b} {a}"  # capitals alone are no name
    assert re.fullmatch(r"Mrs\. (\w+) (\w+)", other)[1] in surrogates.FEMALE_NAMES


def test_draws_that_collide_are_drawn_anew(spark):
    """More two-letter entities than two-letter surrogates of their class: all stay distinct, and none is a real one."""
    texts = [f"{a}{b}@c.org" for a in "bcdfghjklm" for b in "aeiou"] + [f"Mr. {a}{b}" for a in "BCDFGHJKLM" for b in "aeiou"]
    out = rewritten(spark, texts)
    assert len({*out}) == len(texts) and not {*out} & {*texts}
    assert all(re.fullmatch(r"[a-z]+@[a-z]\.example\.org|Mr\. [A-Z][a-z]+", x) for x in out)


def test_repeated_rows_long_texts_and_the_key(spark):
    long = "clean words " * 20_000 + "call +44 20 7946 0958 or a@b.com " * 50
    first, second, third = rewritten(spark, [long, long, "x"])
    assert first == second and "7946" not in first and "a@b.com" not in first and len(first.split()) == len(long.split()) and third == "x"
    df = spark.createDataFrame([(1, "a@b.com")], "doc_id long, text string")
    plan = surrogates.replace_entities(df, "a-secret-key")._jdf.queryExecution().toString()
    assert "a-secret-key" not in plan
