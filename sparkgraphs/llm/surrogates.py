"""Surrogates for personal data, by column expressions alone.

Entities are e-mail addresses, phone numbers, payment cards, IPv4 addresses, national numbers (nnn-nn-nnnn), access key ids, long
hexadecimal secrets, and titled names. Each distinct entity (in a canonical form that ignores case and punctuation) gets a
surrogate drawn by a keyed hash: digits stay digits, letters keep their case and script, vowels of the Latin alphabet stay vowels,
punctuation stays, cards keep their first digit and pass the checksum, phone numbers keep their country code, addresses move to
reserved domains, octets keep their number of digits, titles keep theirs. A letter of any other script is drawn from a few letters
near it in that script's own block, and never stays what it is.

A name is a title with one or two words. The entity is its last word, so that a person has one surname with and without the first
name; first names are drawn from a list that follows the title's gender if written in plain Latin letters, else letter by letter.

The same entity gets the same surrogate in all documents (coreference). Surrogates met twice, or equal to a real entity of their
kind, are drawn anew with the next attempt number until all are distinct. From `LONGER_AFTER` attempts on, a draw has one more
letter or digit of its own class for each further attempt (so that there is room for any number of entities, and nothing of the
real value is ever kept), and octets of any length; kinds of a fixed length (cards, national and phone numbers) go on without.

The key is a parameter of the caller. It is hashed once on the driver, and the plans hold only that digest.

Defined cases: null texts stay null and empty texts empty, with no entities; an entity repeated in a text is replaced each time;
repeated rows are rewritten alike; texts of any length are rewritten whole; tables without entities or rows pass through; columns
named n_entities or kinds in the input are replaced; all other columns pass through.
"""

from __future__ import annotations

import hashlib
import hmac

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Stages, hot_values, table

LONGER_AFTER, MOST_ATTEMPTS = 8, 64
MALE = ("Mr", "Herr", "Monsieur", "Señor", "Sr", "Sir", "Don")
FEMALE = ("Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Señora", "Sra", "Madam", "Doña")
MALE_NAMES = ("Adam", "Bruno", "Carl", "David", "Emil", "Felix", "Georg", "Hugo", "Ivan", "Jonas", "Karim", "Leon", "Martin", "Noel", "Oskar", "Paul")
FEMALE_NAMES = ("Alma", "Berta", "Clara", "Diana", "Elena", "Flora", "Greta", "Helga", "Irene", "Julia", "Karin", "Laura", "Marta", "Nora", "Olga", "Paula")
#: A capitalised word, or (scripts without case) a word of other letters; marks belong to the letters before them.
WORD = r"(?:\p{Lu}[\p{Ll}\p{M}]+|(?:\p{Lo}\p{M}*)+|\p{IsGeorgian}+)"
NAME = rf"(?<![\p{{L}}\p{{N}}_])(?:{'|'.join(MALE + FEMALE)})\.? {WORD}(?: {WORD})?(?![\p{{Ll}}\p{{Lo}}\p{{M}}])"
#: Kinds in the order in which they are tried.
PATTERNS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}",
    "key": r"(?<![A-Za-z0-9])AKIA[0-9A-Z]{16}(?![A-Za-z0-9])",
    "card": r"(?<![\w])[3-6]\d{3}(?:[ -]?\d{4}){3}(?!\w)",
    "phone": r"(?<!\w)\+\d{1,3}[ .-]?\(?\d{2,4}\)?(?:[ .-]?\d{2,4}){2,4}(?!\d)",
    "ssn": r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w-])",
    "ip": r"(?<![\w.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\w]|\.\d)",
    "secret": r"(?<![A-Za-z0-9])(?=[a-f]*[0-9])[0-9a-f]{16,128}(?![A-Za-z0-9])",
    "name": NAME,
}
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: Texts without a digit, an at sign or a title hold no entity.
MAYBE = rf"[0-9@]|(?:{'|'.join(MALE + FEMALE)})\.? [\p{{Lu}}\p{{Lo}}\p{{IsGeorgian}}]"
CONSONANTS = "bcdfghjklmnpqrstvwxyz"
#: Lower-case alphabets whose letters are drawn from all of them.
ALPHABETS = ("0123456789", "aeiou", CONSONANTS, "áéíóúàèìòùäëïöüâêîôûåæø", "ñçß", "αβγδεζηθικλμνξοπρστυφχψω", "абвгдежзиклмнопрстуфхцчшщэюя")
#: Letters of other scripts are drawn from the letters of their own window of so many code points.
WINDOW = 8


def kind_of(entity: Column) -> Column:
    out = None
    for kind, pattern in PATTERNS.items():
        whole = entity.rlike(f"^(?:{pattern})$")
        out = F.when(whole, kind) if out is None else out.when(whole, kind)
    return out.otherwise("secret")


def canonical(kind: Column, entity: Column) -> Column:
    """What is hashed: lower case; of numbers the digits, with country codes set off; of names the last word."""
    digits = F.regexp_replace(entity, r"\D", "")
    country = F.regexp_extract(entity, r"^\+(\d{1,3})[ .(-]", 1)
    return (
        F.when(kind.isin("card", "ssn"), digits)
        .when(kind == "phone", F.concat(F.length(country).cast("string"), F.lit(":"), digits))
        .when(kind == "name", F.lower(F.substring_index(entity, " ", -1)))
        .otherwise(F.lower(entity))
    )


def key_digest(key: str) -> str:
    """What plans hold in place of the key."""
    return hmac.new(key.encode(), b"surrogates", hashlib.sha256).hexdigest()


def stream(kind: Column, canon: Column, attempt: Column, digest: str) -> Column:
    """256 hexadecimal digits that depend on the key, the entity and the attempt."""
    seed = F.concat_ws("|", F.lit(digest), kind, canon, attempt.cast("string"))
    return F.concat(*(F.sha2(F.concat(seed, F.lit(f"|{i}")), 256) for i in range(4)))


def code_point(c: Column) -> Column:
    """The code point of a one-character string, as a BIGINT."""
    return F.conv(F.hex(F.encode(c, "UTF-32")), 16, 10).cast("long")


def character(point: Column) -> Column:
    return F.decode(F.unhex(F.lpad(F.hex(point), 8, "0")), "UTF-32")


def near_letter(c: Column, value: Column) -> Column:
    """Another lower-case or uncased letter from the same aligned window of code points; the next window's if it has no other.

    Windows never cross a script: blocks start at multiples of WINDOW.
    """
    start = F.floor(code_point(c) / WINDOW).cast("long") * WINDOW
    around = lambda at: F.filter(F.transform(F.sequence(F.lit(0), F.lit(WINDOW - 1)), lambda i: character(at + i)), lambda x: x.rlike(r"^[\p{Ll}\p{Lo}]$") & (x != c) & (F.lower(F.upper(x)) == x))
    pick = lambda l: l[value % F.greatest(F.size(l), F.lit(1))]
    return F.coalesce(F.when(F.size(around(start)) > 0, pick(around(start))), F.when(F.size(around(start + WINDOW)) > 0, pick(around(start + WINDOW))), F.lit("x"))


def drawn(text: Column, noise: Column, shift: int = 0) -> Column:
    """`text` (lower case) with each letter and digit replaced by one of its own class; anything else stays."""

    def one(i: Column) -> Column:
        c = text.substr(i + 1, F.lit(1))
        value = F.conv(noise.substr(((i + shift) % 126) * 2 + 1, F.lit(3)), 16, 10).cast("int")
        out = None
        for letters in ALPHABETS:
            new = F.lit(letters).substr(value % len(letters) + 1, F.lit(1))
            hit = F.lit(letters).contains(c)
            out = F.when(hit, new) if out is None else out.when(hit, new)
        other_digit = F.when(c.rlike(r"^\p{N}$"), (value % 10).cast("string"))
        return out.otherwise(F.coalesce(other_digit, F.when(c.rlike(r"^\p{L}$"), near_letter(c, value)), c))

    return F.when(F.length(text) == 0, "").otherwise(F.array_join(F.transform(F.sequence(F.lit(0), F.length(text) - 1), one), ""))


def luhn_digit(head: Column) -> Column:
    """The check digit after an odd number of digits `head` (15 for cards of 16)."""
    digit = lambda i: head.substr(i + 1, F.lit(1)).cast("int")
    doubled = lambda d: F.when(d > 4, 2 * d - 9).otherwise(2 * d)
    weighed = F.transform(F.sequence(F.lit(0), F.length(head) - 1), lambda i: F.when(i % 2 == 0, doubled(digit(i))).otherwise(digit(i)))
    total = F.aggregate(weighed, F.lit(0), lambda a, x: a + x)
    return ((10 - total % 10) % 10).cast("string")


def longer(text: Column, attempt: Column) -> Column:
    """`text` with its last letter or digit once more for each attempt past LONGER_AFTER: a draw then has room for more entities."""
    return F.concat(text, F.repeat(F.regexp_extract(text, r"([\p{L}\p{N}])[^\p{L}\p{N}]*$", 1), F.greatest(attempt - LONGER_AFTER, F.lit(0))))


def surrogate(kind: Column, canon: Column, attempt: Column, digest: str) -> Column:
    """The surrogate of a canonical form, in canonical form."""
    noise = stream(kind, canon, attempt, digest)
    number = lambda at: F.conv(noise.substr(at, 6), 16, 10).cast("int")
    whole = longer(canon, attempt)
    local, domain = longer(F.substring_index(canon, "@", 1), attempt), F.substring_index(canon, "@", -1)
    label, top = F.substring_index(domain, ".", 1), F.substring_index(domain, ".", -1)
    email = F.concat(drawn(local, noise), F.lit("@"), drawn(label, noise, 61), F.lit(".example."), F.when(top.isin("com", "net", "org"), top).otherwise("org"))
    head = F.concat(canon.substr(1, 1), drawn(canon.substr(F.lit(2), F.length(canon) - 2), noise))
    size = F.substring_index(canon, ":", 1).cast("int")
    digits = F.substring_index(canon, ":", -1)
    rest = digits.substr(size + 1, F.length(digits))
    phone = F.concat(size.cast("string"), F.lit(":"), digits.substr(F.lit(1), size), (number(1) % 8 + 2).cast("string"), drawn(rest.substr(F.lit(2), F.length(rest)), noise, 7))
    ssn = F.concat((number(1) % 5 + 1).cast("string"), drawn(canon.substr(F.lit(2), F.length(canon)), noise, 7))
    octet = lambda o, v: F.when(attempt >= LONGER_AFTER, v % 254 + 1).when(F.length(o) == 1, v % 9 + 1).when(F.length(o) == 2, v % 90 + 10).otherwise(v % 156 + 100).cast("string")
    ip = F.array_join(F.transform(F.split(canon, r"\."), lambda o, i: octet(o, F.conv(noise.substr(i * 6 + 1, F.lit(6)), 16, 10).cast("int"))), ".")
    value = lambda i: F.conv(noise.substr((i % 126) * 2 + 1, F.lit(3)), 16, 10).cast("int")
    of = lambda letters, v: F.lit(letters).substr(v % len(letters) + 1, F.lit(1))
    hexa = lambda i: F.when(F.lit("abcdef").contains(whole.substr(i + 1, F.lit(1))), of("abcdef", value(i))).otherwise(of("0123456789", value(i)))
    secret = F.array_join(F.transform(F.sequence(F.lit(0), F.length(whole) - 1), hexa), "")
    access = F.concat(F.lit("akia"), drawn(canon.substr(F.lit(5), F.length(canon)), noise))
    return (
        F.when(kind == "email", email).when(kind == "card", F.concat(head, luhn_digit(head))).when(kind == "phone", phone).when(kind == "ssn", ssn)
        .when(kind == "ip", ip).when(kind == "key", access).when(kind == "name", drawn(whole, noise, 31)).otherwise(secret)
    )


def assign(entities: DataFrame, digest: str, stages: Stages) -> DataFrame:
    """(kind, canon, sur) of distinct entities: distinct surrogates, none of them a real entity of its kind."""
    pending = stages.keep(entities.select("kind", "canon").distinct())
    real, done = pending, []
    for attempt in range(MOST_ATTEMPTS):
        drew = stages.keep(pending.withColumn("sur", surrogate(F.col("kind"), F.col("canon"), F.lit(attempt), digest)))
        holder = drew.groupBy("kind", "sur").agg(F.min("canon").alias("canon"))
        free = holder.join(real.select("kind", F.col("canon").alias("sur")), ["kind", "sur"], "left_anti")
        for earlier in done:
            free = free.join(earlier.select("kind", "sur"), ["kind", "sur"], "left_anti")
        done.append(stages.keep(free.select("kind", "canon", "sur")))
        pending = stages.keep(drew.select("kind", "canon").join(done[-1], ["kind", "canon"], "left_anti"))
        if pending.isEmpty():
            break
        if len(done) > 3:  # few tables in any plan
            done = [stages.keep(_union(done))]
    else:
        raise ValueError(f"no distinct surrogates of one format after {MOST_ATTEMPTS} attempts: {pending.select('kind').distinct().limit(8).toPandas().kind.tolist()}")
    return _union(done)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def capitals(entity: Column, sur: Column) -> Column:
    """`sur` with capitals as `entity` has them: all, the first, or none."""
    return F.when(F.upper(entity) == entity, F.upper(sur)).when(entity.rlike(r"^\p{Lu}"), F.concat(F.upper(sur.substr(1, 1)), sur.substr(F.lit(2), F.length(sur)))).otherwise(sur)


def first_name(title: Column, word: Column, digest: str) -> Column:
    """A first name that follows the title's gender; other scripts are drawn letter by letter."""
    noise = stream(F.lit("first"), F.lower(word), F.lit(0), digest)
    pick = lambda names: F.array(*map(F.lit, names))[F.conv(noise.substr(1, 6), 16, 10).cast("int") % len(names)]
    plain = F.when(title.isin(*MALE), pick(MALE_NAMES)).otherwise(pick(FEMALE_NAMES))
    # the next one if it is the real one
    other = F.when(title.isin(*MALE), F.lit(MALE_NAMES[0])).otherwise(F.lit(FEMALE_NAMES[0]))
    last = F.when(title.isin(*MALE), F.lit(MALE_NAMES[-1])).otherwise(F.lit(FEMALE_NAMES[-1]))
    plain = F.when(plain != word, plain).when(other != word, other).otherwise(last)
    return F.when(word.rlike("^[A-Za-zÀ-ÿ]+$"), plain).otherwise(capitals(word, drawn(F.lower(word), noise, 17)))


def rendered(kind: Column, entity: Column, sur: Column, digest: str) -> Column:
    """A canonical surrogate in the format of the entity it replaces."""
    digits = F.substring_index(sur, ":", -1)
    # each digit of the entity in turn takes the next digit of the surrogate
    step = lambda out, at: F.struct(out.alias("out"), at.alias("at"))
    walk = F.aggregate(
        F.split(entity, ""),
        F.struct(F.lit("").alias("out"), F.lit(0).alias("at")),
        lambda a, c: F.when(c.rlike("[0-9]"), step(F.concat(a["out"], digits.substr(a["at"] + 1, F.lit(1))), a["at"] + 1)).otherwise(step(F.concat(a["out"], c), a["at"])),
        lambda a: a["out"],
    )
    words = F.split(entity, " ")
    title, surname = words[0], capitals(F.element_at(words, -1), sur)
    bare = F.regexp_replace(title, r"\.$", "")
    name = F.when(F.size(words) > 2, F.concat_ws(" ", title, first_name(bare, words[1], digest), surname)).otherwise(F.concat_ws(" ", title, surname))
    cased = F.when(F.upper(entity) == entity, F.upper(sur)).otherwise(sur)
    return F.when(kind.isin("phone", "card", "ssn"), walk).when(kind == "name", name).otherwise(cased)


def replace_entities(docs: DataFrame, key: str, *, text: str = "text", stages: Stages | None = None) -> DataFrame:
    """`docs` with entities replaced by surrogates, n_entities and kinds (distinct kinds found, sorted)."""
    stages = stages or Stages(docs.sparkSession, "surrogates")
    digest = key_digest(key)
    own = [c for c in docs.columns if c not in ("n_entities", "kinds")]
    docs = docs.select(*own)
    has = F.coalesce(F.col(text).rlike(MAYBE) & F.col(text).rlike(ANY), F.lit(False))
    clean = docs.where(~has).withColumns({"n_entities": F.lit(0).cast("long"), "kinds": F.array().cast("array<string>")})
    found = docs.where(has).withColumn("entity_key", F.unhex(F.md5(F.col(text))))
    # texts are rewritten once each: equal texts share their entities
    listed = found.dropDuplicates(["entity_key"]).select("entity_key", F.posexplode(F.regexp_extract_all(F.col(text), F.lit(ANY), F.lit(0))).alias("at", "entity"))
    typed = listed.withColumn("kind", kind_of(F.col("entity"))).withColumn("canon", canonical(F.col("kind"), F.col("entity")))
    typed = stages.keep(typed.select("entity_key", "at", "entity", "kind", "canon", F.xxhash64("kind", "canon").alias("h")))
    table_of = stages.keep(assign(typed, digest, stages)).withColumn("h", F.xxhash64("kind", "canon"))
    hot = F.broadcast(hot_values(typed, "h"))  # at most a thousand
    often = typed.join(hot, "h", "left_semi").join(F.broadcast(table_of.join(hot, "h", "left_semi").drop("h")), ["kind", "canon"])
    seldom = typed.join(hot, "h", "left_anti").join(table_of.drop("h"), ["kind", "canon"])
    out = often.select("entity_key", "at", "kind", "entity", "sur").unionByName(seldom.select("entity_key", "at", "kind", "entity", "sur"))
    out = out.select("entity_key", "kind", F.struct("at", rendered(F.col("kind"), F.col("entity"), F.col("sur"), digest).alias("new")).alias("pair"))
    by_text = stages.keep(out.groupBy("entity_key").agg(F.array_sort(F.collect_list("pair"))["new"].alias("new"), F.array_sort(F.collect_set("kind")).alias("kinds")))
    pieces = F.split(F.col(text), ANY, -1)
    whole = F.array_join(F.zip_with(pieces, "new", lambda a, b: F.concat(a, F.coalesce(b, F.lit("")))), "")
    # plain shuffles on both sides: a text of very many rows is a skewed key, which adaptive execution splits
    joined = found.join(by_text, "entity_key")
    changed = joined.select(*[whole.alias(c) if c == text else F.col(c) for c in own], F.size("new").cast("long").alias("n_entities"), "kinds")
    return clean.unionByName(changed)


def op10_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, text with surrogates, n_entities and kinds of every document. The key of this query is fixed, so that results repeat."""
    return replace_entities(table(spark, sf_dir, "documents").select("doc_id", "text"), "fixture-key")
