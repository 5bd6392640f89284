"""Replacement of personal data and secrets by keyed surrogates (DataFrame functions only).

Entities are found by patterns: e-mail addresses, access keys, assigned secrets (also with blanks around the sign or
with quotes, which stay outside the value, and with a keyword in any case that is part of a longer word), account
numbers (IBAN), card numbers, IPv4 and IPv6 addresses, national numbers (3-2-4 digits), phone numbers (with + or
parentheses, or 3-3-4 digits), and person names after a title or a phrase that introduces one, or with a known given
name. Each is rewritten by a keyed permutation of the
values of its own format: letters stay letters of the same script and case, digits digits; separators, country codes,
card issuers, top-level domains and titles stay; check digits of cards and accounts stay right if they were; given
names of the lists are exchanged within the list of their gender and script; in other names vowels stay vowels and
consonants consonants.
Equal entities get equal surrogates everywhere (a phone number also when it is punctuated differently), and a
permutation never gives two entities of a format the same surrogate, nor an entity itself. A check over all distinct
entities of the corpus confirms this; if it fails, everything is done anew under the next tweak of the key. A
surrogate may be a value that another text has as a real entity: a permutation of a format cannot rule that out.

Edge cases: null texts stay null, empty ones empty; texts without an entity are unchanged; repeated rows get equal
results; what has no letter or digit of the alphabets below (a secret of asterisks) stays; all columns pass, but for
one named entities where that column is asked for.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textscan as ts

#: Given names by gender and script; each list has at least two.
FEMALE_LATIN = "Anna Maria Laura Julia Sarah Emma Sofia Elena Clara Marta Ines".split()
MALE_LATIN = "Peter Thomas Daniel Martin Robert Pablo Carlos Pierre Louis Hans Stefan".split()
FEMALE_CYRILLIC = "Анна Мария Ольга Елена Ирина Юлия Вера".split()
MALE_CYRILLIC = "Иван Пётр Олег Борис Павел Антон Юрий".split()
NAME_LISTS = (FEMALE_LATIN, MALE_LATIN, FEMALE_CYRILLIC, MALE_CYRILLIC)
TITLES = "Mr Mrs Ms Miss Dr Prof Herr Frau Monsieur Madame Señor Señora".split()
#: Alphabets within which letters are exchanged.
PLAIN = ("0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ")
HEX = ("0123456789abcdef",)
GROUPS = ("0123456789", "abcdef", "ABCDEF")
SPOKEN = ("aeiou", "bcdfghjklmnpqrstvwxyz", "AEIOU", "BCDFGHJKLMNPQRSTVWXYZ", "аеиоуыэюя", "бвгджзйклмнпрстфхцчшщ", "АЕИОУЫЭЮЯ", "БВГДЖЗЙКЛМНПРСТФХЦЧШЩ", "áàâäãåéèêëíìîïóòôöõúùûü", "ÁÀÂÄÃÅÉÈÊËÍÌÎÏÓÒÔÖÕÚÙÛÜ", "αβγδεζηθικλμνξοπρστυφχψω", "ΑΒΓΔΕΖΗΘΙΚΛΜΝΞΟΠΡΣΤΥΦΧΨΩ")

_GIVEN = "|".join(n for names in NAME_LISTS for n in names)
_NAME = r"\p{Lu}\p{Ll}+(?:-\p{Lu}\p{Ll}+)?"
EMAIL = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+"
KEY = r"\bAKIA[0-9A-Z]{16}\b"
#: From the keyword on (what precedes it in its word stays outside): the rest of the word, the sign, and the value with or without quotes.
_ASSIGN = r"[\w-]{0,40}[\"']?[ \t]{0,8}(?::=|=>|[=:])[ \t]{0,8}"
SECRET = rf"(?i:password|passwd|pwd|secret|token|api[_-]?key){_ASSIGN}(?:\"[^\"\n]+\"|'[^'\n]+'|[\"']?[^\s,;\"'][^\s,;]*)"
IP = r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)\.){3}(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)(?![\d]|\.\d)"
_H = "[0-9A-Fa-f]{1,4}"
IP6 = rf"(?<![\w:])(?=[0-9A-Fa-f:]*\d)(?:(?:{_H}:){{7}}{_H}|(?:{_H}(?::{_H}){{0,6}})?::(?:{_H}(?::{_H}){{0,6}})?)(?![\w:])"
IBAN = r"\b[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b"
NATIONAL = r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])"
CARD = r"(?<![\d-])\d(?:[ -]?\d){12,18}(?![\d-])"
PHONE = r"(?:\+\d{1,3}[ .-]?)?\(\d{2,4}\)[ .-]?\d{3,4}[ .-]?\d{3,4}\b|\+\d{1,3}(?:[ .-]?\d{2,4}){2,4}\b|(?<![\d.-])(?:\d{3}-\d{3}-\d{4}|\d{3}\.\d{3}\.\d{4}|\d{3} \d{3} \d{4})(?![\d-])"
_TITLE = "|".join((*TITLES, "mr", "mrs", "dr", "prof"))
#: Phrases that a name of two or three words follows.
_BEFORE = r"(?<=\b(?:[Mm]y name is|[Ss]igned by|[Yy]ours,|[Ss]incerely,|[Rr]egards,)[ \n])"
PERSON = rf"\b(?:(?:{_TITLE})\.? {_NAME}(?: {_NAME})?|(?:{_GIVEN}) {_NAME})|{_BEFORE}{_NAME}(?: {_NAME}){{1,2}}"
ENTITY = f"{EMAIL}|{KEY}|{SECRET}|{IBAN}|{IP6}|{IP}|{CARD}|{NATIONAL}|{PHONE}|{PERSON}"
#: A cheap test that every text with an entity passes.
HINT = rf"@|\d{{2}}|\d\.\d|::|:{_H}:|AKIA|[Mm]y name is|[Ss]igned by|[Yy]ours,|[Ss]incerely,|[Rr]egards,|(?i:passw|pwd|secret|token|api[_-]?key)|\b(?:{_TITLE})\b|\b(?:{_GIVEN})\b"

ROUNDS = 4


def kind(e: Column) -> Column:
    """Name of an entity's format."""
    full = lambda p: e.rlike(f"^(?:{p})$")
    return (
        F.when(full(SECRET), "secret").when(e.contains("@"), "email").when(full(KEY), "key").when(full(IBAN), "iban").when(full(IP6), "ip6")
        .when(full(IP), "ip").when(full(CARD), "card").when(full(NATIONAL), "national").when(full(PHONE), "phone").otherwise("person")
    )


def _shuffled(values: Column, sizes: Column, key: Column) -> Column:
    """Values (each below its size) under a keyed permutation that leaves no array as it is: a Feistel network whose
    halves are parts of the array, a step by a constant, and the network backwards."""
    n = F.size(values)
    half = F.ceil(n / 2).cast("int")
    left, right = F.slice(values, F.lit(1), half), F.slice(values, half + 1, n - half)
    m_left, m_right = F.slice(sizes, F.lit(1), half), F.slice(sizes, half + 1, n - half)
    shape = F.array_join(sizes.cast("array<string>"), ",")

    def turn(target: Column, other: Column, m: Column, r: int, sign: int) -> Column:
        digest = F.sha2(F.concat_ws("|", key, F.lit(str(r)), shape, F.array_join(other.cast("array<string>"), ",")), 512)
        step = lambda i: F.conv(F.substring(digest, 4 * (i % 32) + 1, F.lit(4)), 16, 10).cast("int")
        return F.transform(target, lambda x, i: F.pmod(x + sign * step(i), F.get(m, i)))

    def with_halves(s: Column, lft: Column, rgt: Column) -> Column:
        return F.struct(lft.alias("l"), rgt.alias("r"), s["ml"].alias("ml"), s["mr"].alias("mr"))

    def round_(r: int, sign: int):
        if r % 2 == 0:
            return lambda s: with_halves(s, turn(s["l"], s["r"], s["ml"], r, sign), s["r"])
        return lambda s: with_halves(s, s["l"], turn(s["r"], s["l"], s["mr"], r, sign))

    # Each half is computed once for each round: bound to a lambda variable, or the expression would double every round.
    state = F.array(F.struct(left.alias("l"), right.alias("r"), m_left.alias("ml"), m_right.alias("mr")))
    for r in range(ROUNDS):
        state = F.transform(state, round_(r, 1))
    state = F.transform(state, lambda s: with_halves(s, F.transform(s["l"], lambda x, i: F.when(i == 0, F.pmod(x + 1, F.get(s["ml"], i))).otherwise(x)), s["r"]))
    for r in reversed(range(ROUNDS)):
        state = F.transform(state, round_(r, -1))
    return F.flatten(F.transform(state, lambda s: F.concat(s["l"], s["r"])))


def _let(value: Column, body) -> Column:
    """body(value) with the value computed once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _array(values) -> Column:
    return F.array(*map(F.lit, values))


def _rewritten(text: Column, alphabets: Column, key: Column) -> Column:
    """Text with the letters of the alphabets (an array) exchanged within them; others stay."""

    def of(c: Column) -> Column:
        return F.coalesce(F.get(F.filter(alphabets, lambda a: F.instr(a, c) > 0), 0), F.lit(""))

    def placed(marks: Column) -> Column:
        # marks: (letter, alphabet, how many letters of alphabets precede)
        free = F.filter(marks, lambda m: m["a"] != "")
        values = F.transform(free, lambda m: F.instr(m["a"], m["c"]) - 1)
        sizes = F.transform(free, lambda m: F.length(m["a"]))
        moved = _shuffled(values, sizes, key)
        return _let(moved, lambda v: F.array_join(F.transform(marks, lambda m, i: F.when(m["a"] == "", m["c"]).otherwise(F.substring(m["a"], F.get(v, F.size(F.filter(F.slice(marks, F.lit(1), i), lambda x: x["a"] != ""))) + 1, F.lit(1)))), ""))

    letters = F.split(text, "")
    return _let(F.transform(letters, lambda c: F.struct(c.alias("c"), of(c).alias("a"))), placed)


def _check_digit(digits: Column) -> Column:
    """The digit that makes digits + it pass the modulo-10 check."""
    doubled = lambda d: F.when(d > 4, 2 * d - 9).otherwise(2 * d)
    numbers = F.transform(F.reverse(F.filter(F.split(digits, ""), lambda c: c != "")), lambda c, i: F.when(i % 2 == 0, doubled(c.cast("int"))).otherwise(c.cast("int")))
    return F.pmod(-F.aggregate(numbers, F.lit(0), lambda a, x: a + x), F.lit(10))


def _card(e: Column, body: Column) -> Column:
    """The card number with new digits between its first and last; the last keeps its distance from the right check digit."""
    digits = F.regexp_replace(e, r"\D", "")
    head = F.concat(F.substring(digits, 1, 1), body)
    apart = F.pmod(F.substring(digits, -1, 1).cast("int") - _check_digit(F.substring(digits, F.lit(1), F.length(digits) - 1)), F.lit(10))
    new = _let(head, lambda h: F.concat(h, F.pmod(_check_digit(h) + apart, F.lit(10)).cast("string")))
    marks = F.split(e, "")
    return _let(new, lambda d: F.array_join(F.transform(marks, lambda c, i: F.when(c.rlike(r"\d"), F.substring(d, F.size(F.filter(F.slice(marks, F.lit(1), i), lambda x: x.rlike(r"\d"))) + 1, F.lit(1))).otherwise(c)), ""))


def _remainder(account: Column) -> Column:
    """An account number without blanks, its first four characters behind, letters as 10 to 35, modulo 97."""
    turned = F.concat(F.substring(account, F.lit(5), F.length(account)), F.substring(account, 1, 4))
    value = lambda c: F.when(c.rlike("[A-Z]"), F.ascii(c) - 55).otherwise(c.cast("int"))
    return F.aggregate(F.split(turned, ""), F.lit(0), lambda a, c: F.pmod(a * F.when(c.rlike("[A-Z]"), 100).otherwise(10) + value(c), F.lit(97)))


def _valid(e: Column) -> Column:
    return _remainder(F.regexp_replace(e, " ", "")) == 1


def _iban(e: Column, body: Column) -> Column:
    """The account number with a new body: behind new check digits if those of e are right, else with digits of its own."""
    bare = F.concat(F.substring(e, 1, 2), F.lit("00"), F.regexp_replace(body, " ", ""))
    digits = F.when(_valid(e), F.lpad((98 - _remainder(bare)).cast("string"), 2, "0")).otherwise(F.lit(""))
    return F.concat(F.substring(e, 1, 2), digits, body)


def _ip(e: Column, key: Column) -> Column:
    parts = F.transform(F.split(e, r"\."), lambda x: x.cast("int"))
    return F.array_join(_shuffled(parts, F.array_repeat(F.lit(256), 4), key).cast("array<string>"), ".")


def _given(w: Column, new: Column, key: Column) -> Column:
    """A word of a name: a title stays, a given name of a list takes a keyed step along it, another word is new."""
    out = new
    for i, names in enumerate(NAME_LISTS):
        n = len(names)
        step = F.conv(F.substring(F.sha2(F.concat_ws("|", key, F.lit(f"b{i}")), 256), 1, 6), 16, 10).cast("long") % (n - 1) + 1
        place = F.pmod(F.array_position(_array(names), w) - 1 + step, F.lit(n)).cast("int")
        out = F.when(w.isin(names), F.get(_array(names), place)).otherwise(out)
    return F.when(w.rlike(rf"^(?:{_TITLE})\.?$"), w).otherwise(out)


_MAIL_PARTS, _CODE_PARTS = r"(?s)^(.*)(\.[^.]*)$", r"^(\+\d{1,3}(?=[ .(-])|)(.*)$"
_SECRET_PARTS = rf"^((?i:password|passwd|pwd|secret|token|api[_-]?key){_ASSIGN}[\"']?)(.*?)([\"']?)$"


def surrogate(e: Column, key: Column) -> Column:
    """The surrogate of an entity."""
    part = lambda p, i: F.regexp_extract(e, p, i)

    def of(k: Column) -> Column:
        bodies = (
            F.when(k == "person", F.split(e, " ")).when(k == "email", F.array(part(_MAIL_PARTS, 1))).when(k == "key", F.array(F.substring(e, 5, 16)))
            .when(k == "secret", F.array(part(_SECRET_PARTS, 2))).when(k == "card", F.array(F.regexp_replace(F.regexp_replace(e, r"\D", ""), "^.|.$", "")))
            .when(k == "iban", F.array(F.substring(e, F.when(_valid(e), 5).otherwise(3), F.length(e)))).when(k == "phone", F.array(part(_CODE_PARTS, 2))).otherwise(F.array(e))
        )
        alphabets = (
            F.when(k == "person", _array(SPOKEN)).when(k.isin("card", "national", "phone"), _array(PLAIN[:1])).when(k == "ip6", _array(GROUPS))
            .when((k == "secret") & part(_SECRET_PARTS, 2).rlike("^[0-9a-f]+$"), _array(HEX)).otherwise(_array(PLAIN))
        )
        return _let(alphabets, lambda a: _let(F.transform(bodies, lambda b: F.struct(b.alias("old"), _rewritten(b, a, F.concat(key, k)).alias("new"))), lambda done: put_together(k, done)))

    def put_together(k: Column, done: Column) -> Column:
        new = F.get(done, 0)["new"]
        return (
            F.when(k == "person", F.array_join(F.transform(done, lambda w: _given(w["old"], w["new"], key)), " "))
            .when(k == "email", F.concat(new, part(_MAIL_PARTS, 2)))
            .when(k == "key", F.concat(F.substring(e, 1, 4), new))
            .when(k == "secret", F.concat(part(_SECRET_PARTS, 1), new, part(_SECRET_PARTS, 3)))
            .when(k == "ip", _ip(e, F.concat(key, k)))
            .when(k == "card", _card(e, new))
            .when(k == "iban", _iban(e, new))
            .when(k == "phone", F.concat(part(_CODE_PARTS, 1), new))
            .otherwise(new)
        )

    return _let(kind(e), of)


def entities(df: DataFrame) -> DataFrame:
    """Distinct entities of all texts."""
    hit = df.filter(F.col("text").rlike(HINT)).select(F.explode(F.regexp_extract_all("text", F.lit(ENTITY), F.lit(0))).alias("entity"))
    return hit.distinct()


def changeable(e: Column) -> Column:
    """Whether the part of an entity that is rewritten has a letter or digit of the alphabets."""
    k = kind(e)
    part = (
        F.when(k == "email", F.regexp_extract(e, _MAIL_PARTS, 1)).when(k == "secret", F.regexp_extract(e, _SECRET_PARTS, 2))
        .when(k == "person", F.regexp_replace(e, rf"^(?:{_TITLE})\.? ", "")).otherwise(e)
    )
    return part.rlike(f"[{''.join(dict.fromkeys(''.join((*PLAIN, *SPOKEN))))}]")


def faults(found: DataFrame, key: Column) -> int:
    """Number of surrogates that two entities share or that equal their entity (unless nothing in it can change)."""
    named = found.withColumn("surrogate", surrogate(F.col("entity"), key))
    by = named.groupBy("surrogate").agg(F.count(F.lit(1)).alias("n"), F.max(((F.col("entity") == F.col("surrogate")) & changeable(F.col("entity"))).cast("int")).alias("same"))
    return by.filter("n > 1 or same = 1").count()


def chosen_key(df: DataFrame, key: str, tries: int = 8) -> Column:
    """The key, with the first tweak under which the check over all distinct entities finds no fault."""
    found = ts.stored(entities(df), "entities")
    for tweak in range(tries):
        tried = F.lit(f"{key}/{tweak}")
        if not faults(found, tried):
            return tried
    raise ValueError(f"surrogates collide under {tries} tweaks of the key")


def replaced(df: DataFrame, key: str, with_entities: bool = False) -> DataFrame:
    """df with surrogates in text; with_entities adds an array of (kind, entity, surrogate) in order of
    appearance, in place of an input column named entities."""
    used = chosen_key(df, key)
    found = F.when(F.col("text").rlike(HINT), F.regexp_extract_all("text", F.lit(ENTITY), F.lit(0))).otherwise(F.array().cast("array<string>"))
    own = "_sg"
    while own in df.columns:
        own += "_"
    marked = df.withColumn(own, F.transform(found, lambda e: F.struct(kind(e).alias("kind"), e.alias("entity"), surrogate(e, used).alias("surrogate"))))
    between = F.split("text", ENTITY, -1)
    text = F.array_join(F.flatten(F.zip_with(between, F.transform(own, lambda s: s["surrogate"]), lambda a, b: F.array(a, b))), "")
    kept = [c for c in df.columns if not (with_entities and c == "entities")]
    columns = [F.when(F.size(own) > 0, text).otherwise(F.col("text")).alias(c) if c == "text" else F.col(c) for c in kept]
    return marked.select(*columns, *([F.coalesce(own, F.array()).alias("entities")] if with_entities else []))
