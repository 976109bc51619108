"""Surrogates for personal data, in DataFrame functions alone.

One pattern finds e-mail addresses, telephone numbers, IPv4 addresses, payment card and social
security numbers, account numbers (IBAN) and names behind a title; a name's words found so are then found in the whole
document, with a title or without.  Each value is replaced by a
value of its own type and shape: its variable characters go through a keyed permutation without fixed points
(two rounds in which the even and odd places shift one another by a keyed digest, a step of every place, and the
same rounds back), digits
to digits, vowels to vowels and other letters to such letters, in the letter case and the
script (Latin, Cyrillic, Greek) of the original; an address's four numbers are shifted as numbers.
A card keeps its first digit and an account its country; their check digits are computed anew, and are right where they were
right (else off by as much).
Given names that the lists know stay within the list of their gender, and no other name becomes one of them:
its permutation is applied again until it leaves the lists; titles stay.

A permutation maps two values to two surrogates and one value always to the same one, in every document, so
distinctness and coreference need no table, no join and no shuffle of texts.
A step is coprime to its alphabet's size, so a value comes back to itself only after as many steps as the least common multiple of
its alphabets' sizes (105 for a word of Latin vowels and other letters), more than there are listed names.
The column ``distinct_kept`` states for each document that it has as many different surrogates as values, letter case apart;
``collisions`` checks that over all entities of a table.  The key is the caller's: nothing here holds one.

A text is searched only for what its characters allow (an ``@``, a digit, a title), in one pass.

Cases: null text stays null, empty text empty; repeated rows are replaced alike;
an empty table gives no rows; a null id stays null; other columns stay outside the result.
"""

from __future__ import annotations

import hashlib
import math
from collections import Counter
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ROUNDS = 4

#: The types' patterns.
EMAIL = r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9](?:[A-Za-z0-9._%+-]{0,63})@[A-Za-z0-9](?:[A-Za-z0-9-]{0,62})(?:\.[A-Za-z0-9](?:[A-Za-z0-9-]{0,62})){0,6}\.[A-Za-z]{2,24}(?![A-Za-z0-9])"
IPV4 = r"(?<![0-9.])(?:(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])\.){3}(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])(?![0-9]|\.[0-9])"
IBAN = r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])"
CARD = r"(?<![0-9A-Za-z-])[3-6][0-9]{3}(?:[ -]?[0-9]{4}){2}[ -]?[0-9]{3,4}(?![0-9A-Za-z])"
SSN = r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"
PHONE = r"(?<![0-9A-Za-z])(?:\+[0-9]{1,3}[ .-]?)?(?:\([0-9]{2,4}\)[ .-]?[0-9]{3,4}[ .-][0-9]{3,4}|[0-9]{3}[.-][0-9]{3}[.-][0-9]{4})(?![0-9])|(?<![0-9A-Za-z])\+[0-9]{1,3}(?:[ .-]?[0-9]{2,4}){3,4}(?![0-9])"
TITLE_F, TITLE_M = r"Mrs|Ms|Miss|Frau|Mme|Madame|Sra|Señora|Doña", r"Mr|Herr|Monsieur|Sr|Señor|Don"
WORD = r"(?:\p{Lu}\p{L}+(?:['-]\p{Lu}\p{L}+)*|\p{Lu}'\p{Lu}\p{L}+)"
NAME = r"(?<!\p{L})(?:" + TITLE_F + "|" + TITLE_M + r"|Dr|Prof)\.? " + WORD + "(?: " + WORD + ")?"
TITLES = ("Mr", "Ms", "Miss", "Frau", "Mme", "Madame", "Sr", "Señor", "Don", "Doña", "Herr", "Monsieur", "Dr", "Prof")  # what every title begins with
MARK = "\x01"

#: Given names by gender, and the alphabets.
FEMALE = "anna maria mary sarah laura julia emma sophie claire elena lucia carmen ingrid helga petra susan karen linda lisa nancy".split()
MALE = "john james robert michael david peter paul thomas karl hans jean pierre louis carlos juan jose luis mark george henry".split()
VOWELS, CONSONANTS, DIGITS = "aeiou", "bcdfghjklmnpqrstvwxyz", "0123456789"
CYRILLIC, GREEK = "абвгдежзийклмнопрстуфхцчшщъыьэюя", "αβγδεζηθικλμνξοπρστυφχψω"
ALPHABETS = (DIGITS, VOWELS, CONSONANTS, CYRILLIC, GREEK)


def radix(char: Column) -> Column:
    """How many characters may stand in a place; 0 where it stays."""
    out = F.lit(0)
    for a in ALPHABETS:
        out = F.when(F.contains(F.lit(a), char), F.lit(len(a))).otherwise(out)
    return out


def number(char: Column) -> Column:
    out = F.lit(0)
    for a in ALPHABETS:
        out = F.when(F.contains(F.lit(a), char), F.instr(F.lit(a), char) - 1).otherwise(out)
    return out


def letter(like: Column, n: Column) -> Column:
    out = like
    for a in ALPHABETS:
        out = F.when(F.contains(F.lit(a), like), F.lit(a).substr(n + 1, F.lit(1))).otherwise(out)
    return out


def bound(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with the value computed once, not in every place that uses it."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def permuted(values: Column, bases: Column, salt: Column, key: str) -> Column:
    """A keyed permutation of number lists without fixed points.

    Places of one parity are shifted by a digest of those of the other, in turn; all move on by a step; the shifts are undone.
    """

    def shift(state: Column, r: Column, sign: int) -> Column:
        other = F.array_join(F.filter(state, lambda x, i: (i % 2) != (r % 2)).cast("array<string>"), ",")
        digest = F.sha2(F.concat_ws("|", F.lit(key), r.cast("string"), salt, other).cast("binary"), 256)
        by = lambda d, i: F.conv(d.substr((i * 3) % 60 + 1, F.lit(4)), 16, 10).cast("int")
        return bound(digest, lambda d: F.transform(state, lambda x, i: F.when((i % 2 == r % 2) & (F.get(bases, i) > 0), F.pmod(x + sign * by(d, i), F.get(bases, i))).otherwise(x)))

    half, step = ROUNDS // 2, steps(key)
    moved = F.aggregate(F.sequence(F.lit(0), F.lit(half - 1)), values, lambda state, r: shift(state, r, 1))
    moved = F.transform(moved, lambda x, i: F.when(F.get(bases, i) > 0, (x + F.get(step, F.get(bases, i))) % F.get(bases, i)).otherwise(x))
    return F.aggregate(F.sequence(F.lit(half - 1), F.lit(0)), moved, lambda state, r: shift(state, r, -1))


def steps(key: str) -> Column:
    """How far a place moves on, by its alphabet's size: a keyed number coprime to that."""
    out = []
    for n in range(257):
        options = [k for k in range(1, n) if math.gcd(k, n) == 1] or [0]
        out.append(options[int(hashlib.sha256(f"{key}|step|{n}".encode()).hexdigest(), 16) % len(options)])
    return F.expr(f"array({','.join(map(str, out))})")


def reshaped(text: Column, kind: str, key: str) -> Column:
    """``text`` with its letters and digits permuted, its case, marks and other characters kept."""

    def made(chars: Column, original: Column, bases: Column) -> Column:
        shape = F.array_join(bases.cast("array<string>"), ",")
        moved = permuted(F.transform(chars, number), bases, F.concat(F.lit(kind + "|"), shape), key)
        out = F.zip_with(chars, moved, letter)
        cased = F.transform(out, lambda c, i: F.when(F.get(bases, i) == 0, F.get(original, i)).when(F.get(original, i) != F.get(chars, i), F.upper(c)).otherwise(c))
        return F.array_join(cased, "")

    split = lambda t: F.split(t, "")
    return bound(split(F.lower(text)), lambda chars: bound(split(text), lambda original: bound(F.transform(chars, radix), lambda bases: made(chars, original, bases))))


def address(text: Column, key: str) -> Column:
    parts = F.split(text, r"\.").cast("array<int>")
    return F.array_join(permuted(parts, F.array(*[F.lit(256)] * 4), F.lit("ip"), key).cast("array<string>"), ".")


def listed(name: Column, names: list[str]) -> Column:
    """The place in a list of a name written in capitals or with one; 0 for others."""
    return F.when((name == F.upper(name)) | (name == F.initcap(name)), F.array_position(F.array(*[F.lit(n) for n in names]), F.lower(name))).otherwise(F.lit(0))


def alike() -> int:
    """The most listed names of one shape."""
    return max(Counter("".join("v" if c in VOWELS else "c" for c in n) for n in FEMALE + MALE).values())


def one_name(name: Column, key: str) -> Column:
    """A given name of the lists goes to another of its list; any other name to a word of its shape that is in no list."""
    again = lambda w, _: F.when(listed(w, FEMALE + MALE) > 0, reshaped(w, "name", key)).otherwise(w)
    out = F.aggregate(F.sequence(F.lit(1), F.lit(alike())), reshaped(name, "name", key), again)
    for label, names in (("f", FEMALE), ("m", MALE)):
        at = listed(name, names)
        turn = F.conv(F.substring(F.sha2(F.lit(f"{key}|{label}").cast("binary"), 256), 1, 6), 16, 10).cast("int") % (len(names) - 1) + 1
        chosen = F.get(F.array(*[F.lit(n) for n in names]), ((at - 1 + turn) % len(names)).cast("int"))
        out = F.when(at > 0, F.when(name == F.upper(name), F.upper(chosen)).otherwise(F.initcap(chosen))).otherwise(out)
    return out


def kind_of(entity: Column) -> Column:
    return (
        F.when(F.contains(entity, F.lit("@")), "email")
        .when(entity.rlike("^(?:" + IPV4 + ")$"), "ip")
        .when(entity.rlike("^" + IBAN + "$"), "iban")
        .when(entity.rlike("^(?:" + SSN + ")$"), "ssn")
        .when(entity.rlike("^(?:" + CARD + ")$"), "card")
        .when(entity.rlike(r"^[+(0-9]"), "phone")
        .otherwise("name")
    )


def compactly(text: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` on the letters and digits alone, its result set between the other characters of ``text``: so one number has one surrogate however it is written."""
    other = lambda t: F.regexp_replace(t, "[^0-9A-Za-z]", "")
    return bound(use(other(text)), lambda made: F.array_join(F.transform(F.split(text, ""), lambda c, i: F.when(other(c) == "", c).otherwise(made.substr(F.length(other(text.substr(F.lit(1), i + 1))), F.lit(1)))), ""))


def luhn(digits: Column) -> Column:
    """The check digit behind a card's other digits (an array of numbers)."""
    counted = F.transform(F.reverse(digits), lambda d, i: F.when(i % 2 == 0, 2 * d - F.when(d > 4, 9).otherwise(0)).otherwise(d))
    return (10 - F.aggregate(counted, F.lit(0), lambda a, d: a + d) % 10) % 10


def card(number: Column, key: str) -> Column:
    digits = lambda t: F.filter(F.split(t, ""), lambda c: c != "").cast("array<int>")
    n = F.length(number)
    moved = F.concat(F.substring(number, 1, 1), reshaped(number.substr(F.lit(2), n - 2), "card", key))
    off = F.substring(number, -1, 1).cast("int") - luhn(digits(number.substr(F.lit(1), n - 1)))
    return bound(moved, lambda m: F.concat(m, F.pmod(luhn(digits(m)) + off, F.lit(10)).cast("string")))


def account(text: Column, key: str) -> Column:
    """An IBAN with its country, whose two check digits fit the other characters as the original's did."""

    def right(country: Column, rest: Column) -> Column:
        chars = F.filter(F.split(F.concat(rest, country, F.lit("00")), ""), lambda c: c != "")
        value = lambda c: F.when(F.ascii(c) >= 65, F.ascii(c) - 55).otherwise(F.ascii(c) - 48)
        return 98 - F.aggregate(chars, F.lit(0), lambda a, c: (a * F.when(F.ascii(c) >= 65, 100).otherwise(10) + value(c)) % 97)

    country, rest = F.substring(text, 1, 2), text.substr(F.lit(5), F.length(text))
    off = F.substring(text, 3, 2).cast("int") - right(country, rest)
    return bound(reshaped(rest, "iban", key), lambda m: F.concat(country, F.lpad(F.pmod(right(country, m) + off, F.lit(100)).cast("string"), 2, "0"), m))


def surrogate(entity: Column, key: str) -> Column:
    """The replacement of a found value."""
    tld = F.regexp_extract(entity, r"\.[A-Za-z]+$", 0)
    mail = F.concat(reshaped(entity.substr(F.lit(1), F.length(entity) - F.length(tld)), "email", key), tld)
    country = F.regexp_extract(entity, r"^\+[0-9]{1,3}(?=[ .(-])", 0)
    phone = F.concat(country, compactly(entity.substr(F.length(country) + 1, F.length(entity)), lambda t: reshaped(t, "phone", key)))
    words = F.split(entity, " ")
    titled = F.size(words) > 1
    named = F.transform(F.when(titled, F.slice(words, F.lit(2), F.size(words))).otherwise(words), lambda w: one_name(w, key))
    name = F.concat(F.when(titled, F.concat(F.element_at(words, 1), F.lit(" "))).otherwise(F.lit("")), F.array_join(named, " "))
    return bound(
        kind_of(entity),
        lambda kind: (
            F.when(kind == "email", mail)
            .when(kind == "ip", address(entity, key))
            .when(kind == "iban", compactly(entity, lambda t: account(t, key)))
            .when(kind == "card", compactly(entity, lambda t: card(t, key)))
            .when(kind == "phone", phone)
            .when(kind == "name", name)
            .otherwise(compactly(entity, lambda t: reshaped(t, "number", key)))
        ),
    )


def parted(text: Column) -> Column:
    """The text's pieces: at odd places (from 0) the values found, between them the rest."""
    mail, digit, title = F.contains(text, F.lit("@")), text.rlike("[0-9]"), F.contains(text, F.lit(TITLES[0]))
    for t in TITLES[1:]:
        title |= F.contains(text, F.lit(t))

    def searched(pattern: Column) -> Column:
        marked = F.split(F.regexp_replace(text, F.concat(F.lit("("), pattern, F.lit(")")), F.lit(f"{MARK}$1{MARK}")), MARK, -1)
        between, found = F.split(text, pattern, -1), F.regexp_extract_all(text, pattern, F.lit(0))  # for texts that hold the mark
        woven = F.flatten(F.transform(between, lambda t, i: F.when(i < F.size(found), F.array(t, F.get(found, i))).otherwise(F.array(t))))
        return F.when(F.contains(text, F.lit(MARK)), woven).otherwise(marked)

    numbers = "|".join([IPV4, IBAN, CARD, SSN, PHONE])
    plain = F.when(mail & digit, searched(F.lit(EMAIL + "|" + numbers))).when(digit, searched(F.lit(numbers))).when(mail, searched(F.lit(EMAIL)))
    persons = F.regexp_extract_all(text, F.lit(NAME), F.lit(0))
    words = F.array_distinct(F.flatten(F.transform(persons, lambda n: F.filter(F.split(n, " "), lambda w, i: i > 0))))
    every = F.lit(f"{EMAIL}|{numbers}|{NAME}" + r"|(?<!\p{L})(?:")
    named = bound(words, lambda w: F.when(F.size(w) > 0, searched(F.concat(every, F.array_join(w, "|"), F.lit(r")(?!\p{L})")))))
    return F.coalesce(F.when(title, named), plain, F.array(text))


def replace(docs: DataFrame, key: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows ``id, text`` (values replaced) ``, n_entities, kinds`` (of the values, in order) ``, distinct_kept`` for every row of ``docs``."""
    found = docs.select(F.col(id_col), F.col(text_col).alias("text"), parted(F.col(text_col)).alias("pieces"))
    made = found.select(id_col, "text", "pieces", F.transform("pieces", lambda p, i: F.when(i % 2 == 1, surrogate(p, key)).otherwise(p)).alias("made"))
    odd = lambda pieces: F.filter(pieces, lambda p, i: i % 2 == 1)
    many = lambda pieces: F.size(F.array_distinct(F.transform(odd(pieces), F.lower)))
    return made.select(id_col, F.when(F.col("text").isNotNull(), F.array_join("made", "")).alias("text"), F.size(odd("pieces")).alias("n_entities"), F.transform(odd("pieces"), kind_of).alias("kinds"), (many("pieces") == many("made")).alias("distinct_kept"))


def entities(docs: DataFrame, key: str, text_col: str = "text") -> DataFrame:
    """Rows ``kind, value, surrogate`` of all different values found, letter case apart."""
    values = docs.select(F.explode(F.filter(parted(F.col(text_col)), lambda p, i: i % 2 == 1)).alias("value"))
    kind = kind_of(F.col("value"))
    same = values.select(kind.alias("kind"), F.when(kind == "email", F.lower("value")).otherwise(F.col("value")).alias("value")).distinct()
    return same.withColumn("surrogate", surrogate(F.col("value"), key))


def collisions(docs: DataFrame, key: str, text_col: str = "text") -> DataFrame:
    """Rows ``kind, surrogate, n`` of surrogates that several values share: none, if distinctness holds."""
    return entities(docs, key, text_col).groupBy("kind", "surrogate").agg(F.count("*").alias("n")).where(F.col("n") > 1)
