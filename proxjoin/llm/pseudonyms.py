"""Format-preserving Feistel pseudonyms for personal data, with DataFrame functions only.

Values are found by pattern and kept only if valid: card numbers by their check
digit, dates by the calendar, addresses by their octets, phone numbers by their
length. A value becomes a list of small integers, each below its own
modulus: digits below 10, letters below 26, octets below 256, a day as its place
in a cycle of 400 years, 189 * 773 days, a social security number as the places
of its area, group and serial among the valid ones. A Feistel network over the halves of
the list, whose rounds add keyed hashes modulo each modulus, permutes all values
of a format, so different values stay different, equal ones stay linked in all
documents, and the format (case, separators, check digits) stays. ``restore``
runs the rounds backwards.

Defined cases: a null text stays null, an empty one empty; a text without valid
values is returned as it is; values overlap nowhere, the earliest match is
taken; rows that repeat are treated alike; an empty table gives an empty result.
Extra columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh, let

ROUNDS, KEY = 8, "proxjoin"
#: The patterns of personal data, tried in this order at each place.
KINDS = {
    "email": r"[A-Za-z0-9][A-Za-z0-9._%+-]*@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}",
    "date": r"\b\d{4}-\d{2}-\d{2}\b",
    "ip": r"(?<![\d.])\d{1,3}\.\d{1,3}\.\d{1,3}\.\d{1,3}(?!\.?\d)",
    "card": r"(?<![\d-])\d(?:[ -]?\d){12,18}(?![\d-])",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "phone": r"(?:\+1[ .-]?)?(?:\(\d{3}\) ?|(?<!\d)\d{3}[ .-])\d{3}[ .-]\d{4}(?!\d)",
}
ANY = "|".join(f"(?:{p})" for p in KINDS.values())
FIRST_DAY, CYCLE = "1800-01-01", (189, 773)
#: How many areas, groups and serials valid social security numbers have; no area is 0, 666 or above 899.
SSN, NO_AREA = (898, 99, 9999), 666


def digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def numbers(text: Column) -> Column:
    """The characters of a text as integers: 0-9 for digits, 0-25 for letters of either case."""
    code = lambda c: F.ascii(c)
    return F.transform(F.split(text, ""), lambda c: F.when(c.rlike("[0-9]"), code(c) - 48).when(c.rlike("[a-z]"), code(c) - 97).when(c.rlike("[A-Z]"), code(c) - 65).otherwise(0))


def moduli(text: Column) -> Column:
    """How many values each character has in its class; 1 for what never changes."""
    return F.transform(F.split(text, ""), lambda c: F.when(c.rlike("[0-9]"), 10).when(c.rlike("[A-Za-z]"), 26).otherwise(1))


def spelled(values: Column, like: Column) -> Column:
    """Integers as characters of the classes that ``like`` has at their places."""
    one = lambda c, v: F.when(c.rlike("[0-9]"), F.char(48 + v)).when(c.rlike("[a-z]"), F.char(97 + v)).when(c.rlike("[A-Z]"), F.char(65 + v)).otherwise(c)
    return F.array_join(F.zip_with(F.split(like, ""), values, one), "")


def luhn(number: Column) -> Column:
    """The sum of a card number's check: 0 modulo 10 if it is valid."""
    weigh = lambda v, i: F.when(i % 2 == 1, F.when(v > 4, 2 * v - 9).otherwise(2 * v)).otherwise(v)
    return F.aggregate(F.transform(F.reverse(numbers(number)), weigh), F.lit(0), lambda a, x: a + x)


def permuted(values: Column, sizes: Column, key: str, kind: str, back: bool = False) -> Column:
    """values after all rounds: even rounds change the first half by the second, odd ones the second by the first."""

    def turn(now: Column, r: Column) -> Column:
        half = F.floor(F.size(now) / 2).cast("int")
        first = F.slice(now, F.lit(1), half)
        second = F.slice(now, half + 1, F.size(now) - half)
        fixed = F.when(r % 2 == 0, second).otherwise(first)
        digest = F.concat_ws(":", F.lit(key), F.lit(kind), F.array_join(sizes.cast("array<string>"), ","), r.cast("string"), F.array_join(fixed.cast("array<string>"), ","))
        step = lambda i: F.conv(F.substring(F.sha2(F.concat_ws(":", digest, i.cast("string")), 256), 1, 12), 16, 10).cast("long")
        move = lambda v, i: F.when(((i < half) & (r % 2 == 0)) | ((i >= half) & (r % 2 == 1)), F.pmod((v - step(i)) if back else (v + step(i)), F.element_at(sizes, i + 1)).cast("int")).otherwise(v)
        return F.transform(now, move)

    order = range(ROUNDS - 1, -1, -1) if back else range(ROUNDS)
    return F.aggregate(F.array(*map(F.lit, order)), values.cast("array<int>"), turn)


def kind_of(value: Column) -> Column:
    """The kind of a match, or null where it isn't valid."""
    number = digits(value)
    octets = F.split(value, r"\.")
    valid = {
        "email": F.lit(True),
        "date": F.try_to_date(value, "yyyy-MM-dd").isNotNull() & value.between("1800-01-01", "2199-12-31"),
        "ip": F.forall(octets, lambda o: o.cast("int") < 256) & (F.array_join(F.transform(octets, lambda o: o.cast("int").cast("string")), ".") == value),
        "card": (luhn(number) % 10 == 0) & number.rlike("^[2-6]"),
        "ssn": ~value.rlike("^(000|666|9)|-00-|-0000$"),
        "phone": F.length(number).isin(10, 11),
    }
    out = F.lit(None).cast("string")
    for kind in reversed(list(KINDS)):
        out = F.when(value.rlike(f"^(?:{KINDS[kind]})$"), F.when(valid[kind], F.lit(kind))).otherwise(out)
    return out


def laid(number: Column, like: Column) -> Column:
    """The digits of a number in the places that ``like`` has digits."""
    place = lambda i: F.length(digits(F.substring(like, F.lit(1), i + 1)))
    return F.array_join(F.transform(F.split(like, ""), lambda c, i: F.when(c.rlike("[0-9]"), F.substring(number, place(i), F.lit(1))).otherwise(c)), "")


def pseudonym(value: Column, key: str = KEY, back: bool = False) -> Column:
    """The value's pseudonym, or the value itself if it isn't valid; with back, the other way."""

    def of_text(kind: str, text: Column) -> Column:
        return spelled(permuted(numbers(text), moduli(text), key, kind, back), text)

    number = digits(value)
    name = F.substring_index(value, "@", 1)
    body = F.substring(number, F.lit(2), F.length(number) - 2)
    card = F.concat(F.substring(number, 1, 1), of_text("card", body))
    check = F.pmod(10 - luhn(F.concat(card, F.lit("0"))) % 10, F.lit(10)).cast("string")
    octets = F.split(value, r"\.").cast("array<int>")
    day = F.datediff(F.try_to_date(value, "yyyy-MM-dd"), F.lit(FIRST_DAY).cast("date"))
    day = let(permuted(F.array(F.floor(day / CYCLE[1]).cast("int"), (day % CYCLE[1]).cast("int")), F.array(*map(F.lit, CYCLE)), key, "date", back), lambda p: p[0] * CYCLE[1] + p[1])
    part = lambda a, n: F.substring(number, a, n).cast("int")
    area = part(1, 3)
    ssn = permuted(F.array(area - F.when(area > NO_AREA, 2).otherwise(1), part(4, 2) - 1, part(6, 4) - 1), F.array(*map(F.lit, SSN)), key, "ssn", back)
    ssn = let(ssn, lambda p: F.concat(F.lpad((p[0] + F.when(p[0] >= NO_AREA - 1, 2).otherwise(1)).cast("string"), 3, "0"), F.lpad((p[1] + 1).cast("string"), 2, "0"), F.lpad((p[2] + 1).cast("string"), 4, "0")))
    last = lambda n: F.substring(number, -n, n)
    made = {
        "email": F.concat(of_text("email", name), F.substring(value, F.length(name) + 1, F.length(value))),
        "date": F.date_format(F.date_add(F.lit(FIRST_DAY).cast("date"), day), "yyyy-MM-dd"),
        "ip": F.array_join(permuted(octets, F.transform(octets, lambda o: F.lit(256)), key, "ip", back).cast("array<string>"), "."),
        "card": laid(F.concat(card, check), value),
        "ssn": laid(ssn, value),
        # a leading 1 and the area's first digit stay
        "phone": laid(F.concat(F.substring(number, F.lit(1), F.length(number) - 9), of_text("phone", last(9))), value),
    }

    def choose(kind: Column) -> Column:
        out = value
        for k, v in made.items():
            out = F.when(kind == k, v).otherwise(out)
        return out

    return let(kind_of(value), choose)


def masked(text: Column, key: str = KEY, back: bool = False) -> Column:
    """A text with each valid value as its pseudonym; what stands between is untouched."""
    found = F.regexp_extract_all(text, F.lit(ANY), F.lit(0))
    between = F.split(text, ANY, -1)
    put = lambda a, b: F.concat(a, F.coalesce(pseudonym(b, key, back), F.lit("")))
    # most texts hold nothing like a value, and one cheap pattern tells
    return F.when(text.rlike(r"@|\d"), F.array_join(F.zip_with(between, found, put), "")).otherwise(text)


def pseudonymise(docs: DataFrame, key: str = KEY) -> DataFrame:
    """docs with pseudonyms in their texts; same columns."""
    return docs.withColumn("text", masked(F.col("text"), key))


def restore(docs: DataFrame, key: str = KEY) -> DataFrame:
    """The reverse of pseudonymise, for who has the key."""
    return docs.withColumn("text", masked(F.col("text"), key, back=True))


def report(docs: DataFrame, key: str = KEY) -> DataFrame:
    """doc_id, the pseudonymised text and how many valid values of each kind it had."""
    (found,) = fresh(docs, "found")
    matches = F.when(F.col("text").rlike(r"@|\d"), F.transform(F.regexp_extract_all("text", F.lit(ANY), F.lit(0)), kind_of))
    rows = docs.withColumn(found, F.coalesce(matches, F.array().cast("array<string>")))
    number = lambda kind: F.size(F.filter(F.col(found), lambda k: k == kind)).cast("long")
    counts = [number(kind).alias(f"n_{kind}") for kind in KINDS]
    return rows.select("doc_id", masked(F.col("text"), key).alias("text"), *counts)
