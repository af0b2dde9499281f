"""Format-preserving pseudonyms of personal numbers, dates and addresses, in DataFrame functions only.

One expression finds candidates in a text; each is validated by its kind (Luhn digit of cards, mod-97 digits of IBANs, shape
of North American phone numbers, octets up to 255, groups of IPv6 addresses, real calendar dates from 1900 to 2299, US
numbers of areas 001 to 899 without 666) and, if valid, goes through a keyed Feistel network on its own format: characters
are added position by position within their class (digits, letters, first digits of phone blocks), dates permute within 400
Gregorian years as a pair of remainders (189 x 773 days), US numbers within all valid ones, addresses within 32 or 128 bits,
cards and IBANs get fresh check digits. Dates with slashes are month first; those that can only be day first permute among
themselves, by walking the cycle of the network until the day is above 12 again. A network is a bijection on what its test
accepts, so pseudonyms pass the same test, equal values get equal pseudonyms in all documents and different ones stay
different (an IPv6 address is written in full). What is not valid stays as it is. The mail domain and the country of an IBAN
stay; an area code of a phone is valid (2 to 9 first) after the permutation where it was so before.

Nulls: a null text stays null with zero counts. Repeated rows are equal. Everything is row-local: no shuffle, no state, no
Python on executors.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Key of the registered query. A pipeline passes its own secret.
DEMO_KEY = "cutstream-demonstration-key"
ROUNDS = 8
KINDS = ("card", "phone", "ip", "date", "ssn", "email", "iban", "ipv6")
#: Steps of a cycle walk; two in three dates need one, and a walk of so many does not occur.
WALK = 96
#: Candidate formats, tried in this order at each place.
FORMATS = (
    r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+",
    r"(?:\+1[ .-]?|(?<![0-9]))\([0-9]{3}\)[ .-]?[0-9]{3}[ .-][0-9]{4}(?![0-9])",
    r"(?:\+1[ .-]?|(?<![0-9A-Za-z_])(?<![0-9A-Za-z][.+-])(?:1[ .-])?)[0-9]{3}[ .-][0-9]{3}[ .-][0-9]{4}(?![0-9_]|[.-][0-9])",
    r"(?<![0-9A-Za-z.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?![0-9A-Za-z]|\.[0-9])",
    r"(?<![0-9A-Za-z:.])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![0-9A-Za-z:])",
    r"(?<![0-9A-Za-z:.])[0-9A-Fa-f]{3,4}(?::[0-9A-Fa-f]{1,4}){0,5}::(?:[0-9A-Fa-f]{1,4}(?::[0-9A-Fa-f]{1,4}){0,5})?(?![0-9A-Za-z:])",
    r"(?<![0-9A-Za-z])[A-Z]{2}[0-9]{2}(?:[A-Z0-9]{11,30}|(?: [A-Z0-9]{4}){2,7}(?: [A-Z0-9]{1,3})?)(?![0-9A-Za-z])",
    r"(?<![0-9A-Za-z/.])[0-9]{1,2}/[0-9]{1,2}/[0-9]{4}(?![0-9A-Za-z/])",
    r"(?<![0-9A-Za-z/-])[0-9]{4}-[0-9]{2}-[0-9]{2}(?![0-9/-])",
    r"(?<![0-9A-Za-z.])[0-9]{2}\.[0-9]{2}\.[0-9]{4}(?![0-9]|\.[0-9])",
    r"(?<![0-9A-Za-z-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9A-Za-z-])",
    r"(?<![0-9A-Za-z])(?:[0-9]{13,19}|[0-9]{4}([ -])[0-9]{4}\1[0-9]{4}\1[0-9]{1,7}|[0-9]{4}([ -])[0-9]{6}\2[0-9]{5})(?![0-9A-Za-z])",
)
PATTERN = "|".join(FORMATS)
#: A phone number in parts: what stands before it, area, separator, exchange, separator, line.
_PHONE = r"^((?:\+?1[ .-]?)?\(?)([0-9]{3})(\)?[ .-]?)([0-9]{3})([ .-])([0-9]{4})$"
_FIRST_DAY, _DAYS, _A, _B = "1900-01-01", 146097, 189, 773
#: Character classes: first code and number of codes.
_CLASSES = {"d": (48, 10), "n": (50, 8), "z": (48, 2), "h": (97, 16), "a": (97, 26), "A": (65, 26)}


def _let(value: Column, use) -> Column:
    """use(value) with value evaluated once."""
    return F.transform(F.array(value), use)[0]


def _hash(key: str, kind: str, r: Column, value: Column) -> Column:
    return F.sha2(F.concat_ws("|", F.lit(key), F.lit(kind), r.cast("string"), value.cast("string")), 512)


def _number(h: Column, at: Column | int, modulus: int | Column) -> Column:
    """Four hex digits of h from the (at mod 32)-th group on, as a number below modulus."""
    start = at * 4 + 1 if isinstance(at, int) else F.pmod(at, F.lit(32)) * 4 + 1
    return F.pmod(F.conv(F.substring(h, start, F.lit(4)) if isinstance(start, Column) else F.substring(h, start, 4), 16, 10).cast("int"), modulus)


def _added(half: Column, classes: Column, h: Column) -> Column:
    """half plus the key stream of h, each character within its class."""

    def one(i: Column) -> Column:
        c, out = F.substring(half, i, F.lit(1)), None
        k = F.substring(classes, i, F.lit(1))
        for name, (low, n) in _CLASSES.items():
            moved = F.char(F.lit(low) + F.pmod(F.ascii(c) - low + _number(h, i - 1, n), F.lit(n)))
            out = F.when(k == name, moved) if out is None else out.when(k == name, moved)
        return out.otherwise(c)

    return F.when(F.length(half) == 0, F.lit("")).otherwise(F.array_join(F.transform(F.sequence(F.lit(1), F.length(half)), one), ""))


def permuted(value: Column, classes: Column, key: str, kind: str) -> Column:
    """Feistel network on the two halves of a string; classes names each position's alphabet (x: fixed)."""
    n = F.length(value)
    cut = F.floor(n / 2).cast("int")
    part = lambda s, right: F.substring(s, cut + 1, n) if right else F.substring(s, F.lit(1), cut)
    start = F.struct(part(value, False).alias("l"), part(value, True).alias("r"))

    def round_(acc: Column, r: Column) -> Column:
        even = r % 2 == 0
        left = F.when(even, _let(_hash(key, kind, r, acc["r"]), lambda h: _added(acc["l"], part(classes, False), h))).otherwise(acc["l"])
        right = F.when(even, acc["r"]).otherwise(_let(_hash(key, kind, r, acc["l"]), lambda h: _added(acc["r"], part(classes, True), h)))
        return F.struct(left.alias("l"), right.alias("r"))

    return F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), start, round_, lambda acc: F.concat(acc["l"], acc["r"]))


def permuted_pair(a: Column, b: Column, size_a: int, size_b: int, key: str, kind: str) -> Column:
    """Feistel network on a pair of numbers below size_a and size_b; a struct (a, b)."""

    def big(h: Column, n: int) -> Column:
        return F.pmod(F.conv(F.substring(h, 1, 12), 16, 10).cast("long"), F.lit(n))

    def round_(acc: Column, r: Column) -> Column:
        even = r % 2 == 0
        x = F.when(even, F.pmod(acc["a"] + big(_hash(key, kind, r, acc["b"]), size_a), F.lit(size_a))).otherwise(acc["a"])
        y = F.when(even, acc["b"]).otherwise(F.pmod(acc["b"] + big(_hash(key, kind, r, acc["a"]), size_b), F.lit(size_b)))
        return F.struct(x.alias("a"), y.alias("b"))

    return F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), F.struct(a.cast("long").alias("a"), b.cast("long").alias("b")), round_)


def luhn_sum(digits: Column) -> Column:
    """Sum of a digit string as its Luhn check counts it, the last digit once."""
    n = F.length(digits)

    def one(i: Column) -> Column:
        d = F.ascii(F.substring(digits, i, F.lit(1))) - 48
        twice = d * 2
        return F.when((n - i) % 2 == 1, twice - F.when(twice > 9, 9).otherwise(0)).otherwise(d)

    return F.aggregate(F.transform(F.sequence(F.lit(1), n), one), F.lit(0), lambda s, d: s + d)


def _card(m: Column, key: str) -> Column:
    digits = F.regexp_replace(m, "[ -]", "")
    sep = F.regexp_extract(m, "^[0-9]{4}([ -])", 1)

    def make(d: Column) -> Column:
        n = F.length(d)
        own = F.substring(d, F.lit(1), n - 1)
        return _let(permuted(own, F.repeat(F.lit("d"), n - 1), key, "card"), lambda p: F.concat(p, F.pmod(F.lit(10) - F.pmod(luhn_sum(F.concat(p, F.lit("0"))), F.lit(10)), F.lit(10)).cast("string")))

    fours = lambda p: F.concat(F.substring(p, 1, 4), sep, F.substring(p, 5, 4), sep, F.substring(p, 9, 4), sep, F.substring(p, 13, 19))
    uneven = lambda p: F.concat(F.substring(p, 1, 4), sep, F.substring(p, 5, 6), sep, F.substring(p, 11, 5))
    grouped = lambda p: F.when(sep == "", p).when(m.rlike("^[0-9]{4}[ -][0-9]{6}"), uneven(p)).otherwise(fours(p))
    return F.when(luhn_sum(digits) % 10 == 0, _let(make(digits), grouped))


def _phone(m: Column, key: str) -> Column:
    g = lambda i: F.regexp_extract(m, _PHONE, i)
    ten = F.concat(g(2), g(4), g(6))
    classes = F.concat(F.when(ten.rlike("^[2-9]"), "n").otherwise("z"), F.lit("ddndddddd"))
    return F.when(ten.rlike("^[0-9]{3}[2-9]"), _let(permuted(ten, classes, key, "phone"), lambda p: F.concat(g(1), F.substring(p, 1, 3), g(3), F.substring(p, 4, 3), g(5), F.substring(p, 7, 4))))


def _ip(m: Column, key: str) -> Column:
    o = F.transform(F.split(m, r"\."), lambda x: x.cast("int"))
    valid = F.forall(o, lambda x: x <= 255)
    text = lambda p: F.concat_ws(".", F.floor(p["a"] / 256).cast("string"), (p["a"] % 256).cast("string"), F.floor(p["b"] / 256).cast("string"), (p["b"] % 256).cast("string"))
    return F.when(valid, _let(permuted_pair(o[0] * 256 + o[1], o[2] * 256 + o[3], 65536, 65536, key, "ip"), text))


def _ipv6(m: Column, key: str) -> Column:
    """All eight groups of four hex digits, as letters a to p while they permute."""
    halves = F.split(F.lower(m), "::")
    groups = lambda x: F.filter(F.split(x, ":"), lambda g: g != "")
    left, right = groups(halves[0]), F.when(F.size(halves) > 1, groups(F.element_at(halves, -1))).otherwise(F.array().cast("array<string>"))
    given = F.size(left) + F.size(right)
    whole = F.concat(left, F.array_repeat(F.lit("0"), F.greatest(F.lit(0), 8 - given)), right)
    digits = F.array_join(F.transform(whole, lambda g: F.lpad(g, 4, "0")), "")
    moved = permuted(F.translate(digits, "0123456789abcdef", "abcdefghijklmnop"), F.repeat(F.lit("h"), F.lit(32)), key, "ipv6")
    text = lambda p: F.concat_ws(":", *[F.substring(p, 4 * i + 1, 4) for i in range(8)])
    return F.when(F.when(F.size(halves) > 1, given <= 7).otherwise(given == 8), _let(F.translate(moved, "abcdefghijklmnop", "0123456789abcdef"), text))


def _mod97(text: Column) -> Column:
    """Remainder of digits and capitals (10 to 35) read as one number."""

    def step(r: Column, c: Column) -> Column:
        code = F.ascii(c)
        return F.when(code < 65, (r * 10 + code - 48) % 97).otherwise((r * 100 + code - 55) % 97)

    return F.aggregate(F.filter(F.split(text, ""), lambda c: c != ""), F.lit(0), step)


def _iban(m: Column, key: str) -> Column:
    """Country and length stay; each character of the account permutes within its class; check digits 02 to 98."""
    plain = F.translate(m, " ", "")
    country, check, own = F.substring(plain, 1, 2), F.substring(plain, 3, 2), F.substring(plain, F.lit(5), F.length(plain))
    valid = (F.length(plain) >= 15) & (F.length(plain) <= 34) & (check >= "02") & (check <= "98") & (_mod97(F.concat(own, country, check)) == 1)
    classes = F.regexp_replace(F.regexp_replace(own, "[0-9]", "d"), "[A-Z]", "A")
    checked = lambda p: F.concat(country, F.lpad((98 - _mod97(F.concat(p, country, F.lit("00")))).cast("string"), 2, "0"), p)
    spaced = lambda p: F.when(m.contains(" "), F.rtrim(F.regexp_replace(p, "(.{4})", "$1 "))).otherwise(p)
    return F.when(valid, _let(_let(permuted(own, classes, key, "iban"), checked), spaced))


def _moved_day(day: Column, key: str) -> Column:
    """Days since the first one, permuted within 400 years."""
    return _let(permuted_pair(F.floor(day / _B), day % _B, _A, _B, key, "date"), lambda p: (p["a"] * _B + p["b"]).cast("int"))


def _on(day: Column) -> Column:
    return F.date_add(F.lit(_FIRST_DAY).cast("date"), day)


def _date(m: Column, key: str, form: str) -> Column:
    day = F.datediff(F.try_to_timestamp(m, F.lit(form)), F.lit(_FIRST_DAY).cast("date"))
    return F.when((day >= 0) & (day < _DAYS), F.date_format(_on(_moved_day(day, key)), form))


def _slashed(m: Column, key: str) -> Column:
    """Month first where that is a date; else day first, among the dates whose day is above 12. A date written without a
    leading zero gets none."""
    parts = F.split(m, "/")
    padded = F.concat_ws("/", F.lpad(parts[0], 2, "0"), F.lpad(parts[1], 2, "0"), parts[2])
    day = lambda form: F.datediff(F.try_to_timestamp(padded, F.lit(form)), F.lit(_FIRST_DAY).cast("date"))
    within = lambda d: (d >= 0) & (d < _DAYS)
    us, eu = day("MM/dd/yyyy"), day("dd/MM/yyyy")
    walk = lambda d: F.aggregate(F.sequence(F.lit(1), F.lit(WALK)), _moved_day(d, key), lambda x, _: F.when(F.dayofmonth(_on(x)) > 12, x).otherwise(_moved_day(x, key)))
    short = m.rlike("^[0-9]/|/[0-9]/")
    text = lambda d, wide, narrow: F.when(short, F.date_format(d, narrow)).otherwise(F.date_format(d, wide))
    first = _let(_on(_moved_day(us, key)), lambda d: text(d, "MM/dd/yyyy", "M/d/yyyy"))
    other = _let(_on(walk(eu)), lambda d: text(d, "dd/MM/yyyy", "d/M/yyyy"))
    return F.when(within(us), first).when(within(eu) & (F.dayofmonth(_on(eu)) > 12), other)


def _ssn(m: Column, key: str) -> Column:
    """Areas 001 to 899 without 666 and, as one number, groups 01 to 99 with serials 0001 to 9999 permute as a pair."""
    part = lambda at, n: F.substring(m, at, n).cast("int")
    valid = m.rlike("^(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}$")
    area = part(1, 3) - F.when(part(1, 3) > 666, 2).otherwise(1)
    padded = lambda x, n: F.lpad(x.cast("string"), n, "0")
    text = lambda p: F.concat_ws("-", padded(p["a"] + F.when(p["a"] >= 665, 2).otherwise(1), 3), padded(F.floor(p["b"] / 9999) + 1, 2), padded(p["b"] % 9999 + 1, 4))
    return F.when(valid, _let(permuted_pair(area, (part(5, 2) - 1) * 9999 + part(8, 4) - 1, 898, 99 * 9999, key, "ssn"), text))


def _email(m: Column, key: str) -> Column:
    local = F.substring_index(m, "@", 1)
    classes = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(local, "[^A-Za-z0-9]", "-"), "[0-9]", "0"), "[a-z]", "a"), "[A-Z]", "A")
    return F.concat(permuted(local, F.translate(classes, "0-", "dx"), key, "email"), F.substring(m, F.length(local) + 1, F.length(m)))


def pseudonym(m: Column, key: str) -> Column:
    """(kind, text) of one candidate; kind is null where it is not valid."""
    made = [
        ("email", m.contains("@"), _email(m, key)),
        ("phone", m.rlike(_PHONE), _phone(m, key)),
        ("ip", m.rlike(r"^[0-9]{1,3}(?:\.[0-9]{1,3}){3}$"), _ip(m, key)),
        ("date", m.rlike("^[0-9]{4}-[0-9]{2}-[0-9]{2}$"), _date(m, key, "yyyy-MM-dd")),
        ("date", m.rlike(r"^[0-9]{2}\.[0-9]{2}\.[0-9]{4}$"), _date(m, key, "dd.MM.yyyy")),
        ("date", m.contains("/"), _slashed(m, key)),
        ("ssn", m.rlike("^[0-9]{3}-[0-9]{2}-[0-9]{4}$"), _ssn(m, key)),
        ("ipv6", m.contains(":"), _ipv6(m, key)),
        ("iban", m.rlike("^[A-Z]{2}[0-9]{2}"), _iban(m, key)),
    ]
    value, kind = None, None
    for name, test, new in made:
        value = F.when(test, new) if value is None else value.when(test, new)
        kind = F.when(test, F.lit(name)) if kind is None else kind.when(test, F.lit(name))
    return _let(F.struct(value.otherwise(_card(m, key)).alias("new"), kind.otherwise("card").alias("kind")), lambda x: F.struct(F.when(x["new"].isNotNull(), x["kind"]).alias("kind"), F.coalesce(x["new"], m).alias("text")))


def pseudonymise(docs: DataFrame, key: str) -> DataFrame:
    """doc_id, text with pseudonyms, and the number of replaced values of each kind."""
    maybe = F.col("text").rlike("[0-9@]")
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.when(maybe, F.transform(F.regexp_extract_all("text", F.lit(PATTERN), F.lit(0)), lambda m: pseudonym(m, key))).alias("hits"))
    pieces = F.split("text", PATTERN)
    rebuilt = F.concat(F.array_join(F.zip_with(F.slice(pieces, 1, F.size("hits")), "hits", lambda p, h: F.concat(p, h["text"])), ""), F.element_at(pieces, -1))

    def count(kind: str) -> Column:
        own = F.size(F.filter("hits", lambda h: h["kind"] == kind))
        return F.when(F.size("hits") > 0, own).otherwise(0).cast("long").alias(f"n_{kind}")

    return found.select("doc_id", F.when(F.size("hits") > 0, rebuilt).otherwise(F.col("text")).alias("text"), *[count(k) for k in KINDS])


def op2_pii_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with pseudonyms."""
    return pseudonymise(spark.read.parquet(f"{sf_dir}/documents.parquet"), DEMO_KEY)
