"""Format-preserving Feistel pseudonyms for personal data, in DataFrame functions only.

Card numbers (13 to 19 digits, Luhn-valid), phone numbers, US social security numbers,
IPv4 addresses, dates and e-mail addresses are found by one pattern, validated, and each valid value is replaced by
a keyed permutation of its own format, so equal values stay equal in every document and a
pseudonym is as valid as its original. A value is split in two halves in Z_M x Z_N, and
ROUNDS times one half is moved by a keyed SHA-256 of the other (mod its size), which is a
permutation for any M and N: no cycle walking is needed. `inverse=True` undoes it.

Card: all digits but the last are permuted, the last is the Luhn digit of the rest. Phone:
all digits but a country code after "+"; of ten digits without one, area and exchange codes stay
200 or more if they were. Social security number: (valid areas) x (groups and serials). Address: 2^16 x
2^16. Date (yyyy-MM-dd, MM/dd/yyyy, dd.MM.yyyy): the days of 1900 to 2099 (17 x 4297). E-mail: a-z, A-Z and 0-9 of
the local part move within their class, other characters and the domain stay.

Defined results: null texts stay null, empty ones empty; invalid candidates stay as they are; all
of a text is treated, whatever its length; repeated rows give equal rows; extra columns are kept,
whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import unused

ROUNDS = 8
#: Public test key: pseudonyms made with it hide nothing from those who know it.
TEST_KEY = "public test key"
LETTER = r"[\p{L}0-9._%+-]"
PATTERNS = {
    "email": f"(?<!{LETTER}){LETTER}++" + r"@(?:[A-Za-z0-9-]{1,63}\.){1,8}[A-Za-z]{2,24}",
    "ipv4": r"(?<![\d.])\d{1,3}(?:\.\d{1,3}){3}(?![\d]|\.\d)",
    "iso_date": r"(?<![\d-])\d{4}-\d{2}-\d{2}(?![\d-])",
    "us_date": r"(?<![\d/])\d{2}/\d{2}/\d{4}(?![\d/])",
    "dot_date": r"(?<![\d.])\d{2}\.\d{2}\.\d{4}(?!\d|\.\d)",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "phone": r"(?<![\d+])\+\d{1,3}[ .-]?(?:\(\d{1,4}\)[ .-]?)?\d{2,4}(?:[ .-]?\d{2,4}){1,3}(?!\d)|(?<![\d(])\(\d{3}\) ?\d{3}-\d{4}(?!\d)|(?<![\d.-])(?:1-)?\d{3}-\d{3}-\d{4}(?![\d-])|(?<![\d.-])\d{3}\.\d{3}\.\d{4}(?!\d|\.\d)|(?<![\d.-])(?<!\d )\d{3} \d{3} \d{4}(?!\d| \d)",
    "card": r"(?<!\d)(?:\d{13,19}|\d{4}(?:[ -]\d{4}){3}|\d{4}[ -]\d{6}[ -]\d{5})(?!\d)",
}
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
KINDS = ("email", "ipv4", "date", "ssn", "phone", "card")


def let(x: Column, f) -> Column:
    return F.get(F.transform(F.array(x), f), F.lit(0))


def prf(key: str, kind: str, r: Column, x: Column) -> Column:
    """60 bits of SHA-256 of length-free fields parted by a character that none of them holds."""
    return F.conv(F.substring(F.sha2(F.concat_ws("\x1f", F.lit(key), F.lit(kind), r.cast("string"), x.cast("string")), 256), 1, 15), 16, 10).cast("bigint")


def rounds(inverse: bool) -> Column:
    return F.reverse(F.sequence(F.lit(0), F.lit(ROUNDS - 1))) if inverse else F.sequence(F.lit(0), F.lit(ROUNDS - 1))


def feistel(a: Column, b: Column, m: Column, n: Column, key: str, kind: str, inverse: bool) -> Column:
    """struct(a, b): a keyed permutation of Z_m x Z_n."""
    sign = -1 if inverse else 1

    def step(s: Column, r: Column) -> Column:
        left = F.struct(F.pmod(s["a"] + sign * (prf(key, kind, r, s["b"]) % m), m).alias("a"), s["b"].alias("b"))
        right = F.struct(s["a"].alias("a"), F.pmod(s["b"] + sign * (prf(key, kind, r, s["a"]) % n), n).alias("b"))
        return F.when(r % 2 == 0, left).otherwise(right)

    return F.aggregate(rounds(inverse), F.struct(a.cast("bigint").alias("a"), b.cast("bigint").alias("b")), step)


def digits_of(s: Column) -> Column:
    return F.regexp_replace(s, "[^0-9]", "")


def refill(shape: Column, digits: Column) -> Column:
    """shape with its digits replaced, in order, by the given ones."""
    chars = F.regexp_extract_all(shape, F.lit("(?s)."), F.lit(0))
    return F.array_join(F.transform(chars, lambda c, i: F.when(c.rlike("[0-9]"), F.substring(digits, F.length(digits_of(F.substring(shape, F.lit(1), i + 1))), F.lit(1))).otherwise(c)), "")


def permute_digits(d: Column, key: str, kind: str, inverse: bool) -> Column:
    u = F.floor(F.length(d) / 2).cast("int")
    m, n = F.pow(F.lit(10.0), u).cast("bigint"), F.pow(F.lit(10.0), F.length(d) - u).cast("bigint")
    s = feistel(F.substring(d, F.lit(1), u), F.substring(d, u + 1, F.length(d)), m, n, key, kind, inverse)
    return let(s, lambda x: F.concat(F.lpad(x["a"].cast("string"), u, "0"), F.lpad(x["b"].cast("string"), F.length(d) - u, "0")))


def luhn_sum(d: Column, doubled: int) -> Column:
    """Luhn sum; doubled: places from the right, from 0, whose parity is doubled."""
    codes = F.transform(F.reverse(F.split(d, "")), lambda c, i: let(c.cast("int") * F.when(i % 2 == doubled, 2).otherwise(1), lambda v: F.when(v > 9, v - 9).otherwise(v)))
    return F.aggregate(codes, F.lit(0), lambda s, x: s + F.coalesce(x, F.lit(0)))


def card(m: Column, key: str, inverse: bool) -> Column:
    d = digits_of(m)
    body = permute_digits(F.substring(d, F.lit(1), F.length(d) - 1), key, "card", inverse)
    full = let(body, lambda x: F.concat(x, (F.pmod(10 - luhn_sum(x, 0) % 10, F.lit(10))).cast("string")))
    return F.when(luhn_sum(d, 1) % 10 == 0, let(full, lambda x: refill(m, x)))


def ssn(m: Column, key: str, inverse: bool) -> Column:
    area, group, serial = (F.substring(m, a, n).cast("int") for a, n in ((1, 3), (5, 2), (8, 4)))
    valid = (area > 0) & (area < 900) & (area != 666) & (group > 0) & (serial > 0)
    s = feistel(area - F.when(area > 666, 2).otherwise(1), (group - 1) * 9999 + serial - 1, F.lit(898), F.lit(99 * 9999), key, "ssn", inverse)

    def text(x: Column) -> Column:
        a = x["a"] + F.when(x["a"] >= 665, 2).otherwise(1)
        return F.concat_ws("-", F.lpad(a.cast("string"), 3, "0"), F.lpad((F.floor(x["b"] / 9999) + 1).cast("string"), 2, "0"), F.lpad((x["b"] % 9999 + 1).cast("string"), 4, "0"))

    return F.when(valid, let(s, text))


def ipv4(m: Column, key: str, inverse: bool) -> Column:
    o = F.transform(F.split(m, r"\."), lambda x: x.cast("int"))
    valid = F.forall(o, lambda x: x < 256) & ~m.rlike(r"(^|\.)0\d")
    s = feistel(F.get(o, F.lit(0)) * 256 + F.get(o, F.lit(1)), F.get(o, F.lit(2)) * 256 + F.get(o, F.lit(3)), F.lit(65536), F.lit(65536), key, "ipv4", inverse)
    return F.when(valid, let(s, lambda x: F.concat_ws(".", *[v.cast("string") for v in (F.floor(x["a"] / 256), x["a"] % 256, F.floor(x["b"] / 256), x["b"] % 256)])))


def date(m: Column, shape: str, key: str, inverse: bool) -> Column:
    day = F.try_to_date(m, shape)
    at = F.datediff(day, F.lit("1900-01-01").cast("date"))
    s = feistel(F.floor(at / 4297), at % 4297, F.lit(17), F.lit(4297), key, "date", inverse)
    return F.when(day.between("1900-01-01", "2099-12-31"), let(s, lambda x: F.date_format(F.date_add(F.lit("1900-01-01").cast("date"), (x["a"] * 4297 + x["b"]).cast("int")), shape)))


def phone(m: Column, key: str, inverse: bool) -> Column:
    """Digits after a country code; a ten-digit number keeps whether its area and exchange codes are in use (200 or more)."""
    code = F.regexp_extract(m, r"^(\+\d{1,3}|1-)?", 0)
    rest = F.substring(m, F.length(code) + 1, F.length(m))

    def national(x: Column) -> Column:
        area, exchange = F.substring(x, 1, 3).cast("int"), F.substring(x, 4, 3).cast("int")
        low = lambda c: F.when(c < 200, 0).otherwise(200)
        size = lambda c: F.when(c < 200, 200).otherwise(800)
        s = feistel(area - low(area), (exchange - low(exchange)) * 10_000 + F.substring(x, 7, 4).cast("int"), size(area), size(exchange) * 10_000, key, "phone10", inverse)
        pad = lambda c, n: F.lpad(c.cast("string"), n, "0")
        return let(s, lambda y: F.concat(pad(y["a"] + low(area), 3), pad(F.floor(y["b"] / 10_000) + low(exchange), 3), pad(y["b"] % 10_000, 4)))

    def new(x: Column) -> Column:
        return F.when((F.length(x) == 10) & ~code.startswith("+"), national(x)).otherwise(permute_digits(x, key, "phone", inverse))

    return let(digits_of(rest), lambda d: F.concat(code, refill(rest, new(d))))


def email(m: Column, key: str, inverse: bool) -> Column:
    """Letters and digits of the local part move within a-z, A-Z and 0-9; places and all other characters stay."""
    local = F.split_part(m, F.lit("@"), F.lit(1))
    chars = F.regexp_extract_all(local, F.lit("(?s)."), F.lit(0))
    base = lambda c: F.when(c.between(97, 122), 97).when(c.between(65, 90), 65).when(c.between(48, 57), 48)
    size = lambda c: F.when(c.between(48, 57), 10).otherwise(26)
    sign = -1 if inverse else 1

    def moved(x: Column, other: Column, r: Column) -> Column:
        """Each code by its own 16 bits of a hash of the other half; a hash serves 16 places."""
        fields = lambda k: F.concat_ws("\x1f", F.lit(key), F.lit("email"), r.cast("string"), k.cast("string"), F.array_join(other, ","))
        hashes = F.transform(F.sequence(F.lit(0), F.floor(F.size(x) / 16).cast("int")), lambda k: F.sha2(fields(k), 256))
        shift = lambda v, i: F.conv(F.substring(F.get(v, F.floor(i / 16).cast("int")), 4 * (i % 16) + 1, F.lit(4)), 16, 10).cast("int")
        return let(hashes, lambda v: F.transform(x, lambda c, i: F.coalesce(base(c) + F.pmod(c - base(c) + sign * (shift(v, i) % size(c)), size(c)), c)))

    def run(v: Column) -> Column:
        u = F.floor((F.size(v) + 1) / 2).cast("int")
        first = F.struct(F.slice(v, F.lit(1), u).alias("a"), F.slice(v, u + 1, F.size(v)).alias("b"))
        step = lambda s, r: F.when(r % 2 == 0, F.struct(moved(s["a"], s["b"], r).alias("a"), s["b"].alias("b"))).otherwise(F.struct(s["a"].alias("a"), moved(s["b"], s["a"], r).alias("b")))
        return F.aggregate(rounds(inverse), first, step, lambda s: F.concat(s["a"], s["b"]))

    out = let(F.transform(chars, F.ascii), run)
    text = let(chars, lambda own: F.array_join(F.zip_with(own, out, lambda ch, c: F.when(base(c).isNotNull(), F.char(c)).otherwise(ch)), ""))
    return F.concat(text, F.lit("@"), F.split_part(m, F.lit("@"), F.lit(2)))


def pseudonym(m: Column, key: str, inverse: bool) -> Column:
    """struct(kind, text): kind is null for a candidate that fails its validation."""
    is_ = lambda p: m.rlike(f"^(?:{PATTERNS[p]})$")
    kind = F.when(m.contains("@"), "email").when(is_("ipv4"), "ipv4").when(is_("iso_date") | is_("us_date") | is_("dot_date"), "date").when(is_("ssn"), "ssn").when(is_("phone"), "phone").when(is_("card"), "card")

    def of(k: Column) -> Column:
        new = (
            F.when(k == "email", email(m, key, inverse))
            .when(k == "ipv4", ipv4(m, key, inverse))
            .when((k == "date") & m.contains("/"), date(m, "MM/dd/yyyy", key, inverse))
            .when((k == "date") & m.contains("."), date(m, "dd.MM.yyyy", key, inverse))
            .when(k == "date", date(m, "yyyy-MM-dd", key, inverse))
            .when(k == "ssn", ssn(m, key, inverse))
            .when(k == "phone", phone(m, key, inverse))
            .when(k == "card", card(m, key, inverse))
        )
        return let(new, lambda t: F.struct(F.when(t.isNotNull(), k).alias("kind"), F.coalesce(t, m).alias("text")))

    return let(kind, of)


def pseudonymize(docs: DataFrame, key: str = TEST_KEY, inverse: bool = False) -> DataFrame:
    """docs with its text rewritten and `pii` (under another name if docs has one): an array of the kinds replaced, in order of place."""
    pii, old, new = unused(docs, "pii", "old", "new")
    src = docs.withColumnRenamed("text", old)
    found = F.regexp_extract_all(F.col(old), F.lit(ANY), F.lit(0))
    src = src.withColumn(new, F.when(F.col(old).rlike("[0-9@]"), F.transform(found, lambda m: pseudonym(m, key, inverse))))
    some = F.size(F.coalesce(new, F.array())) > 0
    parts = F.split(old, ANY, -1)
    woven = F.array_join(F.zip_with(parts, F.transform(new, lambda x: x["text"]), lambda p, t: F.concat(p, F.coalesce(t, F.lit("")))), "")
    kinds = F.filter(F.transform(new, lambda x: x["kind"]), lambda k: k.isNotNull())
    order = [c if c != "text" else F.when(some, woven).otherwise(F.col(old)).alias("text") for c in docs.columns]
    return src.select(*order, F.when(some, kinds).otherwise(F.array().cast("array<string>")).alias(pii))
