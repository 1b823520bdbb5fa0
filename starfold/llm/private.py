"""PII: format-preserving pseudonyms by a keyed Feistel network, in SQL expressions only.

Found and validated values - card numbers (Luhn), dates, addresses of networks and of mail, telephone and social
numbers, quoted secrets - are permuted within their own format: digits stay digits, letters letters of their
case, a card keeps a right check digit, a date a real date. The same value gives the same pseudonym in every
document, so links survive. Values that fail validation are left as they are.

Defined results: a null text stays null with a count of 0; texts without a digit, an at-sign or the key word of a
secret cannot match and pass unread by the patterns; repeated rows get the same text. A date that is valid with the
day first is read so, else with the month first. The country code of a telephone number stays, so that one number
has one pseudonym in every spelling.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ROUNDS = 8
#: The patterns of the formats.
MAIL = r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]++@[\p{L}\p{N}-]+(?:\.[\p{L}\p{N}-]+)+"
SECRET_KEY = r"(?i:token|secret|api_?key|password)\s{0,3}[=:]"
SECRET = SECRET_KEY + r"\s{0,3}[\"'][0-9A-Za-z_-]{16,128}[\"']"
ADDRESS = r"(?<![0-9.])(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?![0-9]|\.[0-9])"
DATE_YMD = r"(?<![0-9-])[0-9]{4}[-/][0-9]{2}[-/][0-9]{2}(?![0-9-])"
DATE_DMY = r"(?<![0-9./-])[0-9]{2}[./-][0-9]{2}[./-][0-9]{4}(?![0-9])"
SOCIAL = r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"
CARD_FORMS = r"[0-9]{4}(?:[ -][0-9]{4}){3}|[0-9]{4}[ -][0-9]{6}[ -][0-9]{4,5}|[0-9]{13,19}"
CARD = rf"(?<![0-9])(?:{CARD_FORMS})(?![0-9])"
PHONE = r"(?:\+[0-9]{1,3}[ .-]?)?(?:\([0-9]{2,4}\)|(?<![0-9])[0-9]{2,4})[ .-]?[0-9]{3,4}[.-][0-9]{3,4}(?![0-9])"
#: With a country code in any grouping; with the area in brackets; in three groups between blanks.
PHONE_CODE = r"(?<![\p{L}0-9+])\+[1-9][0-9]{0,2}(?:[ .-]?\([0-9]{1,4}\))?(?:[ .-]?[0-9]){6,12}(?![0-9])"
PHONE_AREA = r"\([0-9]{2,4}\)[ .-]?[0-9]{3,4}[ .-]?[0-9]{3,4}(?![0-9])"
PHONE_BLANKS = r"(?<![0-9])(?<![0-9][ .,-])(?:[2-9][0-9]{2} [2-9][0-9]{2} [0-9]{4}|0[0-9]{2,4} [0-9]{3,4} [0-9]{3,4})(?![0-9]|[ .,-][0-9])"
#: Country codes, so that where the code ends does not depend on the spelling.
CODE = r"^(\+(?:1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|[0-9]{1,3})[ .-]?)"
ANY = "|".join((MAIL, SECRET, ADDRESS, DATE_YMD, DATE_DMY, SOCIAL, CARD, PHONE_CODE, PHONE, PHONE_AREA, PHONE_BLANKS))
#: Every text that a pattern matches has one of these.
SOME = f"[0-9@]|{SECRET_KEY}"
DIGITS, LOWER, UPPER = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Days from 1900-01-01 to 2099-12-31, and the two factors of the domain that is walked.
DAYS, FACTOR_A, FACTOR_B = 73049, 271, 270


def mac(key: str, message: Column) -> Column:
    """HMAC with SHA-256 of a text, as hexadecimal digits; the two padded keys are literals."""
    raw = key.encode()
    raw = (hashlib.sha256(raw).digest() if len(raw) > 64 else raw).ljust(64, b"\0")
    inner, outer = bytes(b ^ 0x36 for b in raw), bytes(b ^ 0x5C for b in raw)
    return F.sha2(F.concat(F.lit(outer), F.unhex(F.sha2(F.concat(F.lit(inner), message.cast("binary")), 256))), 256)


def _let(value: Column, use) -> Column:
    """``use`` of a value that is computed once."""
    return F.transform(F.array(value), use)[0]


def _shift(text: Column, stream: Column, alphabets: tuple[str, ...]) -> Column:
    def one(i: Column) -> Column:
        c = F.substring(text, i, F.lit(1))
        step = F.conv(F.substring(stream, F.pmod((i - 1) * 4, F.lit(60)) + 1, F.lit(4)), 16, 10).cast("int")
        out = c
        for alphabet in alphabets:
            at = F.instr(F.lit(alphabet), c)
            out = F.when(at > 0, F.substring(F.lit(alphabet), F.pmod(at - 1 + step, F.lit(len(alphabet))) + 1, F.lit(1))).otherwise(out)
        return out

    return F.when(F.length(text) == 0, text).otherwise(F.array_join(F.transform(F.sequence(F.lit(1), F.length(text)), one), ""))


def permuted(value: Column, key: str, kind: str, alphabets: tuple[str, ...] = (DIGITS, LOWER, UPPER)) -> Column:
    """Feistel permutation of a string among all strings of its format: each round shifts one half, character by character, by a keyed hash of the other."""
    half = F.floor(F.length(value) / 2).cast("int")
    start = F.struct(F.substring(value, F.lit(1), half).alias("l"), F.substring(value, half + 1, F.length(value)).alias("r"))

    def turn(s: Column, k: Column) -> Column:
        left = k % 2 == 0
        target, other = F.when(left, s["l"]).otherwise(s["r"]), F.when(left, s["r"]).otherwise(s["l"])
        stream = mac(key, F.concat(F.lit(f"{kind}|"), k.cast("string"), F.lit("|"), other))
        moved = _let(stream, lambda h: _shift(target, h, alphabets))
        return _let(moved, lambda m: F.struct(F.when(left, m).otherwise(s["l"]).alias("l"), F.when(left, s["r"]).otherwise(m).alias("r")))

    return F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), start, turn, lambda s: F.concat(s["l"], s["r"]))


def _number_turns(left: Column, right: Column, key: str, kind: str, a: int, b: int) -> Column:
    """Feistel permutation of a pair in [0,a) x [0,b)."""
    start = F.struct(left.cast("bigint").alias("l"), right.cast("bigint").alias("r"))

    def turn(s: Column, k: Column) -> Column:
        even = k % 2 == 0
        word = F.concat(F.lit(f"{kind}|"), k.cast("string"), F.lit("|"), F.when(even, s["r"]).otherwise(s["l"]).cast("string"))
        step = F.conv(F.substring(mac(key, word), 1, 12), 16, 10).cast("bigint")
        return _let(step, lambda d: F.struct(F.when(even, F.pmod(s["l"] + d, F.lit(a))).otherwise(s["l"]).alias("l"), F.when(even, s["r"]).otherwise(F.pmod(s["r"] + d, F.lit(b))).alias("r")))

    return F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), start, turn)


def _refill(shape: Column, digits: Column) -> Column:
    """``shape`` with its digits replaced, in order, by those of ``digits``."""
    def one(i: Column) -> Column:
        c = F.substring(shape, i, F.lit(1))
        nth = F.length(F.regexp_replace(F.substring(shape, F.lit(1), i), "[^0-9]", ""))
        return F.when(c.rlike("[0-9]"), F.substring(digits, nth, F.lit(1))).otherwise(c)

    return F.array_join(F.transform(F.sequence(F.lit(1), F.length(shape)), one), "")


def _luhn_sum(digits: Column, double_last: bool) -> Column:
    """Luhn sum; the last digit is doubled where ``double_last``, as for a payload that lacks its check digit."""
    n = F.length(digits)

    def one(i: Column) -> Column:
        d = F.substring(digits, i, F.lit(1)).cast("int")
        twice = (n - i) % 2 == (0 if double_last else 1)
        return F.when(twice, d * 2 - F.when(d > 4, 9).otherwise(0)).otherwise(d)

    return F.aggregate(F.transform(F.sequence(F.lit(1), n), one), F.lit(0), lambda a, x: a + x)


def _new_date(y: Column, m: Column, d: Column, key: str, late: bool = False) -> Column:
    """Another date; where ``late``, a day after the twelfth gives one after the twelfth, so that its month stays told from its day."""
    def inside(x: Column) -> Column:
        fits = x < DAYS
        return fits & (F.dayofmonth(F.date_add(F.lit("1900-01-01").cast("date"), x.cast("int"))) > 12) if late else fits

    day = F.date_diff(F.make_date(y, m, d), F.lit("1900-01-01").cast("date"))

    def walk(v: Column, _k: Column) -> Column:
        moved = _let(_number_turns(F.floor(v["v"] / FACTOR_B), v["v"] % FACTOR_B, key, "date", FACTOR_A, FACTOR_B), lambda s: s["l"] * FACTOR_B + s["r"])
        return F.when(v["done"], v).otherwise(_let(moved, lambda x: F.struct(x.alias("v"), inside(x).alias("done"))))

    start = F.struct(day.cast("bigint").alias("v"), F.lit(False).alias("done"))
    out = F.aggregate(F.sequence(F.lit(1), F.lit(60 if late else 12)), start, walk, lambda v: F.when(v["done"], v["v"]).otherwise(day))
    return F.date_add(F.lit("1900-01-01").cast("date"), out.cast("int"))


def _valid_date(y: Column, m: Column, d: Column) -> Column:
    leap = ((y % 4 == 0) & (y % 100 != 0)) | (y % 400 == 0)
    last = F.when(m.isin(4, 6, 9, 11), 30).when(m == 2, F.when(leap, 29).otherwise(28)).otherwise(31)
    return y.between(1900, 2099) & m.between(1, 12) & (d >= 1) & (d <= last)


def pseudonym(m: Column, key: str) -> Column:
    """The pseudonym of one match; the match itself where it is not valid."""
    whole = lambda p: m.rlike(f"^(?:{p})$")
    part = lambda a, n: F.substring(m, a, n).cast("int")

    local = F.substring_index(m, "@", 1)
    mail = F.concat(permuted(local, key, "mail"), F.substring(m, F.length(local) + 1, F.length(m)))

    quote = F.regexp_extract(m, r"[\"']([0-9A-Za-z_-]+)[\"']$", 1)
    head = F.substring(m, F.lit(1), F.length(m) - F.length(quote) - 1)
    hexes = lambda a: permuted(quote, key, "secret", (a,))
    fresh = F.when(quote.rlike("^[0-9a-f]+$"), hexes("0123456789abcdef")).when(quote.rlike("^[0-9A-F]+$"), hexes("0123456789ABCDEF")).otherwise(permuted(quote, key, "secret"))
    secret = F.concat(head, fresh, F.substring(m, F.length(m), F.lit(1)))

    octet = lambda k: F.element_at(F.split(m, r"\."), k).cast("int")
    good_ip = (octet(1) <= 255) & (octet(2) <= 255) & (octet(3) <= 255) & (octet(4) <= 255)
    ip = _let(_number_turns(octet(1) * 256 + octet(2), octet(3) * 256 + octet(4), key, "ip", 65536, 65536),
              lambda s: F.concat_ws(".", *[F.floor(s[h] / 256).cast("string") if hi else (s[h] % 256).cast("string") for h in ("l", "r") for hi in (True, False)]))

    iso = _valid_date(part(1, 4), part(6, 2), part(9, 2))
    ymd = _let(_new_date(part(1, 4), part(6, 2), part(9, 2), key), lambda d: F.concat(F.date_format(d, "yyyy"), F.substring(m, 5, 1), F.date_format(d, "MM"), F.substring(m, 8, 1), F.date_format(d, "dd")))
    day_first = _valid_date(part(7, 4), part(4, 2), part(1, 2))
    dmy = _let(_new_date(part(7, 4), part(4, 2), part(1, 2), key), lambda d: F.concat(F.date_format(d, "dd"), F.substring(m, 3, 1), F.date_format(d, "MM"), F.substring(m, 6, 1), F.date_format(d, "yyyy")))

    month_first = _valid_date(part(7, 4), part(1, 2), part(4, 2))
    mdy = _let(_new_date(part(7, 4), part(1, 2), part(4, 2), key, late=True), lambda d: F.concat(F.date_format(d, "MM"), F.substring(m, 3, 1), F.date_format(d, "dd"), F.substring(m, 6, 1), F.date_format(d, "yyyy")))

    digits = F.regexp_replace(m, "[^0-9]", "")
    payload = lambda x: F.substring(x, F.lit(1), F.length(x) - 1)
    card = _let(_let(permuted(payload(digits), key, "card", (DIGITS,)), lambda p: F.concat(p, F.pmod(10 - F.pmod(_luhn_sum(p, True), F.lit(10)), F.lit(10)).cast("string"))), lambda x: _refill(m, x))
    good_card = _luhn_sum(digits, False) % 10 == 0

    prefix = F.regexp_extract(m, CODE, 1)
    rest = F.substring(m, F.length(prefix) + 1, F.length(m))
    phone = F.concat(prefix, _let(permuted(F.regexp_replace(rest, "[^0-9]", ""), key, "phone", (DIGITS,)), lambda x: _refill(rest, x)))
    social = _let(permuted(digits, key, "social", (DIGITS,)), lambda x: _refill(m, x))

    return (
        F.when(F.instr(m, "@") > 0, mail)
        .when(m.rlike("[\"']$"), secret)
        .when(whole(r"(?:[0-9]{1,3}\.){3}[0-9]{1,3}"), F.when(good_ip, ip).otherwise(m))
        .when(whole("[0-9]{4}[-/][0-9]{2}[-/][0-9]{2}"), F.when(iso, ymd).otherwise(m))
        .when(whole("[0-9]{2}[./-][0-9]{2}[./-][0-9]{4}"), F.when(day_first, dmy).when(month_first, mdy).otherwise(m))
        .when(whole("[0-9]{3}-[0-9]{2}-[0-9]{4}"), social)
        .when(whole(CARD_FORMS), F.when(good_card, card).otherwise(m))
        .otherwise(phone)
    )


def pseudonymize(docs: DataFrame, *, key: str, text: str = "text", count: str | None = "n_private") -> DataFrame:
    """``docs`` with private values of ``text`` replaced, and their number in ``count``."""
    names = [c for c in docs.columns if c != count]
    rows = docs.select(F.struct("*").alias("row"), F.col(text).alias("t"))
    t = F.col("t")
    found = rows.select("row", "t", F.when(t.rlike(SOME), F.regexp_extract_all(t, F.lit(ANY), F.lit(0))).alias("m"))
    fresh = found.withColumn("f", F.when(F.size("m") > 0, F.transform("m", lambda m: pseudonym(m, key))))
    pieces = F.split(t, ANY, -1)
    joined = F.array_join(F.flatten(F.zip_with(pieces, F.concat("f", F.array(F.lit(""))), lambda a, b: F.array(F.coalesce(a, F.lit("")), F.coalesce(b, F.lit(""))))), "")
    changed = F.aggregate(F.zip_with("m", "f", lambda a, b: F.when(a != b, 1).otherwise(0)), F.lit(0), lambda a, x: a + x)
    some = F.size("f") > 0
    out = [F.when(some, joined).otherwise(t).alias(text) if c == text else F.col(f"row.`{c}`") for c in names]
    if count:
        out.append(F.when(some, changed).otherwise(0).cast("long").alias(count))
    return fresh.select(*out)
