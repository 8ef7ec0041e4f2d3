"""Format-preserving Feistel pseudonyms for personal data, on DataFrame functions alone.

Bank accounts, cards, telephone numbers, IPv4 addresses, e-mail names and dates
are found by one expression, validated, and permuted within their format by an
alternating Feistel network keyed through SHA-256. Signs and spacing stay where
they stand and do not enter the permutation, check digits are made anew, an
address keeps valid octets and a date a valid day, so equal values stay equal
(and distinct ones distinct) over all documents, however they are punctuated.

* account: two capitals, two check digits and 11 to 30 capitals or digits, whole
  or in groups of four, with remainder 1 by 97. The digits after the check digits
  are permuted; country and letters stay.
* number: 12 to 19 digits, alone or in groups of four, with a valid Luhn digit.
  All but the last digit are permuted.
* phone: "+", a country code and digits, or ten digits as 3-3-4. The country code,
  told by the published list whatever signs follow it, stays; a number of ten
  digits is the same with and without its code.
* ip: four octets up to 255, permuted as 32 bits.
* email: the letters and digits before "@", permuted over base 36; the rest stays.
* date: yyyy-mm-dd, dd.mm.yyyy or mm/dd/yyyy that exists, from 1800 to 2199,
  permuted over the 146,097 days of those four centuries.

A match that fails its test stays as it is. Of matches that might begin at one
place, the first of SHAPES is taken. Null texts stay null; empty texts have no
matches. Rows are independent of each other, so repeated rows get equal results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

ROUNDS = 8
#: Key of the registered query; a user passes one of their own.
EXAMPLE_KEY = "example key, to be replaced"
# What each kind looks like, in the order in which alternatives are tried.
SHAPES = {
    "account": r"(?<![0-9A-Za-z])[A-Z]{2}[0-9]{2}(?:[A-Z0-9]{11,30}|(?: [A-Z0-9]{4}){2,7}(?: [A-Z0-9]{1,3})?)(?![0-9A-Za-z])",
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9][A-Za-z0-9._%+-]{0,63}@[A-Za-z0-9-]{1,63}(?:\.[A-Za-z0-9-]{1,63}){1,8}",
    "date": r"(?<![0-9.])(?:[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{2}\.[0-9]{2}\.[0-9]{4}|[0-9]{2}/[0-9]{2}/[0-9]{4})(?![0-9]|\.[0-9])",
    "phone": r"\+[0-9]{1,3}(?:[ .-]?\(?[0-9]{2,4}\)?){2,4}(?![0-9])|(?<![0-9A-Za-z])(?:\([0-9]{3}\) ?|[0-9]{3}[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9A-Za-z])",
    "ip": r"(?<![0-9A-Za-z.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?![0-9A-Za-z]|\.[0-9])",
    "number": r"(?<![0-9A-Za-z])(?:[0-9]{12,19}|[0-9]{4}(?:[ -][0-9]{4}){3})(?![0-9A-Za-z])",
}
KINDS = [*SHAPES]
ANY = "|".join(SHAPES.values())
# Fixed value: telephone country codes of one and two digits, and three for all others.
COUNTRY = r"^\+(1|7|20|27|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|[0-9]{3})"
DAYS, DAY_PARTS, FIRST_DAY = 146_097, (189, 773), "1800-01-01"
CHARS = "0123456789abcdefghijklmnopqrstuvwxyz"


def feistel_string(digits: Column, radix: int, key: str, tag: Column, most: int) -> Column:
    """Permute a string over the first ``radix`` characters, among strings of its length (up to ``most``)."""
    size = F.char_length(digits)
    alphabet = F.lit(CHARS[:radix])

    cut = F.floor(size / 2).cast("int")
    state = F.struct(F.substring(digits, 1, cut).alias("l"), F.substring(digits, cut + 1, size).alias("r"))
    steps = F.array(*[F.lit(i) for i in range(ROUNDS)])

    def step(s, i):
        return F.when(i % 2 == 0, F.struct(_keyed_add(s["l"], s["r"], i).alias("l"), s["r"].alias("r"))).otherwise(F.struct(s["l"].alias("l"), _keyed_add(s["r"], s["l"], i).alias("r")))

    def _keyed_add(half: Column, other: Column, i: Column) -> Column:
        seeds = [F.sha2(F.concat_ws("\x1f", F.lit(key), tag, size, i, F.lit(k), other), 256) for k in range(-(-most // 32))]
        # one-element transform: the stream is computed once a round and named, not once a character
        made = F.transform(
            F.array(F.concat(*seeds)),
            lambda stream: F.array_join(
                F.transform(
                    F.filter(F.split(half, ""), lambda c: c != ""),
                    lambda c, at: F.substring(alphabet, F.pmod(F.instr(alphabet, c) - 1 + F.conv(F.substring(stream, 2 * at + 1, 2), 16, 10).cast("int"), F.lit(radix)) + 1, 1),
                ),
                "",
            ),
        )
        return F.element_at(made, 1)

    return F.aggregate(steps, state, step, lambda s: F.concat(s["l"], s["r"]))


def feistel_number(value: Column, parts: tuple[int, int], key: str, tag: str) -> Column:
    """Permute 0 .. a*b - 1, as a pair of residues of a and b."""
    a, b = parts
    state = F.struct(F.floor(value / b).cast("bigint").alias("l"), F.pmod(value, F.lit(b)).cast("bigint").alias("r"))

    def mixed(i: Column, other: Column) -> Column:
        return F.conv(F.substring(F.sha2(F.concat_ws("\x1f", F.lit(key), F.lit(tag), i, other), 256), 1, 15), 16, 10).cast("bigint")

    def step(s, i):
        left = F.pmod(s["l"] + mixed(i, s["r"]), F.lit(a).cast("bigint"))
        right = F.pmod(s["r"] + mixed(i, s["l"]), F.lit(b).cast("bigint"))
        return F.when(i % 2 == 0, F.struct(left.alias("l"), s["r"].alias("r"))).otherwise(F.struct(s["l"].alias("l"), right.alias("r")))

    return F.aggregate(F.array(*[F.lit(i) for i in range(ROUNDS)]), state, step, lambda s: s["l"] * b + s["r"])


def luhn_sum(digits: Column) -> Column:
    """Luhn sum of a digit string, its last digit counted singly."""
    places = F.filter(F.split(F.reverse(digits), ""), lambda c: c != "")

    def add(total, c):
        d = c["d"].cast("int")
        twice = F.when(d > 4, 2 * d - 9).otherwise(2 * d)
        return total + F.when(c["i"] % 2 == 1, twice).otherwise(d)

    return F.aggregate(F.transform(places, lambda d, i: F.struct(d.alias("d"), i.alias("i"))), F.lit(0), add)


def refill(shape: Column, digits: Column, pattern: str) -> Column:
    """``shape`` with its characters of ``pattern`` replaced, in order, by those of ``digits``."""
    chars = F.filter(F.split(shape, ""), lambda c: c != "")

    def put(s, c):
        hit = c.rlike(pattern)
        return F.struct((s["i"] + F.when(hit, 1).otherwise(0)).alias("i"), F.concat(s["out"], F.when(hit, F.substring(digits, s["i"] + 1, 1)).otherwise(c)).alias("out"))

    return F.aggregate(chars, F.struct(F.lit(0).alias("i"), F.lit("").alias("out")), put, lambda s: s["out"])


def _named(value: Column, use) -> Column:
    """``use`` of a value that is computed once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _number(hit: Column, key: str) -> Column:
    def of(digits: Column) -> Column:
        size = F.char_length(digits)

        def ended(body: Column) -> Column:
            return F.concat(body, F.pmod(10 - luhn_sum(F.concat(body, F.lit("0"))) % 10, F.lit(10)).cast("string"))

        moved = refill(hit, _named(feistel_string(F.substring(digits, F.lit(1), size - 1), 10, key, F.lit("number"), 32), ended), "[0-9]")
        return F.when(luhn_sum(digits) % 10 == 0, moved).otherwise(hit)

    return _named(F.regexp_replace(hit, "[^0-9]", ""), of)


def remainder_97(signs: Column) -> Column:
    """Digits and capitals (A is 10) read as one decimal number, modulo 97."""

    def add(n, c):
        letter = c.rlike("[A-Z]")
        return F.pmod(n * F.when(letter, 100).otherwise(10) + F.when(letter, F.ascii(c) - 55).otherwise(F.ascii(c) - 48), F.lit(97))

    return F.aggregate(F.filter(F.split(signs, ""), lambda c: c != ""), F.lit(0), add)


def _account(hit: Column, key: str) -> Column:
    def of(plain: Column) -> Column:
        country, body = F.substring(plain, 1, 2), F.substring(plain, F.lit(5), F.char_length(plain))
        moved = refill(body, feistel_string(F.regexp_replace(body, "[^0-9]", ""), 10, key, country, 32), "[0-9]")

        def ended(new: Column) -> Column:
            return F.concat(country, F.lpad((98 - remainder_97(F.concat(new, country, F.lit("00")))).cast("string"), 2, "0"), new)

        valid = remainder_97(F.concat(body, F.substring(plain, 1, 4))) == 1
        return F.when(valid & (F.char_length(plain) <= 34), refill(hit, _named(moved, ended), "[0-9A-Z]")).otherwise(hit)

    return _named(F.replace(hit, F.lit(" "), F.lit("")), of)


def _phone(hit: Column, key: str) -> Column:
    def of(digits: Column) -> Column:
        code = F.when(F.substring(hit, 1, 1) == "+", F.regexp_extract(F.concat(F.lit("+"), digits), COUNTRY, 1)).otherwise("")
        rest = F.substring(digits, F.char_length(code) + 1, F.char_length(digits))
        return refill(hit, F.concat(code, feistel_string(rest, 10, key, F.lit("phone"), 32)), "[0-9]")

    return _named(F.regexp_replace(hit, "[^0-9]", ""), of)


def _ip(hit: Column, key: str) -> Column:
    value = F.aggregate(F.split(hit, "\\."), F.lit(0).cast("bigint"), lambda n, o: n * 256 + o.cast("bigint"))
    out = feistel_number(value, (65536, 65536), key, "ip")
    dotted = _named(out, lambda v: F.concat_ws(".", *[F.pmod(F.floor(v / 256**i), F.lit(256)).cast("string") for i in (3, 2, 1, 0)]))
    valid = F.forall(F.split(hit, "\\."), lambda o: o.cast("int") <= 255)
    return F.when(valid, dotted).otherwise(hit)


def _email(hit: Column, key: str) -> Column:
    name = F.substring_index(hit, "@", 1)
    plain = F.lower(F.regexp_replace(name, "[^A-Za-z0-9]", ""))
    return F.concat(refill(name, feistel_string(plain, 36, key, F.lit("email"), 64), "[A-Za-z0-9]"), F.lit("@"), F.substring_index(hit, "@", -1))


def _date(hit: Column, key: str) -> Column:
    out = hit
    for form, shape in (("yyyy-MM-dd", r"^[0-9]{4}-"), ("dd.MM.yyyy", r"^[0-9]{2}\."), ("MM/dd/yyyy", r"^[0-9]{2}/")):
        day = F.datediff(F.try_to_timestamp(hit, F.lit(form)).cast("date"), F.lit(FIRST_DAY).cast("date"))
        moved = _named(day, lambda d: F.date_add(F.lit(FIRST_DAY).cast("date"), feistel_number(d.cast("bigint"), DAY_PARTS, key, "date").cast("int")))
        out = F.when(hit.rlike(shape), F.when((day >= 0) & (day < DAYS), F.date_format(moved, form)).otherwise(hit)).otherwise(out)
    return out


PSEUDONYMS = {"account": _account, "email": _email, "date": _date, "phone": _phone, "ip": _ip, "number": _number}


def kind_of(hit: Column) -> Column:
    """Which alternative a match belongs to, in the order in which they are tried."""
    out = F.lit("number")
    for kind, shape in (("account", r"^[A-Z]{2}[0-9]{2}"), ("ip", r"^[0-9]{1,3}(\.[0-9]{1,3}){3}$"), ("date", r"^([0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{2}[./][0-9]{2}[./][0-9]{4})$"), ("email", "@")):
        out = F.when(hit.rlike(shape), F.lit(kind)).otherwise(out)
        if kind == "ip":
            out = F.when(hit.rlike(r"^\+|^\(|^[0-9]{3}[ .-][0-9]{3}[ .-][0-9]{4}$"), F.lit("phone")).otherwise(out)
    return out


def pseudonymize(docs: DataFrame, key: str) -> DataFrame:
    """``docs`` with ``text`` pseudonymised and one count for each kind: n_account, n_email, n_date, n_phone, n_ip, n_number.

    The counts are of values that changed their form's digits; matches that fail their test are not among them.
    """
    text = F.col("text")
    found = docs.drop(*(f"n_{k}" for k in KINDS)).withColumn("_hits", F.regexp_extract_all(common.text_of(), F.lit(f"({ANY})"), F.lit(1)))

    def judged(hit: Column) -> Column:
        out = F.lit(None).cast("string")
        kind = kind_of(hit)
        for k, f in PSEUDONYMS.items():
            out = F.when(kind == k, f(hit, key)).otherwise(out)
        return F.struct(kind.alias("kind"), hit.alias("was"), out.alias("now"))

    read = found.withColumn("_read", F.when(F.size("_hits") > 0, F.transform("_hits", judged)))
    woven = F.zip_with(F.split(text, ANY, -1), F.col("_read"), lambda piece, r: F.concat(piece, F.coalesce(r["now"], F.lit(""))))
    done = read.withColumn("text", F.when(F.size("_hits") > 0, F.array_join(woven, "")).otherwise(text))

    def of(kind: str):
        return lambda r: (r["kind"] == kind) & (r["was"] != r["now"])

    counts = {f"n_{k}": F.coalesce(F.size(F.filter("_read", of(k))), F.lit(0)).cast("long") for k in KINDS}
    return done.withColumns(counts).withColumns({c: F.greatest(F.col(c), F.lit(0).cast("long")) for c in counts}).drop("_hits", "_read")


def query(spark, sf_dir: str) -> DataFrame:
    return pseudonymize(common.load(spark, sf_dir, "documents").select("doc_id", "text"), EXAMPLE_KEY)


ORACLE = None
"""The keyed network is tested against a direct Python version of it, and for validity, bijection and linkage."""
