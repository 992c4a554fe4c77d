"""Format-preserving pseudonyms for personal data, by Feistel permutations (DataFrame functions only).

Numbers and dates are found by pattern and validated (checksums, ranges,
calendar). Each is then moved within its own format by a keyed permutation, so
that a card number becomes another card number with a right check digit, a date
another date. Equal values get equal pseudonyms in every document, and with the
key :func:`pseudonymize` with ``inverse`` gives the originals back. Mail
addresses, which are neither, get a keyed token.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty

ROUNDS = 10
#: Countries by the length of their IBANs: a grouped one ends where its length says, whatever follows.
IBAN_LENGTHS = {
    15: "NO", 16: "BE", 18: "DK|FI|FK|FO|GL|NL|SD", 19: "MK|SI", 20: "AT|BA|EE|KZ|LT|LU|MN|XK", 21: "CH|HR|LI|LV", 22: "BG|BH|CR|DE|GB|GE|IE|ME|RS|VA",
    23: "AE|GI|IL|IQ|OM|SO|TL", 24: "AD|CZ|ES|MD|PK|RO|SA|SE|SK|TN|VG", 25: "LY|PT|ST", 26: "IS|TR", 27: "BI|DJ|FR|GR|IT|MC|MR|SM",
    28: "AL|AZ|BY|CY|DO|GT|HN|HU|LB|NI|PL|SV", 29: "BR|EG|PS|QA|UA", 30: "JO|KW|MU|YE", 31: "MT|SC", 32: "LC", 33: "RU",
}
GROUPED = "|".join(f"(?:{c})[0-9]{{2}}(?:[ -][A-Z0-9]{{4}}){{{n // 4 - 1}}}" + f"[ -][A-Z0-9]{{{n % 4}}}" * (n % 4 > 0) for n, c in IBAN_LENGTHS.items())
MONTH, DAY = "(?:January|February|March|April|May|June|July|August|September|October|November|December)", "(?:[12][0-9]|3[01]|[1-9])"
#: The forms that are looked for, in this order at one place.
FORMS = {
    "email": r"[A-Za-z0-9][A-Za-z0-9._%+-]*@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}",
    "ip": r"(?<![0-9A-Za-z.])(?:(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])\.){3}(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(?![0-9A-Za-z]|\.[0-9])",
    "iban": r"(?<![0-9A-Za-z])[A-Z]{2}[0-9]{2}[A-Z0-9]{11,30}(?![0-9A-Za-z])",
    "iban_grouped": rf"(?<![0-9A-Za-z])(?:{GROUPED})(?![0-9A-Za-z])",
    "phone_plan": r"(?<![0-9A-Za-z+])\+1[ .-]?\(?[0-9]{3}\)?[ .-]?[0-9]{3}[ .-]?[0-9]{4}(?![0-9A-Za-z])",
    "phone": r"(?<![0-9A-Za-z+])\+(?!1[ .(-])[0-9]{1,3}[ .-]?(?:\([0-9]{2,4}\)[ .-]?)?[0-9]{2,4}(?:[ .-]?[0-9]{2,4}){1,3}(?![0-9A-Za-z]|\.[0-9])",
    "phone_local": r"(?<![0-9A-Za-z+])\([0-9]{3}\) ?[0-9]{3}-[0-9]{4}(?![0-9A-Za-z])",
    "phone_bare": r"(?<![0-9A-Za-z+])(?<![0-9][.-])(?:(?:1-)?[0-9]{3}-[0-9]{3}-[0-9]{4}|(?:1\.)?[0-9]{3}\.[0-9]{3}\.[0-9]{4})(?![0-9A-Za-z]|[.-][0-9])",
    "ssn": r"(?<![0-9A-Za-z-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9A-Za-z-])",
    "date": r"(?<![0-9A-Za-z-])[0-9]{4}-[0-9]{2}-[0-9]{2}(?![0-9A-Za-z-])",
    "date_dots": r"(?<![0-9A-Za-z])(?<![0-9]\.)[0-3][0-9]\.[01][0-9]\.[0-9]{4}(?![0-9A-Za-z]|\.[0-9])",
    "date_slashes": r"(?<![0-9A-Za-z])(?<![0-9]/)[0-3][0-9]/[0-3][0-9]/[0-9]{4}(?![0-9A-Za-z]|/[0-9])",
    "date_month": rf"(?<![0-9A-Za-z]){MONTH} {DAY}, [0-9]{{4}}(?![0-9A-Za-z])",
    "date_day": rf"(?<![0-9A-Za-z]){DAY} {MONTH} [0-9]{{4}}(?![0-9A-Za-z])",
    "card_uneven": r"(?<![0-9A-Za-z])[0-9]{4}(?: [0-9]{6} |-[0-9]{6}-)[0-9]{4,5}(?![0-9A-Za-z])",
    "card": r"(?<![0-9A-Za-z])[0-9]{4}(?:[ -]?[0-9]{4}){2}[ -]?[0-9]{1,7}(?![0-9A-Za-z])",
}
#: Dates: 270 x 272 days from this one on.
EPOCH, SPAN_A, SPAN_B = "1900-01-01", 270, 272
#: How the forms of dates are written. Slashes mean the month first where that is a date.
WRITTEN = {"date": "yyyy-MM-dd", "date_dots": "dd.MM.yyyy", "date_slashes": "MM/dd/yyyy", "date_month": "MMMM d, yyyy", "date_day": "d MMMM yyyy"}
#: Days after the 12th in the months from EPOCH to the end of 2100: 10 x 4447, in 2412 months.
LATE_A, LATE_B, LATE_MONTHS = 10, 4447, 2412


def feistel(a: Column, b: Column, mod_a: Column, mod_b: Column, key: Column, tweak: Column, inverse: bool) -> Column:
    """Struct (a, b), each half moved in turn by a keyed hash of the other, modulo its own range."""

    def step(acc: Column, i: Column) -> Column:
        def shift(other: Column) -> Column:
            return F.conv(F.substring(F.sha2(F.concat_ws("|", key, tweak, i.cast("string"), other.cast("string")), 256), 1, 15), 16, 10).cast("long")

        sign = -1 if inverse else 1
        left = F.struct(F.pmod(acc["a"] + sign * (shift(acc["b"]) % mod_a), mod_a).alias("a"), acc["b"].alias("b"))
        right = F.struct(acc["a"].alias("a"), F.pmod(acc["b"] + sign * (shift(acc["a"]) % mod_b), mod_b).alias("b"))
        return F.when(i % 2 == 0, left).otherwise(right)

    order = F.sequence(F.lit(ROUNDS - 1), F.lit(0), F.lit(-1)) if inverse else F.sequence(F.lit(0), F.lit(ROUNDS - 1))
    return F.aggregate(order, F.struct(a.cast("long").alias("a"), b.cast("long").alias("b")), step)


def with_struct(value: Column, body) -> Column:
    """``body`` of ``value``, evaluated once."""
    return F.transform(F.array(value), body)[0]


def permuted_digits(digits: Column, key: Column, kind: str, inverse: bool) -> Column:
    n = F.length(digits)
    half = F.floor(n / 2).cast("int")
    rest = n - half
    power = lambda x: F.pow(F.lit(10.0), x).cast("long")
    moved = feistel(F.substr(digits, F.lit(1), half), F.substr(digits, half + 1, rest), power(half), power(rest), key, F.concat(F.lit(f"{kind}|"), n.cast("string")), inverse)
    return with_struct(moved, lambda m: F.concat(F.lpad(m["a"].cast("string"), half, F.lit("0")), F.lpad(m["b"].cast("string"), rest, F.lit("0"))))


def only_digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def refilled(mask: Column, digits: Column, skip: Column) -> Column:
    """``mask`` with its digits after the first ``skip`` replaced by ``digits`` in order."""

    def step(acc: Column, c: Column) -> Column:
        digit = c.rlike("^[0-9]$")
        new = F.when(digit & (acc["k"] >= 0), F.substr(digits, acc["k"] + 1, F.lit(1))).otherwise(c)
        return F.struct(F.concat(acc["out"], new).alias("out"), F.when(digit, acc["k"] + 1).otherwise(acc["k"]).alias("k"))

    start = F.struct(F.lit("").alias("out"), (-skip).cast("int").alias("k"))
    return F.aggregate(F.split(mask, ""), start, step, lambda acc: acc["out"])


def luhn_sum(digits: Column, doubled: int) -> Column:
    """Weighted digit sum from the right; places that leave ``doubled`` modulo 2 count double."""
    n = F.length(digits)

    def step(acc: Column, i: Column) -> Column:
        d = F.substr(digits, n - i, F.lit(1)).cast("int")
        twice = F.when(d > 4, 2 * d - 9).otherwise(2 * d)
        return acc + F.when(i % 2 == doubled, twice).otherwise(d)

    return F.aggregate(F.sequence(F.lit(0), n - 1), F.lit(0), step)


def mod97(text: Column) -> Column:
    """Remainder by 97 of a text in which A-Z stand for 10-35."""

    def step(acc: Column, c: Column) -> Column:
        letter = c.rlike("^[A-Z]$")
        return F.when(letter, (acc * 100 + F.ascii(c) - 55) % 97).otherwise((acc * 10 + c.cast("int")) % 97)

    return F.aggregate(F.split(text, ""), F.lit(0), step)


def moved_late(value: Column, key: Column, inverse: bool) -> tuple[Column, Column]:
    """dd/MM/yyyy with a day after the 12th, which stays so: else the pseudonym could be read with the month first."""
    start = F.lit(EPOCH).cast("date")
    before = lambda m: F.datediff(F.add_months(start, m), start).cast("long") - 12 * m
    date = F.try_to_timestamp(value, F.lit("dd/MM/yyyy")).cast("date")
    month = (F.year(date) - 1900) * 12 + F.month(date) - 1
    at = before(month) + F.dayofmonth(date) - 13

    def day(i: Column) -> Column:
        near = F.floor(i / (LATE_A * LATE_B / LATE_MONTHS)).cast("int")
        found = F.array_max(F.filter(F.sequence(F.greatest(near - 2, F.lit(0)), near + 2), lambda m: before(m) <= i))
        return with_struct(found, lambda m: F.date_format(F.date_add(F.add_months(start, m), (i - before(m) + 12).cast("int")), "dd/MM/yyyy"))

    out = with_struct(feistel(F.floor(at / LATE_B), at % LATE_B, F.lit(LATE_A), F.lit(LATE_B), key, F.lit("date|late"), inverse), lambda m: day(m["a"] * LATE_B + m["b"]))
    return date.isNotNull() & (F.dayofmonth(date) > 12) & (month >= 0) & (month < LATE_MONTHS), out


def moved(kind: str, value: Column, key: Column, inverse: bool) -> tuple[Column, Column]:
    """(is it valid, its pseudonym)."""
    if kind == "email":
        token = F.concat(F.substring(F.sha2(F.concat_ws("|", key, F.lit("email"), F.lower(value)), 256), 1, 12), F.lit("@mail.invalid"))
        return F.lit(not inverse), token
    if kind == "ip":
        part = F.split(value, r"\.")
        a, b = (part[0].cast("long") * 256 + part[1].cast("long"), part[2].cast("long") * 256 + part[3].cast("long"))
        out = with_struct(feistel(a, b, F.lit(65536), F.lit(65536), key, F.lit("ip"), inverse), lambda m: F.concat_ws(".", *[x.cast("int").cast("string") for x in (F.floor(m["a"] / 256), m["a"] % 256, F.floor(m["b"] / 256), m["b"] % 256)]))
        return F.lit(True), out
    if kind == "iban":
        valid = mod97(F.concat(F.substr(value, F.lit(5), F.length(value)), F.substring(value, 1, 4))) == 1
        body = F.substr(value, F.lit(5), F.length(value))
        digits = only_digits(body)
        new = F.when(F.length(digits) >= 2, refilled(body, permuted_digits(digits, key, "iban", inverse), F.lit(0))).otherwise(body)
        check = lambda b: F.lpad((98 - mod97(F.concat(b, F.substring(value, 1, 2), F.lit("00")))).cast("string"), 2, "0")
        return valid, with_struct(new, lambda b: F.concat(F.substring(value, 1, 2), check(b), b))
    if kind == "iban_grouped":
        valid, new = moved("iban", F.regexp_replace(value, "[ -]", ""), key, inverse)
        return valid, refilled(value, only_digits(new), F.lit(0))
    if kind.startswith("phone"):
        digits = only_digits(value)
        # The country code stays: what stands before the first blank, bracket or mark (one digit if there is none).
        code = F.when(value.startswith("+"), F.when(value.rlike(r"^\+[0-9]{1,3}[ .(-]"), F.length(F.regexp_extract(value, r"^\+([0-9]+)", 1))).otherwise(1)).when(value.rlike(r"^1[.-]"), 1).otherwise(0)
        own = F.substr(digits, code + 1, F.length(digits))
        return (F.length(digits) >= 8) & (F.length(digits) <= 15), refilled(value, permuted_digits(own, key, "phone", inverse), code)
    if kind == "ssn":
        area, group, serial = (F.substring(value, i, n).cast("int") for i, n in ((1, 3), (5, 2), (8, 4)))
        valid = (area > 0) & (area != 666) & (area < 900) & (group > 0) & (serial > 0)
        a = F.when(area > 666, area - 2).otherwise(area - 1)
        out = with_struct(feistel(a, (group - 1) * 9999 + serial - 1, F.lit(898), F.lit(99 * 9999), key, F.lit("ssn"), inverse), lambda m: F.concat_ws("-", F.lpad(F.when(m["a"] >= 665, m["a"] + 2).otherwise(m["a"] + 1).cast("string"), 3, "0"), F.lpad((F.floor(m["b"] / 9999) + 1).cast("string"), 2, "0"), F.lpad((m["b"] % 9999 + 1).cast("string"), 4, "0")))
        return valid, out
    if kind in WRITTEN:
        day = F.datediff(F.try_to_timestamp(value, F.lit(WRITTEN[kind])).cast("date"), F.lit(EPOCH).cast("date")).cast("long")
        valid = day.isNotNull() & (day >= 0) & (day < SPAN_A * SPAN_B)
        out = with_struct(feistel(F.floor(day / SPAN_B), day % SPAN_B, F.lit(SPAN_A), F.lit(SPAN_B), key, F.lit("date"), inverse), lambda m: F.date_format(F.date_add(F.lit(EPOCH).cast("date"), (m["a"] * SPAN_B + m["b"]).cast("int")), WRITTEN[kind]))
        if kind == "date_slashes":
            late, new = moved_late(value, key, inverse)
            return valid | late, F.when(valid, out).otherwise(new)
        return valid, out
    digits = only_digits(value)
    n = F.length(digits)
    valid = (n >= 13) & (n <= 19) & (luhn_sum(digits, 1) % 10 == 0)
    body = permuted_digits(F.substr(digits, F.lit(1), n - 1), key, "card", inverse)
    full = with_struct(body, lambda b: F.concat(b, ((10 - luhn_sum(b, 0) % 10) % 10).cast("string")))
    return valid, refilled(value, full, F.lit(0))


def pseudonymize(docs: DataFrame, key: str, text: str = "text", doc_id: str = "doc_id", inverse: bool = False) -> DataFrame:
    """One row per row of ``docs``: doc_id, text with pseudonyms, and n_<form> for what was replaced.

    A null text stays null with counts of 0. Values that fail their validation
    stay as they are. ``inverse`` restores numbers and dates (mail addresses
    have no way back). Repeated rows give repeated results.
    """
    pattern = "|".join(FORMS.values())
    body = text_or_empty(text)
    secret = F.lit(key)
    hits = F.regexp_extract_all(body, F.lit(pattern), F.lit(0))
    gaps = F.split(body, pattern, -1)
    whole = lambda form, x: x.rlike(f"^(?:{FORMS[form]})$")

    def change(x: Column) -> Column:
        chain = None
        for form in FORMS:
            valid, new = moved(form, x, secret, inverse)
            kind = form.split("_")[0]
            out = F.when(valid, F.struct(F.lit(kind).alias("kind"), new.alias("new"))).otherwise(F.struct(F.lit("").alias("kind"), x.alias("new")))
            chain = F.when(whole(form, x), out) if chain is None else chain.when(whole(form, x), out)
        return chain.otherwise(F.struct(F.lit("").alias("kind"), x.alias("new")))

    none = F.array().cast("array<struct<kind:string,new:string>>")
    found = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"), F.when(body.rlike(pattern), F.transform(hits, change)).otherwise(none).alias("__hits"))
    # The array is used several times: a generator of one row keeps it from being computed for each use.
    found = found.select("doc_id", "text", F.explode(F.array("__hits")).alias("hits"))
    gaps = F.split(F.col("text"), pattern, -1)
    joined = F.concat_ws("", F.zip_with(gaps, "hits", lambda gap, hit: F.concat(gap, F.coalesce(hit["new"], F.lit("")))))

    def number(kind: str) -> Column:
        return F.size(F.filter("hits", lambda h: h["kind"] == kind)).cast("long").alias(f"n_{kind}")

    kinds = dict.fromkeys(f.split("_")[0] for f in FORMS)
    return found.select("doc_id", F.when(F.size("hits") > 0, joined).otherwise(F.col("text")).alias("text"), *map(number, kinds))
