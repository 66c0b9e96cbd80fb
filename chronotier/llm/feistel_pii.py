"""Pseudonyms for personal data by format-preserving Feistel permutations, with
DataFrame functions only.

Candidates are found by one pattern, validated by kind (check digits, ranges, the
calendar) and replaced in place. A validated value is permuted under the key within
its own format: a card stays a card with a right check digit, an account number one with
right check digits and its country, blanks where they were, a date a date, an address
an address under the same top domain, a phone number one of the same country. Equal values get equal pseudonyms in every document, different
values different ones, and whoever holds the key can invert the permutation.

A round adds a keyed hash of one half to the other half, modulo its size, halves in
turn. Numbers with ranges use two counters; strings of letters and digits are
shifted character by character within their class. The work is one narrow pass.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ROUNDS = 8
#: The kinds and their patterns (Java).
EMAIL = r"[A-Za-z0-9][A-Za-z0-9._%+-]*@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}"
PHONE = r"(\+1[ .-]?)?(\(?)([2-9]\d{2})(\)?[ .-])([2-9]\d{2})([ .-])(\d{4})"
IPV4 = r"\d{1,3}\.\d{1,3}\.\d{1,3}\.\d{1,3}"
#: Lengths of account numbers by country; other countries are taken without blanks.
IBAN_LENGTHS = {15: "NO", 16: "BE", 18: "DK FI NL", 19: "MK SI", 20: "AT BA EE KZ LT LU XK", 21: "CH HR LI LV", 22: "BG DE GB GE IE ME RS", 23: "AE GI IL", 24: "AD CZ ES MD PK RO SA SE SK TN", 25: "PT", 26: "IS TR", 27: "FR GR IT MC SM", 28: "AL AZ CY DO GT HU LB PL", 29: "BR PS QA UA", 30: "JO KW MU", 31: "MT SC"}
#: Country calling codes of one and of two digits; all others have three.
CODES_1, CODES_2 = "1 7".split(), "20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split()
INTL = r"\+[1-9]\d{0,3}(?:[ .-]?\(?\d{1,4}\)?){1,6}"
DATE = r"(?:\d{4}-\d{2}-\d{2}|\d{2}[./]\d{2}[./]\d{4})"
SSN = r"\d{3}-\d{2}-\d{4}"
CARD = r"(?:\d{4}([ -])\d{4}\1\d{4}\1\d{4}|\d{13,19})"


def _iban_pattern() -> str:
    """Account numbers in one run, or in groups of four."""
    parts = []
    for n, names in IBAN_LENGTHS.items():
        whole, rest = divmod(n - 4, 4)
        last = rf" [A-Z0-9]{{{rest}}}" if rest else ""
        parts.append(rf"(?:{names.replace(' ', '|')})\d{{2}}(?:[A-Z0-9]{{{n - 4}}}|(?: [A-Z0-9]{{4}}){{{whole}}}{last})")
    return rf"(?:{'|'.join(parts)}|[A-Z]{{2}}\d{{2}}[A-Z0-9]{{11,30}})"


KINDS = {"email": EMAIL, "iban": _iban_pattern(), "date": DATE, "ssn": SSN, "ip": IPV4, "phone": PHONE, "intl": INTL, "card": CARD}


def _pattern() -> str:
    """All kinds; none next to a letter or digit. The card's back-reference moves
    with the groups before it."""
    kinds = {**KINDS, "card": CARD.replace(r"\1", r"\8")}
    return rf"(?<![\p{{L}}\p{{N}}])(?:{'|'.join(kinds.values())})(?![\p{{L}}\p{{N}}])"


def _hash(key: str, tag: str, i: Column, value: Column) -> Column:
    return F.sha2(F.concat_ws("|", F.lit(key), F.lit(tag), i.cast("string"), value.cast("string")), 256)


def _counters(key: str, tag: str, left: Column, right: Column, sizes: tuple[int, int]) -> Column:
    """The permuted pair as a struct (l, r), 0 <= l < sizes[0], 0 <= r < sizes[1]."""
    f = lambda i, v, m: F.conv(F.substring(_hash(key, tag, i, v), 1, 14), 16, 10).cast("long") % m

    def step(s: Column, i: Column) -> Column:
        l, r = s["l"], s["r"]  # noqa: E741
        return F.when(i % 2 == 0, F.struct(((l + f(i, r, sizes[0])) % sizes[0]).alias("l"), r.alias("r"))).otherwise(F.struct(l.alias("l"), ((r + f(i, l, sizes[1])) % sizes[1]).alias("r")))

    start = F.struct(left.cast("long").alias("l"), right.cast("long").alias("r"))
    return F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), start, step)


def _text(key: str, tag: str, value: Column) -> Column:
    """A string permuted within the class of each character (a-z, A-Z, 0-9; others
    stay); a string of one character has no halves and is shifted by the key alone."""

    def shift(part: Column, other: Column, i: Column) -> Column:
        h = _hash(key, tag, i, other)

        def one(c: Column, at: Column) -> Column:
            by = F.conv(F.substring(h, (at * 3) % 60 + 1, F.lit(4)), 16, 10).cast("int")
            turn = lambda base, n: F.char(F.lit(base) + (F.ascii(c) - base + by) % n)
            return F.when(c.between("0", "9"), turn(48, 10)).when(c.between("a", "z"), turn(97, 26)).when(c.between("A", "Z"), turn(65, 26)).otherwise(c)

        return F.when(part == "", part).otherwise(F.array_join(F.transform(F.split(part, ""), one), ""))

    def step(s: Column, i: Column) -> Column:
        l, r = s["l"], s["r"]  # noqa: E741
        return F.when(i % 2 == 0, F.struct(shift(l, r, i).alias("l"), r.alias("r"))).otherwise(F.struct(l.alias("l"), shift(r, l, i).alias("r")))

    half = F.floor(F.length(value) / 2).cast("int")
    start = F.struct(F.substring(value, F.lit(1), half).alias("l"), F.substring(value, half + 1, F.length(value)).alias("r"))
    done = F.aggregate(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), start, step)
    return F.concat(done["l"], done["r"])


def _luhn(digits: Column) -> Column:
    """Sum of the digits as the check-digit rule weighs them, the last one once."""
    one = lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise(c.cast("int") * 2 - F.when(c.cast("int") > 4, 9).otherwise(0))
    return F.aggregate(F.transform(F.split(F.reverse(digits), ""), one), F.lit(0), lambda a, b: a + b)


def _card(key: str, m: Column) -> tuple[Column, Column]:
    digits = F.regexp_replace(m, r"[ -]", "")
    payload = _text(key, "card", F.substring(digits, F.lit(1), F.length(digits) - 1))
    check = ((10 - _luhn(F.concat(payload, F.lit("0"))) % 10) % 10).cast("string")
    mark = F.regexp_extract(m, r"^\d{4}([ -])", 1)
    whole = F.concat(payload, check)
    grouped = F.array_join(F.array(*[F.substring(whole, 4 * i + 1, 4) for i in range(4)]), "#")
    valid = (_luhn(digits) % 10 == 0) & (F.length(F.regexp_replace(digits, "0", "")) > 0)
    return valid, F.when(mark != "", F.regexp_replace(grouped, F.lit("#"), mark)).otherwise(whole)


def _national(key: str, d: Column) -> Column:
    """Ten digits of the North American plan, permuted within it."""
    p = _counters(key, "phone", F.substring(d, 1, 3).cast("long") - 200, (F.substring(d, 4, 3).cast("long") - 200) * 10000 + F.substring(d, 7, 4).cast("long"), (800, 8_000_000))
    return F.concat((p["l"] + 200).cast("string"), (F.floor(p["r"] / 10000) + 200).cast("string"), F.lpad((p["r"] % 10000).cast("string"), 4, "0"))


def _put_back(m: Column, new: Column, mark: str) -> Column:
    """m with its characters that match mark replaced by those of new, in order."""

    def step(s: Column, c: Column) -> Column:
        taken = c.rlike(mark)
        return F.struct(F.when(taken, s["n"] + 1).otherwise(s["n"]).alias("n"), F.concat(s["out"], F.when(taken, F.substring(new, s["n"] + 1, F.lit(1))).otherwise(c)).alias("out"))

    return F.aggregate(F.split(m, ""), F.struct(F.lit(0).alias("n"), F.lit("").alias("out")), step)["out"]


def _phone(key: str, m: Column) -> tuple[Column, Column]:
    digits = F.regexp_replace(m, r"\D", "")
    new = F.concat(F.substring(digits, F.lit(1), F.length(digits) - 10), _national(key, F.substring(digits, -10, 10)))
    return F.lit(True), _put_back(m, new, r"\d")


def _intl(key: str, m: Column) -> tuple[Column, Column]:
    """A number with a plus keeps its country code; the rest is permuted digit by digit.
    Those of the North American plan go as they do without a plus."""
    d = F.regexp_replace(m, r"\D", "")
    code = F.when(F.substring(d, 1, 1).isin(CODES_1), 1).when(F.substring(d, 1, 2).isin(CODES_2), 2).otherwise(3)
    own = F.substring(d, code + 1, F.length(d))
    new = F.when(d.rlike(r"^1[2-9]\d{2}[2-9]\d{6}$"), F.concat(F.lit("1"), _national(key, F.substring(d, -10, 10))))
    new = new.otherwise(F.concat(F.substring(d, F.lit(1), code), _text(key, "intl", own)))
    return F.length(d).between(8, 15), _put_back(m, new, r"\d")


def _ip(key: str, m: Column) -> tuple[Column, Column]:
    o = F.transform(F.split(m, r"\."), lambda x: x.cast("int"))
    p = _counters(key, "ip", o[0] * 256 + o[1], o[2] * 256 + o[3], (1 << 16, 1 << 16))
    parts = [F.floor(p["l"] / 256), p["l"] % 256, F.floor(p["r"] / 256), p["r"] % 256]
    plain = F.array_join(F.transform(o, lambda x: x.cast("string")), ".") == m  # no leading zeros
    return plain & ~F.exists(o, lambda x: x > 255), F.concat_ws(".", *[x.cast("string") for x in parts])


def _ssn(key: str, m: Column) -> tuple[Column, Column]:
    area, group, serial = (F.substring(m, a, n).cast("long") for a, n in ((1, 3), (5, 2), (8, 4)))
    valid = area.between(1, 899) & (area != 666) & (group > 0) & (serial > 0)
    p = _counters(key, "ssn", area - 1 - (area > 666).cast("long"), (group - 1) * 9999 + serial - 1, (898, 99 * 9999))
    new = p["l"] + 1 + (p["l"] >= 665).cast("long")
    return valid, F.concat_ws("-", F.lpad(new.cast("string"), 3, "0"), F.lpad((F.floor(p["r"] / 9999) + 1).cast("string"), 2, "0"), F.lpad((p["r"] % 9999 + 1).cast("string"), 4, "0"))


def _date(key: str, m: Column) -> tuple[Column, Column]:
    """Years 1900 to 2099. The 29th of February goes to one of another leap year,
    any other day to a year and one of its 365 other days."""
    iso = m.contains("-")
    y = F.when(iso, F.substring(m, 1, 4)).otherwise(F.substring(m, 7, 4)).cast("int")
    mo = F.when(iso, F.substring(m, 6, 2)).otherwise(F.substring(m, 4, 2)).cast("int")
    d = F.when(iso, F.substring(m, 9, 2)).otherwise(F.substring(m, 1, 2)).cast("int")
    real = F.try_to_date(F.format_string("%04d-%02d-%02d", y, mo, d), "yyyy-MM-dd")
    leap = (mo == 2) & (d == 29)
    common = F.dayofyear(F.make_date(F.lit(2001), mo, F.when(leap, 28).otherwise(d))) - 1
    p = _counters(key, "date", y - 1900, common, (200, 365))
    day = F.date_add(F.lit("2001-01-01").cast("date"), p["r"].cast("int"))
    q = _counters(key, "leap", F.floor((y - 1904) / 4), F.lit(0), (49, 1))
    ny = F.when(leap, q["l"] * 4 + 1904).otherwise(p["l"] + 1900).cast("int")
    nm, nd = F.when(leap, 2).otherwise(F.month(day)), F.when(leap, 29).otherwise(F.dayofmonth(day))
    mark = F.substring(m, 3, 1)
    european = F.concat(F.lpad(nd.cast("string"), 2, "0"), mark, F.lpad(nm.cast("string"), 2, "0"), mark, ny.cast("string"))
    return real.isNotNull() & y.between(1900, 2099), F.when(iso, F.format_string("%04d-%02d-%02d", ny, nm, nd)).otherwise(european)


def _mod97(text: Column) -> Column:
    """Remainder by 97 of digits and letters, a letter as 10 to 35."""

    def step(s: Column, c: Column) -> Column:
        return F.when(c.between("0", "9"), s * 10 + c.cast("int")).otherwise(s * 100 + F.ascii(c) - 55) % 97

    return F.aggregate(F.split(text, ""), F.lit(0), step)


def _iban(key: str, m: Column) -> tuple[Column, Column]:
    plain = F.regexp_replace(m, " ", "")
    country, bban = F.substring(plain, 1, 2), F.substring(plain, F.lit(5), F.length(plain) - 4)
    new = _text(key, "iban", bban)
    check = F.lpad((98 - _mod97(F.concat(new, country, F.lit("00")))).cast("string"), 2, "0")
    return _mod97(F.concat(bban, F.substring(plain, 1, 4))) == 1, _put_back(m, F.concat(country, check, new), "[A-Z0-9]")


def _email(key: str, m: Column) -> tuple[Column, Column]:
    """Both sides of the address, but for its last domain; a domain has one pseudonym."""
    domain = F.substring_index(m, "@", -1)
    host, top = F.regexp_extract(domain, r"^(.*)\.[^.]+$", 1), F.regexp_extract(domain, r"(\.[^.]+)$", 1)
    return F.lit(True), F.concat(_text(key, "email", F.substring_index(m, "@", 1)), F.lit("@"), _text(key, "domain", host), top)


MAKERS = {"email": _email, "iban": _iban, "date": _date, "ssn": _ssn, "ip": _ip, "phone": _phone, "intl": _intl, "card": _card}


def _replaced(key: str, m: Column) -> Column:
    """Struct (kind, text) of a candidate; kind is null where it isn't valid."""
    out = F.struct(F.lit(None).cast("string").alias("kind"), m.alias("text"))
    for name in reversed(KINDS):
        valid, new = MAKERS[name](key, m)
        fits = m.rlike(f"^(?:{KINDS[name]})$")
        out = F.when(fits, F.when(valid, F.struct(F.lit("phone" if name == "intl" else name).alias("kind"), new.alias("text"))).otherwise(F.struct(F.lit(None).cast("string").alias("kind"), m.alias("text")))).otherwise(out)
    return out


def pseudonymise(docs: DataFrame, key: str) -> DataFrame:
    """docs with the personal data in text replaced, and two more columns: n_found
    (BIGINT) and kinds, the kinds found in order of place (ARRAY<STRING>; these
    replace columns of those names).

    A null text stays null with n_found 0. Values that fail validation stay as they
    are. Each row stands for itself, so repeated rows give repeated results."""
    pattern = F.lit(_pattern())
    docs = docs.drop("n_found", "kinds")
    met = docs.withColumn("__found", F.transform(F.regexp_extract_all("text", pattern, F.lit(0)), lambda m: _replaced(key, m)))
    # As a column of their own, so that the lambda below does not cut the text up again.
    met = met.withColumn("__gaps", F.when(F.size("__found") > 0, F.split(F.col("text"), _pattern(), -1)))
    gaps = F.col("__gaps")
    tail = F.transform("__found", lambda m, i: F.concat(m["text"], gaps[i + 1]))
    text = F.when(F.size("__found") > 0, F.concat(gaps[0], F.array_join(tail, ""))).otherwise(F.col("text"))
    kinds = F.filter(F.transform("__found", lambda m: m["kind"]), lambda k: k.isNotNull())
    kinds = F.coalesce(kinds, F.array().cast("array<string>"))
    kept = [text.alias(c) if c == "text" else F.col(c) for c in docs.columns]
    return met.select(*kept, F.size(kinds).cast("long").alias("n_found"), kinds.alias("kinds"))
