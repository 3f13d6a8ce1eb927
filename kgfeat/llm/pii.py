"""Format-preserving pseudonyms for personal data, in DataFrame functions only.

Found and validated: payment cards (13 to 19 digits with a right Luhn digit), international bank
account numbers (right remainder modulo 97), telephone numbers of ten digits or with a country code,
IPv4 addresses, social security numbers in the ranges that are issued, and calendar dates. Each is
permuted within its format by a keyed Feistel network, so equal values get equal pseudonyms in every
document and different values stay different. Separators, lengths, country codes and check digits
hold. E-mail addresses have no numeric format to permute; they get a keyed hash in e-mail form,
linked in the same way. What fails validation stays as it is.

A date with slashes is read with the day first; if that is no date, with the month first. The latter
have a day of 13 or more and are permuted among such dates, so no pseudonym stands for two dates.

The network alternates between the two parts of a mixed-radix number (x = a * B + b, a below A, b
below B): a += f(b) mod A, then b += f(a) mod B. Each round can be undone, so the whole is a
permutation of exactly A * B values, with no walking in cycles; f is SHA-256 of key, kind, round
and the other part.
"""

from __future__ import annotations

import calendar

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgfeat.llm.text import given_back, neutral

ROUNDS = 8
KINDS = ("email", "ip", "iban", "abroad", "date", "ssn", "phone", "card")
#: one alternative a kind, in this order; bounds keep them out of longer numbers and words
PATTERNS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+",
    "ip": r"(?<![\w.])(?:(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])\.){3}(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])(?![\w]|\.[0-9])",
    "iban": r"(?<!\w)[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![\w@%+/]|[.-]\w)",
    "abroad": r"(?<![\w+])\+(?:1[0-9]{10}|[2-9](?:[ .()-]{0,2}[0-9]){7,14})(?!\w|[-.][0-9])",
    "date": r"(?<![\w./-])(?:(?:18|19|20|21)[0-9]{2}-[0-9]{2}-[0-9]{2}|[0-9]{1,2}/[0-9]{1,2}/(?:18|19|20|21)[0-9]{2}|[0-9]{1,2}\.[0-9]{1,2}\.(?:18|19|20|21)[0-9]{2})(?![\w/-]|\.[0-9])",
    "ssn": r"(?<![\w-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\w-])",
    "phone": r"(?:\([0-9]{3}\) ?|(?<![\w.-])[0-9]{3}[-. ])[0-9]{3}[-. ][0-9]{4}(?![\w]|[-.][0-9])",
    "card": r"(?<![\w.-])[0-9](?:[ -]?[0-9]){12,18}(?![\w]|[-.][0-9])",
}
ANY = "|".join(f"(?:{PATTERNS[k]})" for k in KINDS)
DAYS_FROM, YEAR_FROM = "1800-01-01", 1800  # 400 Gregorian years from here: 146,097 = 189 * 773 days
#: fixed values: country codes of two digits; 1 and 7 have one digit, all others three
TWO_DIGIT_CODES = "20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split()
AREAS = 898  # areas of social security numbers: 001 to 899 without 666
IBAN_DIGITS = 8  # fewest digits after the check digits


def feistel(x: Column, a: int | Column, b: int | Column, key: str, tweak: str | Column, rounds: int = ROUNDS) -> Column:
    """Keyed permutation of the longs 0 .. a * b - 1 (a, b at most 2^31, a * b below 2^63)."""
    a, b = (v if isinstance(v, Column) else F.lit(v).cast("long") for v in (a, b))
    tweak = tweak if isinstance(tweak, Column) else F.lit(tweak)

    def turn(acc: Column, r: Column) -> Column:
        def f(part: Column, m: Column) -> Column:
            h = F.sha2(F.concat_ws("|", F.lit(key), tweak, r.cast("string"), part.cast("string")), 256)
            return F.conv(F.substring(h, 1, 15), 16, 10).cast("long") % m

        left = F.struct(((acc["a"] + f(acc["b"], a)) % a).alias("a"), acc["b"].alias("b"))
        right = F.struct(acc["a"].alias("a"), ((acc["b"] + f(acc["a"], b)) % b).alias("b"))
        return F.when(r % 2 == 1, left).otherwise(right)

    x = x.cast("long")
    start = F.struct(F.call_function("div", x, b).alias("a"), (x % b).alias("b"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), start, turn, lambda s: s["a"] * b + s["b"])


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _refill(m: Column, digits: Column) -> Column:
    """The digits in the places that m has for them."""
    gaps = F.split(m, "[0-9]", -1)
    return F.array_join(F.zip_with(gaps, F.split(F.concat(digits, F.lit("")), ""), lambda g, d: F.concat(F.coalesce(g, F.lit("")), F.coalesce(d, F.lit("")))), "")


def digits_permuted(d: Column, key: str, tweak: str | Column) -> Column:
    """Keyed permutation of the strings of as many digits as d has (1 to 18)."""
    powers = F.array(*(F.lit(10**i).cast("long") for i in range(10)))
    low = F.shiftright(F.length(d), 1)
    x = feistel(d.cast("long"), F.element_at(powers, F.length(d) - low + 1), F.element_at(powers, low + 1), key, tweak)
    return F.lpad(x.cast("string"), F.length(d), F.lit("0"))


def luhn_sum(d: Column) -> Column:
    """Luhn sum of a digit string whose last digit is the check digit."""
    each = F.transform(F.split(F.reverse(d), ""), lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise(2 * c.cast("int") - F.when(c.cast("int") > 4, 9).otherwise(0)))
    return F.aggregate(each, F.lit(0), lambda s, v: s + v)


def _long(d: Column) -> Column:
    return d.cast("long")


def card_parts(m: Column) -> Column:
    """(before, card, after) of a run of digit groups: the longest part from edge to edge of groups that
    is a valid card, the first of equals; null if there is none."""
    groups = F.split(m, "(?<=[ -])", -1)  # each with the separator after it
    spans = F.flatten(F.transform(F.sequence(F.lit(1), F.size(groups)), lambda i: F.transform(F.sequence(i, F.size(groups)), lambda j: F.struct(i.alias("i"), (j - i + 1).alias("n")))))

    def cut(s: Column) -> Column:
        before = F.array_join(F.slice(groups, F.lit(1), s["i"] - 1), "")
        card = F.regexp_replace(F.array_join(F.slice(groups, s["i"], s["n"]), ""), "[ -]$", "")
        return F.struct(F.length(_digits(card)).alias("n"), (-F.length(before)).alias("at"), before.alias("before"), card.alias("card"), F.substring(m, F.length(before) + F.length(card) + 1, F.length(m)).alias("after"))

    return F.array_max(F.filter(F.transform(spans, cut), lambda c: c["n"].between(13, 19) & ~c["card"].rlike("[A-Z]") & (luhn_sum(_digits(c["card"])) % 10 == 0)))


def rest_97(s: Column) -> Column:
    """The remainder modulo 97 of digits and capitals, these as numbers from 10 on."""
    return F.aggregate(F.split(s, ""), F.lit(0), lambda acc, c: F.when(c.between("0", "9"), acc * 10 + F.ascii(c) - 48).otherwise(acc * 100 + F.ascii(c) - 55) % 97)


def iban_part(m: Column) -> Column:
    """The longest beginning of m, up to an edge of groups, that is a valid account number; null if there is none."""
    groups = F.split(m, " ", -1)
    starts = F.transform(F.sequence(F.lit(1), F.size(groups)), lambda j: F.array_join(F.slice(groups, F.lit(1), j), " "))

    def valid(s: Column) -> Column:
        x = F.replace(s, F.lit(" "), F.lit(""))
        turned = F.concat(F.substring(x, 5, 34), F.substring(x, 1, 4))
        return F.length(x).between(15, 34) & (F.length(_digits(x)) >= IBAN_DIGITS + 2) & F.substring(x, 3, 2).between("02", "98") & (rest_97(turned) == 1)

    return F.get(F.filter(F.reverse(starts), valid), F.lit(0))


def iban_pseudonym(s: Column, key: str) -> Column:
    """Country and letters stay, the digits are permuted half by half, the check digits are made right again."""
    x = F.replace(s, F.lit(" "), F.lit(""))
    form = F.concat(F.substring(x, 1, 2), F.regexp_replace(F.substring(x, 5, 34), "[0-9]", "0"))
    d = F.substring(_digits(x), 3, 34)
    half = F.shiftright(F.length(d), 1)
    halves = F.struct(F.substring(d, F.lit(1), half).alias("a"), F.substring(d, half + 1, F.length(d)).alias("b"))

    def turn(h: Column, r: Column) -> Column:
        new = digits_permuted(h["a"], key, F.concat_ws("|", F.lit("iban"), form, r.cast("string"), h["b"]))
        return F.struct(h["b"].alias("a"), new.alias("b"))

    new = F.aggregate(F.sequence(F.lit(1), F.lit(4)), halves, turn, lambda h: F.concat(h["a"], h["b"]))
    body = F.replace(_refill(F.substring(x, 5, 34), new), F.lit(" "), F.lit(""))
    check = F.lpad((98 - rest_97(F.concat(body, F.substring(x, 1, 2), F.lit("00")))).cast("string"), 2, "0")
    return _refill(s, F.concat(check, new))


def month_first(day: Column, key: str) -> Column:
    """Keyed permutation of the dates with a day of 13 or more: days to 28, the last days of months, and
    leap days each among themselves, which fills their numbers without a gap."""
    year, month, dom = F.year(day) - YEAR_FROM, F.month(day), F.dayofmonth(day)
    dated = lambda y, md: F.concat_ws("-", (y + YEAR_FROM).cast("string"), md).cast("date")
    x = feistel((year * 12 + month - 1) * 16 + dom - 13, 300, 256, key, "date-month-first")
    two = lambda c: F.lpad(c.cast("string"), 2, "0")
    early = dated(F.call_function("div", x, F.lit(192)), F.concat_ws("-", two(F.call_function("div", x % 192, F.lit(16)) + 1), two(x % 16 + 13)))
    ends = [f"{m:02d}-{d}" for m in range(1, 13) for d in range(29, calendar.monthrange(2001, m)[1] + 1)]
    ends_, md = F.array(*map(F.lit, ends)), F.date_format(day, "MM-dd")
    y = feistel(year * len(ends) + F.array_position(ends_, md) - 1, 400, len(ends), key, "date-month-end")
    late = dated(F.call_function("div", y, F.lit(len(ends))), F.element_at(ends_, (y % len(ends) + 1).cast("int")))
    leaps = [v for v in range(400) if calendar.isleap(YEAR_FROM + v)]
    leaps_ = F.array(*map(F.lit, leaps))
    leap = dated(F.element_at(leaps_, (feistel(F.array_position(leaps_, year) - 1, len(leaps), 1, key, "date-leap") + 1).cast("int")), F.lit("02-29"))
    return F.when(dom <= 28, early).when(md == "02-29", leap).otherwise(late)


def date_pseudonym(m: Column, key: str) -> Column:
    """Null if m is no date."""
    part = F.transform(F.split(m, "[-/.]"), lambda c: F.lpad(c, F.greatest(F.length(c), F.lit(2)), F.lit("0")))
    joined = lambda *at: F.concat_ws("-", *(part[k] for k in at)).try_cast("date")

    def moved(day: Column) -> Column:
        return F.date_add(F.lit(DAYS_FROM).cast("date"), feistel(F.datediff(day, F.lit(DAYS_FROM).cast("date")), 189, 773, key, "date").cast("int"))

    padded = F.length(m) == 10
    out = F.when(m.rlike("^[0-9]{4}-"), F.date_format(moved(joined(0, 1, 2)), "yyyy-MM-dd"))
    for mark in "/.":
        shown = lambda day, *form, mark=mark: F.when(padded, F.date_format(day, mark.join(2 * f for f in form) + f"{mark}yyyy")).otherwise(F.date_format(day, mark.join(form) + f"{mark}yyyy"))
        out = out.when(m.contains(mark) & joined(2, 1, 0).isNotNull(), shown(moved(joined(2, 1, 0)), "d", "M"))
        if mark == "/":
            out = out.when(m.contains(mark) & joined(2, 0, 1).isNotNull(), shown(month_first(joined(2, 0, 1), key), "M", "d"))
    return out


def pseudonym(m: Column, key: str) -> Column:
    """The pseudonym of one match, or the match itself where validation fails."""
    d = _digits(m)

    # cards: all digits but the check digit are permuted, the check digit is made right again
    def card(c: Column) -> Column:
        d = _digits(c)
        body = digits_permuted(F.substring(d, F.lit(1), F.length(d) - 1), key, F.concat(F.lit("card"), F.length(d).cast("string")))
        check = ((10 - luhn_sum(F.concat(body, F.lit("0"))) % 10) % 10).cast("string")
        return _refill(c, F.concat(body, check))

    cards = F.element_at(F.transform(F.array(card_parts(m)), lambda p: F.concat(p["before"], card(p["card"]), p["after"])), 1)
    accounts = F.element_at(F.transform(F.array(iban_part(m)), lambda s: F.concat(iban_pseudonym(s, key), F.substring(m, F.length(s) + 1, F.length(m)))), 1)
    # telephone: a first digit of 2 to 9 stays in that range
    def ten(d: Column) -> Column:
        first = F.substring(d, 1, 1).cast("long")
        ranged = F.lpad((feistel((first - 2) * 10**9 + _long(F.substring(d, 2, 9)), 80_000, 100_000, key, "phone") + 2 * 10**9).cast("string"), 10, "0")
        low = F.concat(first.cast("string"), F.lpad(feistel(_long(F.substring(d, 2, 9)), 10**5, 10**4, key, "phone-low").cast("string"), 9, "0"))
        return F.when(first >= 2, ranged).otherwise(low)

    code = F.when(F.substring(d, 1, 1) == "7", F.lit(1)).when(F.substring(d, 1, 2).isin(TWO_DIGIT_CODES), F.lit(2)).otherwise(F.lit(3))
    cc = F.substring(d, F.lit(1), code)
    national = digits_permuted(F.substring(d, code + 1, F.length(d)), key, F.concat(F.lit("phone+"), cc))
    abroad = F.when(m.startswith("+1"), F.concat(F.lit("+1"), ten(F.substring(d, 2, 10)))).otherwise(_refill(m, F.concat(cc, national)))
    area, group, serial = (F.substring(d, at, n).cast("long") for at, n in ((1, 3), (4, 2), (6, 4)))
    issued = area.between(1, 899) & (area != 666) & (group > 0) & (serial > 0)
    y = feistel(((area - 1 - (area > 666).cast("long")) * 99 + group - 1) * 9999 + serial - 1, AREAS * 99, 9999, key, "ssn")
    z = F.call_function("div", y, F.lit(9999 * 99))
    new_ssn = F.concat(F.lpad((z + 1 + (z >= 665).cast("long")).cast("string"), 3, "0"), F.lpad((F.call_function("div", y, F.lit(9999)) % 99 + 1).cast("string"), 2, "0"), F.lpad((y % 9999 + 1).cast("string"), 4, "0"))
    ssn = F.when(issued, _refill(m, new_ssn))
    o = F.split(m, r"\.")
    ipn = feistel(F.aggregate(o, F.lit(0).cast("long"), lambda s, v: s * 256 + v.cast("long")), 65536, 65536, key, "ip")
    ip = F.concat_ws(".", *(F.shiftright(ipn, s).bitwiseAND(F.lit(255).cast("long")).cast("string") for s in (24, 16, 8, 0)))
    h = F.sha2(F.concat_ws("|", F.lit(key), F.lit("email"), F.lower(m)), 256)
    email = F.concat(F.lit("u"), F.substring(h, 1, 16), F.lit("@"), F.lit("m"), F.substring(h, 17, 6), F.lit(".example"))
    made = (
        F.when(m.contains("@"), email)
        .when(m.rlike(rf"^{PATTERNS['ip']}$"), ip)
        .when(m.startswith("+"), abroad)
        .when(m.rlike("^[A-Z]"), F.coalesce(accounts, cards))
        .when(m.rlike(rf"^{PATTERNS['date']}$"), date_pseudonym(m, key))
        .when(m.rlike(rf"^{PATTERNS['ssn']}$"), ssn)
        .when(m.rlike(rf"^{PATTERNS['phone']}$"), _refill(m, ten(d)))
        .otherwise(cards)
    )
    return F.coalesce(made, m)


def pseudonymise(docs: DataFrame, key: str, text_col: str = "text", count_col: str | None = None) -> DataFrame:
    """docs with the text's personal data replaced, all other columns as they are whatever their names.

    Null text stays null and empty text empty; repeated rows and an empty table stay what they are.
    count_col, if named, gets the number of values replaced; a column of that name is overwritten.
    """
    d, (x,) = neutral(docs, text_col)
    t = F.col(x)
    found = F.regexp_extract_all(t, F.lit(ANY), F.lit(0))
    made = F.transform(found, lambda m: pseudonym(m, key))
    some = F.coalesce(t.rlike("[0-9@]"), F.lit(False))
    part = d.withColumn("made", F.when(some, F.struct(found.alias("found"), made.alias("new"))))
    between = F.split(t, ANY, -1)
    joined = F.array_join(F.zip_with(between, F.col("made.new"), lambda b, m: F.concat(b, F.coalesce(m, F.lit("")))), "")
    has = F.col("made").isNotNull() & (F.size("made.found") > 0)
    changed = F.size(F.filter(F.zip_with("made.found", "made.new", lambda a, b: a != b), lambda y: y))
    part = part.withColumn("n", F.when(has, changed).otherwise(F.lit(0)))
    part = part.withColumn(x, F.when(has, joined).otherwise(t))
    if not count_col:
        return given_back(part, docs)
    keep = [F.col(f"c{k}").alias(c) for k, c in enumerate(docs.columns) if c.casefold() != count_col.casefold()]
    return part.select(*keep, F.col("n").alias(count_col))
