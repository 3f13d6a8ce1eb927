from __future__ import annotations

import calendar
import datetime as dt
import hashlib
import random
import re

from pyspark.sql import functions as F

from kgfeat.llm import pii

KEY = "k1"


def brute_feistel(x, a, b, key, tweak):
    p, q = divmod(x, b)
    f = lambda r, v, m: int(hashlib.sha256(f"{key}|{tweak}|{r}|{v}".encode()).hexdigest()[:15], 16) % m
    for r in range(1, pii.ROUNDS + 1):
        if r % 2:
            p = (p + f(r, q, a)) % a
        else:
            q = (q + f(r, p, b)) % b
    return p * b + q


def luhn(s):
    return sum(int(c) if i % 2 == 0 else (2 * int(c) - 9 * (c > "4")) for i, c in enumerate(reversed(s))) % 10


def card(rng, n=16):
    body = "".join(str(rng.randrange(10)) for _ in range(n - 1))
    return body + str(-luhn(body + "0") % 10)


def one(spark, text):
    return pii.pseudonymise(spark.createDataFrame([(text,)], "text string"), KEY).first()["text"]


def test_feistel_is_the_brute_permutation(spark):
    got = [r[0] for r in spark.range(189 * 7).select(pii.feistel(F.col("id"), 189, 7, KEY, "t")).collect()]
    assert sorted(got) == list(range(189 * 7))
    assert got == [brute_feistel(x, 189, 7, KEY, "t") for x in range(189 * 7)]


def test_cards_dates_phones_and_addresses(spark):
    rng = random.Random(3)
    rows = []
    for n in (13, 15, 16, 19):
        rows += [card(rng, n) for _ in range(20)]
    got = [r[0] for r in pii.pseudonymise(spark.createDataFrame([(c,) for c in rows], "text string"), KEY).collect()]
    for a, b in zip(rows, got, strict=True):
        n = len(a)
        lo = (n - 1) // 2
        body = f"{brute_feistel(int(a[:-1]), 10 ** (n - 1 - lo), 10**lo, KEY, f'card{n}'):0{n - 1}d}"
        assert b == body + str(-luhn(body + "0") % 10) and luhn(b) == 0 and a != b
    grouped = rows[45]
    spaced = " ".join(grouped[i : i + 4] for i in range(0, 16, 4))
    assert one(spark, spaced).replace(" ", "") == one(spark, grouped)
    for text, form in (("1999-12-31", "%Y-%m-%d"), ("29/02/2000", "%d/%m/%Y"), ("01.03.1987", "%d.%m.%Y")):
        day = (dt.datetime.strptime(text, form).date() - dt.date(1800, 1, 1)).days
        want = dt.date(1800, 1, 1) + dt.timedelta(brute_feistel(day, 189, 773, KEY, "date"))
        assert one(spark, text) == want.strftime(form)
    phone = one(spark, "+1 (743) 555-3824")
    assert re.fullmatch(r"\+1 \([2-9]\d\d\) \d{3}-\d{4}", phone) and phone != "+1 (743) 555-3824"
    assert one(spark, "10.0.0.255") == ".".join(str(brute_feistel(0x0A0000FF, 65536, 65536, KEY, "ip") >> s & 255) for s in (24, 16, 8, 0))
    assert re.fullmatch(r"\d{3}-\d{2}-\d{4}", one(spark, "123-45-6789"))
    assert "some.one@mail.example.com" not in one(spark, "write to some.one@mail.example.com now")


def test_what_is_not_valid_stays(spark):
    for text in ("4111111111111112", "2023-02-30", "999.1.1.1", "version 1.2.3", "order 12345", "a" * 100_000, "1" * 60, "no data"):
        assert one(spark, text) == text


def test_linked_across_documents_and_whole_texts(spark):
    rng = random.Random(8)
    c = card(rng)
    texts = [f"pay {c} now", f"again: {c}, and {card(rng)}; mail a.b@x.example.org***", None, "", "x " * 30_000 + c + " end"]
    df = spark.createDataFrame([(i, t, 0) for i, t in enumerate(texts)] + [(0, texts[0], 0)], "doc_id long, text string, n_replaced int").drop("n_replaced")
    got = [r for r in pii.pseudonymise(df, KEY, count_col="n").orderBy("doc_id").collect()]
    new = re.search(r"pay (\d+) now", got[0]["text"])[1]
    assert got[0] == got[1] and new != c and new in got[2]["text"] and c not in got[2]["text"]
    assert got[2]["n"] == 3 and got[2]["text"].endswith("***")
    assert got[3]["text"] is None and got[4]["text"] == "" and got[3]["n"] == got[4]["n"] == 0
    assert got[5]["text"] == "x " * 30_000 + new + " end"
    other = pii.pseudonymise(df, "another key").filter("doc_id = 0").first()["text"]
    assert other != got[0]["text"]


def test_plan_has_no_python(spark):
    df = pii.pseudonymise(spark.createDataFrame([("x",)], "text string"), KEY)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_cards_beside_other_digits(spark):
    card, hidden = "4111 1111 1111 1111", "4111111111111111"
    texts = [f"{card} 12/27", f"{hidden} 123", f"{hidden}", f"12 {card}", "1234 5678 9012 3456 78", f"{card} 12/27 and {hidden}"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = [r["text"] for r in pii.pseudonymise(df, "k").orderBy("doc_id").collect()]
    assert all(card not in t and hidden not in t for t in got)
    new = got[2]
    spaced = " ".join(new[i : i + 4] for i in range(0, 16, 4))
    assert got == [f"{spaced} 12/27", f"{new} 123", new, f"12 {spaced}", texts[4], f"{spaced} 12/27 and {new}"]


def many(spark, texts):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return [r["text"] for r in pii.pseudonymise(df, KEY).orderBy("doc_id").collect()]


def test_long_numbers_are_divided_exactly(spark):
    xs = [123_456_789 * 10**9 + r for r in (0, 1, 999_999_998, 999_999_999)] + [123_456_790 * 10**9, 10**18 - 1]
    df = spark.createDataFrame(list(enumerate(xs)), "i long, x long")
    got = [r[0] for r in df.orderBy("i").select(pii.feistel(F.col("x"), 10**9, 10**9, KEY, "t")).collect()]
    assert got == [brute_feistel(x, 10**9, 10**9, KEY, "t") for x in xs]


def test_dates_in_more_forms(spark):
    rng = random.Random(5)
    us = [f"{m:02d}/{d}/{y}" for y in (1999, 2000) for m in range(1, 13) for d in range(13, 32) if d <= calendar.monthrange(y, m)[1]]
    got = many(spark, us)
    assert len(set(got)) == len(us) and sum(a == b for a, b in zip(us, got, strict=True)) < 5
    for t in got:
        assert dt.datetime.strptime(t, "%m/%d/%Y").day >= 13 and len(t) == 10
    padded = [f"{rng.randrange(1, 10):02d}/{rng.randrange(1, 10):02d}/{rng.randrange(1800, 2200)}" for _ in range(50)]
    plain = ["/".join(str(int(x)) for x in t.split("/")) for t in padded]
    for a, b in zip(many(spark, padded), many(spark, plain), strict=True):
        assert "/".join(str(int(x)) for x in a.split("/")) == b
    assert many(spark, ["13/13/1990", "2/30/2001", "0/4/1990"]) == ["13/13/1990", "2/30/2001", "0/4/1990"]
    dotted = one(spark, "7.4.1990")
    assert dt.datetime.strptime(dotted, "%d.%m.%Y") and dotted != "7.4.1990"


def test_month_first_dates_are_permuted(spark):
    days = spark.sql("SELECT explode(sequence(DATE'1800-01-01', DATE'2199-12-31')) AS d").filter("day(d) >= 13")
    got = days.select(pii.month_first(F.col("d"), KEY).alias("n")).agg(F.count("*"), F.count_distinct("n"), F.min(F.dayofmonth("n")), F.min("n").cast("string"), F.max("n").cast("string")).first()
    assert got[0] == got[1] and got[2] == 13 and got[3] >= "1800-01-13" and got[4] <= "2199-12-31"


def test_social_security_numbers_stay_valid(spark):
    rng = random.Random(6)
    valid = sorted({f"{rng.choice([1, 2, 665, 667, 898, 899]):03d}-{rng.randrange(1, 100):02d}-{rng.randrange(1, 10000):04d}" for _ in range(300)})
    got = many(spark, valid)
    assert len(set(got)) == len(valid)
    for t in got:
        a, g, n = map(int, t.split("-"))
        assert 1 <= a <= 899 and a != 666 and g and n and re.fullmatch(r"\d{3}-\d{2}-\d{4}", t)
    wrong = ["000-12-3456", "666-12-3456", "900-12-3456", "123-00-3456", "123-45-0000"]
    assert many(spark, wrong) == wrong


def rest(s):
    return int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97


def test_account_numbers(spark):
    one_, other = "DE89370400440532013000", "GB82 WEST 1234 5698 7654 32"
    texts = [one_, "DE89 3704 0044 0532 0130 00", f"{other} AND more", "DE88370400440532013000", "ID44 4111 1111 1111 1111", "FR1420041010050500013M02606", "AB12 3456 7890 JOE@x.example.org"]
    got = many(spark, texts)
    assert rest(got[0]) == 1 and got[0] != one_ and got[0][:2] == "DE" and len(got[0]) == 22
    assert got[1].replace(" ", "") == got[0] and [len(g) for g in got[1].split()] == [4, 4, 4, 4, 4, 2]
    assert got[2].endswith(" AND more") and got[2][:2] == "GB" and got[2][5:9] == "WEST" and rest(got[2][:-9].replace(" ", "")) == 1
    assert got[3] == texts[3] and got[4].startswith("ID44 ") and "4111 1111" not in got[4] and luhn(got[4][5:].replace(" ", "")) == 0
    assert got[5] != texts[5] and got[5][:2] == "FR" and got[5].index("M") == texts[5].index("M") and rest(got[5]) == 1
    assert "JOE@" not in got[6]


def test_telephone_numbers_with_country_codes(spark):
    texts = ["+49 30 1234567", "+49301234567", "+44 (0)20 7946 0958", "+17435553824", "+1 (743) 555-3824", "+7 495 123-45-67", "+353 1 234 5678", "+12", "1+2 3456"]
    got = many(spark, texts)
    shape = lambda t: re.sub("[0-9]", "0", t)
    assert [shape(t) for t in got] == [shape(t) for t in texts]
    assert all(a != b for a, b in zip(texts[:7], got[:7], strict=True)) and got[7:] == texts[7:]
    assert got[0].replace(" ", "") == got[1] and re.sub(r"\D", "", got[3]) == re.sub(r"\D", "", got[4])
    assert [t[:3] for t in got[:3]] == ["+49", "+49", "+44"] and got[5].startswith("+7 ") and got[6].startswith("+353 ")
