import datetime as dt
import hashlib
import re

from pyspark.sql import functions as F

from exactsum.llm import pseudonyms as P


def slow_feistel(value, left, right, key, kind):
    """The same network on Python integers."""
    a, b = divmod(value, right)

    def h(base, other, turn, x):
        return int(hashlib.sha256(f"{key}|{kind}|{base}|{other}|{turn}|{x}".encode()).hexdigest()[:15], 16) % base

    for turn in range(P.ROUNDS):
        if turn % 2 == 0:
            a = (a + h(left, right, turn, b)) % left
        else:
            b = (b + h(right, left, turn, a)) % right
    return a * right + b


def luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        x = int(c)
        total += x if i % 2 == 0 else x * 2 - 9 * (x > 4)
    return total % 10 == 0


TEXTS = [
    "card 4315726095712222, again 4315-7260-9571-2222.",
    "no card 4315726095712223 x",
    "call +1 (556) 555-9070 or (556) 555-9070 or 556-555-9070",
    "born 1987-02-28, not 1987-02-30; 31.12.1999 and 01/02/2003; old 1066-10-14",
    "host 152.143.123.131. but 300.1.1.1 stays",
    "mmp.98@mail2.example.com and A.b-9@x.org",
    "ssn 123-45-6789",
    "plain words only",
    "",
    None,
    "noise### 4785380592391139$$$ de",
    "x" * 100_000 + " 152.143.123.131",
]


def frame(spark, texts):
    return spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").selectExpr("*", "'keep' as source", "1 as a", "2 as out")


def test_round_trip_and_formats(spark):
    docs = frame(spark, TEXTS)
    hidden = P.pseudonymised(docs, "key one").cache()
    got = {r.doc_id: r.text for r in hidden.collect()}
    assert hidden.columns == docs.columns
    back = {r.doc_id: r.text for r in P.pseudonymised(hidden, "key one", inverse=True).collect()}
    assert back == dict(enumerate(TEXTS))
    for i in (1, 7, 8, 9):
        assert got[i] == TEXTS[i]
    cards = re.findall(r"[\d-]{16,}", got[0])
    assert cards[0] == cards[1].replace("-", "") != "4315726095712222" and luhn(cards[0])
    assert re.fullmatch(r"call \+1 \(\d{3}\) \d{3}-\d{4} or \(\d{3}\) \d{3}-\d{4} or \d{3}-\d{3}-\d{4}", got[2]) and "9070" not in got[2]
    m = re.fullmatch(r"born (\S+), not 1987-02-30; (\S+) and (\S+); old (\S+)", got[3])
    assert 1900 <= dt.date.fromisoformat(m[1]).year <= 2099 and m[1] != "1987-02-28"
    assert 1900 <= dt.datetime.strptime(m[2], "%d.%m.%Y").year <= 2099
    assert not 1900 <= dt.date.fromisoformat(m[4]).year <= 2099
    m = re.fullmatch(r"host (\S+)\. but 300.1.1.1 stays", got[4])
    assert m[1] != "152.143.123.131" and all(0 <= int(x) <= 255 for x in m[1].split("."))
    assert got[11].endswith(m[1])  # equal values stay linked
    assert re.fullmatch(r"[a-z]{3}\.\d\d@mail2\.example\.com and [A-Z]\.[a-z]-\d@x\.org", got[5]) and "mmp.98" not in got[5]
    assert got[10].startswith("noise### ") and got[10] != TEXTS[10]
    other = {r.doc_id: r.text for r in P.pseudonymised(docs, "key two").collect()}
    assert other[0] != got[0]


def test_feistel_is_a_bijection_and_equals_the_slow_one(spark):
    left, right = 27, 37
    d = spark.range(left * right).select("id", P.feistel(F.col("id"), F.lit(left).cast("long"), F.lit(right).cast("long"), "k", "test").alias("y"))
    d = d.withColumn("z", P.feistel(F.col("y"), F.lit(left).cast("long"), F.lit(right).cast("long"), "k", "test", inverse=True))
    rows = d.collect()
    assert sorted(r.y for r in rows) == list(range(left * right))
    assert all(r.z == r.id and r.y == slow_feistel(r.id, left, right, "k", "test") for r in rows)


def test_every_modern_day_has_its_own_pseudonym(spark):
    days = spark.range(73_049).select(F.date_format(F.date_add(F.lit("1900-01-01").cast("date"), F.col("id").cast("int")), "yyyy-MM-dd").alias("text"))
    assert P.pseudonymised(days, "k").distinct().where("text between '1900-01-01' and '2099-12-31'").count() == 73_049


def test_empty_table(spark):
    assert P.pseudonymised(frame(spark, TEXTS).limit(0), "k").count() == 0


def hidden_parts(spark, texts, kept):
    """Pseudonymised texts, after checking that they can be undone and that `kept` matches each."""
    docs = frame(spark, texts)
    hidden = P.pseudonymised(docs, "k")
    assert {r.doc_id: r.text for r in P.pseudonymised(hidden, "k", inverse=True).collect()} == dict(enumerate(texts))
    got = [r.text for r in hidden.orderBy("doc_id").collect()]
    for text, pattern in zip(got, kept):
        assert re.fullmatch(pattern, text), text
    return got


def test_phone_leaves_the_number_after_it(spark):
    phone, ip, card = r"\+1 \(\d{3}\) \d{3}-\d{4}", r"\d+\.\d+\.\d+\.\d+", r"\d{4} \d{4} \d{4} \d{4}"
    texts = ["+1 (826) 555-4081 190.137.223.204", "+1 (843) 555-7672 170.106.47.218", "+1 (826) 555-4081 4539 5787 6362 1460", "+1 (826) 555-4081 12 apples"]
    texts += ["+49 30 9018 2012 190.137.223.204", "+49 30 9018 2012 4539 5787 6362 1460", "+33 1 23 45 67 89 2020-03-25", "+15555550123 12 apples", "+44 20 7946 0958 12 pears", "190.137.223.204 4539 5787 6362 1460"]
    kept = [f"{phone} {ip}", f"{phone} {ip}", f"{phone} {card}", rf"{phone} 12 apples", rf"\+49 \d\d \d{{4}} \d{{4}} {ip}", rf"\+49 \d\d \d{{4}} \d{{4}} {card}", r"\+33 \d( \d\d){4} \d{4}-\d\d-\d\d", r"\+\d{11} 12 apples", r"\+44 \d\d \d{4} \d{4} 12 pears", f"{ip} {card}"]
    got = hidden_parts(spark, texts, kept)
    for secret in ("555-4081", "555-7672", "190.137.223.204", "170.106.47.218", "4539 5787", "9018 2012", "23 45 67", "2020-03-25", "5555550123", "7946 0958"):
        assert not any(secret in t for t in got), secret
    assert got[2].split(" ", 3)[-1] == got[5].split(" ", 4)[-1] == got[9].split(" ", 1)[-1]


def test_cards_in_runs_and_dates_in_timestamps(spark):
    c, date = r"\d{4} \d{4} \d{4} \d{4}", r"\d{4}-\d\d-\d\d"
    texts = ["card 4539 5787 6362 1460 123", "4539 5787 6362 1460 12/27", "12 4539 5787 6362 1460", "4539 5787 6362 1460 4315 7260 9571 2222 7", "4539 5787 6362 1460 190.137.223.204"]
    texts += ["at 2024-03-01T12:00:00Z", "03/25/2020 and 25/03/2020", "1234 5678 9012 3456 78", " ".join(f"{k * 7919 % 9973}" for k in range(1, 60))]
    kept = [f"card {c} 123", f"{c} 12/27", f"12 {c}", f"{c} {c} 7", rf"{c} \d+\.\d+\.\d+\.\d+", f"at {date}T12:00:00Z", r"(0\d|1[0-2])/(1[3-9]|2\d|3[01])/\d{4} and \d\d/\d\d/\d{4}", r"1234 5678 9012 3456 78", r"[\d ]+"]
    got = hidden_parts(spark, texts, kept)
    for secret in ("4539 5787", "4315 7260", "190.137.223.204", "2024-03-01", "03/25/2020", "25/03/2020"):
        assert not any(secret in t for t in got), secret
    assert luhn("".join(re.findall(r"\d", got[2][3:])))
    assert got[0][5:24] == got[1][:19] == got[2][3:] == got[3][:19] == got[4][:19]


def test_national_numbers_stay_valid(spark):
    bad = ["000-12-3456", "666-12-3456", "900-12-3456", "123-00-4567", "123-45-0000"]
    assert hidden_parts(spark, bad, [re.escape(t) for t in bad]) == bad
    good = [f"{a:03d}-{g:02d}-{s:04d}" for a in (1, 77, 665, 667, 899) for g in (1, 50, 99) for s in (1, 1234, 9999)]
    got = hidden_parts(spark, good, [r"(?!000|666|9)\d{3}-(?!00)\d\d-(?!0000)\d{4}"] * len(good))
    assert len(set(got)) == len(good) and not set(got) & set(good)
    for text, moved in zip(good, got):
        a, g, s = map(int, text.split("-"))
        x = slow_feistel(((a - 1 - (a > 666)) * 99 + g - 1) * 9999 + s - 1, 898 * 99, 9999, "k", "ssn")
        head, tail = divmod(x, 9999)
        place = head // 99
        assert moved == f"{place + 1 + (place >= 665):03d}-{head % 99 + 1:02d}-{tail + 1:04d}"


def test_phones_stay_in_their_class(spark):
    dialled = lambda t: re.fullmatch(r"([2-9](?!11)\d\d){2}\d{4}", re.sub(r"\D", "", t)[-10:]) is not None
    texts = [f"({a:03d}) {e:03d}-{n:04d}" for a in (200, 212, 310, 910, 999, 911, 117, 23) for e in (555, 200, 411, 12) for n in (0, 4081)]
    got = hidden_parts(spark, texts, [r"\(\d{3}\) \d{3}-\d{4}"] * len(texts))
    assert all(dialled(a) == dialled(b) and a != b for a, b in zip(texts, got)) and len(set(got)) == len(texts)
    same = hidden_parts(spark, ["+1 (826) 555-4081", "(826) 555-4081", "826-555-4081", "+18265554081"], [r".*"] * 4)
    assert len({re.sub(r"\D", "", t)[-10:] for t in same}) == 1 and same[3].startswith("+1")
    world = hidden_parts(spark, ["+44 20 7946 0958", "+39 06 1234 5678", "+49 30 901820"], [r"\+44 [1-9]\d \d{4} \d{4}", r"\+39 0\d \d{4} \d{4}", r"\+49 [1-9]\d \d{6}"])
    assert "7946" not in world[0] and "1234" not in world[1]


def test_repeated_rows_and_ties_stay_linked(spark):
    docs = spark.createDataFrame([(1, "ssn 123-45-6789"), (1, "ssn 123-45-6789"), (None, "ssn 123-45-6789")], "doc_id long, text string")
    assert P.pseudonymised(docs, "k").select("text").distinct().count() == 1
