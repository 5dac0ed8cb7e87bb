"""Pseudonyms stay inside their formats, are distinct, and lead back to their values."""

import random
import re

from pyspark.sql import functions as F
from test_operators import ODD, empty, luhn, odd  # noqa: F401  fixtures

from rareblock.llm import pseudonyms

KEY = "k"


def there_and_back(spark, values, kind):
    """Pseudonyms of values, all of the kind and distinct, and their way back."""
    df = spark.createDataFrame([(v,) for v in values], "v string").repartition(4)
    to = df.select("v", pseudonyms.pseudonym(F.col("v"), F.lit(kind), KEY).alias("p"))
    got = to.select("v", "p", pseudonyms.kind_of(F.col("p")).alias("kind"), pseudonyms.pseudonym(F.col("p"), F.lit(kind), KEY, back=True).alias("b")).collect()
    assert {r["kind"] for r in got} == {kind} and all(r["b"] == r["v"] for r in got)
    assert len({r["p"] for r in got}) == len({r["v"] for r in got})
    assert sum(r["p"] != r["v"] for r in got) >= 0.9 * len(got)
    return {r["v"]: r["p"] for r in got}


def test_numbers_stay_valid(spark):
    rng = random.Random(3)
    areas = [a for a in range(1, 900) if a != 666]
    values = {f"{rng.choice(areas):03d}-{rng.randint(1, 99):02d}-{rng.randint(1, 9999):04d}" for _ in range(2000)} | {"001-01-0001", "899-99-9999", "665-01-0001", "667-01-0001"}
    there_and_back(spark, sorted(values), "ssn")


def test_calendar_ends_and_both_slash_orders(spark):
    iso = ["0001-01-01", "0001-02-28", "9999-12-31", "9999-01-01", "2000-02-29"] + [f"{y:04d}-0{1 + y % 9}-1{y % 10}" for y in range(1, 9999, 37)]
    there_and_back(spark, iso, "date")
    rng = random.Random(4)
    slashes = {f"{rng.randint(1, 28):02d}/{rng.randint(1, 12):02d}/{rng.randint(1950, 2050)}" for _ in range(2500)} | {f"{rng.randint(1, 12):02d}/{rng.randint(13, 28)}/{rng.randint(1950, 2050)}" for _ in range(2500)}
    got = there_and_back(spark, sorted(slashes), "date")
    month_first = lambda s: int(s[3:5]) > 12
    assert all(month_first(v) == month_first(p) for v, p in got.items()) and all(re.fullmatch(r"\d\d/\d\d/\d{4}", p) for p in got.values())


def test_other_kinds_go_back(spark):
    rng = random.Random(5)
    pick = lambda letters, n: "".join(rng.choice(letters) for _ in range(n))
    there_and_back(spark, [f"password={pick('0123456789abcdef', 8)}" for _ in range(200)] + [f"password={pick('0123456789abcdefgh', 8)}" for _ in range(200)], "secret")
    there_and_back(spark, [f"{i % 256}.{i // 7 % 256}.{i // 11 % 256}.{i % 199}" for i in range(500)], "ip")
    there_and_back(spark, [f"u{i}.x@mail{i % 7}.example.org" for i in range(200)], "email")
    there_and_back(spark, [f"+1 (2{i:02d}) 555-0{i:03d}" for i in range(100)] + [f"+4930{i:07d}" for i in range(100)], "phone")

    def card():
        body = "4" + pick("0123456789", 14)
        return next(body + d for d in "0123456789" if luhn(body + d))

    assert all(luhn(p) for p in there_and_back(spark, sorted({card() for _ in range(300)}), "card").values())

    def account(land, n):
        body = pick("0123456789", n)
        return f"{land}{98 - int(body + ''.join(str(ord(c) - 55) for c in land) + '00') % 97:02d}{body}"

    there_and_back(spark, sorted({account("AT", 16) for _ in range(200)} | {account("DE", 18) for _ in range(200)}), "iban")


def test_a_failed_match_is_tried_shorter(spark):
    near = [("4111 1111 1111 1111 123", "card", " 123"), ("GB82 WEST 1234 5698 7654 32 ABC", "iban", " ABC"), ("4111 1111 1111 1112 123", "", "4111 1111 1111 1112 123")]
    got = pseudonyms.pseudonymise(spark.createDataFrame(near, "text string, want string, tail string"), KEY).collect()
    assert [",".join(p["kind"] for p in r["_private"]) for r in got] == [w for _, w, _ in near]
    assert all(r["text"].endswith(r["tail"]) for r in got) and got[0]["text"][:19] != "4111 1111 1111 1111"


def test_clashing_columns_stay(odd, empty):  # noqa: F811
    assert set(odd.columns) >= {"_values", "_typed", "_renamed", "_private"}
    made = pseudonyms.pseudonymise(odd, KEY)
    assert made.columns == [*odd.columns, "_private_"]
    same = lambda df: sorted(map(repr, df.select(odd.columns).collect()))
    assert same(made) == same(odd) and made.count() == len(ODD)
    assert pseudonyms.pseudonymise(odd, KEY, private_col=None).columns == odd.columns and pseudonyms.pseudonymise(empty, KEY).count() == 0


def test_the_secret_is_not_in_the_plan(spark):
    df = pseudonyms.pseudonymise(spark.createDataFrame([("a@b.cd",)], "text string"), "my own secret")
    assert "my own secret" not in df._jdf.queryExecution().toString()
