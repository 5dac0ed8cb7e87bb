"""Private values replaced by keyed pseudonyms of the same format. SQL functions only, no shuffle.

A match is cut into characters, octets or a number and sent through an alternating Feistel network whose round
function is SHA-512 of key, kind, round and the other half. Each symbol moves within its own class: digits stay
digits, small letters stay small letters. Checksums are recomputed. Dates and 3-2-4 numbers are numbered inside
what their format allows and permuted there. Where a permutation could leave a printed form that is set apart
from another one, it is applied again until the form is met (cycle walking). So equal values get equal pseudonyms
in all documents, different ones differ, a pseudonym is of its value's kind, and the key's holder can go back.
"""

from __future__ import annotations

import hashlib
import hmac

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name

# Values that a number with separators does not run into.
_OTHER = r"(?![0-9]{1,3}(?:\.[0-9]{1,3}){3}(?![0-9]|\.[0-9])|[0-9]{4}-[0-9]{2}-[0-9]{2}(?![0-9])|[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])|(?:0[1-9]|1[0-2])/[0-9]{2}(?![0-9]))"
# Formats of private data, sought in this order at each place.
PATTERNS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+@[A-Za-z0-9-]{1,63}(?:\.[A-Za-z0-9-]{1,63}){1,8}",
    "access_key": r"(?<![A-Za-z0-9])(?:AKIA|ASIA)[0-9A-Z]{16}(?![A-Za-z0-9])",
    "secret": r"(?<![A-Za-z0-9])(?i:password|passwd|pwd|secret|token|api[_-]?key) {0,2}[=:] {0,2}[\"']?[A-Za-z0-9_+/-]{8,}+",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:[A-Z0-9]{11,30}|(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?)(?![A-Za-z0-9])",
    "ip": r"(?<![0-9.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?![0-9]|\.[0-9])",
    "date": r"(?<![0-9./-])(?:[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{2}[./][0-9]{2}[./][0-9]{4})(?![0-9]|[./-][0-9])",
    "phone": r"(?<![0-9+])(?:\+[0-9]{1,3}[ .-]?\(?[0-9]{1,4}\)?(?:(?:[ .-]" + _OTHER + r")?[0-9]{2,4}){1,4}|\([0-9]{3}\) ?[0-9]{3}-[0-9]{4}|[0-9]{3}-[0-9]{3}-[0-9]{4})(?![0-9])",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "card": r"(?<![0-9])[0-9](?:(?:[ -]" + _OTHER + r")?[0-9]){12,18}(?![0-9])",
}
#: A text without any of these characters holds no value of any format; most texts end here.
HINT = "[0-9@=:]"
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())

ROUNDS = 8
#: The calendar from 0001-01-01 to 9999-12-31 has 51 x 101 x 709 days; dates are permuted within windows of 101 x 709.
FIRST_DAY, DATE_A, DATE_B = "0001-01-01", 101, 709
#: First parts of a 3-2-4 number (001 to 899 without 666), and second times third ones, none of them zero.
SSN_A, SSN_B = 898, 99 * 9999
#: Cycle walking ends after so many steps; at most two in five values need one more each time, so about 1 in 10^25 is not done.
WALK = 64


def _let(value: Column, then) -> Column:
    """then(value) with value computed once, also inside a lambda."""
    return F.element_at(F.transform(F.array(value), then), 1)


def _digest(key: str, kind: str, step: Column, rest: Column) -> Column:
    """The round function. What stands in the plan is a key of this kind alone, from which the caller's does not follow."""
    derived = hmac.new(key.encode(), kind.encode(), hashlib.sha256).hexdigest()
    return F.sha2(F.concat_ws("|", F.lit(derived), step.cast("string"), rest).cast("binary"), 512)


def _byte(digest: Column, i: Column) -> Column:
    return F.conv(F.substring(digest, (i % 64) * 2 + 1, F.lit(2)), 16, 10).cast("int")


def _steps(back: bool, rounds: int = ROUNDS) -> Column:
    return F.sequence(F.lit(rounds), F.lit(1)) if back else F.sequence(F.lit(1), F.lit(rounds))


def _moved(symbol: Column, by: Column, alphabets: tuple[str, ...]) -> Column:
    """symbol, by places further in the alphabet that has it."""
    whole = "".join(alphabets)
    starts = [len("".join(alphabets[:i])) for i in range(len(alphabets))]

    def place(at: Column) -> Column:
        out = symbol
        for start, a in zip(reversed(starts), reversed(alphabets), strict=True):
            inside = (at > start) & (at <= start + len(a))
            out = F.when(inside, F.substring(F.lit(whole), F.lit(start + 1) + F.pmod(at - (start + 1) + by, F.lit(len(a))), F.lit(1))).otherwise(out)
        return out

    return _let(F.instr(F.lit(whole), symbol), place)


def _feistel(symbols: Column, key: str, kind: str, move, back: bool) -> Column:
    """An array of symbols through ROUNDS rounds; an even number, so the halves end where they began."""
    sign = -1 if back else 1

    def step(acc: Column, i: Column) -> Column:
        keeps, moves = (acc["a"], acc["b"]) if back else (acc["b"], acc["a"])
        stream = _digest(key, kind, i, F.array_join(keeps.cast("array<string>"), ","))
        done = _let(stream, lambda d: F.transform(moves, lambda s, j: move(s, _byte(d, j) * sign)))
        return F.struct(done.alias("a"), keeps.alias("b")) if back else F.struct(keeps.alias("a"), done.alias("b"))

    def run(all_: Column) -> Column:
        half = F.floor(F.size(all_) / 2).cast("int")
        start = F.struct(F.slice(all_, F.lit(1), half).alias("a"), F.slice(all_, half + 1, F.size(all_)).alias("b"))
        return F.aggregate(_steps(back), start, step, lambda acc: F.concat(acc["a"], acc["b"]))

    return _let(symbols, run)


def _permute_number(number: Column, a_size: int, b_size: int, key: str, kind: str, back: bool) -> Column:
    """A number below a_size * b_size moved among such numbers: its two parts move by turns, each by a hash of the other."""
    noise = lambda i, rest, side: F.conv(F.substring(_digest(key, f"{kind} {side}", i, rest.cast("string")), 1, 12), 16, 10).cast("long")
    sign = -1 if back else 1

    def step(acc: Column, i: Column) -> Column:
        move_a = lambda a, b: F.pmod(a + noise(i, b, "a") * sign, F.lit(a_size)).cast("long")
        move_b = lambda a, b: F.pmod(b + noise(i, a, "b") * sign, F.lit(b_size)).cast("long")
        if back:
            return _let(move_b(acc["a"], acc["b"]), lambda b: F.struct(move_a(acc["a"], b).alias("a"), b.alias("b")))
        return _let(move_a(acc["a"], acc["b"]), lambda a: F.struct(a.alias("a"), move_b(a, acc["b"]).alias("b")))

    start = F.struct(F.floor(number / b_size).cast("long").alias("a"), F.pmod(number, F.lit(b_size)).cast("long").alias("b"))
    return F.aggregate(_steps(back, ROUNDS // 2), start, step, lambda acc: acc["a"] * b_size + acc["b"])


def _walked(value: Column, permute, ok) -> Column:
    """permute(value), again until ok: a permutation of the values that are ok."""
    return F.aggregate(F.sequence(F.lit(2), F.lit(WALK)), permute(value), lambda acc, _: F.when(ok(acc), acc).otherwise(permute(acc)))


DIGITS, SMALL, LARGE, HEX = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789abcdef"


def _chars(text: Column) -> Column:
    return F.filter(F.split(text, ""), lambda c: c != "")


def permute_text(text: Column, key: str, kind: str, alphabets: tuple[str, ...] = (DIGITS, SMALL, LARGE), back: bool = False) -> Column:
    """text with every letter and digit moved within its class; other characters stay."""
    return F.array_join(_feistel(_chars(text), key, kind, lambda s, by: _moved(s, by, alphabets), back), "")


def _digits(text: Column) -> Column:
    return F.regexp_replace(text, "[^0-9]", "")


def _luhn_sum(digits: Column) -> Column:
    """Sum over digits as if a check digit followed the last one."""

    def over(d: Column) -> Column:
        def add(acc: Column, i: Column) -> Column:
            twice = F.substring(d, i, F.lit(1)).cast("int") * F.when((F.length(d) - i) % 2 == 0, 2).otherwise(1)
            return acc + F.floor(twice / 10).cast("int") + twice % 10

        return F.aggregate(F.sequence(F.lit(1), F.length(d)), F.lit(0), add)

    return _let(digits, over)


def luhn_valid(text: Column) -> Column:
    return _let(_digits(text), lambda d: (_luhn_sum(F.substring(d, F.lit(1), F.length(d) - 1)) + F.substring(d, -1, 1).cast("int")) % 10 == 0)


def _laid_out(template: Column, letters: Column) -> Column:
    """letters in the places of the template's letters and digits."""
    place = lambda i: F.length(F.regexp_replace(F.substring(template, F.lit(1), i + 1), "[^A-Za-z0-9]", ""))
    put = lambda line: F.transform(_chars(template), lambda c, i: F.when(c.rlike("[A-Za-z0-9]"), F.substring(line, place(i), F.lit(1))).otherwise(c))
    return F.array_join(_let(letters, put), "")


def _mod97(text: Column) -> Column:
    def add(acc: Column, c: Column) -> Column:
        v = F.instr(F.lit(LARGE), c)
        return F.when(v > 0, (acc * 100 + v + 9) % 97).otherwise((acc * 10 + c.cast("int")) % 97)

    return F.aggregate(_chars(text), F.lit(0), add)


def _flat(text: Column) -> Column:
    return F.replace(text, F.lit(" "), F.lit(""))


def iban_valid(text: Column) -> Column:
    """Check digits are 02 to 98: others would name an account a second time."""
    proper = lambda f: F.length(f).between(15, 34) & F.substring(f, 3, 2).between("02", "98") & (_mod97(F.concat(F.substring(f, F.lit(5), F.lit(40)), F.substring(f, 1, 4))) == 1)
    return _let(_flat(text), proper)


def _iban(text: Column, key: str, back: bool) -> Column:
    land = F.substring(text, 1, 2)

    def whole(body: Column) -> Column:
        check = F.lpad((F.lit(98) - _mod97(F.concat(body, land, F.lit("00")))).cast("string"), 2, "0")
        return F.concat(land, check, body)

    return _laid_out(text, _let(permute_text(F.substring(_flat(text), F.lit(5), F.lit(40)), key, "iban", back=back), whole))


def _card(text: Column, key: str, back: bool) -> Column:
    """The first digit, of the network, stays; the last is the check digit of the others."""
    body = lambda d: F.concat(F.substring(d, 1, 1), permute_text(F.substring(d, F.lit(2), F.length(d) - 2), key, "card", (DIGITS,), back))
    checked = lambda b: F.concat(b, ((F.lit(10) - _luhn_sum(b) % 10) % 10).cast("string"))
    return _laid_out(text, _let(_let(_digits(text), body), checked))


def _octets(text: Column) -> Column:
    return F.split(text, r"\.").cast("array<int>")


def _ip(text: Column, key: str, back: bool) -> Column:
    return F.array_join(_feistel(_octets(text), key, "ip", lambda o, by: F.pmod(o + by, F.lit(256)), back).cast("array<string>"), ".")


def _ssn(text: Column, key: str, back: bool) -> Column:
    part = lambda a, n: F.substring(text, a, n).cast("long")
    first = part(1, 3) - F.when(part(1, 3) > 666, 2).otherwise(1)
    number = first * SSN_B + (part(5, 2) - 1) * 9999 + part(8, 4) - 1

    def printed(n: Column) -> Column:
        pad = lambda v, width: F.lpad(v.cast("string"), width, "0")
        a, rest = F.floor(n / SSN_B).cast("long"), F.pmod(n, F.lit(SSN_B))
        return F.concat_ws("-", pad(a + F.when(a >= 665, 2).otherwise(1), 3), pad(F.floor(rest / 9999).cast("long") + 1, 2), pad(rest % 9999 + 1, 4))

    return _let(_permute_number(number, SSN_A, SSN_B, key, "ssn", back), printed)


def _month_first(text: Column) -> Column:
    """Whether a date with slashes can only be read with the month first."""
    return text.contains("/") & (F.substring(text, 4, 2).cast("int") > 12)


def _day(text: Column) -> Column:
    """Days from FIRST_DAY to the date, null if there is no such day in the calendar."""
    year, front, middle = F.substring(text, 7, 4), F.substring(text, 1, 2), F.substring(text, 4, 2)
    iso = F.when(text.rlike("^[0-9]{4}-"), text).when(_month_first(text), F.concat_ws("-", year, front, middle)).otherwise(F.concat_ws("-", year, middle, front))
    day = F.datediff(iso.try_cast("date"), F.lit(FIRST_DAY).cast("date"))
    return F.when(day >= 0, day)


def _date(text: Column, key: str, back: bool) -> Column:
    """Dates in the form that only reads month first are permuted among themselves: their days are above 12."""
    size = DATE_A * DATE_B
    date_of = lambda day: F.date_add(F.lit(FIRST_DAY).cast("date"), day.cast("int"))
    moved = lambda day: F.floor(day / size).cast("long") * size + _permute_number(F.pmod(day, F.lit(size)), DATE_A, DATE_B, key, "date", back)
    day = _day(text).cast("long")
    return (
        F.when(text.rlike("^[0-9]{4}-"), F.date_format(date_of(moved(day)), "yyyy-MM-dd")).when(text.contains("."), F.date_format(date_of(moved(day)), "dd.MM.yyyy"))
        .when(_month_first(text), F.date_format(date_of(_walked(day, moved, lambda d: F.dayofmonth(date_of(d)) > 12)), "MM/dd/yyyy"))
        .otherwise(F.date_format(date_of(moved(day)), "dd/MM/yyyy"))
    )


def _after(text: Column, head: str, permute) -> Column:
    """text with all but its head (a pattern with one group) permuted."""
    return _let(F.regexp_extract(text, head, 1), lambda kept: F.concat(kept, permute(F.substring(text, F.length(kept) + 1, F.length(text)))))


def _secret(body: Column, key: str, back: bool) -> Column:
    """Digits and a-f stay such; others never become such."""
    plain = lambda s: permute_text(s, key, "secret", back=back)
    return F.when(body.rlike("^[0-9a-f]+$"), permute_text(body, key, "hex", (HEX,), back)).otherwise(_walked(body, plain, lambda s: ~s.rlike("^[0-9a-f]+$")))


def kind_of(value: Column) -> Column:
    """The kind of a matched value, null if its checksum, range or calendar rules it out."""
    is_ = lambda kind: value.rlike(f"^(?:{PATTERNS[kind]})$")
    digits = F.length(_digits(value))
    return (
        F.when(is_("email"), "email").when(is_("access_key"), "access_key").when(is_("secret"), "secret")
        .when(is_("iban") & iban_valid(value), "iban")
        .when(is_("ip"), F.when(F.forall(_octets(value), lambda o: o < 256), "ip"))
        .when(is_("date"), F.when(_day(value).isNotNull(), "date"))
        .when(is_("phone") & digits.between(8, 15), "phone")
        .when(is_("ssn"), F.when(~value.rlike("^(?:000|666|9)|-00-|-0000$"), "ssn"))
        .when(is_("card") & luhn_valid(value), "card")
    )


def pseudonym(value: Column, kind: Column, key: str, back: bool = False) -> Column:
    """value's pseudonym, or with ``back`` the value of a pseudonym."""
    text = lambda label: lambda s: permute_text(s, key, label, back=back)
    return (
        F.when(kind == "email", permute_text(value, key, "email", back=back))
        .when(kind == "access_key", _after(value, "^(.{4})", text("access_key")))
        .when(kind == "secret", _after(value, r"^([A-Za-z_-]+ {0,2}[=:] {0,2}[\"']?)", lambda s: _secret(s, key, back)))
        .when(kind == "iban", _iban(value, key, back))
        .when(kind == "ip", _ip(value, key, back))
        .when(kind == "date", _date(value, key, back))
        .when(kind == "phone", _after(value, r"^((?:\+1(?![0-9])|\+[0-9]{1,3}(?=[ .(-]))?)", text("phone")))
        .when(kind == "ssn", _ssn(value, key, back))
        .when(kind == "card", _card(value, key, back))
        .otherwise(value)
    )


def _typed(value: Column) -> Column:
    """(kind, value, rest) of a match. One that fails its validation as a whole is cut at its separators, from the
    right, until what is left of the cut is valid; the rest stays as it is."""
    whole = lambda kind: F.struct(kind.alias("kind"), value.alias("value"), F.lit("").alias("rest"))
    cuts = F.filter(F.sequence(F.length(value) - 1, F.lit(1)), lambda i: F.substring(value, i + 1, F.lit(1)).isin(" ", "-", "."))
    heads = F.transform(cuts, lambda i: _let(F.substring(value, F.lit(1), i), lambda v: F.struct(kind_of(v).alias("kind"), v.alias("value"), F.substring(value, i + 1, F.length(value)).alias("rest"))))
    valid = F.get(F.filter(heads, lambda h: h["kind"].isNotNull()), F.lit(0))
    return _let(kind_of(value), lambda kind: F.when(kind.isNull() & (F.length(value) > 1), F.coalesce(valid, whole(kind))).otherwise(whole(kind)))


def pseudonymise(docs: DataFrame, key: str, text_col: str = "text", private_col: str | None = "_private") -> DataFrame:
    """docs with private values in ``text_col`` replaced, and a column ``private_col``: an array of (kind, value as
    printed now) per document, empty where nothing was found; None adds no column, and a name that docs has gets
    underscores until it is free. A null text stays null and an empty one empty; all other columns and rows are
    untouched, repeated ones too. Values that fail their validation stay as they are.

    The plan holds keys of 64 hex digits derived from ``key``, one a kind; ``spark.sql.redaction.string.regex`` set to
    ``[0-9a-f]{64}`` keeps them out of printed plans and event logs."""
    values, typed, renamed = (free_name(docs, name) for name in ("_values", "_typed", "_renamed"))
    text = F.col(text_col)
    found = F.when(text.rlike(HINT), F.regexp_extract_all(text, F.lit(ANY), F.lit(0)))
    changed = F.transform(F.col(typed), lambda t: F.struct(t["kind"].alias("kind"), pseudonym(t["value"], t["kind"], key).alias("value"), t["rest"].alias("rest")))
    gaps = F.split(text, ANY, -1)
    woven = F.array_join(F.flatten(F.zip_with(gaps, F.col(renamed), lambda g, m: F.array(g, F.coalesce(m["value"], F.lit("")), F.coalesce(m["rest"], F.lit(""))))), "")
    made = docs.withColumn(values, found).withColumn(typed, F.transform(F.col(values), _typed)).withColumn(renamed, changed)
    made = made.withColumn(text_col, F.when(F.size(values) > 0, woven).otherwise(text))
    if private_col is not None:
        kept = F.transform(F.filter(F.col(renamed), lambda r: r["kind"].isNotNull()), lambda r: F.struct(r["kind"].alias("kind"), r["value"].alias("value")))
        made = made.withColumn(free_name(docs, private_col), F.coalesce(kept, F.array().cast("array<struct<kind:string,value:string>>")))
    return made.drop(values, typed, renamed)
