"""Operator 9, personal data: format-preserving Feistel pseudonyms in native expressions.

Personal values are found by one pattern, validated by kind, and permuted under a key within their
format: a card stays a Luhn-valid card of its length and first digit, an account number keeps its
country and valid check digits, an address has four octets, a social number stays assignable, a
date stays a date of its notation, a phone number keeps its punctuation and country code. Equal
values (of equal kind) get equal pseudonyms in every document; different ones stay different, since a
Feistel network over the product of two residue rings is a permutation. Access keys keep their type and are
permuted among strings of letters and digits. Mail addresses and secrets, which have no format of fixed size, get keyed digests in their form. What fails validation stays.

Everything is DataFrame expressions; no Python runs on executors. Null texts stay null (n_values
0); texts of any length are handled whole; repeated rows alike; other columns pass unchanged, and
those named n_values or kinds are replaced; an empty table gives no rows.
"""

from __future__ import annotations

import warnings

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .store import fresh

#: Key for tests and experiments, used (with a warning) where neither a call nor the session's setting KEY_SETTING gives one.
KEY = "change-this-key"
KEY_SETTING = "spark.nodeweave.pii.key"
ROUNDS = 10

# Formats of personal data. Each starts where no letter or digit precedes (START).
START = r"(?<![\p{L}\p{N}_])"
MAIL = r"(?<![.%+-])[\p{L}\p{N}._%+-]{1,64}+@(?:[\p{L}\p{N}-]{1,63}\.){1,8}\p{L}{2,24}"
SECRET = r"(?i:password|passwd|pwd|token|secret|api[_-]?key|access[_-]?key)\s{0,3}[=:]\s{0,3}[\"']?[^\s\"'|,;]{8,}+"
ACCESS_KEY = r"A[KS]IA[0-9A-Z]{16}(?![\p{L}\p{N}])"
ACCOUNT = r"[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![\p{L}\p{N}])"
ADDRESS = r"(?<!\.)(?:(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)\.){3}(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)(?!\d|\.\d)"
DATE = r"(?<![.\-/])(?:\d{4}-\d{2}-\d{2}|\d{1,2}\.\d{1,2}\.\d{4}|\d{1,2}/\d{1,2}/\d{4})(?!\d|[.\-/]\d)"
SOCIAL = r"(?<!-)\d{3}-\d{2}-\d{4}(?!\d|-\d)"
PHONE = r"(?:\+\d{1,3}[ .-]?(?:\(\d{1,4}\)|\d{1,4})(?:[ .-]?\d{2,4}){2,4}|\(\d{2,4}\)[ .-]?\d{3,4}[ .-]?\d{3,4}|\d{3}[ .-]\d{3}[ .-]\d{4})(?!\d)"
CARD = r"\d(?:[ -]?\d){12,18}(?!\d)"
WORDS = (("mail", MAIL), ("secret", SECRET), ("access_key", ACCESS_KEY), ("account", ACCOUNT))
NUMBERS = (("address", ADDRESS), ("date", DATE), ("social", SOCIAL), ("phone", PHONE), ("card", CARD))
KINDS = WORDS + NUMBERS
#: One scan: the boundary is tested once for all kinds, and number formats only before digits.
PATTERN = START + "(?:" + "|".join(p for _, p in WORDS) + r"|(?=[\d+(])(?:" + "|".join(p for _, p in NUMBERS) + "))"
#: Put around a found value; a text's own first character of it is escaped.
MARK, ESCAPED = "\u0001m", "\u0001e"
#: Day 0 and number of days of the dates that are permuted among all years.
FIRST_DAY, DAY_ROOT = "1900-01-01", 270


def let(value: Column, then) -> Column:
    """``then(value)`` with the value computed and planned once."""
    return F.transform(F.array(value), then)[0]


def _keyed(key: str, kind: str, *parts: Column) -> Column:
    """A pseudo-random number of 60 bits."""
    text = F.concat_ws("|", F.lit(key), F.lit(kind), *[p.cast("string") for p in parts])
    return F.conv(F.substring(F.sha2(text, 256), 1, 15), 16, 10).cast("bigint")


def feistel(left: Column, right: Column, a: Column, b: Column, kind: str, key: str) -> Column:
    """Permutation of Z_a x Z_b: struct(l, r). Halves change in turn by a keyed sum, so any a and b will do."""

    def turn(pair: Column, i: Column) -> Column:
        odd = i % 2 == 1
        l, r = pair["l"], pair["r"]
        return F.struct(
            F.when(odd, F.pmod(l + _keyed(key, kind, i, r) % a, a)).otherwise(l).alias("l"),
            F.when(odd, r).otherwise(F.pmod(r + _keyed(key, kind, i, l) % b, b)).alias("r"),
        )

    start = F.struct(left.cast("bigint").alias("l"), right.cast("bigint").alias("r"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), start, turn)


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, r"[^0-9]", "")


def _power(n: Column) -> Column:
    return F.rpad(F.lit("1"), n.cast("int") + 1, "0").cast("bigint")


def _permuted_digits(digits: Column, kind: str, key: str) -> Column:
    """A digit string of 2 to 30 digits, permuted among those of its length."""
    return let(digits, lambda d: _permuted(d, kind, key))


def _permuted(digits: Column, kind: str, key: str) -> Column:
    n = F.length(digits)
    h = F.floor(n / 2).cast("int")
    kind_n = F.concat(F.lit(kind), n.cast("string"))
    a, b = _power(h), _power(n - h)
    l, r = F.substr(digits, F.lit(1), h).cast("bigint"), F.substr(digits, h + 1).cast("bigint")

    def turn(pair: Column, i: Column) -> Column:
        odd = i % 2 == 1
        return F.struct(
            F.when(odd, F.pmod(pair["l"] + _keyed(key, kind, kind_n, i, pair["r"]) % a, a)).otherwise(pair["l"]).alias("l"),
            F.when(odd, pair["r"]).otherwise(F.pmod(pair["r"] + _keyed(key, kind, kind_n, i, pair["l"]) % b, b)).alias("r"),
        )

    got = F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), F.struct(l.alias("l"), r.alias("r")), turn)
    return F.concat(F.lpad(got["l"].cast("string"), h, "0"), F.lpad(got["r"].cast("string"), n - h, "0"))


def _refill(template: Column, digits: Column) -> Column:
    """The template with its digits replaced, in order, by these."""

    def put(acc: Column, c: Column) -> Column:
        is_digit = c.rlike("^[0-9]$")
        return F.struct(F.concat(acc["s"], F.when(is_digit, F.substr(digits, acc["i"], F.lit(1))).otherwise(c)).alias("s"), (acc["i"] + is_digit.cast("int")).alias("i"))

    return F.aggregate(F.split(template, ""), F.struct(F.lit("").alias("s"), F.lit(1).alias("i")), put)["s"]


def luhn_sum(digits: Column, odd_doubled: bool) -> Column:
    """Luhn sum from the right; ``odd_doubled``: the rightmost digit is doubled (a check digit is to follow)."""

    def part(c: Column, i: Column) -> Column:
        d = c.cast("int")
        twice = (i % 2 == 0) if odd_doubled else (i % 2 == 1)
        return F.when(twice, F.when(d > 4, d * 2 - 9).otherwise(d * 2)).otherwise(d)

    return F.aggregate(F.transform(F.split(F.reverse(digits), ""), part), F.lit(0), lambda s, x: s + x)


def _card(value: Column, key: str) -> Column:
    def valid(d: Column) -> Column:
        body = F.concat(F.substring(d, 1, 1), _permuted_digits(F.substr(d, F.lit(2), F.length(d) - 2), "card", key))
        full = let(body, lambda b: F.concat(b, F.pmod(10 - luhn_sum(b, True) % 10, F.lit(10)).cast("string")))
        return F.when(F.length(d).between(13, 19) & (luhn_sum(d, False) % 10 == 0), full)

    new = let(_digits(value), valid)
    return let(new, lambda n: F.when(n.isNotNull(), _refill(value, n)).otherwise(value))


def _mod97(text: Column) -> Column:
    """Remainder of the number that letters (A = 10) and digits spell."""

    def step(acc: Column, c: Column) -> Column:
        letter = c.rlike("^[A-Z]$")
        return F.when(letter, (acc * 100 + F.ascii(c) - 55) % 97).otherwise((acc * 10 + F.ascii(c) - 48) % 97)

    return F.aggregate(F.split(text, ""), F.lit(0), step)


def _account(value: Column, key: str) -> Column:
    def valid(plain: Column) -> Column:
        country, body = F.substring(plain, 1, 2), F.substr(plain, F.lit(5))
        ok = F.length(plain).between(15, 34) & (_mod97(F.concat(body, F.substring(plain, 1, 4))) == 1)
        new = F.when(F.length(_digits(body)) >= 2, _refill(body, _permuted_digits(_digits(body), "account", key))).otherwise(body)
        packed = let(new, lambda n: F.concat(country, F.lpad((98 - _mod97(F.concat(n, country, F.lit("00")))).cast("string"), 2, "0"), n))
        return F.when(ok, packed)

    def spaced(packed: Column) -> Column:  # spaces return to their places
        step = lambda acc, c: F.struct(F.concat(acc["s"], F.when(c == " ", c).otherwise(F.substr(packed, acc["i"], F.lit(1)))).alias("s"), (acc["i"] + (c != " ").cast("int")).alias("i"))
        woven = F.aggregate(F.split(value, ""), F.struct(F.lit("").alias("s"), F.lit(1).alias("i")), step)["s"]
        return F.when(packed.isNotNull(), woven).otherwise(value)

    return let(let(F.replace(value, F.lit(" "), F.lit("")), valid), spaced)


def _address(value: Column, key: str) -> Column:
    root = F.lit(65536).cast("bigint")
    octets = F.transform(F.split(value, r"\."), lambda x: x.cast("bigint"))
    got = let(octets, lambda o: feistel(o[0] * 256 + o[1], o[2] * 256 + o[3], root, root, "address", key))
    spelled = lambda g: F.concat_ws(".", *[x.cast("string") for x in (F.shiftright(g["l"], 8), g["l"] % 256, F.shiftright(g["r"], 8), g["r"] % 256)])
    return let(got, spelled)


def _social(value: Column, key: str) -> Column:
    area, group, serial = (F.substring(value, *x).cast("bigint") for x in ((1, 3), (5, 2), (8, 4)))
    ok = area.between(1, 899) & (area != 666) & (group > 0) & (serial > 0)
    place = F.when(area > 666, area - 2).otherwise(area - 1)
    got = feistel(place * 99 + group - 1, serial - 1, F.lit(898 * 99).cast("bigint"), F.lit(9999).cast("bigint"), "social", key)

    def spelled(g: Column) -> Column:
        p = F.floor(g["l"] / 99)
        new_area = F.when(p >= 665, p + 2).otherwise(p + 1)
        return F.concat_ws("-", F.lpad(new_area.cast("string"), 3, "0"), F.lpad((g["l"] % 99 + 1).cast("string"), 2, "0"), F.lpad((g["r"] + 1).cast("string"), 4, "0"))

    return F.when(ok, let(got, spelled)).otherwise(value)


def _moved(there: Column, key: str) -> Column:
    """A date permuted among all of 1900 to 2099, or among its year's days where it lies outside."""
    first, root = F.lit(FIRST_DAY).cast("date"), F.lit(DAY_ROOT).cast("bigint")
    index = F.datediff(there, first).cast("bigint")
    back = lambda g: F.date_add(first, (g["l"] * DAY_ROOT + g["r"]).cast("int"))
    near = let(feistel(F.floor(index / DAY_ROOT), index % DAY_ROOT, root, root, "date", key), back)
    begin = F.trunc(there, "year")
    # 365 = 73 x 5 and 366 = 61 x 6
    leap = F.dayofyear(F.date_add(F.add_months(begin, 12), -1)) == 366
    wide, narrow = F.when(leap, F.lit(61)).otherwise(F.lit(73)).cast("bigint"), F.when(leap, F.lit(6)).otherwise(F.lit(5)).cast("bigint")
    at = F.datediff(there, begin).cast("bigint")
    same = let(feistel(F.floor(at / narrow), at % narrow, wide, narrow, "day", key), lambda g: F.date_add(begin, (g["l"] * narrow + g["r"]).cast("int")))
    return F.when(index.between(0, DAY_ROOT * DAY_ROOT - 1), near).otherwise(same)


def _date(value: Column, key: str) -> Column:
    iso, dotted = value.contains("-"), value.contains(".")

    def parse(p: Column) -> Column:
        """Year, month, day and the notation: y-m-d, d.m.y, m/d/y, or d/m/y where the first can't be a month."""
        a, b, c = p[0].cast("int"), p[1].cast("int"), p[2].cast("int")
        parts = lambda y, m, d, how: F.struct(y.alias("y"), m.alias("m"), d.alias("d"), F.lit(how).alias("how"), (F.length(p[0]) == 1).alias("one"), (F.length(p[1]) == 1).alias("two"))
        return F.when(iso, parts(a, b, c, "ymd")).when(dotted, parts(c, b, a, "d.m")).when(a <= 12, parts(c, a, b, "m/d")).otherwise(parts(c, b, a, "d/m"))

    pad = lambda x, n: F.lpad(x.cast("string"), n, "0")
    short = lambda x, brief: F.when(brief & (x < 10), x.cast("string")).otherwise(pad(x, 2))

    def spell(q: Column, new: Column) -> Column:
        y, m, d = pad(F.year(new), 4), F.month(new), F.dayofmonth(new)
        day_first, month_first = (short(d, q["one"]), short(m, q["two"])), (short(m, q["one"]), short(d, q["two"]))
        return F.when(q["how"] == "ymd", F.concat_ws("-", y, pad(m, 2), pad(d, 2))).when(q["how"] == "d.m", F.concat_ws(".", *day_first, y)).when(q["how"] == "m/d", F.concat_ws("/", *month_first, y)).otherwise(F.concat_ws("/", *day_first, y))

    def move(q: Column) -> Column:
        there = F.try_to_timestamp(F.concat_ws("-", pad(q["y"], 4), pad(q["m"], 2), pad(q["d"], 2)), F.lit("yyyy-MM-dd")).cast("date")
        return let(there, lambda t: F.when(t.isNotNull(), let(_moved(t, key), lambda new: spell(q, new))).otherwise(value))

    return let(let(F.split(value, r"[-./]"), parse), move)


def _phone(value: Column, key: str) -> Column:
    kept = F.length(_digits(F.regexp_extract(value, r"^\+\d{1,3}(?=[ .(-])", 0)))

    def move(d: Column) -> Column:
        body = F.substr(d, kept + 1)
        ok = F.length(d).between(7, 15) & (F.length(body) >= 4)
        return F.when(ok, _refill(value, F.concat(F.substr(d, F.lit(1), kept), _permuted_digits(body, "phone", key)))).otherwise(value)

    return let(_digits(value), move)


def _mail(value: Column, key: str) -> Column:
    return F.concat(F.lit("u"), F.substring(F.sha2(F.concat_ws("|", F.lit(key), F.lit("mail"), F.lower(value)), 256), 1, 20), F.lit("@mail.invalid"))


def _secret(value: Column, key: str) -> Column:
    head = F.regexp_extract(value, r"^(?i:[a-z_-]+)\s*[=:]\s*[\"']?", 0)
    tail = F.substr(value, F.length(head) + 1)
    return F.concat(head, F.substring(F.sha2(F.concat_ws("|", F.lit(key), F.lit("secret"), tail), 256), 1, 40))


def _access_key(value: Column, key: str) -> Column:
    """The four letters of its type, then 16 letters and digits permuted among all such."""
    root = F.lit(36**8).cast("bigint")
    number = lambda start: F.conv(F.substring(value, start, 8), 36, 10).cast("bigint")
    spelled = lambda g: F.concat(F.substring(value, 1, 4), *[F.lpad(F.conv(g[x].cast("string"), 10, 36), 8, "0") for x in ("l", "r")])
    return let(feistel(number(5), number(13), root, root, "access", key), spelled)


def kind_of(value: Column) -> Column:
    """The kind whose format a found value has, in the order of KINDS."""
    out = F.lit(None).cast("string")
    for name, pattern in reversed(KINDS):
        out = F.when(value.rlike(f"^(?:{pattern})$"), F.lit(name)).otherwise(out)
    return out


def pseudonym(value: Column, kind: Column, key: str = KEY) -> Column:
    """The pseudonym of a found value of this kind; itself where validation fails."""
    makers = {"mail": _mail, "secret": _secret, "access_key": _access_key, "address": _address, "date": _date, "social": _social, "account": _account, "phone": _phone, "card": _card}
    out = value
    for name, make in makers.items():
        out = F.when(kind == name, make(value, key)).otherwise(out)
    return out


def session_key(spark: SparkSession) -> str:
    """The key that the session's configuration names; the test key, with a warning, where it names none."""
    key = spark.conf.get(KEY_SETTING, None)
    if not key:
        warnings.warn(f"pseudonyms use the public test key; set {KEY_SETTING}", stacklevel=2)
    return key or KEY


def pseudonymise(docs: DataFrame, key: str | None = None) -> DataFrame:
    """``docs`` with values in text replaced, n_values (how many were) and kinds (distinct, sorted)."""
    key = session_key(docs.sparkSession) if key is None else key
    rest = [c for c in docs.columns if c.lower() not in ("n_values", "kinds")]
    marks, pieces, parts = (fresh(rest, x) for x in ("__marked", "__pieces", "__parts"))
    quoted = [F.col(f"`{c}`") for c in rest]
    may = F.col("text").rlike("[0-9@=:]|A[KS]IA")
    marked = F.regexp_replace(F.replace(F.col("text"), F.lit("\u0001"), F.lit(ESCAPED)), F.lit(PATTERN), F.lit(f"{MARK}$0{MARK}"))
    # pieces at odd places (from 0) are found values
    cut = docs.select(*quoted, F.when(may, marked).alias(marks))
    cut = cut.select(*quoted, F.when(F.col(marks).contains(MARK), F.split(marks, MARK)).alias(pieces))

    def one(piece: Column, i: Column) -> Column:
        kind = F.when(i % 2 == 1, kind_of(piece))
        return F.struct(piece.alias("old"), F.when(kind.isNotNull(), pseudonym(piece, kind, key)).otherwise(piece).alias("new"), kind.alias("kind"))

    cut = cut.select(*quoted, F.when(F.col(pieces).isNotNull(), F.transform(pieces, one)).alias(parts))
    some = F.col(parts).isNotNull()
    woven = F.replace(F.array_join(F.transform(parts, lambda p: p["new"]), ""), F.lit(ESCAPED), F.lit("\u0001"))
    changed = F.filter(parts, lambda p: p["old"] != p["new"])
    kinds = F.array_sort(F.array_distinct(F.transform(changed, lambda p: p["kind"])))
    text = F.when(some, woven).otherwise(F.col("text"))
    out = [text.alias(c) if c.lower() == "text" else F.col(f"`{c}`") for c in rest]
    return cut.select(*out, F.when(some, F.size(changed)).otherwise(F.lit(0)).alias("n_values"), F.when(some, kinds).otherwise(F.array().cast("array<string>")).alias("kinds"))


def op9_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents with pseudonyms in place of personal values."""
    return pseudonymise(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
