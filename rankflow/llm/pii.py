"""Pseudonyms for personal data by a Feistel network within the format.

Matches are validated (Luhn, ISO 7064, calendar, area numbers), turned into a
list of digits with a radix each, permuted under a key by a Feistel network over
the two halves of the list, and put back into the format they had.  Check digits
are computed anew, so a pseudonym is as valid as what it stands for; equal
values get equal pseudonyms in all documents, and :func:`reveal` undoes it.

Everything happens within a row, in built-in expressions: no shuffle.  The amounts
that the network shifts by are message authentication codes (HMAC-SHA256).  The key
is a local table of one row, so that no plan, event log or user interface shows it.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rankflow.llm.common import let, packed, require, unpacked

ROUNDS = 8
#: Days from 1900-01-01 to 2099-12-31, as a product of two radices.
DAYS = (17, 4297)
FIRST_DAY = "1900-01-01"

#: Fixed formats, in the order in which they are tried.
FORMATS = {
    "email": r"[A-Za-z0-9][A-Za-z0-9._%+-]*@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,}",
    "iban": r"[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?",
    "ip": r"(?:25[0-5]|2[0-4][0-9]|1[0-9]{2}|[1-9]?[0-9])(?:\.(?:25[0-5]|2[0-4][0-9]|1[0-9]{2}|[1-9]?[0-9])){3}",
    "date": r"(?:19|20)[0-9]{2}[-/](?:0[1-9]|1[0-2])[-/](?:0[1-9]|[12][0-9]|3[01])|(?:0[1-9]|[12][0-9]|3[01])\.(?:0[1-9]|1[0-2])\.(?:19|20)[0-9]{2}|(?:0[1-9]|1[0-2])/(?:0[1-9]|[12][0-9]|3[01])/(?:19|20)[0-9]{2}",
    "ssn": r"(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}",
    "card": r"[2-6](?:[ -]?[0-9]){12,18}",
    "phone": r"(?:\+?1[ .-]?)?(?:\([2-9][0-9]{2}\) ?|[2-9][0-9]{2}[ .-])[2-9][0-9]{2}[ .-][0-9]{4}",
}
PATTERN = r"(?<![\w.+@])(?:" + "|".join(FORMATS.values()) + r")(?![\w@]|\.[0-9])"
STATE = "struct<l:array<int>,r:array<int>>"


def _digits(s: Column) -> Column:
    return F.transform(F.regexp_extract_all(s, F.lit("[0-9]"), F.lit(0)), lambda c: c.cast("int"))


def _luhn(d: Column) -> Column:
    """The check digit that belongs after the digits."""
    n = F.size(d)
    double = lambda x: x * 2 - F.when(x > 4, 9).otherwise(0)
    each = F.transform(d, lambda x, i: F.when((n - i) % 2 == 1, double(x)).otherwise(x))
    return (10 - F.aggregate(each, F.lit(0), lambda a, x: a + x) % 10) % 10


def _mod97(s: Column) -> Column:
    """The letters and digits as one number, a letter as two digits, modulo 97."""
    value = lambda c: F.when(F.ascii(c) < 58, F.ascii(c) - 48).otherwise(F.ascii(c) - 55)
    return F.aggregate(F.split(s, ""), F.lit(0), lambda a, c: (a * F.when(F.ascii(c) < 58, 10).otherwise(100) + value(c)) % 97)


def _base(c: Column) -> Column:
    return F.when(F.ascii(c) < 58, 48).when(F.ascii(c) < 91, 65).otherwise(97)


def _chars(s: Column, among: str) -> Column:
    return F.regexp_extract_all(s, F.lit(among), F.lit(0))


def _fill(s: Column, among: str, chars: Column) -> Column:
    """``s`` with the characters of the class replaced, one by one."""
    return F.array_join(F.zip_with(F.split(s, among, -1), F.concat(chars, F.array(F.lit(""))), lambda a, b: F.concat(a, b)), "")


def _key_table(spark: SparkSession, key: str) -> DataFrame:
    """``inner, outer``: the two pads of the key, as a local relation, whose values plans don't show."""
    raw = key.encode()
    raw = (hashlib.sha256(raw).digest() if len(raw) > 64 else raw).ljust(64, b"\0")
    pads = [bytes(x ^ pad for x in raw) for pad in (0x36, 0x5C)]
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway
    values = gateway.new_array(jvm.java.lang.Object, 2)
    values[0], values[1] = pads
    rows = jvm.java.util.ArrayList()
    rows.add(jvm.org.apache.spark.sql.RowFactory.create(values))
    schema = jvm.org.apache.spark.sql.types.StructType.fromDDL("inner binary not null, outer binary not null")
    return DataFrame(spark._jsparkSession.createDataFrame(rows, schema), spark)


def _code(message: Column) -> Column:
    """The message authentication code, in hexadecimal digits."""
    own = F.unhex(F.sha2(F.concat(F.col("inner"), message.cast("binary")), 256))
    return F.sha2(F.concat(F.col("outer"), own), 256)


def _feistel(values: Column, radices: Column, kind: Column, undo: bool) -> Column:
    """The list permuted: in turn, each half is shifted by amounts that depend on the other."""
    half = F.floor(F.size(values) / 2).cast("int")
    rest = F.size(values) - half
    left, right = F.slice(radices, F.lit(1), half), F.slice(radices, half + 1, rest)

    def shifted(x: Column, radix: Column, other: Column, k: Column) -> Column:
        seed = F.concat_ws("|", kind, k.cast("string"), F.array_join(other.cast("array<string>"), ","))

        def one(v: Column, i: Column) -> Column:
            amount = F.conv(F.substring(_code(F.concat_ws("|", seed, i.cast("string"))), 1, 12), 16, 10).cast("bigint")
            return F.pmod(v - amount if undo else v + amount, radix[i]).cast("int")

        return F.transform(x, one)

    def step(s: Column, k: Column) -> Column:
        even = F.struct(shifted(s["l"], left, s["r"], k).alias("l"), s["r"].alias("r"))
        odd = F.struct(s["l"].alias("l"), shifted(s["r"], right, s["l"], k).alias("r"))
        return F.when(k % 2 == 0, even.cast(STATE)).otherwise(odd.cast(STATE))

    order = [F.lit(k) for k in (reversed(range(ROUNDS)) if undo else range(ROUNDS))]
    start = F.struct(F.slice(values, F.lit(1), half).alias("l"), F.slice(values, half + 1, rest).alias("r")).cast(STATE)
    return F.aggregate(F.array(*order), start, step, lambda s: F.concat(s["l"], s["r"]))


def kind_of(s: Column) -> Column:
    """The format that a match has, with its check passed; null where the check fails."""
    out = F.lit(None).cast("string")
    valid = {
        "iban": _mod97(F.concat(F.substring(_plain(s), F.lit(5), F.char_length(s)), F.substring(s, 1, 4))) == 1,
        "date": _day(s).isNotNull(),
        "card": let(_digits(s), lambda d: _luhn(F.slice(d, F.lit(1), F.size(d) - 1)) == F.element_at(d, -1)),
    }
    for name, pattern in reversed(FORMATS.items()):
        out = F.when(s.rlike(f"^(?:{pattern})$"), F.when(valid.get(name, F.lit(True)), F.lit(name))).otherwise(out)
    return out


def _plain(s: Column) -> Column:
    return F.replace(s, F.lit(" "), F.lit(""))


def _day(s: Column) -> Column:
    """Days since :data:`FIRST_DAY`; null if there is no such date."""
    parts = [(r"^(\d{4})[-/](\d\d)[-/](\d\d)$", (1, 2, 3)), (r"^(\d\d)\.(\d\d)\.(\d{4})$", (3, 2, 1)), (r"^(\d\d)/(\d\d)/(\d{4})$", (3, 1, 2))]
    iso = F.lit(None).cast("string")
    for pattern, at in parts:
        iso = F.when(s.rlike(pattern), F.concat_ws("-", *[F.regexp_extract(s, pattern, g) for g in at])).otherwise(iso)
    return F.date_diff(iso.try_cast("date"), F.lit(FIRST_DAY).cast("date"))


def _swap(s: Column, kind: Column, undo: bool) -> Column:
    """The pseudonym of one validated match."""
    turn = lambda v, r: _feistel(v, r, kind, undo)
    text = lambda v: v.cast("array<string>")

    def letters(v: str | Column, among: str) -> Column:
        """The characters of the class, each kept a digit, small or capital letter."""
        c = _chars(v, among)
        values = F.transform(c, lambda x: F.ascii(x) - _base(x))
        radices = F.transform(c, lambda x: F.when(F.ascii(x) < 58, 10).otherwise(26))
        return F.zip_with(let(F.struct(values.alias("v"), radices.alias("r")), lambda t: turn(t["v"], t["r"])), c, lambda n, x: F.char(n + _base(x)))

    local = F.substring_index(s, "@", 1)
    email = F.concat(_fill(local, "[A-Za-z0-9]", letters(local, "[A-Za-z0-9]")), F.substring(s, F.char_length(local) + 1, F.char_length(s)))

    def iban(body: Column) -> Column:
        check = F.lpad((98 - _mod97(F.concat(body, F.substring(s, 1, 2), F.lit("00")))).cast("string"), 2, "0")
        return _fill(s, "[A-Z0-9]", F.split(F.concat(F.substring(s, 1, 2), check, body), ""))

    octets = F.transform(F.split(s, r"\."), lambda x: x.cast("int"))
    ip = F.array_join(text(turn(octets, F.array_repeat(F.lit(256), 4))), ".")

    def date(day: Column) -> Column:
        return let(
            turn(F.array(F.floor(day / DAYS[1]).cast("int"), day % DAYS[1]), F.array(*map(F.lit, DAYS))),
            lambda v: _as_date(F.date_add(F.lit(FIRST_DAY).cast("date"), v[0] * DAYS[1] + v[1]), s),
        )

    area, group, serial = (F.element_at(F.split(s, "-"), k).cast("int") for k in (1, 2, 3))
    ssn = let(
        turn(F.array(area - 1 - F.when(area > 666, 1).otherwise(0), group - 1, serial - 1), F.array(F.lit(898), F.lit(99), F.lit(9999))),
        lambda v: F.concat_ws("-", F.lpad((v[0] + 1 + F.when(v[0] >= 665, 1).otherwise(0)).cast("string"), 3, "0"), F.lpad((v[1] + 1).cast("string"), 2, "0"), F.lpad((v[2] + 1).cast("string"), 4, "0")),
    )

    def card(d: Column) -> Column:
        body = F.concat(F.slice(d, 1, 1), turn(F.slice(d, F.lit(2), F.size(d) - 2), F.array_repeat(F.lit(10), F.size(d) - 2)))
        return let(body, lambda b: _fill(s, "[0-9]", text(F.concat(b, F.array(_luhn(b))))))

    def phone(d: Column) -> Column:
        low = lambda i: F.when(i.isin(0, 3), 2).otherwise(0)
        own = F.transform(F.slice(d, F.size(d) - 9, F.lit(10)), lambda x, i: x - low(i))
        new = F.transform(turn(own, F.array(*[F.lit(8 if i in (0, 3) else 10) for i in range(10)])), lambda x, i: x + low(i))
        return _fill(s, "[0-9]", text(F.concat(F.slice(d, F.lit(1), F.size(d) - 10), new)))

    by = {
        "email": email,
        "iban": let(F.array_join(letters(F.substring(_plain(s), F.lit(5), F.char_length(s)), "[A-Z0-9]"), ""), iban),
        "ip": ip,
        "date": let(_day(s), date),
        "ssn": ssn,
        "card": let(_digits(s), card),
        "phone": let(_digits(s), phone),
    }
    out = s
    for name, made in by.items():
        out = F.when(kind == name, made).otherwise(out)
    return out


def _as_date(day: Column, like: Column) -> Column:
    made = F.date_format(day, "yyyy-MM-dd")
    for test, pattern in ((like.contains("."), "dd.MM.yyyy"), (F.substring(like, 3, 1) == "/", "MM/dd/yyyy"), (F.substring(like, 5, 1) == "/", "yyyy/MM/dd")):
        made = F.when(test, F.date_format(day, pattern)).otherwise(made)
    return made


def _replaced(docs: DataFrame, key: str, text_col: str, undo: bool) -> DataFrame:
    require(docs, [text_col])
    value = F.col(f"row.{text_col}")
    text = F.coalesce(value, F.lit(""))
    matches = F.transform(_chars(text, PATTERN), lambda m: F.struct(m.alias("value"), kind_of(m).alias("kind")))
    rows = packed(docs).withColumn("found", F.when(text.rlike("[0-9@]"), matches).otherwise(F.array().cast("array<struct<value:string,kind:string>>")))
    rows = rows.crossJoin(F.broadcast(_key_table(docs.sparkSession, key)))  # one row
    made = F.transform("found", lambda x: F.when(x["kind"].isNull(), x["value"]).otherwise(_swap(x["value"], x["kind"], undo)))
    joined = F.zip_with(F.split(text, PATTERN, -1), F.concat(made, F.array(F.lit(""))), lambda a, b: F.concat(a, b))
    return unpacked(rows, docs.columns, {
        "pii_kinds": F.array_compact(F.transform("found", lambda x: x["kind"])),
        text_col: F.when(F.size("found") == 0, value).otherwise(F.array_join(joined, "")),
    })


def pseudonymise(docs: DataFrame, key: str, text_col: str = "text") -> DataFrame:
    """``docs`` with every validated match replaced by its pseudonym, and ``pii_kinds`` in order of occurrence.

    What fails its check (a wrong Luhn digit, 30 February) stays as it is.  A null
    text stays null and has no kinds; a column ``pii_kinds`` of the input is replaced.
    """
    return _replaced(docs, key, text_col, undo=False)


def reveal(docs: DataFrame, key: str, text_col: str = "text") -> DataFrame:
    """The inverse of :func:`pseudonymise` under the same key."""
    return _replaced(docs, key, text_col, undo=True)
