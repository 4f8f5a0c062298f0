"""Format-preserving pseudonyms of personal numbers, dates and addresses in texts, in Spark expressions alone."""

from __future__ import annotations

import hashlib
import hmac

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh

ROUNDS = 8
DIGITS, LOWER, UPPER, HEX = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789abcdef"
#: Days from 1900-01-01 to the first and the last day of four-digit years.
FIRST_DAY, LAST_DAY = -693595, 2958463
_FREE, _END = "(?<![0-9A-Za-z])", "(?![0-9A-Za-z])"

#: What is looked for, in this order where two start at the same place.
PATTERNS = {
    "secret": f"{_FREE}[0-9A-Fa-f]{{32,}}+{_END}",
    "email": r"(?<![0-9A-Za-z._%+-])[0-9A-Za-z._%+-]{1,64}+@(?:[0-9A-Za-z-]{1,63}\.){1,8}[A-Za-z]{2,24}" + _END,
    "ip": r"(?<![0-9A-Za-z.])(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?![0-9A-Za-z]|\.[0-9])",
    "iso_date": f"{_FREE}[0-9]{{4}}(?:-[0-9]{{1,2}}-|/[0-9]{{1,2}}/)[0-9]{{1,2}}(?:{_END}|(?=T[0-9]))",
    "date": rf"{_FREE}[0-9]{{1,2}}(?:/[0-9]{{1,2}}/|\.[0-9]{{1,2}}\.|-[0-9]{{1,2}}-)[0-9]{{4}}{_END}",
    "ssn": f"{_FREE}[0-9]{{3}}-[0-9]{{2}}-[0-9]{{4}}{_END}",
    "phone": rf"(?<![0-9A-Za-z+])(?:\+?[0-9]{{1,3}}[ .-]?)?(?:\([0-9]{{3}}\) ?|[0-9]{{3}}[ .-])[0-9]{{3}}[ .-][0-9]{{4}}{_END}|(?<![0-9A-Za-z+.,])(?:\+|00)[1-9](?:[ .()/-]{{0,2}}[0-9]){{7,14}}{_END}|(?<![0-9A-Za-z+._/])[0-9]{{10}}(?![0-9A-Za-z]|\.[0-9])",
    "card": f"{_FREE}(?:[0-9]{{13,19}}|[0-9]{{4}}(?: [0-9]{{4}}){{2}} [0-9]{{1,7}}|[0-9]{{4}}(?:-[0-9]{{4}}){{2}}-[0-9]{{1,7}}|[0-9]{{4}}[ -][0-9]{{6}}[ -][0-9]{{5}}){_END}",
}
# Country codes, which E.164 fixes.
COUNTRY = "(?:1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|[0-9]{3})"
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())


def bound(value: Column, use) -> Column:
    """use(value), with value computed once."""
    return F.transform(F.array(value), use)[0]


def secret_key(spark: SparkSession, key: str) -> Column:
    """The key as a scalar subquery over one row, derived from the given one: plans, their displays and event logs show
    neither. It is evaluated once on the driver."""
    derived = hmac.new(key.encode(), b"deltaring pseudonyms", hashlib.sha256).hexdigest()
    return spark.createDataFrame([(derived,)], "pseudonym_key string").scalar()


def keyed_numbers(key: Column, text: Column, n: Column) -> Column:
    """n numbers of 32 bits from a keyed hash of a text: SHA-256 of the key and the SHA-256 of key and text, and a count
    of blocks; each number has eight hexadecimal digits of its own."""
    sha = lambda *c: F.sha2(F.concat_ws("|", *c).cast("binary"), 256)
    block = lambda inner, i: sha(F.lit("out"), key, inner, i.cast("string"))
    blocks = lambda inner: F.array_join(F.transform(F.sequence(F.lit(0), F.shiftright(n - 1, 3)), lambda i: block(inner, i)), "")
    digits = bound(sha(F.lit("in"), key, text), blocks)
    return bound(digits, lambda d: F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.conv(F.substring(d, i * 8 + 1, F.lit(8)), 16, 10).cast("long")))


def feistel(cells: Column, key: Column, tweak: Column) -> Column:
    """Permute an array of struct(v, r), 0 <= v < r, among the arrays with the same r in the same places.

    The cells are dealt to two halves by turns; in each round one half is shifted, cell by cell modulo r, by
    keyed numbers from the other half. Every round can be undone, so different arrays stay different.
    Cells with r = 1 keep their 0.
    """

    def half(which: int) -> Column:
        return F.filter(cells, lambda x, i: i % 2 == which)

    def turn(s: Column, i: Column) -> Column:
        seen = F.concat_ws(",", F.transform(s["b"], lambda x: x["v"].cast("string")))
        text = F.concat_ws("|", tweak, i.cast("string"), F.size(s["a"]).cast("string"), seen)
        shifted = lambda by: F.zip_with(s["a"], by, lambda x, y: F.struct(((x["v"] + y) % x["r"]).cast("long").alias("v"), x["r"].alias("r")))
        none = F.filter(s["a"], lambda x: F.lit(False))
        return F.struct(s["b"].alias("a"), F.when(F.size(s["a"]) == 0, none).otherwise(bound(keyed_numbers(key, text, F.size(s["a"])), shifted)).alias("b"))

    start = F.struct(half(0).alias("a"), half(1).alias("b"))
    done = F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), start, turn)
    return bound(done, lambda s: F.transform(cells, lambda _, i: F.when(i % 2 == 0, F.get(s["a"], F.shiftright(i, 1))["v"]).otherwise(F.get(s["b"], F.shiftright(i, 1))["v"])))


def cell(v: Column, r: Column | int) -> Column:
    return F.struct(v.cast("long").alias("v"), (F.lit(r) if isinstance(r, int) else r).cast("long").alias("r"))


def characters(m: Column, key: Column, kind: str, fixed_from: Column | None = None, alphabets: tuple[str, ...] = (DIGITS, LOWER, UPPER)) -> Column:
    """m with each character permuted in its alphabet; those from fixed_from on and all others stay."""

    def alphabet(c: Column, i: Column) -> Column:
        free = F.lit(True)
        if fixed_from is not None:
            free = free & (i < fixed_from)
        out = F.when(~free, F.lit(""))
        for a in alphabets:
            out = out.when(F.instr(F.lit(a), c) > 0, F.lit(a))
        return out.otherwise(F.lit(""))

    def woven(chars: Column) -> Column:
        sets = F.transform(chars, alphabet)

        def placed(s: Column) -> Column:
            cells = F.zip_with(chars, s, lambda c, a: F.when(a == "", cell(F.lit(0), 1)).otherwise(cell(F.instr(a, c) - 1, F.length(a))))
            new = feistel(cells, key, F.lit(kind))
            return bound(new, lambda v: F.array_join(F.transform(chars, lambda c, i: F.when(F.get(s, i) == "", c).otherwise(F.substring(F.get(s, i), (F.get(v, i) + 1).cast("int"), F.lit(1)))), ""))

        return bound(sets, placed)

    return bound(F.split(m, ""), lambda c: woven(F.filter(c, lambda x: x != "")))


def luhn_sum(digits: Column) -> Column:
    """Luhn sum of a string of digits, the last one counting once."""
    each = F.transform(F.split(F.reverse(digits), ""), lambda c, i: F.when(c == "", 0).when(i % 2 == 0, F.when(c == "", 0).otherwise(c.cast("int"))).otherwise(c.cast("int") * 2 - F.when(c.cast("int") > 4, 9).otherwise(0)))
    return F.aggregate(each, F.lit(0), lambda a, x: a + x)


def set_in(m: Column, digits: Column) -> Column:
    """m with its digits replaced by as many given ones, in order."""
    nth = lambda i: F.length(F.regexp_replace(F.substring(m, F.lit(1), i + 1), "[^0-9]", ""))
    return F.array_join(F.transform(F.filter(F.split(m, ""), lambda x: x != ""), lambda c, i: F.when(c.rlike("[0-9]"), F.substring(digits, nth(i), F.lit(1))).otherwise(c)), "")


def card(m: Column, key: Column) -> Column:
    """Numbers that pass the Luhn test, permuted up to their check digit, which is set anew; others stay.

    Only the digits count, so a number has one pseudonym whether it is written in groups or not.
    """

    def moved(digits: Column) -> Column:
        body = characters(F.substring(digits, F.lit(1), F.length(digits) - 1), key, "card", alphabets=(DIGITS,))
        whole = lambda x: F.concat(x, F.pmod(-luhn_sum(F.concat(x, F.lit("0"))), F.lit(10)).cast("string"))
        return F.when(luhn_sum(digits) % 10 == 0, set_in(m, bound(body, whole))).otherwise(m)

    return bound(F.regexp_replace(m, "[^0-9]", ""), moved)


def phone(m: Column, key: Column) -> Column:
    """The digits after the country code, or else the last ten, permuted, written as they were."""

    def moved(d: Column) -> Column:
        kept = F.when(m.startswith("+"), F.regexp_extract(d, f"^{COUNTRY}", 0)).when(m.startswith("00"), F.regexp_extract(d, f"^00{COUNTRY}", 0)).otherwise(F.substring(d, F.lit(1), F.length(d) - 10))
        return bound(kept, lambda k: set_in(m, F.concat(k, characters(F.substring(d, F.length(k) + 1, F.length(d)), key, "phone", alphabets=(DIGITS,)))))

    return bound(F.regexp_replace(m, "[^0-9]", ""), moved)


def address(m: Column, key: Column) -> Column:
    """Four octets below 256 without leading zeros, permuted as numbers; others stay."""
    parts = F.split(m, r"\.")
    good = F.forall(parts, lambda x: (x.cast("int") < 256) & (F.length(x) == F.length(x.cast("int").cast("string"))))
    new = feistel(F.transform(parts, lambda x: cell(x.cast("int"), 256)), key, F.lit("ip"))
    return F.when(good, F.array_join(F.transform(new, lambda v: v.cast("string")), ".")).otherwise(m)


def social(m: Column, key: Column) -> Column:
    """Numbers of the form area-group-serial with values in use, permuted among those; others stay."""
    part = lambda i, n: F.substring(m, i, n).cast("int")
    area, group, serial = part(1, 3), part(5, 2), part(8, 4)
    good = (area > 0) & (area != 666) & (area < 900) & (group > 0) & (serial > 0)
    place = area - 1 - (area > 666).cast("int")
    new = feistel(F.array(cell(place, 898), cell(group - 1, 99), cell(serial - 1, 9999)), key, F.lit("ssn"))
    out = lambda v: F.concat_ws("-", F.lpad((v[0] + 1 + (v[0] >= 665).cast("int")).cast("string"), 3, "0"), F.lpad((v[1] + 1).cast("string"), 2, "0"), F.lpad((v[2] + 1).cast("string"), 4, "0"))
    return F.when(good, bound(new, out)).otherwise(m)


def day(m: Column, key: Column, iso: bool) -> Column:
    """Dates of the calendar from year 1 to 9999, permuted among the 65,536 days of their window from 1900-01-01 (the
    first and the last window end with the years). Others stay.

    They are read as year, month and day, or as day, month and year, or, where only that is a date, as month, day
    and year, and written so again with their separators, without leading zeros if one part has a single digit.
    """
    parts = F.split(m, "[-/.]")
    n = lambda i: F.get(parts, F.lit(i)).cast("int")

    def valid(year: Column, month: Column, dom: Column) -> Column:
        leap = (year % 4 == 0) & (year % 100 != 0) | (year % 400 == 0)
        longest = F.when(month == 2, F.when(leap, 29).otherwise(28)).when(month.isin(4, 6, 9, 11), 30).otherwise(31)
        return year.between(1, 9999) & month.between(1, 12) & (dom >= 1) & (dom <= longest)

    def moved(at: Column, orders: tuple[int, int, int]) -> Column:
        low = F.floor(at / 65536) * 65536
        first, last = low < FIRST_DAY, low + 65535 > LAST_DAY
        start = F.greatest(low, F.lit(FIRST_DAY))
        rows = F.when(first, 15).when(last, 128).otherwise(256)
        columns = F.when(first, 2549).when(last, 73).otherwise(256)
        place = at - start
        new = feistel(F.array(cell(F.floor(place / columns), rows), cell(place % columns, columns)), key, F.lit("day"))
        back = bound(new, lambda v: F.date_add(F.lit("1900-01-01").cast("date"), (start + v[0] * columns + v[1]).cast("int")))

        def written(d: Column) -> Column:
            padded = F.forall(parts, lambda x: F.length(x) > 1)
            two = lambda x: F.when(padded, F.lpad(x.cast("string"), 2, "0")).otherwise(x.cast("string"))
            of = [F.lpad(F.year(d).cast("string"), 4, "0"), two(F.month(d)), two(F.dayofmonth(d))]
            sep = F.regexp_extract(m, "[-/.]", 0)
            return F.concat(of[orders[0]], sep, of[orders[1]], sep, of[orders[2]])

        return bound(back, written)

    def when(order: tuple[int, int, int]) -> tuple[Column, Column]:
        year, month, dom = (n(order.index(i)) for i in range(3))
        good = valid(year, month, dom)
        since = F.datediff(F.make_date(year, month, dom), F.lit("1900-01-01").cast("date"))
        return good, bound(since.cast("long"), lambda at: moved(at, order))

    out = None
    for order in [(0, 1, 2)] if iso else [(2, 1, 0), (1, 2, 0)]:
        good, new = when(order)
        out = F.when(good, new) if out is None else out.when(good, new)
    return out.otherwise(m)


def secret(m: Column, key: Column) -> Column:
    """A hexadecimal run, permuted as in small letters; where capitals and small letters are mixed, capitals stand
    where they stood."""
    use = lambda x: characters(x, key, "secret", alphabets=(HEX,))
    mixed = m.rlike("[A-F]") & m.rlike("[a-f]")
    cased = lambda new: F.array_join(F.zip_with(F.split(m, ""), F.split(new, ""), lambda c, x: F.when(c.rlike("[A-F]"), F.upper(x)).otherwise(x)), "")
    return F.when(mixed, bound(use(F.lower(m)), cased)).otherwise(in_either_case(m, use))


def in_either_case(m: Column, use) -> Column:
    """use(m), for capitals the capitals of what the small letters give, so that both spellings stay linked."""
    return F.when((m == F.upper(m)) & m.rlike("[A-Z]"), F.upper(use(F.lower(m)))).otherwise(use(m))


def pseudonym(m: Column, key: Column) -> Column:
    """The pseudonym of one match of ANY: the first pattern that the whole match fits decides how."""
    whole = lambda kind: m.rlike(f"^(?:{PATTERNS[kind]})$")
    return (
        F.when(whole("secret"), secret(m, key))
        .when(whole("email"), in_either_case(m, lambda x: characters(x, key, "email", fixed_from=F.instr(x, "@") - 1)))
        .when(whole("ip"), address(m, key))
        .when(whole("iso_date"), day(m, key, True))
        .when(whole("date"), day(m, key, False))
        .when(whole("ssn"), social(m, key))
        .when(whole("phone") & m.rlike(r"^(?:\+|00)"), phone(m, key))
        .when(whole("card"), card(m, key))
        .when(whole("phone"), phone(m, key))
        .otherwise(m)
    )


def pseudonymised(df: DataFrame, key: str, column: str = "text") -> DataFrame:
    """df with the values in `column` replaced and `n_pseudonyms`, how many were changed.

    E-mail addresses (before the @), card numbers that pass their test, telephone numbers (after the
    country code), IPv4 addresses, social security numbers, dates and long hexadecimal secrets keep their
    form and become other values of that form under the key; equal values become equal ones everywhere. What
    fails its test stays. Telephone numbers are those in groups of 3-3-4 digits, those with + or 00 and 8 to 15 digits,
    and ten digits alone; national numbers in other groups stay in clear, and so do dates with month names or
    years of two digits. All other characters stay as they are; a null text stays null with 0.
    """
    text, held = F.col(column), fresh(df, "pseudonym_key")
    found_as = fresh(df, "pseudonym_new")
    df, columns = df.withColumn(held, secret_key(df.sparkSession, key)), df.columns

    def replaced(hits: Column) -> Column:
        new = F.transform(hits, lambda m: pseudonym(m, F.col(held)))

        def joined(v: Column) -> Column:
            pieces = F.transform(F.split(text, ANY, -1), lambda x, i: F.concat(x, F.coalesce(F.get(v, i), F.lit(""))))
            changed = F.size(F.filter(F.zip_with(hits, v, lambda a, b: a != b), lambda x: x))
            return F.struct(F.array_join(pieces, "").alias("text"), changed.alias("n"))

        return bound(new, joined)

    found = F.when(text.rlike("[0-9@]") | text.rlike("[A-Fa-f]{32}"), F.regexp_extract_all(text, F.lit(ANY), 0))
    result = F.transform(F.array(found), lambda h: F.when(F.coalesce(F.size(h) > 0, F.lit(False)), replaced(h)))[0]
    rows, new = df.withColumn(found_as, result), F.col(found_as)
    return rows.select(*[F.coalesce(new["text"], F.col(c)).alias(c) if c == column else F.col(c) for c in columns], F.coalesce(new["n"], F.lit(0)).cast("long").alias("n_pseudonyms"))
