"""Format-preserving Feistel pseudonyms for personal numbers, dates and mail names; DataFrame functions only.

Each kind of value is found by a pattern, validated, and mapped to an index pair (l, r) in a domain
of exactly a * b values. A keyed Feistel network of alternating rounds, l := l + F(r) mod a and
r := r + F(l) mod b, permutes that domain, so equal values stay equal in all documents, different
ones stay different, and no table is kept. The permuted pair is written in the format of the found
text: digits go where digits were, separators stay, check digits are computed anew.

    card      13-19 digits that pass the Luhn check: all but the last permuted, check digit renewed
    iban      valid by modulus 97: its account digits permuted, check digits renewed
    ssn       ddd-dd-dddd in the issued ranges, permuted within them
    ip        four octets up to 255, permuted as 32 bits
    date      yyyy-mm-dd or dd.mm.yyyy, dd/mm/yyyy of a real day of 1900-2099, permuted among those days
    phone     + or ( and 7-15 digits, or ddd-ddd-dddd: all digits (after + all but the first) permuted
    email     letters and digits of the name before the @, permuted in base 36 by runs of 22

Defined cases: null text stays null, empty text stays empty; a candidate that fails validation stays
as it is; a pseudonym may by chance equal its value (once in the size of the domain); other columns pass.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Patterns of the candidates, in the order in which they are tried.
PATTERNS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9][A-Za-z0-9._%+-]{0,63}@(?:[A-Za-z0-9-]{1,63}\.){1,8}[A-Za-z]{2,24}",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "ip": r"(?<![\w.])\d{1,3}(?:\.\d{1,3}){3}(?![\w]|\.\d)",
    "date": r"(?<![\w./-])(?:\d{4}-\d{2}-\d{2}|\d{2}([./])\d{2}\1\d{4})(?![\w]|[./-]\d)",
    "ssn": r"(?<![\w-])\d{3}-\d{2}-\d{4}(?![\w]|-\d)",
    "card": r"(?<![\w])\d(?:[ -]?\d){12,18}(?![\w])",
    "phone": r"(?<![\w+])(?:\+\d{1,3}[ .-]?(?:\(\d{1,4}\)[ .-]?)?\d{2,4}(?:[ .-]?\d{2,4}){1,4}|\(\d{2,4}\)[ .-]?\d{3,4}[ .-]?\d{3,4}|\d{3}-\d{3}-\d{4})(?![\w])",
}
ANY = "|".join(f"(?:{p.replace(chr(92) + '1', chr(92) + 'k<sep>').replace('([./])', '(?<sep>[./])')})" for p in PATTERNS.values())
FIRST_DAY, DAYS = "1900-01-01", 73049


@dataclass(frozen=True)
class Settings:
    key: str = "change-this-key"
    rounds: int = 8


def _round_value(s: Settings, tweak: str, turn: Column, half: Column) -> Column:
    digest = F.sha2(F.concat_ws("|", F.lit(s.key), F.lit(tweak), turn.cast("string"), half.cast("string")), 256)
    return F.conv(F.substring(digest, 1, 15), 16, 10).cast("long")


def feistel(left: Column, right: Column, a: Column, b: Column, tweak: str, s: Settings) -> Column:
    """The permuted pair (l, r) of [0, a) x [0, b)."""
    start = F.struct(left.cast("long").alias("l"), right.cast("long").alias("r"))

    def step(pair: Column, turn: Column) -> Column:
        even = turn % 2 == 0
        low = F.when(even, (pair["l"] + _round_value(s, tweak, turn, pair["r"]) % a) % a).otherwise(pair["l"])
        high = F.when(even, pair["r"]).otherwise((pair["r"] + _round_value(s, tweak, turn, pair["l"]) % b) % b)
        return F.struct(low.cast("long").alias("l"), high.cast("long").alias("r"))

    return F.aggregate(F.sequence(F.lit(0), F.lit(s.rounds - 1)), start, step)


def _padded(value: Column, width: Column, base: int = 10) -> Column:
    text = value.cast("string") if base == 10 else F.lower(F.conv(value.cast("string"), 10, base))
    return F.when(width > 0, F.lpad(text, width, "0")).otherwise(F.lit(""))


def _power(base: int, n: Column) -> Column:
    return F.aggregate(F.sequence(F.lit(0), n), F.lit(1).cast("long"), lambda v, i: F.when(i < n, v * base).otherwise(v))


def _permuted_digits(digits: Column, tweak: str, s: Settings, base: int = 10) -> Column:
    """A string of digits of a base, permuted among the strings of its length (up to 36 decimal or 22 base-36 digits)."""
    n = F.length(digits)
    head = F.floor(n / 2).cast("int")
    tail = n - head

    def number(part: Column) -> Column:
        part = F.when(part == "", F.lit("0")).otherwise(part)
        return part.cast("long") if base == 10 else F.conv(part, base, 10).cast("long")

    left, right = number(digits.substr(F.lit(1), head)), number(digits.substr(head + 1, tail))
    pair = feistel(left, right, _power(base, head), _power(base, tail), tweak, s)
    return F.transform(F.array(pair), lambda p: F.concat(_padded(p["l"], head, base), _padded(p["r"], tail, base)))[0]


def _filled(shape: Column, signs: Column, kind: str) -> Column:
    """The shape with its k-th character of a class replaced by the k-th of the signs."""
    def put(c: Column, i: Column) -> Column:
        k = F.length(F.regexp_replace(shape.substr(F.lit(1), i + 1), f"[^{kind}]", ""))
        return F.when(c.rlike(f"^[{kind}]$"), signs.substr(k, F.lit(1))).otherwise(c)

    return F.array_join(F.transform(F.split(shape, ""), put), "")


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _luhn_sum(digits: Column) -> Column:
    """The Luhn sum, the last digit undoubled."""
    def add(total: Column, i: Column) -> Column:
        d = digits.substr(F.length(digits) - i, F.lit(1)).cast("int")
        twice = d * 2
        return total + F.when(i % 2 == 0, d).otherwise(F.when(twice > 9, twice - 9).otherwise(twice))

    return F.aggregate(F.sequence(F.lit(0), F.length(digits) - 1), F.lit(0), add)


def _card(value: Column, s: Settings) -> Column:
    digits = _digits(value)
    body = _permuted_digits(digits.substr(F.lit(1), F.length(digits) - 1), "card", s)
    check = F.transform(F.array(body), lambda x: F.concat(x, ((10 - _luhn_sum(F.concat(x, F.lit("0"))) % 10) % 10).cast("string")))[0]
    return F.when(_luhn_sum(digits) % 10 == 0, _filled(value, check, "0-9")).otherwise(value)


def _mod97(text: Column) -> Column:
    def step(rest: Column, c: Column) -> Column:
        letter = c.rlike("[A-Z]")
        return F.when(letter, (rest * 100 + F.ascii(c) - 55) % 97).otherwise((rest * 10 + c.cast("int")) % 97)

    return F.aggregate(F.split(text, ""), F.lit(0), step)


def _iban(value: Column, s: Settings) -> Column:
    flat = F.regexp_replace(value, " ", "")
    country, account = flat.substr(F.lit(1), F.lit(2)), flat.substr(F.lit(5), F.length(flat))
    valid = _mod97(F.concat(account, country, flat.substr(F.lit(3), F.lit(2)))) == 1
    fresh = _filled(account, _permuted_digits(_digits(account), "iban", s), "0-9")
    made = F.transform(F.array(fresh), lambda x: F.concat(country, F.lpad((98 - _mod97(F.concat(x, country, F.lit("00")))).cast("string"), 2, "0"), x))[0]
    return F.when(valid, _filled(value, made, "A-Z0-9")).otherwise(value)


def _ip(value: Column, s: Settings) -> Column:
    o = F.transform(F.split(value, r"\."), lambda x: x.cast("int"))
    pair = feistel(o[0] * 256 + o[1], o[2] * 256 + o[3], F.lit(65536), F.lit(65536), "ip", s)
    made = F.transform(F.array(pair), lambda p: F.concat_ws(".", F.floor(p["l"] / 256), p["l"] % 256, F.floor(p["r"] / 256), p["r"] % 256))[0]
    return F.when(F.forall(o, lambda x: x <= 255), made).otherwise(value)


def _ssn(value: Column, s: Settings) -> Column:
    p = F.transform(F.split(value, "-"), lambda x: x.cast("int"))
    valid = (p[0] >= 1) & (p[0] <= 899) & (p[0] != 666) & (p[1] >= 1) & (p[2] >= 1)
    area = F.when(p[0] > 666, p[0] - 2).otherwise(p[0] - 1)
    pair = feistel(area, (p[1] - 1) * 9999 + p[2] - 1, F.lit(898), F.lit(99 * 9999), "ssn", s)

    def write(x: Column) -> Column:
        first = F.when(x["l"] >= 665, x["l"] + 2).otherwise(x["l"] + 1)
        return F.concat_ws("-", F.lpad(first.cast("string"), 3, "0"), F.lpad((F.floor(x["r"] / 9999) + 1).cast("string"), 2, "0"), F.lpad((x["r"] % 9999 + 1).cast("string"), 4, "0"))

    return F.when(valid, F.transform(F.array(pair), write)[0]).otherwise(value)


def _date(value: Column, s: Settings) -> Column:
    iso = value.rlike(r"^\d{4}-")
    sign = value.substr(F.lit(3), F.lit(1))
    text = F.when(iso, value).otherwise(F.concat_ws("-", value.substr(F.lit(7), F.lit(4)), value.substr(F.lit(4), F.lit(2)), value.substr(F.lit(1), F.lit(2))))
    day = F.datediff(F.try_to_date(text, "yyyy-MM-dd"), F.lit(FIRST_DAY).cast("date"))
    # 73049 = 229 * 319
    pair = feistel(F.floor(day / 319), day % 319, F.lit(229), F.lit(319), "date", s)

    def write(p: Column) -> Column:
        made = F.date_add(F.lit(FIRST_DAY).cast("date"), (p["l"] * 319 + p["r"]).cast("int"))
        return F.when(iso, F.date_format(made, "yyyy-MM-dd")).otherwise(F.concat(F.date_format(made, "dd"), sign, F.date_format(made, "MM"), sign, F.date_format(made, "yyyy")))

    return F.when(day.between(0, DAYS - 1), F.transform(F.array(pair), write)[0]).otherwise(value)


def _phone(value: Column, s: Settings) -> Column:
    digits = _digits(value)
    kept = F.when(value.startswith("+"), F.lit(1)).otherwise(F.lit(0))
    body = _permuted_digits(digits.substr(kept + 1, F.length(digits)), "phone", s)
    return F.when(F.length(digits).between(7, 15), _filled(value, F.concat(digits.substr(F.lit(1), kept), body), "0-9")).otherwise(value)


def _email(value: Column, s: Settings) -> Column:
    at = F.instr(value, "@")
    name = value.substr(F.lit(1), at - 1)
    flat = F.lower(F.regexp_replace(name, "[^A-Za-z0-9]", ""))
    runs = F.sequence(F.lit(0), F.floor((F.length(flat) - 1) / 22).cast("int"))
    made = F.array_join(F.transform(runs, lambda k: _permuted_digits(flat.substr(k * 22 + 1, F.lit(22)), "email", s, 36)), "")
    return F.concat(_filled(name, made, "A-Za-z0-9"), value.substr(at, F.length(value)))


HANDLERS: dict[str, Callable[[Column, Settings], Column]] = {"email": _email, "iban": _iban, "ip": _ip, "date": _date, "ssn": _ssn, "card": _card, "phone": _phone}


def pseudonym(value: Column, s: Settings = Settings()) -> Column:
    """One found value, rewritten by the first kind whose pattern it is."""
    out = None
    for kind, handler in HANDLERS.items():
        is_kind = value.rlike(f"^(?:{PATTERNS[kind]})$")
        out = F.when(is_kind, handler(value, s)) if out is None else out.when(is_kind, handler(value, s))
    return out.otherwise(value)


def rewrite(docs: DataFrame, column: str = "text", settings: Settings = Settings()) -> DataFrame:
    """The documents with the text rewritten; __found and __changed (arrays of values and of pseudonyms) come on top."""
    text = F.col(column)
    found = F.regexp_extract_all(text, F.lit(ANY), F.lit(0))
    out = docs.withColumn("__found", F.when(text.rlike(ANY), found).otherwise(F.array().cast("array<string>")))
    out = out.withColumn("__changed", F.transform("__found", lambda v: pseudonym(v, settings)))
    between = F.split(text, ANY, -1)
    joined = F.array_join(F.transform(between, lambda piece, i: F.concat(piece, F.coalesce(F.get("__changed", i), F.lit("")))), "")
    return out.withColumn(column, F.when(F.size("__found") > 0, joined).otherwise(text))


def pseudonymise(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:
    """One row per document: doc_id, text, n_found, n_changed."""
    rows = rewrite(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), "text", settings)
    changed = F.size(F.filter(F.arrays_zip("__found", "__changed"), lambda p: p["__found"] != p["__changed"]))
    return rows.select("doc_id", "text", F.coalesce(F.size("__found"), F.lit(0)).alias("n_found"), F.coalesce(changed, F.lit(0)).alias("n_changed"))
