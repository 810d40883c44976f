"""Native column expressions; each has an exact counterpart in the SQL that checks it."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Dimension of the hashed n-gram vectors.
BUCKETS = 256
#: Labels too generic to be a semantic type (fixed values).
GENERIC = ("number", "integer", "numeric value", "string", "text", "value", "id", "identifier", "name", "code", "date", "category", "label", "data", "unknown")


def hash32(text: Column) -> Column:
    """The first 32 bits of md5 as a long; the same in any engine."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def header_norm(header: Column) -> Column:
    """Lower case, without a one-letter prefix and without punctuation."""
    return F.regexp_replace(F.regexp_replace(F.lower(header), "^[a-z]_", ""), "[^a-z0-9]", "")


def grams(text: Column) -> Column:
    """All 2- and 3-grams of a text between boundary marks."""
    marked = F.concat(F.lit("^"), text, F.lit("$"))

    def of(n: int) -> Column:
        return F.when(F.length(marked) >= n, F.transform(F.sequence(F.lit(1), F.length(marked) - (n - 1)), lambda i: marked.substr(i, F.lit(n)))).otherwise(F.array().cast("array<string>"))

    return F.concat(of(2), of(3))


def bucket(gram: Column) -> Column:
    return (hash32(gram) % BUCKETS).cast("int")


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two dense arrays; 0 if one has no length."""
    dot = F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    norm = lambda v: F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
    return F.coalesce(F.try_divide(dot, norm(a) * norm(b)), F.lit(0.0))


def joined(values: Column) -> Column:
    """A set as one string, in order."""
    return F.array_join(F.array_sort(F.array_distinct(values)), "|")


def is_generic(label: Column) -> Column:
    return F.lower(F.trim(label)).isin(*GENERIC)
