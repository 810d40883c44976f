"""The inverted index from values to types, and what it saves: one join per level in place of one per cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def hashed(values: DataFrame) -> DataFrame:
    return values.withColumn("value_hash", F.xxhash64("value"))


def extend(index: DataFrame | None, values: DataFrame, new_types: DataFrame, key: str = "seed_cluster") -> DataFrame:
    """Add to (value_hash, value, label) all values of a key with all its new labels."""
    more = hashed(values.select(key, "value").distinct()).join(new_types.select(key, "label"), key).select("value_hash", "value", "label")
    return (more if index is None else index.select("value_hash", "value", "label").union(more)).distinct()


def lookup(index: DataFrame, values: DataFrame, key: str = "seed_cluster") -> DataFrame:
    """(key, label): the labels of any of a key's values; the value decides where hashes meet."""
    return hashed(values.select(key, "value").distinct()).join(index, ["value_hash", "value"]).select(key, "label").distinct()


def fallback(types: DataFrame, kinds: DataFrame, found: DataFrame, key: str = "seed_cluster") -> DataFrame:
    """(key, label): for keys without a hit, the known labels of their kind."""
    return kinds.join(found.select(key).distinct(), key, "left_anti").join(types.select("kind", "label").distinct(), "kind").select(key, "label")


def edges(rows: DataFrame, key: str, by: list[str]) -> DataFrame:
    """(key, e1, e2, n_values): the different sets of keys that hold a value together, each with its members.

    A set is known by two hashes of its members, made by aggregates that combine before the shuffle; a
    value that very many keys hold makes one set with a row for each key, and no row of pairs.
    """
    held = rows.select(key, *by).distinct()
    sets = held.groupBy(*by).agg(F.bit_xor(F.xxhash64(key)).alias("e1"), F.bit_xor(F.xxhash64(F.lit(1), key)).alias("e2"), F.count("*").alias("c")).where("c > 1").drop("c")
    return held.join(sets, by).groupBy(key, "e1", "e2").agg(F.count("*").alias("n_values"))


def column_sets(values: DataFrame) -> DataFrame:
    """(column_id, kind, value, len, n): the values of each column, those of one length that the same columns hold taken together.

    ``value`` names the set of columns, by two hashes of its members as in ``edges``, and stands for each of the ``n``
    values, which no other column holds: whatever asks which columns have a value in common gets the same answer.
    Values go by 128 bits of hash, so no text is shuffled, and once.
    """
    held = values.select("column_id", "kind", "len", F.xxhash64("value").alias("h1"), F.xxhash64(F.lit(1), "value").alias("h2"))
    together = W.partitionBy("h1", "h2")
    named = held.withColumn("e1", F.bit_xor(F.xxhash64("column_id")).over(together)).withColumn("e2", F.bit_xor(F.xxhash64(F.lit(1), "column_id")).over(together))
    counted = named.groupBy("column_id", "kind", "len", "e1", "e2").agg(F.count("*").alias("n"))
    return counted.select("column_id", "kind", F.concat_ws("_", "e1", "e2").alias("value"), "len", "n")


def sharing(values: DataFrame, key: str = "seed_cluster") -> DataFrame:
    """(a, b): keys with a common value. Values held by the same keys count once: pairs are made from the distinct sets of keys."""
    return pairs_of_sets(values.select(F.col(key).alias("k"), "value"), "k", ["value"]).where("a <> b")


def pairs_of_sets(rows: DataFrame, key: str, by: list[str]) -> DataFrame:
    """(a, b): all ordered pairs of keys that meet under some value of ``by``."""
    held = edges(rows, key, by)
    return held.select("e1", "e2", F.col(key).alias("a")).join(held.select("e1", "e2", F.col(key).alias("b")), ["e1", "e2"]).select("a", "b").distinct()
