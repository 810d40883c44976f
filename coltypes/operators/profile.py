"""Column catalog statistics and distinct values of all columns in one long relation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _distinct() -> Column:
    """Different values, told apart by 128 bits of hash, so that no text is shuffled."""
    return F.countDistinct(F.xxhash64("value"), F.xxhash64(F.lit(1), "value"))


def catalog(columns: DataFrame, cells: DataFrame) -> DataFrame:
    """Catalog rows with n_cells and n_distinct; columns without a cell have zeros."""
    stats = cells.groupBy("column_id").agg(F.count("*").alias("n_cells"), _distinct().alias("n_distinct"))
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    return columns.select("column_id", "table_id", "header", "ordinal", "kind").join(stats, "column_id", "left").select("column_id", "table_id", "header", "ordinal", "kind", zero("n_cells"), zero("n_distinct"))


def column_values(cells: DataFrame) -> DataFrame:
    """(column_id, kind, value, n, len): distinct values, counted before they are shuffled."""
    return cells.groupBy("column_id", "kind", "value").agg(F.count("*").alias("n")).withColumn("len", F.length("value"))


def moments(cells: DataFrame) -> DataFrame:
    """(column_id, n, mean, deviation, lo, hi) of numeric columns."""
    return cells.where("kind = 'num'").groupBy("column_id").agg(F.count("num").alias("n"), F.avg("num").alias("mean"), F.stddev_pop("num").alias("deviation"), F.min("num").alias("lo"), F.max("num").alias("hi"))


def distinct_counts(cells: DataFrame) -> DataFrame:
    """Exact and sketched numbers of distinct values; the sketch is what scales and merges."""
    return cells.groupBy("column_id").agg(_distinct().alias("n_distinct"), F.hll_sketch_estimate(F.hll_sketch_agg("value")).alias("n_sketched"))


def lengths(values: DataFrame) -> DataFrame:
    """(column_id, len, n_values): the length strata of each column."""
    return values.groupBy("column_id", "len").agg(F.count("*").alias("n_values"))
