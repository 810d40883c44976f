"""Vectors of headers, of text columns (mean over distinct values) and of numeric columns (z-score histograms)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.functions.encoders import Encoder, NgramEncoder, encode
from coltypes.functions.exprs import header_norm
from coltypes.operators.profile import moments


def headers(columns: DataFrame, encoder: Encoder | None = None) -> DataFrame:
    """(header_key, vec): one row per distinct normalised header."""
    distinct = columns.select(header_norm(F.col("header")).alias("header_key")).distinct()
    return distinct.withColumn("vec", encode(F.col("header_key"), encoder))


def text_columns(values: DataFrame, encoder: Encoder | None = None) -> DataFrame:
    """(column_id, vec): the mean vector of the distinct values of text columns.

    Values are dealt by value, so a task meets equal values of several columns together and encodes
    them once; sums per column leave the task, not vectors per value.
    """
    encoder = encoder or NgramEncoder()

    def sums(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total: dict[str, np.ndarray] = {}
        count: dict[str, int] = {}
        for batch in batches:
            at, texts = pd.factorize(batch["value"])
            vectors = encoder.encode(list(texts))
            for column, group in pd.Series(at).groupby(batch["column_id"].to_numpy()):
                total[column] = total.get(column, 0) + vectors[group.to_numpy()].sum(axis=0)
                count[column] = count.get(column, 0) + len(group)
            if len(total) > 20_000:
                yield pd.DataFrame({"column_id": list(total), "vec": list(total.values()), "n": list(count.values())})
                total, count = {}, {}
        if total:
            yield pd.DataFrame({"column_id": list(total), "vec": list(total.values()), "n": list(count.values())})

    parts = values.where("kind = 'text'").select("column_id", "value").repartition("value").mapInPandas(sums, "column_id string, vec array<double>, n long")
    wide = parts.select("column_id", "n", F.posexplode("vec").alias("pos", "x"))
    means = wide.groupBy("column_id", "pos").agg((F.sum("x") / F.sum("n")).alias("x"))
    return dense(means, "x")


def dense(parts: DataFrame, value: str) -> DataFrame:
    """(column_id, vec) from (column_id, pos, value) with all positions there."""
    pairs = parts.groupBy("column_id").agg(F.array_sort(F.collect_list(F.struct("pos", value))).alias("p"))
    return pairs.select("column_id", F.transform("p", lambda x: x[value]).alias("vec"))


def zscore_bins(cells: DataFrame, bins: int = 100, reach: float = 4.0, minmax: bool = False) -> DataFrame:
    """(column_id, bin, density): a column's share of cells in each bin of its z-scores.

    A fixed range [-reach, reach] clamps outliers to the end bins; minmax takes the column's own
    range. A constant column has z = 0 everywhere.
    """
    m = moments(cells)
    x = cells.where("kind = 'num'").select("column_id", "num").join(F.broadcast(m), "column_id")
    if minmax:
        share = F.when(F.col("hi") > F.col("lo"), F.round((F.col("num") - F.col("lo")) / (F.col("hi") - F.col("lo")), 9)).otherwise(F.lit(0.0))
    else:
        z = F.when(F.col("deviation") > 0, F.round((F.col("num") - F.col("mean")) / F.col("deviation"), 9)).otherwise(F.lit(0.0))
        share = (z + reach) / (2 * reach)
    place = F.greatest(F.lit(0), F.least(F.lit(bins - 1), F.floor(share * bins))).cast("int")
    counted = x.groupBy("column_id", place.alias("bin"), "n").agg(F.count("*").alias("c"))
    return counted.select("column_id", "bin", (F.col("c") / F.col("n")).alias("density"))


def histograms(cells: DataFrame, bins: int = 100, **how) -> DataFrame:
    """(column_id, vec): dense histogram vectors."""
    held = zscore_bins(cells, bins, **how).groupBy("column_id").agg(F.map_from_entries(F.collect_list(F.struct("bin", "density"))).alias("m"))
    return held.select("column_id", F.transform(F.sequence(F.lit(0), F.lit(bins - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0))).alias("vec"))
