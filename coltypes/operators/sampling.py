"""Samples of values for prompts: by length strata, uniform, by frequency, by value clusters; and dense rows."""

from __future__ import annotations

from functools import reduce

from pyspark.ml import Pipeline
from pyspark.ml.clustering import KMeans
from pyspark.ml.feature import IDF, HashingTF, NGram, RegexTokenizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def _draw(value: Column, seed: int) -> Column:
    return F.md5(F.concat(value, F.lit(f"#{seed}")))


def length_stratified(values: DataFrame, key: str, k: int = 10, allocation: str = "round_robin", seed: int = 0, sizes: DataFrame | None = None) -> DataFrame:
    """(key, value, len): at most k distinct values of each key, spread over string lengths.

    Strata go by size (ties: shorter first); one order, rounds first and strata within a round,
    gives one value of each of the k largest strata when there are more strata than k, and spreads
    the budget over all strata when there are fewer. ``proportional`` gives each stratum one value
    and shares the rest by stratum size, largest remainder first. ``sizes``: (key, len, size) if counted
    before; then ``values`` need only hold the first k of each stratum, see ``strata``.
    """
    distinct = values.select(key, "value").distinct().withColumn("len", F.length("value"))
    stratum = W.partitionBy(key, "len")
    ranked = distinct.withColumn("turn", F.row_number().over(stratum.orderBy(_draw(F.col("value"), seed), "value"))).where(F.col("turn") <= k)
    sizes = distinct.groupBy(key, "len").agg(F.count("*").alias("size")) if sizes is None else sizes
    if allocation == "proportional":
        by_size = W.partitionBy(key).orderBy(F.desc("size"), "len")
        sizes = sizes.withColumn("place", F.row_number().over(by_size)).where(F.col("place") <= k)
        total = W.partitionBy(key)
        spare = F.greatest(F.lit(0), F.lit(k) - F.count("*").over(total))
        exact = spare * (F.col("size") - 1) / F.greatest(F.sum(F.col("size") - 1).over(total), F.lit(1))
        sizes = sizes.withColumn("whole", F.floor(exact)).withColumn("rest", exact - F.floor(exact)).withColumn("spare", spare)
        extra = F.col("spare") - F.sum("whole").over(total)
        order = F.row_number().over(W.partitionBy(key).orderBy(F.desc(F.round("rest", 9)), "len"))
        sizes = sizes.withColumn("quota", 1 + F.col("whole") + F.when(order <= extra, 1).otherwise(0))
        return ranked.join(sizes, [key, "len"]).where(F.col("turn") <= F.col("quota")).select(key, "value", "len")
    order = W.partitionBy(key).orderBy("turn", F.desc("size"), "len")
    return ranked.join(sizes, [key, "len"]).withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).select(key, "value", "len")


def strata(values: DataFrame, k: int = 10, seed: int = 0) -> DataFrame:
    """(column_id, value, len): of distinct values the first k of each column and length in the order in which samples draw.

    The first k of several columns together, of a length or of all lengths, are among these.
    """
    order = W.partitionBy("column_id", "len").orderBy(_draw(F.col("value"), seed), "value")
    return values.select("column_id", "value", "len").withColumn("turn", F.row_number().over(order)).where(F.col("turn") <= k).drop("turn")


def uniform(values: DataFrame, key: str, k: int = 10, seed: int = 0) -> DataFrame:
    """k distinct values of each key, each as likely."""
    order = W.partitionBy(key).orderBy(_draw(F.col("value"), seed), "value")
    return values.select(key, "value").distinct().withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).select(key, "value")


def by_frequency(values: DataFrame, key: str, k: int = 10) -> DataFrame:
    """The k most frequent values of each key."""
    counts = values.groupBy(key, "value").agg(F.sum("n").alias("n"))
    order = W.partitionBy(key).orderBy(F.desc("n"), "value")
    return counts.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).select(key, "value", "n")


def by_value_clusters(values: DataFrame, key: str, k: int = 10, features: int = 1024, seed: int = 7) -> DataFrame:
    """One value near each of k centres of character TF-IDF vectors, for each key: the costly way that length strata replace.

    The vectors of all keys are clustered together; a key takes one value of each of its k largest clusters.
    """
    v = values.select(key, "value").distinct()
    stages = [RegexTokenizer(inputCol="value", outputCol="chars", pattern="", toLowercase=True), NGram(n=2, inputCol="chars", outputCol="grams"), HashingTF(inputCol="grams", outputCol="tf", numFeatures=features), IDF(inputCol="tf", outputCol="tfidf"), KMeans(featuresCol="tfidf", predictionCol="cluster", k=k, seed=seed, maxIter=5)]
    found = Pipeline(stages=stages).fit(v).transform(v).select(key, "value", "cluster")
    one = found.groupBy(key, "cluster").agg(F.count("*").alias("size"), F.min(F.struct(_draw(F.col("value"), seed).alias("d"), "value")).alias("v"))
    order = W.partitionBy(key).orderBy(F.desc("size"), "cluster")
    return one.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k).select(key, F.col("v.value").alias("value"), "cluster")


def dense_rows(df: DataFrame, n: int = 10, seed: int = 0, by: list[str] | None = None, place: str | None = None) -> DataFrame:
    """n rows of a table (of each group) with the most filled cells; equals by a hash of the row. ``place`` names a column for their order.

    For groups, rows are counted by filled cells and the begin of their hash first; only those that can be
    among the n are sorted, so wide rows of a large table are neither sorted nor shuffled.
    """
    filled = sum((F.when(F.col(c).isNotNull(), 1).otherwise(0) for c in df.columns), F.lit(0))
    draw = F.md5(F.concat_ws("|", *[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in df.columns], F.lit(str(seed))))
    if not by:
        return df.orderBy(filled.desc(), draw).limit(n)
    begin = F.substring(draw, 1, 3)
    counts = df.select(*by, filled.alias("__filled"), begin.alias("__begin")).groupBy(*by, "__filled", "__begin").agg(F.count("*").alias("__n"))
    so_far = F.sum("__n").over(W.partitionBy(*by).orderBy(F.desc("__filled"), "__begin"))
    last = counts.withColumn("__before", so_far - F.col("__n")).where(F.col("__before") < n)
    last = last.groupBy(*by).agg(F.max(F.struct((-F.col("__filled")).alias("f"), F.col("__begin").alias("b"))).alias("__last"))
    same = reduce(Column.__and__, [F.col(c).eqNullSafe(F.col(f"__by_{c}")) for c in by])
    able = df.join(F.broadcast(last.withColumnsRenamed({c: f"__by_{c}" for c in by})), same).where(F.struct((-filled).alias("f"), begin.alias("b")) <= F.col("__last"))
    order = W.partitionBy(*by).orderBy(filled.desc(), draw)
    ranked = able.select(*df.columns, F.row_number().over(order).alias("__place")).where(F.col("__place") <= n)
    return ranked.withColumnRenamed("__place", place) if place else ranked.drop("__place")
