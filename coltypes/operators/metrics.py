"""Cost and quality measures over annotations, verdicts, truth and the log of calls."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def tokens(calls: DataFrame, role: str = "discovery") -> DataFrame:
    """in_tokens, out_tokens, n_calls of one role."""
    total = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("long").alias(c)
    return calls.where(F.col("role") == role).agg(total("in_tokens"), total("out_tokens"), F.count("*").alias("n_calls"))


def calls_by_phase(calls: DataFrame) -> DataFrame:
    """Calls by role and phase with totals."""
    return calls.rollup("role", "phase").agg(F.count("*").alias("n_calls"), F.sum("in_tokens").alias("in_tokens"), F.sum("out_tokens").alias("out_tokens"))


def cost(calls: DataFrame, price_in: float, price_out: float) -> DataFrame:
    """Money for the discovery model by prices per million tokens; the annotation model is free."""
    return tokens(calls).select(((F.col("in_tokens") * price_in + F.col("out_tokens") * price_out) / 1e6).alias("cost"))


def cost_per_k(calls: DataFrame, annotations: DataFrame, price_in: float, price_out: float) -> DataFrame:
    """Cost of a thousand annotated columns."""
    n = annotations.agg(F.countDistinct("column_id").alias("n"))
    return cost(calls, price_in, price_out).crossJoin(n).select(F.try_divide(F.col("cost") * 1000, F.col("n")).alias("cost_per_k"))


def cost_ratio(one: DataFrame, other: DataFrame) -> DataFrame:
    """Quotient of two one-row costs."""
    return other.toDF("b").crossJoin(one.toDF("a")).select(F.try_divide("b", "a").alias("ratio"))


def n_types(annotations: DataFrame) -> DataFrame:
    return annotations.agg(F.countDistinct("label").alias("n_types"))


def coverage(annotations: DataFrame, columns: DataFrame) -> DataFrame:
    """Share of columns with a type."""
    typed = annotations.select("column_id").distinct().withColumn("typed", F.lit(1.0))
    return columns.select("column_id").join(typed, "column_id", "left").agg(F.avg(F.coalesce("typed", F.lit(0.0))).alias("coverage"))


def restrict(annotations: DataFrame, ids: DataFrame) -> DataFrame:
    """Annotations of some columns only, to compare methods on common ground."""
    return annotations.join(ids.select("column_id").distinct(), "column_id", "left_semi")


def types_on(annotations: DataFrame, ids: DataFrame) -> DataFrame:
    """Redundancy: different labels on a set of columns."""
    return n_types(restrict(annotations, ids))


def hit_rate(annotations: DataFrame, verdicts: DataFrame) -> DataFrame:
    """Share of annotated columns with at least one valid type."""
    judged = annotations.select("column_id", "label").distinct().join(verdicts.select("column_id", "label", "valid"), ["column_id", "label"], "left")
    best = judged.groupBy("column_id").agg(F.max(F.when(F.col("valid"), 1.0).otherwise(0.0)).alias("hit"))
    return best.agg(F.avg("hit").alias("hit_rate"))


def judged_precision(annotations: DataFrame, verdicts: DataFrame) -> DataFrame:
    """Share of all annotations that are valid."""
    judged = annotations.select("column_id", "label").distinct().join(verdicts.select("column_id", "label", "valid"), ["column_id", "label"], "left")
    return judged.agg(F.avg(F.when(F.col("valid"), 1.0).otherwise(0.0)).alias("judged_precision"))


def confusion(annotations: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """tp, fp, fn over (column, label) sets; ``by`` are columns of both sides."""
    keys = [*(by or []), "column_id", "label"]
    a = annotations.select(*keys).distinct().withColumn("a", F.lit(1))
    t = truth.select(*keys).distinct().withColumn("t", F.lit(1))
    count = lambda c, name: F.count_if(c).alias(name)
    both = a.join(t, keys, "full")
    counts = [count(F.col("a").isNotNull() & F.col("t").isNotNull(), "tp"), count(F.col("t").isNull(), "fp"), count(F.col("a").isNull(), "fn")]
    return both.groupBy(*by).agg(*counts) if by else both.agg(*counts)


def prf(counts: DataFrame) -> DataFrame:
    """Micro precision, recall and F1 beside the counts."""
    tp, fp, fn = (F.col(c) for c in ("tp", "fp", "fn"))
    ratio = lambda a, b: F.coalesce(F.try_divide(a, b), F.lit(0.0))
    return counts.withColumn("p", ratio(tp, tp + fp)).withColumn("r", ratio(tp, tp + fn)).withColumn("f1", ratio(2 * tp, 2 * tp + fp + fn))


def collection_stats(columns: DataFrame, table_rows: DataFrame) -> DataFrame:
    """n_tables, least and most columns and rows of a table, numeric and text columns."""
    widths = columns.groupBy("table_id").agg(F.count("*").alias("w"), F.count_if(F.col("kind") == "num").alias("num"), F.count_if(F.col("kind") == "text").alias("text"))
    joined = widths.join(table_rows, "table_id")
    return joined.agg(F.count("*").alias("n_tables"), F.min("w").alias("min_columns"), F.max("w").alias("max_columns"), F.min("n_rows").alias("min_rows"), F.max("n_rows").alias("max_rows"), F.sum("num").alias("num_columns"), F.sum("text").alias("text_columns"))


def rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    """All doubles rounded, so that engines agree."""
    return df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def share(valid: Column) -> Column:
    return F.avg(F.when(valid, 1.0).otherwise(0.0))
