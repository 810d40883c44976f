"""What types are good for: join discovery and schema matching over column pairs, and hints at dirty data."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coltypes.functions.encoders import Encoder, encode
from coltypes.functions.exprs import cosine
from coltypes.operators.valueindex import column_sets, pairs_of_sets


def _sets(annotations: DataFrame) -> DataFrame:
    return annotations.groupBy("column_id").agg(F.array_sort(F.collect_set("label")).alias("labels"))


def with_types(pairs: DataFrame, annotations: DataFrame) -> DataFrame:
    """Pairs (left_id, right_id) with both label sets; a column without types has the empty set."""
    s, none = _sets(annotations), F.array().cast("array<string>")
    left, right = s.toDF("left_id", "l"), s.toDF("right_id", "r")
    return pairs.join(left, "left_id", "left").join(right, "right_id", "left").withColumn("l", F.coalesce("l", none)).withColumn("r", F.coalesce("r", none))


def agreement(pairs: DataFrame, annotations: DataFrame, denominator: str = "all") -> DataFrame:
    """pct_shared (a common label) and pct_same (equal, non-empty sets) of all pairs, or of pairs typed on both sides."""
    both = with_types(pairs, annotations)
    if denominator == "annotated":
        both = both.where("size(l) > 0 and size(r) > 0")
    share = lambda c: F.round(100 * F.avg(F.when(c, 1.0).otherwise(0.0)), 6)
    return both.agg(share(F.arrays_overlap("l", "r")).alias("pct_shared"), share((F.size("l") > 0) & (F.col("l") == F.col("r"))).alias("pct_same"), F.count("*").alias("n_pairs"))


def pair_similarity(pairs: DataFrame, annotations: DataFrame, encoder: Encoder | None = None) -> DataFrame:
    """Mean cosine of the mean label vectors over pairs typed on both sides, and how many these are."""
    labels = annotations.select("label").distinct().withColumn("v", encode(F.lower("label"), encoder))
    wide = annotations.select("column_id", "label").distinct().join(labels, "label").select("column_id", F.posexplode("v").alias("pos", "x"))
    means = wide.groupBy("column_id", "pos").agg(F.avg("x").alias("x")).groupBy("column_id").agg(F.array_sort(F.collect_list(F.struct("pos", "x"))).alias("p"))
    vectors = means.select("column_id", F.transform("p", lambda y: y["x"]).alias("v"))
    both = pairs.join(vectors.toDF("left_id", "a"), "left_id").join(vectors.toDF("right_id", "b"), "right_id")
    return both.agg(F.avg(cosine(F.col("a"), F.col("b"))).alias("similarity"), F.count("*").alias("n_typed"))


def filter_pairs(pairs: DataFrame, annotations: DataFrame) -> DataFrame:
    """Candidate pairs that share a type: put before or after any join discovery."""
    left = annotations.select(F.col("column_id").alias("left_id"), "label")
    right = annotations.select(F.col("column_id").alias("right_id"), "label")
    return pairs.join(pairs.join(left, "left_id").join(right, ["right_id", "label"]).select("left_id", "right_id").distinct(), ["left_id", "right_id"], "left_semi")


def suspect_columns(annotations: DataFrame, expected: int = 1) -> DataFrame:
    """Columns that got more types than they should hold."""
    return annotations.groupBy("column_id").agg(F.countDistinct("label").alias("n_types")).where(F.col("n_types") > expected)


def truth_pairs(columns: DataFrame, values: DataFrame, task: str, most: int | None = None, sets: DataFrame | None = None) -> DataFrame:
    """(left_id, right_id, relation): column pairs of different tables with the same true type.

    join: the values meet, as they are (equi) or after normalisation (fuzzy). match: equi if the
    values meet, else union. All pairs; with ``most`` a sample, the first so many by a hash of the pair.
    ``sets``: the column sets of the values if made before.
    """
    c = columns.select("column_id", "table_id", "truth")
    a, b = c.toDF("left_id", "lt", "truth"), c.toDF("right_id", "rt", "truth")
    same = a.join(b, "truth").where("left_id < right_id and lt <> rt").select("left_id", "right_id")
    held = F.broadcast(same.select(F.explode(F.array("left_id", "right_id")).alias("column_id")).distinct())  # of the catalog
    v = (values if sets is None else sets).select("column_id", "value").distinct().join(held, "column_id", "left_semi")

    def meet(x: DataFrame) -> DataFrame:
        return pairs_of_sets(x.join(c, "column_id"), "column_id", ["truth", "value"]).toDF("left_id", "right_id").join(same, ["left_id", "right_id"], "left_semi")

    equi = meet(v).withColumn("equi", F.lit(1))
    if task == "join":
        plain = values.join(held, "column_id", "left_semi").select("column_id", F.regexp_replace(F.lower("value"), "[^a-z0-9]", "").alias("value")).where("value <> ''").distinct()
        fuzzy = meet(column_sets(plain.select("column_id", F.lit("").alias("kind"), "value", F.length("value").alias("len"))).select("column_id", "value").distinct())
        rows = fuzzy.join(equi, ["left_id", "right_id"], "left").withColumn("relation", F.when(F.col("equi") == 1, "equi").otherwise("fuzzy"))
    else:
        rows = same.join(equi, ["left_id", "right_id"], "left").withColumn("relation", F.when(F.col("equi") == 1, "equi").otherwise("union"))
    rows = rows.select("left_id", "right_id", "relation")
    if most is None:
        return rows
    order = F.md5(F.concat_ws("|", "left_id", "right_id"))
    return rows.withColumn("h", order).orderBy("h", "left_id", "right_id").limit(most).drop("h")


def running_tokens(calls: DataFrame) -> DataFrame:
    """Token use as the calls went, by target: how cost and vocabulary grow."""
    order = W.orderBy("target").rowsBetween(W.unboundedPreceding, W.currentRow)
    return calls.select("target", "in_tokens", F.sum("in_tokens").over(order).alias("so_far"))
