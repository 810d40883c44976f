"""Verdicts on annotations, pooled once for all methods, by a judge model or by truth labels; samples for manual checks."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coltypes.functions.exprs import is_generic
from coltypes.operators import annotate, context
from coltypes.operators.models import CONCEPT, RuleJudge, TypeModel


def concepts(annotations: DataFrame) -> DataFrame:
    """Annotations with the meaning of their label (itself where unknown); the table of synonyms is a constant of some hundred rows."""
    spark = annotations.sparkSession
    known = spark.createDataFrame(sorted(CONCEPT.items()), "variant string, meaning string")
    return annotations.join(F.broadcast(known), F.lower("label") == F.col("variant"), "left").withColumn("concept", F.coalesce("meaning", "label")).drop("variant", "meaning")


def pool(by_method: dict[str, DataFrame]) -> DataFrame:
    """(column_id, label): every annotation of any method, once."""
    out = None
    for a in by_method.values():
        part = a.select("column_id", "label")
        out = part if out is None else out.union(part)
    return out.distinct()


JUDGED = "column_id string, label string, valid boolean"


def judged(pooled: DataFrame, columns: DataFrame, values: DataFrame, rows: DataFrame | None, model: TypeModel | RuleJudge | None = None, k: int = 10, context_rows: int = 3, drawn: DataFrame | None = None) -> DataFrame:
    """(column_id, label, valid): one verdict of a judge model per column and label, from the header, a sample of values and the table."""
    model = model or RuleJudge()
    asked = pooled.select("column_id", "label").distinct()
    ids = asked.select("column_id").distinct()
    sample = annotate.samples(values.join(ids, "column_id", "left_semi"), k) if drawn is None else drawn.join(ids, "column_id", "left_semi")
    about = columns.join(ids, "column_id", "left_semi").select("column_id", "table_id", "header")
    near = columns.join(about.select("table_id").distinct(), "table_id", "left_semi")
    shown = context.table_rows(near, rows, context_rows).select("table_id", context.shown(F.col("heads")).alias("table"))
    requests = asked.join(about, "column_id").join(sample, "column_id", "left").join(shown, "table_id", "left").withColumn("sample", F.coalesce("sample", F.array().cast("array<string>")))

    def decide(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            valid = [model.judge(r | {"sample": list(r["sample"])}) for r in f.to_dict("records")]
            yield pd.DataFrame({"column_id": f["column_id"], "label": f["label"], "valid": pd.Series(valid, dtype=bool, index=f.index)})

    return requests.select("column_id", "label", "header", "sample", "table").mapInPandas(decide, JUDGED)


def verdicts(pooled: DataFrame, truth: DataFrame) -> DataFrame:
    """(column_id, label, concept, valid): one verdict per column and label by true types, as a person gives; generic labels never pass."""
    right = truth.select("column_id", F.col("label").alias("concept"), F.lit(True).alias("hit"))
    judged = concepts(pooled.select("column_id", "label").distinct()).join(right, ["column_id", "concept"], "left")
    return judged.select("column_id", "label", "concept", (F.coalesce("hit", F.lit(False)) & ~is_generic(F.col("label"))).alias("valid"))


def representatives(annotations: DataFrame) -> DataFrame:
    """(phase, column_id): for each phase and type one column (by hash), each column once per phase."""
    phase = F.when(F.col("phase") == "discovery", "discovery").otherwise("annotation")
    order = W.partitionBy("phase", "label").orderBy(F.md5("column_id"), "column_id")
    ranked = annotations.select(phase.alias("phase"), "label", "column_id").withColumn("place", F.row_number().over(order))
    return ranked.where("place = 1").select("phase", "column_id").distinct()


def synthetic_truth(judged: DataFrame, truth: DataFrame) -> DataFrame:
    """(column_id, label): valid predictions of all methods by meaning, and placeholders for what none found."""
    found = judged.where("valid").select("column_id", F.col("concept").alias("label")).distinct()
    missed = truth.join(found, ["column_id", "label"], "left_anti")
    order = W.partitionBy("column_id").orderBy("label")
    return found.union(missed.select("column_id", F.concat(F.lit("Other_"), F.row_number().over(order).cast("string")).alias("label")))
