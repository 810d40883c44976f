"""Spreading types: to all columns of a seed cluster for free, to other columns by closed-set checks of few candidates."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.operators import context, prompts, sampling, tokens, valueindex
from coltypes.operators.models import RuleModel, TypeModel


def propagate(types: DataFrame, membership: DataFrame, phase: str, threshold: float) -> DataFrame:
    """All labels of a seed cluster for all its columns; no call."""
    rows = membership.select("column_id", "seed_cluster").join(types.select("seed_cluster", "label"), "seed_cluster")
    return rows.select("column_id", "label", F.lit(phase).alias("phase"), F.lit("seed").alias("source"), F.lit(threshold).cast("double").alias("threshold"))


def open_columns(columns: DataFrame, annotations: DataFrame) -> DataFrame:
    return columns.join(annotations.select("column_id").distinct(), "column_id", "left_anti")


def candidates_by(view: str, membership: DataFrame, annotations: DataFrame, wanted: DataFrame) -> DataFrame:
    """(column_id, label, source): labels of typed columns in the same name or value cluster."""
    m = membership.where(F.col(f"{view}_cluster").isNotNull()).select("column_id", f"{view}_cluster")
    known = m.join(annotations.select("column_id", "label"), "column_id").select(f"{view}_cluster", "label").distinct()
    mine = m.join(wanted.select("column_id"), "column_id", "left_semi")
    return mine.join(known, f"{view}_cluster").select("column_id", "label", F.lit(view).alias("source"))


def candidates_by_index(index: DataFrame, values: DataFrame, wanted: DataFrame) -> DataFrame:
    """(column_id, label, source): labels of the column's own values."""
    mine = values.join(F.broadcast(wanted.select("column_id")), "column_id", "left_semi")
    return valueindex.lookup(index, mine, "column_id").select("column_id", "label", F.lit("index").alias("source"))


def samples(values: DataFrame, k: int = 10, sizes: DataFrame | None = None) -> DataFrame:
    """(column_id, sample): at most k values of each column in order; ``sizes`` as in ``length_stratified``."""
    return sampling.length_stratified(values, "column_id", k, sizes=sizes).groupBy("column_id").agg(F.array_sort(F.collect_list("value")).alias("sample"))


def requests(candidates: DataFrame, columns: DataFrame, values: DataFrame, k: int = 10, rows: DataFrame | None = None, context_rows: int = 3, drawn: DataFrame | None = None) -> DataFrame:
    """One row per column and source with candidates: header, kind, sample, table context, candidates.

    ``drawn``: (column_id, sample) of all columns if made before; a column's sample does not depend on what is asked.
    """
    lists = candidates.groupBy("column_id", "source").agg(F.array_sort(F.collect_set("label")).alias("candidates"))
    asked = lists.select("column_id").distinct()
    sample = samples(values.join(asked, "column_id", "left_semi"), k) if drawn is None else drawn.join(asked, "column_id", "left_semi")
    about = columns.select("column_id", "table_id", "header", "kind").join(asked, "column_id", "left_semi")
    near = columns.join(about.select("table_id").distinct(), "table_id", "left_semi")
    shown = context.table_rows(near, rows, context_rows).select("table_id", context.shown(F.col("heads")).alias("table"))
    return lists.join(about, "column_id").join(sample, "column_id", "left").join(shown, "table_id", "left").withColumn("sample", F.coalesce("sample", F.array().cast("array<string>")))


CHECKED = "column_id string, source string, kind string, accepted array<string>, prompt string, response string, in_tokens long, out_tokens long"


def closed_set(asked: DataFrame, model: TypeModel = RuleModel()) -> DataFrame:
    """The answers: labels outside the candidates are discarded, an empty answer is an abstention."""
    def check(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            out = []
            for r in f.to_dict("records"):
                r = r | {"sample": list(r["sample"]), "candidates": list(r["candidates"])}
                got = [c for c in model.verify(r) if c in r["candidates"]]
                prompt, response = prompts.closed_set(r), prompts.answer(got)
                out.append((r["column_id"], r["source"], r["kind"], got, prompt, response, tokens.estimate(prompt), tokens.estimate(response)))
            yield pd.DataFrame(out, columns=[c.split()[0] for c in CHECKED.split(", ")])

    return asked.mapInPandas(check, CHECKED)


def aggregate(checked: DataFrame, phase: str, threshold: float | None) -> DataFrame:
    """Annotations: for text the union over sources, for numbers the name source alone."""
    rows = checked.where("kind = 'text' or source in ('name', 'sibling', 'all')").select("column_id", F.explode("accepted").alias("label"), "source")
    one = rows.groupBy("column_id", "label").agg(F.min("source").alias("source"))
    return one.select("column_id", "label", F.lit(phase).alias("phase"), "source", F.lit(threshold).cast("double").alias("threshold"))


def calls_of(checked: DataFrame, phase: str) -> DataFrame:
    return checked.select(F.lit("annotation").alias("role"), F.lit(phase).alias("phase"), F.col("column_id").alias("target"), "source", "prompt", "response", "in_tokens", "out_tokens")
