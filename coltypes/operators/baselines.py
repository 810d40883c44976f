"""What the method is compared with: whole-table prompting with and without guidance and reuse, and naive routes.

One prompt shows a table's headers and some well filled rows, and asks for all types of all columns.
How the answers differ follows from what a prompt says and shows: the model is told to be guided or
not, strict or not, and gets the rows and the list of the prompt, nothing else.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.operators import annotate, context, discover, prompts, tokens
from coltypes.operators.cascade import Prepared, Result
from coltypes.operators.models import RuleModel, TypeModel
from coltypes.operators.state import ANNOTATIONS, CALLS, frame, keep


def _answer(heads: list[dict], table: str, model: TypeModel, guided: bool, known: list[str] | None) -> tuple[list[tuple], tuple]:
    labels = {}
    for h in heads:
        sample = [v for v in dict.fromkeys(h["values"]) if v]
        labels[h["column_id"]] = model.propose({"headers": [h["header"]], "sample": sample, "kind": h["kind"], "candidates": known or [], "context": [], "guided": guided, "strict": guided})
    prompt = prompts.whole_table(heads, guided, known)
    response = json.dumps({h["header"]: labels[h["column_id"]] for h in heads})
    rows = [(c, label, "table", "table", None) for c, got in labels.items() for label in got]
    return rows, ("discovery", "table", table, "all" if known is not None else "none", prompt, response, tokens.estimate(prompt), tokens.estimate(response))


def llm_only(p: Prepared, guided: bool, reuse: bool, model: TypeModel = RuleModel(), rows: int = 10, columns: DataFrame | None = None) -> Result:
    """One call per table; with reuse in table order, since each prompt lists the types so far; else spread over tasks."""
    spark = p.columns.sparkSession
    wanted = p.columns if columns is None else columns
    tables = context.table_rows(wanted, p.rows, rows)
    if reuse:
        known: list[str] = []
        out, calls = [], []
        for r in tables.orderBy("table_id").toLocalIterator():
            heads = [h.asDict() for h in r["heads"]]
            got, call = _answer(heads, r["table_id"], model, guided, known)
            out += got
            calls.append(call)
            known += [x for x in dict.fromkeys(g[1] for g in got) if x not in known]
        return Result(frame(spark, out, ANNOTATIONS), frame(spark, calls, CALLS))

    def ask(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            told = []
            for table, heads in zip(f["table_id"], f["heads"], strict=True):
                got, call = _answer([dict(h) | {"values": list(h["values"])} for h in heads], table, model, guided, None)
                told.append(([g[0] for g in got], [g[1] for g in got], *call))
            yield pd.DataFrame(told, columns=["columns", "labels", *(c.split()[0] for c in CALLS.split(", "))])

    asked = keep(tables.mapInPandas(ask, f"columns array<string>, labels array<string>, {CALLS}"))
    pairs = asked.select(F.explode(F.arrays_zip("columns", "labels")).alias("z"))
    made = pairs.select(F.col("z.columns").alias("column_id"), F.col("z.labels").alias("label"), F.lit("table").alias("phase"), F.lit("table").alias("source"), F.lit(None).cast("double").alias("threshold"))
    return Result(made, asked.drop("columns", "labels"))


def per_column(p: Prepared, model: TypeModel = RuleModel()) -> Result:
    """The naive route: a discovery call for each column, without candidates."""
    alone = p.columns.select("column_id", F.col("column_id").alias("seed_cluster"))
    got = discover.run(alone, p.columns, p.values, model, config=discover.DiscoverConfig(candidates="none", wave=4096), held_values=p.held(10))
    return Result(annotate.propagate(got.types, alone, "discovery", 1.0), got.calls, got.labels)


def closed_full(p: Prepared, labels: list[str], model: TypeModel = RuleModel(), single: bool = False) -> Result:
    """Every column against the whole vocabulary."""
    vocabulary = frame(p.columns.sparkSession, [(label,) for label in labels], "label string")
    lists = vocabulary.agg(F.array_sort(F.collect_set("label")).alias("all"))
    candidates = p.columns.select("column_id").join(F.broadcast(lists)).select("column_id", F.explode("all").alias("label"), F.lit("all").alias("source"))
    checked = keep(annotate.closed_set(annotate.requests(candidates, p.columns, p.values, rows=p.rows, drawn=p.drawn(10)), model))
    made = annotate.aggregate(checked.withColumn("accepted", F.slice("accepted", 1, 1)) if single else checked, "closed", None)
    return Result(made, annotate.calls_of(checked, "closed"))


def closed_single(p: Prepared, labels: list[str], model: TypeModel = RuleModel()) -> Result:
    """The classical task: the one label of a closed list that fits a column best (the first of the answer), or none."""
    return closed_full(p, labels, model, single=True)


def complete(p: Prepared, cascade: Result, model: TypeModel = RuleModel()) -> Result:
    """Full coverage: the guided whole-table prompt only for columns that the cascade left open."""
    left = keep(annotate.open_columns(p.columns, cascade.annotations))
    more = llm_only(p, True, False, model, columns=left)
    return Result(cascade.annotations.union(more.annotations), cascade.calls.union(more.calls), cascade.types)
