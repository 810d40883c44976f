"""Type discovery: one call per cluster, largest cluster first, with types that its values already have.

Samples, contexts and value-sharing edges of all clusters of a level come from one job each; the
loop over clusters then runs on the driver over these small rows and makes no Spark job. With
``wave`` > 1, clusters of a wave see the types known at its start and their calls run on executors.
"""

from __future__ import annotations

from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coltypes.operators import context, prompts, sampling, tokens, valueindex
from coltypes.operators.models import RuleModel, TypeModel
from coltypes.operators.state import CALLS, frame, keep


@dataclass(frozen=True)
class DiscoverConfig:
    k: int = 10
    n_context: int = 5
    candidates: str = "index"  # index, all, none
    order: str = "size"  # size, id
    sampling: str = "stratified"  # stratified, uniform, frequency
    wave: int = 1


def order(membership: DataFrame, key: str = "seed_cluster") -> DataFrame:
    """(key, n_columns, first, place): the largest first, equals by first column."""
    sized = membership.groupBy(key).agg(F.count("*").alias("n_columns"), F.min("column_id").alias("first"))
    ranked = sized.orderBy(F.desc("n_columns"), "first")
    return ranked.select(key, "n_columns", "first")


def _samples(values: DataFrame, c: DiscoverConfig, sizes: DataFrame | None = None) -> DataFrame:
    if c.sampling == "uniform":
        return sampling.uniform(values, "seed_cluster", c.k)
    if c.sampling == "frequency":
        return sampling.by_frequency(values, "seed_cluster", c.k)
    return sampling.length_stratified(values, "seed_cluster", c.k, sizes=sizes)


def values_of(membership: DataFrame, values: DataFrame) -> DataFrame:
    """(seed_cluster, value, n): the different values of each cluster; membership is a row for each column and goes to the values."""
    held = values.join(F.broadcast(membership.select("column_id", "seed_cluster")), "column_id")
    return held.groupBy("seed_cluster", "value").agg((F.sum("n") if "n" in values.columns else F.count("*")).alias("n"))


@dataclass(frozen=True)
class Held:
    """Of the values of all columns what discovery needs of them, made once for all levels; both are far smaller than the values."""

    sets: DataFrame  # (column_id, value, len, n), see valueindex.column_sets
    strata: DataFrame  # (column_id, value, len), see sampling.strata


def sets_of(membership: DataFrame, sets: DataFrame) -> DataFrame:
    """(seed_cluster, value, len, n): the different sets of values of each cluster."""
    return sets.join(F.broadcast(membership.select("column_id", "seed_cluster")), "column_id").select("seed_cluster", "value", "len", "n").distinct()


def requests(membership: DataFrame, columns: DataFrame, own: DataFrame, c: DiscoverConfig = DiscoverConfig(), sizes: DataFrame | None = None) -> list[dict]:
    """One request per cluster, in order; rows are as many as clusters. ``own``: its values, or the first of its strata if their sizes are given."""
    sample = {r["seed_cluster"]: sorted(r["s"]) for r in _samples(own, c, sizes).groupBy("seed_cluster").agg(F.collect_list("value").alias("s")).collect()}
    beside: dict[str, list] = {}
    if c.n_context:
        for r in context.cooccurring(membership, columns, c.n_context).orderBy("seed_cluster", "rank").collect():
            beside.setdefault(r["seed_cluster"], []).append((r["header"], r["n_tables"], r["of_tables"]))
    joined = membership.select("column_id", "seed_cluster").join(columns.select("column_id", "header", "kind"), "column_id")
    info = joined.groupBy("seed_cluster").agg(F.array_sort(F.collect_set("header")).alias("headers"), F.first("kind").alias("kind"), F.count("*").alias("n"), F.min("column_id").alias("first")).collect()
    info.sort(key=(lambda r: (-r["n"], r["first"])) if c.order == "size" else (lambda r: r["seed_cluster"]))
    return [{"cluster": r["seed_cluster"], "headers": list(r["headers"]), "kind": r["kind"], "sample": sample.get(r["seed_cluster"], []), "context": beside.get(r["seed_cluster"], []), "candidates": []} for r in info]


def _on_executors(spark: SparkSession, batch: list[dict], model: TypeModel) -> list[list[str]]:
    """The calls of a wave, spread over tasks."""
    def call(frames):
        for f in frames:
            yield pd.DataFrame({"at": f["at"], "labels": [model.propose(r) for r in f["request"].map(_unpacked)]})

    rows = [(k, repr(r)) for k, r in enumerate(batch)]
    got = spark.createDataFrame(rows, "at int, request string").repartition(min(len(rows), 64)).mapInPandas(call, "at int, labels array<string>").collect()
    return [r["labels"] for r in sorted(got, key=lambda r: r["at"])]


def _unpacked(text: str) -> dict:
    import ast

    return ast.literal_eval(text)


@dataclass
class Discovered:
    types: DataFrame  # (seed_cluster, kind, label)
    calls: DataFrame
    labels: list[tuple[str, str]]  # (kind, label) of all types so far, in order
    own: DataFrame | None = None  # (seed_cluster, value, n), value may name a set of values


def run(membership: DataFrame, columns: DataFrame, values: DataFrame, model: TypeModel = RuleModel(), known: list[tuple[str, str]] | None = None, index: DataFrame | None = None, config: DiscoverConfig = DiscoverConfig(), phase: str = "discovery", held_values: Held | None = None) -> Discovered:
    """Discover types for each cluster of ``membership`` (column_id, seed_cluster).

    With ``held_values``, values that the same columns hold go through index and edges as one, and samples are drawn from strata.
    """
    spark, known = columns.sparkSession, list(known or [])
    if held_values is None:
        own = keep(values_of(membership, values))
        asked = requests(membership, columns, own, config)
    else:
        own = keep(sets_of(membership, held_values.sets))
        if config.sampling == "frequency":
            asked = requests(membership, columns, values_of(membership, values), config)
        else:
            sizes = own.groupBy("seed_cluster", "len").agg(F.sum("n").alias("size"))
            asked = requests(membership, columns, values_of(membership, held_values.strata), config, sizes)
    near: dict[str, list[tuple]] = {}  # the sets of clusters that share a value, by cluster
    typed: dict[tuple, dict[str, None]] = {}  # the labels of their members so far
    held: dict[str, set[str]] = {}
    if config.candidates == "index" and asked:
        for r in valueindex.edges(own, "seed_cluster", ["value"]).select("seed_cluster", "e1", "e2").toLocalIterator():
            near.setdefault(r["seed_cluster"], []).append((r["e1"], r["e2"]))
        if index is not None:
            for r in valueindex.lookup(index, own).collect():
                held.setdefault(r["seed_cluster"], set()).add(r["label"])
    types, calls = [], []
    for at in range(0, len(asked), max(1, config.wave)):
        batch = asked[at : at + max(1, config.wave)]
        for r in batch:
            if config.candidates == "index":
                hits = set(held.get(r["cluster"], ())).union(*(typed.get(e, ()) for e in near.get(r["cluster"], ())))
                r["candidates"] = sorted(hits) or [label for kind, label in known if kind == r["kind"]]
                r["source"] = "index" if hits else "fallback"
            elif config.candidates == "all":
                r["candidates"] = [label for _, label in known]
        answers = [model.propose(r) for r in batch] if len(batch) == 1 else _on_executors(spark, batch, model)
        for r, labels in zip(batch, answers, strict=True):
            prompt, response = prompts.discovery(r), prompts.answer(labels)
            calls.append(("discovery", phase, r["cluster"], r.get("source", config.candidates), prompt, response, tokens.estimate(prompt), tokens.estimate(response)))
            for e in near.get(r["cluster"], ()):
                typed.setdefault(e, {}).update(dict.fromkeys(labels))
            for label in labels:
                types.append((r["cluster"], r["kind"], label))
                if (r["kind"], label) not in known:
                    known.append((r["kind"], label))
    return Discovered(frame(spark, types, "seed_cluster string, kind string, label string"), frame(spark, calls, CALLS), known, own)
