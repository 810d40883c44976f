"""Name, value and seed clusters; pairs are made once at the lowest threshold and filtered for each level."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.functions.encoders import Encoder
from coltypes.functions.exprs import header_norm
from coltypes.operators import communities, embed, neighbors


@dataclass(frozen=True)
class SeedConfig:
    """Thresholds of names and values may differ (lower for noisy headers); bins and least size as parameters."""

    tau_name: float = 0.9
    tau_value: float = 0.9
    bins: int = 100
    min_size: int = 2
    method: str = "auto"


@dataclass
class Views:
    """Similarity pairs of the three views at the lowest threshold, and the nodes they are between."""

    columns: DataFrame
    name_nodes: DataFrame
    name_pairs: DataFrame
    value_nodes: DataFrame
    value_pairs: DataFrame
    node_of: DataFrame  # (column_id, node): columns of equal value vectors share a node


def _nodes(vectors: DataFrame, columns: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Columns of equal vectors as one node: nodes (id, weight, first), (column_id, node), (id, vec)."""
    kinded = vectors.join(columns.select("column_id", "kind"), "column_id").withColumn("k", F.transform("vec", lambda x: F.round(x, 9)))
    first = kinded.groupBy("kind", "k").agg(F.min("column_id").alias("node"), F.count("*").alias("weight"))
    joined = kinded.join(first, ["kind", "k"])
    nodes = first.select(F.col("node").alias("id"), "weight", F.col("node").alias("first"), "kind")
    return nodes, joined.select("column_id", "node"), joined.where("column_id = node").select(F.col("node").alias("id"), "kind", "vec")


def value_vectors(values: DataFrame, cells: DataFrame, bins: int = 100, encoder: Encoder | None = None) -> DataFrame:
    """(column_id, vec) of all columns: of texts and of numbers."""
    return embed.text_columns(values, encoder).union(embed.histograms(cells, bins))


def views(columns: DataFrame, values: DataFrame, cells: DataFrame, config: SeedConfig = SeedConfig(), encoder: Encoder | None = None, keep=lambda df: df.cache(), vectors: DataFrame | None = None) -> Views:
    """All pairs at the config's thresholds or above of header, text-value and numeric vectors; ``vectors`` of values if made before."""
    keyed = columns.withColumn("header_key", header_norm(F.col("header")))
    name_nodes = keyed.groupBy(F.col("header_key").alias("id")).agg(F.count("*").alias("weight"), F.min("column_id").alias("first"))
    names = embed.headers(columns, encoder).select(F.col("header_key").alias("id"), "vec")
    name_pairs = keep(neighbors.pairs(names, config.tau_name, config.method))
    vectors = keep(value_vectors(values, cells, config.bins, encoder)) if vectors is None else vectors
    nodes, node_of, points = _nodes(vectors, columns)
    points = keep(points)
    value_pairs = None
    for kind in ("text", "num"):
        part = neighbors.pairs(points.where(F.col("kind") == kind).select("id", "vec"), config.tau_value, config.method)
        value_pairs = part if value_pairs is None else value_pairs.union(part)
    return Views(columns, keep(name_nodes), name_pairs, keep(nodes), keep(value_pairs), keep(node_of))


def name_clusters(v: Views, tau: float, min_size: int = 2) -> DataFrame:
    """(column_id, name_cluster)."""
    found = communities.detect(v.name_nodes, v.name_pairs.where(F.round("sim", 6) >= tau), min_size)
    return v.columns.select("column_id", header_norm(F.col("header")).alias("id")).join(found, "id").select("column_id", F.col("community").alias("name_cluster"))


def value_clusters(v: Views, tau: float, min_size: int = 2) -> DataFrame:
    """(column_id, value_cluster); text and numeric columns never mix."""
    found = communities.detect(v.value_nodes, v.value_pairs.where(F.round("sim", 6) >= tau), min_size)
    return v.node_of.join(found, v.node_of["node"] == found["id"]).select("column_id", F.col("community").alias("value_cluster"))


def intersect(names: DataFrame, values: DataFrame, min_size: int = 2) -> DataFrame:
    """(column_id, name_cluster, value_cluster, seed_cluster): columns that agree in both clusters; the seed is named by its first column."""
    both = names.join(values, "column_id")
    seeds = both.groupBy("name_cluster", "value_cluster").agg(F.count("*").alias("n"), F.min("column_id").alias("seed_cluster")).where(F.col("n") >= min_size)
    return both.join(seeds, ["name_cluster", "value_cluster"]).select("column_id", "name_cluster", "value_cluster", "seed_cluster")


def at_level(v: Views, tau: float, config: SeedConfig | None = None) -> DataFrame:
    """Membership of all clustered columns at a level: seed_cluster is null where only one view clusters the column."""
    c = config or SeedConfig(tau, tau)
    names, values = name_clusters(v, c.tau_name, c.min_size), value_clusters(v, c.tau_value, c.min_size)
    seeds = intersect(names, values, c.min_size).select("column_id", "seed_cluster")
    return v.columns.select("column_id", "kind").join(names, "column_id", "left").join(values, "column_id", "left").join(seeds, "column_id", "left").where("name_cluster is not null or value_cluster is not null")


def single_view(membership: DataFrame, view: str) -> DataFrame:
    """Clusters of one view alone in place of seeds (a component ablation)."""
    return membership.withColumn("seed_cluster", F.col(f"{view}_cluster"))
