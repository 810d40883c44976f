"""All queries of the engine by name, with the SQL that checks them where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from coltypes.plans import experiments as E
from coltypes.plans import workbench
from coltypes.plans.oracles import SQL

flagship = E.flagship


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    """The checked queries, then clusters, pipelines, baselines and experiments."""
    found = workbench.queries()
    found |= {
        "flagship": E.flagship,
        "name_clusters_099": E.clusters_at(0.99, "name_cluster"),
        "value_clusters_075": E.clusters_at(0.75, "value_cluster"),
        "seed_clusters_099": E.clusters_at(0.99, "seed_cluster"),
        "seed_clusters_075": E.clusters_at(0.75, "seed_cluster"),
        "tfidf_cluster_sample": E.tfidf_cluster_sample,
        "discovery_prompts": E.discovery_prompts,
        "discovered_types": E.discovered_types,
        "closed_set_text": E.closed_set_of("text"),
        "closed_set_numeric": E.closed_set_of("num"),
        "fixed_075": E.annotations_of("fixed(0.75)"),
        "fixed_090": E.annotations_of("fixed(0.9)"),
        "fixed_099": E.annotations_of("fixed(0.99)"),
        "cascade": E.annotations_of("cascade"),
        "cascade_trace": E.cascade_trace,
        "plain": E.annotations_of("plain"),
        "plain_reuse": E.annotations_of("plain+reuse"),
        "guided": E.annotations_of("guided"),
        "guided_reuse": E.annotations_of("guided+reuse"),
        "per_column": E.annotations_of("per_column"),
        "closed_full": E.annotations_of("closed_full", "MIXED"),
        "closed_single": E.annotations_of("closed_single", "MIXED"),
        "complete_coverage": E.complete_coverage,
        "stream_incremental_annotation": E.stream_incremental_annotation,
    }
    names = ("intro_example", "cascade_example", "embedding_clusters", "header_pairs_lsh", "single_view_clusters", "rest_annotation", "all_collection_stats", "stream_value_index", "sql_functions", "exp_tokens", "exp_quality", "exp_tradeoff", "exp_models", "exp_variants", "exp_multitype", "exp_join_pairs", "exp_match_pairs", "exp_sampling", "exp_sampling_clusters", "exp_manual", "exp_components")
    return found | {n: getattr(E, n) for n in names}


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
