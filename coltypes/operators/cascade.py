"""The cascade over falling thresholds, the single-threshold pipeline, and complete coverage."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.operators import annotate, discover, profile, sampling, seeds, valueindex
from coltypes.operators.discover import DiscoverConfig, Held
from coltypes.operators.models import RuleModel, TypeModel
from coltypes.operators.state import ANNOTATIONS, CALLS, keep, none
from coltypes.shipping import ship
from coltypes.sources.collection import Collection


@dataclass(frozen=True)
class CascadeConfig:
    thresholds: tuple[float, ...] = (0.99, 0.9, 0.75)
    discovery: DiscoverConfig = DiscoverConfig()
    bins: int = 100
    min_size: int = 2
    context_rows: int = 3
    view: str = "both"  # both, name, value
    name_slack: float = 0.0  # headers cluster at a threshold lower by this, for noisy ones
    method: str = "auto"  # how similar pairs are found, see neighbors.pairs


@dataclass
class Result:
    annotations: DataFrame
    calls: DataFrame
    types: list[tuple[str, str]] = field(default_factory=list)
    trace: DataFrame | None = None


class Prepared:
    """What all levels share: distinct values and similarity pairs at the lowest threshold, each made once, when first asked for."""

    def __init__(self, collection: Collection, config: CascadeConfig = CascadeConfig()):
        ship(collection.columns.sparkSession)
        self.collection, self.config = collection, config
        self.columns = keep(collection.columns)
        self._levels: dict[float, DataFrame] = {}
        self._drawn: dict[int, DataFrame] = {}
        self._strata: dict[int, DataFrame] = {}

    @cached_property
    def values(self) -> DataFrame:
        return keep(profile.column_values(self.collection.cells))

    @cached_property
    def sets(self) -> DataFrame:
        """(column_id, kind, value, len, n): values that the same columns hold, as one; index and sharing of all levels come from these."""
        return keep(valueindex.column_sets(self.values))

    def held(self, k: int) -> Held:
        if k not in self._strata:
            self._strata[k] = keep(sampling.strata(self.values, k))
        return Held(self.sets, self._strata[k])

    @cached_property
    def rows(self) -> DataFrame | None:
        return None if self.collection.rows is None else keep(self.collection.rows)

    @cached_property
    def views(self) -> seeds.Views:
        low = min(self.config.thresholds)
        wanted = seeds.SeedConfig(low - self.config.name_slack, low, self.config.bins, method=self.config.method)
        return seeds.views(self.columns, self.values, self.numbers, wanted, keep=keep, vectors=self.vectors)

    @property
    def numbers(self) -> DataFrame:
        return self.collection.cells if self.collection.numbers is None else self.collection.numbers

    @cached_property
    def vectors(self) -> DataFrame:
        """(column_id, vec): the same whatever the thresholds are."""
        return keep(seeds.value_vectors(self.values, self.numbers, self.config.bins))

    def drawn(self, k: int) -> DataFrame:
        """(column_id, sample) of all columns, as closed-set checks and the judge show them."""
        if k not in self._drawn:
            sizes = self.sets.groupBy("column_id", "len").agg(F.sum("n").alias("size"))
            self._drawn[k] = keep(annotate.samples(self.held(k).strata, k, sizes))
        return self._drawn[k]

    def level(self, tau: float) -> DataFrame:
        if tau not in self._levels:
            m = seeds.at_level(self.views, tau, seeds.SeedConfig(tau - self.config.name_slack, tau, min_size=self.config.min_size))
            self._levels[tau] = keep(m if self.config.view == "both" else seeds.single_view(m, self.config.view))
        return self._levels[tau]


def capture(membership: DataFrame, annotations: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(open, candidates): columns of seed clusters without a type, and the labels of their typed siblings by cluster."""
    inside = membership.where("seed_cluster is not null").select("column_id", "seed_cluster")
    typed = inside.join(annotations.select("column_id", "label"), "column_id").select("seed_cluster", "label").distinct()
    return inside.join(annotations.select("column_id").distinct(), "column_id", "left_anti"), typed


def _checked(p: Prepared, candidates: DataFrame, model: TypeModel) -> DataFrame:
    asked = annotate.requests(candidates, p.columns, p.values, p.config.discovery.k, p.rows, p.config.context_rows, p.drawn(p.config.discovery.k))
    return keep(annotate.closed_set(asked, model))


def _rest(p: Prepared, r: Result, tau: float, index: DataFrame | None, model: TypeModel, phase: str) -> Result:
    """Closed-set checks of all columns that are still open, by the clusters of one threshold (and the index if given)."""
    wanted = keep(annotate.open_columns(p.columns, r.annotations))
    text = wanted.where("kind = 'text'")
    level = p.level(tau)
    candidates = annotate.candidates_by("name", level, r.annotations, wanted).union(annotate.candidates_by("value", level, r.annotations, text))
    if index is not None:
        candidates = candidates.union(annotate.candidates_by_index(index, p.sets, text))
    checked = _checked(p, candidates, model)
    more = annotate.aggregate(checked, phase, tau)
    return Result(keep(r.annotations.union(more)), keep(r.calls.union(annotate.calls_of(checked, phase))), r.types)


def fixed(collection: Collection, tau: float, model: TypeModel = RuleModel(), annotator: TypeModel | None = None, config: CascadeConfig = CascadeConfig(), prepared: Prepared | None = None) -> Result:
    """One threshold: seeds, discovery, propagation, closed-set checks of the rest by all three sources."""
    p = prepared or Prepared(collection, replace(config, thresholds=(tau,)))
    inside = p.level(tau).where("seed_cluster is not null").select("column_id", "seed_cluster")
    got = discover.run(inside, p.columns, p.values, model, config=config.discovery, held_values=p.held(config.discovery.k))
    index = valueindex.extend(None, got.own, got.types)
    r = Result(keep(annotate.propagate(got.types, inside, "discovery", tau)), got.calls, got.labels)
    return _rest(p, r, tau, index, annotator or model, "closed")


def run(collection: Collection, config: CascadeConfig = CascadeConfig(), model: TypeModel = RuleModel(), annotator: TypeModel | None = None, prepared: Prepared | None = None) -> Result:
    """Levels from the highest threshold down: siblings' types first, discovery for what they do not fit; then the rest."""
    p = prepared or Prepared(collection, config)
    spark, annotator = p.columns.sparkSession, annotator or model
    r, index, trace = Result(none(spark, ANNOTATIONS), none(spark, CALLS)), None, []
    for tau in sorted(config.thresholds, reverse=True):
        inside, siblings = capture(p.level(tau), r.annotations)
        inside = keep(inside)
        candidates = inside.join(siblings, "seed_cluster").select("column_id", "label", F.lit("sibling").alias("source"))
        checked = _checked(p, candidates, annotator)
        r.annotations = keep(r.annotations.union(annotate.aggregate(checked, "sibling", tau)))
        residual = keep(inside.join(r.annotations.select("column_id").distinct(), "column_id", "left_anti"))
        got = discover.run(residual, p.columns, p.values, model, r.types, index, config.discovery, held_values=p.held(config.discovery.k))
        r.annotations = keep(r.annotations.union(annotate.propagate(got.types, residual, "discovery", tau)))
        r.calls = keep(r.calls.union(annotate.calls_of(checked, "sibling")).union(got.calls))
        index = keep(valueindex.extend(index, got.own, got.types))
        r.types = got.labels
        trace.append((tau, inside.count(), checked.count(), residual.count(), residual.select("seed_cluster").distinct().count()))
    for k, tau in enumerate(sorted(config.thresholds, reverse=True)):
        r = _rest(p, r, tau, index if k == 0 else None, annotator, "rest")
    r.trace = spark.createDataFrame(trace, "threshold double, open_columns long, sibling_checks long, residual_columns long, discovery_calls long")
    return r
