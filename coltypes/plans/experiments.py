"""The experiment workloads over the derived collections, with the offline rule model.

Runs are kept per session, input folder, collection and method, so workloads share them.
"""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coltypes.functions import sqlapi
from coltypes.operators import annotate, baselines, cascade, communities, discover, downstream, embed, judge, metrics, neighbors, profile, sampling
from coltypes.operators.cascade import CascadeConfig, Prepared, Result
from coltypes.operators.discover import DiscoverConfig
from coltypes.operators.models import RuleModel
from coltypes.operators.state import keep, shared_dir
from coltypes.sources import collection as C
from coltypes.sources import tables
from coltypes.streaming import live

METHODS = ("plain", "plain+reuse", "guided", "guided+reuse", "cascade")
COLLECTIONS = ("OPS", "TXT", "MIXED")
_PREPARED: dict[tuple, Prepared] = {}
_RUNS: dict[tuple, Result] = {}
_VERDICTS: dict[tuple, DataFrame] = {}


def clear() -> None:
    """Forget what was kept, so that the next workload is timed by itself."""
    _PREPARED.clear(), _RUNS.clear(), _VERDICTS.clear()


def prepared(spark: SparkSession, sf_dir: str, name: str) -> Prepared:
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _PREPARED:
        _PREPARED[key] = Prepared(C.build(spark, sf_dir, name))
    return _PREPARED[key]


def result(spark: SparkSession, sf_dir: str, name: str, method: str, level: str = "strong", annotator: str | None = None) -> Result:
    """The annotations and calls of a method on a collection."""
    key = (spark.sparkContext.applicationId, sf_dir, name, method, level, annotator)
    if key not in _RUNS:
        p, model = prepared(spark, sf_dir, name), RuleModel(level)
        checker = RuleModel(annotator or level)
        if method == "cascade":
            r = cascade.run(p.collection, p.config, model, checker, p)
        elif method.startswith("fixed"):
            r = cascade.fixed(p.collection, float(method[6:-1]), model, checker, prepared=p)
        elif method == "per_column":
            r = baselines.per_column(p, model)
        elif method == "complete":
            r = baselines.complete(p, result(spark, sf_dir, name, "cascade", level), model)
        elif method in ("closed_full", "closed_single"):
            r = getattr(baselines, method)(p, sorted(C.TRUTH), model)
        else:
            r = baselines.llm_only(p, method.startswith("guided"), method.endswith("reuse"), model)
        r.annotations, r.calls = keep(r.annotations), keep(r.calls)
        _RUNS[key] = r
    return _RUNS[key]


def _truth(p: Prepared) -> DataFrame:
    return p.columns.select("column_id", F.explode(F.split("truth", "[|]")).alias("label"))


def _by_meaning(annotations: DataFrame) -> DataFrame:
    return judge.concepts(annotations.select("column_id", "label", "phase")).select("column_id", F.col("concept").alias("label"), "phase")


def _one_row(*frames: DataFrame) -> DataFrame:
    """Several one-row frames side by side."""
    out = frames[0]
    for f in frames[1:]:
        out = out.crossJoin(f)
    return out


def judged(spark: SparkSession, sf_dir: str, name: str, *runs: tuple) -> DataFrame:
    """Verdicts of the judge model on the pool of some runs (method, level, annotator), each column and label once."""
    key = (spark.sparkContext.applicationId, sf_dir, name, runs)
    if key not in _VERDICTS:
        p = prepared(spark, sf_dir, name)
        pooled = judge.pool({str(x): result(spark, sf_dir, name, *x).annotations for x in runs})
        _VERDICTS[key] = keep(judge.judged(pooled, p.columns, p.values, p.rows, drawn=p.drawn(10)))
    return _VERDICTS[key]


def quality(p: Prepared, annotations: DataFrame, common: DataFrame, verdicts: DataFrame | None = None) -> DataFrame:
    """Measures on the columns ``common`` to all that are compared: judged if verdicts are given, and p, r, f1 against the true types."""
    a = metrics.restrict(annotations, common)
    rows = [metrics.prf(metrics.confusion(_by_meaning(a), metrics.restrict(_truth(p), common))).select("p", "r", "f1")]
    if verdicts is not None:
        rows = [metrics.hit_rate(a, verdicts), metrics.judged_precision(a, verdicts), *rows]
    return metrics.rounded(_one_row(*rows))


def usage(p: Prepared, r: Result) -> DataFrame:
    """Tokens and calls of discovery, different types and coverage."""
    return metrics.rounded(_one_row(metrics.tokens(r.calls), metrics.n_types(r.annotations), metrics.coverage(r.annotations, p.columns)))


def _all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def _named(collection: str, method: str, row: DataFrame) -> DataFrame:
    return row.select(F.lit(collection).alias("collection"), F.lit(method).alias("method"), "*")


def exp_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens, types and coverage of five methods on three collections."""
    return _all([_named(c, m, usage(prepared(spark, sf_dir, c), result(spark, sf_dir, c, m))) for c in COLLECTIONS for m in METHODS])


def _quality_rows(spark: SparkSession, sf_dir: str, c: str, methods: tuple[str, ...]) -> list[DataFrame]:
    p, common = prepared(spark, sf_dir, c), result(spark, sf_dir, c, "cascade").annotations
    verdicts = judged(spark, sf_dir, c, *((m,) for m in methods))
    return [_named(c, m, quality(p, result(spark, sf_dir, c, m).annotations, common, verdicts)) for m in methods]


def exp_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Judged hit rate and precision, and micro scores, of five methods on the columns that the cascade annotated; one pool of verdicts for each collection."""
    return _all([row for c in COLLECTIONS for row in _quality_rows(spark, sf_dir, c, METHODS)])


def exp_manual(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores by phase on one column of each type that the cascade found in it; the truth is what any method got right, and placeholders for the rest."""
    rows = []
    for c in COLLECTIONS:
        p, runs = prepared(spark, sf_dir, c), {m: result(spark, sf_dir, c, m).annotations for m in METHODS}
        sample = keep(judge.representatives(runs["cascade"]))
        by_person = judge.verdicts(judge.pool(runs), _truth(p))
        truth = keep(judge.synthetic_truth(by_person, _truth(p)).join(sample, "column_id").select("phase", "column_id", "label"))
        for m, a in runs.items():
            own = judge.concepts(a.select("column_id", "label")).select("column_id", F.col("concept").alias("label")).join(sample, "column_id")
            rows.append(_named(c, m, metrics.rounded(metrics.prf(metrics.confusion(own, truth, ["phase"])))))
    return _all(rows)


def exp_tradeoff(spark: SparkSession, sf_dir: str, price_in: float = 2.0, price_out: float = 8.0) -> DataFrame:
    """Cost per thousand columns and as a multiple of the cascade's, F1 and redundancy on the columns that the cascade annotated."""
    rows = []
    for c in COLLECTIONS:
        p, best = prepared(spark, sf_dir, c), result(spark, sf_dir, c, "cascade")
        least = metrics.cost(best.calls, price_in, price_out)
        for m in METHODS:
            r = result(spark, sf_dir, c, m)
            times = metrics.cost_ratio(least, metrics.cost(r.calls, price_in, price_out)).withColumnRenamed("ratio", "times_cascade")
            rows.append(_named(c, m, _one_row(quality(p, r.annotations, best.annotations).select("f1"), metrics.rounded(_one_row(metrics.cost_per_k(r.calls, r.annotations, price_in, price_out), times)), metrics.types_on(r.annotations, best.annotations))))
    return _all(rows)


def exp_models(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Discovery models and annotation models of three strengths, on OPS; one pool of verdicts."""
    p = prepared(spark, sf_dir, "OPS")
    runs = {f"discovery {level}": ("cascade", level) for level in ("strong", "medium", "weak")} | {f"annotation {level}": ("cascade", "strong", level) for level in ("medium", "weak")}
    verdicts, rows = judged(spark, sf_dir, "OPS", *runs.values()), []
    for swapped, run in runs.items():
        r = result(spark, sf_dir, "OPS", *run)
        rows.append(_one_row(quality(p, r.annotations, r.annotations, verdicts), usage(p, r)).select(F.lit(swapped).alias("swapped"), "hit_rate", "judged_precision", "n_types", "coverage", "f1"))
    return _all(rows)


def exp_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Single thresholds against the cascade, on OPS, each on the columns that it annotated; one pool of verdicts."""
    p, methods = prepared(spark, sf_dir, "OPS"), ("fixed(0.75)", "fixed(0.9)", "fixed(0.99)", "cascade")
    verdicts, rows = judged(spark, sf_dir, "OPS", *((m,) for m in methods)), []
    for m in methods:
        r = result(spark, sf_dir, "OPS", m)
        rows.append(_one_row(quality(p, r.annotations, r.annotations, verdicts), usage(p, r)).select(F.lit(m).alias("method"), "hit_rate", "judged_precision", "n_types", "coverage", "n_calls"))
    return _all(rows)


def exp_multitype(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Precision, recall and F1 on the columns of mixed types: on all of them, and on those that the cascade typed."""
    p, rows = prepared(spark, sf_dir, "MIXED"), []
    mixed = p.columns.where("base_table = 'multi'")
    typed = mixed.join(result(spark, sf_dir, "MIXED", "cascade").annotations.select("column_id").distinct(), "column_id", "left_semi")
    for scope, ids in (("all", mixed), ("typed by the cascade", typed)):
        truth = metrics.restrict(_truth(p), ids)
        for m in ("guided", "cascade", "complete"):
            a = metrics.restrict(_by_meaning(result(spark, sf_dir, "MIXED", m).annotations), ids)
            rows.append(metrics.rounded(metrics.prf(metrics.confusion(a, truth))).select(F.lit(scope).alias("scope"), F.lit(m).alias("method"), "*"))
    return _all(rows)


def intro_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Columns of differing headers that mix two kinds of values, taken as one cluster and typed by one call."""
    built = C.build(spark, sf_dir, "MULTI")
    wanted = built.columns.where("column_id in ('multi_01.location', 'multi_02.loc')")
    cells = built.cells.join(wanted.select("column_id"), "column_id", "left_semi")
    members = wanted.select("column_id", F.lit("example").alias("seed_cluster"))
    got = discover.run(members, wanted, profile.column_values(cells))
    return annotate.propagate(got.types, members, "discovery", 0.75).select("column_id", "label")


#: The six columns of the example: table, header, form of the values; the names of eight nations stand for ``NATION_%d``.
EXAMPLE = [
    ("t1", "PickupLocationAddress", "NATION_%d"), ("t2", "pickup_location_address", "NATION_%d"), ("t3", "pickup_location_adress", "NATION_%d"),
    ("t4", "pickup_location", "NATION_%d"), ("t5", "location_address", "NATION_%dB"), ("t6", "qqq", "zz %d zz"),
]


def example(spark: SparkSession, sf_dir: str | None = None) -> C.Collection:
    """The example with values made here, or with those of the table ``nation``."""
    columns = spark.createDataFrame([(f"{t}.{h}", t, h, 0, "text", t, h, "") for t, h, _ in EXAMPLE], C.CATALOG)
    if sf_dir is None:
        named = spark.createDataFrame([(n, f"NATION_{n}") for n in range(1, 9)], "n int, name string")
    else:
        named = tables.table(spark, sf_dir, "nation").where("n_nationkey between 1 and 8 and n_name is not null").select(F.col("n_nationkey").cast("int").alias("n"), F.col("n_name").alias("name"))
    number = F.col("n").cast("string")
    made = {"NATION_%d": F.col("name"), "NATION_%dB": F.concat("name", F.lit("B")), "zz %d zz": F.concat(F.lit("zz "), number, F.lit(" zz"))}
    held = named.select("n", F.explode(F.array(*[F.struct(F.lit(t).alias("t"), F.lit(h).alias("h"), made[form].alias("value")) for t, h, form in EXAMPLE])).alias("c")).select("n", "c.*")
    cells = held.select(F.concat_ws(".", "t", "h").alias("column_id"), F.lit("text").alias("kind"), "value", F.lit(None).cast("double").alias("num"))
    rows = held.select(F.col("t").alias("table_id"), F.col("n").alias("place"), F.col("h").alias("base_column"), "value")
    return C.Collection("EXAMPLE", columns, cells, rows)


def cascade_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Six columns, levels 0.99, 0.9 and 0.75: a pair found at once, two that fit its types at the lower levels, a residual of one, one that never joins."""
    r = cascade.run(example(spark, sf_dir), CascadeConfig())
    return r.annotations.select("column_id", "label", "phase", "threshold")


def embedding_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Communities of the given vectors at cosine 0.3."""
    v = tables.table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("string").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"))
    nodes = v.select("id", F.lit(1).alias("weight"), F.lpad("id", 12, "0").alias("first"))
    found = communities.of_vectors(nodes.join(v, "id"), 0.3)
    return communities.detect(nodes, neighbors.block(v, 0.3)) if found is None else found


def header_pairs_lsh(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Header pairs by random projections, checked exactly."""
    v = embed.headers(C.base_columns(spark)).withColumnRenamed("header_key", "id")
    return metrics.rounded(neighbors.lsh(v, 0.4, 16, 1.0))


def single_view_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of name-only, value-only and seed clusters at three levels, on OPS."""
    p, rows = prepared(spark, sf_dir, "OPS"), []
    for tau in (0.99, 0.9, 0.75):
        for view in ("name", "value", "seed"):
            c = p.level(tau).where(f"{view}_cluster is not null")
            rows.append(c.agg(F.countDistinct(f"{view}_cluster").alias("n_clusters"), F.count("*").alias("n_columns")).select(F.lit(tau).alias("tau"), F.lit(view).alias("view"), "*"))
    return _all(rows)


def rest_annotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the pass over columns outside seed clusters added, by threshold and source, on OPS."""
    a = result(spark, sf_dir, "OPS", "cascade").annotations.where("phase = 'rest'")
    return a.groupBy("threshold", "source").agg(F.countDistinct("column_id").alias("n_columns"), F.countDistinct("label").alias("n_types"))


def all_collection_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tables, columns and rows of the three collections."""
    built = [C.build(spark, sf_dir, c) for c in COLLECTIONS]
    return _all([metrics.collection_stats(b.columns, b.sizes).select(F.lit(b.name).alias("collection"), "*") for b in built])


def stream_value_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The value index kept as state, over documents' languages arriving as a stream with their type."""
    schema = tables.table(spark, sf_dir, "documents").schema
    docs = spark.readStream.schema(schema).parquet(f"{sf_dir}/documents.parquet*")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    name = f"index_{uuid.uuid4().hex[:8]}"
    q = live.value_index(docs.select(F.col("lang").alias("value"), F.lit("Language Code").alias("label"))).writeStream.outputMode("update").format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The SQL entry: sample and type the nation names in one statement."""
    sqlapi.register(spark, {"nation_view": tables.table(spark, sf_dir, "nation")})
    return spark.sql("select t.header, t.label, estimated_tokens(t.label) n_tokens from (select collect_set(n_name) v from nation_view) s, lateral discover_types('n_name', s.v, 'text') t")


def _pair_task(spark: SparkSession, sf_dir: str, name: str, task: str, most: int | None = None) -> DataFrame:
    p = prepared(spark, sf_dir, name)
    pairs = keep(downstream.truth_pairs(p.columns, p.values, task, most, p.sets))
    rows = []
    for m in METHODS:
        a = result(spark, sf_dir, name, m).annotations
        rows.append(_one_row(downstream.agreement(pairs, a), metrics.rounded(downstream.pair_similarity(pairs, a))).select(F.lit(m).alias("method"), "*"))
    return _all(rows)


def exp_join_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Do both sides of joinable column pairs get the same types?"""
    return _pair_task(spark, sf_dir, "MIXED", "join")


def exp_match_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Do matching columns get the same types, with or without common values?"""
    return _pair_task(spark, sf_dir, "OPS", "match")


def exp_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Switches off one component at a time, on TXT; scores on the columns that the full cascade annotated."""
    p, common = prepared(spark, sf_dir, "TXT"), result(spark, sf_dir, "TXT", "cascade").annotations
    switches = {
        "all on": {},
        "no index": {"discovery": DiscoverConfig(candidates="all")},
        "no candidates": {"discovery": DiscoverConfig(candidates="none")},
        "no context": {"discovery": DiscoverConfig(n_context=0)},
        "unordered": {"discovery": DiscoverConfig(order="id")},
        "uniform sample": {"discovery": DiscoverConfig(sampling="uniform")},
        "frequency sample": {"discovery": DiscoverConfig(sampling="frequency")},
        "no rows": {"context_rows": 0},
        "looser names": {"name_slack": 0.1},
        "names only": {"view": "name"},
        "values only": {"view": "value"},
    }
    rows = []
    for label, change in switches.items():
        config = CascadeConfig(**change)
        p.values, p.sets, p.rows, p.vectors, p.views, p.drawn(config.discovery.k)  # made once for all switches
        own = Prepared.__new__(Prepared)
        own.__dict__ = p.__dict__ | {"config": config, "_levels": {} if {"view", "name_slack"} & set(change) else p._levels}
        if "name_slack" in change:
            del own.__dict__["views"]  # pairs of headers at a lower threshold
        r = cascade.run(p.collection, config, prepared=own)
        rows.append(_one_row(usage(p, r), quality(p, r.annotations, common)).select(F.lit(label).alias("switch"), "*"))
    return _all(rows)


def _shown(ways: dict[str, DataFrame]) -> DataFrame:
    """How many lengths and values the samples of all columns have together."""
    rows = []
    for way, s in ways.items():
        each = s.groupBy("column_id").agg(F.countDistinct(F.length("value")).alias("lengths"), F.count("*").alias("n_values"))
        rows.append(each.agg(F.sum("lengths").cast("long").alias("lengths"), F.sum("n_values").cast("long").alias("n_values")).select(F.lit(way).alias("way"), "*"))
    return _all(rows)


def _mixed_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    return C.build(spark, sf_dir, "MULTI").cells.groupBy("column_id", "value").agg(F.count("*").alias("n"))


def exp_sampling(spark: SparkSession, sf_dir: str, k: int = 4) -> DataFrame:
    """How many lengths and values each way of sampling shows of the mixed columns."""
    values = _mixed_values(spark, sf_dir)
    return _shown({"stratified": sampling.length_stratified(values, "column_id", k), "uniform": sampling.uniform(values, "column_id", k), "frequency": sampling.by_frequency(values, "column_id", k)})


def exp_sampling_clusters(spark: SparkSession, sf_dir: str, k: int = 4) -> DataFrame:
    """The same for the costly way, clusters of TF-IDF vectors, beside the stratified one."""
    values = _mixed_values(spark, sf_dir)
    return _shown({"value clusters": sampling.by_value_clusters(values, "column_id", k), "stratified": sampling.length_stratified(values, "column_id", k)})


def complete_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cascade, its complement and the guided baseline: coverage against tokens, and F1 over all columns."""
    rows = []
    for c in COLLECTIONS:
        p = prepared(spark, sf_dir, c)
        for m in ("cascade", "complete", "guided"):
            r = result(spark, sf_dir, c, m)
            rows.append(_named(c, m, _one_row(usage(p, r).drop("n_types"), quality(p, r.annotations, p.columns).select("f1"))))
    return _all(rows)


def annotations_of(method: str, name: str = "OPS"):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return result(spark, sf_dir, name, method).annotations.select("column_id", "label", "phase", "source", "threshold")

    return query


def discovered_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = result(spark, sf_dir, "OPS", "cascade")
    return spark.createDataFrame([(k, kind, label) for k, (kind, label) in enumerate(r.types)], "seq int, kind string, label string")


def discovery_prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return result(spark, sf_dir, "OPS", "cascade").calls.where("role = 'discovery'")


def cascade_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    result(spark, sf_dir, "OPS", "cascade")
    return result(spark, sf_dir, "OPS", "cascade").trace


def closed_set_of(kind: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = prepared(spark, sf_dir, "TXT")
        known = result(spark, sf_dir, "TXT", "cascade").annotations.where("phase = 'discovery'")
        wanted = annotate.open_columns(p.columns, known).where(F.col("kind") == kind)
        level = p.level(0.75)
        candidates = annotate.candidates_by("name", level, known, wanted)
        if kind == "text":
            candidates = candidates.union(annotate.candidates_by("value", level, known, wanted))
        asked = annotate.requests(candidates, p.columns, p.values, rows=p.rows, drawn=p.drawn(10))
        return annotate.closed_set(asked).select("column_id", "source", F.array_join("accepted", "|").alias("accepted"), "in_tokens", "out_tokens")

    return query


def clusters_at(tau: float, column: str, name: str = "OPS"):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return prepared(spark, sf_dir, name).level(tau).where(F.col(column).isNotNull()).select("column_id", column)

    return query


def tfidf_cluster_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    values = C.build(spark, sf_dir, "MULTI").cells.select("column_id", "value").distinct()
    return sampling.by_value_clusters(values, "column_id", 6)


def stream_incremental_annotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """New documents' columns arrive as a stream; values known from OPS and TXT types get labels, others are queued."""
    from coltypes.operators import valueindex

    index = None
    for c in ("OPS", "TXT"):
        types = result(spark, sf_dir, c, "cascade").annotations.select("column_id", "label")
        index = valueindex.extend(index, prepared(spark, sf_dir, c).values, types, "column_id")
    index = keep(index)
    schema = tables.table(spark, sf_dir, "documents").schema
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    docs = spark.readStream.schema(schema).parquet(f"{sf_dir}/documents.parquet*")  # one file, or a folder of files of any name
    labels = "column_id string, label string, epoch long"
    spark.createDataFrame([], labels).write.parquet(f"{base}/labels")  # there even if no batch comes
    cells = docs.select(F.explode(F.array(F.struct(F.lit("new.lang").alias("column_id"), F.col("lang").alias("value")), F.struct(F.lit("new.source").alias("column_id"), F.col("source").alias("value")))).alias("c")).select("c.*")
    q = live.annotate_batches(cells, index, f"{base}/labels", f"{base}/queue", f"{base}/checkpoint")
    q.processAllAvailable()
    q.stop()
    return spark.read.schema(labels).parquet(f"{base}/labels").groupBy("column_id", "label").agg(F.count("*").alias("n_batches"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seed clusters of the base tables with their headers and a length-stratified sample."""
    p = Prepared(C.base_collection(spark, sf_dir))
    m = p.level(0.75).where("seed_cluster is not null").select("column_id", "seed_cluster")
    values = p.values.join(m, "column_id")
    sample = sampling.length_stratified(values, "seed_cluster", 10).groupBy("seed_cluster").agg(F.array_join(F.array_sort(F.collect_list("value")), " | ").alias("sample"))
    heads = m.join(p.columns, "column_id").groupBy("seed_cluster").agg(F.array_join(F.array_sort(F.collect_set("header")), "|").alias("headers"), F.first("kind").alias("kind"), F.count("*").alias("n_columns"))
    return heads.join(sample, "seed_cluster").select("seed_cluster", "headers", "kind", "n_columns", "sample")
