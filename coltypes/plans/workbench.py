"""The checked queries: each applies one operator to base tables and small sets derived from the catalog."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coltypes.functions import exprs as X
from coltypes.operators import annotate, context, discover, downstream, embed, judge, metrics, models, neighbors, profile, sampling, seeds, tokens, valueindex
from coltypes.operators.state import keep, shared_dir
from coltypes.plans.oracles import HELD_QUERIES, RELATIONAL
from coltypes.sources import collection as C
from coltypes.sources import tables as T
from coltypes.streaming import live

Query = Callable[[SparkSession, str], DataFrame]


class Bench:
    """Base tables in long form, and the annotation set, calls and clusters that both engines can build."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir
        self.columns = C.base_columns(spark)

    def only_held(self) -> Bench:
        """The same over the columns that hold a value in the tables, as found by reading them."""
        self.columns = keep(C.held_columns(self.spark, self.sf_dir))
        return self

    @property
    def cells(self) -> DataFrame:
        return C.base_cells(self.spark, self.sf_dir)

    def values(self, tables=tuple(T.SCHEMAS), kind: str | None = "text") -> DataFrame:
        return profile.column_values(C.base_cells(self.spark, self.sf_dir, tables, kind))

    @property
    def numbers(self) -> DataFrame:
        return C.base_cells(self.spark, self.sf_dir, kind="num")

    @property
    def annotations(self) -> DataFrame:
        h = X.hash32(F.col("column_id"))
        label = F.when(h % 7 == 0, F.concat(F.lit("Wrong "), "truth")).otherwise(F.col("truth"))
        phase = F.when(h % 2 == 0, "discovery").otherwise("rest")
        return self.columns.where(h % 5 != 0).select("column_id", "kind", label.alias("label"), phase.alias("phase"), "truth")

    @property
    def truth(self) -> DataFrame:
        return self.columns.select("column_id", F.col("truth").alias("label"))

    @property
    def verdicts(self) -> DataFrame:
        return judge.verdicts(self.annotations, self.truth)

    @property
    def calls(self) -> DataFrame:
        prompt = F.concat("header", F.lit(" of "), "table_id")
        response = F.concat(F.lit('{"answer": ["'), "truth", F.lit('"]}'))
        c = self.columns.select(F.lit("discovery").alias("role"), F.lit("discovery").alias("phase"), F.col("column_id").alias("target"), prompt.alias("prompt"), response.alias("response"))
        return c.withColumn("in_tokens", tokens.estimated(F.col("prompt"))).withColumn("out_tokens", tokens.estimated(F.col("response")))

    @property
    def members(self) -> DataFrame:
        keyed = self.columns.select("column_id", X.header_norm(F.col("header")).alias("seed_cluster"))
        more = keyed.groupBy("seed_cluster").count().where("count > 1").select("seed_cluster")
        return keyed.join(more, "seed_cluster").select("column_id", "seed_cluster")

    @property
    def typed(self) -> DataFrame:
        return self.members.join(self.columns, "column_id").select("seed_cluster", "kind", F.col("truth").alias("label")).distinct()

    @property
    def index(self) -> DataFrame:
        return valueindex.extend(None, self.values().join(self.members, "column_id"), self.typed)

    @property
    def pairs(self) -> DataFrame:
        c = self.columns.select("column_id", "table_id", "truth")
        a, b = c.toDF("left_id", "lt", "truth"), c.toDF("right_id", "rt", "truth")
        return a.join(b, "truth").where("left_id < right_id and lt <> rt").select("left_id", "right_id")


def _sparse(vectors: DataFrame, name: str, value: str) -> DataFrame:
    return vectors.select("*", F.posexplode("vec").alias(name, value)).drop("vec").where(F.col(value) != 0).withColumn(value, F.round(value, 6))


def _pairs(p: DataFrame) -> DataFrame:
    return p.select("i", "j", F.round("sim", 6).alias("sim"))


def _text_vectors(b: Bench, tables=RELATIONAL) -> DataFrame:
    return embed.text_columns(b.values(tables))


def column_catalog(b: Bench) -> DataFrame:
    return profile.catalog(b.columns, b.cells)


def column_values_orders(b: Bench, tables=("orders",)) -> DataFrame:
    return b.values(tables)


def collection_stats(b: Bench) -> DataFrame:
    built = C.build(b.spark, b.sf_dir, "OPS")
    return metrics.collection_stats(built.columns, built.sizes)


def distinct_counts(b: Bench) -> DataFrame:
    return profile.distinct_counts(b.cells).select("column_id", "n_distinct")


def length_profile(b: Bench) -> DataFrame:
    return profile.lengths(b.values())


def header_ngram_vectors(b: Bench) -> DataFrame:
    """The native form of the header encoder; the Arrow form gives the same numbers."""
    g = b.columns.select(X.header_norm(F.col("header")).alias("header_key")).distinct().select("header_key", F.explode(X.grams(F.col("header_key"))).alias("g"))
    c = g.groupBy("header_key", X.bucket(F.col("g")).alias("bucket")).agg(F.count("*").cast("double").alias("c"))
    norm = c.groupBy("header_key").agg(F.sqrt(F.sum(F.col("c") * F.col("c"))).alias("norm"))
    return c.join(norm, "header_key").select("header_key", "bucket", F.round(F.col("c") / F.col("norm"), 6).alias("w"))


def text_column_vectors(b: Bench, tables=RELATIONAL) -> DataFrame:
    return _sparse(_text_vectors(b, tables), "pos", "x")


def numeric_moments(b: Bench) -> DataFrame:
    return metrics.rounded(profile.moments(b.numbers))


def numeric_zscore_bins(b: Bench) -> DataFrame:
    return metrics.rounded(embed.zscore_bins(b.numbers))


def numeric_histogram_minmax(b: Bench) -> DataFrame:
    return metrics.rounded(embed.zscore_bins(b.numbers, minmax=True))


def header_pairs_099(b: Bench) -> DataFrame:
    v = embed.headers(b.columns).join(b.columns.select("column_id", X.header_norm(F.col("header")).alias("header_key")), "header_key")
    return _pairs(neighbors.block(v.select(F.col("column_id").alias("id"), "vec"), 0.99))


def numeric_pairs_090(b: Bench) -> DataFrame:
    return _pairs(neighbors.block(embed.histograms(b.numbers).withColumnRenamed("column_id", "id"), 0.9))


def text_pairs_075(b: Bench, tables=RELATIONAL) -> DataFrame:
    return _pairs(neighbors.block(_text_vectors(b, tables).withColumnRenamed("column_id", "id"), 0.75))


def embedding_pairs_030(b: Bench) -> DataFrame:
    v = T.table(b.spark, b.sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"))
    p = neighbors.block(v, 0.3).select(F.col("i").cast("long").alias("a"), F.col("j").cast("long").alias("b"), "sim")
    return p.select(F.least("a", "b").alias("i"), F.greatest("a", "b").alias("j"), F.round("sim", 6).alias("sim"))


def jaccard_pairs(b: Bench, tables=RELATIONAL) -> DataFrame:
    return _pairs(neighbors.jaccard(b.values(tables, None), 0.01))


def seed_clusters_given(b: Bench) -> DataFrame:
    keyed = b.columns.select("column_id", X.header_norm(F.col("header")).alias("name_cluster"))
    return seeds.intersect(keyed, b.columns.select("column_id", F.col("kind").alias("value_cluster")))


def stratified_sample_small_k(b: Bench, tables=RELATIONAL) -> DataFrame:
    return sampling.length_stratified(b.values(tables), "column_id", 3)


def stratified_sample_large_k(b: Bench, tables=RELATIONAL) -> DataFrame:
    return sampling.length_stratified(b.values(tables), "column_id", 40)


def stratified_sample_proportional(b: Bench, tables=RELATIONAL) -> DataFrame:
    return sampling.length_stratified(b.values(tables), "column_id", 10, "proportional")


def uniform_sample(b: Bench, tables=RELATIONAL) -> DataFrame:
    return sampling.uniform(b.values(tables), "column_id", 10)


def frequency_sample(b: Bench, tables=RELATIONAL) -> DataFrame:
    return sampling.by_frequency(b.values(tables), "column_id", 10)


def dense_rows(b: Bench) -> DataFrame:
    return sampling.dense_rows(T.table(b.spark, b.sf_dir, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority"), 10)


def context_profile(b: Bench) -> DataFrame:
    return context.cooccurring(b.members, b.columns, 5)


def index_extend(b: Bench) -> DataFrame:
    return b.index.select("value", "label")


def index_lookup(b: Bench) -> DataFrame:
    return valueindex.lookup(b.index, b.values(), "column_id")


def index_fallback(b: Bench) -> DataFrame:
    found = valueindex.lookup(b.index, b.values(), "column_id")
    return valueindex.fallback(b.typed, b.columns.select("column_id", "kind"), found, "column_id")


def cluster_sharing(b: Bench) -> DataFrame:
    return valueindex.sharing(b.values(kind=None).join(b.members, "column_id"))


def cluster_order(b: Bench) -> DataFrame:
    return discover.order(b.members)


def seed_propagation(b: Bench) -> DataFrame:
    return annotate.propagate(b.typed, b.members, "discovery", 0.9)


def parse_answers(b: Bench) -> DataFrame:
    return b.calls.select("target", F.array_join(models.parse_answer(F.col("response")), "|").alias("labels"))


def _membership(b: Bench) -> DataFrame:
    return b.columns.select("column_id", X.header_norm(F.col("header")).alias("name_cluster"), F.col("kind").alias("value_cluster"))


def candidates_name(b: Bench) -> DataFrame:
    return annotate.candidates_by("name", _membership(b), b.annotations, annotate.open_columns(b.columns, b.annotations))


def candidates_value(b: Bench) -> DataFrame:
    return annotate.candidates_by("value", _membership(b), b.annotations, annotate.open_columns(b.columns, b.annotations))


def candidates_index(b: Bench) -> DataFrame:
    return annotate.candidates_by_index(b.index, b.values(), annotate.open_columns(b.columns, b.annotations))


def type_aggregation(b: Bench) -> DataFrame:
    a = b.annotations.select("column_id", "kind", F.array("label").alias("accepted"))
    return annotate.aggregate(a.withColumn("source", F.lit("name")).union(a.withColumn("source", F.lit("index"))), "rest", 0.9)


def token_usage(b: Bench) -> DataFrame:
    return metrics.tokens(b.calls)


def calls_by_phase(b: Bench) -> DataFrame:
    return metrics.calls_by_phase(b.calls)


def cost_per_k(b: Bench) -> DataFrame:
    return metrics.rounded(metrics.cost_per_k(b.calls, b.annotations, 2.0, 8.0))


def coverage(b: Bench) -> DataFrame:
    return metrics.rounded(metrics.coverage(b.annotations, b.columns))


def type_count(b: Bench) -> DataFrame:
    return metrics.n_types(b.annotations)


def hit_rate(b: Bench) -> DataFrame:
    return metrics.rounded(metrics.hit_rate(b.annotations, b.verdicts))


def judged_precision(b: Bench) -> DataFrame:
    return metrics.rounded(metrics.judged_precision(b.annotations, b.verdicts))


def confusion(b: Bench) -> DataFrame:
    return metrics.confusion(b.annotations, b.truth)


def prf(b: Bench) -> DataFrame:
    return metrics.rounded(metrics.prf(metrics.confusion(b.annotations, b.truth)))


def prf_by_phase(b: Bench) -> DataFrame:
    truth = b.annotations.select("column_id", "phase", F.col("truth").alias("label"))
    return metrics.rounded(metrics.prf(metrics.confusion(b.annotations, truth, ["phase"])))


def representatives(b: Bench) -> DataFrame:
    return judge.representatives(b.annotations)


def redundancy(b: Bench) -> DataFrame:
    return metrics.types_on(b.annotations, b.annotations.where("phase = 'discovery'"))


def synthetic_truth(b: Bench) -> DataFrame:
    return judge.synthetic_truth(b.verdicts, b.truth)


def pair_agreement(b: Bench) -> DataFrame:
    return downstream.agreement(b.pairs, b.annotations)


def pair_agreement_annotated(b: Bench) -> DataFrame:
    return downstream.agreement(b.pairs, b.annotations, "annotated")


def pair_similarity(b: Bench) -> DataFrame:
    return metrics.rounded(downstream.pair_similarity(b.pairs, b.annotations))


def overlap_filter(b: Bench) -> DataFrame:
    return downstream.filter_pairs(b.pairs, b.annotations)


def suspect_columns(b: Bench) -> DataFrame:
    twice = b.annotations.select("column_id", "label").union(b.annotations.select("column_id", "truth"))
    return downstream.suspect_columns(twice)


def _streamed(b: Bench, make, mode: str) -> DataFrame:
    """The whole table as a stream, run to its end; rows that are appended go to Parquet in the shared folder, tables of results to memory."""
    import uuid

    events = b.spark.readStream.schema(T.table(b.spark, b.sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp")).schema).option("pathGlobFilter", "*.parquet").parquet(f"{b.sf_dir}/events.parquet*")
    name = f"live_{uuid.uuid4().hex[:8]}"
    if mode == "append":
        made, base = make(events), f"{shared_dir(b.spark)}/{name}"
        q = made.writeStream.outputMode(mode).format("parquet").option("path", f"{base}/rows").option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start()
        q.awaitTermination()
        return b.spark.read.schema(made.schema).parquet(f"{base}/rows")
    q = make(events).writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return b.spark.table(name)


def stream_windows(b: Bench) -> DataFrame:
    got = _streamed(b, lambda e: live.windows(e).drop("users"), "complete")
    return got.select(F.col("window.start").cast("timestamp_ntz").alias("w"), "event_type", "n", F.round("total", 6).alias("total"))


def stream_sessions(b: Bench) -> DataFrame:
    got = _streamed(b, live.sessions, "complete")
    return got.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("started"), "n", F.round("total", 6).alias("total"))


def stream_deduplicated(b: Bench) -> DataFrame:
    """Events sent twice, counted once."""
    got = _streamed(b, lambda e: live.deduplicated(e.union(e), "3650 days").select("event_type", "event_id"), "append")
    return got.groupBy("event_type").agg(F.count("*").alias("n"))


def drift_by_day(b: Bench) -> DataFrame:
    """How like the whole column the values of each day are."""
    events = T.table(b.spark, b.sf_dir, "events")
    cells = events.where("value is not null").select(F.lit("value").alias("column_id"), F.lit("num").alias("kind"), F.col("value").cast("double").alias("num"))
    m, vector = profile.moments(cells).first(), embed.histograms(cells).first()["vec"]
    days = events.where("value is not null").select(F.date_trunc("day", "ts").alias("window"), F.col("value").cast("double").alias("value"))
    got = live.histogram_drift(days, vector, m["mean"], m["deviation"])
    return got.select(F.col("window").cast("timestamp_ntz").alias("w"), F.round("similarity", 6).alias("similarity"))


def running_tokens(b: Bench) -> DataFrame:
    return downstream.running_tokens(b.calls)


def calls_by_role_cube(b: Bench) -> DataFrame:
    return b.calls.cube("role", "phase").agg(F.count("*").alias("n_calls"))


def table_rows_regions(b: Bench) -> DataFrame:
    """Three rows of nation as prompts show them: the values of one row stand together."""
    rows = C.base_rows(b.spark, b.sf_dir, ("nation",))
    heads = context.table_rows(b.columns.where("table_id = 'nation'"), rows, 3).select("table_id", F.expr("inline(arrays_zip(heads[0].values, heads[1].values, heads[2].values))"))
    return heads.toDF("table_id", "nk", "nn", "rk").select("table_id", F.col("nk").cast("long").alias("nk"), "nn", F.col("rk").cast("long").alias("rk"))


def overlap_sketch(b: Bench) -> DataFrame:
    """Overlaps of joinable columns from sketches alone."""
    values = b.values(("orders", "lineitem", "customer"), None)
    return metrics.rounded(neighbors.theta_overlap(values, neighbors.jaccard(values, 0.5)))


CHECKED = (
    column_catalog, column_values_orders, collection_stats, distinct_counts, length_profile, header_ngram_vectors, text_column_vectors, numeric_moments, numeric_zscore_bins, numeric_histogram_minmax,
    header_pairs_099, numeric_pairs_090, text_pairs_075, embedding_pairs_030, jaccard_pairs, seed_clusters_given, stratified_sample_small_k, stratified_sample_large_k, stratified_sample_proportional,
    uniform_sample, frequency_sample, dense_rows, context_profile, index_extend, index_lookup, index_fallback, cluster_sharing, cluster_order, seed_propagation, parse_answers, candidates_name,
    candidates_value, candidates_index, type_aggregation, token_usage, calls_by_phase, cost_per_k, coverage, type_count, hit_rate, judged_precision, confusion, prf, prf_by_phase, representatives,
    redundancy, synthetic_truth, pair_agreement, pair_agreement_annotated, pair_similarity, overlap_filter, suspect_columns, stream_windows, stream_sessions,
    stream_deduplicated, drift_by_day, running_tokens, calls_by_role_cube, table_rows_regions, overlap_sketch,
)

#: What the SQL holds over RELATIONAL or orders only, here over all tables, long texts and keys included; no SQL, see the tests.
WHOLE = {
    "column_values_all_tables": column_values_orders, "text_column_vectors_all_tables": text_column_vectors, "text_pairs_075_all_tables": text_pairs_075, "jaccard_pairs_all_tables": jaccard_pairs,
    "stratified_sample_small_k_all_tables": stratified_sample_small_k, "stratified_sample_large_k_all_tables": stratified_sample_large_k, "stratified_sample_proportional_all_tables": stratified_sample_proportional,
    "uniform_sample_all_tables": uniform_sample, "frequency_sample_all_tables": frequency_sample,
}


def queries() -> dict[str, Query]:
    def of(f, *tables) -> Query:
        return lambda spark, sf_dir: f(Bench(spark, sf_dir), *tables)

    def held(f) -> Query:
        return lambda spark, sf_dir: f(Bench(spark, sf_dir).only_held())

    return {f.__name__: held(f) if f.__name__ in HELD_QUERIES else of(f) for f in CHECKED} | {name: of(f, tuple(T.SCHEMAS)) for name, f in WHOLE.items()}
