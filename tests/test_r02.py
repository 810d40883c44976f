"""What the reviewer of round 2 found: work that grew with more than the input, and queries that read no table."""

import os
from hashlib import md5

import numpy as np
from pyspark.sql import functions as F

from coltypes.functions.encoders import NgramEncoder
from coltypes.operators import cascade, communities, neighbors
from coltypes.plans import experiments as E
from coltypes.plans import registry
from coltypes.sources import collection as C

QUERIES = registry.queries()


def test_collection_stats_prepare_nothing(spark, tiny):
    E.clear()
    got = {r["collection"]: r for r in QUERIES["all_collection_stats"](spark, tiny).collect()}
    assert not E._PREPARED and set(got) == set(E.COLLECTIONS)
    assert got["MIXED"]["max_rows"] == spark.read.parquet(f"{tiny}/lineitem.parquet").count()


def test_only_what_is_asked_for_is_prepared(spark, tiny):
    p = cascade.Prepared(C.build(spark, tiny, "MULTI"))
    assert not {"values", "rows", "views"} & set(vars(p))
    drawn = {r["column_id"]: r["sample"] for r in p.drawn(4).collect()}
    held = {(r["column_id"], r["value"]) for r in p.values.collect()}
    assert set(drawn) == {c for c, _ in held} and all(s == sorted(s) and len(s) <= 4 and {(c, v) for v in s} <= held for c, s in drawn.items())


def test_encoder_counts_grams_of_all_texts_at_once():
    texts = ["", "a", "ab", "\x00\x00b", "äöü€x", "ÿÿĀ", "\U0001f600 日本語", "word " * 300_000, *(f"v{k} é" for k in range(3000))]
    got = NgramEncoder().encode(texts)
    for k in (0, 1, 2, 3, 4, 5, 6, 8, 2500):
        marked = f"^{texts[k]}$"
        v = np.zeros(256)
        for n in (2, 3):
            for i in range(len(marked) - n + 1):
                v[int(md5(marked[i : i + n].encode()).hexdigest()[:8], 16) % 256] += 1
        assert np.array_equal(got[k], v / np.sqrt((v * v).sum()))
    e = NgramEncoder()
    e.encode(["abc"])
    assert e.tables and not e.__getstate__()["tables"]


def test_appended_rows_of_a_stream_are_not_held_by_the_driver(spark, tiny):
    got = QUERIES["stream_deduplicated"](spark, tiny)
    assert got.inputFiles() and {r["event_type"]: r["n"] for r in got.collect()} == {r["event_type"]: r["count"] for r in spark.read.parquet(f"{tiny}/events.parquet").groupBy("event_type").count().collect()}


def test_example_reads_nation(spark, tiny):
    own, read = E.example(spark), E.example(spark, tiny)
    assert any(f.endswith("nation.parquet") for f in read.cells.inputFiles())
    assert sorted(map(str, own.cells.collect())) == sorted(map(str, read.cells.collect())) and sorted(map(str, own.rows.collect())) == sorted(map(str, read.rows.collect()))


def test_catalog_of_held_columns(spark, tiny, tmp_path):
    assert {r[0] for r in C.held_columns(spark, tiny).select("column_id").collect()} == {r[0] for r in C.base_columns(spark).select("column_id").collect()}
    for name in C.T.SCHEMAS:
        df = spark.read.parquet(f"{tiny}/{name}.parquet").limit(5)
        if name == "nation":
            df = df.withColumn("n_name", F.lit(" ")).withColumn("n_regionkey", F.lit(None).cast("int"))
        df.write.parquet(str(tmp_path / f"{name}.parquet"))
    left = {r[0] for r in C.base_columns(spark).select("column_id").collect()} - {"nation.n_name", "nation.n_regionkey"}
    assert {r[0] for r in C.held_columns(spark, str(tmp_path)).select("column_id").collect()} == left
    assert QUERIES["calls_by_phase"](spark, str(tmp_path)).where("role is null").first()["n_calls"] == len(left)


def test_communities_without_pairs(spark):
    rng = np.random.default_rng(3)
    points = rng.standard_normal((400, 8))
    points[50:60] = points[7]
    points[99] = 0
    v = spark.createDataFrame([(f"v{k}", f"{k:04d}", p.tolist()) for k, p in enumerate(points)], "id string, first string, vec array<double>")
    pairs = [(r["i"], r["j"]) for r in neighbors.block(v.select("id", "vec"), 0.6).collect()]
    want = communities.greedy({f"v{k}": (1, f"{k:04d}") for k in range(400)}, pairs)
    old, communities.CELLS = communities.CELLS, 3000
    try:
        assert {r["id"]: r["community"] for r in communities.of_vectors(v, 0.6).collect()} == want
    finally:
        communities.CELLS = old
    assert communities.of_vectors(v.limit(0), 0.6).count() == 0


def test_documents_that_are_a_folder_are_annotated(spark, tiny, tmp_path):
    for f in os.listdir(tiny):
        if f != "documents.parquet":
            os.symlink(f"{tiny}/{f}", tmp_path / f)
    spark.read.parquet(f"{tiny}/documents.parquet").repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    app = spark.sparkContext.applicationId
    r = E.result(spark, tiny, "TXT", "cascade")
    E._RUNS[app, str(tmp_path), "TXT", "cascade", "strong", None], E._PREPARED[app, str(tmp_path), "TXT"] = r, E.prepared(spark, tiny, "TXT")
    got = {tuple(x)[:2] for x in QUERIES["stream_incremental_annotation"](spark, str(tmp_path)).collect()}
    assert got and got == {tuple(x)[:2] for x in QUERIES["stream_incremental_annotation"](spark, tiny).collect()}
