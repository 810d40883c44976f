"""Findings of the third review."""

import os
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from coltypes.operators import discover, neighbors, sampling, valueindex
from coltypes.plans import experiments as E
from coltypes.plans import registry


def test_all_pairs_are_found_however_many_vectors(spark):
    rng = np.random.default_rng(3)
    m = rng.standard_normal((20_100, 48))
    m /= np.linalg.norm(m, axis=1)[:, None]
    beside = rng.standard_normal((400, 48))
    beside -= (beside * m[:400]).sum(axis=1)[:, None] * m[:400]
    beside /= np.linalg.norm(beside, axis=1)[:, None]
    m[400:800] = m[:400] * 0.81 + beside * (1 - 0.81**2) ** 0.5
    v = spark.createDataFrame([(f"v{k:05d}", x.tolist()) for k, x in enumerate(m)], "id string, vec array<double>").repartition(4)
    want = set()
    for at in range(0, len(m), 2000):
        p, q = np.nonzero(np.round(m[at : at + 2000] @ m.T, 6) >= 0.8)
        want |= {(f"v{i + at:05d}", f"v{j:05d}") for i, j in zip(p.tolist(), q.tolist(), strict=True) if i + at < j}
    got = neighbors.pairs(v, 0.8).where(F.round("sim", 6) >= 0.8).select("i", "j").collect()
    assert len(want) >= 400 and len(got) == len(want) and {tuple(r) for r in got} == want


def test_values_that_the_same_columns_hold_are_one(spark):
    rows = [("a", f"{k}") for k in range(900)] + [("b", f"{k}") for k in range(300, 1200)] + [("c", f"{k}") for k in range(5)] + [("d", "x"), ("d", "äy")]
    values = spark.createDataFrame([(c, "text", v, 1, len(v)) for c, v in rows], "column_id string, kind string, value string, n long, len int")
    sets = valueindex.column_sets(values)
    holders, want = defaultdict(set), defaultdict(int)
    for c, v in rows:
        holders[v].add(c)
    for c, v in rows:
        want[c, len(v), frozenset(holders[v])] += 1
    got, members = sets.collect(), defaultdict(set)
    for r in got:
        members[r["value"]].add(r["column_id"])
    assert {(r["column_id"], r["len"], frozenset(members[r["value"]])): r["n"] for r in got} == want and len(got) == len(want) < 20
    assert {tuple(r) for r in valueindex.sharing(sets, "column_id").collect()} == {tuple(r) for r in valueindex.sharing(values, "column_id").collect()}


@pytest.mark.parametrize("way", ["stratified", "uniform", "frequency"])
def test_discovery_from_sets_and_strata_is_the_same(spark, tiny, way):
    p = E.prepared(spark, tiny, "TXT")
    inside = p.level(0.75).where("seed_cluster is not null").select("column_id", "seed_cluster")
    config = discover.DiscoverConfig(sampling=way, k=6)
    held = p.held(6)
    plain = discover.run(inside, p.columns, p.values, config=config)
    other = discover.run(inside, p.columns, p.values, config=config, held_values=held)
    assert plain.calls.count() > 3 and sorted(plain.calls.collect()) == sorted(other.calls.collect())
    assert other.own.count() < plain.own.count()
    wanted = p.columns.where("kind = 'text'")
    found = [annotated(x, v, wanted) for x, v in ((plain, p.values), (other, p.sets))]
    assert found[0] and found[0] == found[1]


def annotated(d, values, wanted):
    index = valueindex.extend(None, d.own, d.types)
    return {tuple(r) for r in E.annotate.candidates_by_index(index, values, wanted).collect()}


def test_dense_rows_of_groups(spark):
    rng = np.random.default_rng(5)
    rows = [(None if k % 7 == 0 else f"g{k % 3}", None if rng.random() < 0.4 else int(rng.integers(9)), None if rng.random() < 0.4 else f"t{rng.integers(4)}") for k in range(4000)]
    df = spark.createDataFrame(rows, "g string, a int, b string").repartition(5)
    got = sampling.dense_rows(df, 10, by=["g"], place="place").collect()
    for g in (None, "g0", "g1", "g2"):
        own = df.where(F.col("g").eqNullSafe(g))
        assert sorted(map(str, [r[:3] for r in got if r["g"] == g])) == sorted(map(str, [tuple(r) for r in sampling.dense_rows(own, 10).collect()]))
        assert sorted(r["place"] for r in got if r["g"] == g) == list(range(1, 11))


def test_new_documents_are_annotated_by_values_of_ops_too(spark, tiny, tmp_path, monkeypatch):
    for f in os.listdir(tiny):
        if f != "documents.parquet":
            os.symlink(f"{tiny}/{f}", tmp_path / f)
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    docs.withColumn("lang", F.lit("BUILDING")).write.parquet(str(tmp_path / "documents.parquet"))
    app = spark.sparkContext.applicationId
    for c in ("OPS", "TXT"):
        monkeypatch.setitem(E._RUNS, (app, str(tmp_path), c, "cascade", "strong", None), E.result(spark, tiny, c, "cascade"))
        monkeypatch.setitem(E._PREPARED, (app, str(tmp_path), c), E.prepared(spark, tiny, c))
    got = {tuple(x)[:2] for x in registry.queries()["stream_incremental_annotation"](spark, str(tmp_path)).collect()}
    p = E.prepared(spark, tiny, "OPS")
    holders = p.values.where("value = 'BUILDING'").select("column_id")
    want = {("new.lang", r["label"]) for r in E.result(spark, tiny, "OPS", "cascade").annotations.join(holders, "column_id").collect()}
    assert want and {x for x in got if x[0] == "new.lang"} == want
