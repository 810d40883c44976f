"""Worked examples and properties of the engine's operators."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from coltypes.functions import exprs
from coltypes.functions.encoders import NgramEncoder
from coltypes.operators import annotate, communities, context, downstream, embed, judge, metrics, models, neighbors, profile, prompts, sampling, seeds, valueindex


def frame(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


def test_header_forms_and_vectors(spark):
    df = frame(spark, [("c_custkey",), ("custKey",), ("Cust-Key",)], "header string")
    assert [r[0] for r in df.select(exprs.header_norm(F.col("header"))).collect()] == ["custkey"] * 3
    one = NgramEncoder().encode(["custkey", "cust_keys"])
    assert np.allclose(np.linalg.norm(one, axis=1), 1)
    native = frame(spark, [("custkey",)], "t string").select(F.explode(exprs.grams(F.col("t"))).alias("g")).groupBy(exprs.bucket(F.col("g")).alias("b")).count().collect()
    v = np.zeros(256)
    for r in native:
        v[r["b"]] = r["count"]
    assert np.allclose(v / np.linalg.norm(v), one[0])


STRATA = [("k", v) for v in ["AFRICA", "EUROPE", "ASIA", "AMERICA", "MIDDLE EAST"] + [f"NATION_{i}" for i in range(25)]]


@pytest.mark.parametrize(("k", "lengths"), [(4, [4, 6, 8, 9]), (6, [4, 6, 7, 8, 9, 11]), (10, [4, 6, 6, 7, 8, 8, 9, 9, 9, 11]), (40, None)])
def test_length_strata(spark, k, lengths):
    got = sampling.length_stratified(frame(spark, STRATA, "key string, value string"), "key", k).collect()
    assert len(got) == min(k, 30)
    if lengths:
        assert sorted(r["len"] for r in got) == lengths


@settings(max_examples=4, deadline=None)
@given(st.sets(st.text("ab", min_size=1, max_size=6), min_size=1, max_size=30), st.integers(1, 12))
def test_strata_properties(spark, values, k):
    got = sampling.length_stratified(frame(spark, [("x", v) for v in values], "key string, value string"), "key", k).collect()
    shown, all_lengths = {len(r["value"]) for r in got}, {len(v) for v in values}
    assert len(got) == min(k, len(values))
    assert len(shown) == min(k, len(all_lengths))


def test_histograms(spark):
    rows = [("a", "num", str(x), float(x)) for x in range(50)] + [("b", "num", str(3 * x + 7), 3.0 * x + 7) for x in range(50)] + [("c", "num", "5", 5.0)] * 3
    cells = frame(spark, rows, "column_id string, kind string, value string, num double")
    v = {r["column_id"]: np.array(r["vec"]) for r in embed.histograms(cells).collect()}
    assert np.allclose(v["a"], v["b"])
    assert all(abs(x.sum() - 1) < 1e-9 for x in v.values())
    assert v["c"][50] == 1


def test_communities_path_and_rounds(spark):
    nodes = {n: (1, n) for n in "1234"}
    pairs = [("1", "2"), ("2", "3"), ("3", "4")]
    assert communities.greedy(nodes, pairs) == {"1": "1", "2": "1", "3": "1"}
    rng = np.random.default_rng(3)
    for _ in range(3):
        n = 14
        nodes = {f"n{i:02d}": (int(rng.integers(1, 3)), f"n{i:02d}") for i in range(n)}
        pairs = [(f"n{i:02d}", f"n{j:02d}") for i in range(n) for j in range(i + 1, n) if rng.random() < 0.2]
        want = communities.greedy(nodes, pairs)
        nf = frame(spark, [(k, *v) for k, v in nodes.items()], "id string, weight long, first string")
        got = {r["id"]: r["community"] for r in communities.rounds(nf, frame(spark, pairs, "i string, j string")).collect()}
        assert got == want


def test_pair_methods_agree(spark):
    rng = np.random.default_rng(1)
    base = rng.normal(size=(6, 8))
    rows = [(f"v{i:02d}", (base[i % 6] + 0.15 * rng.normal(size=8)).tolist()) for i in range(30)]
    v = frame(spark, rows, "id string, vec array<double>")
    exact = {(r["i"], r["j"]) for r in neighbors.exact(v, 0.9).collect()}
    assert exact
    assert {(r["i"], r["j"]) for r in neighbors.block(v, 0.9, 7).collect()} == exact
    found = {(r["i"], r["j"]) for r in neighbors.lsh(v, 0.9, 16, 2.0).collect()}
    assert found <= exact
    assert len(found) >= 0.9 * len(exact)


def test_seed_intersection(spark):
    names = frame(spark, [("a", "n1"), ("b", "n1"), ("c", "n1"), ("d", "n2")], "column_id string, name_cluster string")
    values = frame(spark, [("a", "v1"), ("b", "v1"), ("c", "v2"), ("d", "v1")], "column_id string, value_cluster string")
    got = {r["column_id"]: r["seed_cluster"] for r in seeds.intersect(names, values).collect()}
    assert got == {"a": "a", "b": "a"}


def test_context_profile(spark):
    cols = [("customer.c_custkey", "customer", "c_custkey", 0, "num"), ("customer.c_name", "customer", "c_name", 1, "text"), ("orders.o_custkey", "orders", "o_custkey", 1, "num"), ("orders.o_status", "orders", "o_status", 2, "text")]
    m = frame(spark, [("customer.c_custkey", "s"), ("orders.o_custkey", "s")], "column_id string, seed_cluster string")
    got = [(r["header"], r["n_tables"], r["of_tables"]) for r in context.cooccurring(m, frame(spark, cols, "column_id string, table_id string, header string, ordinal int, kind string")).orderBy("rank").collect()]
    assert got == [("c_name", 1, 2), ("o_status", 1, 2)]


def test_index_and_fallback(spark):
    values = frame(spark, [("c1", "ASIA"), ("c1", "EUROPE")], "seed_cluster string, value string")
    index = valueindex.extend(None, values, frame(spark, [("c1", "R")], "seed_cluster string, label string"))
    more = frame(spark, [("c2", "ASIA"), ("c2", "x"), ("c3", "y")], "seed_cluster string, value string")
    found = valueindex.lookup(index, more)
    assert [(r[0], r[1]) for r in found.collect()] == [("c2", "R")]
    types = frame(spark, [("text", "R"), ("num", "N")], "kind string, label string")
    kinds = frame(spark, [("c2", "text"), ("c3", "text"), ("c4", "num")], "seed_cluster string, kind string")
    assert sorted((r[0], r[1]) for r in valueindex.fallback(types, kinds, found).collect()) == [("c3", "R"), ("c4", "N")]
    again = valueindex.extend(index, values, frame(spark, [("c1", "R")], "seed_cluster string, label string"))
    assert again.count() == index.count()


def test_answers(spark):
    texts = ['{"answer": ["Nation Name", " nation name", "string", ""]}', "not json", '{"answer": "x"}', '{"answer": ["A b", "C"]}']
    assert models.parse(texts[0]) == ["Nation Name"]
    assert models.parse(texts[1]) == models.parse(texts[2]) == []
    got = [r[0] for r in frame(spark, [(t,) for t in texts], "t string").select(models.parse_answer(F.col("t"))).collect()]
    assert got[0] == ["Nation Name"] and got[1] == [] and got[3] == ["A b", "C"]


def test_rule_model_reuses_and_abstains():
    m = models.RuleModel()
    request = {"headers": ["n_name"], "sample": ["NATION_1", "NATION_22"], "kind": "text", "candidates": [], "context": []}
    first = m.propose(request)[0]
    assert models.concept(first) == "Nation Code Name"
    assert m.propose(request | {"headers": ["nation"], "candidates": [first]}) == [first]
    check = {"header": "x", "sample": ["NATION_1"], "kind": "text", "candidates": ["Part Brand"], "table": ""}
    assert m.verify(check) == []
    assert "NATION_1" in prompts.closed_set(check)


def test_numbers_use_names_only(spark):
    checked = frame(spark, [("c", "index", "num", ["A"]), ("c", "name", "num", ["B"]), ("t", "index", "text", ["A"])], "column_id string, source string, kind string, accepted array<string>")
    assert sorted((r["column_id"], r["label"]) for r in annotate.aggregate(checked, "rest", 0.9).collect()) == [("c", "B"), ("t", "A")]


def test_measures(spark):
    a = frame(spark, [("c1", "a"), ("c1", "b"), ("c2", "a"), ("c3", "c")], "column_id string, label string")
    valid = frame(spark, [("c1", "a", True), ("c1", "b", False), ("c2", "a", False), ("c3", "c", True)], "column_id string, label string, valid boolean")
    assert metrics.hit_rate(a, valid).first()[0] == pytest.approx(2 / 3)
    assert metrics.judged_precision(a, valid).first()[0] == 0.5
    truth = frame(spark, [("c1", "a"), ("c1", "d"), ("c2", "b"), ("c3", "c")], "column_id string, label string")
    r = metrics.prf(metrics.confusion(a, truth)).first()
    assert (r["tp"], r["fp"], r["fn"], r["p"], r["r"], r["f1"]) == (2, 2, 2, 0.5, 0.5, 0.5)


def test_pair_measures(spark):
    pairs = frame(spark, [("a", "b"), ("c", "d"), ("a", "e")], "left_id string, right_id string")
    ann = frame(spark, [("a", "x"), ("b", "x"), ("c", "x"), ("c", "y"), ("d", "y")], "column_id string, label string")
    r = downstream.agreement(pairs, ann).first()
    assert (round(r["pct_shared"], 4), round(r["pct_same"], 4), r["n_pairs"]) == (66.6667, 33.3333, 3)
    assert downstream.filter_pairs(pairs, ann).count() == 2
    assert downstream.suspect_columns(ann).first()["column_id"] == "c"


def test_judge(spark):
    pooled = judge.pool({"m": frame(spark, [("c", "Nation Code Title"), ("c", "string")], "column_id string, label string")})
    truth = frame(spark, [("c", "Nation Code Name"), ("c", "Part Name")], "column_id string, label string")
    v = {r["label"]: r["valid"] for r in judge.verdicts(pooled, truth).collect()}
    assert v == {"Nation Code Title": True, "string": False}
    made = {r["label"] for r in judge.synthetic_truth(judge.verdicts(pooled, truth), truth).collect()}
    assert made == {"Nation Code Name", "Other_1"}


def test_profile_skips_blanks(spark, tmp_path):
    from coltypes.sources import cells_source, tables

    frame(spark, [(1, " ", [1]), (2, "x", [2]), (None, None, None)], "a int, b string, c array<int>").coalesce(1).write.parquet(str(tmp_path / "t.parquet"))
    cells_source.register(spark)
    file = str(next((tmp_path / "t.parquet").glob("*.parquet")))
    got = spark.read.format("cells").option("paths", file).load()
    assert got.where("header = 'a'").count() == 2 and got.where("header = 'c'").count() == 0
    assert tables.flat(spark.read.parquet(str(tmp_path / "t.parquet"))).columns == ["a", "b"]
    cells = frame(spark, [("x", "text", "a", None), ("x", "text", "a", None)], "column_id string, kind string, value string, num double")
    assert [(r["value"], r["n"]) for r in profile.column_values(cells).collect()] == [("a", 2)]
