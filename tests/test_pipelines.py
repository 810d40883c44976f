"""How the framework behaves with the offline model, and that queries agree with their SQL."""

import glob
import os

import duckdb
import pytest

import __spark_entry__ as entry
from coltypes.operators import cascade, metrics
from coltypes.plans import experiments as E
from coltypes.plans import oracles, registry


def rows_of(df):
    cols = sorted(df.columns)
    return cols, sorted(tuple("" if v is None else f"{v:.6f}" if isinstance(v, float) else str(v) for v in r) for r in df.select(*[f"`{c}`" for c in cols]).collect())


@pytest.mark.parametrize("name", ["column_catalog", "numeric_zscore_bins", "header_pairs_099", "text_pairs_075", "stratified_sample_large_k", "stratified_sample_proportional", "context_profile", "index_extend", "candidates_index", "prf_by_phase", "stream_sessions"])
def test_query_equals_sql(spark, tiny, name):
    con = duckdb.connect()
    for f in glob.glob(f"{tiny}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    cols, got = rows_of(registry.queries()[name](spark, tiny))
    q = con.execute(registry.oracle_sql()[name])
    names = [d[0] for d in q.description]
    assert sorted(names) == cols
    want = sorted(tuple("" if v is None else f"{v:.6f}" if isinstance(v, float) else str(v) for v in (r[names.index(c)] for c in cols)) for r in q.fetchall())
    assert got == want


def test_queries_over_all_tables_equal_brute_force(spark, tiny):
    """Values by DuckDB, everything else by plain Python."""
    con = duckdb.connect()
    for f in glob.glob(f"{tiny}/*.parquet"):
        con.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    sets, counts = {}, {}
    for c, kind, v, n in con.execute(f"select column_id, kind, value, count(*) from ({oracles.LONG}) group by all").fetchall():
        sets.setdefault(c, set()).add(v)
        if kind == "text":
            counts.setdefault(c, {})[v] = n
    run = lambda name: registry.queries()[f"{name}_all_tables"](spark, tiny).collect()
    got = {(r["i"], r["j"]): r["sim"] for r in run("jaccard_pairs")}
    want = {(i, j): len(a & b) / len(a | b) for i, a in sets.items() for j, b in sets.items() if i < j}
    assert got == pytest.approx({k: v for k, v in want.items() if round(v, 6) >= 0.01}, abs=1e-6)
    assert got["lineitem.l_orderkey", "orders.o_orderkey"] > 0.9
    assert {(r["column_id"], r["value"]): r["n"] for r in run("column_values")} == {(c, v): n for c, own in counts.items() for v, n in own.items()}
    for name, k in (("stratified_sample_small_k", 3), ("stratified_sample_large_k", 40), ("stratified_sample_proportional", 10), ("uniform_sample", 10), ("frequency_sample", 10)):
        sample = {}
        for r in run(name):
            sample.setdefault(r["column_id"], []).append(r["value"])
        assert {c: len(v) for c, v in sample.items()} == {c: min(k, len(v)) for c, v in counts.items()}
        assert all(set(v) <= set(counts[c]) and len(set(v)) == len(v) for c, v in sample.items())
        if name == "frequency_sample":
            assert all(sorted((counts[c][x] for x in v), reverse=True) == sorted(counts[c].values(), reverse=True)[:k] for c, v in sample.items())
    vectors = {}
    for r in run("text_column_vectors"):
        vectors.setdefault(r["column_id"], {})[r["pos"]] = r["x"]
    assert set(vectors) == set(counts)
    dot = lambda a, b: sum(x * b.get(p, 0) for p, x in a.items())
    cosines = {(i, j): dot(a, b) / (dot(a, a) * dot(b, b)) ** 0.5 for i, a in vectors.items() for j, b in vectors.items() if i < j}
    near = {(r["i"], r["j"]): r["sim"] for r in run("text_pairs_075")}
    assert near == pytest.approx({p: x for p, x in cosines.items() if p in near}, abs=1e-4) and {p for p, x in cosines.items() if x > 0.7501} <= set(near)


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_flagship(spark):
    got = entry.entry(spark).collect()
    assert got and all(r["n_columns"] >= 2 for r in got)


def test_cascade_invariants(spark, tiny):
    p = E.prepared(spark, tiny, "OPS")
    r = E.result(spark, tiny, "OPS", "cascade")
    a = r.annotations.collect()
    kinds = {c["column_id"]: c["kind"] for c in p.columns.collect()}
    assert all(not (kinds[x["column_id"]] == "num" and x["source"] in ("value", "index")) for x in a)
    phases = {}
    for x in a:
        phases.setdefault(x["column_id"], set()).add((x["phase"], x["threshold"]))
    assert all(len(v) == 1 for v in phases.values())
    plain = E.result(spark, tiny, "OPS", "guided")
    out = lambda y: metrics.tokens(y.calls).first()["out_tokens"]
    assert out(r) < out(plain) / 2
    assert metrics.n_types(r.annotations).first()[0] < metrics.n_types(plain.annotations).first()[0]
    assert metrics.tokens(r.calls).first()["n_calls"] < p.columns.count()
    fixed = {t: metrics.coverage(E.result(spark, tiny, "OPS", f"fixed({t})").annotations, p.columns).first()[0] for t in (0.75, 0.99)}
    assert fixed[0.99] <= fixed[0.75]


def test_match_pairs_are_all_pairs(spark, tiny, monkeypatch):
    monkeypatch.setattr(E, "METHODS", ("cascade",))
    tables = {}
    for c in E.prepared(spark, tiny, "OPS").columns.collect():
        tables.setdefault(c["truth"], []).append(c["table_id"])
    want = sum(x < y for own in tables.values() for x in own for y in own)
    got = E.exp_match_pairs(spark, tiny).collect()
    assert [r["n_pairs"] for r in got] == [want] and want > 1563


def test_captured_columns_leave(spark):
    m = spark.createDataFrame([("a", "s"), ("b", "s")], "column_id string, seed_cluster string")
    ann = spark.createDataFrame([("a", "T")], "column_id string, label string")
    left, siblings = cascade.capture(m, ann)
    assert [r["column_id"] for r in left.collect()] == ["b"] and [r["label"] for r in siblings.collect()] == ["T"]


def test_import_needs_no_session():
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; e.queries(); e.oracle_sql()"], cwd=root, capture_output=True, text=True)
    assert done.returncode == 0, done.stderr[-500:]


def test_sql_functions(spark, tiny):
    from coltypes.functions import sqlapi

    assert E.sql_functions(spark, tiny).count() == 1
    sqlapi.register(spark)
    got = spark.sql("select len from length_sample(array('a','bb','cc','ddd'), 3)").collect()
    assert sorted(r[0] for r in got) == [1, 2, 3]
    assert abs(spark.sql("select cosine_of(array(1d, 0d), array(1d, 1d))").first()[0] - 0.5**0.5) < 1e-9
