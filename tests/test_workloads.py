"""Every workload that has no SQL: what must hold of its rows, or the same by plain Python."""

import itertools
import json
import threading
from collections import defaultdict
from http.server import BaseHTTPRequestHandler, HTTPServer

import numpy as np
import pytest
from pyspark.sql import functions as F

from coltypes.operators import baselines, cascade, context, judge, models, neighbors, prompts, valueindex
from coltypes.plans import experiments as E
from coltypes.plans import registry
from coltypes.sources import collection as C
from coltypes.streaming import live

QUERIES = registry.queries()


def run(spark, tiny, name):
    return [r.asDict() for r in QUERIES[name](spark, tiny).collect()]


# ---- table rows in prompts


def test_prompt_rows_are_rows(spark, tiny):
    built = C.build(spark, tiny, "OPS")
    heads = {r["table_id"]: r["heads"] for r in context.table_rows(built.columns, built.rows, 10).collect()}
    orders = {(str(r["o_orderkey"]), str(r["o_custkey"]), r["o_orderstatus"]) for r in spark.read.parquet(f"{tiny}/orders.parquet").collect()}
    seen = 0
    for table, columns in heads.items():
        assert len({len(c["values"]) for c in columns}) == 1 and 1 <= len(columns[0]["values"]) <= 10
        if table.startswith("orders_"):
            by = [c["values"] for c in columns]
            assert all(x in orders for x in zip(by[0], by[1], by[2], strict=True))
            seen += 1
    assert seen > 1


def test_filled_rows_come_first(spark):
    df = spark.createDataFrame([("t", None, "a"), ("t", "1", "b"), ("t", "2", None), ("t", "3", "c"), ("u", None, None)], "table_id string, x string, y string")
    picked = C.dense_rows(df, 2, by=["table_id"], place="place")
    assert {(r["x"], r["y"]) for r in picked.where("table_id = 't'").collect()} == {("1", "b"), ("3", "c")}
    columns = spark.createDataFrame([("t.x", "t", "x", 0, "text", "t", "x", ""), ("t.y", "t", "y", 1, "text", "t", "y", ""), ("v.z", "v", "z", 0, "text", "v", "z", "")], C.CATALOG)
    rows = spark.createDataFrame([("t", 1, "x", "1"), ("t", 1, "y", None), ("t", 2, "x", "3"), ("t", 2, "y", "c")], "table_id string, place int, base_column string, value string")
    shown = {r["table_id"]: r["s"] for r in context.table_rows(columns, rows, 3).select("table_id", context.shown(F.col("heads")).alias("s")).collect()}
    assert shown == {"t": "x | y\n1 | \n3 | c", "v": "z"}
    assert {r["s"] for r in context.table_rows(columns, None).select(context.shown(F.col("heads")).alias("s")).collect()} == {"x | y", "z"}


# ---- neighbours and shared values


def test_hyperplanes_recall(spark):
    rng = np.random.default_rng(1)
    centres = rng.standard_normal((60, 24))
    points = [(f"p{k:04d}", (centres[k % 60] + rng.standard_normal(24) * 0.35).tolist()) for k in range(900)]
    v = spark.createDataFrame(points, "id string, vec array<double>")
    want = {(r["i"], r["j"]): r["sim"] for r in neighbors.block(v, 0.8).collect()}
    got = {(r["i"], r["j"]): r["sim"] for r in neighbors.hyperplanes(v, 0.8, size=64).collect()}
    assert len(want) > 2000 and set(got) <= set(want) and len(got) >= 0.9 * len(want)
    assert all(abs(got[p] - want[p]) < 1e-9 for p in got)
    assert neighbors.hyperplanes(v.where("false"), 0.8).count() == 0
    small = neighbors.block(v, 0.8, 100)
    assert {(r["i"], r["j"]) for r in small.collect()} == set(want)


def test_edges_by_brute_force(spark):
    rng = np.random.default_rng(2)
    rows = sorted({(f"c{rng.integers(0, 9)}", f"v{rng.integers(0, 40)}") for _ in range(160)} | {(f"c{k}", "hot") for k in range(9)})
    df = spark.createDataFrame(rows, "column_id string, value string")
    owners = defaultdict(set)
    for c, v in rows:
        owners[v].add(c)
    sets = defaultdict(int)
    for own in owners.values():
        if len(own) > 1:
            sets[frozenset(own)] += 1
    got = defaultdict(set)
    weight = {}
    for r in valueindex.edges(df, "column_id", ["value"]).collect():
        got[r["e1"], r["e2"]].add(r["column_id"])
        weight[r["e1"], r["e2"]] = r["n_values"]
    assert {frozenset(m): weight[e] for e, m in got.items()} == dict(sets)
    own = defaultdict(set)
    for c, v in rows:
        own[c].add(v)
    want = {(a, b): len(own[a] & own[b]) / len(own[a] | own[b]) for a, b in itertools.combinations(sorted(own), 2)}
    assert {(r["i"], r["j"]): r["sim"] for r in neighbors.jaccard(df, 0.0).collect()} == pytest.approx(want)


def test_sketches_estimate_overlaps(spark, tiny):
    got = {(r["i"], r["j"]): r["overlap"] for r in run(spark, tiny, "overlap_sketch")}
    b = registry.workbench.Bench(spark, tiny)
    exact = {(r["i"], r["j"]): r["sim"] for r in neighbors.jaccard(b.values(("orders", "lineitem", "customer"), None), 0.5).collect()}
    assert set(got) == set(exact) and got == pytest.approx(exact, abs=0.05)


# ---- models


def test_replay_of_stored_calls(spark, tiny):
    p, r = E.prepared(spark, tiny, "TXT"), E.result(spark, tiny, "TXT", "cascade")
    replayed = models.ReplayModel.of(r.calls)
    again = cascade.run(p.collection, p.config, replayed, replayed, p)
    rows = lambda x: sorted(map(tuple, x.annotations.select("column_id", "label", "phase", "threshold").collect()), key=str)
    assert rows(again) == rows(r)
    assert models.ReplayModel({}, models.RuleModel()).propose({"headers": ["c_custkey"], "sample": [], "kind": "num", "candidates": ["Customer Key"], "context": []}) == ["Customer Key"]


def test_what_a_prompt_does_not_ask_for_is_not_done():
    m = models.RuleModel()
    both = {"headers": ["p_name"], "sample": ["AFRICA", "NATION_3", "ASIA"], "kind": "text", "candidates": ["Part Name", "World Region Name", "Nation Code Name"], "context": []}
    assert m.propose(both) == ["World Region Name", "Nation Code Name"]
    assert m.propose(both | {"guided": False}) == ["Part Name"]
    drawn = {"headers": ["o_orderdate"], "sample": [], "kind": "num", "candidates": ["Order Key"], "context": []}
    assert m.propose(drawn | {"strict": False}) == ["Order Key"] and m.propose(drawn) != ["Order Key"]
    asked = {"header": "orderline", "sample": ["1"], "kind": "num", "candidates": ["Order Line Number", "Tax Rate"], "table": "l_orderkey | orderline"}
    assert m.verify(asked) == ["Order Line Number"]


def test_judge_by_its_own_rules():
    j = models.RuleJudge()
    ask = lambda label, header, sample, table="": j.judge({"label": label, "header": header, "sample": sample, "table": table})
    assert ask("Customer Key", "c_custkey", ["1", "2"]) and ask("Customer Identifier", "cust_keys", ["1"])
    assert not ask("Supplier Key", "c_custkey", ["1"], "c_custkey | c_name") and not ask("value", "value", ["1"]) and not ask(" ", "x", [])
    assert ask("Web Page Link", "u", ["https://a.example/x"]) and not ask("Tax Rate", "u", ["https://a.example/x"])


def test_chat_client_roles_and_back_off():
    seen, refused = [], [2]

    class Handler(BaseHTTPRequestHandler):
        def do_POST(self):
            body = json.loads(self.rfile.read(int(self.headers["Content-Length"])))
            seen.append((body["temperature"], body["messages"][0]["content"]))
            if refused[0]:
                refused[0] -= 1
                self.send_response(429)
                self.end_headers()
                return
            text = json.dumps({"choices": [{"message": {"content": json.dumps({"answer": ["yes"]})}}]}).encode()
            self.send_response(200)
            self.end_headers()
            self.wfile.write(text)

        def log_message(self, *args):
            pass

    server = HTTPServer(("127.0.0.1", 0), Handler)
    threading.Thread(target=server.serve_forever, daemon=True).start()
    try:
        m = models.HttpModel(f"http://127.0.0.1:{server.server_port}/", "any", pause=0.01)
        assert m.propose({"headers": ["a"], "sample": [], "kind": "text", "candidates": [], "context": []}) == ["yes"]
        assert m.judge({"header": "a", "sample": [], "label": "x", "table": "a"}) is True
        assert m.verify({"header": "a", "sample": [], "candidates": ["yes"], "kind": "text", "table": "a"}) == ["yes"]
    finally:
        server.shutdown()
    assert [t for t, _ in seen] == [0.3, 0.3, 0.3, 0.0, 0.0] and "Proposed type: x" in seen[3][1]


# ---- pipelines and baselines


def test_cascade_example_trace(spark):
    r = cascade.run(E.example(spark), cascade.CascadeConfig())
    trace = [tuple(x) for x in r.trace.orderBy(F.desc("threshold")).collect()]
    assert trace == [(0.99, 2, 0, 2, 1), (0.9, 1, 1, 0, 0), (0.75, 2, 2, 1, 1)]
    got = {x["column_id"]: (x["label"], x["phase"], x["threshold"]) for x in r.annotations.collect()}
    name = got["t1.PickupLocationAddress"][0]
    assert models.concept(name) == "Nation Code Name"
    assert got == {
        "t1.PickupLocationAddress": (name, "discovery", 0.99), "t2.pickup_location_address": (name, "discovery", 0.99), "t3.pickup_location_adress": (name, "sibling", 0.9),
        "t4.pickup_location": (name, "sibling", 0.75), "t5.location_address": (got["t5.location_address"][0], "discovery", 0.75),
    }
    assert got["t5.location_address"][0] != name


def test_lower_threshold_for_names(spark):
    p = cascade.Prepared(E.example(spark), cascade.CascadeConfig((0.9,), name_slack=0.15))
    together = {r["column_id"] for r in p.level(0.9).where("seed_cluster is not null").collect()}
    assert "t4.pickup_location" in together and "t6.qqq" not in together


@pytest.mark.parametrize("name", ["plain", "plain_reuse", "guided", "guided_reuse", "per_column"])
def test_baselines(spark, tiny, name):
    rows = run(spark, tiny, name)
    columns = {c["column_id"] for c in E.prepared(spark, tiny, "OPS").columns.collect()}
    assert {r["column_id"] for r in rows} == columns and all(r["label"].strip() for r in rows)
    calls = E.result(spark, tiny, "OPS", name.replace("_reuse", "+reuse")).calls.collect()
    if name != "per_column":
        tables = {c["table_id"] for c in E.prepared(spark, tiny, "OPS").columns.collect()}
        assert sorted(c["target"] for c in calls) == sorted(tables)
        assert all((prompts.GUIDANCE in c["prompt"]) == name.startswith("guided") and ("Types known so far" in c["prompt"]) == name.endswith("reuse") for c in calls)
    else:
        assert len(calls) == len(columns)


def test_closed_lists(spark, tiny):
    full, one = run(spark, tiny, "closed_full"), run(spark, tiny, "closed_single")
    assert {r["label"] for r in full} <= set(C.TRUTH)
    held = defaultdict(set)
    for r in full:
        held[r["column_id"]].add(r["label"])
    assert {r["column_id"] for r in one} == set(held) and len(one) == len(held) and all(r["label"] in held[r["column_id"]] for r in one)
    b = E.prepared(spark, tiny, "MIXED")
    asked = E.annotate.requests(b.columns.limit(1).select("column_id", F.lit("Tax Rate").alias("label"), F.lit("all").alias("source")), b.columns, b.values, rows=b.rows)
    assert "\n" in asked.first()["table"]


def test_complement_covers_all(spark, tiny):
    p, r = E.prepared(spark, tiny, "MIXED"), E.result(spark, tiny, "MIXED", "cascade")
    got = baselines.complete(p, r)
    assert got.annotations.select("column_id").distinct().count() == p.columns.count()
    assert {x["column_id"] for x in got.annotations.join(r.annotations.select("column_id").distinct(), "column_id", "left_semi").where("phase = 'table'").collect()} == set()


def test_quality_by_plain_python(spark, tiny):
    """The five methods on common columns, recomputed from their annotations and one pool of verdicts."""
    got = {(r["collection"], r["method"]): r for r in run(spark, tiny, "exp_quality")}
    assert len(got) == 15
    p = E.prepared(spark, tiny, "TXT")
    truth = {c["column_id"]: set(c["truth"].split("|")) for c in p.columns.collect()}
    runs = {m: E.result(spark, tiny, "TXT", m).annotations.collect() for m in E.METHODS}
    common = {r["column_id"] for r in runs["cascade"]}
    verdicts = {(r["column_id"], r["label"]): r["valid"] for r in E.judged(spark, tiny, "TXT", *((m,) for m in E.METHODS)).collect()}
    assert set(verdicts) == {(r["column_id"], r["label"]) for rows in runs.values() for r in rows}
    for m, rows in runs.items():
        mine = defaultdict(set)
        for r in rows:
            if r["column_id"] in common:
                mine[r["column_id"]].add(r["label"])
        flat = [(c, x) for c, own in mine.items() for x in own]
        row = got["TXT", m]
        assert row["hit_rate"] == pytest.approx(np.mean([any(verdicts[c, x] for x in own) for c, own in mine.items()]), abs=1e-6)
        assert row["judged_precision"] == pytest.approx(np.mean([verdicts[x] for x in flat]), abs=1e-6)
        meant = {c: {models.concept(x) for x in own} for c, own in mine.items()}
        tp = sum(len(meant.get(c, set()) & truth[c]) for c in common)
        fp, fn = sum(len(v) for v in meant.values()) - tp, sum(len(truth[c]) for c in common) - tp
        assert row["f1"] == pytest.approx(2 * tp / (2 * tp + fp + fn), abs=1e-6)


def test_manual_sample_by_plain_python(spark, tiny):
    got = {(r["collection"], r["method"], r["phase"]): r for r in run(spark, tiny, "exp_manual")}
    p = E.prepared(spark, tiny, "TXT")
    truth = {c["column_id"]: set(c["truth"].split("|")) for c in p.columns.collect()}
    runs = {m: E.result(spark, tiny, "TXT", m).annotations.collect() for m in E.METHODS}
    sample = {(r["phase"], r["column_id"]) for r in judge.representatives(E.result(spark, tiny, "TXT", "cascade").annotations).collect()}
    mean = lambda m, c: {models.concept(r["label"]) for r in runs[m] if r["column_id"] == c}
    for m in E.METHODS:
        for phase in {x for x, _ in sample}:
            tp = fp = fn = 0
            for _, c in (x for x in sample if x[0] == phase):
                found = {models.concept(r["label"]) for k in E.METHODS for r in runs[k] if r["column_id"] == c} & truth[c]
                wanted = found | {f"Other_{k}" for k in range(len(truth[c] - found))}
                mine = mean(m, c)
                tp, fp, fn = tp + len(mine & wanted), fp + len(mine - wanted), fn + len(wanted - mine)
            row = got["TXT", m, phase]
            assert (row["tp"], row["fp"], row["fn"]) == (tp, fp, fn)


@pytest.mark.parametrize("name,rows", [("exp_tokens", 15), ("exp_tradeoff", 15), ("exp_variants", 4), ("exp_multitype", 6), ("exp_join_pairs", 5), ("complete_coverage", 9), ("exp_sampling_clusters", 2), ("single_view_clusters", 9), ("all_collection_stats", 3)])
def test_workload_rows(spark, tiny, name, rows):
    got = run(spark, tiny, name)
    assert len(got) == rows
    for r in got:
        for k in ("coverage", "hit_rate", "judged_precision", "p", "r", "f1"):
            assert k not in r or r[k] is None or 0 <= r[k] <= 1
    by = {(r.get("collection"), r.get("method") or r.get("swapped") or r.get("switch") or r.get("way")): r for r in got}
    if name == "exp_tokens":
        for c in E.COLLECTIONS:
            assert by[c, "cascade"]["out_tokens"] < min(by[c, m]["out_tokens"] for m in E.METHODS[:4])
            assert by[c, "guided+reuse"]["n_types"] <= by[c, "guided"]["n_types"] and by[c, "guided"]["coverage"] == 1
    if name == "exp_tradeoff":
        assert all(by[c, "cascade"]["times_cascade"] == 1 for c in E.COLLECTIONS)
    if name == "exp_variants":
        cover = [by[None, m]["coverage"] for m in ("fixed(0.75)", "fixed(0.9)", "fixed(0.99)", "cascade")]
        assert cover[0] >= cover[1] >= cover[2] and cover[3] >= cover[2]
    if name == "complete_coverage":
        for c in E.COLLECTIONS:
            assert by[c, "complete"]["coverage"] == 1 and by[c, "complete"]["f1"] >= by[c, "cascade"]["f1"]
    if name == "all_collection_stats":
        rows_ = {r["collection"]: r for r in got}
        assert rows_["MIXED"]["max_rows"] == spark.read.parquet(f"{tiny}/lineitem.parquet").count()
    if name == "single_view_clusters":
        size = {(r["tau"], r["view"]): r["n_columns"] for r in got}
        assert all(size[t, "seed"] <= min(size[t, "name"], size[t, "value"]) for t in (0.99, 0.9, 0.75))


def test_clusters_of_given_vectors(spark, tiny):
    rows = {r["id"]: r["community"] for r in run(spark, tiny, "embedding_clusters")}
    vectors = {str(r["vec_id"]): np.array(r["embedding"], float) for r in spark.read.parquet(f"{tiny}/embeddings.parquet").collect()}
    groups = defaultdict(list)
    for i, c in rows.items():
        groups[c].append(vectors[i] / np.linalg.norm(vectors[i]))
    assert groups and all(len(g) >= 2 and max((np.array(g) @ np.array(g).T >= 0.2999995).sum(axis=1)) == len(g) for g in groups.values())


def test_value_cluster_samples(spark, tiny):
    got = run(spark, tiny, "tfidf_cluster_sample")
    values = {(r["column_id"], r["value"]) for r in C.build(spark, tiny, "MULTI").cells.collect()}
    assert {(r["column_id"], r["value"]) for r in got} <= values and max(len([1 for r in got if r["column_id"] == c]) for c, _ in values) <= 6


@pytest.mark.parametrize("name", ["header_pairs_lsh", "rest_annotation", "closed_set_text", "closed_set_numeric", "discovered_types", "discovery_prompts", "cascade_trace", "name_clusters_099", "value_clusters_075", "intro_example"])
def test_other_queries_run(spark, tiny, name):
    got = run(spark, tiny, name)
    if name == "discovery_prompts":
        assert got and all(r["source"] in ("index", "fallback") and r["prompt"] and json.loads(r["response"])["answer"] for r in got)
    if name == "intro_example":
        assert {models.concept(r["label"]) for r in got} == {"World Region Name", "Nation Code Name"} and len(got) == 4


# ---- streams


def test_streams_with_state(spark, tiny):
    got = run(spark, tiny, "stream_value_index")
    assert {r["labels"] for r in got} == {"Language Code"} and {r["value"] for r in got} == {r["lang"] for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    found = run(spark, tiny, "stream_incremental_annotation")
    assert {r["column_id"] for r in found} <= {"new.lang", "new.source"} and found


def test_late_rows_and_upserts(spark, tmp_path):
    schema = "event_id long, event_type string, user_id long, value double, ts timestamp"
    for k, day in enumerate(("2024-01-01", "2024-03-01", "2024-01-02")):
        spark.createDataFrame([(k, "x", 1, 1.0, f"{day} 10:00:00")], "event_id long, event_type string, user_id long, value double, t string").selectExpr("event_id", "event_type", "user_id", "value", "cast(t as timestamp) ts").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    q = live.windows(stream).drop("users").writeStream.outputMode("append").format("memory").queryName("late_test").trigger(availableNow=True).start()
    q.awaitTermination()
    assert live.late_rows(q) <= 1
    counts = stream.groupBy("event_type").agg(F.count("*").alias("n"))
    up = live.upsert(counts, ["event_type"], str(tmp_path / "table"), str(tmp_path / "check"))
    up.processAllAvailable()
    last = up.lastProgress["batchId"]
    up.stop()
    versions = [k for k in range(last + 1) if (tmp_path / "table" / f"v{k}").exists()]
    assert [tuple(r) for r in live.latest(spark, str(tmp_path / "table"), versions[-1]).collect()] == [("x", 3)]
