"""The pipeline's stages against what each should do with its own input."""

import re
from collections import defaultdict

import corpus_pipeline
import numpy as np
from test_ops import brute_components, brute_sure, brute_tiles, sets_of
from tokenizers import Tokenizer

from coltypes.llm import decontam, quality, queries, secrets

SF = "/root/testdata/sf0.01"


def test_stages(spark):
    """Each stage's rows from a slow version of what it should do with its own input."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels, benchmark = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("labels", "benchmark"))
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "near_dedup", "decontamination", "secrets", "packing"]
    model = quality.fit(docs, labels)
    passed = {r["doc_id"] for r in quality.score(docs, model).where("predicted = 1").collect()}
    items = {r["item_id"]: re.findall(r"[^\W_]+", r["text"].lower()) for r in benchmark.collect()}
    library = Tokenizer.from_file(queries.tokenizer(queries.WORDS))
    for name, stage in corpus_pipeline.STAGES:
        before = {r["doc_id"]: r for r in docs.collect()}
        made = stage(spark, docs, SF).cache()
        rows = made.collect()
        if name == "packing":
            pieces = defaultdict(list)
            for r in rows:
                pieces[r["doc_id"]].append((r["start"], np.frombuffer(r["ids"], "<u4").tolist()))
            got = {i: [x for _, part in sorted(p) for x in part] for i, p in pieces.items()}
            assert got == {i: [*library.encode(r["text"], add_special_tokens=False).ids, 1] for i, r in before.items()}
            break
        after = {r["doc_id"]: r for r in rows}
        assert made.columns == docs.columns and len(rows) == len(after)
        if name == "quality":
            assert set(after) == passed
        if name == "near_dedup":
            part = brute_components(sets_of({i: r["text"] for i, r in before.items()}, 5), 80)
            assert set(after) == {i for i, p in part.items() if i == p}
        if name == "decontamination":
            words = {i: re.findall(r"[^\W_]+", r["text"].lower()) for i, r in before.items()}
            runs = {k: {tuple(w[a : a + 5]) for a in range(len(w) - 4)} for k, w in items.items()}
            dirty = set()
            for i, w in words.items():
                own = {tuple(w[a : a + 5]) for a in range(len(w) - 4)}
                near = [k for k in items if own & runs[k]]
                if any(sum(n for _, _, n in brute_tiles(items[k], w, 5)) >= 0.5 * len(items[k]) for k in near):
                    dirty.add(i)
            assert dirty and set(after) == set(before) - dirty
        if name != "secrets":
            assert all(after[i] == before[i] for i in after)
        else:
            assert set(after) == set(before)
            for i, r in after.items():
                spans = secrets.scan(before[i]["text"])[1]
                assert set(brute_sure(before[i]["text"])) <= set(spans)
                text, at = "", 0
                for k, c in enumerate(before[i]["text"]):
                    inside = [(s, e) for s, _, e in spans if s <= k < e]
                    text += c if not inside else "[SECRET]" if k >= at else ""
                    at = max([at, *(e for _, e in inside)])
                assert r["text"] == text and r["n_chars"] == len(text)
        docs = made
    got = corpus_pipeline.run(spark, SF)
    assert got.agg({"length": "sum"}).first()[0] == made.agg({"length": "sum"}).first()[0]


def test_stages_on_awkward_tables(spark, tmp_path):
    rows = [(1, None, "en", "s", 0, "x"), (2, "", None, "s", 0, "x"), (None, "a b c", "en", None, None, "x"), (4, "same words here", "en", "s", 15, "x"), (4, "same words here", "en", "s", 15, "x")]
    schema = "doc_id long, text string, lang string, source string, n_chars long, score string"
    spark.createDataFrame([(4, 1)], "doc_id long, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    spark.createDataFrame([(1, "q")], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    for table in (rows, []):
        docs = spark.createDataFrame(table, schema)
        for _, stage in corpus_pipeline.STAGES[:-1]:
            docs = stage(spark, docs, str(tmp_path))
            assert docs.columns == [c.split()[0] for c in schema.split(", ")]
        assert docs.count() == len(table)
        corpus_pipeline.STAGES[-1][1](spark, docs, str(tmp_path)).collect()


def test_queries():
    assert sorted(n.split("_")[0] for n in queries.queries() if n.startswith("op")) == sorted(f"op{k}" for k in range(1, 11))
    assert decontam.Settings().least == 5
