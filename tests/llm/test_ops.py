"""The corpus operators against brute force, round trips and held-out labels; awkward rows for each."""

import itertools
import re
import zlib
from hashlib import sha256

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from coltypes.llm import bpe, common, decontam, langid, licenses, linkage, neardup, packing, pii, quality, queries, records, secrets, simhash, wordhash

SF = "/root/testdata/sf0.01"
ODD = [(1, None), (2, ""), (3, "   \n\t "), (4, "one"), (4, "one"), (None, "no id here at all"), (5, "é中 ﬃ İ x" * 50), (6, "word " * 60000)]


@pytest.fixture(scope="session")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="session")
def rows(docs):
    return {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}


def odd(spark):
    """Nulls, empty and very long texts, repeated rows, and columns whose names clash with inner ones."""
    return spark.createDataFrame([(i, t, 7, "k") for i, t in ODD], "doc_id long, text string, score int, key string")


def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, lang string, n_chars long")


# ---- words and hashes


@given(st.lists(st.text(st.characters(codec="utf-8"), max_size=60), max_size=5))
@settings(max_examples=60, deadline=None)
def test_word_hashes(texts):
    raw, offsets = wordhash.utf8(pa.array(texts, pa.string()))
    hashes, starts, ends, at = wordhash.words(raw, offsets, wordhash.SPACE_ENDS)
    seen = {}
    for k, text in enumerate(texts):
        want = text.encode().lower().split()
        own = [raw[s:e].tobytes().lower() for s, e in zip(starts[at[k] : at[k + 1]], ends[at[k] : at[k + 1]], strict=True)]
        assert own == want
        for w, h in zip(want, hashes[at[k] : at[k + 1]].tolist(), strict=True):
            assert seen.setdefault(w, h) == h
    assert len(set(seen.values())) == len(seen)


# ---- near duplicates


def sets_of(rows, width):
    out = {}
    for i, t in rows.items():
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), t or ""))
        out[i] = {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())
    return out


def brute_components(sets, percent):
    owners = {}
    for i, s in sets.items():
        for x in s:
            owners.setdefault(x, []).append(i)
    shared = {}
    for own in owners.values():
        for a, b in itertools.combinations(sorted(own), 2):
            shared[a, b] = shared.get((a, b), 0) + 1
    root = {i: i for i in sets}

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for (a, b), n in shared.items():
        if 100 * n >= percent * (len(sets[a]) + len(sets[b]) - n):
            p, q = top(a), top(b)
            root[max(p, q)] = min(p, q)
    return {i: top(i) for i in sets}


def test_near_duplicates_equal_brute_force(spark, docs, rows):
    sets = sets_of(rows, 4)
    want = brute_components(sets, 80)
    got = {r["doc_id"]: r for r in neardup.groups(docs, neardup.Settings(width=4)).collect()}
    assert {i: r["component_id"] for i, r in got.items()} == want
    assert {i: r["n_shingles"] for i, r in got.items()} == {i: len(s) for i, s in sets.items()}
    assert sum(r["kept"] for r in got.values()) == len(set(want.values()))


def test_near_copies_in_blocks(spark):
    """A large group of copies that differ from each other more than from a common origin, in small blocks."""
    rng = np.random.default_rng(5)
    base = [f"w{x}" for x in rng.integers(0, 5000, 120)]
    texts = {}
    for i in range(150):
        t = list(base)
        for k in rng.integers(0, 120, int(rng.integers(0, 7))):
            t[k] = f"z{rng.integers(0, 10**6)}"
        texts[i] = " ".join(t)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in neardup.groups(df, neardup.Settings(width=4, block_keys=16)).collect()}
    assert got == brute_components(sets_of(texts, 4), 80)


def test_near_duplicates_odd_rows(spark):
    got = neardup.groups(odd(spark), neardup.Settings(width=4)).collect()
    assert len(got) == len(ODD)
    assert all(r["component_id"] == r["doc_id"] and r["kept"] for r in got)
    assert neardup.groups(empty(spark)).count() == 0
    assert neardup.keep_one(odd(spark)).columns == ["doc_id", "text", "score", "key"]
    assert neardup.keep_one(odd(spark)).count() == len(ODD)


def test_near_duplicates_with_clashing_ids(spark):
    """Rows of one id are kept or not each by its own text, and one of a group is kept."""
    words = [f"w{k}" for k in range(60)]
    one, near, alone, other = " ".join(words), " ".join([*words[:-1], "x"]), "quite another text than all of these", " ".join(reversed(words))
    rows_ = [(1, one), (7, one), (7, alone), (3, other), (3, other.replace("w0", "y")), (9, other), (5, near), (5, ""), (8, None), (8, None)]
    df = spark.createDataFrame([(i, t, k) for k, (i, t) in enumerate(rows_)], "doc_id long, text string, place int")
    kept = [rows_[r["place"]] for r in neardup.keep_one(df).collect()]
    assert (1, one) in kept and (7, alone) in kept and kept.count((8, None)) == 2 and (5, "") in kept
    assert sum(t == other or t == rows_[4][1] for _, t in kept) == 1 and all(i == 3 for i, t in kept if t and t.startswith("w59"))
    assert len(kept) == 6 == sum(r["kept"] for r in neardup.groups(df).collect())
    leads = [(1, one), (1, alone), (2, alone)]  # an id with one copy and one leader: the group of the leader stays
    got = neardup.keep_one(spark.createDataFrame([(0, one), *leads], "doc_id long, text string")).collect()
    assert sorted((r["doc_id"], r["text"]) for r in got) == [(0, one), (1, alone)]


def test_signatures_tell_large_sets_apart():
    """Minima of large sets are small; the values kept still differ where sets do, and bands agree as often as they should."""
    rng, s = np.random.default_rng(3), neardup.Settings()
    shared, own = (rng.integers(0, 1 << 63, n, dtype=np.uint64) for n in (4000, 16000))
    one, two = (neardup.signature(np.concatenate([shared, x]), s.size) for x in np.split(own, 2))
    assert abs((one == two).mean() - 0.2) < 0.12  # 4000 of 20000
    pairs = neardup.survivors(np.array([one, two, one]), np.full(3, 12000), np.arange(3), np.arange(3), s, neardup.least_matches(s))
    assert [x.tolist() for x in pairs] == [[0], [2]]
    assert not len(neardup.survivors(np.array([one, one]), np.full(2, 9), np.arange(2), np.zeros(2), s, neardup.least_matches(s))[0])


def test_colliding_keys_are_noticed(spark):
    """Two sets in one 64-bit key count, so that all is done again with other hashes; those of another seed differ."""
    run = object.__new__(neardup._Search)
    run.tables, rows = linkage.Tables("t"), [(1, 1, 3, 5, 7, b"s"), (2, 1, 3, 5, 7, b"s"), (3, 1, 3, 6, 7, b"s"), (4, 1, 3, 6, 8, b"s"), (5, 1, 0, None, None, None)]
    run.sketch = spark.createDataFrame(rows, neardup.SKETCH)
    assert run._collapse() == 1 and run.keys.count() == 2
    run.tables.drop(run.sketch)
    one = np.arange(9, dtype=np.uint64)
    assert len({*neardup._keys(one, 0), *neardup._keys(one, 1)}) == 4 and neardup._keys(one[:0], 0) == (None, None)


def test_filters_hold_no_wanted_row_back(spark):
    rows, wanted = spark.range(5000).selectExpr("id as k", "1 as __x"), spark.range(0, 5000, 50).selectExpr("id as k")
    maybe, others = linkage.sifted(rows, "k", wanted, 100)
    got = {r["k"] for r in maybe.collect()}
    assert set(range(0, 5000, 50)) <= got and len(got) < 1500
    assert got.isdisjoint(r["k"] for r in others.collect()) and others.count() == 5000 - len(got) and maybe.columns == rows.columns
    assert linkage.sifted(rows, "k", wanted, 1 << 40) == (rows, None)


def test_pruning_bound():
    least = neardup.least_matches(neardup.Settings())
    assert (np.diff(least) > 0).all() and least[-1] < 0.8 * neardup.Settings().size
    a, b = np.arange(60, dtype=np.uint64), np.arange(20, 80, dtype=np.uint64)
    assert neardup.overlaps([a, b])[0, 1] == 40


# ---- quality


def test_quality_held_out(spark, docs):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    model = quality.fit(docs, labels, lambda i: common.id_remainder(i, 5) != 0)
    scored = {r["doc_id"]: r for r in quality.score(docs, model).collect()}
    held = [(r["quality"], scored[r["doc_id"]]) for r in labels.collect() if zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0]
    good = [s["predicted"] for q, s in held if q == 1]
    bad = [s["predicted"] for q, s in held if q == 0]
    assert np.mean(good) > 0.97
    assert np.mean(bad) < 0.35
    kept = quality.keep_good(docs, model)
    assert kept.columns == docs.columns
    assert kept.count() == sum(s["predicted"] for s in scored.values())


def test_training_takes_all_blocks_of_a_text():
    s, text = quality.Settings(), "".join(f"{k:04d}" + "x" * 508 for k in range(100)) + "end"
    batch = pa.record_batch([pa.array([1, 0], pa.int32()), pa.array([text, None])], ["label", "text"])
    got = next(quality._blocks(s)([batch])).column("block").to_pylist()
    assert b"".join(got).decode() == text and len(got) == 101


def test_quality_odd_rows(spark):
    labels = spark.createDataFrame([(4, 1), (5, 0), (None, 1), (6, 3)], "doc_id long, quality int")
    model = quality.fit(odd(spark), labels)
    got = quality.score(odd(spark), model).collect()
    assert len(got) == len(ODD) and all(0 <= r["score"] <= 1 for r in got)
    none = quality.fit(odd(spark), labels.where("false"))
    assert {r["score"] for r in quality.score(odd(spark), none).collect()} == {0.5}
    assert quality.score(empty(spark), model).count() == 0


# ---- tokenizers, records, packing


@pytest.mark.parametrize("name", [queries.BYTES, queries.WORDS])
def test_encoder_equals_library(name, rows):
    e, library = bpe.Encoder(queries.tokenizer(name)), Tokenizer.from_file(queries.tokenizer(name))
    specials = ["<|endoftext|> a", "see <|endoftext|> here", "A<|STARTOFTEXT|>b<|startoftext|>c <|endoftext|><|endoftext|>", "x" * 99 + " <|endoftext|>"]
    for text in [*specials, *list(rows.values())[:150], *(t or "" for _, t in ODD[:-1]), "it's  'll\xa0 x\x85y ²3 don't", "  lead", "tail \n\n "]:
        assert e.encode(text).tolist() == library.encode(text, add_special_tokens=False).ids


LIBRARY = {name: Tokenizer.from_file(queries.tokenizer(name)) for name in (queries.BYTES, queries.WORDS)}
PART = st.text(st.characters(max_codepoint=0x260, exclude_categories=["Cs"]), max_size=20) | st.sampled_from(["<|endoftext|>", "<|startoftext|>", "<|endof", "text|>", "<|"])


@given(st.lists(PART, max_size=4).map("".join))
@settings(max_examples=150, deadline=None)
def test_encoder_on_any_text(text):
    """Against the library as it comes from the file, with the strings of its special tokens mixed in."""
    for name, library in LIBRARY.items():
        assert bpe.encoder(queries.tokenizer(name)).encode(text).tolist() == library.encode(text, add_special_tokens=False).ids


def test_special_tokens_as_text():
    e, library = bpe.Encoder(queries.tokenizer(queries.BYTES), special_as_text=True), Tokenizer.from_file(queries.tokenizer(queries.BYTES))
    library.encode_special_tokens = True
    for text in ("a <|endoftext|> b", "<|endoftext|>"):
        assert e.encode(text).tolist() == library.encode(text, add_special_tokens=False).ids


def test_encoder_with_a_full_store(monkeypatch, rows):
    monkeypatch.setattr(bpe, "STORE", 50)
    e = bpe.Encoder(queries.tokenizer(queries.WORDS))
    for text in list(rows.values())[:20]:
        assert e.encode(text).tolist() == e.library.encode(text, add_special_tokens=False).ids
    assert len(e.place) <= 50


def slow_crc32c(data):
    crc = 0xFFFFFFFF
    for b in data:
        crc ^= b
        for _ in range(8):
            crc = (crc >> 1) ^ (records.POLYNOMIAL if crc & 1 else 0)
    return crc ^ 0xFFFFFFFF


@given(st.lists(st.binary(max_size=700), max_size=6))
@settings(max_examples=40, deadline=None)
def test_checksums_and_frames(payloads):
    assert records.crc32c(payloads).tolist() == [slow_crc32c(p) for p in payloads]
    data = b"".join(records.frames(payloads))
    assert [p for ps in records.read(pa.BufferReader(data), 64) for p in ps] == payloads


def test_known_checksum_and_damage():
    assert records.crc32c([b"123456789"])[0] == 0xE3069283
    data = bytearray(records.frames([b"hello there"])[0])
    data[14] ^= 1
    with pytest.raises(records.Damaged):
        list(records.read(pa.BufferReader(bytes(data))))
    with pytest.raises(records.Damaged):
        list(records.read(pa.BufferReader(records.frames([b"hello"])[0][:-1])))


def test_records_round_trip(spark, docs, rows):
    manifest = records.write(docs, queries.tokenizer(queries.BYTES), 2, common.fresh_path(spark, "t"), files=3)
    got = {r["doc_id"]: r for r in records.read_back(manifest).collect()}
    library, start = Tokenizer.from_file(queries.tokenizer(queries.BYTES)), 0
    for i in sorted(rows):
        ids = np.array([*library.encode(rows[i], add_special_tokens=False).ids, 2], "<u4")
        assert (got[i]["start"], got[i]["n_tokens"], got[i]["ids_crc32"]) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    first = min(manifest.collect(), key=lambda r: r["file"])
    picked = list(records.read_at(first["data"], first["offsets"], [3, 0]))
    assert [p[0] for p in picked] == [sorted(rows)[3], sorted(rows)[0]]


def test_records_odd_rows(spark):
    m = records.write(odd(spark), queries.tokenizer(queries.BYTES), 2, common.fresh_path(spark, "t"), files=2)
    got = records.read_back(m).collect()
    assert len(got) == len(ODD) and sum(r["n_tokens"] == 1 for r in got) == 2
    assert records.read_back(records.write(empty(spark), queries.tokenizer(queries.BYTES), 2, common.fresh_path(spark, "t"))).count() == 0


def test_packing_covers_every_id(spark, docs, rows):
    got = packing.pack_documents(docs, queries.tokenizer(queries.WORDS), 1).collect()
    library = Tokenizer.from_file(queries.tokenizer(queries.WORDS))
    by_doc, by_sequence = {}, {}
    for r in got:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_sequence.setdefault(r["sequence_id"], []).append(r)
    for i, text in rows.items():
        ids = np.array([*library.encode(text, add_special_tokens=False).ids, 1], "<u4")
        at = 0
        for r in sorted(by_doc[i], key=lambda r: r["start"]):
            assert r["start"] == at and r["doc_tokens"] == len(ids)
            assert r["ids_crc32"] == zlib.crc32(ids[at : at + r["length"]].tobytes())
            at += r["length"]
        assert at == len(ids)
    for pieces in by_sequence.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048
    used = sum(r["length"] for r in got)
    assert used / (2048 * len(by_sequence)) > 0.99 or len(by_sequence) - used / 2048 <= 8


def test_packing_limits(spark):
    s = packing.Settings(tokens=100, segments=4, loss=60, window=64, cut=False)
    rng = np.random.default_rng(2)
    items = [(i, int(n), int(n * f)) for i, (n, f) in enumerate(zip(rng.integers(1, 70, 300), rng.random(300), strict=True))] + [(1000, 500, 10)]
    got = packing.assign(spark.createDataFrame(items, "item_id long, tokens long, loss long"), s).collect()
    assert sorted(r["item_id"] for r in got) == sorted(i for i, _, _ in items)
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append(r)
    for rows_ in by.values():
        if len(rows_) > 1:  # an item beyond a limit has a sequence of its own
            assert sum(r["tokens"] for r in rows_) <= 100 and len(rows_) <= 4 and sum(r["loss"] for r in rows_) <= 60
    assert len(packing.pack_documents(odd(spark), queries.tokenizer(queries.WORDS), 1).collect()) >= len(ODD)
    assert packing.pack_documents(empty(spark), queries.tokenizer(queries.WORDS), 1).count() == 0


def test_packed_ids_and_loss(spark, rows):
    """The ids and masks that come out are the documents'; loss counts of the input bind under their own limit."""
    library = Tokenizer.from_file(queries.tokenizer(queries.WORDS))
    texts = {i: t[:3000] for i, t in list(rows.items())[:120]}
    ids = {i: [*library.encode(t, add_special_tokens=False).ids, 1] for i, t in texts.items()}
    bears = {i: None if i % 5 == 0 else len(x) * (i % 4) // 4 for i, x in ids.items()}
    df = spark.createDataFrame([(i, t, bears[i]) for i, t in texts.items()], "doc_id long, text string, answer long")
    for s in (packing.Settings(tokens=100, segments=4, loss=30, window=64), packing.Settings()):
        pieces, sequences = {}, {}
        for r in packing.pack_sequences(df, queries.tokenizer(queries.WORDS), 1, s, "answer").collect():
            mask = list(r["loss_mask"])
            assert len(mask) == r["length"] and (r["offset"] or not mask[0])
            pieces.setdefault(r["doc_id"], []).append((r["start"], np.frombuffer(r["ids"], "<u4").tolist(), mask, r["offset"]))
            sequences.setdefault(r["sequence_id"], []).append((r["length"], sum(mask)))
        for i, want in ids.items():
            own = sorted(pieces[i])
            assert [x for p in own for x in p[1]] == want
            loss = len(want) if bears[i] is None else bears[i]
            for start, part, mask, offset in own:
                assert mask == [int(start + k >= len(want) - loss and (offset or k) > 0) for k in range(len(part))]
        for p in sequences.values():
            assert sum(n for n, _ in p) <= s.tokens and len(p) <= s.segments and sum(m for _, m in p) <= s.loss
    full = [p for p in sequences.values() if sum(n for n, _ in p) == 2048]
    assert full


def test_assign_keeps_items_without_tokens(spark):
    items = [(1, 0, 0), (2, None, None), (3, 5, 2), (4, 0, 3)]
    for cut in (False, True):
        got = packing.assign(spark.createDataFrame(items, "item_id long, tokens long, loss long"), packing.Settings(cut=cut)).collect()
        assert sorted((r["item_id"], r["tokens"]) for r in got) == [(1, 0), (2, 0), (3, 5), (4, 0)]


# ---- decontamination


def brute_tiles(item, text, least):
    """Greedy tiling by its definition: all matches, longest first, then leftmost in the text."""
    used_i, used_t, out = set(), set(), []
    while True:
        best = (0, 0, 0)
        for t in range(len(text)):
            for p in range(len(item)):
                n = 0
                while p + n < len(item) and t + n < len(text) and item[p + n] == text[t + n] and p + n not in used_i and t + n not in used_t:
                    n += 1
                if n > best[0]:
                    best = (n, p, t)
        if best[0] < least:
            return out
        n, p, t = best
        out.append((p, t, n))
        used_i.update(range(p, p + n)), used_t.update(range(t, t + n))


@given(st.lists(st.integers(0, 3), min_size=4, max_size=18), st.lists(st.integers(0, 3), min_size=4, max_size=24))
@settings(max_examples=80, deadline=None)
def test_tiles_equal_brute_force(item, text):
    got = decontam.tiles(np.array(item, np.uint64), np.array(text, np.uint64), 3)
    assert sorted(n for _, _, n in got) == sorted(n for _, _, n in brute_tiles(item, text, 3))
    assert all(item[p : p + n] == text[t : t + n] for p, t, n in got)


def test_decontamination_finds_passages(spark, docs, rows):
    benchmark = spark.read.parquet(f"{SF}/benchmark.parquet")
    items = {r["item_id"]: re.findall(r"[^\W_]+", r["text"].lower()) for r in benchmark.collect()}
    got = {(r["doc_id"], r["item_id"]): r["coverage"] for r in decontam.find(docs, benchmark).collect()}
    planted = {(i, k) for i, t in rows.items() for k, w in items.items() if " ".join(w) in " ".join(re.findall(r"[^\W_]+", t.lower()))}
    assert planted and planted <= set(got)
    for (i, k), coverage in list(got.items())[:20]:
        text = re.findall(r"[^\W_]+", rows[i].lower())
        runs = {tuple(items[k][a : a + 5]) for a in range(len(items[k]) - 4)}
        assert coverage >= 0.5 and runs & {tuple(text[a : a + 5]) for a in range(len(text) - 4)}
    clean = decontam.keep_clean(docs, benchmark)
    assert clean.columns == docs.columns and clean.count() == len(rows) - len({i for i, _ in got})


def test_decontamination_reordered_and_odd(spark):
    item = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi"
    text = "noise ZETA, eta theta iota kappa lambda mu nu xi more noise alpha beta gamma delta epsilon end"
    bench = spark.createDataFrame([(1, item), (2, None), (3, ""), (4, "one two")], "item_id long, text string")
    df = spark.createDataFrame([(9, text), (8, "alpha beta only"), (7, "xx one TWO yy")], "doc_id long, text string")
    assert {(r["doc_id"], r["item_id"], r["coverage"]) for r in decontam.find(df, bench).collect()} == {(9, 1, 1.0), (7, 4, 1.0)}
    assert {(r["doc_id"], r["item_id"]) for r in decontam.find(df, bench, decontam.Settings(block_bytes=10)).collect()} == {(9, 1), (7, 4)}
    assert decontam.find(odd(spark), bench).count() == 0
    assert decontam.find(empty(spark), bench).count() == 0
    assert decontam.keep_clean(odd(spark), bench.where("false")).count() == len(ODD)


# ---- secrets


def brute_sure(text):
    found = []
    for m in re.finditer(r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text):
        if len(m.group(2)) >= 6:
            found.append((m.start(), 0, m.end()))
    found += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m.group()) >= 20]
    found += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m.group()) >= 24]
    return sorted(found)


def test_sure_spans_equal_brute_force(spark, docs, rows):
    for r in secrets.find(docs).collect():
        want = brute_sure(rows[r["doc_id"]])
        assert r["base_sha256"] == sha256(secrets.written(want).encode()).hexdigest()
        assert set(secrets.written(want).split(",")) <= set(r["spans"].split(","))


@given(st.lists(st.sampled_from(list("AKIA0f9aZ =:\"' token") + ["token=", "AKIA", "secret: ", "deadbeef"]), max_size=60).map("".join))
@settings(max_examples=200, deadline=None)
def test_sure_spans_on_any_text(text):
    assert secrets.sure(text) == brute_sure(text)


def test_linked_parts():
    key = "wJalrXUtnFEMI7MDENGbPxRfiCYEXAMPLEKEY99"
    near = f"client_id = svc-backup  {key}  https://db.example.net:5432/x"
    kinds = lambda t: [secrets.KINDS[k] for _, k, _ in secrets.scan(t)[1]]
    assert kinds(near) == ["ident", "weak", "endpoint"]
    assert kinds(f"{key} alone") == []
    assert kinds("client_id = svc-backup https://db.example.net:5432/x") == []
    assert kinds(f"client_id = svc-backup {'x ' * 600} {key}") == []


def test_linked_parts_without_identifier_or_assignment():
    key, hexed, url = "wJalrXUtnFEMI7MDENGbPxRfiCYEXAMPLEKEY99x", "0123456789abcdef" * 2, "https://db.example.net/x"
    kinds = lambda t: [secrets.KINDS[k] for _, k, _ in secrets.scan(t)[1]]
    assert kinds(f"{url} {key}") == ["endpoint", "weak"] and kinds(f"{key} db.example.net:5432") == ["weak", "endpoint"]
    assert kinds(f"client_id=svc-backup {url} {hexed}") == ["ident", "endpoint", "hex"]
    assert kinds(f"{url} {hexed}") == ["endpoint", "hex"] and kinds(f"{url} token=abcdef12") == ["endpoint", "assign"]
    assert kinds(f"{url} {'x ' * 600} {key}") == [] and kinds(f"{url} client_id=svc-backup") == []
    # identifier and endpoint on both sides of a secret, and an endpoint in reach of the identifier alone
    assert kinds(f"client_id=svc-backup {'x ' * 150}{key} {'x ' * 150}{url}") == ["ident", "weak", "endpoint"]
    assert kinds(f"{url} {'x ' * 150}client_id=svc-backup {'x ' * 150}{key}") == ["endpoint", "ident", "weak"]
    assert secrets.masked(*(lambda t: (t, secrets.scan(t)[1]))(f"see {url} {key}.")) == "see [SECRET] [SECRET]."


@given(st.lists(st.sampled_from(["client_id=svc-backup", "wJalrXUtnFEMI7MDENGbPxRfiCY", "0123456789abcdef" * 2, "https://db.example.net/x", "token=abcdef12", "AKIA" + "Q7" * 8, "pad " * 5]), max_size=14))
@settings(max_examples=150, deadline=None)
def test_linked_parts_equal_brute_force(words):
    text, reach = " ".join(words), 40
    base, got = secrets.scan(text, secrets.Settings(reach))
    at, parts = 0, []
    for w in words:
        kind = {"c": 3, "w": 4, "0": 2, "h": 5, "t": 0, "A": 1}.get(w[0])
        parts += [(at, kind, at + len(w))] if kind is not None else []
        at += len(w) + 1
    meet = lambda a, b: a[0] <= b[2] + reach and b[0] <= a[2] + reach
    secret, ident, end = ([p for p in parts if p[1] in ks] for ks in ((0, 2, 4), (1, 3), (5,)))
    tied = [p for p in ident if any(meet(p, s) for s in secret)]
    want = [p for p in tied if p[1] == 3] + [p for p in end if any(meet(p, s) for s in secret + tied)] + [p for p in secret if p[1] == 4 and any(meet(p, q) for q in ident + end)]
    assert got == sorted(base + want)


def test_secrets_odd_rows_and_mask(spark):
    got = secrets.find(odd(spark)).collect()
    assert len(got) == len(ODD) and all(r["spans"] == "" for r in got)
    df = spark.createDataFrame([(1, 'x token = "abcdef123" y', 23), (2, None, 0), (3, "clean", 5)], "doc_id long, text string, n_chars long")
    rows_ = {r["doc_id"]: r for r in secrets.mask(df).collect()}
    assert rows_[1]["text"] == 'x [SECRET]" y' and rows_[1]["n_chars"] == 13
    assert rows_[2]["text"] is None and rows_[3]["text"] == "clean"
    assert secrets.mask(empty(spark)).count() == 0


# ---- language


def test_language_held_out(spark, docs):
    model = langid.fit(docs, lambda i: common.id_remainder(i, 4) != 2)
    truth = {r["doc_id"]: r["lang"] for r in docs.collect()}
    got = [r for r in langid.predict(docs, model).collect() if zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2]
    assert np.mean([r["lang_pred"] == truth[r["doc_id"]] for r in got]) > 0.97


def test_language_model_sums_to_one():
    model = langid.build({"a": ["abab ba", "aab"], "b": ["bbb ab", "cab"]}, langid.Settings(order=3))
    alphabet = [ord(c) for c in " abc"]
    for before in ("ab", "ba", "zz", "c "):
        total = np.zeros(2)
        for c in [*alphabet, 0x3B1]:
            codes = np.array([*map(ord, before), c], np.uint32)
            at = np.array([0, len(codes)])
            grams, ctx = langid._grams(codes, at, 3), langid._before(langid._grams(codes, at, 3), at, 3)
            lp = np.zeros(2)
            for n in (2, 1, 0):
                place = model.grams[n].find(grams[n][-1:])[0]
                if place >= 0:
                    lp += model.log_p[n][place]
                    break
                if n == 0:
                    lp += model.floor
                    break
                place = model.contexts[n].find(ctx[n - 1][-1:])[0]
                if place >= 0:
                    lp += model.log_gamma[n][place]
            total += np.exp(lp)
        assert np.allclose(total, 1, atol=0.02)


def test_language_batches_and_odd_rows(spark, docs):
    model = langid.fit(docs, settings=langid.Settings(per_language=60))
    texts = [r["text"] for r in docs.limit(40).collect()]
    together, alone = model.entropy(texts)[0], np.concatenate([model.entropy([t])[0] for t in texts])
    assert np.allclose(together, alone, atol=1e-4)
    got = {r["doc_id"]: r for r in langid.predict(odd(spark), model).where("doc_id is not null").collect()}
    assert [got[i]["lang_pred"] for i in (1, 2, 3)] == ["und"] * 3 and got[1]["score"] == 0
    assert got[4]["lang_pred"] != "und"
    assert langid.predict(empty(spark), model).count() == 0
    assert {r["lang_pred"] for r in langid.predict(odd(spark), langid.fit(empty(spark))).collect()} == {"und"}


# ---- fingerprints


def test_edited_texts_and_fingerprints(spark, docs, rows):
    got = {r["doc_id"]: r for r in simhash.compare_edited(docs, files=5).collect()}
    order = sorted(rows)
    for i, j in zip(order, [*order[1:], order[0]], strict=True):
        n = len(rows[i]) // 4
        want = rows[i][: len(rows[i]) - n] + rows[j][:n]
        assert got[i]["edited_sha256"] == sha256(want.encode()).hexdigest() and got[i]["n_chars"] == len(rows[i])
        assert got[i]["near_next"] == 1 - (int(got[i]["fingerprint"], 16) ^ int(got[j]["fingerprint"], 16)).bit_count() / 64
    same = {}
    for i, t in rows.items():
        assert same.setdefault(t, got[i]["fingerprint"]) == got[i]["fingerprint"]
    assert np.mean([r["near_edited"] for r in got.values()]) > np.mean([r["near_next"] for r in got.values()]) + 0.15


def test_block_tables_find_all(spark):
    rng = np.random.default_rng(4)
    prints = [int(x) for x in rng.integers(-(1 << 63), 1 << 63 - 1, 60, dtype=np.int64)]
    for k in range(60):
        p = prints[k] & (2**64 - 1)
        for b in rng.choice(64, int(rng.integers(1, 6)), replace=False):
            p ^= 1 << int(b)
        prints.append(p - (1 << 64) if p >> 63 else p)
    df = spark.createDataFrame([*enumerate(prints), (None, 5)], "doc_id long, fingerprint long")
    got = {r["doc_id"]: r["class_id"] for r in simhash.near_classes(df).collect() if r["doc_id"] is not None}
    root = {i: i for i in range(len(prints))}

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, j in itertools.combinations(range(len(prints)), 2):
        if ((prints[i] ^ prints[j]) & (2**64 - 1)).bit_count() <= 3:
            root[max(top(i), top(j))] = min(top(i), top(j))
    assert got == {i: top(i) for i in root}


def test_fingerprints_odd_rows(spark):
    got = simhash.compare_edited(odd(spark), files=3).collect()
    assert len(got) == len(ODD)
    assert simhash.compare_edited(empty(spark)).count() == 0
    alone = simhash.compare_edited(spark.createDataFrame([(1, "abcd efgh")], "doc_id long, text string")).first()
    assert alone["near_next"] == 1.0


# ---- licenses


def test_licenses(spark, docs, rows):
    got = licenses.scan(docs).collect()
    assert {r["doc_id"] for r in got} == {i for i, t in rows.items() if re.search("[Ll]icense", t)}
    for r in got:
        assert r["coverage"] == 1.0 and "icense" in rows[r["doc_id"]][r["start"] : r["end"]]
    text = "é! Permission is hereby granted, free of CHARGE, to any person obtaining one copy of this software and associated documentation files (the Software), to deal in the Software without any restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software. end"
    one = licenses.scan(spark.createDataFrame([(1, text)], "doc_id long, text string")).collect()
    assert [(r["license"], text[r["start"] : r["start"] + 10]) for r in one] == [("mit-permission", "Permission")]
    assert 0.9 < one[0]["coverage"] < 1
    assert licenses.scan(odd(spark)).count() == 0 and licenses.scan(empty(spark)).count() == 0
    assert licenses.scan(docs, {"blank": "", "dots": "..."}).count() == 0


@given(st.lists(st.integers(0, 2**64 - 1), min_size=1, max_size=40))
def test_winnowing_guarantee(values):
    h = np.array(values, np.uint64)
    kept = set(licenses.winnowed(h, 6).tolist())
    assert all(kept & set(range(k, k + min(6, len(h)))) for k in range(max(1, len(h) - 5)))


# ---- personal data


def test_pseudonyms(spark):
    texts = ["Call +1 (017) 555-7713 or 555-123-4567.", "4111 1111 1111 1111 and 4111-1111-1111-1111 not 4111111111111112", "10.0.0.1 300.1.2.3", "2024-02-29 31.12.1999 2023-02-30", "123-45-6789 000-11-2222", "DE89 3704 0044 0532 0130 00", "John.Smith99@mail7.example.com", None, "", "4111111111111111"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in pii.pseudonymise(df).collect()}
    luhn = lambda s: sum(sum(divmod(int(c) * (1 + k % 2), 10)) for k, c in enumerate(reversed(s))) % 10 == 0
    a, b = re.search(r"^(\S+ \S+ \S+ \S+) and (\S+)", got[1]).groups()
    assert a.replace(" ", "") == b.replace("-", "") == got[9] != "4111111111111111" and luhn(got[9])
    assert "4111111111111112" in got[1] and "300.1.2.3" in got[2] and "2023-02-30" in got[3] and "000-11-2222" in got[4]
    assert re.fullmatch(r"Call \+1 \(\d{3}\) \d{3}-\d{4} or \d{3}-\d{3}-\d{4}\.", got[0]) and "7713" not in got[0]
    iban = got[5].replace(" ", "")
    assert int("".join(str(int(c, 36)) for c in iban[4:] + iban[:4])) % 97 == 1 and got[5] != texts[5]
    assert got[6].endswith("@mail7.example.com") and "smith" not in got[6].lower()
    assert got[7] is None and got[8] == ""
    other = pii.pseudonymise(df, pii.Settings(key="another")).where("doc_id = 9").first()["text"]
    assert other != got[9]


def test_feistel_permutes_its_domain(spark):
    s = pii.Settings()
    df = spark.range(21).select(pii.feistel((F.col("id") / 7).cast("long"), F.col("id") % 7, F.lit(3), F.lit(7), "t", s).alias("p"))
    assert len({(r["p"]["l"], r["p"]["r"]) for r in df.collect()}) == 21
    days = spark.sql("select date_format(date_add(date'1999-12-01', cast(id as int)), 'yyyy-MM-dd') v from range(400)")
    assert days.select(pii.pseudonym(F.col("v"))).distinct().count() == 400


def test_pseudonyms_plan_and_odd_rows(spark):
    out = pii.pseudonymise(odd(spark))
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan
    assert sorted(str(r["text"]) for r in out.collect()) == sorted(str(t) for _, t in ODD)
    assert pii.pseudonymise(empty(spark)).count() == 0
