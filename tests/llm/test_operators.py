import hashlib
import math
import random
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from nearcohort.llm import bpe, decontaminate, exact_dedup, licenses, ngram_join, passages, quality, queries, sharding, urls, warc
from nearcohort.plans.runtime import Workspace

VOCAB = public_tokenizers.path("byte_bpe_50k.json")


# -- benchmark decontamination ----------------------------------------------------------------
def test_contamination_equals_brute_force(spark):
    r = random.Random(3)
    words = [f"v{i}" for i in range(400)]
    items = [(i, " ".join(r.choices(words, k=r.randint(1, 60)))) for i in range(25)]
    docs = []
    for i in range(60):
        w = r.choices(words, k=r.choice([3, 40, 400, 4000]))
        if i % 2:
            w[len(w) // 2:len(w) // 2] = items[i % 25][1].split()
            if i % 4 == 1:
                w[len(w) // 2] = "changed"
        docs.append((i, " ".join(w)))
    want = set()
    for d, t in docs:
        for i, u in items:
            k = min(5, len(u.split()))
            q, own = decontaminate.word_shingles(u, k), decontaminate.word_shingles(t, k)
            if len(t.split()) >= k and 100 * len(q & own) >= 80 * len(q):
                want.add((d, i, len(q), len(q & own)))
    got = decontaminate.contaminated(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    assert {tuple(x)[:4] for x in got.collect()} == want and len(want) > 20


def test_contamination_edges(spark, weird, nothing):
    items = spark.createDataFrame([(1, None), (2, ""), (3, "one TWO three"), (4, "é à ü 日本 語 ü")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contaminated(weird, items).collect()}
    assert got == {(4, 3), (5, 3), (6, 3), (7, 3), (9, 4), (10, 4)}
    assert decontaminate.contaminated(nothing, items).count() == 0
    assert decontaminate.contaminated(weird, items.limit(0)).count() == 0
    kept = decontaminate.drop_contaminated(weird, items)
    assert kept.columns == weird.columns and kept.count() == 6
    assert decontaminate.drop_contaminated(nothing, items).count() == 0


def test_short_items_are_found_inside_documents(spark):
    docs = spark.createDataFrame([(1, "x y Alpha beta y"), (2, "alpha x beta"), (2, "beta"), (None, "ALPHA BETA"), (3, "alpha")], "doc_id long, text string")
    items = spark.createDataFrame([(1, "alpha beta"), (2, "beta"), (2, "beta"), (3, "x y alpha beta y z")], "item_id long, text string")
    got = sorted((r["doc_id"] or 0, r["item_id"]) for r in decontaminate.contaminated(docs, items).collect())
    assert got == [(0, 1), (0, 2), (0, 2), (1, 1), (1, 2), (1, 2), (2, 2), (2, 2), (2, 2), (2, 2)]
    left = decontaminate.drop_contaminated(docs, items).collect()
    assert [tuple(r) for r in left] == [(3, "alpha")]


def test_bin_minima_follow_from_shared_bits():
    r = np.random.default_rng(4)
    for n in (1, 2, 9, 500):
        s = np.unique(r.integers(0, 1 << 63, n, np.uint64) >> np.uint64(r.integers(0, 40)))
        for bits in (3, 8, 20, 40):
            assert (decontaminate.sketch(s, bits) == (decontaminate.shared_bits(s) < bits)).all()


# -- byte-pair encoding -------------------------------------------------------------------------
TEXTS = ["", "a", "Hello  world\n\n x", "I'll we've don't", "<|endoftext|>x<|endoftext|> y", "naïve 日本語 🎉👩‍👩‍👧  z\x1c\x85", "1234 ５６ Ⅻ", "x" * 500, "ab\r\n\tcd  "]


def test_codec_equals_library():
    lib = Tokenizer.from_file(VOCAB)
    mine = bpe.codec(open(VOCAB, encoding="utf-8").read())
    r = random.Random(1)
    more = ["".join(chr(r.choice([r.randint(32, 126), r.randint(160, 1500), r.randint(0x4E00, 0x4F00), 32, 10])) for _ in range(80)) for _ in range(200)]
    for t in TEXTS + more:
        ids = lib.encode(t, add_special_tokens=False).ids
        assert np.frombuffer(mine.encode(t), "<u4").tolist() == ids
        assert mine.decode(mine.encode(t)).decode("utf-8", "replace") == lib.decode(ids, skip_special_tokens=False)


def test_round_trip_query(spark, weird, nothing):
    lib = Tokenizer.from_file(VOCAB)
    text = {r["doc_id"]: r["text"] or "" for r in weird.collect()}
    for r in bpe.round_trip(weird, VOCAB).collect():
        ids = lib.encode(text[r["doc_id"]], add_special_tokens=False).ids
        assert r["n_tokens"] == len(ids)
        assert r["ids_sha256"] == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(text[r["doc_id"]].encode()).hexdigest()
    assert bpe.round_trip(nothing, VOCAB).count() == 0


def test_cache_is_bounded(monkeypatch):
    monkeypatch.setattr(bpe, "CACHE_WORDS", 5)
    c = bpe.Codec(__import__("json").load(open(VOCAB, encoding="utf-8")))
    c.encode(" ".join(f"w{i}" for i in range(50)))
    assert len(c.known) <= 5


# -- quality --------------------------------------------------------------------------------------
def test_quality_on_held_out_labels(spark):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    got = quality.score(docs, quality.fit(docs, labels)).join(labels, "doc_id").where("held_out").collect()
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in got)
    assert sum(r["predicted"] == r["quality"] for r in got) >= 0.93 * len(got)


def test_expression_equals_model(spark):
    r = np.random.default_rng(0)
    x = r.random((400, len(quality.FEATURES))).round(3)
    y = ((x[:, 2] > 0.5) & (x[:, 5] <= 0.6)).astype(float)
    m = quality.fit_rules(x, y)
    assert ((m.score(x) >= 0.5) == y).mean() > 0.97 and 0 < len(m.rules) < 80
    df = spark.createDataFrame([tuple(map(float, v)) for v in x], ", ".join(f"{f} double" for f in quality.FEATURES))
    got = [v[0] for v in df.select(m.column()).collect()]
    assert np.allclose(got, m.score(x))


def test_quality_edges(spark, weird, nothing):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    m = quality.fit(weird, none)
    got = quality.score(weird, m).collect()
    assert len(got) == 12 and all(r["score"] == 0.5 for r in got)
    one = quality.fit(weird, spark.createDataFrame([(i, 1, 0) for i in range(1, 12)], "doc_id long, quality int, toxic int"))
    assert all(r["score"] > 0.5 for r in quality.score(weird, one).collect())
    kept = quality.keep_good(weird, one)
    assert kept.columns == weird.columns and kept.count() == 12
    assert quality.score(nothing, m).count() == 0
    s = quality.block_statistics(np.array([0, 0, 3]), np.frombuffer(b"A b", np.uint8))
    assert s.shape == (2, len(quality.FEATURES)) and s[0, 0] == 0 and s[1, quality.FEATURES.index("upper_share")] == pytest.approx(1 / 3, abs=1e-6)


def plain_statistics(text):
    """The features of one text, written down plainly."""
    raw = (text or "").encode()
    kinds = dict.fromkeys(quality._KINDS, 0)
    for b in raw:
        c = chr(b)
        kinds["high" if b >= 128 else "lower" if "a" <= c <= "z" else "upper" if "A" <= c <= "Z" else "digit" if c.isdigit() else
              "newline" if c == "\n" else "space" if c in " \t\r\v\f" else "bang" if c in "!?" else "decor" if c in "*#$%&~^" else
              "pipe" if c in "|\\/<>[]{}" else "stop" if c in ".,;:'\"()-" else "other"] += 1
    words = raw.lower().split()
    lines = [tuple(x.split()) for x in raw.lower().split(b"\n")]
    lines = [x for x in lines if x]
    n = max(1, len(words))
    rich = math.log(max(1, len(set(words)))) / math.log(len(words)) if len(words) > 1 else 1.0
    return [math.log1p(len(raw)), math.log1p(len(words)), *(kinds[k] / max(1, len(raw)) for k in quality._KINDS), sum(map(len, words)) / n,
            len(set(words)) / n, rich, len(set(lines)) / max(1, len(lines)), math.log1p(len(words) / max(1, len(lines)))]


def test_quality_query_equals_a_plain_version(spark):
    """Every score of the registered query, from plain statistics and the rules read one by one."""
    d = "/root/testdata/sf0.001"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    model = quality.fit(docs, labels)
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    got = {r["doc_id"]: r for r in queries.QUERIES["op4_quality_classifier"](spark, d).collect()}
    assert set(got) == set(text)
    for i, t in text.items():
        x = [round(v, 6) for v in plain_statistics(t)]
        z = model.bias
        for rule, w in model.rules:
            if all((x[quality.FEATURES.index(f)] <= b) == below for f, below, b in rule.terms):
                z += w
        want = 1 / (1 + math.exp(-z))
        assert got[i]["score"] == pytest.approx(want, abs=1e-9) and got[i]["predicted"] == (want >= 0.3)
        assert got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0)


def test_keep_good_takes_any_column_name(spark):
    docs = spark.createDataFrame([(1, "some text", 1.0, 2, 3), (1, "some text", 1.0, 2, 3), (None, None, 2.0, 3, 4)], "doc_id long, text string, __log_bytes double, statistics int, row_key int")
    kept = quality.keep_good(docs, quality.RuleModel(1.0, [(quality.Rule((("log_bytes", False, 0.5),)), 1.0)]))
    assert kept.columns == docs.columns and kept.count() == 3
    for drop in (exact_dedup.drop_duplicates, ngram_join.drop_near_duplicates, passages.remove_repeats):
        left = drop(docs)
        assert left.columns == docs.columns and left.count() == (3 if drop is passages.remove_repeats else 2)


# -- exact dedup ----------------------------------------------------------------------------------
def test_exact_groups(spark, weird, nothing):
    got = {r["doc_id"]: r for r in exact_dedup.duplicate_groups(weird, "largest").collect()}
    assert got[1]["keep_id"] == 2 and not got[1]["kept"] and got[2]["kept"] and got[2]["group_size"] == 2
    assert got[9]["keep_id"] == 10 and got[4]["kept"] and got[4]["text_sha256"] == hashlib.sha256(b"one two three").hexdigest()
    small = {r["doc_id"]: r["keep_id"] for r in exact_dedup.duplicate_groups(weird).collect()}
    assert small[10] == 9 and small[2] == 1
    assert exact_dedup.duplicate_groups(nothing).count() == 0
    kept = exact_dedup.drop_duplicates(weird, "largest")
    assert kept.columns == weird.columns and kept.count() == 10
    with pytest.raises(ValueError):
        exact_dedup.duplicate_groups(weird, "any")


def test_texts_that_share_a_digest_are_told_apart(spark, monkeypatch):
    monkeypatch.setattr(exact_dedup, "content_digest", lambda text="text": F.encode(F.substring(F.coalesce(F.col(text), F.lit("")), 1, 1), "utf-8"))
    docs = spark.createDataFrame([(1, "aa"), (2, "ab"), (3, "ab"), (4, "b"), (5, "b"), (6, "c")], "doc_id long, text string")
    got = {r["doc_id"]: (r["keep_id"], r["group_size"]) for r in exact_dedup.duplicate_groups(docs).collect()}
    assert got == {1: (1, 1), 2: (2, 2), 3: (2, 2), 4: (4, 2), 5: (4, 2), 6: (6, 1)}


def test_rows_are_removed_one_by_one(spark):
    rows = [(1, "a"), (2, "a"), (1, "b"), (7, "z"), (7, "z"), (None, "z"), (None, "q"), (None, "q"), (9, None), (8, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = exact_dedup.duplicate_groups(docs, "largest").collect()
    assert len(got) == 10 and all(r["kept"] is not None for r in got)
    assert sorted((r["doc_id"] or 0, r["keep_id"] or 0, r["group_size"]) for r in got if r["kept"]) == [(0, 0, 2), (1, 1, 1), (2, 2, 2), (7, 7, 3), (9, 9, 2)]
    for keep, want in (("largest", [(None, "q"), (1, "b"), (2, "a"), (7, "z"), (9, None)]), ("smallest", [(None, "q"), (1, "a"), (1, "b"), (7, "z"), (8, "")])):
        left = [tuple(r) for r in exact_dedup.drop_duplicates(docs, keep).collect()]
        assert sorted(left, key=lambda r: (r[0] or 0, r[1] or "")) == want


def _log(spark, n, different, memtable):
    return spark.range(0, n, 1, 3).select(
        F.col("id"), F.col("id").alias("row"), F.unhex(F.sha2((F.col("id") % different).cast("string").cast("binary"), 256)).alias("digest"),
        F.floor(F.col("id") / memtable).cast("long").alias("memtable"))


def test_index_of_several_runs(spark):
    log = _log(spark, 3000, 2000, 100)
    index = exact_dedup.DigestIndex(Workspace(spark, "lsm"), 3000)
    index.flush(log.where("id < 1500"))
    index.flush(log.where("id >= 1500"))
    assert index.runs.select("run").distinct().count() == 2 * exact_dedup.RUNS
    want = {r["digest"]: (r["a"], r["z"], r["n"]) for r in log.groupBy("digest").agg(F.min("id").alias("a"), F.max("id").alias("z"), F.count("*").alias("n")).collect()}
    shared = {r["digest"] for r in index.shared().collect()}
    assert {d for d, w in want.items() if w[2] > 1} <= shared and len(shared) < 1150  # all in several runs, few by chance
    asked = log.where("id < 50").unionByName(_log(spark, 60, 60, 9).withColumn("digest", F.unhex(F.md5(F.col("id").cast("string")))))
    found = {r["digest"]: (r["least"]["id"], r["greatest"]["id"], r["n"]) for r in index.look_up(asked).collect()}
    assert len(found) == 50 and all(want[d] == v for d, v in found.items())
    level = index.compact().collect()
    assert {r["digest"]: (r["least"]["id"], r["greatest"]["id"], r["n"]) for r in level} == want and len(level) == 2000
    assert index.look_up(log).count() == 2000 and index.runs.select("run").distinct().count() == 1


def test_groups_across_memtables(spark, monkeypatch):
    monkeypatch.setattr(exact_dedup, "MEMTABLE_ROWS", 50)
    docs = spark.range(0, 2000, 1, 3).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, "hot").otherwise((F.col("id") % 700).cast("string")).alias("text"))
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    groups = {}
    for i, t in texts.items():
        groups.setdefault(t, []).append(i)
    for r in exact_dedup.duplicate_groups(docs, "largest").collect():
        g = groups[texts[r["doc_id"]]]
        assert (r["keep_id"], r["group_size"], r["kept"]) == (max(g), len(g), r["doc_id"] == max(g))


# -- substring dedup --------------------------------------------------------------------------------
def test_chunks_cover_the_text_and_survive_insertions():
    r = random.Random(2)
    raw = bytes(r.randrange(97, 123) for _ in range(5000))
    ends = passages.cuts(np.frombuffer(raw, np.uint8))
    assert ends[-1] == 5000 and ends == sorted(set(ends))
    assert all(b - a <= passages.MAX_CHUNK for a, b in zip([0, *ends], ends, strict=False))

    def chunks(b):
        e = passages.cuts(np.frombuffer(b, np.uint8))
        return {b[i:j] for i, j in zip([0, *e[:-1]], e, strict=True)}

    moved = chunks(raw[:100] + b"inserted" + raw[100:])
    assert len(chunks(raw) & moved) >= 0.9 * len(chunks(raw))
    assert passages.cuts(np.zeros(0, np.uint8)) == []


def test_rolling_hash_equals_its_definition():
    data = np.frombuffer(bytes(range(1, 100)), np.uint8)
    want, h = [], 0
    for b in data:
        h = ((h << 1) + int(passages._GEAR[b])) & 0xFFFFFFFF
        want.append(h)
    assert passages.gear(data).tolist() == want


def test_planted_passage_is_found_and_removed(spark):
    r = random.Random(4)
    text = lambda n: " ".join("".join(r.choices("abcdefgh", k=r.randint(2, 8))) for _ in range(n))
    passage = text(60)
    docs = [(i, text(200) if i % 5 else text(80) + " " + passage + " " + text(70)) for i in range(1, 31)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = passages.repeated_spans(df).collect()
    assert {x["doc_id"] for x in got} == {i for i, _ in docs if i % 5 == 0}
    assert {x["doc_id"] for x in got if x["n_later"] == 0} == {5} and {x["first_doc"] for x in got} == {5}
    clean = {x["doc_id"]: x["text"] for x in passages.remove_repeats(df).collect()}
    assert passage in clean[5] and passage not in clean[10] and clean[1] == dict(docs)[1]


def test_short_passages_are_found_in_every_place(spark):
    r = random.Random(11)
    common = ["".join(r.choices("etaoinshrdlu", k=r.choice((2, 3, 4, 5, 5, 6, 7, 9)))) for _ in range(3000)]
    text = lambda n: " ".join(r.choices(common, k=n))
    docs, planted = [], []
    for k in range(1500):
        p = text(51 + k % 10)
        for i in (2 * k, 2 * k + 1):
            before = text(60)
            docs.append((i, f"{before} {p} {text(60)}"))
            planted.append((i, len(before) + 1, len(p)))
    found = {}
    for x in passages.repeated_spans(spark.createDataFrame(docs, "doc_id long, text string")).collect():
        found.setdefault(x["doc_id"], []).append((x["start"], x["start"] + x["size"]))
    whole = sum(any(a <= s and s + n <= b for a, b in found.get(i, ())) for i, s, n in planted)
    assert whole >= 0.995 * len(planted)
    texts = dict(docs)
    for i, spans in found.items():
        assert all(texts[i][a:b] in texts[i ^ 1] for a, b in spans if b - a < 1000)


def test_spans_against_brute_force(spark):
    """Small texts with passages shared by two or more: what is reported is repeated, what is long and
    repeated is reported."""
    r = random.Random(21)
    word = lambda: "".join(r.choices("abcdefghijklmnop", k=r.randint(3, 9)))
    text = lambda n: " ".join(word() for _ in range(n))
    shared = [text(70) for _ in range(8)]
    docs = [(i, " ".join(r.choice([text(r.randint(5, 60)), r.choice(shared)]) for _ in range(r.randint(1, 4)))) for i in range(60)]
    docs += [(100, docs[3][1]), (101, docs[3][1])]
    texts = dict(docs)
    spans = {}
    for x in passages.repeated_spans(spark.createDataFrame(docs, "doc_id long, text string")).collect():
        spans.setdefault(x["doc_id"], []).append((x["start"], x["start"] + x["size"]))
    grams = {}  # every place of every run of 24 characters
    for i, t in docs:
        for a in range(len(t) - 23):
            grams.setdefault(t[a:a + 24], set()).add((i, a))
    missed = total = 0
    for i, t in docs:
        again = [len(grams[t[a:a + 24]]) > 1 for a in range(max(0, len(t) - 23))]
        covered = np.zeros(len(t), bool)
        for a, b in spans.get(i, ()):
            covered[a:b] = True
            # each place in a span lies in a run that occurs elsewhere
            ok = np.zeros(len(t), bool)
            for p in range(max(0, a - 23), min(b, len(again))):
                if again[p]:
                    ok[p:p + 24] = True
            assert ok[a:b].all(), (i, a, b)
        at = 0
        while at < len(again):  # runs of 250 repeated characters and more
            end = at
            while end < len(again) and again[end]:
                end += 1
            if end - at + 23 >= 250:
                total += 1
                missed += covered[at:end + 23].mean() < 0.9
            at = end + 1
    assert total > 40 and missed <= 0.02 * total


def test_passages_row_by_row(spark):
    r = random.Random(5)
    text = lambda n: " ".join("".join(r.choices("abcdefgh", k=r.randint(2, 8))) for _ in range(n))
    p = text(70)
    docs = spark.createDataFrame([(1, f"{text(30)} {p}", 0), (1, f"{p} {text(30)}", 1), (None, p, 2), (3, None, 3), (4, text(90), 4)], "doc_id long, text string, cuts int")
    got = sorted((x["doc_id"] or 0, x["n_later"] > 0, x["first_doc"]) for x in passages.repeated_spans(docs).collect())
    assert [g[:2] for g in got] == [(0, True), (1, False), (1, True)] and {g[2] for g in got} == {1}
    left = {x["cuts"]: x["text"] for x in passages.remove_repeats(docs).collect()}
    assert p in left[0] and p not in left[1] and len(left[2]) < 40 and left[3] is None and len(left) == 5


def test_passage_edges(weird, nothing):
    got = {(r["doc_id"], r["start"], r["size"]) for r in passages.repeated_spans(weird, 1).collect()}
    assert (9, 0, 26) in {g for g in got} or any(g[0] == 9 for g in got)
    assert not any(g[0] in (1, 2) for g in got)
    assert passages.repeated_spans(nothing).count() == 0 and passages.remove_repeats(weird).count() == 12


# -- licenses ---------------------------------------------------------------------------------------
def test_license_spans(spark, weird, nothing):
    rows = [(1, "x y z. Released under the MIT License.\nmore words"), (2, "released UNDER the mit license and licensed under cc by-nc 4.0 ok"),
            (3, "under the license of things"), (4, None), (5, licenses.TEMPLATES[1][1].replace("free of charge", "at no cost") + " end"),
            (6, "Released under the MIT License. " * 3), (7, "Licensed under the Apache License, Version 2.0.")]
    got = licenses.license_spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    have = {(r["doc_id"], r["license"]) for r in got}
    assert have == {(1, "mit-notice"), (2, "mit-notice"), (2, "cc-by-nc-4.0-notice"), (5, "mit-grant"), (6, "mit-notice"), (7, "apache-2.0-notice")}
    one = next(r for r in got if r["doc_id"] == 1)
    assert rows[0][1].encode()[one["start_byte"]:one["end_byte"]] == b"Released under the MIT License" and one["coverage"] == 1.0
    assert sum(r["doc_id"] == 6 for r in got) == 3
    grant = next(r for r in got if r["doc_id"] == 5)
    assert 0.8 <= grant["coverage"] < 1
    assert licenses.license_spans(nothing).count() == 0 and licenses.license_spans(weird, []).count() == 0


def test_recall_of_candidates_against_alignment_of_everything(spark):
    """Templates with a share of their words replaced, dropped or added, inside other text: what a
    whole alignment finds, the fingerprints must bring up."""
    r = random.Random(12)
    filler = lambda n: " ".join("".join(r.choices("etaoinshrdlu", k=r.randint(2, 9))) for _ in range(n))
    docs, truth = [], set()
    plain = lambda t: ["".join(c if c.isalnum() or ord(c) > 127 else " " for c in x) for x in [t.lower()]][0].split()
    for k in range(260):
        name, text = licenses.TEMPLATES[k % len(licenses.TEMPLATES)]
        w, rate = text.split(), r.choice([0.0, 0.04, 0.08, 0.12])
        out = []
        for x in w:
            y = r.random()
            out += [] if y < rate / 3 else [filler(1)] if y < 2 * rate / 3 else [x, filler(1)] if y < rate else [x]
        docs.append((k, f"{filler(40)} {' '.join(out)} {filler(40)}"))
        a, b = plain(text), plain(" ".join(out))
        row = [0] * (len(b) + 1)
        for u in a:  # longest common subsequence
            new = [0]
            for j, v in enumerate(b):
                new.append(row[j] + 1 if u == v else max(row[j + 1], new[-1]))
            row = new
        if row[-1] >= licenses.MIN_COVERAGE * len(a):
            truth.add((k, name))
    got = {(x["doc_id"], x["license"]) for x in licenses.license_spans(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert len(truth) > 200 and len(truth & got) >= 0.95 * len(truth)
    clean = spark.createDataFrame([(i, filler(400)) for i in range(50)], "doc_id long, text string")
    assert licenses.license_spans(clean).count() == 0
    table = spark.createDataFrame([("own", "my own little license of ten words for everybody here"), ("none", None)], "name string, text string")
    assert [x["license"] for x in licenses.license_spans(spark.createDataFrame([(None, "x My own little license of ten words, for everybody here!")], "doc_id long, text string"), table).collect()] == ["own"]


def test_alignment_equals_longest_common_subsequence():
    r = random.Random(6)
    for _ in range(100):
        a, b = (np.array([r.randrange(4) for _ in range(r.randint(1, 12))], np.uint64) for _ in range(2))
        table = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i in range(len(a)):
            for j in range(len(b)):
                table[i + 1][j + 1] = table[i][j] + 1 if a[i] == b[j] else max(table[i][j + 1], table[i + 1][j])
        assert licenses.align(a, b, 0, 50)[0] == table[-1][-1]


# -- sharding ---------------------------------------------------------------------------------------
def test_shards(spark, weird, nothing):
    r = random.Random(8)
    rows = [(i, "hot text" if i % 3 == 0 else " ".join(r.choices("abcde", k=r.randint(1, 60)))) for i in range(3000)]
    got = sharding.shard(spark.createDataFrame(rows, "doc_id long, text string"), 10).collect()
    assert len(got) == 3000
    load = [sum(x["size"] for x in got if x["shard"] == k) for k in range(10)]
    assert max(load) <= 1.02 * min(load)
    for k in range(10):
        assert sorted(x["slot"] for x in got if x["shard"] == k) == list(range(sum(x["shard"] == k for x in got)))
    text = dict(rows)
    assert all(x["text_crc32"] == zlib.crc32(text[x["doc_id"]].encode()) and x["size"] == len(text[x["doc_id"]]) + 16 for x in got)
    where = {}
    for x in got:
        where.setdefault(text[x["doc_id"]], set()).add(x["shard"])
    assert all(len(v) == 1 for t, v in where.items() if t != "hot text") and len(where["hot text"]) > 1
    small = sharding.shard(weird, 3).collect()
    assert len(small) == 12 and next(x for x in small if x["doc_id"] == 1)["size"] == 16
    assert sharding.shard(nothing, 3).count() == 0
    with pytest.raises(ValueError):
        sharding.shard(weird, 0)


def test_sharding_query_against_its_contract(spark):
    d = "/root/testdata/sf0.01"
    text = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{d}/documents.parquet").collect()}
    got = queries.QUERIES["op8_vector_sharding"](spark, d).collect()
    assert sorted(r["doc_id"] for r in got) == sorted(text) and {r["shard"] for r in got} <= set(range(40))
    slots, load = {}, {}
    for r in got:
        raw = (text[r["doc_id"]] or "").encode()
        assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(raw) + 16, zlib.crc32(raw), "bytes", None)
        assert r["n_words"] == len((text[r["doc_id"]] or "").split())
        slots.setdefault(r["shard"], []).append(r["slot"])
        load[r["shard"]] = load.get(r["shard"], 0) + r["size"]
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    # no packing beats the mean or the longest text
    assert max(load.values()) <= max(1.05 * sum(load.values()) / 40, max(r["size"] for r in got))


def test_packing_balances_every_dimension():
    r = np.random.default_rng(1)
    v = r.random((2000, 3)) + 0.01
    b = sharding.pack(v, 8)
    loads = np.array([v[b == k].sum(axis=0) for k in range(8)])
    assert (loads.max(axis=0) / loads.min(axis=0)).max() < 1.1
    assert sharding.pack(np.zeros((0, 3)), 4).tolist() == []


# -- urls -------------------------------------------------------------------------------------------
def test_url_rules_and_terms(spark):
    cases = {
        None: ("", "", None, "allow"), "": ("", "", None, "allow"), "no scheme/casino": ("", "", None, "block"),
        "http://A.Example.org/es/x": ("a.example.org", "/es/x", "example.org/es/", "block"), "http://example.org/en/12?q#f": ("example.org", "/en/12", "example.org/en/1", "block"),
        "https://x.org/casino": ("x.org", "/casino", "org/", "allow"), "http://notexample.org/es/": ("notexample.org", "/es/", "org/", "allow"),
        "http://shop.com/fr/cheap-pills": ("shop.com", "/fr/cheap-pills", "com/fr/", "allow"), "http://shop.com/de/": ("shop.com", "/de/", "com/de/", "block"),
        "http://casino-win.net/": ("casino-win.net", "/", None, "block"), "http://casinos.net/": ("casinos.net", "/", None, "allow"),
        "http://free-bets.net": ("free-bets.net", "", None, "block"), "http://free-free.net/x": ("free-free.net", "/x", None, "allow"),
        "http://écasino.net/": ("écasino.net", "/", None, "allow"), "http://x.net/casinoé": ("x.net", "/casinoé", None, "allow"),
        "http://XXX.net?x=1": ("xxx.net", "", None, "block"), "http://org/x": ("org", "/x", "org/", "allow")}
    df = spark.createDataFrame([(i, u, 5) for i, u in enumerate(cases)], "page_id long, url string, host int")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in urls.judge(df).collect()}
    assert got == dict(enumerate(cases.values()))
    assert urls.judge(df.limit(0)).count() == 0
    words = spark.createDataFrame([("Widgets", None), ("red", 1.0), ("blue", 1.0), ("blue", 0.5), (None, 1.0)], "term string, weight double")
    pages = spark.createDataFrame([(1, "http://a.net/widgets"), (1, "http://a.net/red-blue"), (None, "http://a.net/red"), (2, "http://casino.net")], "page_id long, url string")
    got = sorted((r["page_id"] or 0, r["verdict"], r["n_strict"], r["n_soft"]) for r in urls.judge(pages, vocabulary=words).collect())
    assert got == [(0, "allow", 0, 1), (1, "block", 0, 2), (1, "block", 1, 0), (2, "allow", 0, 0)]


# -- archives ---------------------------------------------------------------------------------------
def test_archives_round_trip(spark):
    magic = "WARC/1.0\r\n"
    whole = magic + "WARC-Type: response\r\nWARC-Record-ID: <urn:page:99>\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n"
    html = {1: "x" * 100, 2: "x" * 100, 3: "short", 4: "short", 5: None, 6: "", 7: f"a {magic} b " + "y" * 200, 8: whole, 9: f"{magic}{magic}", 10: f"p{whole}q{whole}",
            11: "é" * 200, 12: "é" * 200, 13: "end\r\n\r\n", 14: magic, 15: "x" * 99, 16: "x" * 99}
    df = spark.createDataFrame([(i, None if i == 3 else f"http://h/{i}\r\nX: y", h, "z") for i, h in html.items()], "page_id long, url string, html string, digest string")
    for options in ({}, {"compression": "none"}, {"file_records": 2}):
        got = {r["page_id"]: r for r in warc.archive_round_trip(df.repartition(3), **options).collect()}
        assert sorted(got) == sorted(html)
        for i, h in html.items():
            raw = (h or "").encode()
            assert got[i]["payload_bytes"] == len(raw) and got[i]["payload_digest"] == hashlib.sha256(raw).hexdigest(), (i, options)
            assert (got[i]["record_type"], got[i]["refers_to"]) == (("revisit", {2: 1, 12: 11}[i]) if i in (2, 12) else ("response", None))
    assert warc.archive_round_trip(df.limit(0)).count() == 0


def test_archives_are_plain_warc(spark):
    work = Workspace(spark, "warc")
    where = work.place("one")
    warc.write_archives(spark.createDataFrame([(1, "http://h/", "<p>hi</p>")], "page_id long, url string, html string").coalesce(1), where, work, "none")
    (raw,) = [bytes(r["content"]) for r in spark.read.format("binaryFile").load(where).collect() if r["length"]]
    assert raw.startswith(b"WARC/1.0\r\nWARC-Type: response\r\n") and raw.endswith(b"\r\n\r\n<p>hi</p>\r\n\r\n") and b"Content-Length: 9\r\n" in raw


# -- kernels ----------------------------------------------------------------------------------------
def test_shingles_do_not_depend_on_blocks(monkeypatch):
    from nearcohort.llm import textblocks as T

    texts = pa.array(["a b c d e f", None, "", "A B", "é " * 30, "x y z w v u t s"] * 3)
    one = [s.tolist() for s in T.shingle_sets(texts)]
    monkeypatch.setattr(T, "BLOCK_BYTES", 7)
    assert [s.tolist() for s in T.shingle_sets(texts)] == one
    assert [s.tolist() for s in T.shingle_sets(texts.slice(4, 5))] == one[4:9]
