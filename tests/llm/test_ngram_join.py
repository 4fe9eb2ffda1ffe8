import math
import random
import re

import numpy as np
import pyarrow as pa

from nearcohort.llm import ngram_join as N
from nearcohort.llm.decontaminate import word_shingles


def shingles(t):
    return word_shingles(t, 5)


def brute(docs):
    """docs: (id, text) -> {id: (set size, component)}."""
    sets = {i: shingles(t) for i, t in docs}
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                up[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


def family(seed=0, n=120):
    r = random.Random(seed)
    words = [f"w{i}" for i in range(300)]
    docs, base = [], [r.choices(words, k=r.randint(5, 80)) for _ in range(15)]
    shared = r.choices(words, k=40)
    for i in range(n):
        w = list(r.choice(base))
        for _ in range(r.choice([0, 0, 1, 2, 5])):
            w[r.randrange(len(w))] = r.choice(words)
        if r.random() < 0.3:
            w = w + shared
        docs.append((i * 3 + 1, " ".join(w)))
    return docs


def test_join_equals_brute_force(spark):
    for seed in (1, 2):
        docs = family(seed)
        got = N.jaccard_classes(spark.createDataFrame(docs, "doc_id long, text string")).collect()
        assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == brute(docs)


def test_edges_of_the_domain(spark, weird, nothing):
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in N.jaccard_classes(weird).collect()}
    assert got[1] == (0, 1) and got[2] == (0, 2) and got[3] == (0, 3)
    assert got[4] == (1, 4) and got[5] == (1, 4) and got[6] == (1, 6) and got[10][1] == 9 and got[11][0] == 1
    assert len(got) == 12
    assert N.jaccard_classes(nothing).count() == 0
    kept = N.drop_near_duplicates(weird)
    assert kept.columns == weird.columns and {5, 10}.isdisjoint({r["doc_id"] for r in kept.collect()}) and kept.count() == 10


def test_search_of_a_block_equals_brute_force():
    r = random.Random(5)
    for _ in range(60):
        sets = [np.unique(np.array(r.sample(range(60), r.randint(1, 40)), np.uint64)) for _ in range(20)]
        q = np.unique(np.array(r.sample(range(60), r.randint(1, 40)), np.uint64))
        want = [(i, len(set(q) & set(s))) for i, s in enumerate(sets)
                if 100 * len(set(q) & set(s)) >= 80 * len(set(q) | set(s))]
        assert N.TOccurrence(sets).search(q) == want
    assert N.TOccurrence([]).search(q) == []


def test_overlap_bounds():
    for n in range(1, 60):
        for m in range(1, 60):
            linked = [o for o in range(min(n, m) + 1) if 100 * o >= 80 * (n + m - o)]
            if linked:
                assert linked[0] == N.overlap_needed(n, m) >= max(N.need(n), N.need(m))


def test_texts_whose_words_collide_in_weak_hashes_are_apart(spark):
    thue = ["".join("ab"[(bin(i).count("1") + f) % 2] for i in range(2048)) for f in (0, 1)]
    docs = [(1, thue[0]), (2, thue[1]), (3, f"x y z w {thue[0]}"), (4, f"x y z w {thue[1]}"), (5, thue[0])]
    got = {r["doc_id"]: r["component_id"] for r in N.jaccard_classes(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == {1: 1, 2: 2, 3: 3, 4: 4, 5: 1}


def test_words_decide_where_hashes_collide(spark, monkeypatch, tmp_path):
    """With hashes of a few bits different texts share signatures and shingles; the words tell them apart."""
    real = N.shingle_sets

    def weak(texts, k=5):
        for s in real(texts, k):
            yield np.unique(s % np.uint64(3))

    monkeypatch.setattr(N, "shingle_sets", weak)
    a, b, c = "one two three four five", "six seven eight nine ten", "a b c d e"
    texts = pa.array([a, b, c, a.upper()])
    sets = list(weak(texts))
    assert len({s.tobytes() for s in sets}) < 3
    batch = lambda rows: pa.RecordBatch.from_pylist(rows, pa.schema([("b", pa.int64()), ("part", pa.int64()), ("lead", pa.bool_()), ("row", pa.int64()), ("text", pa.string())]))
    rows = [{"b": 1, "part": 0, "lead": i == 0, "row": i + 1, "text": t} for i, t in enumerate([a, b, c, a.upper()])]
    links = [tuple(r.values()) for rb in N._search(iter([batch(rows)]), 5, 80) for r in rb.to_pylist()]
    assert links == [(4, 1, 1)]
    canon = [x for rb in N._canonical(iter([pa.RecordBatch.from_pydict({"row": pa.array([1, 2, 3, 4]), "text": texts})]), 5) for x in rb.to_pydict()["canon"]]
    assert canon[0] == canon[3] and len(set(canon)) == 3


def test_equal_sets_in_other_orders_are_one_class(spark):
    docs = [(1, "a " * 9), (2, "a " * 30), (3, "A " * 9), (4, "p q r s t p q r s t p"), (5, "q r s t p q r s t p")]
    got = {r["doc_id"]: r["class_id"] for r in N.jaccard_classes(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 4: 4, 5: 4}


def test_repeated_and_missing_ids_keep_their_own_sets(spark):
    text = "one two three four five six seven eight nine ten"
    docs = spark.createDataFrame([(7, text), (7, "quite another text of seven words"), (7, text), (None, text), (None, "alone with no id at all"), (9, text + " x")],
                                 "doc_id long, text string")
    got = sorted((r["doc_id"] or 0, r["n_shingles"], r["component_id"] or 0) for r in N.jaccard_classes(docs).collect())
    assert got == [(0, 2, 0), (0, 6, 7), (7, 2, 7), (7, 6, 7), (7, 6, 7), (9, 7, 7)]
    left = sorted(((r["doc_id"] or 0), r["text"]) for r in N.drop_near_duplicates(docs).collect())
    assert left == [(0, "alone with no id at all"), (7, text), (7, "quite another text of seven words")]


def test_all_links_of_all_classes(spark):
    base = [[f"b{j}w{i}" for i in range(60)] for j in range(3)]
    docs = [(3 * i + 1, " ".join([*base[i % 3][:-1 - i % 2], f"end{i // 6}"])) for i in range(36)]
    links, members = N.jaccard_links(spark.createDataFrame(docs, "doc_id long, text string"))
    sets = {i: shingles(t) for i, t in docs}
    rep = {}
    for i in sorted(sets):
        rep.setdefault(frozenset(sets[i]), i)
    want = {(a, b, len(sets[a] & sets[b])) for a in rep.values() for b in rep.values()
            if a > b and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])}
    assert {tuple(r) for r in links.collect()} == want and len(want) > 20
    assert {r["doc_id"]: r["class_id"] for r in members.collect()} == {i: rep[frozenset(s)] for i, s in sets.items()}


def test_blocks_of_a_hot_leader_are_split(spark, monkeypatch):
    monkeypatch.setattr(N, "BLOCK_CLASSES", 4)
    monkeypatch.setattr(N, "BLOCK_TEXT", 200)
    base = [f"w{i}" for i in range(60)]
    docs = [(i, " ".join([*base, f"end{i}"])) for i in range(1, 41)]
    assert {r["component_id"] for r in N.jaccard_classes(spark.createDataFrame(docs, "doc_id long, text string")).collect()} == {1}


def test_words_are_split_at_ascii_blanks_only(spark):
    t = "a b\x0bc\x1fd E f g"
    words = re.findall(r"[^\x20\x09-\x0D]+", t)
    assert len(words) == 4
    got = N.jaccard_classes(spark.createDataFrame([(1, t), (2, t.replace("E", "e"))], "doc_id long, text string")).collect()
    assert {r["component_id"] for r in got} == {1}


def _posted(spark, seed, step=1):
    """Random sets over 60 shingles whose values are multiples of ``step``: (sets, lists, postings)."""
    r = random.Random(seed)
    base = [r.sample(range(60), r.randint(5, 40)) for _ in range(8)]
    sets = {}
    for c in range(1, 61):
        s = set(r.choice(base)) if r.random() < 0.8 else set(r.sample(range(60), r.randint(1, 40)))
        for _ in range(r.choice([0, 1, 2])):
            s.add(r.randrange(60))
        sets.setdefault(tuple(sorted(x * step for x in s)), c)
    none = np.zeros(0, np.uint64)
    post = [(int(h), c, len(s), i, math.floor(math.log(len(s)) / math.log(1.25) + 1e-9))
            for s, c in sets.items() for i, h in enumerate(N.short_lists(np.array(s, np.uint64), none, none, 80))]
    placed = N._placed(spark.createDataFrame(post, "h long, c long, n long, pos int, band long"), None)
    linked = {(a, b) for s, a in sets.items() for t, b in sets.items() if a > b and 100 * len({*s} & {*t}) >= 80 * len({*s} | {*t})}
    return placed, N._lists(placed), linked


def test_pairs_meet_once_also_where_16_bits_tell_nothing(spark):
    for seed, step in ((1, 1), (2, 1), (3, 1 << 16)):
        placed, lists, linked = _posted(spark, seed, step)
        near = N._may_meet(placed, 80)
        met = [tuple(r) for r in N._meetings(near, lists, 80).collect()]
        assert linked and linked <= set(met) and len(met) == len(set(met))
        assert near.count() < placed.count()
        assert set(met) == {tuple(r) for r in N._meetings(placed, lists, 80).collect()}


def test_what_meets_carries_its_lists_in_16_bits(spark):
    placed, lists, _ = _posted(spark, 1)
    plan = N._meetings(N._may_meet(placed, 80), lists, 80)._jdf.queryExecution().analyzed().toString()
    assert "smallint" in plan and "hs_a" not in plan
