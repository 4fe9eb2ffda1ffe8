"""N-gram Jaccard join: a distributed T-occurrence search.

Two texts link when ``100 * |A & B| >= pct * |A | B|`` for their sets of word shingles.
A text with ``n`` shingles can only link with one that shares at least
``need(n) = ceil(pct * n / 100)`` of them, so it must share one of any ``n - need(n) + 1``.
Every text therefore divides its inverted lists: the *short* ones (its rarest shingles, by
counts over the whole corpus) are distributed by Spark and say which blocks of documents a
text has to be searched in; the *long* ones never leave their text.

1. ``frequent_shingles`` counts in all texts; a bounded table of heavy counts is kept.  It
   only sets the order of a text's lists and cannot change the result.
2. Texts with equal sets become one class, so copies are never paired.
3. The short lists are the postings ``(shingle, class)``.  Lists of one class are dropped, and so
   are postings that by size and place cannot be the first that a linked pair shares.
4. Leaders: a class visits a few of the leaders of its lists and length bands, round by round
   as long as a round finds links for a hundredth of the classes that share a list.
   A round is linear in the classes, also for a group of thousands of near copies, and together
   they unite nearly all that links.
5. Visits that share too few short lists to reach the overlap are dropped.
6. A leader and the classes that visit it form blocks of bounded size; the texts of a block
   travel once each.  In a block ``TOccurrence`` answers the leader's query by divide and
   skip: its shorter lists are merged in a heap that skips ahead, its longest lists are probed
   by binary search, and what reaches the overlap is compared on the words themselves.
7. Components; then the *rest*: classes that share a list but are still in different
   components are all searched, so no link between different components is lost.  Such a pair
   is met once, on the first list that both have, and only if all their short lists allow a link.
8. Components again.

``jaccard_links`` searches all pairs of classes that share a list and reports every link;
``jaccard_classes`` needs the components only and leaves out links within what is united.
"""

from __future__ import annotations

import hashlib
import heapq
import math
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearcohort.llm.rows import keyed_rows, without
from nearcohort.llm.textblocks import plain_shingles, plain_words, release, shingle_sets
from nearcohort.operators.components import components
from nearcohort.plans.runtime import Workspace, ship, small

#: Entries of the table of frequent shingles: at most 16 MB, whatever the corpus.
MAX_FREQUENT = 1_000_000
#: Leaders that a class meets in the first rounds and in all later ones; the rest is compared in
#: full afterwards, so neither these nor the number of rounds can change the result.
LEADER_TAKES = (2, 4, 8)
MAX_ROUNDS = 12
#: Another round follows one that found links for this share of the classes that share a list.
ROUND_YIELD = 0.01
#: Classes of one block beside its leader, and bytes of text that a task indexes at once.
BLOCK_CLASSES = 256
BLOCK_TEXT = 1 << 20
#: Fixed value: weight of the logarithm in the number of probed lists (divide and skip).
PROBE_WEIGHT = 0.0085


def need(n, pct: int = 80):
    """Least overlap with any linked set (ceil(pct*n/100)); works on ints and arrays."""
    return -(-pct * n // 100)


def overlap_needed(n, m, pct: int = 80):
    """Least overlap of sets of n and m: 100*o >= pct*(n+m-o)."""
    return -(-pct * (n + m) // (100 + pct))


class TOccurrence:
    """Inverted lists over a block of sets, searched by divide-and-skip."""

    def __init__(self, sets: list[np.ndarray]):
        self.sizes = np.array([len(s) for s in sets], np.int64)
        grams = np.concatenate(sets) if sets else np.zeros(0, np.uint64)
        who = np.repeat(np.arange(len(sets)), self.sizes)
        order = np.argsort(grams, kind="stable")  # a stable sort leaves every list in order
        grams, ids = grams[order], who[order]
        new = np.ones(len(grams), bool)
        new[1:] = grams[1:] != grams[:-1]
        self.at = np.append(np.flatnonzero(new), len(grams))
        self.keys = grams[self.at[:-1]]
        self.ids = ids.tolist()
        # (list number, id) in one integer: a probe of a long list is one binary search
        self.flat = (np.cumsum(new) - 1) * max(1, len(sets)) + ids

    def search(self, query: np.ndarray, pct: int = 80) -> list[tuple[int, int]]:
        """(ordinal, overlap) of every set that links with ``query`` (a sorted set)."""
        n, many = len(query), max(1, len(self.sizes))
        if not n or not len(self.keys):
            return []
        pos = np.searchsorted(self.keys, query)
        pos = pos[(pos < len(self.keys)) & (self.keys[np.minimum(pos, len(self.keys) - 1)] == query)]
        t = need(n, pct)
        if len(pos) < t:
            return []
        size = self.at[pos + 1] - self.at[pos]
        pos = pos[np.argsort(size, kind="stable")]
        probed = min(t - 1, int(t / (PROBE_WEIGHT * math.log2(int(size.max())) + 1)))
        short, long = pos[:len(pos) - probed], pos[len(pos) - probed:]
        found = []
        for one, count in self._merge(short.tolist(), t - probed):
            t_pair = overlap_needed(n, int(self.sizes[one]), pct)
            if count + len(long) < t_pair:
                continue
            want = long * many + one
            at = np.searchsorted(self.flat, want)
            count += int((self.flat[np.minimum(at, len(self.flat) - 1)] == want).sum())
            if count >= t_pair:
                found.append((one, count))
        return found

    def _merge(self, lists: list[int], t: int) -> Iterator[tuple[int, int]]:
        """(id, count) of the ids on at least ``t`` of ``lists``, without reading all of them.

        If fewer than t lists begin with the least id, t-1 lists in all are taken off the heap:
        what lies before the id then on top is on no more than these, so they skip to it.
        """
        ids, place = self.ids, {x: int(self.at[x]) for x in lists}
        end = {x: int(self.at[x + 1]) for x in lists}
        heap = [(ids[place[x]], x) for x in lists]
        heapq.heapify(heap)
        while len(heap) >= t:
            top, off = heap[0][0], []
            while heap and heap[0][0] == top:
                off.append(heapq.heappop(heap)[1])
            if len(off) >= t:
                yield top, len(off)
                for x in off:
                    place[x] += 1
            else:
                while heap and len(off) < t - 1:
                    off.append(heapq.heappop(heap)[1])
                if not heap:
                    return
                for x in off:
                    place[x] = bisect_left(ids, heap[0][0], place[x], end[x])
            for x in off:
                if place[x] < end[x]:
                    heapq.heappush(heap, (ids[place[x]], x))


def _frequent(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[pa.RecordBatch]:
    release()
    held, n = [], 0

    def out():
        h, c = np.unique(np.concatenate(held), return_counts=True)
        keep = c >= 2
        return pa.RecordBatch.from_arrays([pa.array(h[keep].view(np.int64)), pa.array(c[keep])], ["h", "c"])

    for b in batches:
        for s in shingle_sets(b.column("text"), k):
            held.append(s)
            n += len(s)
            if n >= 2_000_000:
                yield out()
                held, n = [], 0
    if held:
        yield out()


def frequent_shingles(rows: DataFrame, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Heavy shingles of the corpus with counts, at most ``MAX_FREQUENT`` of them.

    All texts are read.  A task adds up two million shingles at a time and reports those that it
    meets twice among them, so counts are lower bounds; they order the lists and nothing else.
    """
    got = (rows.select("text").mapInArrow(lambda it: _frequent(it, k), "h long, c long")
           .groupBy("h").agg(F.sum("c").alias("c")).where("c >= 6")
           .orderBy(F.desc("c"), "h").limit(MAX_FREQUENT).toPandas())
    h = got["h"].to_numpy(np.int64).view(np.uint64)
    order = np.argsort(h)
    return h[order], got["c"].to_numpy(np.int64)[order]


def short_lists(s: np.ndarray, hot: np.ndarray, counts: np.ndarray, pct: int) -> np.ndarray:
    """The shingles whose lists are merged: the rarest n - need + 1 (ties by value)."""
    p = len(s) - need(len(s), pct) + 1
    if not len(hot):
        return s[:p]
    at = np.minimum(np.searchsorted(hot, s), len(hot) - 1)
    warm = hot[at] == s
    cold = s[~warm]
    if len(cold) >= p:
        return cold[:p]
    w, c = s[warm], counts[at[warm]]
    return np.concatenate([cold, w[np.lexsort((w, c))][:p - len(cold)]])


def _raw(text) -> bytes:
    """UTF-8 of an Arrow string, without decoding it; null counts as empty."""
    return text.as_buffer().to_pybytes() if text.is_valid else b""


def _digest16(parts) -> bytes:
    h = hashlib.blake2b(digest_size=16)
    for x in parts:
        h.update(x)
    return h.digest()


SIGNATURES = "row long, n long, sig binary, seq binary, pre array<long>"


def _signatures(batches, k, pct, hot, counts):
    """Set size, digests of the set of hashes and of the words in order, short lists of each text."""
    release()
    hot, counts = hot.value, counts.value
    for b in batches:
        n, sig, seq, pre, texts = [], [], [], [], b.column("text")
        for i, s in enumerate(shingle_sets(texts, k)):
            n.append(len(s))
            sig.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
            seq.append(_digest16([b" ".join(plain_words(_raw(texts[i])))]) if len(s) else None)
            pre.append(short_lists(s, hot, counts, pct).view(np.int64) if len(s) else None)
        yield pa.RecordBatch.from_arrays(
            [b.column("row"), pa.array(n, pa.int64()), pa.array(sig, pa.binary()), pa.array(seq, pa.binary()),
             pa.array(pre, pa.list_(pa.int64()))], ["row", "n", "sig", "seq", "pre"])


def _canonical(batches, k):
    """A digest of the set of shingles themselves, in order."""
    for b in batches:
        got = [_digest16(x + b"\n" for x in sorted(plain_shingles(plain_words(_raw(t)), k))) for t in b.column("text")]
        yield pa.RecordBatch.from_arrays([b.column("row"), pa.array(got, pa.binary())], ["row", "canon"])


def _classes(sigs: DataFrame, rows: DataFrame, work: Workspace, k: int) -> DataFrame:
    """``row, n, class``: the least row with the same shingle set; without shingles its own.

    Equal digests of hashes propose a class.  Where all its texts have the same words in the
    same order (the usual case) that settles it; other texts are compared by a digest of their
    shingles as words, which tells apart texts whose hashes collide.
    """
    own = sigs.select("row", "n", "sig")
    some = work.save(sigs.where("n > 0").groupBy("sig").agg(
        F.min("row").alias("class"), F.min("seq").alias("lo"), F.max("seq").alias("hi")), "classes")
    mixed = work.save(some.where("lo <> hi").select("sig"), "mixed-classes")
    if mixed.isEmpty():
        told = own.join(some.select("sig", "class"), "sig", "left")
    else:
        mixed = small(mixed, mixed.count())
        unsure = work.save(own.join(mixed, "sig", "left_semi").select("row", "sig"), "unsure")
        texts = rows.join(small(unsure.select("row"), unsure.count()), "row", "left_semi").select("row", "text")
        canon = work.save(texts.mapInArrow(lambda it: _canonical(it, k), "row long, canon binary").join(unsure, "row"), "canon")
        own = own.join(canon.select("row", "canon"), "row", "left").withColumn("canon", F.coalesce("canon", F.unhex(F.lit(""))))
        least = (some.join(mixed, "sig", "left_anti").select("sig", F.unhex(F.lit("")).alias("canon"), "class")
                 .unionByName(canon.groupBy("sig", "canon").agg(F.min("row").alias("class"))))
        told = own.join(least, ["sig", "canon"], "left")
    return work.save(told.select("row", "n", F.coalesce("class", "row").alias("class")), "members")


LINKS = "a long, b long, shared long"


def _search(batches, k, pct):
    """Links of blocks: rows (b, part, lead, row, text), each block's leader b before its classes."""
    release()
    blocks: list[tuple[int, int, list[int]]] = []  # (leader, place of its text, rows of its classes)
    texts: list[bytes] = []
    held, key, leader = 0, None, b""

    def flush():
        a, b, o = [], [], []
        sets = list(shingle_sets(pa.array(texts, pa.large_binary()).view(pa.large_string()), k)) if texts else []
        for lead, at, members in blocks:
            own = None
            for i, _ in TOccurrence(sets[at + 1:at + 1 + len(members)]).search(sets[at], pct):
                # hashes found it, the words decide
                own = plain_shingles(plain_words(texts[at]), k) if own is None else own
                other = plain_shingles(plain_words(texts[at + 1 + i]), k)
                common = len(own & other)
                if 100 * common >= pct * (len(own) + len(other) - common):
                    a.append(members[i])
                    b.append(lead)
                    o.append(common)
        return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (a, b, o)], ["a", "b", "shared"])

    for rb in batches:
        lead, part, row, text = (rb.column(c) for c in ("b", "part", "row", "text"))
        first = rb.column("lead")
        for i in range(rb.num_rows):  # texts are read one at a time from the batch
            raw, one = _raw(text[i]), (lead[i].as_py(), part[i].as_py())
            if first[i].as_py():
                key, leader = one, raw
                blocks.append((one[0], len(texts), []))
            else:
                if one != key:
                    raise RuntimeError("a block without its leader")
                if held >= BLOCK_TEXT:
                    yield flush()
                    blocks, texts, held = [(one[0], 0, [])], [leader], len(leader)
                blocks[-1][2].append(row[i].as_py())
            texts.append(raw)
            held += len(raw)
    yield flush()


def _chance(common, pct: int):
    """Is the count on the short lists enough for sets of n_a and n_b to reach the overlap.

    What two sets share outside both short parts is less than the greater ``need``, so a
    pair that links must occur ``overlap - greatest(need) + 1`` times on the short lists.
    """
    return common >= (F.ceil(F.lit(pct) * (F.col("n_a") + F.col("n_b")) / F.lit(100 + pct) - 1e-9)
                      - F.ceil(F.lit(pct) * F.greatest("n_a", "n_b") / F.lit(100) - 1e-9) + 1)


def _promising(pairs: DataFrame, lists: DataFrame, pct: int) -> DataFrame:
    """Pairs that occur often enough on the short lists."""
    side = [lists.select(F.col("c").alias(x), F.col("n").alias(f"n_{x}"), F.col("hs").alias(f"hs_{x}")) for x in "ab"]
    return (pairs.join(side[0], "a").join(side[1], "b")
            .where(_chance(F.size(F.array_intersect("hs_a", "hs_b")), pct)).select("a", "b"))


def _linked(pairs: DataFrame, rows: DataFrame, work: Workspace, k: int, pct: int) -> DataFrame:
    """Those of ``pairs`` (a visits b) that link, with their overlap.

    A leader's classes are dealt to blocks by hash, so a leader of a third of all classes fills
    many tasks; a text is sent once for each block that it is in.
    """
    most = pairs.groupBy("b").agg(F.ceil(F.count("*") / BLOCK_CLASSES).cast("long").alias("parts"))
    dealt = pairs.join(most, "b").withColumn("part", F.pmod(F.xxhash64("a"), F.col("parts")))
    leaders = most.select("b", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part"))
    asked = work.save(dealt.select("b", "part", F.col("a").alias("row"), F.lit(False).alias("lead")).unionByName(
        leaders.select("b", "part", F.col("b").alias("row"), F.lit(True).alias("lead"))), "visits")
    sent = rows.select("row", "text").join(small(asked, asked.count()), "row")
    sent = sent.select("b", "part", "lead", "row", "text").repartition("b", "part").sortWithinPartitions("b", "part", F.desc("lead"))
    return work.save(sent.mapInArrow(lambda it: _search(it, k, pct), LINKS), "links")


def _fits(pct: int) -> str:
    """May a shingle at places pos_a and pos_b of the two orders be the first common one.

    All that two sets share lies at or behind their first common shingle, so each set must
    have the overlap that the pair needs from its place on.  Also refuses sizes too unlike.
    """
    t = f"ceil({pct} * (n_a + n_b) / {100 + pct} - 1e-9)"
    return f"pos_a <= n_a - {t} and pos_b <= n_b - {t}"


def _placed(live: DataFrame, comp: DataFrame | None) -> DataFrame:
    """Postings with the component of their class, so far."""
    if comp is None:
        return live.withColumn("comp", F.col("c"))
    return (live.join(comp.withColumnRenamed("id", "c"), "c", "left")
            .withColumn("comp", F.coalesce("comp", "c")))


def _may_meet(placed: DataFrame, pct: int) -> DataFrame:
    """Postings whose list may hold the first shingle that a class shares with a linked one of another component.

    Each list tells its least size and farthest reach by bands of length; what no size and place there
    fits (see ``_fits``) is dropped.  A pair that links keeps both postings of its first common list.
    """
    reach = 100 * F.col("n") - (100 + pct) * F.col("pos")
    bands = placed.groupBy("h", "band").agg(F.min("n").alias("least"), F.max(reach).alias("reach"), F.min("comp").alias("lo"), F.max("comp").alias("hi"))
    lists = bands.groupBy("h").agg(F.collect_list(F.struct("band", "least", "reach", "lo", "hi")).alias("there"))
    lists = lists.where("size(there) > 1 or there[0].lo < there[0].hi")
    fits = F.expr(f"exists(there, x -> abs(x.band - band) <= 1 and (x.lo <> comp or x.hi <> comp) and x.reach >= {pct} * n - 1 "
                  f"and pos <= n - ceil({pct} * (n + x.least) / {100 + pct} - 1e-9))")
    return placed.join(lists, "h").where(fits).drop("there")


def _leader_pairs(placed: DataFrame, number: int, take: int, pct: int) -> DataFrame:
    """Each class (a) with the ``take`` leaders (b) of other components that lead most of its lists.

    The leader of a list and band is its first class by id, in later rounds by a hash.
    """
    rank = F.col("c") if number == 0 else F.xxhash64("c", F.lit(number))
    lead = placed.withColumn("rank", rank).groupBy("h", "band").agg(F.min(F.struct("rank", "c", "n", "comp", "pos")).alias("l"))
    lead = lead.select("h", F.explode(F.array("band", F.col("band") - 1)).alias("band"),
                       F.col("l.c").alias("b"), F.col("l.n").alias("n_b"), F.col("l.comp").alias("comp_b"), F.col("l.pos").alias("pos_b"))
    met = (placed.select("h", "band", F.col("c").alias("a"), F.col("n").alias("n_a"), "comp", F.col("pos").alias("pos_a"))
           .join(lead, ["h", "band"]).where("comp <> comp_b").where(_fits(pct)))
    often = met.groupBy("a", "b").agg((-F.count("*")).alias("k"))
    few = often.groupBy("a").agg(F.slice(F.array_sort(F.collect_list(F.struct("k", "b"))), 1, take).alias("f"))
    return few.select("a", F.explode("f.b").alias("b"))


def _index(rows: DataFrame, work: Workspace, k: int, pct: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(members, lists, live): every row's size and class; the shared short lists of each class; their postings
    that may be the first of a linked pair."""
    sc = rows.sparkSession.sparkContext
    hot, counts = (sc.broadcast(x) for x in frequent_shingles(rows, k))
    sigs = work.save(rows.mapInArrow(lambda it: _signatures(it, k, pct, hot, counts), SIGNATURES), "signatures")
    member = _classes(sigs, rows, work, k)
    copies = member.where("row <> class").select("row")
    posts = (sigs.join(small(copies, copies.count()), "row", "left_anti")
             .select(F.posexplode("pre").alias("pos", "h"), F.col("row").alias("c"), "n"))
    shared = posts.groupBy("h").agg(F.count("*").alias("k")).where("k > 1").select("h")  # a class is on a list once
    # bands of length: linked sets lie in the same band or in neighbouring ones
    band = F.floor(F.log(F.col("n").cast("double")) / F.log(F.lit(100.0 / pct)) + 1e-9)
    live = work.save(posts.join(shared, "h").withColumn("band", band), "short-lists")
    work.drop(sigs)
    lists = work.save(_lists(live), "lists")
    near = work.save(_may_meet(_placed(live, None), pct).drop("comp"), "near-lists")
    work.drop(live)
    return member, lists, near


def _lists(live: DataFrame) -> DataFrame:
    """The shared short lists of each class, in the order of all sets: never more than its own short part."""
    own = F.transform(F.array_sort(F.collect_list(F.struct("pos", "h"))), lambda x: x["h"])
    return live.groupBy("c").agg(F.first("n").alias("n"), own.alias("hs"))


def _meetings(placed: DataFrame, lists: DataFrame, pct: int) -> DataFrame:
    """All pairs of classes of different components that can link, each once.

    A pair meets on the first list that both have.  Whatever they share lies at or behind it, and
    they must share enough of their short lists.  A posting carries the lists before its own whole,
    as these tell whether a pair has met, and those from its own on in 16 bits: equal ones can only
    make two texts seem to share more, but for ``lost``, those of one text that fall together.
    """
    at = F.array_position("hs", F.col("h")).cast("int")
    tail = F.slice("hs", at, F.size("hs"))
    wide = placed.join(lists.select("c", "hs"), "c").select(
        "h", "c", "n", "band", "pos", "comp", F.slice("hs", 1, at - 1).alias("head"), (F.size("hs") - at + 1).alias("many"),
        F.array_distinct(F.transform(tail, lambda x: (x.bitwiseAND(F.lit(65535)) - 32768).cast("short"))).alias("tail"))
    wide = wide.withColumn("lost", F.col("many") - F.size("tail"))
    sides = [wide.select("h", *[F.col(x).alias(f"{x}_{side}") for x in ("n", "band", "pos", "comp", "head", "tail", "lost")], F.col("c").alias(side)) for side in "ab"]
    near = F.expr("a > b and comp_a <> comp_b and abs(band_a - band_b) <= 1") & F.expr(_fits(pct))
    common = F.size(F.array_intersect("tail_a", "tail_b")) + F.least("lost_a", "lost_b")
    met = sides[0].join(sides[1], (sides[0]["h"] == sides[1]["h"]) & near & ~F.arrays_overlap("head_a", "head_b") & _chance(common, pct))
    return met.select("a", "b")


def _components(rows: DataFrame, work: Workspace, k: int, pct: int) -> DataFrame:
    """``row, n, class, comp``: least rows of a row's class and of its component."""
    member, lists, live = _index(rows, work, k, pct)
    classes = lists.count()
    links, placed = None, _placed(live, None)
    for number in range(MAX_ROUNDS):
        take = LEADER_TAKES[min(number, len(LEADER_TAKES) - 1)]
        pairs = work.save(_promising(_leader_pairs(placed, number, take, pct), lists, pct), "leader-pairs")
        found = _linked(pairs, rows, work, k, pct)
        links = found if links is None else links.unionByName(found)
        comp = work.save(components(links, src="a", dst="b", work=work), "components")
        placed = work.save(_may_meet(_placed(live, comp), pct), "open-lists")
        if found.count() <= ROUND_YIELD * classes:
            break
    rest = work.save(_meetings(placed, lists, pct), "rest-pairs")
    more = _linked(rest, rows, work, k, pct)
    comp = work.save(components(links.unionByName(more), src="a", dst="b", work=work), "components")
    return (member.join(comp.withColumnRenamed("id", "class"), "class", "left")
            .select("row", "n", "class", F.coalesce("comp", "class").alias("comp")))


def jaccard_classes(docs: DataFrame, k: int = 5, pct: int = 80, work: Workspace | None = None) -> DataFrame:
    """One row per row of ``docs``: ``doc_id, n_shingles, component_id, class_id``.

    ``class_id`` is the least doc_id with the same shingle set, ``component_id`` the least
    one reachable by links.  Null, blank and word-less texts have no shingle, link with
    nothing and stand alone.  ``docs`` needs doc_id and text; other columns, whatever their
    names, are ignored.  Rows that repeat a doc_id and rows without one are texts of their own
    (their sets are not mixed); a component whose rows all lack an id has a null one.  An empty
    table gives an empty result.
    """
    spark = docs.sparkSession
    ship(spark)
    work = work or Workspace(spark, "ngram-join")
    keyed, key, unique = keyed_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), work)
    got = _components(keyed.select(F.col(key).alias("row"), "text"), work, k, pct)
    if unique:
        return got.select(F.col("row").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("comp").alias("component_id"),
                          F.col("class").alias("class_id"))
    got = work.save(got.join(keyed.select(F.col(key).alias("row"), "doc_id"), "row"), "rows")
    for name in ("comp", "class"):
        least = got.groupBy(name).agg(F.min("doc_id").alias(f"{name}_id"))
        got = got.join(least, name)
    return got.select("doc_id", F.col("n").alias("n_shingles"), F.col("comp_id").alias("component_id"), "class_id")


def jaccard_links(docs: DataFrame, k: int = 5, pct: int = 80, work: Workspace | None = None) -> tuple[DataFrame, DataFrame]:
    """(links, members): every link between classes of different sets, and what the classes hold.

    ``links`` has ``a, b, shared`` with a > b, ``members`` ``doc_id, n_shingles, class_id``; copies are
    not expanded into pairs.  doc_id must be unique and not null here (else: ValueError), as a
    link names classes by it.  The links of n near copies are up to n * n / 2 rows: that is the
    result, so use ``jaccard_classes`` where components are enough.
    """
    spark = docs.sparkSession
    ship(spark)
    work = work or Workspace(spark, "ngram-links")
    keyed, key, unique = keyed_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), work)
    if not unique:
        raise ValueError("links need a unique doc_id")
    rows = keyed.select(F.col(key).alias("row"), "text")
    member, lists, live = _index(rows, work, k, pct)
    pairs = work.save(_meetings(_placed(live, None), lists, pct), "pairs")
    return _linked(pairs, rows, work, k, pct), member.select(
        F.col("row").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("class").alias("class_id"))


def drop_near_duplicates(docs: DataFrame, k: int = 5, pct: int = 80, work: Workspace | None = None) -> DataFrame:
    """``docs`` with one row of every component: the one with the least doc_id.

    Exactly one row stays of each, also if rows repeat a doc_id or have none (a null id never
    stays before another).  Null, blank and word-less texts have no links, so all of them stay.
    Columns, whatever their names, and their order are kept; an empty table stays empty.
    """
    spark = docs.sparkSession
    ship(spark)
    work = work or Workspace(spark, "ngram-join")
    keyed, key, unique = keyed_rows(docs, work)
    got = _components(keyed.select(F.col(key).alias("row"), "text"), work, k, pct)
    if unique:
        gone = got.where("row <> comp")
    else:
        got = got.join(keyed.select(F.col(key).alias("row"), F.col("doc_id").cast("long").alias("id")), "row")
        got = work.save(got.select("row", "comp", F.struct(F.col("id").isNull().alias("none"), "id", "row").alias("rank")), "ranked")
        gone = got.join(got.groupBy("comp").agg(F.min("rank").alias("best")), "comp").where("rank.row <> best.row")
    return without(keyed, work.save(gone.select("row"), "near-copies"), key, docs.columns)
