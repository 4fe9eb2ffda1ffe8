"""Benchmark decontamination: size-partitioned MinHash containment search.

A test item is *contained* in a document when at least ``pct`` percent of its distinct
word shingles occur there.  Containment in a long text is a tiny Jaccard similarity, so one
sketch length can't serve all texts: documents are partitioned by the power of two above
their number of shingles, and each partition sketches with ``4 * 2**p`` one-permutation
bins, which keeps 88-94 % of a document's shingles as bin minima whatever its length.  The
items, which are the query set, are sketched for each partition; an item with a common bin
minimum is a candidate and is verified on the words themselves.

An item's sketches need no table each: a shingle is a bin minimum in every partition whose bins
are told apart by more leading bits than it shares with the next smaller shingle of its item.

A candidate is missed only if none of the shared shingles survives: below 0.12**(0.8*q) for
an item of q shingles.  Items with fewer than ``FEW`` shingles are looked up by all their
shingles instead, which is exact, and so are items of fewer than ``k`` words, whose one shingle
is their whole sequence: it is looked for at every place of every document.

The documents are read once per block of items and never shuffled.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearcohort.llm.rows import keyed_rows, without
from nearcohort.llm.textblocks import blocks, hold, plain_shingles, plain_words, sets_of, shingle_sets, word_grams, words
from nearcohort.plans.runtime import Workspace, ship

#: Items with fewer shingles skip the sketches: all their shingles are looked up.
FEW = 8
#: Item text broadcast at once; a larger item table is searched in several passes.  A worker
#: holds about five times as much.
BLOCK_ITEM_BYTES = 16 << 20

RESULT = "doc_id long, item_id long, n_item long, n_shared long, containment double"
_U = np.uint64


def partition_bits(n: int) -> int:
    """log2 of the number of bins for a document of ``n`` shingles."""
    return max(1, int(n - 1).bit_length()) + 2


def sketch(s: np.ndarray, bits: int) -> np.ndarray:
    """Mask of the minima of the non-empty bins; ``s`` is sorted, bins are its leading bits."""
    b = s >> _U(64 - bits)
    first = np.ones(len(s), bool)
    first[1:] = b[1:] != b[:-1]
    return first


def shared_bits(s: np.ndarray) -> np.ndarray:
    """Leading bits that each of the sorted ``s`` shares with the one before it (the first: none)."""
    x = s[1:] ^ s[:-1]
    n = np.zeros(len(s), np.uint8)
    for step in (32, 16, 8, 4, 2, 1):
        none = x < _U(1 << (64 - step))
        n[1:][none] += step
        x = np.where(none, x << _U(step), x)
    return n


def word_shingles(text: str | None, k: int) -> set[bytes]:
    """The shingles of ``textblocks.shingle_sets`` as words, for the exact check."""
    return plain_shingles(plain_words((text or "").encode("utf-8", "replace")), k)


class ItemIndex:
    """Shingles of a block of items with the sketches that each belongs to."""

    def __init__(self, items: list[tuple[int, str]], k: int, pct: int):
        self.k, self.pct, self.items = k, pct, items
        self.sets = list(shingle_sets(pa.array([t for _, t in items], pa.string()), k))
        self.size = np.array([len(s) for s in self.sets], np.int64)
        #: words of each item that has fewer than k: its one shingle is that long
        self.short = np.zeros(len(items), np.int64)
        for i in np.flatnonzero(self.size == 1):
            n = len(plain_words(items[i][1].encode("utf-8", "replace")))
            self.short[i] = n if n < k else 0
        self.lengths = np.unique(self.short[self.short > 0]).tolist()
        v = np.concatenate([np.zeros(0, _U), *self.sets])
        who = np.repeat(np.arange(len(items), dtype=np.int32), self.size)
        least = np.concatenate([np.zeros(0, np.uint8), *(shared_bits(s) if len(s) >= FEW else np.zeros(len(s), np.uint8) for s in self.sets)])
        order = np.argsort(v, kind="stable")
        self.v, self.who, self.least = v[order], who[order], least[order]

    def candidates(self, s: np.ndarray) -> np.ndarray:
        """Items that share a bin minimum with the document ``s`` (or, if few, a shingle)."""
        lo, hi = np.searchsorted(self.v, s, "left"), np.searchsorted(self.v, s, "right")
        at = np.flatnonzero(hi > lo)
        if not len(at):
            return at
        bits = partition_bits(len(s))
        minimum = sketch(s, bits)[at]
        place = np.concatenate([np.arange(lo[i], hi[i]) for i in at])
        who = self.who[place]
        few = self.size[who] < FEW
        own = np.repeat(minimum, (hi - lo)[at]) & (self.least[place] < bits)
        return np.unique(who[(few | own) & (self.short[who] == 0)])

    def search(self, s: np.ndarray, h: np.ndarray, raw):
        """(item number, shared) of the items in a document of shingles ``s`` and words ``h``; ``raw()`` gives it."""
        if not len(s) or not self.items:
            return
        own: dict[int, set[bytes]] = {}

        def exact(i: int, k: int):
            if k not in own:
                own[k] = plain_shingles(plain_words(raw()), k)
            mine = plain_shingles(plain_words(self.items[i][1].encode("utf-8", "replace")), k)
            return len(mine & own[k]), len(mine)

        for i in self.candidates(s):
            x = self.sets[i]
            at = np.minimum(np.searchsorted(s, x), len(s) - 1)
            if 100 * int((s[at] == x).sum()) >= self.pct * len(x):
                shared, n = exact(i, self.k)
                if 100 * shared >= self.pct * n:
                    yield int(i), shared, n
        for n in self.lengths:
            grams = np.unique(word_grams(h, n, self.k))
            lo, hi = np.searchsorted(self.v, grams, "left"), np.searchsorted(self.v, grams, "right")
            for j in np.flatnonzero(hi > lo):
                for i in self.who[lo[j]:hi[j]]:
                    if self.short[i] == n and exact(i, n)[0]:
                        yield int(i), 1, 1


def _scan(batches, items, key, k, pct):
    index = hold(("items", key), lambda: ItemIndex(items.value, k, pct))
    for b in batches:
        found = []
        ids, texts = b.column("doc_id"), b.column("text")
        for row, off, data in blocks(texts):
            _, _, h, first = words(off, data)
            for r, s in enumerate(sets_of(h, first, k)):
                if len(s):
                    raw = lambda r=r: data[off[r]:off[r + 1]].tobytes()  # noqa: B023, E731
                    for i, shared, n in index.search(s, h[first[r]:first[r + 1]], raw):
                        found.append((ids[row + r].as_py(), index.items[i][0], n, shared, shared / n))
        cols = list(zip(*found, strict=True)) if found else [[]] * 5
        yield pa.RecordBatch.from_arrays(
            [pa.array(c, t) for c, t in zip(cols, [pa.int64()] * 4 + [pa.float64()], strict=True)],
            ["doc_id", "item_id", "n_item", "n_shared", "containment"])


def contaminated(docs: DataFrame, items: DataFrame, k: int = 5, pct: int = 80) -> DataFrame:
    """Every (document, item) with ``containment >= pct`` percent.

    ``docs`` has doc_id and text, ``items`` item_id and text; other columns, whatever their names,
    are ignored.  Null, blank and word-less texts contain nothing and are contained in nothing.
    An item of fewer than ``k`` words has its whole sequence as its one shingle and is found
    wherever a text has these words one after the other.  Repeated rows, repeated ids and null
    ids give rows of their own; empty tables give an empty result.
    """
    spark = docs.sparkSession
    ship(spark)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    items = items.select(F.col("item_id").cast("long").alias("item_id"), "text").where("text is not null")
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = 1 + total // BLOCK_ITEM_BYTES
    found = spark.createDataFrame([], RESULT)
    for i in range(n):
        block = [tuple(r) for r in items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == i).collect()]
        sent, key = spark.sparkContext.broadcast(block), uuid.uuid4().hex
        found = found.unionByName(docs.mapInArrow(lambda it, sent=sent, key=key: _scan(it, sent, key, k, pct), RESULT))
    return found


def drop_contaminated(docs: DataFrame, items: DataFrame, k: int = 5, pct: int = 80,
                      work: Workspace | None = None) -> DataFrame:
    """``docs`` without the rows that contain an item, by the rule of ``contaminated``.

    Rows are removed one by one, not by their doc_id; null and word-less texts stay.  Columns,
    whatever their names, and their order are kept; an empty table stays empty.
    """
    work = work or Workspace(docs.sparkSession, "decontaminate")
    rows, key, _ = keyed_rows(docs, work)
    bad = contaminated(rows.select(F.col(key).alias("doc_id"), "text"), items, k, pct)
    return without(rows, work.save(bad.select("doc_id").distinct(), "contaminated"), key, docs.columns)
