"""Exact dedup: a log-structured merge index of content digests, DataFrame functions only.

* Memtable: rows that a task holds one after the other; memtables are dealt to ``RUNS`` runs.
  A flush merges the memtables of a run into one row per digest, sorted by digest, with the
  smallest and the largest identifier and the number of rows.
* Filter: each run has a blocked Bloom filter, a table of 64-bit words in which a digest sets
  ``FILTER_BITS`` bits.  Filters of runs are united by OR.
* Look-up: a run is read only for the digests that its filter may hold.
* Compaction: a digest that passes the filter of no older run is in one run only and moves to
  the next level as it is; the others are merged.  Of equal digests the smallest (or largest)
  identifier is kept.
* Hits, digests of more than one row, are verified on their bytes: the texts of each are grouped
  by value.  Should different texts share a digest, they are told apart by the text itself.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from nearcohort.llm.rows import keyed_rows, without
from nearcohort.plans.runtime import Workspace, small

#: Rows of a memtable, and runs that the memtables of one flush are dealt to.
MEMTABLE_ROWS = 4096
RUNS = 4
#: Digests per 64-bit word of a filter and bits that each sets: about 0.3 % pass by chance.
WORD_DIGESTS = 4
FILTER_BITS = 4
#: Digests with their rows (about 100 bytes) that may be broadcast.
BROADCAST_DIGESTS = 200_000


def content_digest(text: str = "text") -> Column:
    """SHA-256 of the text in UTF-8; null counts as empty."""
    return F.unhex(F.sha2(F.coalesce(F.col(text), F.lit("")).cast("binary"), 256))


def _mask(digest: str) -> Column:
    """The bits of a digest in its word."""
    h = f"xxhash64({digest}, 1)"
    return F.expr(" | ".join(f"shiftleft(1L, cast(shiftrightunsigned({h}, {6 * i}) & 63 as int))" for i in range(FILTER_BITS)))


def _merged(runs: DataFrame) -> DataFrame:
    """What several runs know of a digest, as one row."""
    return runs.groupBy("digest").agg(F.min("least").alias("least"), F.max("greatest").alias("greatest"), F.sum("n").alias("n"))


class DigestIndex:
    """Sorted runs ``run, digest, least, greatest, n`` with filters, in the shared folder.

    ``least`` is a struct (none, id, row), ``greatest`` (id, row), so a null id comes last in both.
    ``expected`` digests size the filters; more only make them pass more.
    """

    def __init__(self, work: Workspace, expected: int):
        self.work = work
        self.blocks = max(1, expected // (RUNS * WORD_DIGESTS))
        self.count = 0
        self.runs: DataFrame | None = None
        self.filters: DataFrame | None = None

    def _block(self) -> Column:
        return F.pmod(F.xxhash64("digest"), F.lit(self.blocks)).alias("block")

    def _keep(self, runs: DataFrame, name: str) -> DataFrame:
        """Write sorted runs and their filters."""
        runs = self.work.save(runs.sortWithinPartitions("run", "digest"), name)
        words = self.work.save(runs.groupBy("run", self._block()).agg(F.bit_or(_mask("digest")).alias("bits")), f"{name}-filters")
        self.runs = runs if self.runs is None else self.runs.unionByName(runs)
        self.filters = words if self.filters is None else self.filters.unionByName(words)
        return runs

    def flush(self, log: DataFrame) -> DataFrame:
        """Add rows ``memtable, digest, id, row`` as new runs; returns them."""
        run = (F.pmod("memtable", F.lit(RUNS)) + self.count).cast("int").alias("run")
        self.count += RUNS
        return self._keep(log.groupBy(run, "digest").agg(
            F.min(F.struct(F.col("id").isNull().alias("none"), "id", "row")).alias("least"),
            F.max(F.struct("id", "row")).alias("greatest"), F.count("*").alias("n")), "runs")

    def _words(self, bits: DataFrame) -> DataFrame:
        return small(bits, bits.count())

    def look_up(self, digests: DataFrame) -> DataFrame:
        """``digest, least, greatest, n`` of those of ``digests`` that the index holds."""
        asked = digests.select("digest").distinct().withColumns({"block": self._block(), "mask": _mask("digest")})
        maybe = (asked.join(self._words(self.filters), "block").where(F.col("bits").bitwiseAND(F.col("mask")) == F.col("mask"))
                 .select("run", "digest"))
        maybe = self.work.save(maybe, "may-hold")
        return _merged(self.runs.join(small(maybe, maybe.count(), BROADCAST_DIGESTS), ["run", "digest"], "left_semi"))

    def shared(self) -> DataFrame:
        """Digests that, by the filters, an older run may hold as well (a superset of those that one does)."""
        before = W.partitionBy("block").orderBy("run").rowsBetween(W.unboundedPreceding, -1)
        older = self.work.save(self.filters.withColumn("bits", F.bit_or("bits").over(before)).where("bits is not null"), "older-filters")
        return (self.runs.select("run", "digest", self._block(), _mask("digest").alias("mask")).join(self._words(older), ["run", "block"])
                .where(F.col("bits").bitwiseAND(F.col("mask")) == F.col("mask")).select("digest").distinct())

    def compact(self) -> DataFrame:
        """Merge all runs into one: a row per digest."""
        both = self.work.save(self.shared(), "in-several")
        some = small(both, both.count(), BROADCAST_DIGESTS)
        merged = _merged(self.runs.join(some, "digest", "left_semi"))
        alone = self.runs.join(some, "digest", "left_anti").drop("run")
        whole = alone.unionByName(merged).withColumn("run", F.lit(self.count))
        self.count, self.runs, self.filters = self.count + 1, None, None
        return self._keep(whole, "level").drop("run")


def _decided(docs: DataFrame, row: str, keep: str, work: Workspace) -> DataFrame:
    """``row, doc_id, keep_id, group_size, kept, digest``; ``row`` is a unique column of ``docs``."""
    if keep not in ("smallest", "largest"):
        raise ValueError("keep must be 'smallest' or 'largest'")
    number = F.monotonically_increasing_id()
    # a memtable is the next rows of a task; tasks start at another run each
    memtable = F.floor(number.bitwiseAND(F.lit((1 << 33) - 1)) / MEMTABLE_ROWS) + F.shiftright(number, 33)
    log = work.save(docs.select(content_digest().alias("digest"), F.col("doc_id").cast("long").alias("id"),
                                F.col(row).alias("row"), memtable.cast("long").alias("memtable")), "log")
    index = DigestIndex(work, log.count())
    index.flush(log)
    hits = work.save(index.compact().where("n > 1"), "hits")
    hit = small(hits, hits.count(), BROADCAST_DIGESTS)
    # byte verification: texts of hit digests, pre-aggregated before the shuffle
    texts = (docs.select(content_digest().alias("digest"), F.coalesce("text", F.lit("")).alias("text"),
                         F.col("doc_id").cast("long").alias("id"), F.col(row).alias("row"))
             .join(hit.select("digest"), "digest", "left_semi"))
    forked = work.save(texts.groupBy("digest", "text").agg(F.lit(1).alias("one"))
                       .groupBy("digest").agg(F.count("*").alias("k")).where("k > 1").select("digest"), "forked")
    chosen = "least" if keep == "smallest" else "greatest"

    def out(df: DataFrame) -> DataFrame:
        one = F.col(chosen).isNull()
        return df.select("row", F.col("id").alias("doc_id"), F.when(one, F.col("id")).otherwise(F.col(f"{chosen}.id")).alias("keep_id"),
                         F.coalesce("n", F.lit(1).cast("long")).alias("group_size"),
                         (one | (F.col("row") == F.col(f"{chosen}.row"))).alias("kept"), "digest")

    if forked.isEmpty():
        return out(log.join(hit, "digest", "left"))
    odd = texts.join(forked, "digest", "left_semi")
    own = odd.groupBy("digest", "text").agg(
        F.min(F.struct(F.col("id").isNull().alias("none"), "id", "row")).alias("least"),
        F.max(F.struct("id", "row")).alias("greatest"), F.count("*").alias("n"))
    return out(log.join(hit, "digest", "left").join(forked, "digest", "left_anti")).unionByName(
        out(odd.join(own, ["digest", "text"])))


def duplicate_groups(docs: DataFrame, keep: str = "smallest", work: Workspace | None = None) -> DataFrame:
    """``doc_id, keep_id, group_size, kept, text_sha256`` of every row of ``docs``.

    Texts are equal when their bytes are; null and empty texts are equal.  Of a group exactly
    one row stays, that with the smallest (or, ``keep='largest'``, largest) doc_id: a null doc_id
    never stays before another, and of rows that repeat the doc_id one stays.  ``kept`` is never
    null; ``keep_id`` is null for a group without any id.  Columns other than doc_id and text,
    whatever their names, are ignored.  An empty table gives an empty result.
    """
    work = work or Workspace(docs.sparkSession, "exact-dedup")
    rows, key, _ = keyed_rows(docs.select("doc_id", "text"), work)
    return _decided(rows, key, keep, work).select(
        "doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


def drop_duplicates(docs: DataFrame, keep: str = "smallest", work: Workspace | None = None) -> DataFrame:
    """``docs`` with exactly one row of every group of equal texts, by the rule of ``duplicate_groups``.

    Rows are removed one by one, not by their doc_id, so a text that shares its doc_id with a copy
    stays.  Columns, whatever their names, and their order are kept; an empty table stays empty.
    """
    work = work or Workspace(docs.sparkSession, "exact-dedup")
    rows, key, _ = keyed_rows(docs, work)
    gone = work.save(_decided(rows, key, keep, work).where("not kept").select("row"), "dropped")
    return without(rows, gone, key, docs.columns)
