"""Substring dedup: content-defined chunks by a gear rolling hash.

A gear hash over the last 32 bytes decides the cuts, so an insertion moves only the cuts
near it and later chunks are found again.  Chunks are compared by a 128-bit digest.  A chunk
that occurs more than once is repeated; neighbouring repeated chunks form a run.  Runs only
propose: each is grown to both sides as far as its bytes equal those beside another occurrence
of its outer chunk (the first one; for the first itself, the last).  A grown span is reported
if it has at least ``min_bytes``.  A repeated passage none of whose chunks lies whole inside it
in two places proposes nothing and stays unfound.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from nearcohort.llm.rows import fresh, keyed_rows
from nearcohort.llm.textblocks import mix, release
from nearcohort.plans.runtime import Workspace, ship

#: A cut needs this many leading bits of the rolling hash to be zero: 32 bytes on average.
CUT_BITS = 5
MIN_CHUNK, MAX_CHUNK = 16, 256
MIN_SPAN_BYTES = 100
#: Bytes compared beside a run at first, and bytes of a text whose questions go with one copy of it.
FIRST_BESIDE = 64
ASKS_BYTES = 1_000_000

_GEAR = mix(np.arange(1, 257, dtype=np.uint64)).astype(np.uint32)
CHUNKS = "doc_id long, start long, size int, d1 long, d2 long"


def gear(data: np.ndarray) -> np.ndarray:
    """Rolling hash after each byte: sum of gear[byte] << age over the last 32 bytes."""
    h = _GEAR[data]
    step = 1
    while step < 32:
        h[step:] = h[step:] + (h[:-step] << np.uint32(step))
        step *= 2
    return h


def cuts(data: np.ndarray) -> list[int]:
    """Ends of the chunks of a text (the last one is its length)."""
    n, out, last = len(data), [], 0
    marks = np.flatnonzero(gear(data) >> np.uint32(32 - CUT_BITS) == 0) + 1 if n else ()
    for m in (*marks, n):
        while m - last > MAX_CHUNK:
            last += MAX_CHUNK
            out.append(int(last))
        if m - last >= MIN_CHUNK or (m == n and m > last):
            last = int(m)
            out.append(last)
    return out


def _chunks(batches):
    release()
    for b in batches:
        docs, start, size, d1, d2 = [], [], [], [], []

        def out(docs=docs, start=start, size=size, d1=d1, d2=d2):
            got = pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(start, pa.int64()), pa.array(size, pa.int32()),
                                              pa.array(d1, pa.int64()), pa.array(d2, pa.int64())],
                                             ["doc_id", "start", "size", "d1", "d2"])
            for x in (docs, start, size, d1, d2):
                x.clear()
            return got

        for i, t in zip(b.column("doc_id"), b.column("text"), strict=True):
            raw = (t.as_py() or "").encode("utf-8", "replace")
            at, doc = 0, i.as_py()
            for e in cuts(np.frombuffer(raw, np.uint8)):
                v = xxhash.xxh3_128_intdigest(raw[at:e])
                docs.append(doc)
                start.append(at)
                size.append(e - at)
                d1.append((v >> 64) - (1 << 63))
                d2.append((v & ((1 << 64) - 1)) - (1 << 63))
                at = e
            if len(docs) > 100_000:
                yield out()
        yield out()


def chunk_table(docs: DataFrame) -> DataFrame:
    """Every chunk of every whole text: ``doc_id, start, size, d1, d2`` (bytes of UTF-8)."""
    ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_chunks, CHUNKS)


def _beside(batches, most):
    """The bytes beside each asked place, read away from it: ``doc_id, at, side, bytes``."""
    for b in batches:
        docs, at, side, beside = [], [], [], []

        def out(docs=docs, at=at, side=side, beside=beside):
            got = pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(at, pa.int64()), pa.array(side, pa.int32()),
                                              pa.array(beside, pa.binary())], ["doc_id", "at", "side", "bytes"])
            for x in (docs, at, side, beside):
                x.clear()
            return got

        for i, t, asks in zip(b.column("doc_id"), b.column("text"), b.column("asks"), strict=True):
            raw, doc = (t.as_py() or "").encode("utf-8", "replace"), i.as_py()
            for q in asks.as_py():
                p = q["at"]
                docs.append(doc)
                at.append(p)
                side.append(q["side"])
                beside.append(raw[p:p + most] if q["side"] else raw[max(0, p - most):p][::-1])
            if len(docs) >= 50_000:
                yield out()
        yield out()


def _common(batches, most):
    """Length of the common start of two byte strings: ``run, side, grown, more``; more if that is all of them."""
    for b in batches:
        grown, more = [], []
        for x, y in zip(b.column("mine").to_pylist(), b.column("theirs").to_pylist(), strict=True):
            n = min(len(x), len(y))
            u, v = np.frombuffer(x, np.uint8, n), np.frombuffer(y, np.uint8, n)
            apart = np.flatnonzero(u != v)
            grown.append(int(apart[0]) if len(apart) else n)
            more.append(grown[-1] == most)
        yield pa.RecordBatch.from_arrays([b.column("run"), b.column("side"), pa.array(grown, pa.int32()), pa.array(more, pa.bool_())],
                                         ["run", "side", "grown", "more"])


def _grown(docs: DataFrame, asks: DataFrame, work: Workspace) -> DataFrame:
    """``run, side, grown``: equal bytes beside ``own_doc, own_at`` and ``other_doc, other_at``.

    Some bytes are compared first; the few sides that are equal throughout go on with more.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where("doc_id IS NOT NULL")
    most, done = FIRST_BESIDE, None
    while True:
        ends = [asks.select(F.col(f"{x}_doc").alias("doc_id"), F.col(f"{x}_at").alias("at"), "side") for x in ("own", "other")]
        per_doc = (ends[0].union(ends[1]).distinct().groupBy("doc_id", F.expr(f"at div {ASKS_BYTES}").alias("part"))
                   .agg(F.collect_list(F.struct("at", "side")).alias("asks")).drop("part"))
        beside = work.save(texts.join(per_doc, "doc_id").select("doc_id", "text", "asks").mapInArrow(
            lambda it, n=most: _beside(it, n), "doc_id long, at long, side int, bytes binary"), "beside")
        as_of = lambda x, name: beside.select(F.col("doc_id").alias(f"{x}_doc"), F.col("at").alias(f"{x}_at"), "side", F.col("bytes").alias(name))  # noqa: B023, E731
        both = (asks.join(as_of("own", "mine"), ["own_doc", "own_at", "side"]).join(as_of("other", "theirs"), ["other_doc", "other_at", "side"])
                .select("run", "side", "mine", "theirs"))
        got = work.save(both.mapInArrow(lambda it, n=most: _common(it, n), "run string, side int, grown int, more boolean"), "grown")
        work.drop(beside)
        part = got.where("NOT more").select("run", "side", "grown")
        done = part if done is None else done.unionByName(part)
        if not got.where("more").take(1):
            return done
        asks = work.save(asks.join(got.where("more").select("run", "side"), ["run", "side"], "left_semi"), "asks")
        most *= 32


def repeated_spans(docs: DataFrame, min_bytes: int = MIN_SPAN_BYTES, work: Workspace | None = None) -> DataFrame:
    """``doc_id, start, size, n_chunks, n_later, first_doc``: maximal repeated spans.

    ``n_later`` counts the chunks whose first occurrence (least doc_id, then offset) is
    elsewhere, so a span with 0 is the one to keep; ``first_doc`` is the least document
    that holds one of the span's chunks first.  Null and empty texts have no chunk.
    Copies of a whole document are one span from 0 to its end.  Rows that repeat a doc_id or have
    none are texts of their own, in the order of their numbers.  Columns other than doc_id and
    text, whatever their names, are ignored; an empty table gives an empty result.
    """
    work = work or Workspace(docs.sparkSession, "passages")
    rows, key, unique = keyed_rows(docs.select("doc_id", "text"), work)
    spans = _spans(rows.select(F.col(key).alias("doc_id"), "text"), min_bytes, work)
    if unique:
        return spans
    own = rows.select(F.col(key).alias("row"), F.col("doc_id").cast("long").alias("id"))
    for name in ("doc_id", "first_doc"):
        spans = spans.join(own.withColumnsRenamed({"row": name, "id": f"{name}_id"}), name).drop(name).withColumnRenamed(f"{name}_id", name)
    return spans.select("doc_id", "start", "size", "n_chunks", "n_later", "first_doc")


def _spans(docs: DataFrame, min_bytes: int, work: Workspace) -> DataFrame:
    """``repeated_spans`` of rows with a unique ``doc_id``."""
    chunks = work.save(chunk_table(docs), "chunks")
    place = F.struct("doc_id", "start")
    groups = (chunks.groupBy("d1", "d2").agg(F.count("*").alias("n"), F.min(place).alias("f"), F.max(place).alias("l"))
              .where("n > 1"))
    later = (F.col("f.doc_id") != F.col("doc_id")) | (F.col("f.start") != F.col("start"))
    hit = (chunks.join(groups, ["d1", "d2"])
           .select("doc_id", "start", "size", F.col("f.doc_id").alias("first_doc"), later.cast("int").alias("later"),
                   F.when(later, F.col("f")).otherwise(F.col("l")).alias("other")))
    by_doc = W.partitionBy("doc_id").orderBy("start")
    gap = (F.col("start") != F.coalesce(F.lag(F.col("start") + F.col("size")).over(by_doc), F.lit(-1))).cast("int")
    runs = work.save(
        hit.withColumn("gap", gap).withColumn("span", F.sum("gap").over(by_doc))
        .groupBy("doc_id", "span").agg(
            F.min("start").alias("start"), F.max(F.col("start") + F.col("size")).alias("end"), F.count("*").alias("n_chunks"),
            F.sum("later").cast("long").alias("n_later"), F.min("first_doc").alias("first_doc"),
            F.min_by("other", "start").alias("at_left"),
            F.max_by(F.struct(F.col("other.doc_id").alias("doc_id"), (F.col("other.start") + F.col("size")).alias("start")), "start").alias("at_right"))
        .withColumn("run", F.concat_ws(" ", "doc_id", "start")), "runs")
    work.drop(chunks)
    asks = runs.where("doc_id IS NOT NULL").select("run", F.col("doc_id").alias("own_doc"), F.explode(F.array(
        F.struct(F.lit(0).alias("side"), F.col("start").alias("own_at"), F.col("at_left").alias("other")),
        F.struct(F.lit(1).alias("side"), F.col("end").alias("own_at"), F.col("at_right").alias("other")))).alias("q")).select(
            "run", "q.side", "own_doc", "q.own_at", F.col("q.other.doc_id").alias("other_doc"), F.col("q.other.start").alias("other_at"))
    asks = asks.where("own_at > 0 AND other_at > 0 OR side = 1").where("other_doc IS NOT NULL")
    grown = _grown(docs, asks, work).groupBy("run").agg(F.max(F.when(F.col("side") == 0, F.col("grown"))).alias("before"),
                                                        F.max(F.when(F.col("side") == 1, F.col("grown"))).alias("after"))
    wide = (runs.join(grown, "run", "left")
            .withColumn("start", F.col("start") - F.coalesce("before", F.lit(0))).withColumn("end", F.col("end") + F.coalesce("after", F.lit(0))))
    # grown runs that meet are one span
    so_far = F.max("end").over(W.partitionBy("doc_id").orderBy("start", "end").rowsBetween(W.unboundedPreceding, -1))
    apart = (F.col("start") > F.coalesce(so_far, F.lit(-1))).cast("int")
    spans = (wide.withColumn("apart", apart)
             .withColumn("span", F.sum("apart").over(W.partitionBy("doc_id").orderBy("start", "end").rowsBetween(W.unboundedPreceding, 0)))
             .groupBy("doc_id", "span").agg(
                 F.min("start").alias("start"), (F.max("end") - F.min("start")).alias("size"), F.sum("n_chunks").alias("n_chunks"),
                 F.sum("n_later").alias("n_later"), F.min("first_doc").alias("first_doc")))
    return spans.where(F.col("size") >= min_bytes).drop("span")


def _cut_out(batches, columns, cuts):
    release()
    for b in batches:
        texts = []
        for t, spans in zip(b.column("text"), b.column(cuts), strict=True):
            text, cut = t.as_py(), spans.as_py()
            if text is not None and cut:
                raw, at, keep = text.encode("utf-8", "replace"), 0, []
                for a, n in sorted((c["start"], c["size"]) for c in cut):
                    keep.append(raw[at:a])
                    at = max(at, a + n)
                # cuts may split a character: its loose bytes go with the passage
                text = b"".join([*keep, raw[at:]]).decode("utf-8", "ignore")
            texts.append(text)
        yield pa.RecordBatch.from_arrays(
            [pa.array(texts, pa.string()) if c == "text" else b.column(c) for c in columns], list(columns))


def remove_repeats(docs: DataFrame, min_bytes: int = MIN_SPAN_BYTES, work: Workspace | None = None) -> DataFrame:
    """``docs`` with every repeated span removed from all places but its first.

    Row by row, by the rule of ``repeated_spans``: all rows stay, null texts too.
    """
    work = work or Workspace(docs.sparkSession, "passages")
    rows, key, _ = keyed_rows(docs, work)
    spans = _spans(rows.select(F.col(key).alias("doc_id"), "text"), min_bytes, work).where("n_later > 0")
    cuts = fresh("cuts", rows.columns)
    per_doc = spans.groupBy(F.col("doc_id").alias(key)).agg(F.collect_list(F.struct("start", "size")).alias(cuts))
    wide = rows.join(per_doc, key, "left")
    columns = docs.columns
    kinds = ", ".join(f"`{c}` {t}" for c, t in docs.dtypes)
    return wide.select(*[f"`{c}`" for c in (*columns, cuts)]).mapInArrow(lambda it: _cut_out(it, columns, cuts), kinds)
