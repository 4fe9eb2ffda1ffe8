"""Sharding by vector bin packing: bytes, tokens and rows are balanced jointly.

Equal texts form a group and are placed together.  What is packed is bounded whatever the
corpus: small groups are bundled by hash into ``BUNDLES`` items, and a group with more
than 1/64 of a shard's bytes is split into pieces, so no group can unbalance a shard.
The driver packs these items, largest first, each where the dot product of its vector with
the residual capacity is highest.  Slots are gapless and are numbered without gathering a shard.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from nearcohort.plans.runtime import Workspace

BUNDLES = 8192
PIECES_PER_SHARD = 64
#: Rows that one task numbers.
NUMBER_ROWS = 5_000


def pack(vectors: np.ndarray, bins: int) -> np.ndarray:
    """Bin of each row of ``vectors``; capacity is the mean load in every dimension."""
    total = vectors.sum(axis=0)
    scaled = vectors / np.where(total > 0, total / bins, 1.0)
    out = np.zeros(len(vectors), np.int64)
    left = np.ones((bins, vectors.shape[1]))
    for i in np.lexsort((np.arange(len(vectors)), -scaled[:, 0])):
        fit = left @ scaled[i]
        open_ = left[:, 0] >= scaled[i, 0]
        if open_.any():
            b = int(np.argmax(np.where(open_, fit, -np.inf)))
        else:
            b = int(np.argmax(left[:, 0]))
        left[b] -= scaled[i]
        out[i] = b
    return out


def shard(docs: DataFrame, shards: int = 40, work: Workspace | None = None) -> DataFrame:
    """``doc_id, size, text_crc32, n_words, shard, slot`` of every row.

    ``size`` is the text's UTF-8 bytes (null: none) plus 16.  Null and empty texts are one
    group.  Repeated rows are rows like others; an empty table gives an empty result.
    """
    if shards < 1:
        raise ValueError("shards must be positive")
    spark = docs.sparkSession
    work = work or Workspace(spark, "sharding")
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = work.save(docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(text) + 16).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"), F.regexp_count(text, F.lit(r"\S+")).cast("long").alias("n_words"),
        F.unhex(F.md5(text.cast("binary"))).alias("g")), "rows")
    n_rows, total = rows.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    most = max(1, total // (shards * PIECES_PER_SHARD))
    # fewer than shards * PIECES_PER_SHARD groups can be larger than that
    heavy = rows.groupBy("g").agg(F.sum("size").alias("b")).where(F.col("b") > most).orderBy("g").collect()
    base, table = BUNDLES, []
    for r in heavy:
        n = -(-r["b"] // most)
        table.append((bytes(r["g"]), base, n))
        base += n
    heavy = spark.createDataFrame(table, "g binary, base long, n long")
    salt = F.pmod(F.xxhash64("doc_id", F.lit("piece")), F.col("n"))
    placed = rows.join(F.broadcast(heavy), "g", "left").withColumn(
        "item", F.coalesce(F.col("base") + salt, F.pmod(F.xxhash64("g"), F.lit(BUNDLES))))
    items = placed.groupBy("item").agg(
        F.sum("size").alias("b"), F.sum("n_words").alias("w"), F.count("*").alias("r")).orderBy("item").collect()
    bins = pack(np.array([(x["b"], x["w"], x["r"]) for x in items], float).reshape(-1, 3), shards)
    table = [(x["item"], int(b)) for x, b in zip(items, bins, strict=True)]
    out = placed.join(F.broadcast(spark.createDataFrame(table, "item long, shard int")), "item")
    parts = max(1, n_rows // (shards * NUMBER_ROWS))
    out = work.save(out.select("doc_id", "size", "text_crc32", "n_words", "shard",
                               F.pmod(F.xxhash64("doc_id", "text_crc32"), F.lit(parts)).alias("part")), "placed")
    before = W.partitionBy("shard").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    start = out.groupBy("shard", "part").agg(F.count("*").alias("n")).withColumn(
        "before", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    number = F.row_number().over(W.partitionBy("shard", "part").orderBy("doc_id", "text_crc32"))
    return (out.withColumn("number", number).join(start, ["shard", "part"])
            .select("doc_id", "size", "text_crc32", "n_words", "shard",
                    (F.col("before") + F.col("number") - 1).cast("long").alias("slot")))
