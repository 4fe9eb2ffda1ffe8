"""The social graphs that the given tables hold."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nearcohort.kernels.meetings import meeting_pairs
from nearcohort.kernels.near_pairs import near_pairs
from nearcohort.model import Graph
from nearcohort.operators.graph import canonical_edges, latest_checkin
from nearcohort.plans.runtime import ship
from nearcohort.sources.tables import event_attributes, table

#: All vectors are compared with all, in pairs of blocks: so many blocks at least, so many vectors in one at most.
LEAST_BLOCKS = 16
BLOCK_VECTORS = 8192
#: Members of one block of ``_meetings``: a pair of blocks takes a byte for each pair of members.
BLOCK_MEMBERS = 8192


def _pairs(df: DataFrame, key: list[str], who: str) -> DataFrame:
    """Distinct pairs of ``who`` that share a key."""
    d = df.select(*key, F.col(who).alias("src")).distinct()
    return canonical_edges(d.join(d.withColumnRenamed("src", "dst"), key).where("src < dst"))


def _of(df: DataFrame, who: str, ids: DataFrame) -> DataFrame:
    """Rows of ``df`` whose ``who`` is among ``ids`` (id)."""
    return df.join(ids.select(F.col("id").alias(who)), who, "left_semi")


def _meetings(df: DataFrame, key: str, who: str, members: int = BLOCK_MEMBERS) -> DataFrame:
    """The same where few members meet very often (``key`` and ``who`` are whole numbers): one task for each
    pair of blocks of members, and no pair is shuffled."""
    d = df.select(F.col(key).cast("long").alias("key"), F.col(who).cast("long").alias("id")).where("key IS NOT NULL AND id IS NOT NULL")
    blocks = max(4, -(-d.agg(F.approx_count_distinct("id")).first()[0] // members))
    put = d.withColumn("block", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("long")).distinct()
    put = put.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))))
    put = put.select("key", "id", "block", F.least("block", "other").alias("left"), F.greatest("block", "other").alias("right"))
    ship(df.sparkSession)

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return meeting_pairs(batches)

    return put.repartition(blocks * (blocks + 1) // 2, "left", "right").groupBy("left", "right").applyInArrow(pairs, "src long, dst long")


def buyers(spark: SparkSession, sf_dir: str) -> Graph:
    """Customers who ordered one part in one calendar month."""
    orders, items = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    bought = (orders.join(items.select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey"), "o_orderkey")
              .select("o_custkey", "l_partkey", F.date_trunc("month", "o_orderdate").alias("month")))
    last = latest_checkin(orders.select(F.col("o_custkey").alias("user"), F.col("o_orderdate").alias("ts"),
                                        F.col("o_orderkey").alias("seq"), "o_totalprice"))
    v = (table(spark, sf_dir, "customer").join(last.withColumnRenamed("user", "c_custkey"), "c_custkey")
         .select(F.col("c_custkey").alias("id"), F.col("c_mktsegment").alias("kw"), (F.col("c_acctbal") / 100).alias("x"),
                 (F.col("o_totalprice") / 5000).alias("y")))
    spent = orders.groupBy(F.col("o_custkey").alias("id")).agg(F.round(F.sum("o_totalprice"), 2).alias("influence"))
    among = lambda ids: _pairs(_of(bought, "o_custkey", ids), ["l_partkey", "month"], "o_custkey")
    return Graph(v.join(spent, "id", "left"), _pairs(bought, ["l_partkey", "month"], "o_custkey"), "buyers", among)


def baskets(spark: SparkSession, sf_dir: str, least: int = 6, keyword: str = "p_type") -> Graph:
    """Parts that share an order of at least ``least`` distinct parts."""
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").distinct()
    if least > 1:
        big = items.groupBy("l_orderkey").agg(F.count("*").alias("n")).where(F.col("n") >= least).select("l_orderkey")
        items = items.join(big, "l_orderkey", "left_semi")
    v = table(spark, sf_dir, "part").select(
        F.col("p_partkey").alias("id"), F.col(keyword).alias("kw"), (F.col("p_retailprice") - 900).alias("x"),
        (2.0 * F.col("p_size")).alias("y"),
        F.array_distinct(F.concat(F.array("p_type", "p_brand"), F.split("p_name", " "))).alias("attrs"))
    if keyword != "p_type":
        v = v.withColumn("attrs", F.array("kw"))
    among = lambda ids: _pairs(_of(items, "l_partkey", ids), ["l_orderkey"], "l_partkey")
    return Graph(v.drop("attrs"), _pairs(items, ["l_orderkey"], "l_partkey"), "baskets" if least > 1 else "baskets_all", among)


def baskets_attrs(spark: SparkSession, sf_dir: str) -> Graph:
    """``baskets`` with attribute sets: type and brand."""
    g = baskets(spark, sf_dir)
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.array("p_type", "p_brand").alias("attrs"))
    return g.with_(vertices=g.vertices.join(part, "id"))


def active(spark: SparkSession, sf_dir: str, minutes: int = 1) -> Graph:
    """Users with events in one minute (or ten)."""
    ev = event_attributes(table(spark, sf_dir, "events"))
    bucket = F.floor(F.unix_micros("ts") / F.lit(minutes * 60_000_000)).alias("bucket")
    last = latest_checkin(ev.select(F.col("user_id").alias("user"), "ts", F.col("event_id").alias("seq"), "event_type", "value", "k"))
    v = last.select(F.col("user").alias("id"), F.col("event_type").alias("kw"), F.col("value").alias("x"), F.col("k").alias("y"))
    met = ev.select(bucket, "user_id")
    among = lambda ids: _meetings(_of(met, "user_id", ids), "bucket", "user_id")
    return Graph(v, _meetings(met, "bucket", "user_id"), "active" if minutes == 1 else f"active{minutes}", among)


def vectors(spark: SparkSession, sf_dir: str, least: float = 0.35) -> Graph:
    """Embeddings of at least that cosine: all pairs at every size, one task per pair of blocks."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("id"), F.col("label").cast("string").alias("kw"), "embedding")
    v = e.select("id", "kw", F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"))
    whole = e.where("id IS NOT NULL AND size(embedding) > 0 AND NOT exists(embedding, x -> x IS NULL)").select("id", "embedding")
    blocks = max(LEAST_BLOCKS, -(-whole.count() // BLOCK_VECTORS))
    put = whole.withColumn("block", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("long"))
    put = put.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))))
    put = put.select("id", "block", F.size("embedding").alias("dim"), F.least("block", "other").alias("left"),
                     F.greatest("block", "other").alias("right"), "embedding")
    ship(spark)

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return near_pairs(batches, bound)

    bound = least - 1e-6  # what rounds to 6 decimals up to ``least``
    found = put.groupBy("dim", "left", "right").applyInArrow(pairs, "src long, dst long, cos double")
    return Graph(v, canonical_edges(found.where(F.round("cos", 6) >= least)), "vectors")


def suppliers(spark: SparkSession, sf_dir: str, common: int = 3) -> Graph:
    """Suppliers with at least ``common`` orders in common."""
    items = table(spark, sf_dir, "lineitem")
    d = items.select("l_orderkey", F.col("l_suppkey").alias("src")).distinct()
    e = (d.join(d.withColumnRenamed("src", "dst"), "l_orderkey").where("src < dst").groupBy("src", "dst")
         .agg(F.count("*").alias("n")).where(F.col("n") >= common))
    region = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    mean = items.groupBy("l_suppkey").agg(F.round(100 * F.avg("l_discount"), 6).alias("y"))
    v = (table(spark, sf_dir, "supplier").join(F.broadcast(region), F.col("s_nationkey") == F.col("n_nationkey"))
         .join(mean, F.col("s_suppkey") == F.col("l_suppkey"))
         .select(F.col("s_suppkey").alias("id"), F.col("r_name").alias("kw"), (F.col("s_acctbal") / 100).alias("x"), "y"))
    return Graph(v, canonical_edges(e), "suppliers")


def articles(spark: SparkSession, sf_dir: str, least: int = 40) -> Graph:
    """Documents that share a trimmed line of at least ``least`` characters."""
    docs = table(spark, sf_dir, "documents")
    line = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line"))
    v = docs.select(F.col("doc_id").alias("id"), F.col("lang").alias("kw"), F.round(F.log("n_chars"), 6).alias("x"),
                    F.pmod("doc_id", F.lit(100)).cast("double").alias("y"))
    good = table(spark, sf_dir, "labels").groupBy(F.col("doc_id").alias("id")).agg(F.avg("quality").alias("influence"))
    v = v.join(good, "id", "left").fillna({"influence": 0.0})
    return Graph(v, _pairs(line.where(F.length("line") >= least), ["line"], "doc_id"), "articles")


GRAPHS = {"buyers": buyers, "baskets": baskets, "active": active, "vectors": vectors, "suppliers": suppliers, "articles": articles,
          "baskets_all": lambda s, d: baskets(s, d, 1), "active10": lambda s, d: active(s, d, 10),
          "baskets_brand": lambda s, d: baskets(s, d, 6, "p_brand"), "baskets_attrs": baskets_attrs}


def load(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """A graph by its name."""
    if name not in GRAPHS:
        raise ValueError(f"unknown graph {name}")
    return GRAPHS[name](spark, sf_dir)
