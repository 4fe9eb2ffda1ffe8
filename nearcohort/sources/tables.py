"""Reading the given tables, text formats and JSON; writing results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A Parquet table; timestamps without zone become TIMESTAMP (watermarks need it)."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.withColumns({c: F.col(c).cast("timestamp") for c, t in df.dtypes if t == "timestamp_ntz"})


def read_edge_list(spark: SparkSession, path: str) -> DataFrame:
    """Tab-separated vertex pairs; lines that do not parse are dropped."""
    df = (spark.read.schema("src long, dst long, bad string").option("sep", "\t").option("comment", "#")
          .option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "bad").csv(path))
    return df.where("src is not null and dst is not null and bad is null").select("src", "dst")


def read_checkins(spark: SparkSession, path: str) -> DataFrame:
    """Tab-separated user, ISO time, latitude, longitude, place: ``user, ts, seq, x, y, kw``."""
    df = spark.read.schema("user long, ts timestamp, y double, x double, place string").option("sep", "\t").csv(path)
    return df.where("user is not null and ts is not null").select(
        "user", "ts", F.xxhash64("place").alias("seq"), "x", "y", F.lit(None).cast("string").alias("kw"))


def event_attributes(events: DataFrame) -> DataFrame:
    """Events with ``k``, the number that their JSON properties carry (null if malformed)."""
    return events.withColumn("k", F.get_json_object("props", "$.k").cast("double"))


def write_groups(groups: DataFrame, path: str, graph: str, fmt: str = "parquet") -> None:
    """Groups partitioned by graph; parquet, json or csv."""
    if fmt not in ("parquet", "json", "csv"):
        raise ValueError(f"unknown format {fmt}")
    w = groups.withColumn("graph", F.lit(graph)).write.mode("overwrite").partitionBy("graph").format(fmt)
    (w.option("header", True) if fmt == "csv" else w).save(path)


def write_rounds(rounds: DataFrame, path: str, graph: str, method: str) -> None:
    """The log of tested radii, partitioned by graph and method, appended to that of other runs."""
    (rounds.withColumns({"graph": F.lit(graph), "method": F.lit(method)}).write.mode("append").partitionBy("graph", "method").parquet(path))


def write_bucketed(edges: DataFrame, name: str, buckets: int = 16) -> None:
    """A table bucketed by src: repeated joins on it need no exchange of the edges."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "dst").saveAsTable(name)
