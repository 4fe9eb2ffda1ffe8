"""Check-ins as a stream: latest locations, co-activity edges, windows and standing queries."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from nearcohort.model import Graph
from nearcohort.operators.graph import canonical_edges
from nearcohort.plans.runtime import ship

LATE = "10 minutes"
LATEST = "user long, ts timestamp, seq long, x double, y double, kw string"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Events as a stream of ``user, ts, seq, x, y, kw`` (time with zone, for watermarks)."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.select(F.col("user_id").alias("user"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("seq"),
                      F.col("value").alias("x"), F.get_json_object("props", "$.k").cast("double").alias("y"), F.col("event_type").alias("kw"))


def _keep_latest(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    best = state.get if state.exists else None
    for pdf in batches:
        for r in pdf.itertuples(index=False):
            mine = (int(r.ts.value // 1000), int(r.seq), float(r.x), float(r.y), r.kw)
            if best is None or mine[:2] > tuple(best)[:2]:
                best = mine
    state.update(best)
    ts, seq, x, y, kw = best
    yield pd.DataFrame([(key[0], pd.Timestamp(ts, unit="us"), seq, x, y, kw)], columns=["user", "ts", "seq", "x", "y", "kw"])


def latest_locations(events: DataFrame) -> DataFrame:
    """The last check-in of each user that has news in a trigger; out-of-order rows never win."""
    ship(events.sparkSession)
    return events.groupBy("user").applyInPandasWithState(
        _keep_latest, LATEST, "ts long, seq long, x double, y double, kw string", "update", GroupStateTimeout.NoTimeout)


def coactivity(events: DataFrame, width: str = "1 minute", late: str = LATE) -> DataFrame:
    """(window, users) of each closed tumbling window; ``pair_up`` turns them into edges."""
    return (events.withWatermark("ts", late).groupBy(F.window("ts", width))
            .agg(F.array_sort(F.collect_set("user")).alias("users")))


def pair_up(windows: DataFrame) -> DataFrame:
    """Canonical edges between the users of each window."""
    one = windows.select(F.explode("users").alias("src"), "users")
    return canonical_edges(one.select("src", F.explode("users").alias("dst")).where("src < dst"))


def activity(events: DataFrame, width: str = "10 minutes", slide: str | None = "5 minutes", late: str = LATE) -> DataFrame:
    """(start, kw, n) per sliding (or, without slide, tumbling) window."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return (events.withWatermark("ts", late).groupBy(w.alias("w"), "kw").agg(F.count("*").alias("n"))
            .select(F.col("w.start").alias("start"), "kw", "n"))


def sessions(events: DataFrame, gap: str = "15 minutes", late: str = LATE) -> DataFrame:
    """(user, start, end, n) of each session."""
    return (events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user").agg(F.count("*").alias("n"))
            .select("user", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n"))


def met_within(events: DataFrame, seconds: int = 30, late: str = LATE) -> DataFrame:
    """Stream-stream join: pairs of users active within ``seconds`` of each other.

    Equal or neighbouring buckets give the join a key, the interval lets old state go.
    """
    k = F.floor(F.unix_micros("ts") / F.lit(seconds * 1_000_000))
    a = events.withWatermark("ts", late).select(F.col("user").alias("src"), F.col("ts").alias("ts_a"), k.alias("k_a"))
    b = events.withWatermark("ts", late).select(F.col("user").alias("dst"), F.col("ts").alias("ts_b"),
                                                F.explode(F.array(k - 1, k, k + 1)).alias("k_b"))
    near = F.expr(f"k_a = k_b and src < dst and ts_b >= ts_a - interval {seconds} seconds and ts_b <= ts_a + interval {seconds} seconds")
    return a.join(b, near).select("src", "dst", "ts_a", "ts_b")


def run_to_end(stream: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Drive a stream over all that is there into a memory table (tests and small sinks)."""
    q = (stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint)
         .trigger(availableNow=True).start())
    q.awaitTermination()
    return stream.sparkSession.table(name)


class StandingQueries:
    """Registered queries that are answered anew after each batch of check-ins.

    ``upsert`` is a ``foreachBatch`` function: it merges the batch into the latest
    locations, takes the edges anew and reports the queries whose groups changed.
    """

    def __init__(self, edges: DataFrame, queries: DataFrame, on_change: Callable[[int, DataFrame], None], **options):
        self.edges, self.queries, self.on_change, self.options = edges, queries, on_change, options
        self.latest: DataFrame | None = None
        self.before: DataFrame | None = None

    def upsert(self, batch: DataFrame, epoch: int) -> None:
        from nearcohort.plans.runtime import Workspace
        from nearcohort.plans.solve import solve

        work = Workspace(batch.sparkSession, "standing")
        rows = batch.select("user", "ts", "seq", "x", "y", "kw")
        rows = rows if self.latest is None else rows.unionByName(self.latest)
        last = F.max_by(F.struct("ts", "seq", "x", "y", "kw"), F.struct("ts", "seq"))
        old, self.latest = self.latest, work.save(rows.groupBy("user").agg(last.alias("r")).select("user", "r.*"), "latest")
        work.drop(old)
        graph = Graph(self.latest.select(F.col("user").alias("id"), "kw", "x", "y"), self.edges, "standing")
        now = solve(graph, self.queries, work=work, **self.options).groups
        if self.before is None:
            changed = now
        else:
            keys = now.exceptAll(self.before).select("qid").unionByName(self.before.exceptAll(now).select("qid")).distinct()
            changed = now.join(F.broadcast(keys), "qid", "left_semi")
        self.before = now
        self.on_change(epoch, changed)
