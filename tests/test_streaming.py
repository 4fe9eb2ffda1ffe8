import pytest
from pyspark.sql import functions as F

from nearcohort.model import make_queries
from nearcohort.operators.graph import latest_checkin
from nearcohort.plans.solve import solve
from nearcohort.sources.graphs import load
from nearcohort.sources.tables import event_attributes, table
from nearcohort.streaming import checkins as C

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def parts(spark, tmp_path_factory):
    """The events in three files, some rows late by file order."""
    path = str(tmp_path_factory.mktemp("events"))
    ev = spark.read.parquet(f"{SF}/events.parquet")
    ev.withColumn("p", F.col("event_id") % 3).repartition(1).write.partitionBy("p").parquet(path + "/in")
    return path + "/in"


def test_latest_location_equals_batch(spark, parts, tmp_path):
    got = C.run_to_end(C.latest_locations(C.read_events(spark, parts)), "latest_out", "update", str(tmp_path / "a"))
    got = latest_checkin(got).select("user", "seq")
    ev = event_attributes(table(spark, SF, "events")).select(F.col("user_id").alias("user"), "ts", F.col("event_id").alias("seq"))
    assert set(map(tuple, got.collect())) == set(map(tuple, latest_checkin(ev).select("user", "seq").collect()))


def test_coactivity_equals_batch(spark, parts, tmp_path):
    flat = C.read_events(spark, parts, 100)
    win = C.run_to_end(C.coactivity(flat, late="40 days"), "win_out", "complete", str(tmp_path / "b"))
    assert set(map(tuple, C.pair_up(win).collect())) == set(map(tuple, load(spark, SF, "active").edges.collect()))


def test_windows_and_sessions_equal_batch(spark, parts, tmp_path):
    flat = C.read_events(spark, parts, 100)
    e = event_attributes(table(spark, SF, "events")).select(
        F.col("user_id").alias("user"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_type").alias("kw"))
    slide = C.run_to_end(C.activity(flat, late="40 days"), "slide_out", "complete", str(tmp_path / "c"))
    assert sorted(map(tuple, slide.collect())) == sorted(map(tuple, C.activity(e, late="40 days").collect()))
    # sessions anew, without session windows: a gap of fifteen minutes begins another
    times = {}
    for r in e.select("user", F.unix_micros("ts").alias("t")).collect():
        times.setdefault(r["user"], []).append(r["t"])
    want, gap = [], 15 * 60 * 1_000_000
    for user, ts in times.items():
        run = []
        for t in [*sorted(ts), None]:
            if run and (t is None or t - run[-1] >= gap):
                want.append((user, run[0], run[-1] + gap, len(run)))
                run = []
            run.append(t)
    sess = C.run_to_end(C.sessions(flat, late="40 days"), "sess_out", "complete", str(tmp_path / "d"))
    assert sorted(map(tuple, sess.select("user", F.unix_micros("start"), F.unix_micros("end"), "n").collect())) == sorted(want)


def test_rows_later_than_the_watermark_are_dropped(spark, tmp_path):
    """Minutes 0-59 first, then minute 0 again with a row too late and minute 58 with one just in time."""
    def put(n, rows):
        df = spark.createDataFrame([(i, f"2024-01-01 {t}", u, "click", 1.0, '{"k": 1}') for i, t, u in rows], "event_id long, t string, user_id long, event_type string, value double, props string")
        df.select("event_id", F.col("t").cast("timestamp_ntz").alias("ts"), "user_id", "event_type", "value", "props").coalesce(1).write.parquet(str(tmp_path / "in" / f"{n}"))

    def drive():
        stream = C.activity(C.read_events(spark, str(tmp_path / "in"), 100), "1 minute", None, late="10 minutes")
        q = (stream.writeStream.format("parquet").option("path", str(tmp_path / "out")).outputMode("append")
             .option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start())
        q.awaitTermination()

    put("p=1", [(i, f"00:{i:02d}:00", 1) for i in range(60)])
    drive()
    put("p=2", [(100, "00:00:30", 2), (101, "00:58:30", 2), (102, "02:00:00", 2)])
    drive()
    got = sorted((r["m"], r["n"]) for r in spark.read.parquet(str(tmp_path / "out")).select(F.minute("start").alias("m"), "n").collect())
    # minute 0 was closed with one row long before; minute 58 was still open
    assert got == [(m, 2 if m == 58 else 1) for m in range(60)]


def test_stream_join(spark, parts, tmp_path):
    flat = C.read_events(spark, parts, 100)
    got = C.run_to_end(C.met_within(flat, late="40 days"), "met_out", "append", str(tmp_path / "e"))
    e = spark.read.parquet(f"{SF}/events.parquet").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    two = e.select(F.col("user_id").alias("src"), "t").crossJoin(e.select(F.col("user_id").alias("dst"), F.col("t").alias("u")))
    want = two.where("src < dst and abs(t - u) <= 30000000").select("src", "dst").distinct()
    assert set(map(tuple, got.select("src", "dst").collect())) == set(map(tuple, want.collect()))


def test_standing_queries_report_changes(spark, parts):
    seen, answers = [], []
    edges = load(spark, SF, "active").edges
    ask = make_queries(spark, [(1, 50.0, 50.0, [], 0, 2), (2, 50.0, 50.0, ["nothing"], 1, 2)])

    def note(epoch, df):
        seen.append(epoch)
        answers.append(sorted((r["qid"], r["d"], r["member"]) for r in df.collect()))

    sq = C.StandingQueries(edges, ask, note)
    q = C.read_events(spark, parts).writeStream.foreachBatch(sq.upsert).trigger(availableNow=True).start()
    q.awaitTermination()
    assert len(seen) == 3 and sq.latest.count() == spark.read.parquet(f"{SF}/events.parquet").select("user_id").distinct().count()
    # what was reported last is the answer of a search over all events at once
    want = sorted((r["qid"], r["d"], r["member"]) for r in solve(load(spark, SF, "active"), ask).groups.collect())
    assert want and [a for a in answers if a][-1] == want and all(x[0] == 1 for a in answers for x in a)
    # a batch that moves nobody changes nothing
    sq.upsert(sq.latest, 9)
    assert answers[-1] == []
