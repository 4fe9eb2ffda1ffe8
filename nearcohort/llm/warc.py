"""WARC archives: writing with revisits, reading by a verified chain of boundaries.

Writing: a record per page through Spark's text writer, whose line separator is the blank
lines that end a record.  Of equal payloads the least page is the response and the others
revisit it.

Reading: Spark's text reader splits the files at every version line, also at those inside
payloads, in parallel.  Each piece is a *candidate* record: its Content-Length says where its
successor must start.  Only candidates that the chain from the start of the file reaches
are records.  Runs of candidates that follow one another in a split of a file are contracted
first, so no task sees more than a split; pointer jumping over what remains takes a logarithm
of the number of splits and breaks.  Records whose payload holds a version line are put together
again from their pieces.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from nearcohort.plans.runtime import Workspace, small

MAGIC = "WARC/1.0\r\n"
END = "\r\n\r\n"
#: Records of one archive file.
FILE_RECORDS = 4_000
#: Payloads below this many bytes are always stored.
REVISIT_BYTES = 100


def _payload() -> Column:
    return F.coalesce(F.col("html"), F.lit(""))


def _digest(c: Column) -> Column:
    return F.sha2(c.cast("binary"), 256)


def write_archives(pages: DataFrame, path: str, work: Workspace, compression: str = "gzip",
                   file_records: int = FILE_RECORDS) -> None:
    """One record per row of ``pages`` (page_id, url, html) into files under ``path``."""
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", _payload().alias("html"))
    facts = work.save(pages.select("page_id", F.octet_length("html").cast("long").alias("n"),
                                   _digest(F.col("html")).alias("digest")), "facts")
    lead = (facts.where(F.col("n") >= REVISIT_BYTES).groupBy("digest")
            .agg(F.min("page_id").alias("lead"), F.count("*").alias("k")).where("k > 1").drop("k"))
    again = work.save(facts.join(lead, "digest").where("page_id <> lead")
                      .select("page_id", "digest", "lead").distinct(), "revisits")
    rec = (pages.withColumn("digest", _digest(F.col("html")))
           .join(small(again, again.count()), ["page_id", "digest"], "left"))
    new = F.col("lead").isNull()

    def line(name: str, value: Column) -> Column:
        return F.coalesce(F.concat(F.lit(name + ": "), value, F.lit("\r\n")), F.lit(""))

    value = F.concat(
        F.lit(MAGIC), line("WARC-Type", F.when(new, "response").otherwise("revisit")),
        line("WARC-Record-ID", F.concat(F.lit("<urn:page:"), F.col("page_id").cast("string"), F.lit(">"))),
        line("WARC-Date", F.lit("1970-01-01T00:00:00Z")),
        line("WARC-Target-URI", F.regexp_replace("url", r"[\r\n]", " ")),
        line("WARC-Payload-Digest", F.concat(F.lit("sha256:"), F.col("digest"))),
        line("WARC-Refers-To", F.concat(F.lit("<urn:page:"), F.col("lead").cast("string"), F.lit(">"))),
        line("WARC-Profile", F.when(~new, "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")),
        line("Content-Type", F.lit("text/html")),
        line("Content-Length", F.when(new, F.octet_length("html")).otherwise(0).cast("string")),
        F.lit("\r\n"), F.when(new, F.col("html")).otherwise(""))
    (rec.select(value.alias("value")).write.option("lineSep", END).option("compression", compression)
     .option("maxRecordsPerFile", file_records).text(path))


def _pieces(spark: SparkSession, path: str) -> DataFrame:
    """What lies between version lines: ``file, block, at, value`` (``at`` orders a block)."""
    return (spark.read.option("lineSep", MAGIC).text(path)
            .select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("block"),
                    F.monotonically_increasing_id().alias("at"), "value"))


def _parsed(df: DataFrame) -> DataFrame:
    """Header fields, claimed body and its digest of each piece."""
    head = F.substring_index("value", END, 1)
    field = lambda name, what: F.regexp_extract(F.col("head"), rf"(?i)(?:^|\r\n){name}: *{what}", 1)
    raw = F.col("value").cast("binary")
    df = df.withColumn("head", F.when(F.contains(F.col("value"), F.lit(END)), head))
    df = df.withColumn("skip", F.octet_length("head") + 4).withColumn(
        "claim", F.expr("try_cast(nullif(regexp_extract(head, '(?i)(?:^|\\\\r\\\\n)Content-Length: *([0-9]+)', 1), '') as long)"))
    body = F.substring(raw, F.col("skip") + 1, F.col("claim").cast("int"))
    return df.select(
        "file", "block", "at", F.octet_length("value").cast("long").alias("size"), "skip", "claim",
        F.expr("try_cast(nullif(" + "regexp_extract(head, '(?i)WARC-Record-ID: *<urn:page:(-?[0-9]+)>', 1), '') as long)").alias("page_id"),
        F.nullif(field("WARC-Type", "([a-z]+)"), F.lit("")).alias("record_type"),
        F.nullif(field("WARC-Target-URI", "([^\r\n]*)"), F.lit("")).alias("url"),
        F.expr("try_cast(nullif(" + "regexp_extract(head, '(?i)WARC-Refers-To: *<urn:page:(-?[0-9]+)>', 1), '') as long)").alias("refers_to"),
        F.sha2(body, 256).alias("digest"))


def _placed(df: DataFrame, work: Workspace, name: str) -> DataFrame:
    """Adds ``nth`` in the block and ``pos``, the offset of the piece's version line."""
    own = W.partitionBy("file", "block").orderBy("at")
    df = df.withColumn("nth", F.row_number().over(own)).withColumn(
        "inner", F.coalesce(F.sum(F.col("size") + len(MAGIC)).over(own.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    df = work.save(df, name)
    sizes = df.groupBy("file", "block").agg(F.sum(F.col("size") + len(MAGIC)).alias("total"))
    before = W.partitionBy("file").orderBy("block").rowsBetween(W.unboundedPreceding, -1)
    start = sizes.select("file", "block", F.coalesce(F.sum("total").over(before), F.lit(0)).alias("start"))
    return (df.join(start, ["file", "block"])
            .withColumn("pos", F.col("start") + F.col("inner") - len(MAGIC)).drop("start", "inner", "at"))


def read_archives(spark: SparkSession, path: str, work: Workspace) -> DataFrame:
    """``page_id, url, record_type, refers_to, payload_bytes, payload_digest`` of every record.

    A revisit gets bytes and digest of the response that it refers to.
    """
    cand = _placed(_parsed(_pieces(spark, path)), work, "pieces").where("pos >= 0")
    cand = work.save(cand.withColumn("succ", F.col("pos") + len(MAGIC) + F.col("skip") + F.col("claim") + len(END)),
                     "candidates")
    order = W.partitionBy("file", "block").orderBy("pos")
    linked = cand.select("file", "block", "pos", "succ", F.lag("succ").over(order).alias("came"),
                         F.lead("pos").over(order).alias("next"))
    jumps = linked.where("succ is not null and (next is null or succ <> next)").select("file", F.col("succ").alias("pos")).distinct()
    cut = linked.join(jumps.withColumn("aim", F.lit(True)), ["file", "pos"], "left")
    cut = cut.withColumn("head", (F.col("came").isNull() | (F.col("came") != F.col("pos")) | F.coalesce("aim", F.lit(False))).cast("int"))
    runs = work.save(cut.withColumn("run", F.sum("head").over(order)), "runs")
    heads = runs.groupBy("file", "block", "run").agg(F.min("pos").alias("pos"), F.max_by("succ", "pos").alias("to"))
    hops = work.save(heads.join(heads.select("file", F.col("pos").alias("to")), ["file", "to"], "left_semi")
                     .select("file", "pos", "to"), "hops")
    reach = work.save(heads.where("pos = 0").select("file", "pos"), "reached")
    n = reach.count()
    while True:
        nxt = work.save(reach.unionByName(reach.join(hops, ["file", "pos"]).select("file", F.col("to").alias("pos")))
                        .distinct(), "reached")
        m = nxt.count()
        reach = nxt
        if m == n:
            break
        n = m
        far = hops.select("file", F.col("pos").alias("to"), F.col("to").alias("far"))
        hops = work.save(hops.join(far, ["file", "to"]).select("file", "pos", F.col("far").alias("to"))
                         .unionByName(hops).distinct(), "hops")
    good = (runs.join(heads.join(reach, ["file", "pos"], "left_semi").select("file", "block", "run"), ["file", "block", "run"], "left_semi")
            .select("file", "pos"))
    record = cand.join(good, ["file", "pos"], "left_semi")
    whole = F.col("skip") + F.col("claim") <= F.col("size")
    broken = work.save(record.where(~whole).drop("digest"), "broken")
    record = record.where(whole)
    if not broken.isEmpty():
        files = broken.select("file").distinct()
        text = _pieces(spark, path).join(files, "file", "left_semi")
        text = _placed(text.withColumn("size", F.octet_length("value").cast("long")), work, "pieces-of-broken")
        parts = broken.select("file", F.col("pos").alias("own"), "succ").join(
            text.select("file", F.col("pos").alias("part"), "value"), "file").where("part >= own and part < succ")
        joined = (parts.groupBy("file", F.col("own").alias("pos"))
                  .agg(F.array_sort(F.collect_list(F.struct("part", "value"))).alias("p"))
                  .select("file", "pos", F.array_join(F.transform("p", lambda x: x["value"]), MAGIC).cast("binary").alias("raw")))
        record = record.unionByName(broken.join(joined, ["file", "pos"]).withColumn(
            "digest", F.sha2(F.substring(F.col("raw"), F.col("skip") + 1, F.col("claim").cast("int")), 256)).drop("raw"))
    record = record.select("page_id", "url", "record_type", "refers_to", F.col("claim").alias("payload_bytes"), "digest")
    base = record.where("record_type = 'response'").select(
        F.col("page_id").alias("refers_to"), F.col("payload_bytes").alias("full"), F.col("digest").alias("full_digest")).distinct()
    later = (record.where("record_type = 'revisit'").join(base, "refers_to")
             .select("page_id", "url", "record_type", "refers_to", F.col("full").alias("payload_bytes"),
                     F.col("full_digest").alias("payload_digest")))
    return (record.where("record_type = 'response'")
            .select("page_id", "url", "record_type", "refers_to", "payload_bytes", F.col("digest").alias("payload_digest"))
            .unionByName(later))


def archive_round_trip(pages: DataFrame, work: Workspace | None = None, **options) -> DataFrame:
    """Write ``pages`` as archives and read them back.

    Null html is an empty payload, a null url or page_id an absent header line.  An empty
    table gives an empty result.  Rows that repeat a page_id are records of their own; page_id should be
    unique among equal payloads for revisits to be told apart.
    """
    work = work or Workspace(pages.sparkSession, "warc")
    where = work.place("archives")
    write_archives(pages, where, work, **options)
    return read_archives(pages.sparkSession, where, work)
