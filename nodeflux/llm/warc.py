"""WARC archives: a writer, and a reader that verifies record boundaries as a chain.

Writing uses Spark's text sink with the record terminator as line separator, so archives
can be written to and read from any store that Spark reaches. Of pages with equal payloads
of a minimum size, the one with the largest page_id is a response, others revisit it.

Reading: tasks cut the archive at the terminators and emit, for each piece that starts like
a record, its offset and its successor's offset (header length and Content-Length). What
looks like a record may lie in a payload; so the successor links are jumped over in
doubling steps from each file's start, and only reached records stay.

Defined results: a null payload is empty; a null url gives no target line; a null page_id
stays null; pages with equal page_id and payload are all responses if that id is the largest;
line ends in urls are percent-encoded; an empty table gives no records; other columns play
no part.
"""

from __future__ import annotations

import math
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, discard, shared_dir

END = "\r\n\r\n"
#: Equal payloads of fewer bytes are all written in full.
REVISIT_BYTES = 1000
#: Broadcast the digests that occur twice only up to so many.
BROADCAST_DIGESTS = 100_000
RECORDS_PER_FILE = 1024
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def _line(name: str, value: Column) -> Column:
    return F.coalesce(F.concat(F.lit(f"{name}: "), value.cast("string"), F.lit("\r\n")), F.lit(""))


def _urn(page_id: Column) -> Column:
    """A stable record id; equal page ids get equal ids."""
    h = F.md5(F.coalesce(page_id.cast("string"), F.lit("")))
    cuts = [(1, 8), (9, 4), (13, 4), (17, 4), (21, 12)]
    return F.concat(F.lit("<urn:uuid:"), F.concat_ws("-", *[F.substring(h, a, n) for a, n in cuts]), F.lit(">"))


def planned(pages: DataFrame, revisit_bytes: int = REVISIT_BYTES) -> DataFrame:
    """pages(page_id, url, payload, bytes, digest, first): first is the response's page_id for revisits."""
    base = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("payload")).withColumns(
        {"bytes": F.octet_length("payload").cast("long"), "digest": F.sha1("payload")}
    )
    again = cut(
        base.filter(F.col("bytes") >= revisit_bytes).select("digest", "page_id")
        .groupBy("digest").agg(F.count("*").alias("n"), F.max("page_id").alias("last"))
        .filter("n > 1").drop("n"),
        "warc-digests",
    )
    small = again.count() <= BROADCAST_DIGESTS
    joined = base.join(F.broadcast(again) if small else again, "digest", "left")
    first = F.when((F.col("bytes") >= revisit_bytes) & (F.coalesce("page_id", F.col("last") - 1) < F.col("last")), F.col("last"))
    return joined.withColumn("first", first).drop("last")


def records(plan: DataFrame) -> DataFrame:
    """(value): a WARC record without its final terminator."""
    revisit = F.col("first").isNotNull()
    http = F.concat(
        F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "),
        F.col("bytes").cast("string"), F.lit(END),
    )
    block = F.when(revisit, F.col("http")).otherwise(F.concat("http", "payload"))
    url = F.replace(F.replace(F.col("url"), F.lit("\r"), F.lit("%0D")), F.lit("\n"), F.lit("%0A"))
    head = F.concat(
        F.lit("WARC/1.1\r\nWARC-Type: "), F.when(revisit, "revisit").otherwise("response"), F.lit("\r\n"),
        _line("WARC-Record-ID", _urn(F.col("page_id"))),
        F.lit("WARC-Date: 2024-01-01T00:00:00Z\r\n"),
        _line("WARC-Target-URI", url),
        _line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))),
        F.when(revisit, F.concat(_line("WARC-Profile", F.lit(PROFILE)), _line("WARC-Refers-To", _urn(F.col("first"))),
                                 _line("X-Refers-To-Page", F.col("first")))).otherwise(""),
        _line("X-Page-Id", F.col("page_id")),
        F.lit("Content-Type: application/http;msgtype=response\r\nContent-Length: "),
        F.octet_length("block").cast("string"),
    )
    return plan.withColumn("http", http).withColumn("block", block).select(F.concat(head, F.lit(END), F.col("block")).alias("value"))


def write_warc(pages: DataFrame, path: str, compression: str = "gzip", revisit_bytes: int = REVISIT_BYTES) -> None:
    (
        records(planned(pages, revisit_bytes)).write.option("lineSep", END).option("compression", compression)
        .option("maxRecordsPerFile", RECORDS_PER_FILE).text(path)
    )


def pieces(spark: SparkSession, path: str) -> DataFrame:
    """(file, block, nth, value): what lies between terminators, in the order of the file."""
    rows = spark.read.option("lineSep", END).text(path)
    return rows.select(
        F.col("_metadata.file_path").alias("file"),
        F.col("_metadata.file_block_start").alias("block"),
        F.monotonically_increasing_id().alias("nth"),
        "value",
    )


def candidates(cuts: DataFrame) -> DataFrame:
    """(file, block, nth, off, next) of every piece that looks like a record's header.

    off is the byte offset in the (decompressed) file. A payload that ends with a line end
    leaves that line end in front of the next header. Only headers and lengths are shuffled.
    """
    looks = F.col("value").rlike(r"^(?:\r\n)?WARC/1\.[01]\r\n")
    slim = cuts.select(
        "file", "block", "nth", (F.octet_length("value") + F.lit(len(END))).cast("long").alias("size"),
        F.when(looks, F.expr("substr(value, if(startswith(value, '\r\n'), 3, 1))")).alias("head"),
    )
    before = Window.partitionBy("file").orderBy("block", "nth").rowsBetween(Window.unboundedPreceding, -1)
    length = F.regexp_extract("head", r"(?i)\r\nContent-Length:[ \t]*([0-9]{1,18})[ \t]*(?:\r\n|$)", 1).try_cast("long")
    header = F.octet_length("head") + F.lit(len(END))
    return (
        slim.withColumn("at", F.coalesce(F.sum("size").over(before), F.lit(0)))
        .filter("head is not null")
        .withColumn("off", F.col("at") + F.col("size") - header)
        .select("file", "block", "nth", "off", (F.col("off") + header + length + F.lit(len(END))).alias("next"))
        .filter("next is not null")
    )


def reachable(links: DataFrame) -> DataFrame:
    """(file, off) of the records on the chain from each file's start, by pointer jumping.

    After k rounds the first 2^k records of each chain are marked; each round doubles the
    jumps with one join on (file, off), so no task follows a chain by itself.
    """
    most = links.groupBy("file").count().agg(F.max("count")).first()[0] or 0
    marked = cut(links.filter("off = 0").select("file", "off"), "warc-reach")
    jump = cut(links.select("file", "off", "next"), "warc-jump")
    for _ in range(math.ceil(math.log2(most + 1))):
        ahead = marked.join(jump, ["file", "off"]).select("file", F.col("next").alias("off"))
        more = cut(marked.union(ahead).distinct(), "warc-reach")
        onward = jump.select("file", F.col("off").alias("next"), F.col("next").alias("beyond"))
        twice = cut(jump.join(onward, ["file", "next"]).select("file", "off", F.col("beyond").alias("next")), "warc-jump")
        discard(marked), discard(jump)
        marked, jump = more, twice
    return marked.join(links.select("file", "off"), ["file", "off"], "left_semi")


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """(page_id, record_type, digest, refers_to, payload): records on the verified chain; a revisit has a null payload."""
    cuts = pieces(spark, path)
    links = cut(candidates(cuts), "warc-links")
    good = reachable(links)
    # each piece belongs to the last verified record at or before it; rows of a file stay in
    # one partition, so payloads are shuffled once
    starts = links.join(good, ["file", "off"], "left_semi").select(
        "file", "block", "nth", F.lit(None).cast("string").alias("value"), F.col("off").alias("rec")
    )
    rows = cuts.withColumn("rec", F.lit(None).cast("long")).unionByName(starts)
    upto = Window.partitionBy("file").orderBy("block", "nth", F.col("rec").isNull())
    owned = rows.withColumn("rec", F.last("rec", ignorenulls=True).over(upto)).filter("value is not null and rec is not null")
    whole = owned.groupBy("file", "rec").agg(F.sort_array(F.collect_list(F.struct("block", "nth", "value"))).alias("parts"))
    texts = F.transform("parts", lambda p: p["value"])
    def field(name: str, kind: str = "string") -> Column:
        return F.regexp_extract("head", rf"(?i)\r\n{name}:[ \t]*(.*?)[ \t]*(?:\r\n|$)", 1).try_cast(kind)

    parsed = (
        whole.select(F.get(texts, 0).alias("head"), F.array_join(F.expr("slice(transform(parts, p -> p.value), 2, size(parts))"), END).alias("block"))
        .withColumn("length", field("Content-Length", "long"))
        # a line end that closes the payload was read as part of the terminator
        .withColumn("block", F.when(F.octet_length("block") + 2 == F.col("length"), F.concat("block", F.lit("\r\n"))).otherwise(F.col("block")))
        # what was left of the last terminator of a file is no part of the record
        .withColumn("block", F.when(F.octet_length("block") > F.col("length"), F.expr("cast(substr(cast(block AS binary), 1, cast(length AS int)) AS string)")).otherwise(F.col("block")))
    )
    body = F.expr("substr(block, locate('\r\n\r\n', block) + 4)")
    kind = field("WARC-Type")
    return parsed.select(
        field("X-Page-Id", "long").alias("page_id"),
        kind.alias("record_type"),
        F.regexp_extract("head", r"(?i)\r\nWARC-Payload-Digest:[ \t]*sha1:([0-9a-z]+)", 1).alias("digest"),
        field("X-Refers-To-Page", "long").alias("refers_to"),
        F.when(kind == "response", body).alias("payload"),
    )


def read_pages(spark: SparkSession, path: str) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to), revisits resolved through their response."""
    got = cut(
        read_warc(spark, path).select(
            "page_id", "record_type", "digest", "refers_to",
            F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha1("payload").alias("payload_digest"),
        ),
        "warc-read",
    )
    asked = got.filter("record_type = 'revisit'").select(F.col("refers_to").alias("page_id"), "digest").distinct()
    sources = (
        got.filter("record_type = 'response'").join(asked, ["page_id", "digest"], "left_semi")
        .groupBy(F.col("page_id").alias("refers_to"), "digest")
        .agg(F.max("payload_bytes").alias("full_bytes"), F.max("payload_digest").alias("full_digest"))
    )
    sources = cut(sources, "warc-sources")
    if sources.count() <= BROADCAST_DIGESTS:
        sources = F.broadcast(sources)
    return got.join(sources, ["refers_to", "digest"], "left").select(
        "page_id",
        F.coalesce("payload_bytes", "full_bytes").alias("payload_bytes"),
        F.coalesce("payload_digest", "full_digest").alias("payload_digest"),
        "record_type",
        "refers_to",
    )


def op5_warc(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    path = f"{shared_dir(spark)}/warc-{uuid.uuid4().hex}"
    write_warc(pages, path)
    return read_pages(spark, path)


OP5_SQL = r"""
WITH p AS (
  SELECT page_id, coalesce(html, '') AS payload, strlen(coalesce(html, '')) AS payload_bytes FROM pages
), q AS (
  SELECT *, max(page_id) OVER (PARTITION BY payload) AS last FROM p
)
SELECT page_id, payload_bytes, sha1(payload) AS payload_digest,
       CASE WHEN payload_bytes >= 1000 AND page_id < last THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN payload_bytes >= 1000 AND page_id < last THEN last END AS refers_to
FROM q
"""
