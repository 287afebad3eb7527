"""Streams of events as graphs: windows, duplicates, degrees, and a watched list of nodes."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from nodeflux.functions.params import Params
from nodeflux.operators.graph import build
from nodeflux.operators.push import adaptive_push, sized
from nodeflux.plans.storage import shared_dir
from nodeflux.sources.tables import load


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files with a fixed schema."""
    schema = load(spark, sf_dir, "events").schema
    rows = spark.readStream.schema(schema).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need a time with a zone


def with_edges(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """(ts, a, b): a user and an (event type, hour) node; rows later than the delay are dropped by stateful operators."""
    return events.withWatermark("ts", delay).select(
        "ts", F.concat(F.lit("u:"), F.col("user_id").cast("string")).alias("a"),
        F.concat(F.lit("h:"), F.concat_ws("/", "event_type", F.hour("ts").cast("string"))).alias("b"),
    )


def tumbling(events: DataFrame, size: str = "1 hour", slide: str | None = None, delay: str = "10 minutes") -> DataFrame:
    """(start, event_type, events, users_value): counts and sums of a window; slide makes windows overlap."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return (
        events.withWatermark("ts", delay).groupBy(window.alias("w"), "event_type")
        .agg(F.count("*").alias("events"), F.round(F.sum("value"), 4).alias("total"))
        .select(F.col("w.start").alias("start"), "event_type", "events", "total")
    )


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    """(start, user_id, events): runs of a user's events with gaps below `gap`."""
    return (
        events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events"))
        .select(F.col("w.start").alias("start"), "user_id", "events")
    )


def fresh_edges(events: DataFrame, delay: str = "40 days") -> DataFrame:
    """(a, b): each edge once within the watermark."""
    return with_edges(events, delay).dropDuplicatesWithinWatermark(["a", "b"]).select("a", "b")


def degrees(events: DataFrame) -> DataFrame:
    """(user_id, events): running counts, in update or complete mode."""
    return events.groupBy("user_id").agg(F.count("*").alias("events"))


def collect_stream(stream: DataFrame, mode: str, name: str) -> DataFrame:
    """Run over all that is there and return the result, which is written to the shared folder: the driver holds no row.

    In complete mode each batch holds the whole result and the last one counts; else the batches together. A batch that is
    run again overwrites itself. A stream without batches gives an empty table.
    """
    spark = stream.sparkSession
    base, schema, done = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}", stream.schema, []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/batch={number}")
        done.append(number)

    stream.writeStream.outputMode(mode).foreachBatch(keep).queryName(name).trigger(availableNow=True).start().awaitTermination()
    if not done:
        return spark.createDataFrame([], schema)
    wanted = [max(done)] if mode == "complete" else sorted(set(done))
    return spark.read.schema(schema).parquet(*[f"{base}/batch={number}" for number in wanted])


def watch(events: DataFrame, targets: DataFrame, p: Params, out: Callable[[DataFrame, int], None], theta: float | None = None, store: str | None = None, **options) -> StreamingQuery:
    """For each batch of events: add its edges to the stored ones, rebuild the graph, and estimate targets(key) again.

    The stored edges survive a restart; a batch that is run again adds nothing new. `store` is the folder of edges and
    state, by default one for the application; options go to adaptive_push.
    """
    spark = events.sparkSession
    base = store or f"{shared_dir(spark)}/watch-{spark.sparkContext.applicationId}"

    def refresh(batch: DataFrame, number: int) -> None:
        batch.select("a", "b").distinct().write.mode("overwrite").parquet(f"{base}/edges/batch={number}")
        g = build(spark.read.parquet(f"{base}/edges").select("a", "b"))
        asked = g.nodes.join(sized(targets), "key").select(F.col("qid").cast("int").alias("qid"), F.col("node").alias("t"))
        out(adaptive_push(g, asked, p, theta=theta, **options).df, number)

    return (
        with_edges(events).writeStream.foreachBatch(refresh).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    )


def stream_static(events: DataFrame, customers: DataFrame) -> DataFrame:
    """(c_mktsegment, events): a stream joined with a table."""
    joined = events.join(customers, events["user_id"] == customers["c_custkey"])
    return joined.groupBy("c_mktsegment").agg(F.count("*").alias("events"))


def stream_pairs(left: DataFrame, right: DataFrame, within: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """(user_id, left_id, right_id): two event streams joined on user within an interval of time."""
    one = left.withWatermark("ts", delay).select(F.col("user_id"), F.col("event_id").alias("left_id"), F.col("ts").alias("left_ts"))
    two = right.withWatermark("ts", delay).select(F.col("user_id").alias("other"), F.col("event_id").alias("right_id"), F.col("ts").alias("right_ts"))
    return one.join(two, F.expr(f"user_id = other AND right_ts >= left_ts AND right_ts <= left_ts + INTERVAL {within}")).select("user_id", "left_id", "right_id")
