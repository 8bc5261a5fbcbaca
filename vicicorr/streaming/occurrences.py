"""Event occurrences as a stream: windows, late rows, and the test for each closed window."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.balls import balls, cut, set_ball
from ..operators.kendall import kendall_test
from ..sources.graphs import EventGraph, shared_dir


def occurrence_stream(spark: SparkSession, sf_dir: str, late: str = "1 hour") -> DataFrame:
    """File stream of the events table: (node, event, ts) with a watermark."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")
    return raw.select(F.col("user_id").alias("node"), F.col("event_type").alias("event"), F.col("ts").cast("timestamp").alias("ts")).withWatermark("ts", late)


def windowed(df: DataFrame, kind: str = "tumbling") -> DataFrame:
    """Occurrences by window: counts of events and of their nodes (approximate in a stream)."""
    w = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "1 day", "12 hours"), "session": F.session_window("ts", "30 minutes")}[kind]
    return df.groupBy(w.alias("w"), "event").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event", "n")


def run_to_table(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there now and return what it wrote."""
    spark = df.sparkSession
    name = "stream_" + uuid.uuid4().hex
    at = f"{shared_dir(spark)}/{name}"
    if mode == "append":
        q = df.writeStream.format("parquet").option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start(f"{at}/out")
    else:  # rows as each micro-batch changes them
        q = df.writeStream.foreachBatch(lambda b, i: b.write.mode("append").parquet(f"{at}/out")).outputMode(mode).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{at}/out")


def window_nodes(stream: DataFrame, a: str, b: str, length: str = "1 day") -> DataFrame:
    """(start, node, has_a, has_b): a row comes out once, when the watermark has closed its window."""
    some = stream.where(F.col("event").isin(a, b)).groupBy(F.window("ts", length).alias("w"), "node")
    return some.agg(F.max(F.col("event") == a).alias("has_a"), F.max(F.col("event") == b).alias("has_b")).select(F.col("w.start").alias("start"), "node", "has_a", "has_b")


def test_nodes(days: DataFrame, g: EventGraph, h: int) -> DataFrame:
    """days(start, node, has_a, has_b) -> the test of each window on the nodes that see one of its events: (start, n, s, z), all windows in one plan."""
    days = cut(days)
    roots = set_ball(g.adj, days.select("node"), h).select(F.col("node").alias("root"))
    reach = cut(balls(g.adj, roots, h).select("root", "node"))
    sizes = reach.groupBy("root").agg(F.count(F.lit(1)).alias("size"))
    seen = reach.join(days, "node").groupBy("start", "root").agg(F.count_if("has_a").alias("cnt_a"), F.count_if("has_b").alias("cnt_b"))
    return kendall_test(seen.join(sizes, "root"), "start").select("start", "n", "s", "z")


def test_windows(stream: DataFrame, g: EventGraph, a: str, b: str, h: int, length: str = "1 day") -> DataFrame:
    """The test once for each closed window, the graph static: (start, n, s, z).

    State is a row a (window, node); a window still open when the stream ends gives none."""
    spark = stream.sparkSession
    at = f"{shared_dir(spark)}/vrc_{uuid.uuid4().hex}"

    def each(batch: DataFrame, number: int) -> None:
        test_nodes(batch, g, h).write.mode("append").parquet(f"{at}/out")

    window_nodes(stream, a, b, length).writeStream.foreachBatch(each).outputMode("append").option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("start timestamp, n long, s long, z double").parquet(f"{at}/out")


def first_seen(stream: DataFrame) -> DataFrame:
    """Each (node, event) once within the watermark."""
    return stream.dropDuplicatesWithinWatermark(["node", "event"])


def running_totals(stream: DataFrame, after: str = "2 days") -> DataFrame:
    """(event, node, n, last_ts): occurrences so far and the last, of each event and node that a micro-batch touches.

    A key's state goes when nothing has come for ``after`` in event time."""
    keep_ms = int(pd.Timedelta(after).total_seconds() * 1000)

    def update(key, frames, state):
        if state.hasTimedOut:
            state.remove()
            return
        n, last = state.get if state.exists else (0, 0)
        for f in frames:
            n += len(f)
            last = max(last, int(f["us"].max()))
        state.update((n, last))
        state.setTimeoutTimestamp(max(last // 1000, state.getCurrentWatermarkMs()) + keep_ms)
        yield pd.DataFrame({"event": [key[0]], "node": [key[1]], "n": [n], "last_us": [last]})

    rows = stream.withColumn("us", F.unix_micros("ts"))
    return rows.groupBy("event", "node").applyInPandasWithState(update, "event string, node long, n long, last_us long", "n long, last_us long", "update", "EventTimeTimeout")
