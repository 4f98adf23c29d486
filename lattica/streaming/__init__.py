"""Edges from an event stream: users of consecutive minutes' activity, with late data dropped by watermark."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def read_events(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(path)


def activity(events: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(window_start, user_id, n): events of each user per tumbling or sliding window; works on batches and streams."""
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy(F.window("ts", width, slide) if slide else F.window("ts", width), "user_id").agg(F.count("*").alias("n")).select(F.col("window.start").alias("window_start"), "user_id", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(session_start, session_end, user_id, n)."""
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    return rows.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("session_start"), F.col("session_window.end").alias("session_end"), "user_id", "n")


def distinct_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def window_edges(active: DataFrame) -> DataFrame:
    """(a, b, n): each user beside the next larger one active in the same window, so a window of k users gives k - 1 pairs, not k squared."""
    from pyspark.sql import Window as W

    rows = active.withColumn("b", F.lead("user_id").over(W.partitionBy("window_start").orderBy("user_id")))
    return rows.where("b is not null").groupBy(F.col("user_id").alias("a"), "b").agg(F.count("*").alias("n"))


def last_seen(events: DataFrame) -> DataFrame:
    """(user_id, last_ts, n): state kept per user over all micro-batches."""
    import pandas as pd

    def step(key, frames, state):
        n, last = state.get if state.exists else (0, None)
        for pdf in frames:
            n += len(pdf)
            top = pdf.ts.max()
            last = top.value if last is None else max(last, top.value)
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "last_ts": [pd.Timestamp(last)], "n": [n]})

    return events.select("user_id", "ts").groupBy("user_id").applyInPandasWithState(step, "user_id long, last_ts timestamp, n long", "n long, last long", "update", "NoTimeout")


def keep_clustered(events: DataFrame, path: str, checkpoint: str, options=None, trigger=None):
    """A query that adds each batch's edges to the graph at path/edges and clusters it again from the last clustering at path/clusters."""
    from ..operators.engine import refined
    from ..operators.graph import modularity_graph, symmetrize
    from ..operators.options import Options
    from ..sources import settle

    def merge(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        edges = symmetrize(window_edges(activity(batch)).select("a", "b"), weighted=True)
        old = f"{path}/edges/{number - 1}"
        if number:
            edges = spark.read.parquet(old).unionByName(edges).groupBy("src", "dst").agg(F.sum("w").alias("w"))
        edges.write.mode("overwrite").parquet(f"{path}/edges/{number}")
        g = modularity_graph(spark.read.parquet(f"{path}/edges/{number}"))
        start = None
        if number:
            last = spark.read.parquet(f"{path}/clusters/{number - 1}")
            start = settle(g.vertices.select("id").join(last, "id", "left").select("id", F.coalesce("cid", "id").alias("cid")), "start")
        refined(g, options or Options(uncoarsen=False), start).clusters.write.mode("overwrite").parquet(f"{path}/clusters/{number}")

    writer = events.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint)
    return (writer.trigger(**trigger) if trigger else writer).start()
