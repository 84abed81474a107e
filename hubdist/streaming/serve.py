"""Streams around a static index: answering requests, and graph snapshots by event window."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.query import packed_distance, query_labels


def answer_stream(requests: DataFrame, packed: DataFrame) -> DataFrame:
    """Requests (qid, s, t) with distances: two stream-static joins on packed labels, a row per request; null if an end is unknown or there is no path."""
    a = packed.select(F.col("v").alias("s"), F.col("hubs").alias("ha"), F.col("dists").alias("da"))
    b = packed.select(F.col("v").alias("t"), F.col("hubs").alias("hb"), F.col("dists").alias("db"))
    return requests.join(a, "s", "left").join(b, "t", "left").select("qid", "s", "t", packed_distance(F.col("ha"), F.col("da"), F.col("hb"), F.col("db")).alias("dist"))


def answer_batches(requests: DataFrame, labels: DataFrame, out: str, checkpoint: str):
    """Each micro-batch answered by the batch query and appended to ``out``."""
    return requests.writeStream.foreachBatch(lambda df, _: query_labels(labels, df).write.mode("append").parquet(out)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def events_stream(spark: SparkSession, path: str, schema) -> DataFrame:
    """Events from files, with event time and each event once."""
    ev = spark.readStream.schema(schema).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
    return ev.withWatermark("ts", "10 minutes").dropDuplicatesWithinWatermark(["event_id"])


def window_activity(events: DataFrame, size: str = "1 day", slide: str | None = None) -> DataFrame:
    """Events and users per window: what tells when a snapshot is due."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.groupBy(w.alias("w")).agg(F.count("*").alias("events"), F.approx_count_distinct("user_id").alias("users")).select(F.col("w.start").alias("start"), "events", "users")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events")).select("user_id", F.col("w.start").alias("start"), "events")


def late_events(events: DataFrame, on_time: DataFrame, size: str = "1 day") -> DataFrame:
    """(start, late): events of a batch table per window that a stream's closed windows ``on_time`` (start, events) lack."""
    every = events.groupBy(F.window("ts", size).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")
    return every.join(on_time.select("start", "events"), "start").select("start", (F.col("n") - F.col("events")).alias("late"))


def handoffs(events: DataFrame, gap_us: int = 300_000_000) -> DataFrame:
    """(src, dst, us) of a stream of events (key, user_id, us): per key the user before and the next one within the gap; state is one event a key.

    Events of a micro-batch are ordered inside it; one that is older than the state starts no handoff.
    """
    import pandas as pd

    def step(key, parts, state):
        last = state.get if state.exists else None
        rows = pd.concat(list(parts)).sort_values(["us", "user_id"])
        out = []
        for user, us in zip(rows["user_id"].tolist(), rows["us"].tolist(), strict=True):
            if last is not None and us < last[1]:
                continue
            if last is not None and us - last[1] <= gap_us and user != last[0]:
                out.append((last[0], user, us))
            last = (user, us)
        if last is not None:
            state.update(last)
        yield pd.DataFrame(out, columns=["src", "dst", "us"])

    return events.groupBy("key").applyInPandasWithState(step, "src long, dst long, us long", "user_id long, us long", "append", "NoTimeout")


def swap_index(build, root: str, spark: SparkSession) -> str:
    """Build a new index under ``root`` by ``build(path)`` and point the manifest at it; readers of the old one are not disturbed."""
    import uuid

    path = f"{root}/index-{uuid.uuid4().hex}"
    build(path)
    spark.createDataFrame([(path,)], "path string").coalesce(1).write.mode("overwrite").json(f"{root}/current")
    return path


def current_index(spark: SparkSession, root: str) -> str:
    return spark.read.schema("path string").json(f"{root}/current").first()[0]
