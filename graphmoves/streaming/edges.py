"""Edges from an event stream: windows, late data, state, joins, and warm-started clustering per batch."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from graphmoves.session import shared_folder, table

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    """The events file or folder as a stream with timestamps that watermarks accept. A pattern, so that one file may be the path."""
    head, _, last = path.rpartition("/")
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(f"{head}/[{last[0]}]{last[1:]}")
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("k", F.get_json_object("props", "$.k").cast("long"))


def usage_windows(events: DataFrame, size: str = "1 hour", slide: str | None = None, late: str = "1 day") -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    own = events.withWatermark("ts", late) if events.isStreaming else events
    return own.groupBy(w.alias("w"), "user_id", "k").agg(F.count("*").alias("w_count")).select(F.col("w.start").alias("start"), "user_id", "k", "w_count")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 day") -> DataFrame:
    """Sessions of each user. A stream appends a session once the watermark has passed its end; in complete mode open ones show too."""
    own = events.withWatermark("ts", late) if events.isStreaming else events
    return own.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


def first_edges(events: DataFrame, late: str = "1 day") -> DataFrame:
    """Each edge once within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["user_id", "k"]).select("user_id", "k", "ts")


def running_degree(events: DataFrame) -> DataFrame:
    """Degree of each user so far, kept as state."""
    def step(key, batches, state: GroupState):
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [n]})

    return events.select("user_id", "k").groupBy("user_id").applyInPandasWithState(step, "user_id long, degree long", "n long", "update", GroupStateTimeout.NoTimeout)


def with_static(events: DataFrame, labels: DataFrame) -> DataFrame:
    """Labels of users beside their events; Spark broadcasts the labels only below its own size limit."""
    return events.join(labels, events.user_id == labels.id, "left").select("event_id", "user_id", "c")


def clicks_then_purchases(events: DataFrame, within: str = "1 hour", late: str = "1 day") -> DataFrame:
    """Purchases of a user within a time after a click: a join of two streams."""
    mark = lambda t, n: events.where(F.col("event_type") == t).select(F.col("user_id").alias(n + "u"), F.col("ts").alias(n + "t"), F.col("event_id").alias(n + "e"))
    c, p = mark("click", "c"), mark("purchase", "p")
    if events.isStreaming:
        c, p = c.withWatermark("ct", late), p.withWatermark("pt", late)
    return c.join(p, F.expr(f"cu = pu and pt >= ct and pt <= ct + interval {within}")).select("ce", "pe")


def run_to_end(df: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Process what there is into files in the shared folder, and read them back: all rows of append and update mode, the last result of complete mode."""
    spark = df.sparkSession
    at = checkpoint or f"{shared_folder(spark)}/stream{uuid.uuid4().hex}"
    w = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{at}/checkpoint")
    if mode == "append":
        w.format("parquet").option("path", f"{at}/out").start().awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{at}/out")


    def keep(out: DataFrame, number: int) -> None:
        out.write.mode("overwrite" if mode == "complete" else "append").parquet(f"{at}/out")

    w.foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{at}/out")


def cluster_batches(events: DataFrame, cfg=None, on_labels=None) -> list[dict]:
    """foreachBatch: merge each batch's edges into the graph, start from the last labels, move, keep the labels."""
    from graphmoves.model import Config
    from graphmoves.plans.moving import local_moving
    from graphmoves.session import drop, snapshot
    from graphmoves.sources.build import from_pairs

    seen: dict = {"pairs": None, "labels": None, "log": []}

    def batch(df: DataFrame, number: int) -> None:
        own = df.where("k is not null").groupBy((2 * F.col("user_id")).alias("a"), (2 * F.col("k") + 1).alias("b")).agg(F.count("*").alias("w"))
        old = seen["pairs"]
        seen["pairs"] = snapshot(own if old is None else own.union(old).groupBy("a", "b").agg(F.sum("w").alias("w")))
        g = from_pairs(seen["pairs"])
        start = None
        if seen["labels"] is not None:
            start = g.nodes.select("id").join(seen["labels"], "id", "left").select("id", F.coalesce("c", "id").alias("c"))
        before = seen["labels"]
        seen["labels"], trace = local_moving(g, start, cfg or Config(max_rounds=2), "modularity")
        drop(old, before, g.edges, g.nodes)
        seen["log"].append({"batch": number, "moved": trace[-1][3], "clusters": trace[-1][4]})
        if on_labels:
            on_labels(seen["labels"], number)

    events.writeStream.foreachBatch(batch).trigger(availableNow=True).option("checkpointLocation", f"{shared_folder(events.sparkSession)}/batches{uuid.uuid4().hex}").start().awaitTermination()
    return seen["log"]


def batch_events(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).withColumn("k", F.get_json_object("props", "$.k").cast("long"))
