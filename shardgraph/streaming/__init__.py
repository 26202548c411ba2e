"""Graphs from event streams: windows, late data, duplicates, stateful chains, joins and growing degrees."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from shardgraph.build import prepare
from shardgraph.model.graph import ShardedGraph
from shardgraph.session import exists, scratch_path, table_name


def events(spark: SparkSession, sf: str) -> DataFrame:
    """The events table as a file stream, times in the session's zone."""
    schema = spark.read.parquet(f"{sf}/events.parquet").schema
    return spark.readStream.schema(schema).parquet(_folder(spark, sf)).withColumn("ts", F.col("ts").cast("timestamp"))


def _folder(spark: SparkSession, sf: str) -> str:
    """A file stream reads folders; a single file is copied into one in the shared folder."""
    path = scratch_path(spark, "stream-events")
    spark.read.parquet(f"{sf}/events.parquet").repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(path)
    return path


def drained(df: DataFrame, mode: str, label: str) -> DataFrame:
    """Run a stream over all that is there and read what it wrote. Update and complete modes keep the last batch's rows."""
    spark = df.sparkSession
    out, state = scratch_path(spark, f"{label}-out"), scratch_path(spark, f"{label}-state")
    if mode == "append":
        q = df.writeStream.outputMode("append").option("checkpointLocation", state).format("parquet").option("path", out).trigger(availableNow=True).start()
    else:
        q = df.writeStream.outputMode(mode).option("checkpointLocation", state).foreachBatch(lambda b, k: b.write.mode("overwrite").parquet(out)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


def tumbling(stream: DataFrame, width: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(stream: DataFrame, width: str = "1 hour", step: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """A user's chain, cut where it pauses."""
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "n")


def without_repeats(stream: DataFrame, late: str = "10 minutes") -> DataFrame:
    """An edge's repeated arrivals within the watermark are dropped."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def chain_edges(stream: DataFrame) -> DataFrame:
    """(src, dst): each user's last event is state; a new one gives an edge from it."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        last = state.get[0] if state.exists else None
        ids = rows["event_id"].tolist()
        pairs = list(zip([last, *ids[:-1]] if last is not None else ids[:-1], ids if last is not None else ids[1:], strict=True))
        state.update((ids[-1],))
        yield pd.DataFrame(pairs, columns=["src", "dst"], dtype="int64")

    return stream.select("user_id", "event_id", "ts").groupBy("user_id").applyInPandasWithState(step, "src long, dst long", "last long", "append", GroupStateTimeout.NoTimeout)


def click_to_purchase(stream: DataFrame, within: str = "1 hour") -> DataFrame:
    """A stream joined with itself on user and time interval: edges from clicks to purchases."""
    a = stream.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("event_id").alias("src"), F.col("ts").alias("ta")).withWatermark("ta", "1 hour")
    b = stream.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("dst"), F.col("ts").alias("tb")).withWatermark("tb", "1 hour")
    return a.join(b, F.expr(f"u = user_id and tb > ta and tb <= ta + interval {within}")).select("src", "dst")


def degrees_so_far(stream: DataFrame) -> DataFrame:
    """Events of each user so far, in complete mode."""
    return stream.groupBy("user_id").agg(F.count("*").alias("n"))


def grow_shards(stream_edges: DataFrame, sg: ShardedGraph) -> ShardedGraph:
    """A prepared graph with a stream's edges(src, dst, weight) added to the shards that own their destinations.

    Each batch is dealt by the graph's intervals and appended to the same buckets; when all that is there has come,
    counts, degrees, CSR, mirrors and filters are made anew, so that skipping stays free of loss. Edges whose ends aren't
    vertices of the graph are left out. A batch that is run again after a failure is appended once: its number is kept with it.
    """
    spark = stream_edges.sparkSession
    done = scratch_path(spark, "grown-batches")
    known = (F.col("src") >= 0) & (F.col("src") < sg.n) & (F.col("dst") >= 0) & (F.col("dst") < sg.n)

    def put(batch: DataFrame, k: int) -> None:
        if exists(spark, f"{done}/{k}"):
            return
        routed = batch.where(known).select("src", "dst", "weight", sg.shard_of(F.col("dst")).alias("shard_id"))
        routed.repartition(sg.buckets, "shard_id").write.insertInto(table_name(sg.edges_at))
        spark.range(1).write.parquet(f"{done}/{k}")

    q = stream_edges.writeStream.foreachBatch(put).option("checkpointLocation", scratch_path(spark, "grow")).trigger(availableNow=True).start()
    q.awaitTermination()
    return prepare.refresh(sg)
