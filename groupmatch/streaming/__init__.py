"""Edges from event streams, and re-matching of the leaders that changes touch."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from groupmatch.durable import shared_folder
from groupmatch.model import GroupPattern, SocialGraph


def replay(spark: SparkSession, sf_dir: str, name: str = "events") -> DataFrame:
    """A table's files as a stream; a folder of part files gives several batches."""
    place = f"{sf_dir}/{name}.parquet"
    schema = spark.read.parquet(place).schema
    # A single file has no folder of its own to watch: its folder is read with a filter on the name.
    single = not [f for f in spark.read.parquet(place).inputFiles() if f"{name}.parquet/" in f]
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1)
    rows = reader.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir) if single else reader.parquet(place)
    # Watermarks need time with a zone.
    return rows.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in rows.columns else rows


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream to the end of its input into Parquet in the shared folder and returns the rows.

    Complete and update modes write every batch through foreachBatch and keep the last complete one."""
    spark = stream.sparkSession
    place = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", f"{place}/data").option("checkpointLocation", f"{place}/state").outputMode("append").trigger(availableNow=True).start()
    else:
        def write(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{place}/data")

        query = stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{place}/state").outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{place}/data")


def tumbling(events: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type")
    return w.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "1 hour", step: str = "15 minutes") -> DataFrame:
    w = events.withWatermark("ts", "1 hour").groupBy(F.window("ts", width, step))
    return w.agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    w = events.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap), "user_id")
    return w.agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), "user_id", "n")


def deduplicated(events: DataFrame, key: str = "event_id") -> DataFrame:
    return events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark([key])


def joined(events: DataFrame, orders: DataFrame) -> DataFrame:
    """Events with a static table of customers' order counts."""
    n = orders.groupBy("o_custkey").agg(F.count("*").alias("orders"))
    return events.join(n, F.col("user_id") == F.col("o_custkey")).select("event_id", "user_id", "orders")


def transitions(events: DataFrame) -> DataFrame:
    """(user_id, src_type, dst_type): each user's consecutive event types, with the last one as state."""

    def step(key, batches, state: GroupState):
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        kinds = rows.event_type.tolist()
        pairs = list(zip([last, *kinds[:-1]], kinds))
        state.update((kinds[-1],))
        yield pd.DataFrame([(key[0], a, b) for a, b in pairs if a is not None], columns=["user_id", "src_type", "dst_type"])

    return events.select("user_id", "ts", "event_id", "event_type").groupBy("user_id").applyInPandasWithState(step, "user_id long, src_type string, dst_type string", "last string", "append", GroupStateTimeout.NoTimeout)


def touched_leaders(g: SocialGraph, p: GroupPattern, changed: DataFrame) -> DataFrame:
    """Leader candidates whose undirected ball of the pattern's diameter holds an end of a changed edge
    (src, dst): only their groups can differ."""
    from groupmatch.operators import candidates, locality

    ends = changed.select(F.explode(F.array("src", "dst")).alias("v"))
    near = locality.near(g, ends, p.diameter()).select(F.col("v").alias("leader"))
    heads = candidates.select(g, p.node(p.leader)).select(F.col("v").alias("leader"))
    return near.join(heads, "leader", "left_semi")


def refreshed(g: SocialGraph, p: GroupPattern, old_members: DataFrame, changed: DataFrame) -> DataFrame:
    """Members after edges changed (`g` is the new graph): touched leaders are matched again, others stay.

    For removed edges pass the union of old and new edges as the graph of the balls."""
    from groupmatch.durable import settle
    from groupmatch.operators import explore

    leaders = settle(touched_leaders(g, p, changed), "touched")
    fresh = explore.match(g, p, leaders=leaders).members()
    return old_members.join(leaders, "leader", "left_anti").unionByName(fresh)
