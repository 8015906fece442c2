"""Hyperedges from a stream of events: windows, sessions, duplicates, running degrees."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..session import work_folder

STORE = "spark.sql.streaming.stateStore.providerClass"
EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream, its time as a timestamp (watermarks need one)."""
    s = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(df: DataFrame, mode: str = "complete") -> DataFrame:
    """Run the stream over all that is there, with a checkpoint, and give the rows that a sink of this mode holds in the end.

    Executors write each micro-batch to a folder of its number, which a batch that runs again overwrites; no row goes through the
    driver. State is kept in RocksDB, outside the heap. In mode 'complete' the last batch stands for all.
    """
    spark, name = df.sparkSession, f"s_{uuid.uuid4().hex}"
    path = f"{work_folder(spark)}/stream/{name}"
    numbers = []

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/rows/batch={number}")
        numbers.append(number)

    before = spark.conf.get(STORE, None)
    spark.conf.set(STORE, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        q = df.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        spark.conf.set(STORE, before) if before else spark.conf.unset(STORE)
    if not numbers:
        return spark.createDataFrame([], df.schema)
    held = numbers[-1:] if mode == "complete" else sorted(set(numbers))
    return spark.read.schema(df.schema).parquet(*[f"{path}/rows/batch={n}" for n in held])


def members_per_window(events: DataFrame, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """Hyperedge = (event type, window): distinct users and events in it."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    g = events.groupBy(w.alias("w"), "event_type").agg(F.size(F.collect_set("user_id")).cast("long").alias("members"), F.count("*").alias("events"))
    return g.select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "members", "events")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Hyperedge = session of a user: the event types in it."""
    g = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events"), F.size(F.collect_set("event_type")).cast("long").alias("types"))
    return g.select("user_id", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "events", "types")


def deduplicated(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def running_degrees(events: DataFrame) -> DataFrame:
    """Per (event type, day) a state of users seen; every batch gives the hyperedge's size and weight so far."""

    def update(key, frames, state):
        users, n = set(state.get[0]) if state.exists else set(), state.get[1] if state.exists else 0
        for f in frames:
            users.update(f["user_id"].tolist())
            n += len(f)
        state.update((sorted(users), n))
        yield pd.DataFrame({"event_type": [key[0]], "day": [key[1]], "size": [len(users)], "events": [n]})

    rows = events.select("event_type", F.date_format("ts", "yyyy-MM-dd").alias("day"), "user_id")
    return rows.groupBy("event_type", "day").applyInPandasWithState(update, "event_type string, day string, size long, events long", "users array<long>, n long", "update", GroupStateTimeout.NoTimeout)


def joined_with(events: DataFrame, vectors: DataFrame) -> DataFrame:
    """Stream-static join: each event with its user's vector (id, vec)."""
    return events.join(vectors.withColumnRenamed("id", "user_id"), "user_id")


def dropped_late(query) -> int:
    """Rows that a finished query's stateful operators dropped because the watermark had passed them (of the progress reports that are kept)."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p["stateOperators"])


def closed_windows(events: DataFrame, delay: str = "1 hour", length: str = "1 day") -> DataFrame:
    """Windows as in `members_per_window`, for append mode: each comes out once, when the watermark has passed its end; later rows are dropped."""
    w = F.window("ts", length)
    g = events.withWatermark("ts", delay).groupBy(w.alias("w"), "event_type").agg(F.approx_count_distinct("user_id").alias("members"), F.count("*").alias("events"))
    return g.select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "members", "events")


def running_volumes(events: DataFrame, path: str) -> DataFrame:
    """Degrees (side, id, total) of users and of (event type, day) hyperedges, and the volume (side 'all'), kept up over micro-batches.

    All three are sums of memberships, so each batch writes its own partial sums to a folder named by its number. A batch that runs
    again after a failure overwrites that folder and nothing counts twice.
    """
    spark = events.sparkSession

    def sums(batch: DataFrame, number: int) -> None:
        edge = F.concat_ws(" ", "event_type", F.date_format("ts", "yyyy-MM-dd"))
        sides = F.explode(F.array(*[F.struct(F.lit(s).alias("side"), c.alias("id")) for s, c in (("node", F.col("user_id").cast("string")), ("edge", edge), ("all", F.lit("")))]))
        rows = batch.select(sides.alias("k")).groupBy("k.side", "k.id").agg(F.count("*").alias("part"))
        rows.write.mode("overwrite").parquet(f"{path}/batch={number}")

    q = events.writeStream.foreachBatch(sums).option("checkpointLocation", f"{path}-checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    parts = spark.read.schema("side string, id string, part long").parquet(f"{path}/batch=*")
    return parts.groupBy("side", "id").agg(F.sum("part").alias("total"))
