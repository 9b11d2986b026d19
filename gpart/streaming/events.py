"""Graphs and partitions from streams: windows of edge counts, duplicates, joins with a partition, one-pass placement.

Streams are read from files and run with an available-now trigger; results of a query are what a complete run leaves behind. The
checkpoints and outputs are in the shared checkpoint folder.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gpart.session import checkpoint_dir


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream of files; ts, the event time, as a point in time. The table is one file of its folder, or a folder."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/events.parquet")
    folder = path.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(path).isDirectory()
    reader = spark.readStream.schema(schema)
    stream = reader.parquet(f"{sf_dir}/events.parquet") if folder else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def complete(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs the stream over all that is available and returns its result: the rows of the last version of each batch's output."""
    spark = stream.sparkSession
    checkpoint_dir(spark)
    home = f"{spark.sparkContext.getCheckpointDir()}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{home}/out/{'last' if mode == 'complete' else number}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{home}/state").trigger(availableNow=True).foreachBatch(keep).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{home}/out/*")


def window_counts(events: DataFrame, width: str, step: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, event_type, n) for tumbling (no step) or sliding windows; complete when the run ends."""
    frame = F.window("ts", width, step) if step else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(frame.alias("win"), "event_type").agg(F.count("*").alias("n")).select(F.col("win.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def session_counts(events: DataFrame, gap: str, late: str = "1 hour") -> DataFrame:
    """(user_id, start, until, n) for sessions that end after a gap."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("win"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("win.start").cast("timestamp_ntz").alias("start"), F.col("win.end").cast("timestamp_ntz").alias("until"), "n")


def first_of_user_type(events: DataFrame, late: str = "3650 days") -> DataFrame:
    """(user_id, event_type) once each."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")


def with_partition(events: DataFrame, partition: DataFrame) -> DataFrame:
    """(event_id, block): a stream joined with a static partition of the users."""
    return events.join(partition.select(F.col("id").alias("user_id"), "block"), "user_id").select("event_id", "block")


def place_users(events: DataFrame, k: int, cap: int) -> DataFrame:
    """One-pass placement of users as they first appear, with state: (id, block). One state holds the loads of all blocks, as in any
    one-pass greedy placement; users of one event type are drawn to the block where that type is commonest."""

    def run(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        loads, seen, kinds = list(state.get[0]) if state.exists else [0] * k, set(state.get[1]) if state.exists else set(), list(state.get[2]) if state.exists else [0] * (8 * k)
        out = []
        rows = pd.concat([*batches]).sort_values(["ts", "event_id"])
        for user, kind in zip(rows["user_id"], rows["event_type"], strict=True):
            if user in seen:
                continue
            seen.add(user)
            place = sum(map(ord, kind)) % 8
            fits = [b for b in range(k) if loads[b] < cap] or [min(range(k), key=loads.__getitem__)]
            best = max(fits, key=lambda b: (kinds[8 * b + place] * (1 - loads[b] / cap), -loads[b], -b))
            loads[best] += 1
            kinds[8 * best + place] += 1
            out.append((user, best))
        state.update((loads, sorted(seen), kinds))
        yield pd.DataFrame(out, columns=["id", "block"]).astype({"id": "int64", "block": "int32"})

    keyed = events.withColumn("one", F.lit(0))
    return keyed.groupBy("one").applyInPandasWithState(run, "id long, block int", "loads array<long>, seen array<long>, kinds array<long>", "append", "NoTimeout")
