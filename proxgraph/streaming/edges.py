"""Streams of events: windows, sessions, dedup, transition arcs and graph snapshots.

``events.ts`` has no zone; watermarks need a zoned timestamp, so it is cast (the session's zone is to
be UTC).
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..session import ship
from ..storage import saved, shared_folder


def event_stream(spark: SparkSession, sf_dir: str, copies: int = 1, files: int = 4, watermark: str = "1 hour", closing: str | None = None) -> DataFrame:
    """The event table as a stream: sorted files in the shared folder, one a trigger.

    With ``copies`` over one, each file is there that many times.  With ``closing``, the longest time that a window stays
    open after its last event, all files are one trigger, and a last event (all null but ``ts``) is so late that the
    watermark passes every window but its own: append mode then gives all of them.
    """
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    folder = f"{shared_folder(spark)}/streams/{uuid.uuid4().hex}"
    for _ in range(copies):
        e.repartitionByRange(files, "ts").sortWithinPartitions("ts", "event_id").write.mode("append").parquet(folder)
    s = spark.readStream.schema(e.schema)
    if closing is None:
        s = s.option("maxFilesPerTrigger", files * copies)
    else:
        last = e.agg(F.max("ts").alias("ts")).where("ts is not null").select((F.col("ts") + F.expr(f"INTERVAL {watermark} + INTERVAL {closing} + INTERVAL 1 day")).alias("ts"))
        last.select(*(F.col("ts") if f.name == "ts" else F.lit(None).cast(f.dataType).alias(f.name) for f in e.schema)).write.mode("append").parquet(folder)
    s = s.parquet(folder)
    return s.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def tumbling(s: DataFrame, width: str = "1 day") -> DataFrame:
    return s.groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("events"), F.sum("value").alias("total")).select(F.col("window.start").alias("start"), "event_type", "events", "total")


def sliding(s: DataFrame, width: str = "1 day", step: str = "6 hours") -> DataFrame:
    return s.groupBy(F.window("ts", width, step)).agg(F.count("*").alias("events")).select(F.col("window.start").alias("start"), "events")


def sessions(s: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return s.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("events")).select("user_id", F.col("session_window.start").alias("start"), "events")


def dedup(s: DataFrame) -> DataFrame:
    return s.dropDuplicatesWithinWatermark(["event_id"])


def _link(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """Arcs between neighbouring events of a key; the last event is kept for the next batch."""
    rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
    users = rows["user_id"].tolist()
    if state.exists:
        users = [state.get[0], *users]
    if users:
        state.update((users[-1],))
    yield pd.DataFrame({"src": users[:-1], "dst": users[1:]}, dtype="int64")


def transitions(s: DataFrame, by: str = "event_type") -> DataFrame:
    """(src, dst): from each event's user to the next one's with the same ``by``, over batches in time order."""
    ship(s.sparkSession)
    return s.select(by, "ts", "event_id", "user_id").groupBy(by).applyInPandasWithState(_link, "src long, dst long", "user long", "append", GroupStateTimeout.NoTimeout)


def run_to_end(s: DataFrame, mode: str) -> DataFrame:
    """Everything the stream has now, as a table (memory sink for complete mode, Parquet for append)."""
    spark, name = s.sparkSession, f"px_{uuid.uuid4().hex}"
    place = f"{shared_folder(spark)}/streams/{name}"
    writer = s.writeStream.outputMode(mode).option("checkpointLocation", f"{place}_state").trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", place).start()
    else:
        query = writer.format("memory").queryName(name).start()
    query.awaitTermination()
    return spark.read.schema(s.schema).parquet(place) if mode == "append" else spark.table(name)


def refresh(s: DataFrame, solve: Callable[[DataFrame], DataFrame], sink: list) -> object:
    """After each batch of arcs (src, dst), add them to the edge table and answer again with ``solve(edges)``.

    ``sink`` gets each answer; the edge table is written anew for every batch, so a batch that is run
    again gives the same table.
    """
    tables: dict[int, DataFrame] = {}

    def merge(batch: DataFrame, number: int) -> None:
        fresh = batch.select("src", "dst").distinct()
        before = tables.get(number - 1)
        tables[number] = saved(fresh if before is None else before.unionByName(fresh).distinct())
        sink.append(solve(tables[number]))

    folder = f"{shared_folder(s.sparkSession)}/streams/{uuid.uuid4().hex}_state"
    return s.writeStream.foreachBatch(merge).option("checkpointLocation", folder).trigger(availableNow=True).start()
