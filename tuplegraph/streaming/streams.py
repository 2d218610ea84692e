"""Events as a stream: windows, incremental postings and degrees, joins, query-log statistics, user state, duplicates.

Every function takes and gives a streaming DataFrame; ``drain`` runs one to the end of its source into a memory table, the
way tests and registered queries look at it.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..session import prepare, shared_dir

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str, delay: str | None = "1 hour", files: str = "events.parquet") -> DataFrame:
    """The events table, ``files`` of a folder, as a file stream, with a watermark on ``ts``."""
    rows = prepare(spark).readStream.schema(SCHEMA).option("pathGlobFilter", files).parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))
    return rows.withWatermark("ts", delay) if delay else rows


def tumbling(rows: DataFrame, size: str = "1 day") -> DataFrame:
    """(start, event_type, n)."""
    return rows.groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(rows: DataFrame, size: str = "2 days", step: str = "1 day") -> DataFrame:
    return rows.groupBy(F.window("ts", size, step).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(rows: DataFrame, gap: str = "6 hours") -> DataFrame:
    """(user_id, start, n): runs of a user's events with gaps below ``gap``."""
    return rows.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def degrees(rows: DataFrame) -> DataFrame:
    """(user_id, indeg): running in-degree of customers from events."""
    return rows.groupBy("user_id").agg(F.count(F.lit(1)).alias("indeg"))


def with_customers(rows: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join: events with the segment of their customer."""
    return rows.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id")


def views_then_purchases(rows: DataFrame, other: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: a purchase of the same user within a time after a view."""
    v = rows.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("viewed"), F.col("event_id").alias("view_id"))
    p = other.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("bought"), F.col("event_id").alias("purchase_id"))
    return v.join(p, (F.col("u") == F.col("user_id")) & (F.col("bought") >= F.col("viewed")) & (F.col("bought") <= F.col("viewed") + F.expr(f"interval {within}"))).select("view_id", "purchase_id")


def unique(rows: DataFrame, columns: list[str]) -> DataFrame:
    return rows.dropDuplicatesWithinWatermark(columns)


def decayed(rows: DataFrame, half_life: float = 86400.0, idle: float | None = None) -> DataFrame:
    """(user_id, n, activation): per-user activation that halves every ``half_life`` seconds, kept as state.

    ``idle``: a user without events for so many seconds starts anew, and a timer on event time removes the state once the
    watermark has passed; rows behind the watermark are dropped then.
    """

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        level, last, n = state.get if state.exists else (0.0, 0.0, 0)
        for now in pd.concat(list(parts)).sort_values(["at", "event_id"])["at"]:
            if idle is not None and n and now - last > idle:
                n = 0
            level = level * 0.5 ** (max(0.0, now - last) / half_life) + 1.0 if n else 1.0
            last, n = now, n + 1
        state.update((level, last, n))
        if idle is not None:
            state.setTimeoutTimestamp(max(int((last + idle) * 1000), state.getCurrentWatermarkMs()) + 1)
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "activation": [level]})

    timer = GroupStateTimeout.NoTimeout if idle is None else GroupStateTimeout.EventTimeTimeout
    timed = rows.select("user_id", "event_id", "ts", (F.unix_micros("ts") / 1e6).alias("at"))
    return timed.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, activation double", "level double, last double, n long", "update", timer)


def upsert(spark: SparkSession, path: str, keys: list[str], sums: list[str]):
    """A foreachBatch function that adds each batch's sums to a table kept as numbered versions; the newest is read."""

    def run(batch: DataFrame, number: int) -> None:
        new = batch.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in sums])
        if number > 0:
            old = spark.read.parquet(f"{path}/v={number - 1}")
            new = old.unionByName(new).groupBy(*keys).agg(*[F.sum(c).alias(c) for c in sums])
        new.write.mode("overwrite").parquet(f"{path}/v={number}")
        if number > 1:  # the version before the last is kept for a batch that is run again
            removed = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/v={number - 2}")
            removed.getFileSystem(spark._jsc.hadoopConfiguration()).delete(removed, True)

    return run


def newest(spark: SparkSession, path: str) -> DataFrame:
    """The newest version that ``upsert`` has written."""
    rows = spark.read.parquet(path)
    return rows.where(F.col("v") == rows.agg(F.max("v")).first()[0]).drop("v")


def finished(query, seconds: int = 600) -> None:
    """Waits for a query over what its source has now; one that does not end is stopped and raises."""
    if not query.awaitTermination(seconds):
        query.stop()
        raise TimeoutError(f"the streaming query did not end within {seconds} seconds")


def log_statistics(spark: SparkSession, log: DataFrame, path: str) -> None:
    """Query-log rows (term, cluster_id, hits) into the history that adaptive choice reads."""
    finished(log.writeStream.foreachBatch(upsert(spark, path, ["term", "cluster_id"], ["hits"])).option("checkpointLocation", f"{path}/_checkpoint").trigger(availableNow=True).start())


def incremental_edges(spark: SparkSession, rows: DataFrame, path: str) -> None:
    """Degrees of customers from new events, batch by batch."""
    finished(rows.select("user_id", F.lit(1).cast("long").alias("indeg")).writeStream.foreachBatch(upsert(spark, path, ["user_id"], ["indeg"])).option("checkpointLocation", f"{path}/_checkpoint").trigger(availableNow=True).start())


def drain(rows: DataFrame, mode: str = "complete") -> DataFrame:
    """All rows of a streaming query over what its source has now, by way of files in the shared folder, a folder a batch."""
    spark = rows.sparkSession
    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/rows/v={number}")

    finished(rows.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{path}/_checkpoint").trigger(availableNow=True).start())
    root = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/rows")
    if not root.getFileSystem(spark._jsc.hadoopConfiguration()).exists(root):
        return spark.createDataFrame([], rows.schema)
    return newest(spark, f"{path}/rows") if mode == "complete" else spark.read.parquet(f"{path}/rows").drop("v")


def deliver(rows: DataFrame, path: str) -> int:
    """Runs a stateful query over what its source has now, into ``path``; how many rows came behind the watermark and were
    dropped. Run again on the same ``path``, it goes on from its checkpoint."""

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/rows/v={number}")

    query = rows.writeStream.foreachBatch(keep).outputMode("append").option("checkpointLocation", f"{path}/_checkpoint").trigger(availableNow=True).start()
    finished(query)
    reports = query.recentProgress
    ids = [p.batchId for p in reports]
    if ids and len(set(ids)) >= int(rows.sparkSession.conf.get("spark.sql.streaming.numRecentProgressUpdates", "100")):
        raise RuntimeError("the query had more batches than it keeps reports of")
    return sum(o.numRowsDroppedByWatermark for p in reports for o in p.stateOperators)
