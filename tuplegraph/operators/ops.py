"""Relational operators around the graph methods, one function each, on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import shared_dir
from ..sources.catalog import table


def round_trip(spark: SparkSession, sf_dir: str, form: str) -> DataFrame:
    """Nations written in a text or column format and read back with their schema."""
    rows = table(spark, sf_dir, "nation")
    path = f"{shared_dir(spark)}/nation_{form}"
    rows.write.mode("overwrite").format(form).save(path)
    return spark.read.schema(rows.schema).format(form).load(path)


def as_of(events: DataFrame) -> DataFrame:
    """(event_id, last_purchase): each event's latest earlier purchase of the same user; one sort a user."""
    bought = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True)
    window = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return events.select("event_id", bought.over(window).alias("last_purchase"))


def interval_join(events: DataFrame, seconds: int = 3600) -> DataFrame:
    """(view_id, purchase_id): purchases of a user within a time after a view. Buckets of that length keep the join local."""
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    size = seconds * 1_000_000
    rows = events.withColumn("at", at).withColumn("bucket", F.floor(F.col("at") / size))
    views = rows.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("at").alias("seen"), F.col("event_id").alias("view_id"), F.explode(F.array("bucket", F.col("bucket") + 1)).alias("bucket"))
    bought = rows.where("event_type = 'purchase'").select("user_id", "at", "bucket", F.col("event_id").alias("purchase_id"))
    joined = views.join(bought, (views.u == bought.user_id) & (views.bucket == bought.bucket))
    return joined.where((F.col("at") >= F.col("seen")) & (F.col("at") <= F.col("seen") + size)).select("view_id", "purchase_id")


def band_join(parts: DataFrame, width: float = 0.05) -> DataFrame:
    """(a, b): parts of a brand whose prices differ by at most ``width``; price buckets keep candidates few."""
    rows = parts.select("p_brand", "p_partkey", "p_retailprice", F.floor(F.col("p_retailprice") / (2 * width)).alias("bucket"))
    left = rows.select("p_brand", F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("pa"), F.explode(F.array(F.col("bucket") - 1, F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    right = rows.select("p_brand", F.col("p_partkey").alias("b"), F.col("p_retailprice").alias("pb"), "bucket")
    return left.join(right, ["p_brand", "bucket"]).where((F.col("a") < F.col("b")) & (F.abs(F.col("pa") - F.col("pb")) <= width)).select("a", "b")


def hops(edges: DataFrame, start: DataFrame, k: int) -> DataFrame:
    """(node_id, hop): nodes within k steps along edges, with their first step; the frontier is distinct each round."""
    seen = start.select("node_id").distinct().withColumn("hop", F.lit(0))
    frontier = seen
    for step in range(1, k + 1):
        new = frontier.join(edges, F.col("node_id") == F.col("src")).select(F.col("dst").alias("node_id")).distinct().join(seen.select("node_id"), "node_id", "left_anti").withColumn("hop", F.lit(step))
        seen, frontier = seen.unionByName(new), new
    return seen


def hash_sample(df: DataFrame, column: str, parts: int, keep: int) -> DataFrame:
    """Rows whose hashed column falls into ``keep`` of ``parts``: the same rows in every run."""
    return df.where(F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(parts)) < keep)


def edit_matches(values: DataFrame, term: str, most: int) -> DataFrame:
    """(value, distance) within an edit distance, after blocking by length."""
    near = values.where(F.length("value").between(len(term) - most, len(term) + most))
    return near.withColumn("distance", F.levenshtein("value", F.lit(term))).where(F.col("distance") <= most)
