"""Iteration with cut lineage: each round ends in the shared folder, and the driver sees one count."""

from __future__ import annotations

import gc
import math
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import shared_dir

#: Rows of a side that may be broadcast when they were counted; beyond it the join shuffles.
BROADCAST_ROWS = 100_000
#: Rows whose shuffle files may lie on disk at once while a large table is cut.
PASS_ROWS = 20_000_000


def dealt(df: DataFrame, by: str) -> DataFrame:
    """Rows shuffled into the partitions that ``cut`` makes its buckets of."""
    return df.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), by)


def cut(df: DataFrame, by: str | None = None, rows: int = 0, over: str | None = None, lie: bool = False) -> DataFrame:
    """The same rows without their lineage: written once as compressed Parquet in the shared folder and read again.

    ``by``: rows are dealt into buckets of this column, so that joins on it shuffle only their other side. ``rows``: how many
    rows are shuffled for it; above PASS_ROWS they are written in passes over hashes of ``over`` (``by`` if none is given), and
    a pass deletes its shuffle files before the next one. ``lie``: the rows are dealt by the column already, and not again.
    """
    spark = df.sparkSession
    name = f"cut_{uuid.uuid4().hex}"
    at = f"{shared_dir(spark)}/{name}"
    passes, n = max(1, math.ceil(rows / PASS_ROWS)), int(spark.conf.get("spark.sql.shuffle.partitions"))
    for number in range(passes):
        part = df if passes == 1 else df.where(F.pmod(F.xxhash64(F.lit("pass"), F.col(over or by)), F.lit(passes)) == number)
        if by is None:
            part.write.mode("append").option("compression", "zstd").parquet(at)
        else:
            (part if lie else part.repartition(n, by)).write.mode("append").option("compression", "zstd").option("path", at).bucketBy(n, by).saveAsTable(name, format="parquet")
        if passes > 1:
            sweep(spark)
    out = spark.read.schema(df.schema).parquet(at) if by is None else spark.table(name)
    out.cut_at, out.cut_by = at, by
    return out


def drop(*frames: DataFrame) -> None:
    """Delete the files of cuts that nothing reads any more, and let go of the shuffle files behind them."""
    for df in frames:
        jvm = df.sparkSession._jvm
        path = jvm.org.apache.hadoop.fs.Path(df.cut_at)
        path.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(path, True)
        if df.cut_by is not None:
            df.sparkSession.sql(f"DROP TABLE IF EXISTS {df.cut_at.rsplit('/', 1)[1]}")
    sweep(frames[0].sparkSession)


def sweep(spark: SparkSession) -> None:
    """Let go of the shuffle files of finished plans: Spark deletes them when the driver has collected the plans."""
    gc.collect()
    spark._jvm.System.gc()


def few(df: DataFrame) -> DataFrame:
    """A stored table, to be broadcast if it was counted to be small."""
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


def until_fixed(state: DataFrame, step: Callable[[DataFrame, int], tuple[DataFrame, bool]], max_rounds: int) -> tuple[DataFrame, int]:
    """Apply ``step`` until it reports no change; (last state, rounds)."""
    for number in range(max_rounds):
        state, changed = step(state, number)
        if not changed:
            return state, number + 1
    return state, max_rounds
