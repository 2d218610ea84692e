"""Pieces shared by the text operators: table access, lineage cuts, components, numeric mixing."""

from __future__ import annotations

import os
import tempfile
import uuid
from pathlib import Path

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space that separates words in every contract on words.
WORD_BREAK = r"[\x20\x09-\x0D]+"


def prepare(spark: SparkSession) -> SparkSession:
    """Make the package importable in Python workers and a checkpoint folder known to the session.

    The folder named by ``spark.checkpoint.dir`` is used as it is; one is made only where none is set.
    """
    context = spark.sparkContext
    root = str(Path(__file__).resolve().parents[2])
    known = context.environment.get("PYTHONPATH", "")
    if root not in known.split(os.pathsep):
        context.environment["PYTHONPATH"] = os.pathsep.join(x for x in (root, known) if x)
    if not context._jsc.sc().getCheckpointDir().isDefined():
        context.setCheckpointDir(context.getConf().get("spark.checkpoint.dir") or tempfile.mkdtemp(prefix="checkpoints-"))
    return spark


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder of this session, as a URI that driver and executors share."""
    prepare(spark)
    return spark.sparkContext._jsc.sc().getCheckpointDir().get()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return prepare(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def cut(df: DataFrame) -> DataFrame:
    """The same rows without their lineage: written as Parquet in the shared folder and read again.

    Columns of the later plan are pruned in the read, and the sizes of small tables are known to the planner.
    """
    spark = df.sparkSession
    at = f"{shared_dir(spark)}/cut-{uuid.uuid4().hex}"
    df.write.parquet(at)
    return spark.read.schema(df.schema).parquet(at)


def fold(column: str, parts: int) -> Column:
    """crc32 of the id's decimal text, modulo ``parts``: the folds that the contracts name."""
    return F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(parts))


def let(value: Column, body) -> Column:
    """``body`` of a column that is computed once a row; a plain reference inside a lambda would be computed for every element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit words (the public splitmix constants)."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, label) for all ends of ``edges`` (a, b): label is the least node that is reachable.

    A round points each node at its least neighbour, halves the chains of these pointers, and carries on with the distinct
    links between what the ends point at. Nodes that are settled leave with their links, so later rounds are small: each
    halves the nodes at least, and the links of a dense group collapse in the first. Only one flag a round reaches the
    driver. Hubs are fine: minima are combined before the shuffle, and joins are on a side of unique nodes.
    """
    # one row gives both directions, so that edges of a plan that may vary from run to run are taken from one run
    both = F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b"))))
    links = cut(edges.where("a <> b").select(both.alias("e")).select("e.a", "e.b").distinct())
    labels = None
    for _ in range(max_rounds):
        first = links.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("up"))
        far = first.select(F.col("node").alias("up"), F.col("up").alias("top"))
        ups = cut(first.join(far, "up").select("node", F.col("top").alias("label")))
        if labels is None:
            labels = ups
        else:
            moved = ups.select(F.col("node").alias("label"), F.col("label").alias("new"))
            labels = cut(labels.join(moved, "label", "left").select("node", F.coalesce("new", "label").alias("label")))
        to = lambda c: ups.select(F.col("node").alias(c), F.col("label").alias(c * 2))
        links = cut(links.where("a < b").join(to("a"), "a").join(to("b"), "b").where("aa <> bb").select(F.explode(F.array(F.struct(F.col("aa").alias("a"), F.col("bb").alias("b")), F.struct(F.col("bb").alias("a"), F.col("aa").alias("b")))).alias("e")).select("e.a", "e.b").distinct())
        if links.isEmpty():
            return labels
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
