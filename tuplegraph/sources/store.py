"""The clustered graph on disk: a small graph that is read at the start, and clusters that are read on demand."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.cluster import represent
from ..operators.graph import Graph
from ..operators.quotient import quotient

BUCKETS = 64


def write_quotient(graph: Graph, membership: DataFrame, path: str, weight: str = "inverse_sum", prestige: str = "sum") -> None:
    small = quotient(graph, membership, weight, prestige)
    small.nodes.write.mode("overwrite").parquet(f"{path}/clusters")
    small.edges.write.mode("overwrite").parquet(f"{path}/super_edges")


def write_clusters(graph: Graph, membership: DataFrame, path: str, buckets: int = BUCKETS) -> None:
    """Nodes and edges by bucket of clusters, sorted by cluster, so a read of few clusters touches few row groups.

    A folder holds a bucket, not a cluster: folders of clusters would be too many small files.
    """
    ordered, _ = represent(membership)
    edge = F.shiftright(F.xxhash64("cluster_id"), 56)
    bucket = F.pmod(edge, F.lit(buckets)).cast("int")
    nodes = graph.nodes.join(ordered, "node_id").withColumn("bucket", bucket)
    nodes.repartition(buckets, "bucket").sortWithinPartitions("cluster_id", "ordinal").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/nodes")
    edges = graph.edges.join(membership.withColumnRenamed("node_id", "src"), "src").withColumn("bucket", bucket)
    edges.repartition(buckets, "bucket").sortWithinPartitions("cluster_id", "src", "dst").write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/edges")


def read_quotient(spark: SparkSession, path: str) -> Graph:
    return Graph(spark.read.parquet(f"{path}/clusters"), spark.read.parquet(f"{path}/super_edges"))


def read_clusters(spark: SparkSession, path: str, ids: DataFrame, kind: str = "nodes", buckets: int = BUCKETS) -> DataFrame:
    """Rows of the clusters in ``ids`` (cluster_id): a semi join on bucket and cluster, which prunes folders and row groups."""
    wanted = ids.select("cluster_id").distinct().withColumn("bucket", F.pmod(F.shiftright(F.xxhash64("cluster_id"), 56), F.lit(buckets)).cast("int"))
    return spark.read.parquet(f"{path}/{kind}").join(wanted, ["bucket", "cluster_id"], "left_semi")


@dataclass
class Cache:
    """Clusters that were read stay persisted under a version; a new version drops them."""

    spark: SparkSession
    path: str
    buckets: int = 64
    version: int = 0
    held: dict = field(default_factory=dict)

    def nodes(self, name: str, ids: DataFrame) -> DataFrame:
        key = (self.version, name)
        if key not in self.held:
            self.held[key] = read_clusters(self.spark, self.path, ids, "nodes", self.buckets).persist()
        return self.held[key]

    def renew(self) -> None:
        for frame in self.held.values():
            frame.unpersist()
        self.held.clear()
        self.version += 1


def load_time(spark: SparkSession, path: str) -> DataFrame:
    """(form, seconds, rows) to open the small graph and the whole one."""
    rows = []
    for form, names in (("quotient", ("clusters", "super_edges")), ("full", ("nodes", "edges"))):
        began = time.perf_counter()
        n = sum(spark.read.parquet(f"{path}/{x}").count() for x in names)
        rows.append((form, time.perf_counter() - began, n))
    return spark.createDataFrame(rows, "form string, seconds double, n_rows long")
