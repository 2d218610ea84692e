"""Looking at one tuple, its references, and what refers to it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import Graph


def relations(nodes: DataFrame) -> DataFrame:
    return nodes.groupBy("rel").agg(F.count(F.lit(1)).alias("n_nodes"))


def neighbours(graph: Graph, key: str, page: int = 0, size: int = 20) -> DataFrame:
    """(etype, direction, node_key): what a tuple points at and what points at it, in pages."""
    own = graph.nodes.where(F.col("node_key") == key).select(F.col("node_id").alias("src"))
    near = graph.edges.join(F.broadcast(own), "src").select(F.col("dst").alias("node_id"), "etype", "direction")
    return near.join(graph.nodes.select("node_id", "node_key"), "node_id").select("etype", "direction", "node_key").orderBy("etype", "direction", "node_key").offset(page * size).limit(size)
