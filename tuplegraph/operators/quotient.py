"""The graph of clusters: super-edges, their weights, cluster prestige, and the superedge graphs between clusters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.loop import cut, dealt
from .graph import Graph


def labelled(edges: DataFrame, membership: DataFrame) -> DataFrame:
    """Edges with the clusters of both ends; stored edges lie in buckets of their target, so only the sources are shuffled."""
    source = membership.select(F.col("node_id").alias("src"), F.col("cluster_id").alias("src_c"))
    target = membership.select(F.col("node_id").alias("dst"), F.col("cluster_id").alias("dst_c"))
    return edges.join(target, "dst").join(source, "src")


def super_edges(edges: DataFrame, membership: DataFrame, weight: str = "inverse_sum") -> DataFrame:
    """(src_c, dst_c, n_links, weight, min_link) for pairs of clusters with an edge between them.

    inverse_sum: parallel resistance of the links; harmonic: that times their number; min: the least.
    """
    grouped = labelled(edges, membership).where("src_c <> dst_c").groupBy("src_c", "dst_c")
    rows = grouped.agg(F.count(F.lit(1)).alias("n_links"), F.sum(1 / F.col("weight")).alias("conductance"), F.min("weight").alias("min_link"))
    value = {"inverse_sum": 1 / F.col("conductance"), "harmonic": F.col("n_links") / F.col("conductance"), "min": F.col("min_link")}[weight]
    return rows.select("src_c", "dst_c", "n_links", value.alias("weight"), "min_link")


def cluster_nodes(nodes: DataFrame, membership: DataFrame, prestige: str = "sum") -> DataFrame:
    """(cluster_id, n_nodes, prestige): sum, max or avg over the members."""
    how = {"sum": F.sum, "max": F.max, "avg": F.avg}[prestige]
    return nodes.join(membership, "node_id").groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n_nodes"), how("prestige").alias("prestige"))


def _super_nodes(nodes: DataFrame, membership: DataFrame, prestige: str = "sum") -> DataFrame:
    return cluster_nodes(nodes, membership, prestige).select(F.col("cluster_id").alias("node_id"), F.concat(F.lit("cluster:"), F.col("cluster_id").cast("string")).alias("node_key"), F.lit("cluster").alias("rel"), F.lit("").alias("text"), "prestige")


def _super_links(src: str, dst: str, weight: str) -> list:
    return [F.col(src).alias("src"), F.col(dst).alias("dst"), F.lit("cluster>cluster").alias("etype"), F.lit("fwd").alias("direction"), F.col(weight).alias("weight"), F.lit(1.0).alias("priority")]


def quotient(graph: Graph, membership: DataFrame, weight: str = "inverse_sum", prestige: str = "sum") -> Graph:
    """The graph whose nodes are clusters."""
    return Graph(_super_nodes(graph.nodes, membership, prestige), super_edges(graph.edges, membership, weight).select(*_super_links("src_c", "dst_c", "weight")))


def cluster_graph(nodes: DataFrame, pairs: DataFrame, membership: DataFrame) -> Graph:
    """``quotient`` by inverse sums, stored, from pairs of nodes (``cluster.two_way``) instead of edges; it has its own pairs.

    Both ways of a pair go through the shuffles as one row.
    """
    low = membership.select(F.col("node_id").alias("a"), F.col("cluster_id").alias("a_c"))
    high = membership.select(F.col("node_id").alias("b"), F.col("cluster_id").alias("b_c"))
    flows = ["flow_there", "flow_back"] if "flow_there" in pairs.columns else [(1 / F.col(c)).alias(f"flow_{c}") for c in ("there", "back")]
    rows = pairs.select("a", "b", *flows).join(low, "a").join(high, "b").where("a_c <> b_c")
    ahead = F.col("a_c") < F.col("b_c")
    there, back = (F.when(ahead, F.col(x)).otherwise(F.col(y)).alias(z) for x, y, z in (("flow_there", "flow_back", "there"), ("flow_back", "flow_there", "back")))
    sides = dealt(rows.select(F.least("a_c", "b_c").alias("a"), F.greatest("a_c", "b_c").alias("b"), there, back), "a")
    kept = cut(sides.groupBy("a", "b").agg((1 / F.sum("there")).alias("there"), (1 / F.sum("back")).alias("back")), "a", lie=True)
    edges = kept.select(*_super_links("a", "b", "there")).unionByName(kept.select(*_super_links("b", "a", "back"))).where("weight is not null")
    return Graph(cut(_super_nodes(nodes, membership)), edges, kept)


def intranode(edges: DataFrame, membership: DataFrame) -> DataFrame:
    return labelled(edges, membership).where("src_c = dst_c")


def positive(edges: DataFrame, membership: DataFrame, src_c: int, dst_c: int) -> DataFrame:
    """(src, dst): the links from one cluster to another."""
    return labelled(edges, membership).where((F.col("src_c") == src_c) & (F.col("dst_c") == dst_c)).select("src", "dst").distinct()


def negative(edges: DataFrame, membership: DataFrame, src_c: int, dst_c: int) -> DataFrame:
    """(src, dst): the links that are absent between two clusters; both are capped in size, so their product is small."""
    one = membership.where(F.col("cluster_id") == src_c).select(F.col("node_id").alias("src"))
    two = membership.where(F.col("cluster_id") == dst_c).select(F.col("node_id").alias("dst"))
    return one.crossJoin(F.broadcast(two)).join(positive(edges, membership, src_c, dst_c), ["src", "dst"], "left_anti")


def polarity(edges: DataFrame, membership: DataFrame) -> DataFrame:
    """(src_c, dst_c, n_positive, n_negative, chosen): which of the two superedge graphs is smaller."""
    sizes = membership.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"))
    links = labelled(edges, membership).where("src_c <> dst_c").select("src", "dst", "src_c", "dst_c").distinct().groupBy("src_c", "dst_c").agg(F.count(F.lit(1)).alias("n_positive"))
    rows = links.join(sizes.select(F.col("cluster_id").alias("src_c"), F.col("n").alias("a")), "src_c").join(sizes.select(F.col("cluster_id").alias("dst_c"), F.col("n").alias("b")), "dst_c")
    less = F.col("a") * F.col("b") - F.col("n_positive")
    return rows.select("src_c", "dst_c", "n_positive", less.alias("n_negative"), F.when(F.col("n_positive") <= less, "positive").otherwise("negative").alias("chosen"))


def update(old: DataFrame, edges: DataFrame, membership: DataFrame, touched: DataFrame, weight: str = "inverse_sum") -> DataFrame:
    """Super-edges after a split: those of ``touched`` (cluster_id, old and new names) are computed anew, the others kept."""
    ids = touched.select("cluster_id").distinct()
    source, target = ids.withColumnRenamed("cluster_id", "src_c"), ids.withColumnRenamed("cluster_id", "dst_c")
    kept = old.join(source, "src_c", "left_anti").join(target, "dst_c", "left_anti")
    new = super_edges(edges, membership, weight)
    changed = new.join(source, "src_c", "left_semi").unionByName(new.join(source, "src_c", "left_anti").join(target, "dst_c", "left_semi"))
    return kept.unionByName(changed.select(*kept.columns))
