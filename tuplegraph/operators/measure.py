"""Measures of memory, work and accuracy."""

from __future__ import annotations

import time

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .graph import Graph
from .quotient import labelled


def memory(v: Column | float, e: Column | float, model: str = "full", mapping: bool = False, drop: int = 0):
    """Bytes of a graph: full, five numbers a node and three an edge; slim, nine bytes a node and eight an edge.

    ``mapping`` adds four bytes a node, ``drop`` takes four bytes a node for each array that degrees derived from offsets save.
    """
    size = 20 * v + 12 * e if model == "full" else 9 * v + 8 * e
    return size + (4 * v if mapping else 0 * v) - 4 * drop * v


def counts(graph: Graph) -> DataFrame:
    """(n_nodes, n_edges) in one row."""
    return graph.nodes.agg(F.count(F.lit(1)).alias("n_nodes")).crossJoin(graph.edges.agg(F.count(F.lit(1)).alias("n_edges")))


def reduction(full: Graph, small: Graph) -> DataFrame:
    """(node_ratio, edge_ratio) in one row."""
    a, b = counts(full), counts(small).toDF("v", "e")
    return a.crossJoin(b).select((F.col("n_nodes") / F.col("v")).alias("node_ratio"), (F.col("n_edges") / F.col("e")).alias("edge_ratio"))


def timed(make) -> tuple[DataFrame, float]:
    """A DataFrame and the seconds until all its rows are there."""
    began = time.perf_counter()
    out = make().persist()
    out.count()
    return out, time.perf_counter() - began


def tree_key(answers: DataFrame) -> DataFrame:
    """Answers with ``tree_hash`` of their undirected edges (or single node)."""
    ends = F.transform("tree", lambda e: F.array_join(F.array_sort(F.split(e, ">")), "-"))
    return answers.withColumn("tree_hash", F.md5(F.when(F.size("tree") == 0, F.col("root").cast("string")).otherwise(F.array_join(F.array_sort(ends), ",")).cast("binary")))


def precision(answers: DataFrame, reference: DataFrame, k: int = 10) -> DataFrame:
    """(query_id, n_exact, n_score): of the k best, how many trees the reference's k best have too; and how many scores, as multisets."""
    a, r = (tree_key(x.where(F.col("rnk") <= k)) for x in (answers, reference))
    same = a.select("query_id", "tree_hash").intersect(r.select("query_id", "tree_hash")).groupBy("query_id").agg(F.count(F.lit(1)).alias("n_exact"))
    score = lambda x: x.select("query_id", F.round("tree_score", 6).alias("s"))
    equal = score(a).intersectAll(score(r)).groupBy("query_id").agg(F.count(F.lit(1)).alias("n_score"))
    ids = reference.select("query_id").distinct()
    return ids.join(same, "query_id", "left").join(equal, "query_id", "left").select("query_id", F.coalesce("n_exact", F.lit(0)).alias("n_exact"), F.coalesce("n_score", F.lit(0)).alias("n_score"))


def acceptable(answers: DataFrame, reference: DataFrame, k: int = 10) -> DataFrame:
    """(query_id, n_acceptable): of the k best, how many have no more nodes and edges than the largest of the reference's k best."""
    most = reference.where(F.col("rnk") <= k).groupBy("query_id").agg(F.max("n_nodes").alias("max_nodes"), F.max("n_edges").alias("max_edges"))
    own = answers.where(F.col("rnk") <= k).select("query_id", "n_nodes", "n_edges")
    return most.join(own, "query_id", "left").groupBy("query_id").agg(F.count_if((F.col("n_nodes") <= F.col("max_nodes")) & (F.col("n_edges") <= F.col("max_edges"))).alias("n_acceptable"))


def quality(answers: DataFrame, epsilon: float = 0.05) -> DataFrame:
    """(query_id, rnk, gap, good): how far each score is below the query's best."""
    best = F.max("tree_score").over(Window.partitionBy("query_id"))
    return answers.select("query_id", "rnk", (best - F.col("tree_score")).alias("gap"), ((best - F.col("tree_score")) <= epsilon).alias("good"))


def compare_clusterings(results: DataFrame, memory_limit: int, top: int = 5) -> DataFrame:
    """(clustering, quality_sum, seconds, place): by the scores of the ``top`` best answers, less time first among equals.

    results: (clustering, query_id, rnk, tree_score, seconds, bytes); clusterings above the limit do not take part.
    """
    fits = results.where(F.col("bytes") <= memory_limit)
    sums = fits.where(F.col("rnk") <= top).groupBy("clustering").agg(F.round(F.sum("tree_score"), 6).alias("quality_sum"), F.max("seconds").alias("seconds"))
    return sums.withColumn("place", F.row_number().over(Window.orderBy(F.desc("quality_sum"), "seconds", "clustering")))  # a row for each clustering


def score_gap(answers: DataFrame) -> DataFrame:
    """(query_id, rnk, ratio) of each score to the one before."""
    before = F.lag("tree_score").over(Window.partitionBy("query_id").orderBy("rnk"))
    return answers.select("query_id", "rnk", F.when(before > 0, F.col("tree_score") / before).alias("ratio"))


def bound_coverage(rows: DataFrame) -> DataFrame:
    """Share of answers whose real cost lies within its bounds; rows (lower, cost, upper)."""
    return rows.agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("cost").between(F.col("lower"), F.col("upper")).cast("double")).alias("covered"))


def tightness(edges: DataFrame, membership: DataFrame, alpha: float) -> DataFrame:
    """(node_id, cluster_id, tightness, tight): weight of a member's edges into its own cluster over the cluster's size."""
    size = membership.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"))
    inner = labelled(edges, membership).where("src_c = dst_c").groupBy(F.col("src").alias("node_id")).agg(F.sum("weight").alias("w"))
    rows = membership.join(inner, "node_id", "left").join(size, "cluster_id")
    value = F.coalesce("w", F.lit(0.0)) / F.col("n")
    return rows.select("node_id", "cluster_id", value.alias("tightness"), (value >= alpha).alias("tight"))


def cut_report(edges: DataFrame, membership: DataFrame) -> DataFrame:
    """(place, n_edges, mean_weight) inside clusters and across."""
    where = F.when(F.col("src_c") == F.col("dst_c"), "inside").otherwise("across")
    return labelled(edges, membership).groupBy(where.alias("place")).agg(F.count(F.lit(1)).alias("n_edges"), F.round(F.avg("weight"), 6).alias("mean_weight"))


def objective(graph: Graph, membership: DataFrame) -> DataFrame:
    """(n_clusters, largest, slim_bytes) of a clustering, in one row."""
    sizes = membership.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"))
    pairs = labelled(graph.edges, membership).where("src_c <> dst_c").select("src_c", "dst_c").distinct().agg(F.count(F.lit(1)).alias("e"))
    return sizes.agg(F.count(F.lit(1)).alias("n_clusters"), F.max("n").alias("largest")).crossJoin(pairs).select("n_clusters", "largest", (9 * F.col("n_clusters") + 8 * F.col("e")).alias("slim_bytes"))  # one row each


def link_histogram(super_edges: DataFrame) -> DataFrame:
    """(log_links, n): super-edges by the whole log2 of their number of links."""
    return super_edges.groupBy(F.floor(F.log2("n_links")).cast("long").alias("log_links")).agg(F.count(F.lit(1)).alias("n"))


def degree_exponent(edges: DataFrame, side: str = "dst") -> DataFrame:
    """(slope, n_degrees): log-log slope of the degree histogram."""
    histogram = edges.groupBy(side).agg(F.count(F.lit(1)).alias("d")).groupBy("d").agg(F.count(F.lit(1)).alias("n"))
    return histogram.agg(F.regr_slope(F.log2("n"), F.log2("d")).alias("slope"), F.count(F.lit(1)).alias("n_degrees"))


def bits_per_edge(total_bits: DataFrame, edges: DataFrame) -> DataFrame:
    return total_bits.agg(F.sum("total_bits").alias("bits")).crossJoin(edges.agg(F.count(F.lit(1)).alias("n"))).select((F.col("bits") / F.col("n")).alias("bits_per_edge"))


def minimality(answers: DataFrame) -> DataFrame:
    """(query_id, root_violations): answers whose root has one branch and no keyword."""
    kids = F.size(F.array_distinct(F.filter(F.transform("tree", lambda e: F.split(e, ">")), lambda e: e[0] == F.col("root").cast("string"))))
    return answers.groupBy("query_id").agg(F.count_if((F.size("tree") > 0) & (kids < 2) & ~F.array_contains("leaves", F.col("root"))).alias("root_violations"))


def precompute_cost(n_terms: int, rounds: int, n_edges: int) -> int:
    """Edge visits of keyword ranks for all terms."""
    return n_terms * rounds * n_edges


def limit_sweep(by_limit: dict[int, DataFrame], reference: DataFrame) -> DataFrame:
    """(n_limit, query_id, n_acceptable) for answers at several first-phase limits."""
    out = None
    for limit, answers in sorted(by_limit.items()):
        part = acceptable(answers, reference).select(F.lit(limit).cast("long").alias("n_limit"), "query_id", "n_acceptable")
        out = part if out is None else out.unionByName(part)
    return out
