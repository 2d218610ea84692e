"""Two-phase search: search the graph of clusters, expand the clusters of its answers, search the expanded part.

With extensions: fetch more on a drop of scores, spend spare memory on keyword or neighbour clusters, keep some clusters
whole in a mixed graph.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import search
from ..operators.graph import Graph
from ..operators.quotient import labelled, quotient
from .loop import cut, few

LIMIT, GAMMA = 100, 0.5


def cluster_matches(matches: DataFrame, membership: DataFrame) -> DataFrame:
    return matches.join(membership, "node_id").select("query_id", "term", F.col("cluster_id").alias("node_id")).distinct()


def phase1(small: Graph, matches: DataFrame, membership: DataFrame, queries: DataFrame, limit: int = LIMIT, algorithm: str = "bidirectional") -> DataFrame:
    """Up to ``limit`` artificial answers of each query."""
    return search.whole_search(small, cluster_matches(matches, membership), queries, algorithm, k=limit, limit=limit)


def clusters_of(answers: DataFrame) -> DataFrame:
    """(query_id, cluster_id, reason) of all clusters in artificial answers."""
    ends = F.flatten(F.transform("tree", lambda e: F.split(e, ">").cast("array<long>")))
    return answers.select("query_id", F.explode(F.array_union(F.array("root"), ends)).alias("cluster_id")).distinct().withColumn("reason", F.lit("answer"))


def induce(graph: Graph, membership: DataFrame, chosen: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges and nodes of each query's chosen clusters; an edge stays if both its ends do."""
    ids = chosen.select("query_id", "cluster_id").distinct()
    own = few(cut(membership.join(ids, "cluster_id").select("query_id", "node_id")))
    sources, targets = own.withColumnRenamed("node_id", "src"), own.withColumnRenamed("node_id", "dst")
    edges = graph.edges.select("src", "dst", "weight").join(sources, "src").join(targets, ["query_id", "dst"]).select("query_id", "src", "dst", "weight")
    nodes = own.join(graph.nodes.select("node_id", "prestige"), "node_id").select("query_id", "node_id", "prestige")
    return edges, nodes


def phase2(graph: Graph, membership: DataFrame, chosen: DataFrame, matches: DataFrame, k: int = 10, algorithm: str = "bidirectional") -> DataFrame:
    edges, nodes = induce(graph, membership, chosen)
    inside = matches.join(nodes.select("query_id", "node_id"), ["query_id", "node_id"], "left_semi")
    full = matches.groupBy("query_id").agg(F.count_distinct("term").alias("n"))
    whole = inside.groupBy("query_id").agg(F.count_distinct("term").alias("n")).join(full, ["query_id", "n"]).select("query_id")
    return search.local_search(inside.join(whole, "query_id", "left_semi"), edges.join(whole, "query_id", "left_semi"), nodes.join(whole, "query_id", "left_semi"), algorithm, k=k)


def two_phase(graph: Graph, membership: DataFrame, matches: DataFrame, queries: DataFrame, k: int = 10, limit: int = LIMIT, algorithms: tuple[str, str] = ("bidirectional", "bidirectional"), weight: str = "inverse_sum", prestige: str = "sum") -> tuple[DataFrame, DataFrame, DataFrame]:
    """(answers, artificial answers, trace); the trace has (query_id, phase, touched, explored)."""
    small = quotient(graph, membership, weight, prestige)
    small = Graph(cut(small.nodes), cut(small.edges, "dst"))
    artificial = cut(phase1(small, matches, membership, queries, limit, algorithms[0]))
    real = cut(phase2(graph, membership, clusters_of(artificial), matches, k, algorithms[1]))
    counted = lambda a, p: a.groupBy("query_id").agg(F.max("touched").alias("touched"), F.max("explored").alias("explored")).select("query_id", F.lit(p).cast("long").alias("phase"), "touched", "explored")
    return real, artificial, counted(artificial, 1).unionByName(counted(real, 2))


def should_fetch(answers: DataFrame, gamma: float = GAMMA) -> DataFrame:
    """(query_id, rnk, drop): where the next score falls to ``gamma`` of the one before or below."""
    before = F.lag("tree_score").over(Window.partitionBy("query_id").orderBy("rnk"))
    return answers.withColumn("before", before).where(F.col("before").isNotNull()).select("query_id", "rnk", (F.col("tree_score") <= gamma * F.col("before")).alias("drop"))


def limit_for(origin: DataFrame, small: int = 100, large: int = 400, cut_at: int = 5000) -> DataFrame:
    """(query_id, n_limit): more first-phase answers for queries with a large keyword set."""
    return origin.groupBy("query_id").agg(F.when(F.max("origin") >= cut_at, large).otherwise(small).alias("n_limit"))


def interleaved(graph: Graph, membership: DataFrame, matches: DataFrame, queries: DataFrame, k: int = 10, limit: int = 25, gamma: float = GAMMA, max_rounds: int = 3) -> DataFrame:
    """Both phases again with twice the limit while some query's scores drop."""
    answers = None
    for r in range(max_rounds):
        answers, _, _ = two_phase(graph, membership, matches, queries, k, limit * 2**r)
        if should_fetch(answers, gamma).where("drop").isEmpty():
            break
    return answers


def keyword_clusters(matches: DataFrame, membership: DataFrame, sizes: DataFrame, chosen: DataFrame, memory: int, seed: int = 0) -> DataFrame:
    """Clusters that hold a keyword and are not chosen yet, in random order while they fit ``memory`` bytes.

    sizes: (cluster_id, bytes).
    """
    own = matches.join(membership, "node_id").select("query_id", "cluster_id").distinct().join(chosen.select("query_id", "cluster_id"), ["query_id", "cluster_id"], "left_anti").join(sizes, "cluster_id")
    running = F.sum("bytes").over(Window.partitionBy("query_id").orderBy(F.md5(F.concat(F.lit(f"{seed}:"), F.col("cluster_id").cast("string")).cast("binary"))))
    return own.withColumn("used", running).where(F.col("used") <= memory).select("query_id", "cluster_id", F.lit("keyword").alias("reason"))


def keyword_nodes(matches: DataFrame) -> DataFrame:
    """(query_id, node_id): matched nodes without their clusters."""
    return matches.select("query_id", "node_id").distinct()


def neighbours(chosen: DataFrame, super_edges: DataFrame, per_cluster: int = 1) -> DataFrame:
    """Clusters beside the chosen ones, the nearest ``per_cluster`` of each."""
    near = chosen.select("query_id", F.col("cluster_id").alias("src_c")).join(super_edges.select("src_c", "dst_c", "weight"), "src_c")
    new = near.join(chosen.select("query_id", F.col("cluster_id").alias("dst_c")), ["query_id", "dst_c"], "left_anti")
    order = Window.partitionBy("query_id", "src_c").orderBy("weight", "dst_c")
    return new.withColumn("r", F.row_number().over(order)).where(F.col("r") <= per_cluster).select("query_id", F.col("dst_c").alias("cluster_id"), F.lit("neighbour").alias("reason")).distinct()


def parallel_clusters(matches: DataFrame, second: DataFrame, membership: DataFrame) -> DataFrame:
    """Clusters of the first clustering that meet a cluster of a second one (by activation) with a matched node."""
    hit = matches.join(second.withColumnRenamed("cluster_id", "page"), "node_id").select("query_id", "page").distinct()
    return hit.join(second.withColumnRenamed("cluster_id", "page"), "page").join(membership, "node_id").select("query_id", "cluster_id", F.lit("activation").alias("reason")).distinct()


def mixed(graph: Graph, membership: DataFrame, expanded: DataFrame, weight: str = "inverse_sum") -> Graph:
    """A graph in which the clusters of ``expanded`` (cluster_id) are their nodes and all others stay single nodes."""
    ids = expanded.select("cluster_id").distinct().withColumn("open", F.lit(True))
    override = membership.join(ids, "cluster_id", "left").select("node_id", F.when(F.col("open"), F.col("node_id")).otherwise(F.col("cluster_id")).alias("cluster_id"))
    return quotient(graph, override, weight)


def normalised(mixed_graph: Graph, expanded_nodes: DataFrame) -> Graph:
    """Prestige as a share of the largest of its granularity, so that clusters do not outrank tuples by size alone."""
    fine = mixed_graph.nodes.join(expanded_nodes.select("node_id").withColumn("fine", F.lit(True)), "node_id", "left").withColumn("fine", F.coalesce("fine", F.lit(False)))
    most = fine.groupBy("fine").agg(F.greatest(F.max("prestige"), F.lit(1e-300)).alias("m"))
    return Graph(fine.join(F.broadcast(most), "fine").withColumn("prestige", F.col("prestige") / F.col("m")).drop("m", "fine"), mixed_graph.edges)


def iterate_mixed(graph: Graph, membership: DataFrame, matches: DataFrame, queries: DataFrame, k: int = 10, rounds: int = 3) -> DataFrame:
    """Search a mixed graph, expand the clusters of its answers, and again, until answers are made of tuples."""
    expanded = membership.select("cluster_id").limit(0)
    answers = None
    for _ in range(rounds):
        small = mixed(graph, membership, expanded)
        small = Graph(cut(small.nodes), cut(small.edges))
        ids = expanded.withColumn("open", F.lit(True))
        at = membership.join(ids, "cluster_id", "left").select("node_id", F.when(F.col("open"), F.col("node_id")).otherwise(F.col("cluster_id")).alias("place"))
        own = matches.join(at, "node_id").select("query_id", "term", F.col("place").alias("node_id")).distinct()
        answers = cut(search.whole_search(small, own, queries, k=k))
        seen = clusters_of(answers).select("cluster_id").distinct().join(membership.select("cluster_id").distinct(), "cluster_id", "left_semi")
        new = cut(expanded.select("cluster_id").union(seen).distinct())
        if new.join(expanded, "cluster_id", "left_anti").isEmpty():
            break
        expanded = new
    return answers


def phantoms(artificial: DataFrame, real: DataFrame) -> DataFrame:
    """(query_id, n_artificial, n_real, phantom): queries with artificial answers and no real one."""
    a = artificial.groupBy("query_id").agg(F.count(F.lit(1)).alias("n_artificial"))
    r = real.groupBy("query_id").agg(F.count(F.lit(1)).alias("n_real"))
    return a.join(r, "query_id", "left").select("query_id", "n_artificial", F.coalesce("n_real", F.lit(0)).alias("n_real"), F.col("n_real").isNull().alias("phantom"))


def suggest(history: DataFrame, queries: DataFrame, per_term: int = 3) -> DataFrame:
    """(query_id, cluster_id, reason): the clusters that earlier answers to the same terms used most; history (term, cluster_id, hits)."""
    best = history.withColumn("r", F.row_number().over(Window.partitionBy("term").orderBy(F.desc("hits"), "cluster_id"))).where(F.col("r") <= per_term)
    return best.join(F.broadcast(queries), "term").select("query_id", "cluster_id", F.lit("adaptive").alias("reason")).distinct()


def clusters_read(chosen: DataFrame, graph: Graph, membership: DataFrame) -> DataFrame:
    """(query_id, n_clusters, bytes) of an expansion, by the slim memory model."""
    edges = labelled(graph.edges, membership).where("src_c = dst_c").groupBy(F.col("src_c").alias("cluster_id")).agg(F.count(F.lit(1)).alias("e"))
    sizes = membership.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("v")).join(edges, "cluster_id", "left").select("cluster_id", (9 * F.col("v") + 8 * F.coalesce("e", F.lit(0))).alias("bytes"))
    return chosen.select("query_id", "cluster_id").distinct().join(sizes, "cluster_id").groupBy("query_id").agg(F.count(F.lit(1)).alias("n_clusters"), F.sum("bytes").alias("bytes"))
