"""Answer trees: assembly, scores, minimality, duplicates, ranking, text."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scores import LAMBDA, edge_score, node_score, tree_score
from ..plans.loop import cut, few


def assemble(ways: DataFrame, graph_edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """(query_id, root, leaves, tree, members, total, root_weight, leaf_weight) from ``search.paths`` rows.

    Shared edges count once. leaves are the distinct ends of the ways; tree holds ``src>dst`` of each edge in order.
    """
    steps = cut(ways.where("src <> dst").select("query_id", "root", "src", "dst").distinct())
    real = few(steps).join(graph_edges.select("src", "dst", "weight"), ["src", "dst"]).groupBy("query_id", "root", "src", "dst").agg(F.min("weight").alias("w"))
    trees = real.groupBy("query_id", "root").agg(
        F.array_sort(F.collect_list(F.concat_ws(">", F.col("src").cast("string"), F.col("dst").cast("string")))).alias("tree"),
        F.sum("w").alias("total"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_list(F.array("src", "dst"))))).alias("members"),
        F.count_if(F.col("src") == F.col("root")).alias("branches"),
    )
    prestige = nodes.select("node_id", "prestige", "node_key")
    held = cut(ways.where("src = dst").select("query_id", "root", F.col("src").alias("node_id")).distinct())
    ends = few(held).join(prestige, "node_id")
    leaves = ends.groupBy("query_id", "root").agg(F.array_sort(F.collect_list("node_id")).alias("leaves"), F.array_sort(F.collect_list("node_key")).alias("leaf_list"), F.sum("prestige").alias("leaf_weight"))
    out = leaves.join(trees, ["query_id", "root"], "left").join(prestige.select(F.col("node_id").alias("root"), F.col("prestige").alias("root_weight"), F.col("node_key").alias("root_key")), "root")
    return out.select(
        "query_id", "root", "root_key", "leaves", F.array_join("leaf_list", ",").alias("leaf_keys"),
        F.coalesce("tree", F.array().cast("array<string>")).alias("tree"), F.coalesce("members", F.array("root")).alias("members"),
        F.coalesce("total", F.lit(0.0)).alias("total"), F.coalesce("branches", F.lit(0)).alias("branches"), "root_weight", "leaf_weight",
    )


def score(answers: DataFrame, mode: str = "product", edge: str = "proximity", lam: float = LAMBDA) -> DataFrame:
    single = F.size("tree") == 0
    scored = answers.withColumn("node_score", node_score(F.col("root_weight"), F.col("leaf_weight"), single)).withColumn("edge_score", edge_score(F.col("total"), edge))
    return scored.withColumn("tree_score", tree_score(F.col("edge_score"), F.col("node_score"), mode, lam))


def root_minimal(answers: DataFrame) -> DataFrame:
    """Answers whose root has two branches, or holds a keyword."""
    return answers.where((F.col("branches") != 1) | F.array_contains("leaves", F.col("root")))


def subset_minimal(answers: DataFrame) -> DataFrame:
    """Answers that strictly contain no other answer of their query. Candidates meet on a shared node, the smaller one's root."""
    other = answers.select("query_id", F.col("members").alias("inner"), F.col("root").alias("inner_root"))
    holder = answers.select("query_id", "root", "tree", "members", F.explode("members").alias("inner_root"))
    bad = holder.join(other, ["query_id", "inner_root"]).where((F.size("inner") < F.size("members")) & (F.size(F.array_except("inner", "members")) == 0)).select("query_id", "root", "tree").distinct()
    return answers.join(bad, ["query_id", "root", "tree"], "left_anti")


def identity(answers: DataFrame) -> DataFrame:
    """With ``tree_hash``: of the undirected edges, or of the node alone."""
    ends = F.transform("tree", lambda e: F.array_join(F.array_sort(F.split(e, ">")), "-"))
    return answers.withColumn("tree_hash", F.md5(F.when(F.size("tree") == 0, F.col("root").cast("string")).otherwise(F.array_join(F.array_sort(ends), ","))))


def dedupe(answers: DataFrame) -> DataFrame:
    """Of answers with equal edges, the best scored; needs ``tree_score``."""
    order = Window.partitionBy("query_id", "tree_hash").orderBy(F.desc(F.round("tree_score", 9)), "root")
    return identity(answers).withColumn("_r", F.row_number().over(order)).where("_r = 1").drop("_r")


def rank(answers: DataFrame, k: int = 10) -> DataFrame:
    """The k best of each query; ties by root, then leaves."""
    order = Window.partitionBy("query_id").orderBy(F.desc(F.round("tree_score", 9)), "root", "leaf_keys")
    return answers.withColumn("rnk", F.row_number().over(order).cast("long")).where(F.col("rnk") <= k)


def emit(answers: DataFrame, bound: DataFrame) -> DataFrame:
    """Answers whose score reaches the best that an unseen one can have: ``bound`` (query_id, best_unseen), one row a query."""
    return answers.join(F.broadcast(bound), "query_id").where(F.col("tree_score") >= F.col("best_unseen")).drop("best_unseen")


def unseen_bound(frontier_cost: DataFrame, most_node: float, lam: float = LAMBDA) -> DataFrame:
    """(query_id, best_unseen) from the least cost that the frontier has left: no unseen tree weighs less."""
    return frontier_cost.select("query_id", (1 / (1 + F.col("cost")) * F.pow(F.lit(most_node), F.lit(lam))).alias("best_unseen"))


def render(answers: DataFrame, nodes: DataFrame) -> DataFrame:
    """(query_id, rnk, node_key, text) of every node of each answer."""
    each = answers.select("query_id", "rnk", F.explode("members").alias("node_id"))
    return each.join(nodes.select("node_id", "node_key", "text"), "node_id").select("query_id", "rnk", "node_key", "text")


def report(answers: DataFrame) -> DataFrame:
    return answers.select("query_id", "rnk", "root_key", "leaf_keys", F.size("members").cast("long").alias("n_nodes"), F.size("tree").cast("long").alias("n_edges"), F.round("node_score", 6).alias("node_score"), F.round("edge_score", 6).alias("edge_score"), F.round("tree_score", 6).alias("tree_score"))
