"""Spreading activation on DataFrames: (query_id, term, node_id, activation)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

MU = 0.5


def seed(matches: DataFrame, nodes: DataFrame) -> DataFrame:
    """Prestige over the size of the keyword's node set."""
    size = F.count(F.lit(1)).over(Window.partitionBy("query_id", "term"))
    return matches.join(nodes.select("node_id", "prestige"), "node_id").select("query_id", "term", "node_id", (F.col("prestige") / size).alias("activation"))


def shares(edges: DataFrame, direction: str = "in", least: bool = False) -> DataFrame:
    """(giver, taker, share): what part of the activation that a node passes on goes along each of its edges, inversely to weight.

    ``in``: to the sources of the edges that enter the giver; ``out``: to the targets of those that leave it. An edge's
    ``priority``, where there is one, multiplies its part. ``least`` adds the least weight of the edges, as ``w``.
    """
    pulls = (F.col("priority") if "priority" in edges.columns else F.lit(1.0)) / F.col("weight")
    giver, taker = ("dst", "src") if direction == "in" else ("src", "dst")
    pull = edges.groupBy(F.col(giver).alias("giver")).agg(F.sum(pulls).alias("pull"))
    links = edges.groupBy(F.col(giver).alias("giver"), F.col(taker).alias("taker")).agg(F.sum(pulls).alias("s"), *([F.min("weight").alias("w")] if least else []))
    return links.join(pull, "giver").select("giver", "taker", (F.col("s") / F.col("pull")).alias("share"), *(["w"] if least else []))


def spread(state: DataFrame, edges: DataFrame, mu: float = MU, direction: str = "in", combine: str = "max") -> DataFrame:
    """One step: a node keeps 1 - mu of its activation and passes mu on; what meets at a node is combined by max or sum."""
    kept = state.withColumn("activation", F.col("activation") * (1 - mu))
    given = state.join(shares(edges, direction), state.node_id == F.col("giver")).select("query_id", "term", F.col("taker").alias("node_id"), (mu * F.col("activation") * F.col("share")).alias("activation"))
    how = F.max if combine == "max" else F.sum
    return kept.unionByName(given).groupBy("query_id", "term", "node_id").agg(how("activation").alias("activation"))


def priority(state: DataFrame) -> DataFrame:
    """(query_id, node_id, total): activation over all keywords, the order in which nodes are taken."""
    return state.groupBy("query_id", "node_id").agg(F.sum("activation").alias("total"))


def spread_rounds(state: DataFrame, edges: DataFrame, rounds: int, batch: int, mu: float = MU, combine: str = "max", direction: str = "in") -> DataFrame:
    """Batched best-first spreading: each round only the ``batch`` most activated nodes of a query that were not taken yet pass on."""
    from ..plans.loop import cut

    state = cut(state.withColumn("taken", F.lit(False)))
    how = F.max if combine == "max" else F.sum
    part = cut(shares(edges, direction))
    for _ in range(rounds):
        order = Window.partitionBy("query_id").orderBy(F.desc("total"), "node_id")
        open_ = state.where("not taken").groupBy("query_id", "node_id").agg(F.sum("activation").alias("total"))
        picked = open_.withColumn("r", F.row_number().over(order)).where(F.col("r") <= batch).select("query_id", "node_id")
        now = state.join(picked.withColumn("now", F.lit(True)), ["query_id", "node_id"], "left").withColumn("now", F.coalesce("now", F.lit(False)))
        given = now.where("now").join(part, F.col("node_id") == F.col("giver")).select("query_id", "term", F.col("taker").alias("node_id"), (mu * F.col("activation") * F.col("share")).alias("activation"), F.lit(False).alias("taken"))
        kept = now.select("query_id", "term", "node_id", F.when(F.col("now"), F.col("activation") * (1 - mu)).otherwise(F.col("activation")).alias("activation"), (F.col("taken") | F.col("now")).alias("taken"))
        state = cut(kept.unionByName(given).groupBy("query_id", "term", "node_id").agg(how("activation").alias("activation"), F.max("taken").alias("taken")))
        if picked.isEmpty():
            break
    return state
