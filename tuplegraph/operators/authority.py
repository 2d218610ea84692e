"""Random-walk authority: one rank for all queries, one for each keyword, and their combination."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.loop import cut

DAMPING = 0.85


def transfer(edges: DataFrame) -> DataFrame:
    """(src, dst, share): each edge's part of what its source passes on."""
    degree = edges.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    return edges.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n")).join(degree, "src").select("src", "dst", (F.col("n") / F.col("deg")).alias("share"))


def global_rank(nodes: DataFrame, edges: DataFrame, damping: float = DAMPING, rounds: int = 20, tolerance: float | None = None) -> DataFrame:
    """(node_id, rank), summing to one; what dangling nodes hold goes to all."""
    links = cut(transfer(edges))
    ids = cut(nodes.select("node_id"))
    n = ids.count()
    state = ids.withColumn("rank", F.lit(1.0 / max(1, n)))
    for _ in range(rounds):
        given = state.join(links, F.col("node_id") == F.col("src")).groupBy(F.col("dst").alias("node_id")).agg(F.sum(F.col("rank") * F.col("share")).alias("got"))
        lost = F.broadcast(state.join(links.select(F.col("src").alias("node_id")).distinct(), "node_id", "left_anti").agg(F.coalesce(F.sum("rank"), F.lit(0.0)).alias("lost")))
        new = ids.join(given, "node_id", "left").crossJoin(lost).select("node_id", ((1 - damping) / n + damping * (F.coalesce("got", F.lit(0.0)) + F.col("lost") / n)).alias("rank"))  # lost: one row
        new = cut(new)
        if tolerance is not None:
            moved = new.join(state.withColumnRenamed("rank", "old"), "node_id").agg(F.sum(F.abs(F.col("rank") - F.col("old")))).first()[0]
            state = new
            if moved < tolerance:
                break
        state = new
    return state


def keyword_rank(edges: DataFrame, matches: DataFrame, damping: float = DAMPING, rounds: int = 8, cutoff: float = 0.0) -> DataFrame:
    """(term, node_id, rank): walks that restart at the keyword's nodes only; ranks below ``cutoff`` are dropped each round."""
    links = cut(transfer(edges))
    origins = matches.select("term", "node_id").distinct()
    base = cut(origins.join(origins.groupBy("term").agg(F.count(F.lit(1)).alias("n")), "term").select("term", "node_id", (1.0 / F.col("n")).alias("base")))
    state = base.select("term", "node_id", F.col("base").alias("rank"))
    for _ in range(rounds):
        given = state.join(links, F.col("node_id") == F.col("src")).select("term", F.col("dst").alias("node_id"), (damping * F.col("rank") * F.col("share")).alias("rank"))
        start = base.select("term", "node_id", ((1 - damping) * F.col("base")).alias("rank"))
        state = cut(given.unionByName(start).groupBy("term", "node_id").agg(F.sum("rank").alias("rank")).where(F.col("rank") >= cutoff))
    return state


def score(keyword: DataFrame, overall: DataFrame, how: str = "product", share: float = 0.5) -> DataFrame:
    """(term, node_id, score) from both ranks: their product, or a weighted sum."""
    both = keyword.join(overall.withColumnRenamed("rank", "overall"), "node_id")
    value = F.col("rank") * F.col("overall") if how == "product" else share * F.col("rank") + (1 - share) * F.col("overall")
    return both.select("term", "node_id", value.alias("score"))


def combine(scores: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, node_id, score): product over the query's terms; a node without one of them has no score."""
    wanted = queries.groupBy("query_id").agg(F.count_distinct("term").alias("n"))
    rows = scores.join(F.broadcast(queries), "term").where("score > 0").groupBy("query_id", "node_id").agg(F.count(F.lit(1)).alias("n"), F.exp(F.sum(F.log("score"))).alias("score"))
    return rows.join(F.broadcast(wanted), ["query_id", "n"]).select("query_id", "node_id", "score")


def precompute(keyword: DataFrame, path: str, buckets: int = 64) -> None:
    """Ranked lists by term, in buckets of terms."""
    rows = keyword.withColumn("bucket", F.pmod(F.xxhash64("term"), F.lit(buckets)).cast("int"))
    rows.repartition(buckets, "bucket").sortWithinPartitions("term", F.desc("rank")).write.mode("overwrite").partitionBy("bucket").parquet(path)


def near_objects(distances: DataFrame, nodes: DataFrame, find_rel: str, k: int = 10) -> DataFrame:
    """(query_id, node_id, cost): tuples of one relation by the sum of their unit distances to the keywords' nodes."""
    own = nodes.where(F.col("rel") == find_rel).select("node_id")
    return distances.join(own, "node_id", "left_semi").groupBy("query_id", "node_id").agg(F.count(F.lit(1)).alias("n_terms"), F.sum("dist").alias("cost"))
