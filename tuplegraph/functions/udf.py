"""The SQL surface: views of the graph and a table function that searches a query's subgraph."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..operators.graph import Graph
from ..operators.kernels import Adjacency, bidirectional
from ..session import prepare


class KeywordSearch:
    """Rows of a query's graph in, answers out; called as keyword_search(TABLE(g) PARTITION BY query_id).

    A table function cannot open tables, so the graph is its argument: rows (query_id, kind, a, b, x, term) with kind e for
    edges, n for nodes with prestige, m for matches.
    """

    def __init__(self):
        self.query, self.edges, self.prestige, self.matches = None, [], {}, {}

    def eval(self, row):
        self.query = row["query_id"]
        if row["kind"] == "e":
            self.edges.append((row["a"], row["b"], row["x"]))
        elif row["kind"] == "n":
            self.prestige[row["a"]] = row["x"]
        else:
            self.matches.setdefault(row["term"], set()).add(row["a"])

    def terminate(self):
        if self.matches:
            answers, _, _ = bidirectional(Adjacency(self.edges), self.matches, 10, self.prestige)
            for i, a in enumerate(sorted(answers, key=lambda a: (a["cost"], a["root"]))[:10]):
                yield self.query, i + 1, a["root"], float(a["cost"]), len(a["nodes"])


def register(spark: SparkSession) -> None:
    prepare(spark)
    spark.udtf.register("keyword_search", udtf(KeywordSearch, returnType="query_id string, rnk int, root long, cost double, n_nodes int"))


def views(graph: Graph, answers: DataFrame | None = None) -> None:
    graph.nodes.createOrReplaceTempView("nodes")
    graph.edges.createOrReplaceTempView("edges")
    if answers is not None:
        answers.createOrReplaceTempView("answers")


def query_rows(edges: DataFrame, nodes: DataFrame, matches: DataFrame) -> DataFrame:
    """The table function's argument."""
    none = F.lit(None)
    return (
        edges.select("query_id", F.lit("e").alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("weight").alias("x"), none.cast("string").alias("term"))
        .unionByName(nodes.select("query_id", F.lit("n").alias("kind"), F.col("node_id").alias("a"), none.cast("long").alias("b"), F.col("prestige").alias("x"), none.cast("string").alias("term")))
        .unionByName(matches.select("query_id", F.lit("m").alias("kind"), F.col("node_id").alias("a"), none.cast("long").alias("b"), F.lit(0.0).alias("x"), "term"))
    )
