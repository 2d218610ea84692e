"""Relations, references between them, and their discovery."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import prepare


@dataclass(frozen=True)
class Relation:
    name: str
    code: int
    key: tuple[str, ...]
    text: tuple[str, ...]


@dataclass(frozen=True)
class Reference:
    """Rows of ``child`` point at the row of ``parent`` whose key equals ``column``."""

    child: str
    column: str
    parent: str
    similarity: float = 1.0
    kind: str = "key"

    @property
    def etype(self) -> str:
        return f"{self.child}>{self.parent}"


# The given tables. Codes order relations and are the high bits of node ids.
RELATIONS = {
    r.name: r
    for r in (
        Relation("region", 1, ("r_regionkey",), ("r_name",)),
        Relation("nation", 2, ("n_nationkey",), ("n_name",)),
        Relation("customer", 3, ("c_custkey",), ("c_name", "c_mktsegment")),
        Relation("supplier", 4, ("s_suppkey",), ("s_name",)),
        Relation("part", 5, ("p_partkey",), ("p_name", "p_brand", "p_type")),
        Relation("orders", 6, ("o_orderkey",), ("o_orderstatus", "o_orderpriority")),
    )
}
LINK = Relation("lineitem", 7, ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"), ("l_returnflag", "l_linestatus"))
REFERENCES = (
    Reference("nation", "n_regionkey", "region"),
    Reference("customer", "c_nationkey", "nation"),
    Reference("supplier", "s_nationkey", "nation"),
    Reference("orders", "o_custkey", "customer"),
)
LINK_REFERENCES = (Reference("lineitem", "l_orderkey", "orders"), Reference("lineitem", "l_partkey", "part"), Reference("lineitem", "l_suppkey", "supplier"))
INCLUSIONS = (Reference("events", "user_id", "customer", kind="inclusion"), Reference("labels", "doc_id", "documents", kind="inclusion"))
KEY_BITS = 56


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return prepare(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def relation_graph(spark: SparkSession, references: tuple[Reference, ...] = REFERENCES + LINK_REFERENCES) -> DataFrame:
    """Undirected graph of relations: one row for each direction of each reference."""
    pairs = sorted({(a, b) for r in references for a, b in ((r.child, r.parent), (r.parent, r.child))})
    return spark.createDataFrame(pairs, "relation string, neighbour string")


def is_key(df: DataFrame, columns: tuple[str, ...]) -> bool:
    """Whether no two rows agree in the columns."""
    return df.groupBy(*columns).count().where("count > 1").isEmpty()


def discover_inclusions(child: DataFrame, column: str, parent: DataFrame, key: str) -> DataFrame:
    """One row: distinct child values, those missing in the parent, and whether the inclusion holds."""
    values = child.select(F.col(column).alias("v")).where("v is not null").distinct()
    missing = values.join(parent.select(F.col(key).alias("v")).distinct(), "v", "left_anti").agg(F.count(F.lit(1)).alias("missing"))
    return values.agg(F.count(F.lit(1)).alias("n_values")).crossJoin(missing).withColumn("holds", F.col("missing") == 0)  # one row each


def discover_references(spark: SparkSession, sf_dir: str, pairs: list[tuple[str, str, str, str]]) -> DataFrame:
    """(child, column, parent, key, n_values, missing, holds) for candidate pairs; each is one anti join."""
    out = None
    for child, column, parent, key in pairs:
        row = discover_inclusions(table(spark, sf_dir, child), column, table(spark, sf_dir, parent), key)
        row = row.select(F.lit(child).alias("child"), F.lit(column).alias("column_name"), F.lit(parent).alias("parent"), F.lit(key).alias("parent_key"), "n_values", "missing", "holds")
        out = row if out is None else out.unionByName(row)
    return out
