"""Connected components by least labels and label jumps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.loop import cut, dealt, drop


def components(links: DataFrame, max_rounds: int = 40) -> DataFrame:
    """(node, label) for the ends of links (a, b): the least node that is reachable. The driver sees one flag a round."""
    turned = F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b"))))  # both from one evaluation
    both = cut(dealt(links.where("a <> b").select(turned.alias("e")).select("e.a", "e.b"), "b").distinct(), "b", lie=True)
    before = state = cut(both.groupBy(F.col("b").alias("node")).agg(F.least(F.min("a"), F.min("b")).alias("label")))  # each link is there both ways
    for _ in range(max_rounds):
        near = both.join(state.withColumnRenamed("node", "b").hint("shuffle_hash"), "b").groupBy(F.col("a").alias("node")).agg(F.min("label").alias("near"))
        step = state.hint("merge").join(near, "node").select("node", "label", F.least("label", "near").alias("to"))
        jump = state.select(F.col("node").alias("to"), F.col("label").alias("far"))
        moved = cut(step.hint("merge").join(jump, "to", "left").select("node", F.least("to", F.coalesce("far", "to")).alias("new"), "label"))
        drop(before)
        before, state = moved, moved.select("node", F.col("new").alias("label"))
        if moved.where("new <> label").isEmpty():
            drop(both)
            return state
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
