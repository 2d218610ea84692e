"""Answer scores as columns: node part, edge part, and their two combinations."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

LAMBDA = 0.2


def edge_score(total: Column, mode: str = "proximity") -> Column:
    """From the sum of edge weights. ``proximity`` falls with the sum; ``printed`` is the other published form and rises."""
    if mode == "proximity":
        return 1 / (1 + total)
    if mode == "printed":
        return F.when(total == 0, F.lit(0.0)).otherwise(1 / (1 + 1 / F.when(total == 0, 1.0).otherwise(total)))
    raise ValueError(mode)


def node_score(root: Column, leaves: Column, single: Column) -> Column:
    """Root weight plus leaf weights; a tree of one node counts its node once."""
    return F.when(single, root).otherwise(root + leaves)


def tree_score(edge: Column, node: Column, mode: str = "product", lam: float = LAMBDA) -> Column:
    if mode == "product":
        return edge * F.pow(node, F.lit(lam))
    if mode == "sum":
        return lam * node + (1 - lam) * edge
    raise ValueError(mode)


def inverse_sum(weight: Column) -> Column:
    """Aggregate: parallel resistance of the weights."""
    return 1 / F.sum(1 / weight)
