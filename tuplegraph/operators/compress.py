"""Compression of adjacency: prefix codes by in-degree, coding against a reference list, gaps, runs."""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def code_lengths(frequencies: dict) -> dict:
    """Length of each symbol's prefix code by its frequency; equal sums by order of creation."""
    heap = [(f, i, [s]) for i, (s, f) in enumerate(sorted(frequencies.items(), key=lambda x: (x[1], x[0])))]
    heapq.heapify(heap)
    lengths = dict.fromkeys(frequencies, 0 if len(frequencies) > 1 else 1)
    serial = len(heap)
    while len(heap) > 1:
        (f, _, a), (g, _, b) = heapq.heappop(heap), heapq.heappop(heap)
        for s in a + b:
            lengths[s] += 1
        heapq.heappush(heap, (f + g, serial, a + b))
        serial += 1
    return lengths


def huffman(edges: DataFrame, side: str = "dst", stop: bool = True) -> DataFrame:
    """(degree, n_nodes, code_bits, total_bits): codes by class of degree, then the place within the class.

    The tree is built from the histogram of degrees, which is small however large the graph is. ``side``: which end of an
    edge is coded; ``stop``: a stop symbol for each list takes part, else lists are told apart by their length.
    """
    other = "src" if side == "dst" else "dst"
    degree = edges.groupBy(side).agg(F.count(F.lit(1)).alias("degree"))
    histogram = degree.groupBy("degree").agg(F.count(F.lit(1)).alias("n_nodes"))
    lists = edges.select(other).distinct().count() if stop else 0
    rows = {r["degree"]: r["n_nodes"] for r in histogram.collect()}  # distinct degrees
    weights = {f"d{d}": d * n for d, n in rows.items()} | ({"stop": lists} if lists else {})
    lengths = code_lengths(weights)
    out = [(int(d), int(n), int(lengths[f"d{d}"] + max(0, (n - 1).bit_length())), int(d * n * (lengths[f"d{d}"] + max(0, (n - 1).bit_length())))) for d, n in sorted(rows.items())]
    if lists:
        out.append((0, int(lists), int(lengths["stop"]), int(lists * lengths["stop"])))
    return edges.sparkSession.createDataFrame(out, "degree long, n_nodes long, code_bits long, total_bits long")


def huffman_codes(spark, frequencies: dict) -> DataFrame:
    """(symbol, length, code): canonical prefix codes."""
    lengths, code, last, out = code_lengths(frequencies), 0, 0, []
    for n, s in sorted((n, s) for s, n in lengths.items()):
        code <<= n - last
        out.append((s, n, format(code, f"0{n}b")))
        code, last = code + 1, n
    return spark.createDataFrame(out, "symbol string, length int, code string")


def against(reference: Column, own: Column) -> Column:
    """struct<bits, extras>: which entries of the reference the list has, and its others."""
    return F.struct(F.array_join(F.transform(reference, lambda x: F.when(F.array_contains(own, x), "1").otherwise("0")), "").alias("bits"), F.array_except(own, reference).alias("extras"))


def restore(reference: Column, bits: Column, extras: Column) -> Column:
    return F.array_sort(F.concat(F.filter(reference, lambda x, i: F.substring(bits, i + 1, 1) == "1"), extras))


def gaps(own: Column) -> Column:
    """First entry, then differences of a sorted list."""
    return F.transform(own, lambda x, i: F.when(i == 0, x).otherwise(x - F.get(own, i - 1)))


def ungap(coded: Column) -> Column:
    return F.transform(F.sequence(F.lit(1), F.size(coded)), lambda n: F.aggregate(F.slice(coded, F.lit(1), n), F.lit(0).cast("long"), lambda s, x: s + x))


def runs(bits: Column) -> Column:
    """Lengths of equal runs of a bit string, with the first bit in front: ``1:3,1,2``."""
    cut = F.filter(F.split(F.regexp_replace(bits, "(?<=0)(?=1)|(?<=1)(?=0)", ","), ","), lambda x: x != "")
    return F.concat_ws(":", F.substring(bits, 1, 1), F.array_join(F.transform(cut, lambda x: F.length(x).cast("string")), ","))


def reference_sizes(lists: DataFrame, pairs: DataFrame) -> DataFrame:
    """(node_id, ref_id, n_shared, n_extra): what coding a list against another leaves."""
    own = lists.select("node_id", "targets")
    other = lists.select(F.col("node_id").alias("ref_id"), F.col("targets").alias("reference"))
    return pairs.join(own, "node_id").join(other, "ref_id").select("node_id", "ref_id", F.size(F.array_intersect("targets", "reference")).cast("long").alias("n_shared"), F.size(F.array_except("targets", "reference")).cast("long").alias("n_extra"))


def arborescence(cost: np.ndarray) -> np.ndarray:
    """The parent of each node in the least directed tree out of node 0; ``cost[v, u]`` is of the edge from v to u.

    Every node takes its cheapest parent; while that makes a cycle, the cycle becomes one node, into which an edge costs
    what it adds to the cycle's own edge that it replaces. Ties go to the lower number, so to node 0 first.
    """
    cost = cost.astype(float)
    np.fill_diagonal(cost, np.inf)
    cost[:, 0] = np.inf
    parent = cost.argmin(axis=0)
    parent[0] = 0
    seen, cycle = np.zeros(len(cost), int), []
    for start in range(1, len(cost)):
        v = start
        while v and not seen[v]:
            seen[v], v = start, parent[v]
        if v and seen[v] == start:
            cycle = [v]
            while parent[cycle[-1]] != v:
                cycle.append(parent[cycle[-1]])
            break
    if not cycle:
        return parent
    rest = np.setdiff1d(np.arange(len(cost)), cycle)
    m = len(rest)
    into = cost[np.ix_(rest, cycle)] - cost[parent[cycle], cycle]
    out = cost[np.ix_(cycle, rest)]
    small = np.full((m + 1, m + 1), np.inf)
    small[:m, :m], small[:m, m], small[m, :m] = cost[np.ix_(rest, rest)], into.min(axis=1), out.min(axis=0)
    above, leave = arborescence(small), out.argmin(axis=0)
    for k in range(1, m):
        parent[rest[k]] = cycle[leave[k]] if above[k] == m else rest[above[k]]
    parent[cycle[into[above[m]].argmin()]] = rest[above[m]]
    return parent


def choose_reference(lists: DataFrame, membership: DataFrame, id_bits: int = 32) -> DataFrame:
    """(node_id, ref_id or null, bits): references inside each cluster by a least spanning arborescence of coding costs.

    A list's cost alone is id_bits an entry; against a reference it is one bit for each of its entries and id_bits for each
    extra. Clusters are capped, so all pairs of one stay in a task.
    """

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("node_id")
        own = [set(t) for t in frame.targets]
        n = len(own)
        cost = np.zeros((n + 1, n + 1))
        cost[0, 1:] = [id_bits * len(t) for t in own]
        for v in range(n):
            cost[v + 1, 1:] = [len(own[v]) + id_bits * len(t - own[v]) for t in own]
        parent = arborescence(cost)[1:]
        ids = frame.node_id.to_numpy()
        out = pd.DataFrame({"node_id": ids, "ref_id": [None if p == 0 else int(ids[p - 1]) for p in parent], "bits": cost[parent, np.arange(1, n + 1)].astype("int64")})
        return out.astype({"ref_id": "Int64"})

    rows = lists.select("node_id", "targets").join(membership, "node_id")
    return rows.groupBy("cluster_id").applyInPandas(one, "node_id long, ref_id long, bits long")
