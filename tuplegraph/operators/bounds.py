"""Bounds on the cost of a real answer below an answer of clusters."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import all_pairs
from .quotient import intranode, labelled


#: Nodes of a cluster up to which its least costs are found in a dense table, together with those of others like it.
DENSE = 64
#: Entries of the dense tables that a task holds at once.
ENTRIES = 1_000_000


def _widest(kind, a, b, x, own, n_clusters: int):
    """(diameter, min_transit) arrays of clusters 0 to n - 1 from their rows; ``own`` is the cluster of each, in order.

    Costs are added in the direction of the way, as ``all_pairs`` adds them, so both give the same numbers.
    """
    inf = float("inf")
    far, cross = np.zeros(n_clusters), np.full(n_clusters, inf)
    node = np.flatnonzero(kind == "n")
    node = node[np.lexsort((a[node], own[node]))]
    ids, at = a[node], own[node]
    size = np.bincount(at, minlength=n_clusters)
    first = np.concatenate([[0], np.cumsum(size)])
    values, code = np.unique(np.concatenate([ids, a, b]), return_inverse=True)
    key = at * len(values) + code[: len(ids)]  # in order, as node is
    place = lambda of, c: np.searchsorted(key, of * len(values) + c) - first[of]
    s, d = code[len(ids) : len(ids) + len(a)], code[len(ids) + len(a) :]
    edge, enter, leave = (np.flatnonzero(kind == k) for k in "eio")
    order = np.argsort(size, kind="stable")
    order = order[(size[order] > 0) & (size[order] <= DENSE)]
    spot = np.full(n_clusters, -1)
    while len(order):
        many = max(1, ENTRIES // int(size[order[0]]) ** 2)
        group = order[:many]
        group = group[: max(1, ENTRIES // int(size[group[-1]]) ** 2)]
        group = group[size[group] <= 2 * size[group[0]]]
        order, m, n = order[len(group) :], len(group), int(size[group[-1]])
        spot[:] = -1
        spot[group] = np.arange(m)
        link = np.full((m, n, n), inf)
        e = edge[spot[own[edge]] >= 0]
        np.minimum.at(link, (spot[own[e]], place(own[e], s[e]), place(own[e], d[e])), x[e])
        cost = np.full((m, n, n), inf)
        cost[:, np.arange(n), np.arange(n)] = 0.0
        while True:
            before = cost.copy()
            for k in range(n):
                np.minimum(cost, cost[:, :, k, None] + link[:, k, None, :], out=cost)
            if np.array_equal(before, cost):
                break
        real = np.arange(n)[None, :] < size[group][:, None]
        both = real[:, :, None] & real[:, None, :]
        far[group] = np.where(both, cost, 0.0).max(axis=(1, 2))
        into, out = np.zeros((m, n), bool), np.zeros((m, n), bool)
        i, o = enter[spot[own[enter]] >= 0], leave[spot[own[leave]] >= 0]
        into[spot[own[i]], place(own[i], s[i])] = True
        out[spot[own[o]], place(own[o], s[o])] = True
        cross[group] = np.where(into[:, :, None] & out[:, None, :], cost, inf).min(axis=(1, 2))
    for c in np.flatnonzero(size > DENSE):
        lo, hi = np.searchsorted(own, [c, c + 1])
        k, u, v, w = kind[lo:hi], a[lo:hi], b[lo:hi], x[lo:hi]
        e, nodes = k == "e", u[k == "n"].tolist()
        cost = all_pairs(nodes, zip(u[e].tolist(), v[e].tolist(), w[e].tolist(), strict=True))
        far[c] = max(cost.get((p, q), inf) for p in nodes for q in nodes)
        cross[c] = min((cost.get((p, q), inf) for p in u[k == "i"].tolist() for q in u[k == "o"].tolist()), default=inf)
    return far, cross


def _whole(frames):
    """Frames in order of cluster, dealt so that none ends within a cluster."""
    held: list[pd.DataFrame] = []
    for frame in frames:
        if not len(frame):
            continue
        ids = frame.cluster_id.to_numpy()
        last = int(np.searchsorted(ids, ids[-1]))  # where the last cluster begins
        if last == 0 and held and held[-1].cluster_id.iloc[-1] == ids[0]:
            held.append(frame)
            continue
        done = pd.concat([*held, frame.iloc[:last]], ignore_index=True)
        held = [frame.iloc[last:]]
        if len(done):
            yield done
    if held:
        yield pd.concat(held, ignore_index=True)


def diameters(edges: DataFrame, membership: DataFrame) -> DataFrame:
    """(cluster_id, diameter, min_transit): largest least cost inside a cluster (infinite if a pair is apart), and the least
    cost of crossing it, from a node that an edge enters to one that an edge leaves.

    Edges are labelled once; a task takes its clusters many at a time.
    """
    row = lambda c, kind, a, b, x: F.struct(F.col(c).alias("cluster_id"), F.lit(kind).alias("kind"), F.col(a).alias("a"), b.alias("b"), x.alias("x"))
    none, zero = F.lit(0).cast("long"), F.lit(0.0)
    parts = F.when(F.col("src_c") == F.col("dst_c"), F.array(row("src_c", "e", "src", F.col("dst"), F.col("weight")))).otherwise(F.array(row("dst_c", "i", "dst", none, zero), row("src_c", "o", "src", none, zero)))
    links = labelled(edges, membership).select(F.explode(parts).alias("r")).select("r.*").groupBy("cluster_id", "kind", "a", "b").agg(F.min("x").alias("x"))
    nodes = membership.select("cluster_id", F.lit("n").alias("kind"), F.col("node_id").alias("a"), none.alias("b"), zero.alias("x"))
    rows = links.unionByName(nodes).repartition("cluster_id").sortWithinPartitions("cluster_id")

    def many(frames):
        for frame in _whole(frames):
            names, own = np.unique(frame.cluster_id.to_numpy(), return_inverse=True)
            far, cross = _widest(*(frame[c].to_numpy() for c in ("kind", "a", "b", "x")), own, len(names))
            yield pd.DataFrame({"cluster_id": names, "diameter": far, "min_transit": cross})

    return rows.mapInPandas(many, "cluster_id long, diameter double, min_transit double")


def reaches(edges: DataFrame, membership: DataFrame) -> DataFrame:
    """(cluster_id, widest): largest least cost inside a cluster among the pairs that have a way."""
    inside = labelled(edges, membership).where("src_c = dst_c").groupBy("src", "dst", "src_c").agg(F.min("weight").alias("x")).select(F.col("src_c").alias("cluster_id"), F.col("src").alias("a"), F.col("dst").alias("b"), "x")

    def one(key, frame: pd.DataFrame) -> pd.DataFrame:
        cost = all_pairs(sorted(set(frame.a) | set(frame.b)), zip(frame.a.tolist(), frame.b.tolist(), frame.x.tolist(), strict=True))
        return pd.DataFrame({"cluster_id": [key[0]], "widest": [max(cost.values())]})

    found = inside.groupBy("cluster_id").applyInPandas(one, "cluster_id long, widest double")
    return membership.select("cluster_id").distinct().join(found, "cluster_id", "left").select("cluster_id", F.coalesce("widest", F.lit(0.0)).alias("widest"))


def transits(edges: DataFrame, membership: DataFrame) -> DataFrame:
    """(cluster_id, enter, leave, cost): least cost inside a cluster from each node that an edge enters to each that one leaves."""
    both = labelled(edges, membership)
    inside = both.where("src_c = dst_c").groupBy("src", "dst", "src_c").agg(F.min("weight").alias("x")).select(F.col("src_c").alias("cluster_id"), F.lit("e").alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), "x")
    gate = lambda side, c, kind: both.where("src_c <> dst_c").select(F.col(c).alias("cluster_id"), F.lit(kind).alias("kind"), F.col(side).alias("a"), F.lit(0).cast("long").alias("b"), F.lit(0.0).alias("x")).distinct()

    def one(key, frame: pd.DataFrame) -> pd.DataFrame:
        e = frame[frame.kind == "e"]
        enter, leave = frame[frame.kind == "i"].a.tolist(), set(frame[frame.kind == "o"].a)
        cost = all_pairs(enter, zip(e.a.tolist(), e.b.tolist(), e.x.tolist(), strict=True))
        rows = [(key[0], a, b, c) for (a, b), c in cost.items() if b in leave]
        return pd.DataFrame(rows, columns=["cluster_id", "enter", "leave", "cost"]).astype({"cluster_id": "int64", "enter": "int64", "leave": "int64", "cost": "float64"})

    return inside.unionByName(gate("dst", "dst_c", "i")).unionByName(gate("src", "src_c", "o")).groupBy("cluster_id").applyInPandas(one, "cluster_id long, enter long, leave long, cost double")


def of_answers(artificial: DataFrame, super_links: DataFrame, per_cluster: DataFrame, mode: str = "sound") -> DataFrame:
    """(query_id, rnk, clusters, lower, upper) of artificial answers (query_id, rnk, root, tree, leaves), as ``bounds`` has them.

    super_links: (src_c, dst_c, least); per_cluster: (cluster_id, diameter, min_transit).
    """
    ends = F.transform("tree", lambda e: F.split(e, ">").cast("array<long>"))
    each = artificial.select("query_id", "rnk", "leaves", F.array_sort(F.array_union(F.array("root"), F.flatten(ends))).alias("clusters"), ends.alias("ends"))
    crossed = each.select("query_id", "rnk", F.explode("ends").alias("e")).select("query_id", "rnk", F.col("e")[0].alias("src_c"), F.col("e")[1].alias("dst_c")).join(super_links, ["src_c", "dst_c"]).groupBy("query_id", "rnk").agg(F.sum("least").alias("links"))
    beside = F.size(F.filter("ends", lambda e: F.array_contains(e, F.col("c"))))
    nodes = each.withColumn("c", F.explode("clusters")).withColumn("holds", F.array_contains("leaves", F.col("c"))).withColumn("ends_at", beside + F.col("holds").cast("int"))
    times = F.lit(1) if mode == "printed" else F.greatest(F.col("ends_at") - 1, F.lit(0))
    part = F.when(times > 0, times * F.col("diameter")).otherwise(0.0)  # no attachment to bridge, however far its nodes are apart
    sums = nodes.join(per_cluster.withColumnRenamed("cluster_id", "c"), "c").groupBy("query_id", "rnk", "clusters").agg(F.sum(F.when(~F.col("holds"), F.col("min_transit")).otherwise(0.0)).alias("lower"), F.sum(part).alias("inside"))
    return sums.join(crossed, ["query_id", "rnk"], "left").select("query_id", "rnk", "clusters", "lower", (F.col("inside") + F.coalesce("links", F.lit(0.0))).alias("upper"))


def bounds(tree: list[tuple[int, int, float]], roles: dict[int, bool], diameter: dict[int, float], transit: dict[int, float], mode: str = "sound") -> tuple[float, float]:
    """(lower, upper) cost of a real answer below a tree of clusters.

    tree: (parent, child, least link); roles: whether a keyword is taken from the cluster. Lower: crossings of clusters
    without keywords. Upper, printed: links and one diameter a cluster; sound: a diameter for each attachment but one.
    """
    nodes = roles.keys()
    lower = sum(transit[c] for c in nodes if not roles[c])
    links = sum(w for _, _, w in tree)
    if mode == "printed":
        return lower, links + sum(diameter[c] for c in nodes)
    ends = {c: sum(c in e[:2] for e in tree) + bool(roles[c]) for c in nodes}
    return lower, links + sum(max(ends[c] - 1, 0) * diameter[c] for c in nodes)


def role(answers: DataFrame, matched: DataFrame) -> DataFrame:
    """(query_id, rnk, cluster_id, role) of each cluster of an artificial answer: root, keyword or intermediate."""
    each = answers.select("query_id", "rnk", "root", F.explode(F.array_union(F.array("root"), F.flatten(F.transform("tree", lambda e: F.split(e, ">").cast("array<long>"))))).alias("cluster_id"))
    with_terms = each.join(matched.select("query_id", F.col("node_id").alias("cluster_id")).distinct().withColumn("m", F.lit(True)), ["query_id", "cluster_id"], "left")
    return with_terms.select("query_id", "rnk", "cluster_id", F.when(F.col("cluster_id") == F.col("root"), "root").when(F.col("m"), "keyword").otherwise("intermediate").alias("role"))


def crossing_pairs(edges: DataFrame, membership: DataFrame) -> DataFrame:
    """(cluster_id, n_inner): edges inside each cluster, the work that ``diameters`` has in it."""
    return intranode(edges, membership).groupBy(F.col("src_c").alias("cluster_id")).agg(F.count(F.lit(1)).alias("n_inner"))
