"""Clusterings of the graph: (node_id, cluster_id), every node once, sizes up to a cap. A cluster is named by its least node."""

from __future__ import annotations

import hashlib
import math
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.loop import cut, dealt, drop, sweep
from ..session import prepare
from .graph import Graph, offsets
from .kernels import Adjacency, by_activation, grow

#: Nodes that one task clusters in sequence.
LOCAL_NODES = 50_000
#: Links up to which one task takes over the remaining rounds of a clustering, with the same clusters.
LOCAL_LINKS = 2_000_000


def hash60(text: Column, half: int = 0) -> Column:
    """A 60-bit number from the md5 of a string, the same in any SQL engine."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1 + 16 * half, 15), 16, 10).cast("long")


def named(groups: DataFrame) -> DataFrame:
    """(node_id, g) to (node_id, cluster_id): the least node of each group."""
    least = groups.groupBy("g").agg(F.min("node_id").alias("cluster_id"))
    return groups.join(least.hint("merge"), "g").select("node_id", "cluster_id")


def signatures(graph: Graph) -> DataFrame:
    """(node_id, degree, s1, s2): order-free sums of hashed out-list entries with weights, and the prestige.

    Sums are combined before the shuffle, so a hub's list is never gathered.
    """
    entry = F.concat_ws(":", F.col("dst").cast("string"), F.round(F.col("weight") * 1e6).cast("long").cast("string"))
    sums = graph.edges.groupBy(F.col("src").alias("node_id")).agg(F.count(F.lit(1)).alias("degree"), F.sum(hash60(entry).cast("decimal(20,0)")).alias("s1"), F.sum(hash60(entry, 1).cast("decimal(20,0)")).alias("s2"))
    return graph.nodes.select("node_id", "prestige").join(sums, "node_id", "left").fillna(0, ["degree"]).select("node_id", "prestige", "degree", F.coalesce("s1", F.lit(0)).alias("s1"), F.coalesce("s2", F.lit(0)).alias("s2"))


def adjacency(graph: Graph, size: int) -> DataFrame:
    """Nodes with equal lists, weights and prestige, ``size`` at most together."""
    same = ["prestige", "degree", "s1", "s2"]
    number = F.floor((F.row_number().over(Window.partitionBy(*same).orderBy("node_id")) - 1) / size)
    return named(signatures(graph).withColumn("g", F.struct(*same, number.alias("n"))).select("node_id", "g"))


def similar_adjacency(graph: Graph, size: int, tau: float = 0.75, bands: int = 8) -> DataFrame:
    """Nodes whose out-neighbour sets have a Jaccard similarity of ``tau`` or more with the first of their group.

    A band is the least hash of the neighbours; the nodes of a band's bucket that are not in a group yet are compared with
    the bucket's first node, band after band, on full lists. So a bucket costs its size, not its pairs.
    """
    links = cut(graph.edges.groupBy("src", "dst").agg(F.lit(1).alias("one")).drop("one"))
    least = [F.min(F.xxhash64(F.lit(b), F.col("dst"))).alias(f"m{b}") for b in range(bands)]
    keys = cut(links.groupBy(F.col("src").alias("node_id")).agg(F.count(F.lit(1)).alias("degree"), *least))
    state = cut(graph.nodes.select("node_id").join(keys.select("node_id"), "node_id", "left").withColumn("head", F.lit(None).cast("long")))
    for band in range(bands):
        free = state.where("head is null").select("node_id").join(keys, "node_id").select("node_id", "degree", F.col(f"m{band}").alias("m"))
        first = free.groupBy("m").agg(F.min(F.struct("node_id", "degree")).alias("f"), F.count(F.lit(1)).alias("n")).where("n > 1").select("m", F.col("f.node_id").alias("first"), F.col("f.degree").alias("first_degree"))
        asked = free.join(first, "m").where("node_id <> first").where(F.least("degree", "first_degree") >= tau * F.greatest("degree", "first_degree"))
        shared = asked.join(links, F.col("node_id") == F.col("src")).join(links.select(F.col("src").alias("first"), F.col("dst")), ["first", "dst"]).groupBy("node_id", "first", "degree", "first_degree").agg(F.count(F.lit(1)).alias("both"))
        near = cut(shared.where(F.col("both") >= tau * (F.col("degree") + F.col("first_degree") - F.col("both"))).select("node_id", F.col("first").alias("new")))
        heads = near.select(F.col("new").alias("node_id"), "new").distinct()
        state = cut(state.join(near.unionByName(heads), "node_id", "left").select("node_id", F.coalesce("head", "new").alias("head")))
    state = state.withColumn("head", F.coalesce("head", "node_id"))
    number = F.floor((F.row_number().over(Window.partitionBy("head").orderBy("node_id")) - 1) / size)
    return named(state.withColumn("g", F.struct("head", number.alias("n"))).select("node_id", "g"))


def random(graph: Graph, size: int) -> DataFrame:
    """Pages of ``size`` nodes in the order of a hash of the key."""
    rows = graph.nodes.select("node_id", hash60(F.col("node_key")).alias("h"), F.lit(1).alias("one"))
    paged = offsets(rows, "one", "h").withColumn("g", F.floor(F.col("offset") / size))
    return named(paged.select("node_id", "g"))


def _local(graph: Graph, make) -> DataFrame:
    spark = prepare(graph.nodes.sparkSession)
    nodes = graph.nodes.select(F.lit(0).alias("part"), F.lit("n").alias("kind"), F.col("node_id").alias("a"), F.lit(0).cast("long").alias("b"), F.col("prestige").alias("x"))
    edges = graph.edges.groupBy("src", "dst").agg(F.min("weight").alias("w"))
    rows = nodes.unionByName(edges.select(F.lit(0).alias("part"), F.lit("e").alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("w").alias("x")))

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        n, e = frame[frame.kind == "n"], frame[frame.kind == "e"]
        ids = n.a.tolist()
        got = make(Adjacency(zip(e.a.tolist(), e.b.tolist(), e.x.tolist(), strict=True)), ids, dict(zip(ids, n.x.tolist(), strict=True)))
        least: dict = {}
        for v, c in got.items():
            least[c] = min(v, least.get(c, v))
        return pd.DataFrame({"node_id": list(got), "cluster_id": [least[c] for c in got.values()]})

    return spark.createDataFrame([], "node_id long, cluster_id long").unionByName(rows.groupBy("part").applyInPandas(one, "node_id long, cluster_id long"))


def _order(ids, seed: int):
    return sorted(ids, key=lambda v: hashlib.md5(f"{seed}:{v}".encode()).digest())


def _grown(graph: Graph, size: int, criterion: str, order, parts: int | None, seed: int = 0, scan: str = "members") -> DataFrame:
    """Clusters grown in sequence by one task, or by ``rounds`` over all edges where more than one task is needed."""
    if (parts or math.ceil(graph.nodes.count() / LOCAL_NODES)) > 1:
        return rounds(graph, size, criterion, seed=seed, scan=scan)
    return _local(graph, lambda g, ids, p: grow(g, ids, size, criterion, order(ids), scan))


def connection(graph: Graph, size: int, seed: int = 0, parts: int | None = None) -> DataFrame:
    """Connected clusters around random seeds."""
    return _grown(graph, size, "connection", lambda ids: _order(ids, seed), parts, seed)


def ratio(graph: Graph, size: int, scan: str = "members", criterion: str = "ratio", parts: int | None = None) -> DataFrame:
    """Clusters that grow by the free neighbour whose forward and backward weights are most alike, or by least diameter."""
    return _grown(graph, size, criterion, sorted, parts, scan=scan)


def greedy_ball(graph: Graph, size: int, seed: int = 0, parts: int | None = None) -> DataFrame:
    """Random seeds take all their neighbours, then those of the nearest member, and so on."""
    return _grown(graph, size, "ball", lambda ids: _order(ids, seed), parts, seed)


def activated(graph: Graph, activation: DataFrame, page: int, mu: float = 0.5, parts: int | None = None) -> DataFrame:
    """Clusters in order of activation; ``activation`` (node_id, activation) becomes the nodes' start values.

    What a node passes on is below its own activation, so picks come in the order of the largest activation that any path
    brings. Above one task that order is found by rounds of relaxation over all edges, with the same pages.
    """
    nodes = graph.nodes.drop("prestige").join(activation, "node_id", "left").withColumn("prestige", F.coalesce("activation", F.lit(0.0)))
    if (parts or math.ceil(graph.nodes.count() / LOCAL_NODES)) <= 1:
        return _local(Graph(nodes, graph.edges), lambda g, ids, act: by_activation(g, act, page, mu))
    links = graph.edges.groupBy("src", "dst").agg(F.min("weight").alias("w"))
    pull = links.groupBy("dst").agg(F.sum(1 / F.col("w")).alias("pull"))
    shares = cut(links.join(pull, "dst").select("src", "dst", (1 / F.col("w")).alias("part"), "pull"))
    state = cut(nodes.select("node_id", F.col("prestige").alias("act")))
    fresh = state.where("act > 0")
    while not fresh.isEmpty():
        given = shares.join(fresh.withColumnRenamed("node_id", "dst"), "dst").groupBy(F.col("src").alias("node_id")).agg(F.max(F.lit(mu) * F.col("act") * F.col("part") / F.col("pull")).alias("given"))
        fresh = cut(state.join(given, "node_id").where(F.col("given") > F.col("act")).select("node_id", F.col("given").alias("act")))
        state = cut(state.join(fresh.withColumnRenamed("act", "new"), "node_id", "left").select("node_id", F.coalesce("new", "act").alias("act")))
    # runs of the global order, numbered from the counts of the runs before them, so no window spans all rows
    runs = cut(state.orderBy(F.desc("act"), "node_id").withColumn("run", F.spark_partition_id()))
    before = runs.groupBy("run").agg(F.count(F.lit(1)).alias("n")).withColumn("base", F.coalesce(F.sum("n").over(Window.orderBy("run").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("n")
    at = F.row_number().over(Window.partitionBy("run").orderBy(F.desc("act"), "node_id")) - 1 + F.col("base")
    return named(runs.join(F.broadcast(before), "run").select("node_id", F.floor(at / page).alias("g")))


def _sides(edges: DataFrame) -> DataFrame:
    """(a, b, there, back): each edge of two nodes, a below b, with its weight where its direction puts it."""
    ahead = F.col("src") < F.col("dst")
    return edges.where("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"), F.when(ahead, F.col("weight")).alias("there"), F.when(~ahead, F.col("weight")).alias("back"))


def two_way(edges: DataFrame) -> DataFrame:
    """(a, b, there, back, flow_there, flow_back) for each two nodes with an edge, a below b, in buckets of a.

    ``there`` is the least weight from a to b and ``flow_there`` the sum of the inverse weights; null where the way is absent.
    """
    found = dealt(_sides(edges), "a").groupBy("a", "b").agg(F.min("there").alias("there"), F.min("back").alias("back"), F.sum(1 / F.col("there")).alias("flow_there"), F.sum(1 / F.col("back")).alias("flow_back"))
    return cut(found, "a", edges.count(), lie=True)


def paired(edges: DataFrame, criterion: str, pairs: DataFrame | None = None) -> DataFrame:
    """(src, dst, and what the criterion compares) for each two nodes with an edge, once each way, in buckets of dst.

    ``w`` is the lesser weight of both ways; ``unlike`` the greater over the lesser, infinite where one way is absent. ``pairs``:
    what ``two_way`` gives for the edges, where it is stored already.
    """
    low, high = F.least("there", "back"), F.greatest("there", "back")
    both = F.col("there").isNotNull() & F.col("back").isNotNull()
    value = {"connection": [], "ratio": [F.when(both, high / low).otherwise(F.lit(float("inf"))).alias("unlike")]}.get(criterion, [low.alias("w")])
    if pairs is None:
        sides = _sides(edges)
        found = dealt(sides, "a").groupBy("a", "b").agg(F.min("there").alias("there"), F.min("back").alias("back")) if value else dealt(sides.select("a", "b"), "a").distinct()
        kept = cut(found.select("a", "b", *value), "a", edges.count(), lie=True)
        sweep(edges.sparkSession)
    else:
        kept = pairs.select("a", "b", *value)
    rest = kept.columns[2:]
    low_, high_ = kept.select(F.col("b").alias("src"), F.col("a").alias("dst"), *rest), kept.select(F.col("a").alias("src"), F.col("b").alias("dst"), *rest)
    links = cut(low_.unionByName(dealt(high_, "dst")), "dst", 2 * kept.count(), lie=True)  # those of a lie in its bucket already
    if pairs is None:
        drop(kept)
    return links


def _settled(rows: DataFrame, size: int, criterion: str, scan: str) -> DataFrame:
    """(node_id, new): the rounds of ``rounds`` from here on to their end, by one task.

    ``rows``: kind 0, a free node and its turn; kind 1, a link from a free node ``src`` to another; kind 2, a link to a member
    of a cluster with room, with that cluster, its room and turn, and the member's reach.
    """

    def one(frames):
        frame = pd.concat(frames, ignore_index=True)
        kind, src, dst = (frame[c].to_numpy() for c in ("kind", "src", "dst"))
        if not len(kind):
            return
        ids, joined = np.unique(np.concatenate([src, dst])), kind == 2
        names = np.unique(np.concatenate([ids, frame.cluster_id.to_numpy()[joined]]))  # ids and names are sorted: numbers compare like them
        at, own = np.searchsorted(ids, src), np.searchsorted(names, ids)
        free, turn, reach, of = np.zeros(len(ids), bool), np.zeros(len(ids), np.int64), np.zeros(len(ids)), np.full(len(ids), -1)
        room, token = np.zeros(len(names), np.int64), np.zeros(len(names), np.int64)
        free[at[kind == 0]], turn[at[kind == 0]] = True, frame.turn.to_numpy()[kind == 0]
        token[own] = turn
        member, known = np.searchsorted(ids, dst[joined]), np.searchsorted(names, frame.cluster_id.to_numpy()[joined])
        of[member], reach[member], room[known], token[known] = known, frame.reach.to_numpy()[joined], frame.room.to_numpy()[joined], frame.turn.to_numpy()[joined]
        s, d, value = at[kind > 0], np.searchsorted(ids, dst[kind > 0]), frame.value.to_numpy()[kind > 0]
        start = free.copy()
        while free.any():
            c = of[d]
            can = free[s] & (c >= 0) & (room[c] > 0)
            if scan == "seed" and criterion != "ball":
                can &= own[d] == c
            o = np.flatnonzero(can)
            v, c = s[o], c[o]
            far = reach[d[o]] + (value[o] if criterion == "ball" else 0.0)
            want = token[c].astype(float) if criterion == "connection" else value[o] if criterion == "ratio" else far
            o = np.lexsort((far, c, want, v))
            o = o[np.r_[True, v[o][1:] != v[o][:-1]]] if len(o) else o
            v, c, far, want = v[o], c[o], far[o], want[o]
            idle = free.copy()
            idle[v] = False
            o = np.lexsort((v, want, c))
            v, c, far = v[o], c[o], far[o]
            got = np.arange(len(c)) - np.searchsorted(c, c) < room[c]
            seeds = idle.copy()
            seeds[s[idle[s] & idle[d] & ((turn[d] < turn[s]) | ((turn[d] == turn[s]) & (d < s)))]] = False
            v, c, far, seeds = v[got], c[got], far[got], np.flatnonzero(seeds)
            of[v], reach[v], free[v] = c, far, False
            np.subtract.at(room, c, 1)
            of[seeds], free[seeds], room[own[seeds]] = own[seeds], False, size - 1
            keep = free[s] & ((of[d] < 0) | (room[of[d]] > 0))
            s, d, value = s[keep], d[keep], value[keep]
        yield pd.DataFrame({"node_id": ids[start], "new": names[of[start]]})

    return rows.repartition(1).mapInPandas(one, "node_id long, new long")


def rounds(graph: Graph, size: int, criterion: str = "connection", max_rounds: int | None = None, seed: int = 0, scan: str = "members") -> DataFrame:
    """Connection, ratio, diameter or ball clusters in parallel rounds of proposals, until every node has a cluster.

    A round makes seeds of free nodes that come first, by a hash, among their free neighbours when no cluster with room is
    near; every other free node beside such a cluster proposes to the one that its criterion prefers; a cluster accepts the
    best proposals that it has room for (one a round by diameter, since each member changes the distances). Whoever is
    accepted touches a member, so clusters stay connected. Every round takes a node, so the loop ends by itself. Links whose
    source has a cluster, or whose target lies in a full one, are left out when half of the nodes that were free are taken.
    The first round makes seeds only, found in the buckets of the links. Once there are LOCAL_LINKS links at most, one task
    goes on by the same rules to the end (not by diameter).
    """
    links, mirrored = paired(graph.edges, criterion, graph.pairs), True
    turn = lambda c: F.xxhash64(F.lit(seed), F.col(c))
    first = links.groupBy(F.col("dst").alias("node_id")).agg(F.min(F.struct(turn("src").alias("t"), F.col("src").alias("v"))).alias("f"))
    later = (F.col("f.t") < turn("node_id")) | ((F.col("f.t") == turn("node_id")) & (F.col("f.v") < F.col("node_id")))
    state = cut(graph.nodes.select("node_id").join(first, "node_id", "left").select("node_id", F.when(F.coalesce(later, F.lit(False)), None).otherwise(F.col("node_id")).alias("cluster_id"), F.lit(0.0).alias("reach")))
    want = {"connection": turn("cluster_id").cast("double"), "ratio": F.col("unlike"), "ball": F.col("far"), "diameter": F.col("wide")}[criterion]
    apart = cut(state.where("cluster_id is not null").select("cluster_id", F.col("cluster_id").alias("dst"), F.col("cluster_id").alias("other"), F.lit(0.0).alias("d"))) if criterion == "diameter" else None
    done, left, near, reached = 1, state.count(), links.count(), None
    while max_rounds is None or done < max_rounds:
        done += 1
        sizes = state.where("cluster_id is not null").groupBy("cluster_id").agg((F.lit(size) - F.count(F.lit(1))).alias("room")).where("room > 0")
        now = state.where("cluster_id is null").count()
        if now == 0:
            break
        if now < left / 2 and near > 0:
            useful = state.join(sizes.withColumnRenamed("room", "r"), "cluster_id", "left").where("cluster_id is null or r is not null").select(F.col("node_id").alias("dst"))
            side = "dst" if mirrored else "src"  # while each link is there both ways, its twin tells the same without a shuffle of all
            mine = links.join(state.where("cluster_id is null").select(F.col("node_id").alias(side)), side)
            mine = mine.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *links.columns[2:]) if mirrored else mine
            whole, links, mirrored = links, cut(mine.join(useful, "dst").select(*links.columns), "dst"), False
            drop(whole)
            left, near = now, links.count()
        if apart is None and max_rounds is None and near + now <= LOCAL_LINKS:
            target = state.join(sizes, "cluster_id", "left").where("cluster_id is null or room is not null").withColumnRenamed("node_id", "dst")
            value = F.col(links.columns[2]) if len(links.columns) > 2 else F.lit(0.0)
            home = F.coalesce("cluster_id", "dst")
            asking = links.join(target, "dst").join(state.where("cluster_id is null").select(F.col("node_id").alias("src")), "src").select(F.when(F.col("cluster_id").isNull(), 1).otherwise(2).alias("kind"), "src", "dst", value.alias("value"), home.alias("cluster_id"), "reach", F.coalesce("room", F.lit(0)).cast("long").alias("room"))
            alone = state.where("cluster_id is null").select(F.lit(0).alias("kind"), F.col("node_id").alias("src"), F.col("node_id").alias("dst"), F.lit(0.0).alias("value"), F.col("node_id").alias("cluster_id"), F.lit(0.0).alias("reach"), F.lit(0).cast("long").alias("room"))
            got = cut(_settled(asking.unionByName(alone).withColumn("turn", turn("cluster_id")), size, criterion, scan))
            before, state = state, cut(state.join(got, "node_id", "left").select("node_id", F.coalesce("cluster_id", "new").alias("cluster_id"), "reach"))
            drop(before, got)
            break
        open_ = state.join(sizes, "cluster_id").select(F.col("node_id").alias("dst"), "cluster_id", "reach", "room")
        open_ = open_.where(F.col("dst") == F.col("cluster_id")) if scan == "seed" and criterion != "ball" else open_
        free = state.where("cluster_id is null").select("node_id")
        offers = links.join(open_, "dst").join(free.withColumnRenamed("node_id", "src"), "src").withColumn("far", F.col("reach") + (F.col("w") if "w" in links.columns else 0.0))
        if apart is not None:
            reached = cut(offers.join(apart, ["cluster_id", "dst"]).groupBy("src", "cluster_id", "other").agg(F.min(F.col("d") + F.col("w")).alias("d")))
            offers = offers.join(reached.groupBy("src", "cluster_id").agg(F.max("d").alias("wide")), ["src", "cluster_id"]).withColumn("room", F.lit(1).cast("long"))
        best = offers.withColumn("want", want).groupBy("src").agg(F.min(F.struct("want", "cluster_id", "far", "room")).alias("o"))
        asked = cut(best.select(F.col("src").alias("node_id"), "o.cluster_id", "o.want", "o.far", "o.room"))
        taken = asked.withColumn("r", F.row_number().over(Window.partitionBy("cluster_id").orderBy("want", "node_id"))).where("r <= room").select("node_id", F.col("cluster_id").alias("new"), F.col("far").alias("at"))
        idle = cut(free.join(asked.select("node_id"), "node_id", "left_anti"))
        beside = links.join(idle.withColumnRenamed("node_id", "dst"), "dst").join(idle.withColumnRenamed("node_id", "src"), "src")
        beaten = beside.where((turn("dst") < turn("src")) | ((turn("dst") == turn("src")) & (F.col("dst") < F.col("src")))).select(F.col("src").alias("node_id")).distinct()
        seeds = idle.join(beaten, "node_id", "left_anti").select("node_id", F.col("node_id").alias("new"), F.lit(0.0).alias("at"))
        got = cut(taken.unionByName(seeds))
        if got.isEmpty():
            drop(asked, idle, got)
            break
        spent = [asked, idle, got]
        if apart is not None:
            joined = got.select(F.col("node_id").alias("src"), F.col("new").alias("cluster_id"))
            far = reached.join(joined, ["src", "cluster_id"])
            spent += [reached, apart]
            apart = cut(apart.unionByName(far.select("cluster_id", F.col("src").alias("dst"), "other", "d")).unionByName(far.select("cluster_id", F.col("other").alias("dst"), F.col("src").alias("other"), "d")).unionByName(joined.select("cluster_id", F.col("src").alias("dst"), F.col("src").alias("other"), F.lit(0.0).alias("d"))))
        before, state = state, cut(state.join(got, "node_id", "left").select("node_id", F.coalesce("cluster_id", "new").alias("cluster_id"), F.when(F.col("new").isNotNull(), F.col("at")).otherwise(F.col("reach")).alias("reach")))
        drop(before, *spent)
    drop(links)
    return named(state.select("node_id", F.coalesce("cluster_id", "node_id").alias("g")))


def correlation(nodes: DataFrame, links: DataFrame, seed: int = 0, max_rounds: int = 500) -> DataFrame:
    """Correlation clustering by pivots: nodes that come first among their undecided neighbours become pivots and take those.

    Links lie in buckets of one end, where a round finds its pivots; those of decided nodes are left out, and a node without
    any left is a cluster of its own. No table of nodes is broadcast: their files are small beside their rows.
    """
    turn = lambda c: F.xxhash64(F.lit(seed), F.col(c))
    both, settled = paired(links.select("src", "dst", F.lit(1.0).alias("weight")), "connection"), []
    for _ in range(max_rounds):
        if both.isEmpty():
            drop(both)
            every = nodes.select("node_id").hint("merge").join(reduce(DataFrame.unionByName, settled), "node_id", "left") if settled else nodes.select("node_id", F.lit(None).cast("long").alias("cluster_id"))
            out = cut(named(every.select("node_id", F.coalesce("cluster_id", "node_id").alias("g"))))
            if settled:
                drop(*settled)
            return out
        first = both.groupBy(F.col("dst").alias("node_id")).agg(F.min(F.struct(turn("src").alias("t"), F.col("src").alias("v"))).alias("f"))
        later = (F.col("f.t") < turn("node_id")) | ((F.col("f.t") == turn("node_id")) & (F.col("f.v") < F.col("node_id")))
        pivots = cut(first.where(~later).select("node_id"), "node_id", lie=True)
        near = both.join(pivots.select(F.col("node_id").alias("dst")).hint("shuffle_hash"), "dst")
        taken = near.groupBy(F.col("src").alias("node_id")).agg(F.min(F.struct(turn("dst").alias("t"), F.col("dst").alias("v"))).alias("f"))
        got = cut(taken.select("node_id", F.col("f.v").alias("cluster_id")).unionByName(pivots.select("node_id", F.col("node_id").alias("cluster_id"))), "node_id")
        gone = got.select(F.col("node_id").alias("dst")).hint("shuffle_hash")
        half = both.join(gone, "dst", "left_anti").select(F.col("dst").alias("src"), F.col("src").alias("dst"))  # each link is there both ways
        whole, both = both, cut(dealt(half, "dst").join(gone, "dst", "left_anti").select("src", "dst"), "dst", lie=True)
        drop(whole, pivots)
        settled.append(got)
    raise RuntimeError(f"pivots did not settle in {max_rounds} rounds")


def represent(membership: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(node_id, cluster_id, ordinal) and (cluster_id, n_nodes, offset): map, order and offsets."""
    ordered = membership.withColumn("ordinal", (F.row_number().over(Window.partitionBy("cluster_id").orderBy("node_id")) - 1).cast("int"))
    sizes = membership.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n_nodes"))
    return ordered, offsets(sizes, "n_nodes", "cluster_id")


def merge_twins(graph: Graph) -> DataFrame:
    """(rel, first_id, n_nodes, text): nodes of one relation with equal lists become one, with the union of their texts.

    A group's texts are a set, so equal texts are kept once however large the group is.
    """
    rows = signatures(graph).join(graph.nodes.select("node_id", "rel", "text"), "node_id")
    keys = ["rel", "degree", "s1", "s2"]
    texts = rows.select(*keys, "text").distinct().groupBy(*keys).agg(F.array_join(F.array_sort(F.collect_list("text")), " | ").alias("text"))
    groups = rows.groupBy(*keys).agg(F.min("node_id").alias("first_id"), F.count(F.lit(1)).alias("n_nodes"))
    return groups.join(texts, keys).select("rel", "first_id", "n_nodes", "text")


def merge_similar(graph: Graph, similarity, tau: float) -> DataFrame:
    """(node_id, first_id): nodes of one relation with equal lists that are similar to the first of them.

    ``similarity`` takes the columns of two texts and gives a column from 0 to 1, such as one that an ontology supplies.
    """
    rows = signatures(graph).join(graph.nodes.select("node_id", "rel", "text"), "node_id")
    keys = ["rel", "degree", "s1", "s2"]
    first = rows.groupBy(*keys).agg(F.min(F.struct("node_id", "text")).alias("f")).select(*keys, F.col("f.node_id").alias("first_id"), F.col("f.text").alias("first_text"))
    return rows.join(first, keys).where(similarity(F.col("text"), F.col("first_text")) >= tau).select("node_id", "first_id")


def faults(graph: Graph, membership: DataFrame, size: int, connected: bool = True) -> DataFrame:
    """One row: n_nodes that have a cluster, n_twice with several, n_over clusters above the size, n_split in several pieces."""
    from .components import components

    membership = cut(membership, "node_id")  # no join broadcasts it: its file is small beside its rows
    target, source = (membership.select(F.col("node_id").alias(x), F.col("cluster_id").alias(y)) for x, y in (("dst", "d"), ("src", "c")))
    inner = graph.edges.select("src", "dst").join(target.hint("shuffle_hash"), "dst").join(source.hint("shuffle_hash"), "src").where("c = d")  # edges lie in buckets of dst
    inner = cut(inner, rows=graph.edges.count(), over="src") if connected else inner
    joined = components(inner.select(F.col("src").alias("a"), F.col("dst").alias("b"))) if connected else membership.select(F.col("node_id").alias("node"), F.col("cluster_id").alias("label"))
    pieces = membership.hint("merge").join(joined.withColumnRenamed("node", "node_id"), "node_id", "left").groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n"), F.count_distinct(F.coalesce("label", "node_id")).alias("p"))
    known = graph.nodes.select("node_id").hint("merge").join(membership, "node_id").groupBy("node_id").agg(F.count(F.lit(1)).alias("c"))
    one = known.agg(F.count(F.lit(1)).alias("n_nodes"), F.count_if(F.col("c") > 1).alias("n_twice"))
    return one.crossJoin(pieces.agg(F.count_if(F.col("n") > size).alias("n_over"), F.count_if(F.col("p") > 1).alias("n_split")))  # one row each


def levels(graph: Graph, size: int, fit: int, technique=None, most: int = 4) -> list[DataFrame]:
    """Clusterings of clusterings until at most ``fit`` clusters are left, or after ``most`` levels.

    A level's edges are stored once as the pairs of their ends, from which its clusters and the next level's pairs are found.
    """
    from .quotient import cluster_graph

    out, current = [], Graph(graph.nodes, graph.edges, two_way(graph.edges))
    while True:
        membership = cut((technique or greedy_ball)(current, size))
        out.append(membership)
        n, pairs = membership.select("cluster_id").distinct().count(), current.pairs
        if n <= fit or n >= current.nodes.count() or len(out) == most:
            drop(pairs)
            return out
        current = cluster_graph(current.nodes, pairs, membership)
        drop(pairs)


# ---- refinement of a coarse partition ----


def coarse_by_links(graph: Graph, most: float) -> DataFrame:
    """Components over edges of weight at most ``most``."""
    from .components import components

    links = graph.edges.where(F.col("weight") <= most).select(F.col("src").alias("a"), F.col("dst").alias("b"))
    found = components(links)
    return graph.nodes.select("node_id").join(found.withColumnRenamed("node", "node_id"), "node_id", "left").select("node_id", F.coalesce("label", "node_id").alias("cluster_id"))


def clustered_split(membership: DataFrame, edges: DataFrame, elements: list[int], max_attempts: int = 3, most_k: int = 32, iterations: int = 10) -> DataFrame:
    """Split elements by k-means on vectors of which clusters their nodes point at.

    k starts at the number of other elements that the element points at and grows by two when a run leaves one group;
    elements that no attempt splits come back whole. Elements are split side by side, one task each.
    """
    inside = membership.where(F.col("cluster_id").isin(elements))
    targets = edges.join(membership.select(F.col("node_id").alias("dst"), F.col("cluster_id").alias("target")), "dst").select(F.col("src").alias("node_id"), "target")
    rows = inside.join(targets.groupBy("node_id", "target").agg(F.count(F.lit(1)).alias("n")), "node_id", "left")

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        ids = sorted(frame.node_id.unique())
        named_ = {v: i for i, v in enumerate(ids)}
        outs = sorted(x for x in frame.target.dropna().unique())
        x = np.zeros((len(ids), max(1, len(outs))))
        place = {t: i for i, t in enumerate(outs)}
        for v, t, n in zip(frame.node_id, frame.target, frame.n, strict=True):
            if t == t:
                x[named_[v], place[t]] = n
        k = min(most_k, max(2, len(outs)))
        label = np.zeros(len(ids), int)
        for _ in range(max_attempts):
            random_ = np.random.default_rng(int(frame.cluster_id.iloc[0]) % 2**32)
            centre = x[random_.permutation(len(ids))[: min(k, len(ids))]].copy()
            for _ in range(iterations):
                label = ((x[:, None, :] - centre[None]) ** 2).sum(axis=2).argmin(axis=1)
                for c in range(len(centre)):
                    if (label == c).any():
                        centre[c] = x[label == c].mean(axis=0)
            if len(set(label.tolist())) > 1:
                break
            k = min(most_k, k + 2)
        least = {c: min(v for v, own in zip(ids, label, strict=True) if own == c) for c in set(label.tolist())}
        return pd.DataFrame({"node_id": ids, "cluster_id": [least[c] for c in label.tolist()]})

    return rows.groupBy("cluster_id").applyInPandas(one, "node_id long, cluster_id long")


def refine(graph: Graph, start: DataFrame, policy: str = "largest", abort_max: int = 6, batch: int = 64, max_rounds: int | None = None, least: int = 4, seed: int = 0) -> DataFrame:
    """Refine a partition by splits of its elements until ``abort_max`` splits in a row fail or none is left to split.

    policy: which elements are split next, the largest or a random choice; ``batch`` of them a round.
    """
    state, failed, tried, done = cut(start), 0, set(), 0
    while max_rounds is None or done < max_rounds:
        done += 1
        sizes = state.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= least).where(~F.col("cluster_id").isin(sorted(tried) or [-1]))
        order = [F.desc("n"), "cluster_id"] if policy == "largest" else [F.xxhash64(F.lit(seed), "cluster_id")]
        chosen = [r["cluster_id"] for r in sizes.orderBy(*order).limit(batch).collect()]
        if not chosen:
            break
        split = cut(clustered_split(state, graph.edges, chosen))
        parts = {r["old"]: r["n"] for r in split.join(state.withColumnRenamed("cluster_id", "old"), "node_id").groupBy("old").agg(F.count_distinct("cluster_id").alias("n")).collect()}
        state = cut(state.where(~F.col("cluster_id").isin(chosen)).unionByName(split))
        for c in chosen:
            failed = failed + 1 if parts.get(c, 1) < 2 else 0
            if parts.get(c, 1) < 2:
                tried.add(c)
        if failed >= abort_max:
            break
    return state
