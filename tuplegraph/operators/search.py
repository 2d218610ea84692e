"""Keyword search in rounds on DataFrames, and in one task per query for graphs that fit.

A round joins the frontier with the edges that enter it and keeps the least cost of each (query, term, node). All queries
of a workload share the rounds. Ties go to the smaller node id, which is the relation's code and then the key.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scores import edge_score, node_score, tree_score
from ..plans.loop import BROADCAST_ROWS, cut, drop, few, sweep
from ..session import prepare
from .graph import Graph
from .index import complete
from .kernels import Adjacency, backward, bidirectional

#: Rows (edges, nodes and matches) of one query that a task may hold in local mode.
LOCAL_ROWS = 4_000_000


def entering(edges: DataFrame) -> DataFrame:
    """Edges in buckets of their target, as stored graphs have them; others are stored so."""
    return edges if getattr(edges, "cut_by", None) == "dst" else cut(edges, "dst")


def keyword_distances(edges: DataFrame, matches: DataFrame, max_cost: float = 4.0, max_rounds: int = 200, unit: bool = False, allowed: tuple[str, ...] | None = None, start: DataFrame | None = None, slack: float = 1e-9) -> DataFrame:
    """(query_id, term, node_id, dist): least cost of a way from a node to a node of the term's set, up to ``max_cost``.

    ``unit`` counts edges instead of weights, ``allowed`` restricts edge types, ``start`` gives (node_id, start) costs of
    matched nodes.
    """
    links = entering(edges)
    links = links if allowed is None else links.where(F.col("etype").isin(list(allowed)))
    links = links.select("src", "dst", (F.lit(1.0) if unit else F.col("weight")).alias("w")).where(F.col("w") <= max_cost + slack)
    state = matches.select("query_id", "term", "node_id", F.lit(0.0).alias("dist"))
    if start is not None:
        state = state.drop("dist").join(start, "node_id").select("query_id", "term", "node_id", F.col("start").alias("dist"))
    state = cut(state.withColumn("new", F.lit(True)))
    keys = ["query_id", "term", "node_id"]
    for _ in range(max_rounds):
        frontier = state.where("new").select("query_id", "term", F.col("node_id").alias("dst"), "dist")
        found = frontier.hint("shuffle_hash").join(links, "dst").select("query_id", "term", F.col("src").alias("node_id"), (F.col("dist") + F.col("w")).alias("offer")).where(F.col("offer") <= max_cost + slack)
        offers = found.groupBy(*keys).agg(F.min("offer").alias("offer"))
        merged = state.drop("new").join(offers, keys, "full_outer")
        better = F.col("offer").isNotNull() & (F.col("dist").isNull() | (F.col("offer") < F.col("dist") - slack))
        before, state = state, cut(merged.select(*keys, F.when(better, F.col("offer")).otherwise(F.col("dist")).alias("dist"), better.alias("new")))
        drop(before)
        if state.where("new").isEmpty():
            return state.drop("new")
    raise RuntimeError(f"distances did not settle in {max_rounds} rounds")


def next_hops(edges: DataFrame, dist: DataFrame, slack: float = 1e-9) -> DataFrame:
    """Distances with the next node on a least way (null at a match); among equals the smallest node."""
    links = edges.select("src", "dst", F.col("weight").alias("w"))
    ahead = dist.select("query_id", "term", F.col("node_id").alias("dst"), F.col("dist").alias("ahead"))
    own = dist.select("query_id", "term", F.col("node_id").alias("src"), "dist")
    # an edge on a least way is one of least weight between its ends, so parallel edges need no sum before
    ways = ahead.hint("shuffle_hash").join(links, "dst").join(own, ["query_id", "term", "src"]).where(F.abs(F.col("w") + F.col("ahead") - F.col("dist")) <= slack).withColumnRenamed("src", "node_id")
    best = ways.groupBy("query_id", "term", "node_id").agg(F.min("dst").alias("next_id"))
    return dist.join(best, ["query_id", "term", "node_id"], "left")


def roots(dist: DataFrame, queries: DataFrame, pool: int) -> DataFrame:
    """(query_id, root, cost): nodes with a distance for every term, the ``pool`` cheapest of each query."""
    wanted = queries.groupBy("query_id").agg(F.count_distinct("term").alias("n"))
    sums = dist.groupBy("query_id", F.col("node_id").alias("root")).agg(F.count(F.lit(1)).alias("n"), F.sum("dist").alias("cost"))
    whole = sums.join(F.broadcast(wanted), ["query_id", "n"]).withColumn("cost", F.round("cost", 6))
    ranked = whole.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy("cost", "root")))
    return ranked.where(F.col("r") <= pool).select("query_id", "root", "cost")


def paths(found: DataFrame, hops: DataFrame, max_hops: int = 200) -> DataFrame:
    """(query_id, root, term, src, dst): the edges of each root's least way to each term; one row with src = dst at its end."""
    step = few(found).select("query_id", "root").join(hops.select("query_id", "term", "node_id", "next_id"), (hops.query_id == found.query_id) & (hops.node_id == found.root)).select(found.query_id, "root", "term", F.col("node_id").alias("src"), F.col("next_id").alias("dst"))
    out, ways = None, hops.select("query_id", "term", F.col("node_id").alias("at"), F.col("next_id").alias("ahead"))
    for _ in range(max_hops):
        step = cut(step)
        part = step.select("query_id", "root", "term", "src", F.coalesce("dst", "src").alias("dst"))
        out = part if out is None else out.unionByName(part)
        going = step.where("dst is not null")
        if going.isEmpty():
            return out
        going = few(going)
        step = going.join(ways, (going.query_id == ways.query_id) & (going.term == ways.term) & (going.dst == ways.at)).select(going.query_id, "root", going.term, F.col("at").alias("src"), F.col("ahead").alias("dst"))
    raise RuntimeError(f"a way has more than {max_hops} hops")


def several_paths(edges: DataFrame, dist: DataFrame, per_node: int, slack: float = 1e-9) -> DataFrame:
    """(query_id, term, node_id, r, next_id, cost): the ``per_node`` cheapest ways of each node to each term that begin with
    different edges; ties by the next node. One way a node hides answers whose best branch is taken by another keyword."""
    links = edges.groupBy("src", "dst").agg(F.min("weight").alias("w"))
    ahead = dist.select("query_id", "term", F.col("node_id").alias("next_id"), F.col("dist").alias("ahead"))
    steps = dist.select("query_id", "term", "node_id").join(links.withColumnsRenamed({"src": "node_id", "dst": "next_id"}), "node_id")
    ways = steps.join(ahead, ["query_id", "term", "next_id"]).select("query_id", "term", "node_id", "next_id", F.round(F.col("w") + F.col("ahead"), 6).alias("cost"))
    order = Window.partitionBy("query_id", "term", "node_id").orderBy("cost", "next_id")
    return ways.withColumn("r", F.row_number().over(order)).where(F.col("r") <= per_node)


def backward_rounds(graph: Graph, matches: DataFrame, queries: DataFrame, max_cost: float = 4.0, pool: int = 50) -> DataFrame:
    """Candidate answers by least ways: (query_id, root, src, dst, term or null); see ``answers.assemble``."""
    matches = complete(matches, queries)
    dist = keyword_distances(graph.edges, matches, max_cost)
    found = cut(roots(dist, queries, pool))
    return paths(found, next_hops(graph.edges, dist))


def bidirectional_rounds(graph: Graph, matches: DataFrame, queries: DataFrame, k: int = 10, batch: int = 64, mu: float = 0.5, combine: str = "max", max_rounds: int = 500, slack: float = 1e-9, allowed: tuple[str, ...] | None = None) -> DataFrame:
    """(query_id, term, node_id, dist, activation, taken): bidirectional search in rounds, exact for the ``k`` cheapest roots.

    The most activated nodes that are open pass on distance and activation against their in-edges, and take distances
    along their out-edges from neighbours that have one. A node whose distance improves is open again, so improvements
    reach what depends on it. A way through an open node costs its distance and one edge at least, so a node stays closed
    once that is more than the query's k-th cheapest root so far; the search ends when nothing is left. The batch doubles
    each round, so the number of rounds does not follow the size of the origin sets. ``allowed`` restricts edge types; an
    edge's priority multiplies its share of the activation.
    """
    from . import activation

    every = graph.edges if allowed is None else graph.edges.where(F.col("etype").isin(list(allowed)))
    stored = getattr(graph.edges, "cut_by", None) == "dst"  # in the buckets of the links already, so nothing is shuffled for them
    share = activation.shares(every, "in", least=True).select(F.col("taker").alias("src"), F.col("giver").alias("dst"), "w", F.col("share").alias("s"))
    n_edges = every.count()
    links, outward = cut(share, "dst", 0 if stored else n_edges, lie=stored), None
    sweep(links.sparkSession)
    least = links.agg(F.min("w")).first()[0] or 0.0
    seeded = activation.seed(complete(matches, queries), graph.nodes)
    state = cut(seeded.select("query_id", "term", "node_id", F.lit(0.0).alias("dist"), "activation", F.lit(False).alias("taken")))
    keys, how = ["node_id", "query_id", "term"], F.max if combine == "max" else F.sum  # sorts compare numbers before strings
    for number in range(max_rounds):
        kth = roots(state, queries, k).groupBy("query_id").agg(F.count(F.lit(1)).alias("n"), F.max("cost").alias("kth")).where(F.col("n") >= k).select("query_id", "kth")
        live = state.where("not taken").join(F.broadcast(kth), "query_id", "left").where(F.col("kth").isNull() | (F.col("dist") + least <= F.col("kth") + slack))
        total = live.groupBy("query_id", "node_id").agg(F.sum("activation").alias("a"))
        order = Window.partitionBy("query_id").orderBy(F.desc("a"), "node_id")
        picked = cut(total.withColumn("r", F.row_number().over(order)).where(F.col("r") <= batch * 2 ** min(number, 40)).select("query_id", "node_id"))
        n_picked = picked.count()
        if n_picked == 0:
            drop(picked, links, *([] if outward is None else [outward]))
            return state
        if outward is None and n_picked > BROADCAST_ROWS:  # fewer are broadcast, and find their out-edges in any buckets
            outward = cut(links.select("src", "dst", "w"), "src", n_edges)
            sweep(links.sparkSession)
        small = lambda df, n=n_picked: F.broadcast(df) if n <= BROADCAST_ROWS else df.hint("shuffle_hash")
        now = small(state.join(small(picked), ["query_id", "node_id"]))
        back = now.withColumnRenamed("node_id", "dst").join(links, "dst")
        back = back.select("query_id", "term", F.col("src").alias("node_id"), (F.col("dist") + F.col("w")).alias("offer"), (mu * F.col("activation") * F.col("s")).alias("gift"))
        ahead = small(picked.withColumnRenamed("node_id", "src")).join(links if outward is None else outward, "src").select("query_id", F.col("src").alias("node_id"), "dst", "w")
        known = state.select("query_id", "term", F.col("node_id").alias("dst"), "dist")
        front = ahead.join(known, ["query_id", "dst"]).select("query_id", "term", "node_id", (F.col("dist") + F.col("w")).alias("offer"), F.lit(0.0).alias("gift"))
        offers = back.unionByName(front).groupBy(*keys).agg(F.min("offer").alias("offer"), how("gift").alias("gift"))
        merged = state.join(offers, keys, "full_outer").join(picked.withColumn("now", F.lit(True)), ["query_id", "node_id"], "left")
        better = F.col("offer").isNotNull() & (F.col("dist").isNull() | (F.col("offer") < F.col("dist") - slack))
        kept = F.coalesce("activation", F.lit(0.0)) * F.when(F.col("now"), 1 - mu).otherwise(1.0)
        gift = F.coalesce("gift", F.lit(0.0))
        before, state = state, cut(merged.select(*keys, F.when(better, F.col("offer")).otherwise(F.col("dist")).alias("dist"), (F.greatest(kept, gift) if combine == "max" else kept + gift).alias("activation"), (~better & (F.coalesce("taken", F.lit(False)) | F.coalesce("now", F.lit(False)))).alias("taken")))
        drop(before, picked)
    raise RuntimeError(f"the search did not end in {max_rounds} rounds")


def _starts(nodes: DataFrame, own: list[str]) -> DataFrame:
    """Start costs of matched nodes: the higher a node's prestige, the lower."""
    return nodes.select(*own, "node_id", (1 / (1 + F.col("prestige"))).alias("first")).distinct()


def _cheapest(state: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """(query_id, root, cost): the k cheapest roots whose ways begin with two edges or that hold a keyword themselves."""
    one = F.count(F.lit(1)).alias("n")
    sums = state.groupBy("query_id", F.col("node_id").alias("root")).agg(one, F.sum("dist").alias("cost"), F.count("way").alias("going"), F.min("way").alias("first"), F.max("way").alias("last"))
    whole = sums.join(F.broadcast(wanted), ["query_id", "n"]).where((F.col("going") < F.col("n")) | (F.col("first") != F.col("last"))).withColumn("cost", F.round("cost", 6))
    order = Window.partitionBy("query_id").orderBy("cost", "root")
    return whole.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).select("query_id", "root", "cost")


def cheapest_answers(matches: DataFrame, edges: DataFrame, nodes: DataFrame, k: int = 10, max_cost: float = 1e9, lam: float = 0.2, max_rounds: int = 500, slack: float = 1e-9, origin_weight: bool = False) -> DataFrame:
    """The columns of ``local_search``, in rounds of joins over graphs of any size: the trees of the k cheapest roots, exactly.

    ``edges`` and ``nodes`` hold one graph for all queries, or with a query_id each query's own. A round passes the
    distances of the open nodes on against their in-edges and keeps with each the edge it came by. A node waits while its
    distance and one edge more are above its query's k-th cheapest root, and the search ends when all others are closed.
    Touched are the nodes with a distance, explored those that passed one on. With ``origin_weight``, a matched node starts
    at 1 / (1 + prestige) instead of 0.
    """
    own = ["query_id"] if "query_id" in edges.columns else []
    keys = ["node_id", "query_id", "term"]  # sorts compare numbers before strings
    links = (cut(edges) if own else entering(edges)).select(*own, "src", "dst", F.col("weight").alias("w"))
    least = links.agg(F.min("w")).first()[0] or 0.0
    wanted = cut(matches.groupBy("query_id").agg(F.count_distinct("term").alias("n")))
    start = matches.select(*keys).distinct().withColumn("first", F.lit(0.0))
    if origin_weight:
        start = start.drop("first").join(_starts(nodes, own), [*own, "node_id"], "left").withColumn("first", F.coalesce("first", F.lit(1.0)))
    state = cut(start.select(*keys, F.col("first").alias("dist"), F.lit(None).cast("long").alias("way"), F.lit(True).alias("open"), F.lit(False).alias("taken")))
    for _ in range(max_rounds):
        kth = _cheapest(state, wanted, k).groupBy("query_id").agg(F.count(F.lit(1)).alias("n"), F.max("cost").alias("kth")).where(F.col("n") >= k).select("query_id", "kth")
        near = F.col("dist") + least <= F.coalesce("kth", F.lit(max_cost)) + slack
        picked = cut(state.where("open").join(F.broadcast(kth), "query_id", "left").where(near).select(*keys, "dist"))
        if picked.isEmpty():
            break
        offer = (F.col("dist") + F.col("w")).alias("offer")
        offers = picked.withColumnRenamed("node_id", "dst").hint("shuffle_hash").join(links, [*own, "dst"]).select("query_id", "term", F.col("src").alias("node_id"), offer, F.col("dst").alias("by"))
        offers = offers.where(F.col("offer") <= max_cost + slack).groupBy(*keys).agg(F.min(F.struct("offer", "by")).alias("o"))
        merged = state.join(offers, keys, "full_outer").join(picked.select(*keys, F.lit(True).alias("now")), keys, "left")
        better = F.col("o").isNotNull() & (F.col("dist").isNull() | (F.col("o.offer") < F.col("dist") - slack))
        waits = F.coalesce("open", F.lit(False)) & F.col("now").isNull()
        took = F.coalesce("taken", F.lit(False)) | F.col("now").isNotNull()
        before, state = state, cut(merged.select(*keys, F.when(better, F.col("o.offer")).otherwise(F.col("dist")).alias("dist"), F.when(better, F.col("o.by")).otherwise(F.col("way")).alias("way"), (better | waits).alias("open"), took.alias("taken")))
        drop(before, picked)
    else:
        raise RuntimeError(f"the search did not end in {max_rounds} rounds")
    found = cut(_cheapest(state, wanted, k))
    ways = cut(paths(found, state.select(*keys, F.col("way").alias("next_id"))))
    weights = links.groupBy("src", "dst").agg(F.min("w").alias("w"))
    prestige = nodes.select("node_id", "prestige").distinct()
    steps = ways.where("src <> dst").select("query_id", "root", "src", "dst").distinct().join(weights, ["src", "dst"])
    trees = steps.groupBy("query_id", "root").agg(F.array_sort(F.collect_list(F.struct("src", "dst"))).alias("e"), F.sum("w").alias("total"))
    ends = ways.where("src = dst").select("query_id", "root", "term", F.col("src").alias("node_id")).join(prestige, "node_id")
    held = ends.groupBy("query_id", "root").agg(F.array_sort(F.collect_list(F.struct("term", "node_id"))).alias("held"), F.collect_set(F.struct("node_id", "prestige")).alias("leaf"))
    out = held.join(trees, ["query_id", "root"], "left").join(prestige.withColumnsRenamed({"node_id": "root", "prestige": "root_weight"}), "root")
    tree = F.coalesce(F.transform("e", lambda x: F.concat_ws(">", x.src.cast("string"), x.dst.cast("string"))), F.array().cast("array<string>"))
    members = F.coalesce(F.size(F.array_distinct(F.concat("e.src", "e.dst"))), F.lit(1))
    leaf = F.aggregate(F.array_sort("leaf"), F.lit(0.0), lambda a, x: a + x.prestige)
    out = out.select("query_id", "root", F.col("held.node_id").alias("leaves"), tree.alias("tree"), members.alias("n_nodes"), node_score(F.col("root_weight"), leaf, F.col("e").isNull()).alias("node_score"), edge_score(F.coalesce("total", F.lit(0.0))).alias("edge_score"))
    out = out.withColumn("tree_score", F.when(F.col("node_score") == 0, 0.0).otherwise(tree_score(F.col("edge_score"), F.col("node_score"), lam=lam)))
    work = state.groupBy("query_id", "node_id").agg(F.max("taken").alias("t")).groupBy("query_id").agg(F.count(F.lit(1)).alias("touched"), F.count_if("t").alias("explored"))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc(F.round("tree_score", 9)), "root")).cast("int").alias("rnk")
    return out.join(F.broadcast(work), "query_id").select("query_id", rank, "root", "leaves", "tree", "n_nodes", F.size("tree").alias("n_edges"), "node_score", "edge_score", "tree_score", "touched", "explored")


def cheapest_combinations(matches: DataFrame, edges: DataFrame, nodes: DataFrame, k: int = 10, max_cost: float = 1e9, lam: float = 0.2, per_root: int = 2, origin_weight: bool = False, max_rounds: int = 500, slack: float = 1e-9) -> DataFrame:
    """``cheapest_answers`` with up to ``per_root`` origins of each keyword at a root: the k cheapest different trees.

    A node keeps its ``per_root`` nearest origins of each term; an origin that is near at a node is near at the next one on
    the way, so no others are needed. Combinations that give the same tree count once; when they leave fewer than k trees,
    the search is run again for more combinations.
    """
    own = ["query_id"] if "query_id" in edges.columns else []
    links = cut((cut(edges) if own else entering(edges)).select(*own, "src", "dst", F.col("weight").alias("w")).groupBy(*own, "src", "dst").agg(F.min("w").alias("w")), None if own else "dst")
    n_terms = matches.groupBy("query_id").agg(F.count_distinct("term").alias("n"))
    wanted, least = cut(n_terms), links.agg(F.min("w")).first()[0] or 0.0
    prestige = nodes.select(*own, "node_id", "prestige").distinct()
    many = k
    while True:
        state, found = _origins(matches, links, nodes, wanted, own, many, least, max_cost, per_root, origin_weight, max_rounds, slack)
        out = cut(_trees(state, found, links, prestige, own, k, lam, max_rounds))
        full = found.groupBy("query_id").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") >= many).select("query_id")
        short = full.join(out.groupBy("query_id").agg(F.count(F.lit(1)).alias("c")).where(F.col("c") >= k), "query_id", "left_anti")
        if short.isEmpty():
            return out
        drop(state, found, out)
        many *= 4


def _origins(matches, links, nodes, wanted, own, many, least, max_cost, per_root, origin_weight, max_rounds, slack):
    """(query_id, term, node_id, origin, dist, way, ...) of the nearest origins, and the ``many`` cheapest combinations at roots."""
    at = ["query_id", "term", "node_id"]
    start = matches.select(*at).distinct().withColumn("first", F.lit(0.0))
    if origin_weight:
        start = start.drop("first").join(_starts(nodes, own), [*own, "node_id"], "left").withColumn("first", F.coalesce("first", F.lit(1.0)))
    state = cut(start.select(*at, F.col("node_id").alias("origin"), F.col("first").alias("dist"), F.lit(None).cast("long").alias("way"), F.lit(True).alias("open"), F.lit(False).alias("taken")))
    near = Window.partitionBy(*at).orderBy("dist", "origin")
    for _ in range(max_rounds):
        found = cut(_combinations(state, wanted, many))
        kth = found.groupBy("query_id").agg(F.count(F.lit(1)).alias("c"), F.max("cost").alias("kth")).where(F.col("c") >= many).select("query_id", "kth")
        picked = cut(state.where("open").join(F.broadcast(kth), "query_id", "left").where(F.col("dist") + least <= F.coalesce("kth", F.lit(max_cost)) + slack).select(*at, "origin", "dist"))
        if picked.isEmpty():
            return state, found
        step = picked.withColumnRenamed("node_id", "dst").hint("shuffle_hash").join(links, [*own, "dst"])
        offers = step.select("query_id", "term", F.col("src").alias("node_id"), "origin", (F.col("dist") + F.col("w")).alias("offer"), F.col("dst").alias("by")).where(F.col("offer") <= max_cost + slack)
        offers = offers.groupBy(*at, "origin").agg(F.min(F.struct("offer", "by")).alias("o"))
        merged = state.join(offers, [*at, "origin"], "full_outer").join(picked.select(*at, "origin", F.lit(True).alias("now")), [*at, "origin"], "left")
        better = F.col("o").isNotNull() & (F.col("dist").isNull() | (F.col("o.offer") < F.col("dist") - slack))
        waits = F.coalesce("open", F.lit(False)) & F.col("now").isNull()
        took = F.coalesce("taken", F.lit(False)) | F.col("now").isNotNull()
        rows = merged.select(*at, "origin", F.when(better, F.col("o.offer")).otherwise(F.col("dist")).alias("dist"), F.when(better, F.col("o.by")).otherwise(F.col("way")).alias("way"), (better | waits).alias("open"), took.alias("taken"))
        before, state = state, cut(rows.withColumn("r", F.row_number().over(near)).where(F.col("r") <= per_root).drop("r"))
        drop(before, picked, found)
    raise RuntimeError(f"the search did not end in {max_rounds} rounds")


def _combinations(state: DataFrame, wanted: DataFrame, many: int) -> DataFrame:
    """(query_id, root, picks, cost): the cheapest combinations of one origin for each term, as in ``_cheapest``; of those with the
    same origins one."""
    pick = F.struct("term", "origin", "dist", "way")
    lists = state.groupBy("query_id", F.col("node_id").alias("root"), "term").agg(F.array_sort(F.collect_list(pick)).alias("l"))  # a few origins
    every = lists.groupBy("query_id", "root").agg(F.count(F.lit(1)).alias("n"), F.array_sort(F.collect_list(F.struct("term", "l"))).alias("t")).join(F.broadcast(wanted), ["query_id", "n"])
    rows = every.select("query_id", "root", F.explode(F.expr("aggregate(t, array(slice(t[0].l, 1, 0)), (acc, x) -> flatten(transform(acc, a -> transform(x.l, p -> concat(a, array(p))))))")).alias("picks"))
    going = F.array_distinct("picks.way")
    rows = rows.where(F.exists("picks", lambda p: p.way.isNull()) | (F.size(going) > 1))
    rows = rows.withColumn("cost", F.round(F.aggregate("picks", F.lit(0.0), lambda s, p: s + p.dist), 6))
    same = Window.partitionBy("query_id", "root", F.array_sort(F.array_distinct("picks.origin"))).orderBy("cost", "picks.origin")
    rows = rows.withColumn("s", F.row_number().over(same)).where("s = 1").drop("s")
    order = Window.partitionBy("query_id").orderBy("cost", "root", "picks.origin")
    return rows.withColumn("number", F.row_number().over(order)).where(F.col("number") <= many)


def _trees(state: DataFrame, found: DataFrame, links: DataFrame, prestige: DataFrame, own: list[str], k: int, lam: float, max_hops: int) -> DataFrame:
    """The different trees of combinations in order of cost, scored."""
    ways = state.select("query_id", "term", "origin", F.col("node_id").alias("src"), F.col("way").alias("dst"))
    step = found.select("query_id", "number", "root", F.explode("picks").alias("p")).select("query_id", "number", "root", "p.term", "p.origin", F.col("root").alias("src"), F.col("p.way").alias("dst"))
    steps = None
    for hop in range(max_hops):
        step = cut(step.withColumn("hop", F.lit(hop)))
        steps = step if steps is None else steps.unionByName(step)
        going = step.where("dst is not null").select("query_id", "number", "root", "term", "origin", F.col("dst").alias("src"))
        if going.isEmpty():
            break
        step = few(going).join(ways, ["query_id", "term", "origin", "src"]).select("query_id", "number", "root", "term", "origin", "src", "dst")
    else:
        raise RuntimeError(f"a way has more than {max_hops} hops")
    steps = cut(steps)
    weights = few(cut(steps.where("dst is not null").select("query_id", "src", "dst").distinct())).join(links, [*own, "src", "dst"]).groupBy("query_id", "src", "dst").agg(F.min("w").alias("w"))
    ends = steps.select("query_id", F.explode(F.array("root", "origin")).alias("node_id")).distinct()
    held = few(cut(ends)).join(prestige, [*own, "node_id"]).select("query_id", F.col("node_id").alias("src"), F.lit(None).cast("long").alias("dst"), F.col("prestige").alias("w"))
    work = state.groupBy("query_id", "node_id").agg(F.max("taken").alias("t")).groupBy("query_id").agg(F.count(F.lit(1)).alias("touched"), F.count_if("t").alias("explored"))
    none = lambda t: F.lit(None).cast(t)
    known = weights.select("query_id", "src", "dst", "w").unionByName(held).select("query_id", none("int").alias("number"), none("long").alias("root"), none("string").alias("term"), none("long").alias("origin"), "src", "dst", none("int").alias("hop"), "w")
    rows = steps.withColumn("w", none("double")).unionByName(known)

    def one(key, frame: pd.DataFrame) -> pd.DataFrame:
        facts, rest = frame[frame.number.isna()], frame[frame.number.notna()]
        ids = lambda c: [None if pd.isna(x) else int(x) for x in c]
        weight = {(s, d): w for s, d, w in zip(ids(facts.src), ids(facts.dst), facts.w, strict=True)}
        seen, out = set(), []
        for _, part in sorted(rest.groupby("number"), key=lambda p: p[0]):
            part = part.sort_values(["term", "hop"])
            root, parent = int(part.root.iloc[0]), {int(part.root.iloc[0]): None}
            for s, d in zip(ids(part.src), ids(part.dst), strict=True):
                if d is not None and d not in parent:
                    parent[d] = s  # a way that meets the tree again keeps the first branch
            tree = sorted((p, c) for c, p in parent.items() if p is not None)
            leaves = [int(v) for v in part.drop_duplicates("term").origin]
            if tuple(tree or [root]) in seen or (tree and sum(p == root for p, _ in tree) < 2 and root not in leaves):
                continue
            seen.add(tuple(tree or [root]))
            node = weight.get((root, None), 0.0) + (sum(weight.get((v, None), 0.0) for v in set(leaves)) if tree else 0.0)
            edge = 1 / (1 + sum(weight[e] for e in tree))
            out.append((key[0], 0, root, leaves, [f"{p}>{c}" for p, c in tree], len(parent), len(tree), node, edge, edge * node**lam if node else 0.0))
        out = sorted(out[:k], key=lambda r: (-round(r[9], 9), r[2], r[4]))
        return pd.DataFrame([(r[0], i + 1, *r[2:]) for i, r in enumerate(out)], columns=["query_id", "rnk", "root", "leaves", "tree", "n_nodes", "n_edges", "node_score", "edge_score", "tree_score"])

    # the group of a query holds the ways of its combinations only
    trees = rows.groupBy("query_id").applyInPandas(one, "query_id string, rnk int, root long, leaves array<long>, tree array<string>, n_nodes int, n_edges int, node_score double, edge_score double, tree_score double")
    return trees.join(F.broadcast(work), "query_id")


def local_search(matches: DataFrame, edges: DataFrame, nodes: DataFrame, algorithm: str = "bidirectional", k: int = 10, limit: int | None = None, mu: float = 0.5, combine: str = "max", max_cost: float = 1e9, origin_weight: bool = False, per_root: int = 1, lam: float = 0.2, rows: int = LOCAL_ROWS) -> DataFrame:
    """Search each query's own graph in one task: (query_id, rnk, root, leaves, tree, n_nodes, n_edges, node_score, edge_score, tree_score, touched, explored).

    ``edges`` (query_id, src, dst, weight) and ``nodes`` (query_id, node_id, prestige) hold the query's own graph. Its size
    is counted first: queries above ``rows`` are searched by ``cheapest_answers``, or ``cheapest_combinations`` where a root may
    have several trees.
    """
    spark = prepare(edges.sparkSession)
    empty = F.lit(None)
    parts = (
        edges.select("query_id", F.lit("e").alias("kind"), F.col("src").alias("a"), F.col("dst").alias("b"), F.col("weight").alias("x"), empty.cast("string").alias("term"))
        .unionByName(nodes.select("query_id", F.lit("n").alias("kind"), F.col("node_id").alias("a"), F.lit(0).cast("long").alias("b"), F.col("prestige").alias("x"), empty.cast("string").alias("term")))
        .unionByName(matches.select("query_id", F.lit("m").alias("kind"), F.col("node_id").alias("a"), F.lit(0).cast("long").alias("b"), F.lit(0.0).alias("x"), "term"))
    )
    large = cut(parts.groupBy("query_id").count().where(F.col("count") > rows).select("query_id"))
    beyond = None
    if not large.isEmpty():
        mine = lambda df: df.join(F.broadcast(large), "query_id", "left_semi")
        beyond = _in_rounds(mine(matches), mine(edges), mine(nodes), algorithm, limit or k, max_cost, lam, origin_weight, per_root)
        parts = parts.join(F.broadcast(large), "query_id", "left_anti")
    names = ["query_id", "rnk", "root", "leaves", "tree", "n_nodes", "n_edges", "node_score", "edge_score", "tree_score", "touched", "explored"]

    def one(key, frame: pd.DataFrame) -> pd.DataFrame:
        e, n, m = (frame[frame.kind == kind] for kind in "enm")
        small = Adjacency(zip(e.a.tolist(), e.b.tolist(), e.x.tolist(), strict=True))
        prestige = dict(zip(n.a.tolist(), n.x.tolist(), strict=True))
        sets = {t: set(g.a.tolist()) for t, g in m.groupby("term")}
        if algorithm == "bidirectional":
            answers, touched, explored = bidirectional(small, sets, k, prestige, mu, combine, limit=limit)
        else:
            answers, touched, explored = backward(small, sets, k, prestige, origin_weight, max_cost, per_root, limit=limit)
        seen, scored = set(), []
        for a in answers:
            identity = tuple(a["edges"]) or (a["root"],)
            kids = {c for p, c in a["edges"] if p == a["root"]}
            leaves = {v for _, v in a["leaves"]}
            if (a["edges"] and len(kids) < 2 and a["root"] not in leaves) or identity in seen:
                continue  # a root with one branch that holds no keyword, or the tree was there before
            seen.add(identity)
            node = prestige.get(a["root"], 0.0) + (sum(prestige.get(v, 0.0) for v in leaves) if a["edges"] else 0.0)
            edge = 1 / (1 + a["cost"])
            scored.append((edge * node**lam if node else 0.0, edge, node, a))
        scored.sort(key=lambda s: (-round(s[0], 9), s[3]["root"], s[3]["edges"]))
        out = [(key[0], i + 1, a["root"], [v for _, v in a["leaves"]], [f"{p}>{c}" for p, c in a["edges"]], len(a["nodes"]), len(a["edges"]), node, edge, tree, touched, explored) for i, (tree, edge, node, a) in enumerate(scored[: limit or k])]
        return pd.DataFrame(out, columns=names)

    schema = "query_id string, rnk int, root long, leaves array<long>, tree array<string>, n_nodes int, n_edges int, node_score double, edge_score double, tree_score double, touched long, explored long"
    spark.conf.set("spark.sql.execution.arrow.pyspark.enabled", "true")
    found = parts.groupBy("query_id").applyInPandas(one, schema)
    return found if beyond is None else found.unionByName(beyond)


def _in_rounds(matches: DataFrame, edges: DataFrame, nodes: DataFrame, algorithm: str, k: int, max_cost: float, lam: float, origin_weight: bool, per_root: int) -> DataFrame:
    """The search above one task. Start costs and several origins a root belong to the backward search."""
    if algorithm == "bidirectional" and (origin_weight or per_root > 1):
        raise ValueError("the bidirectional search takes no start costs and gives one tree a root")
    if per_root > 1:
        return cheapest_combinations(matches, edges, nodes, k, max_cost, lam, per_root, origin_weight)
    return cheapest_answers(matches, edges, nodes, k, max_cost, lam, origin_weight=origin_weight)


def whole_search(graph: Graph, matches: DataFrame, queries: DataFrame, algorithm: str = "bidirectional", rows: int = LOCAL_ROWS, **options) -> DataFrame:
    """``local_search`` of one graph for all queries. Above ``rows`` the queries share rounds, and the graph is not copied."""
    if graph.edges.count() + graph.nodes.count() > rows:
        return _in_rounds(matches, graph.edges, graph.nodes, algorithm, options.get("limit") or options.get("k", 10), options.get("max_cost", 1e9), options.get("lam", 0.2), options.get("origin_weight", False), options.get("per_root", 1))
    edges, nodes = for_queries(graph, queries)
    return local_search(matches, edges, nodes, algorithm, rows=rows, **options)


def for_queries(graph: Graph, queries: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The whole graph once for each query, as ``local_search`` takes it; queries are a few broadcast rows."""
    ids = F.broadcast(queries.select("query_id").distinct())
    return graph.edges.select("src", "dst", "weight").crossJoin(ids), graph.nodes.select("node_id", "prestige").crossJoin(ids)
