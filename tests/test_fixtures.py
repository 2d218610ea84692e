"""Hand-made graphs with results worked out by hand."""

import itertools

import numpy as np
import pandas as pd
import pytest
from conftest import SF
from pyspark.sql import functions as F

from tuplegraph.functions import scores
from tuplegraph.operators import activation, answers, bounds, cluster, compress, graph, jointree, measure, quotient
from tuplegraph.operators.kernels import Adjacency, backward, bidirectional, by_activation, distances, grow, steiner
from tuplegraph.plans import twophase


def unit(*pairs):
    return Adjacency([(a, b, 1.0) for a, b in pairs])


def test_root_with_one_branch_is_no_answer():
    g = unit((1, 2), (1, 3), (4, 1), (4, 5), (9, 4))
    found, _, _ = backward(g, {"alpha": {5}, "beta": {2, 3}}, 10, per_root=2)
    roots = {a["root"] for a in found}
    assert 9 not in roots and 4 in roots
    trees = [a["nodes"] for a in found if a["root"] == 4]
    assert [1, 2, 4, 5] in trees and [1, 3, 4, 5] in trees


def test_one_path_a_node_loses_alternatives():
    g = unit((1, 2), (1, 3), (4, 1), (4, 5))
    found, _, _ = bidirectional(g, {"alpha": {5}, "beta": {2, 3}}, 10, {n: 1.0 for n in range(6)})
    assert len([a for a in found if a["root"] == 4]) == 1


def test_backward_finds_the_exact_root():
    g = Adjacency([(1, 2, 1.0), (1, 3, 3.0), (4, 2, 1.0), (4, 3, 1.0), (5, 4, 1.0), (5, 3, 0.5)])
    cost, root = steiner(g, {"a": {2}, "b": {3}})
    found, _, _ = backward(g, {"a": {2}, "b": {3}}, 1)
    assert (cost, root) == (2.0, 4) and found[0]["root"] == 4


def test_bidirectional_run_to_the_end_has_exact_costs():
    g = Adjacency([(a, b, 1.0 + (a * b) % 3) for a in range(12) for b in range(12) if a != b and (a + 2 * b) % 5 == 0])
    sets = {"x": {1, 2}, "y": {7}}
    exact = {t: distances(g, s)[0] for t, s in sets.items()}
    found, _, _ = bidirectional(g, sets, 10**6, {n: 1.0 for n in range(12)})
    for a in found:
        assert a["cost"] <= sum(exact[t][a["root"]] for t in sets) + 1e-9


def test_activation_shares(spark):
    matches = spark.createDataFrame([("q", "t", 1), ("q", "t", 2)], "query_id string, term string, node_id long")
    nodes = spark.createDataFrame([(1, 4.0), (2, 0.0)], "node_id long, prestige double")
    edges = spark.createDataFrame([(7, 1, 1.0), (8, 1, 3.0)], "src long, dst long, weight double")
    state = activation.seed(matches, nodes)
    got = {r.node_id: r.activation for r in activation.spread(state, edges).collect()}
    assert got[1] == pytest.approx(1.0) and got[7] == pytest.approx(0.75) and got[8] == pytest.approx(0.25)


def test_scores(spark):
    row = spark.range(1).select(
        scores.edge_score(F.lit(4.0), "printed").alias("p"), scores.edge_score(F.lit(4.0)).alias("e"), scores.edge_score(F.lit(0.0), "printed").alias("p0"), scores.edge_score(F.lit(0.0)).alias("e0"),
        scores.tree_score(F.lit(0.2), F.lit(10.0)).alias("product"), scores.tree_score(F.lit(0.2), F.lit(10.0), "sum").alias("sum"),
    ).first()
    assert (row.p, row.e, row.p0, row.e0) == (0.8, 0.2, 0.0, 1.0)
    assert row.product == pytest.approx(0.316979, abs=1e-6) and row.sum == pytest.approx(2.16)


def test_super_edge_weights_and_prestige(spark):
    edges = spark.createDataFrame([(1, 4, 1.0), (2, 5, 2.0), (3, 5, 4.0)], "src long, dst long, weight double")
    m = spark.createDataFrame([(1, 1), (2, 1), (3, 1), (4, 4), (5, 4)], "node_id long, cluster_id long")
    nodes = spark.createDataFrame([(1, 2.0), (2, 3.0), (3, 7.0)], "node_id long, prestige double")
    value = {w: quotient.super_edges(edges, m, w).first().weight for w in ("inverse_sum", "harmonic", "min")}
    assert value["inverse_sum"] == pytest.approx(0.571429, abs=1e-6) and value["harmonic"] == pytest.approx(1.714286, abs=1e-6) and value["min"] == 1
    assert [quotient.cluster_nodes(nodes, m, p).first().prestige for p in ("sum", "max", "avg")] == [12, 7, 4]


def test_polarity(spark):
    links = [(a, b, 1.0) for a in (1, 2) for b in (3, 4, 5)][:5]
    edges = spark.createDataFrame(links, "src long, dst long, weight double")
    m = spark.createDataFrame([(1, 1), (2, 1), (3, 3), (4, 3), (5, 3)], "node_id long, cluster_id long")
    r = quotient.polarity(edges, m).first()
    assert (r.n_positive, r.n_negative, r.chosen) == (5, 1, "negative")
    assert quotient.negative(edges, m, 1, 3).count() == 1


def test_bounds():
    tree = [(0, 1, 1.0), (1, 2, 2.0), (1, 3, 2.0)]
    roles, diameter = {0: True, 1: False, 2: True, 3: True}, {0: 3.0, 1: 4.0, 2: 1.0, 3: 1.0}
    assert bounds.bounds(tree, roles, diameter, {1: 2.0}, "printed") == (2.0, 14.0)
    assert bounds.bounds(tree, roles, diameter, {1: 2.0}) == (2.0, 18.0)


def test_cluster_growth():
    g = Adjacency([(1, 2, 1.0), (2, 1, 1.0), (1, 3, 1.0), (3, 1, 3.0), (1, 4, 1.0), (4, 1, 2.0)])
    got = grow(g, [1, 2, 3, 4], 3, "ratio", [1])
    assert {v for v, c in got.items() if c == 1} == {1, 2, 4}
    star = Adjacency([(0, k, 1.0) for k in range(1, 6)])
    got = grow(star, range(6), 4, "ball", range(6))
    assert {v for v, c in got.items() if c == 0} == {0, 1, 2, 3}
    apart = grow(Adjacency([]), [1, 2], 2, "connection", [1, 2])
    assert apart == {1: 1, 2: 2}
    pages = by_activation(Adjacency([]), {1: 5.0, 2: 4.0, 3: 3.0, 4: 2.0}, 2)
    assert pages == {1: 1, 2: 1, 3: 3, 4: 3}


def test_fetch_trigger_and_budget(spark):
    a = spark.createDataFrame([("q", 1, 1.0), ("q", 2, 0.9), ("q", 3, 0.3)], "query_id string, rnk int, tree_score double")
    assert {r.rnk: r.drop for r in twophase.should_fetch(a).collect()} == {2: False, 3: True}


def test_acceptable_and_quality(spark):
    ref = spark.createDataFrame([("q", 1, 5, 4)], "query_id string, rnk int, n_nodes int, n_edges int")
    own = spark.createDataFrame([("q", 1, 5, 4), ("q", 2, 6, 5), ("q", 3, 3, 2)], "query_id string, rnk int, n_nodes int, n_edges int")
    assert measure.acceptable(own, ref).first().n_acceptable == 2
    s = spark.createDataFrame([("q", 1, 0.9), ("q", 2, 0.88), ("q", 3, 0.5)], "query_id string, rnk int, tree_score double")
    got = {r.rnk: (round(r.gap, 6), r.good) for r in measure.quality(s).collect()}
    assert got[2] == (0.02, True) and got[3] == (0.4, False)


def test_memory_formulas():
    assert measure.memory(1e6, 1e7) == 140e6 and measure.memory(0.5e6, 5e6) == 70e6
    assert round(measure.memory(1.771e6, 4.248e6, "slim") / 1e6, 1) == 49.9
    assert round(measure.memory(17710, 1.378e6, "slim") / 1e6, 1) == 11.2
    assert round((measure.memory(17710, 1.378e6, "slim") + 4 * 1.771e6) / 1e6, 1) == 18.3


def test_compression(spark):
    x, y = F.array(*[F.lit(v) for v in (5, 7, 12, 101, 190)]), F.array(*[F.lit(v) for v in (5, 8, 12, 101, 190, 300)])
    r = spark.range(1).select(compress.against(x, y).alias("c")).select("c.bits", "c.extras", compress.restore(x, F.col("c.bits"), F.col("c.extras")).alias("back")).first()
    assert (r.bits, r.extras, r.back) == ("10111", [8, 300], [5, 8, 12, 101, 190, 300])
    g = spark.range(1).select(compress.gaps(F.array(*[F.lit(v) for v in (3, 7, 8, 20)])).alias("g")).first().g
    assert g == [3, 4, 1, 12]
    lengths = compress.code_lengths({"a": 4, "b": 2, "c": 1, "d": 1})
    assert sorted(lengths.values()) == [1, 2, 3, 3] and sum(2.0**-n for n in lengths.values()) == 1


def test_join_tree():
    found = jointree.enumerate_trees({"x": {"customer"}, "y": {"supplier"}}, 3)
    assert found[0][0].joins == 2 and found[0][0].relations == {"customer", "nation", "supplier"}


def test_subset_minimal(spark):
    rows = [("q", 2, ["x"], [2], [2], 0, 0.0), ("q", 1, ["1>2", "1>3"], [1, 2, 3], [2, 3], 2, 2.0)]
    a = spark.createDataFrame([(q, r, [] if r == 2 else t, m, leaf, b, c) for q, r, t, m, leaf, b, c in rows], "query_id string, root long, tree array<string>, members array<long>, leaves array<long>, branches int, total double")
    assert [r.root for r in answers.subset_minimal(a).collect()] == [2]


def test_bidirectional_rounds_reach_exact_costs(spark):
    from tuplegraph.operators import search
    from tuplegraph.operators.graph import Graph

    links = [(a, b, 1.0 + (a * b) % 3) for a in range(12) for b in range(12) if a != b and (a + 2 * b) % 5 == 0]
    edges = spark.createDataFrame([(a, b, "x", w) for a, b, w in links], "src long, dst long, etype string, weight double")
    nodes = spark.createDataFrame([(n, 1.0) for n in range(12)], "node_id long, prestige double")
    queries = spark.createDataFrame([("q", "x"), ("q", "y")], "query_id string, term string")
    matches = spark.createDataFrame([("q", "x", 1), ("q", "x", 2), ("q", "y", 7)], "query_id string, term string, node_id long")
    got = search.bidirectional_rounds(Graph(nodes, edges), matches, queries, k=10**6, batch=100, max_rounds=12).collect()
    g = Adjacency(links)
    exact = {"x": distances(g, {1, 2})[0], "y": distances(g, {7})[0]}
    assert {(r.term, r.node_id): r.dist for r in got} == {(t, v): c for t in exact for v, c in exact[t].items()}


def test_answers_in_rounds_are_the_cheapest_trees(spark):
    from tuplegraph.operators import search
    from tuplegraph.operators.graph import Graph

    rng = np.random.default_rng(5)
    links = [(a, int(b), float(w)) for a in range(30) for b, w in zip(rng.choice(30, 3, replace=False), rng.uniform(1, 2, 3)) if a != b]
    sets = {"p": {"x": {1, 2}, "y": {7, 9}, "z": {20}}, "q": {"x": {4}, "y": {4, 11}}, "none": {"x": {3}, "y": {99}}}
    edges = spark.createDataFrame(links, "src long, dst long, weight double")
    nodes = spark.createDataFrame([(n, 1.0 + n % 4) for n in range(30)] + [(99, 1.0)], "node_id long, prestige double")
    matches = spark.createDataFrame([(q, t, n) for q, terms in sets.items() for t, ids in terms.items() for n in ids], "query_id string, term string, node_id long")
    queries = matches.select("query_id", "term").distinct()
    graph = Graph(nodes, edges)
    rows = lambda df: {(r.query_id, r.root): (tuple(r.leaves), frozenset(r.tree), r.n_nodes, r.n_edges, round(r.node_score, 9), round(r.edge_score, 9), round(r.tree_score, 9), r.rnk) for r in df.collect()}
    every = rows(search.whole_search(graph, matches, queries, k=10**6))
    assert len({q for q, _ in every}) == 2 and len(every) > 20
    assert rows(search.whole_search(graph, matches, queries, k=10**6, rows=0)) == every
    # each query's own graph, one query above the bound and the others not
    own, ids = search.for_queries(graph, queries)
    more = ids.unionByName(spark.range(1000, 2000).selectExpr("'p' AS query_id", "id AS node_id", "1D AS prestige"))
    assert rows(search.local_search(matches, own, more, k=10**6, rows=500)) == every
    g = Adjacency(links)
    few = rows(search.whole_search(graph, matches, queries, k=3, rows=0))
    for q in ("p", "q"):
        exact = [distances(g, ids)[0] for ids in sets[q].values()]
        best = sorted((sum(d[r] for d in exact), r) for p, r in every if p == q)[:3]
        assert {r for p, r in few if p == q} == {r for _, r in best}
        assert all(few[q, r][:7] == every[q, r][:7] for _, r in best)
    with pytest.raises(ValueError):
        search.whole_search(graph, matches, queries, rows=0, per_root=2)


def test_clusters_above_one_task_grow_over_every_edge(spark):
    from tuplegraph.operators import cluster
    from tuplegraph.operators.graph import Graph

    # a path of consecutive numbers: cut by residues of the number, it has no edge left
    links = [(a, b, 1.0) for v in range(1, 40) for a, b in ((v, v + 1), (v + 1, v))]
    graph = Graph(spark.createDataFrame([(v, 1.0) for v in range(1, 41)], "node_id long, prestige double"), spark.createDataFrame(links, "src long, dst long, weight double"))
    makers = [cluster.connection, cluster.ratio, cluster.greedy_ball, lambda g, n, parts: cluster.ratio(g, n, scan="seed", parts=parts), lambda g, n, parts: cluster.ratio(g, n, criterion="diameter", parts=parts)]
    for make in makers:
        groups = {}
        for r in make(graph, 5, parts=4).collect():
            groups.setdefault(r.cluster_id, []).append(r.node_id)
        assert sorted(v for g in groups.values() for v in g) == list(range(1, 41))
        for g in groups.values():
            assert sorted(g) == list(range(min(g), min(g) + len(g))) and len(g) <= 5  # connected by edges of the path
        for a, b in zip(sorted(groups), sorted(groups)[1:], strict=False):
            assert len(groups[a]) + len(groups[b]) > 2  # single nodes are never side by side
    start = spark.createDataFrame([(7, 1.0), (30, 0.9)], "node_id long, activation double")
    whole, parted = ({r.node_id: r.cluster_id for r in cluster.activated(graph, start, 6, parts=n).collect()} for n in (1, 4))
    assert whole == parted


def test_similarity_recall(spark):
    """Nearest vectors against brute force, for the rows whose id is divisible by 20."""
    sf = SF.replace("0.001", "0.01")
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").collect()
    ids, x = np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], float)
    asked = np.flatnonzero(ids % 20 == 0)
    near = x[asked] @ x.T
    near[np.arange(len(asked)), asked] = -9
    want = {(ids[q], ids[k]) for q, row in zip(asked, near, strict=True) for k in np.argsort(-row, kind="stable")[:3]}
    got = {(r.a, r.b) for r in graph.similarity_edges(spark, sf).where("a % 20 = 0").collect()}
    assert len(got & want) >= 0.9 * len(want)


def test_bounds_of_answers(spark):
    """The DataFrame form gives what the plain form gives, in both modes."""
    artificial = spark.createDataFrame([("q", 1, 1, ["1>2", "2>3"], [1, 3]), ("q", 2, 4, [], [4])], "query_id string, rnk int, root long, tree array<string>, leaves array<long>")
    links = spark.createDataFrame([(1, 2, 1.5), (2, 3, 2.0)], "src_c long, dst_c long, least double")
    per = spark.createDataFrame([(1, 3.0, 0.5), (2, 4.0, 0.25), (3, 5.0, 1.0), (4, 7.0, 2.0)], "cluster_id long, diameter double, min_transit double")
    roles, wide, cross = {1: True, 2: False, 3: True}, {1: 3.0, 2: 4.0, 3: 5.0, 4: 7.0}, {1: 0.5, 2: 0.25, 3: 1.0, 4: 2.0}
    for mode in ("sound", "printed"):
        got = {r.rnk: (r.lower, r.upper) for r in bounds.of_answers(artificial, links, per, mode).collect()}
        assert got[1] == bounds.bounds([(1, 2, 1.5), (2, 3, 2.0)], roles, wide, cross, mode)
        assert got[2] == bounds.bounds([], {4: True}, wide, cross, mode)


def test_similar_lists_meet_the_threshold(spark):
    rows = [(1, d) for d in range(10, 20)] + [(2, d) for d in range(10, 19)] + [(3, d) for d in range(10, 15)] + [(4, 50), (5, 50)]
    nodes = spark.createDataFrame([(k, f"x:{k}", "x", "", 1.0) for k in (*range(1, 6), *range(10, 20), 50)], "node_id long, node_key string, rel string, text string, prestige double")
    edges = spark.createDataFrame([(a, b, "x", "fwd", 1.0, 1.0) for a, b in rows], "src long, dst long, etype string, direction string, weight double, priority double")
    got = {r.node_id: r.cluster_id for r in cluster.similar_adjacency(graph.Graph(nodes, edges), 8, tau=0.75, bands=16).collect()}
    assert got[1] == got[2] == 1 and got[3] == 3 and got[4] == got[5] == 4 and len(got) == 16


def test_arborescence_is_least():
    """Against all ways of giving each node a parent; small whole costs make ties and cycles."""
    rng = np.random.default_rng(5)
    for _ in range(200):
        n = int(rng.integers(2, 6))
        cost = rng.integers(1, 9, (n, n))

        def rooted(parent):
            for v in range(1, n):
                for _ in range(n):
                    v = parent[v - 1] if v else 0
                if v:
                    return False
            return True

        total = lambda parent: sum(cost[p, v + 1] for v, p in enumerate(parent))
        best = min(total(p) for p in itertools.product(range(n), repeat=n - 1) if rooted(p))
        got = compress.arborescence(cost)[1:].tolist()
        assert rooted(got) and total(got) == best


def test_choice_of_reference(spark):
    lists = spark.createDataFrame([(1, [10, 11, 12]), (2, [10, 11, 12, 13]), (3, [50]), (4, [10, 11, 12, 13, 14])], "node_id long, targets array<long>")
    got = {r.node_id: (r.ref_id, r.bits) for r in compress.choose_reference(lists, lists.selectExpr("node_id", "1L AS cluster_id")).collect()}
    assert got == {1: (None, 96), 2: (1, 35), 3: (None, 32), 4: (2, 36)}


def test_rounds_leave_no_old_states(spark, tmp_path):
    """Of a search in rounds only the stored edges and the last state stay in the shared folder."""
    from pathlib import Path

    from tuplegraph.operators import search
    from tuplegraph.session import shared_dir

    home = Path(shared_dir(spark).removeprefix("file:"))
    before = set(home.iterdir())
    edges = spark.createDataFrame([(v, v + 1, "x", 1.0) for v in range(6)], "src long, dst long, etype string, weight double")
    matches = spark.createDataFrame([("q", "t", 6)], "query_id string, term string, node_id long")
    got = search.keyword_distances(edges, matches, 9.0)
    assert {r.node_id: r.dist for r in got.collect()} == {v: 6.0 - v for v in range(7)}
    assert len(set(home.iterdir()) - before) == 2


def test_cluster_rounds_leave_only_the_membership(spark):
    from pathlib import Path

    from tuplegraph.operators import cluster
    from tuplegraph.operators.graph import Graph
    from tuplegraph.session import shared_dir

    home = Path(shared_dir(spark).removeprefix("file:"))
    links = [(a, b, 1.0) for v in range(1, 20) for a, b in ((v, v + 1), (v + 1, v))]
    whole = Graph(spark.createDataFrame([(v, 1.0) for v in range(1, 21)], "node_id long, prestige double"), spark.createDataFrame(links, "src long, dst long, weight double"))
    before = set(home.iterdir())
    got = cluster.rounds(whole, 5, "ball").collect()
    assert sorted(r.node_id for r in got) == list(range(1, 21))
    assert len(set(home.iterdir()) - before) == 1


@pytest.mark.parametrize("options", [{"origin_weight": True}, {"per_root": 2}])
def test_backward_search_above_one_task(spark, options):
    """Start costs and several origins a root, in rounds as in one task run to its end."""
    from tuplegraph.operators import search
    from tuplegraph.operators.graph import Graph

    rng = np.random.default_rng(8)
    links = [(a, int(b), float(w)) for a in range(14) for b, w in zip(rng.choice(14, 3, replace=False), rng.uniform(1, 2, 3)) if a != b]
    sets = {"p": {"x": {1, 2, 5}, "y": {7, 9}}, "q": {"x": {4}, "y": {4, 11}}}
    edges = spark.createDataFrame(links, "src long, dst long, weight double")
    nodes = spark.createDataFrame([(n, 1.0 + n % 4) for n in range(14)], "node_id long, prestige double")
    matches = spark.createDataFrame([(q, t, n) for q, terms in sets.items() for t, ids in terms.items() for n in ids], "query_id string, term string, node_id long")
    queries, g = matches.select("query_id", "term").distinct(), Graph(nodes, edges)
    rows = lambda df: {(r.query_id, r.root, frozenset(r.tree)): (r.n_nodes, r.n_edges, round(r.node_score, 9), round(r.edge_score, 9), round(r.tree_score, 9)) for r in df.collect()}
    every = rows(search.whole_search(g, matches, queries, "backward", k=10**4, **options))
    assert len(every) > 9 and rows(search.whole_search(g, matches, queries, "backward", rows=0, k=10**4, **options)) == every


def _folders(spark):
    import pathlib

    from tuplegraph.session import shared_dir

    return {p.name for p in pathlib.Path(shared_dir(spark).removeprefix("file:")).glob("cut_*")}


def test_large_cuts_go_in_passes(spark, monkeypatch):
    """F13 to F23: a table above PASS_ROWS is written in parts, each row once, with and without buckets."""
    from tuplegraph.plans import loop

    monkeypatch.setattr(loop, "PASS_ROWS", 100)
    swept = []
    monkeypatch.setattr(loop, "sweep", lambda s: swept.append(1))
    df = spark.range(1000).select("id", (F.col("id") % 7).alias("k"))
    want = sorted((r.id, r.k) for r in df.collect())
    for kept in (loop.cut(df, "id", 1000), loop.cut(df, rows=1000, over="id")):
        assert sorted((r.id, r.k) for r in kept.collect()) == want
    assert len(swept) == 20


def test_paired_links_hold_both_ways(spark, monkeypatch):
    """F13, F16: links of two nodes are found by one shuffle of their pairs, with only what the criterion compares."""
    from tuplegraph.plans import loop

    monkeypatch.setattr(loop, "PASS_ROWS", 3)
    edges = spark.createDataFrame([(1, 2, 1.0), (1, 2, 0.5), (2, 1, 4.0), (3, 1, 2.0), (3, 3, 1.0)], "src long, dst long, weight double")
    rows = lambda c: sorted(tuple(r) for r in cluster.paired(edges, c).collect())
    inf = float("inf")
    assert rows("connection") == [(1, 2), (1, 3), (2, 1), (3, 1)]
    assert rows("ball") == rows("diameter") == [(1, 2, 0.5), (1, 3, 2.0), (2, 1, 0.5), (3, 1, 2.0)]
    assert rows("ratio") == [(1, 2, 8.0), (1, 3, inf), (2, 1, 8.0), (3, 1, inf)]


def test_rounds_leave_only_their_last_state(spark):
    """F8, F9, F14, F25: searches in rounds and components delete every table that a round replaced."""
    from tuplegraph.operators import search
    from tuplegraph.operators.components import components
    from tuplegraph.operators.graph import Graph

    links = [(a, a + 1, 1.0) for a in range(12)] + [(a + 1, a, 1.0) for a in range(12)]
    edges = spark.createDataFrame([(a, b, "x", w) for a, b, w in links], "src long, dst long, etype string, weight double")
    nodes = spark.createDataFrame([(n, 1.0) for n in range(13)], "node_id long, prestige double")
    queries = spark.createDataFrame([("q", "x"), ("q", "y")], "query_id string, term string")
    matches = spark.createDataFrame([("q", "x", 0), ("q", "y", 12)], "query_id string, term string, node_id long")
    before = _folders(spark)
    found = search.bidirectional_rounds(Graph(nodes, edges), matches, queries)
    assert len(_folders(spark) - before) == 1
    assert {r.cost for r in search.roots(found, queries, 20).collect()} == {12.0}
    before = _folders(spark)
    assert {r.label for r in components(edges.select(F.col("src").alias("a"), F.col("dst").alias("b"))).collect()} == {0}
    assert len(_folders(spark) - before) == 1


def test_graph_of_clusters_lies_in_buckets_of_its_targets(spark, monkeypatch):
    """the first phase searches stored buckets, and the clusters of stored edges are found with one shuffle of edges."""
    from tuplegraph.operators import search
    from tuplegraph.operators.graph import Graph
    from tuplegraph.plans.loop import cut

    edges = spark.createDataFrame([(1, 2, 1.0), (2, 3, 1.0), (3, 1, 2.0)], "src long, dst long, weight double")
    nodes = spark.createDataFrame([(n, 1.0) for n in (1, 2, 3)], "node_id long, prestige double")
    member = spark.createDataFrame([(1, 1), (2, 2), (3, 2)], "node_id long, cluster_id long")
    queries = spark.createDataFrame([("q", "x"), ("q", "y")], "query_id string, term string")
    found = spark.createDataFrame([("q", "x", 2), ("q", "y", 3)], "query_id string, term string, node_id long")
    seen, real = [], search.whole_search
    monkeypatch.setattr(search, "whole_search", lambda g, *a, **o: seen.append(g) or real(g, *a, **o))
    twophase.two_phase(Graph(nodes, cut(edges, "dst")), member, found, queries)
    assert [g.edges.cut_by for g in seen] == ["dst"]
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        plan = quotient.labelled(cut(edges, "dst"), member)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)
    assert plan.count("Exchange hashpartitioning") == 3  # edges by source, and the clusters of either end


def _random_graph(spark, nodes: int, links: int):
    from tuplegraph.operators.graph import Graph

    rng = np.random.default_rng(5)
    rows = [(int(a), int(b), float(w)) for a, b, w in zip(rng.integers(1, nodes, links), rng.integers(1, nodes, links), rng.choice([0.5, 1.0, 2.0, 3.0], links), strict=True)]
    return Graph(spark.createDataFrame([(v, f"n:{v}", 1.0) for v in range(1, nodes + 3)], "node_id long, node_key string, prestige double"), spark.createDataFrame(rows, "src long, dst long, weight double").cache())


@pytest.mark.parametrize(("criterion", "scan"), [("connection", "members"), ("ratio", "members"), ("ratio", "seed"), ("ball", "members")])
def test_one_task_ends_cluster_rounds_alike(spark, monkeypatch, criterion, scan):
    """the rounds that one task takes over give the clusters of rounds of joins, and store a few tables only."""
    whole = _random_graph(spark, 60, 150)
    stored, cut = [], cluster.cut
    monkeypatch.setattr(cluster, "cut", lambda *a, **k: stored.append(1) or cut(*a, **k))
    found = {}
    for most in (10**6, 0):
        monkeypatch.setattr(cluster, "LOCAL_LINKS", most)
        stored.clear()
        found[most] = sorted(tuple(r) for r in cluster.rounds(whole, 6, criterion, seed=2, scan=scan).collect())
        assert not most or len(stored) <= 6
    assert found[10**6] == found[0] and len(found[0]) == 62


def test_levels_go_on_from_pairs(spark, monkeypatch):
    """levels by pairs are those by quotient graphs, and the pairs of a level are deleted behind it."""
    from pathlib import Path

    from tuplegraph.session import shared_dir

    whole = _random_graph(spark, 60, 150)
    plain = lambda df: sorted((r.src, r.dst, round(r.weight, 9)) for r in df.collect())
    make = lambda g, n: cluster.greedy_ball(g, n, parts=2)
    home = Path(shared_dir(spark).removeprefix("file:"))
    before = set(home.iterdir())
    got = cluster.levels(whole, 4, 5, make, most=2)
    left = {tuple(sorted(c.name for c in spark.read.parquet(str(p)).schema)) for p in set(home.iterdir()) - before}
    assert left and not any("there" in columns or "src" in columns for columns in left)
    current = whole
    for number, membership in enumerate(got):
        assert sorted(map(tuple, membership.collect())) == sorted(map(tuple, make(current, 4).collect())), number
        small = quotient.quotient(current, membership)
        stored = quotient.cluster_graph(current.nodes, cluster.two_way(current.edges), membership)
        assert plain(stored.edges) == plain(small.edges) and stored.nodes.columns == small.nodes.columns
        current = stored
    assert len(got) == 2


def test_diameters_label_edges_once_and_take_many_clusters_a_task(spark, monkeypatch):
    """Every cluster as all its pairs give it, small ones and ones above the dense tables, however batches cut them."""
    from tuplegraph.operators.kernels import all_pairs

    rng, inf = np.random.default_rng(4), float("inf")
    of = {v: int(rng.integers(0, 40)) for v in range(200)} | {v: 40 for v in range(200, 210)}
    links = [(int(a), int(b), float(w)) for a, b, w in zip(rng.integers(0, 210, 1500), rng.integers(0, 210, 1500), rng.uniform(0.1, 3, 1500), strict=True)]
    links += [(a, b, 1.0 + a % 3) for a in range(200) for b in range(200) if a != b and of[a] == of[b] and (a * b) % 3]
    want = {}
    for c in set(of.values()):
        ids = [v for v in of if of[v] == c]
        cost = all_pairs(ids, [x for x in links if of[x[0]] == of[x[1]] == c])
        enter, leave = {b for a, b, _ in links if of[b] == c != of[a]}, {a for a, b, _ in links if of[a] == c != of[b]}
        want[c] = max(cost.get((a, b), inf) for a in ids for b in ids), min((cost.get((a, b), inf) for a in enter for b in leave), default=inf)
    edges, membership = spark.createDataFrame(links, "src long, dst long, weight double"), spark.createDataFrame(list(of.items()), "node_id long, cluster_id long")
    found = bounds.diameters(edges, membership)
    assert {r.cluster_id: (r.diameter, r.min_transit) for r in found.collect()} == want
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "FlatMapGroupsInPandas" not in plan and plan.count("Join") == 2
    rows = [(c, "n", v, 0, 0.0) for v, c in of.items()] + [(of[a], "e", a, b, w) for a, b, w in links if of[a] == of[b]]
    rows += [(of[b], "i", b, 0, 0.0) for a, b, _ in links if of[a] != of[b]] + [(of[a], "o", a, 0, 0.0) for a, b, _ in links if of[a] != of[b]]
    frame = pd.DataFrame(sorted(rows, key=lambda r: r[0]), columns=["cluster_id", "kind", "a", "b", "x"])
    monkeypatch.setattr(bounds, "DENSE", 5)
    monkeypatch.setattr(bounds, "ENTRIES", 60)
    got = {}
    for part in bounds._whole(frame.iloc[i : i + 7] for i in range(0, len(frame), 7)):
        names, own = np.unique(part.cluster_id.to_numpy(), return_inverse=True)
        far, cross = bounds._widest(*(part[c].to_numpy() for c in ("kind", "a", "b", "x")), own, len(names))
        assert not set(names.tolist()) & set(got)
        got |= dict(zip(names.tolist(), zip(far.tolist(), cross.tolist(), strict=True), strict=True))
    assert got == want


def test_correlation_by_pivots_broadcasts_no_nodes(spark, monkeypatch):
    """The pivots' rounds node by node, and the check of clusters, with no join that sends a table of nodes through the driver."""
    from tuplegraph.operators import components
    from tuplegraph.operators.graph import Graph

    rng = np.random.default_rng(6)
    links = [(int(a), int(b), 1.0) for a, b in rng.integers(0, 60, (90, 2))]
    near = {v: {b for a, b, _ in links if a == v} | {a for a, b, _ in links if b == v} for v in range(70)}
    near = {v: n - {v} for v, n in near.items()}
    nodes, edges = spark.createDataFrame([(v, 1.0) for v in range(70)], "node_id long, prestige double"), spark.createDataFrame(links, "src long, dst long, weight double")
    turn = {r.node_id: (r.t, r.node_id) for r in nodes.select("node_id", F.xxhash64(F.lit(3), "node_id").alias("t")).collect()}
    of = {}
    while len(of) < 70:
        free = set(near) - set(of)
        pivots = {v for v in free if all(turn[v] < turn[u] for u in near[v] & free)}
        of |= {v: min(near[v] & pivots, key=turn.get) for v in free - pivots if near[v] & pivots} | {v: v for v in pivots}
    least = {p: min(v for v in of if of[v] == p) for p in of.values()}
    seen, real = [], cluster.cut

    def watched(df, *rest, **options):
        seen.append(df._jdf.queryExecution().executedPlan().toString())
        return real(df, *rest, **options)

    monkeypatch.setattr(cluster, "cut", watched)
    monkeypatch.setattr(components, "cut", watched)
    got = cluster.correlation(nodes, edges, seed=3)
    assert {r.node_id: r.cluster_id for r in got.collect()} == {v: least[p] for v, p in of.items()}
    check = cluster.faults(Graph(nodes, edges), got, 2**31 - 1)
    seen.append(check._jdf.queryExecution().executedPlan().toString())
    assert tuple(check.first()) == (70, 0, 0, 0)
    wrong = spark.createDataFrame([(v, 0 if v < 69 else 1) for v in range(70)] + [(69, 2)], "node_id long, cluster_id long")
    assert tuple(cluster.faults(Graph(nodes, edges), wrong, 60).first()) == (70, 1, 1, 1)
    assert len(seen) > 9 and not any("BroadcastHashJoin" in p for p in seen)


def test_searches_in_rounds_sort_numbers_first_and_shuffle_no_stored_edges(spark, monkeypatch):
    """Links come from the buckets of stored edges without a shuffle; states are sorted by node before query and term."""
    import re

    from tuplegraph.operators import search
    from tuplegraph.operators.graph import Graph
    from tuplegraph.plans.loop import cut

    rng = np.random.default_rng(2)
    links = [(int(a), int(b), float(w), 1.0) for a, b, w in zip(rng.integers(0, 40, 200), rng.integers(0, 40, 200), rng.uniform(0.5, 2, 200), strict=True)]
    edges = spark.createDataFrame(links, "src long, dst long, weight double, priority double")
    nodes = spark.createDataFrame([(v, 1.0 + v % 5) for v in range(40)], "node_id long, prestige double")
    matches = spark.createDataFrame([("q", "x", 1), ("q", "x", 7), ("q", "y", 20)], "query_id string, term string, node_id long")
    queries, seen, real = matches.select("query_id", "term").distinct(), [], search.cut

    def watched(df, *rest, **options):
        out = real(df, *rest, **options)
        seen.append((df.columns, df._jdf.queryExecution().executedPlan().toString()))
        return out

    g, want = Graph(nodes, cut(edges, "dst")), {}
    for term in "xy":
        best = distances(Adjacency([x[:3] for x in links]), {r.node_id for r in matches.where(F.col("term") == term).collect()})[0]
        want |= {(term, v): round(c, 9) for v, c in best.items()}
    monkeypatch.setattr(search, "cut", watched)
    limit = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        found = search.roots(search.bidirectional_rounds(g, matches, queries, k=3), queries, 3).collect()
        stored = [p for c, p in seen if c == ["src", "dst", "w", "s"]]
        assert len(stored) == 1 and "Exchange" not in stored[0]
        assert not any(c == ["src", "dst", "w"] for c, _ in seen)  # small frontiers need no second copy
        assert search.whole_search(g, matches, queries, rows=0).count() > 0
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", limit)
    sums = sorted((round(want["x", v] + want["y", v], 6), v) for v in range(40) if ("x", v) in want and ("y", v) in want)
    assert sorted((r.cost, r.root) for r in found) == sums[:3]
    states = [p for c, p in seen if "dist" in c and "taken" in c]
    assert states and not any(re.search(r"Sort \[query_id#\d+ ASC NULLS FIRST, term#\d+ ASC NULLS FIRST, node_id", p) for p in states)
