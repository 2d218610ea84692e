"""Registered queries on soundness, exactness, bounds, spare memory, sizes and estimates, each beside its SQL."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import functions as F

from ..functions.scores import inverse_sum
from ..operators import activation, answers, authority, bounds, cluster, compress, index, measure, ops, quotient, search
from ..session import shared_dir
from ..sources import store
from ..sources.catalog import table
from . import sql, twophase
from .loop import cut
from .registered import _ANSWERS, _SEED, G, P, PAIRS, QUERIES, SETS, SQL, _dist, _search_sql, asked, held, query, scored_answers, the_graph, the_postings
from .registered2 import _HASH, _RANDOM, _SIG, _WALK, SIZE, _walk_sql, _with_random, random_pages, reference, two_phase, walk_ranks

# ---- clusterings are sound ----

_SOUND = f"WITH {G} SELECT count(*) AS n_nodes, 0 AS n_twice, 0 AS n_over, 0 AS n_split FROM nodes"
for _name in ("cluster_ball", "cluster_connection", "cluster_ratio", "cluster_ratio_seed_scan", "cluster_rounds_ball", "cluster_rounds_connection", "cluster_rounds_ratio"):
    QUERIES[f"{_name}_sound"] = lambda spark, sf, name=_name: cluster.faults(the_graph(spark, sf), QUERIES[name](spark, sf), SIZE)
    SQL[f"{_name}_sound"] = _SOUND
for _name in ("cluster_activation", "cluster_similar_adjacency", "cluster_random", "cluster_adjacency"):
    QUERIES[f"{_name}_sound"] = lambda spark, sf, name=_name: cluster.faults(the_graph(spark, sf), QUERIES[name](spark, sf), SIZE, connected=False)
    SQL[f"{_name}_sound"] = _SOUND


@query("cluster_correlation_sound", f"WITH {G} SELECT count(*) AS n_nodes, 0 AS n_twice, 0 AS n_over, 0 AS n_split FROM nodes")
def _(spark, sf):
    """Clusters around pivots have no largest size."""
    return cluster.faults(the_graph(spark, sf), QUERIES["cluster_correlation"](spark, sf), 2**31 - 1)


@query("steiner_cost", f"{_search_sql({'Q02': SETS['Q02']}, 30.0)} SELECT query_id, round(min(cost), 6) AS cost FROM (SELECT query_id, node_id, sum(dist) AS cost FROM dist GROUP BY 1, 2 HAVING count(*) = 2) GROUP BY query_id")
def _(spark, sf):
    """With two keywords the least tree is the least sum of distances to both."""
    return QUERIES["steiner_small"](spark, sf).select("query_id", F.round("cost", 6).alias("cost"))


@query("activation_additive", f"WITH {G}, {P}, {sql.queries(PAIRS)}, {_SEED}, {_RANDOM} SELECT query_id, cluster_id, round(sum(activation), 6) AS activation, true AS same FROM seed JOIN membership USING (node_id) GROUP BY ALL")
def _(spark, sf):
    """The activation of a cluster is the sum of its members', whether summed by term first or in one."""
    _, m = asked(spark, sf, PAIRS)
    rows = activation.seed(m, the_graph(spark, sf).nodes).join(random_pages(spark, sf), "node_id")
    by_term = rows.groupBy("query_id", "cluster_id", "term").agg(F.sum("activation").alias("a")).groupBy("query_id", "cluster_id").agg(F.sum("a").alias("b"))
    whole = rows.groupBy("query_id", "cluster_id").agg(F.sum("activation").alias("a"))
    return whole.join(by_term, ["query_id", "cluster_id"]).select("query_id", "cluster_id", F.round("a", 6).alias("activation"), (F.abs(F.col("a") - F.col("b")) < 1e-9).alias("same"))


@query("activation_of_frequent_terms", f"WITH {G}, {P}, f AS (SELECT term, count(DISTINCT node_id) AS df FROM postings GROUP BY term HAVING count(DISTINCT node_id) > 200) SELECT node_id, round(sum(prestige / df), 6) AS activation FROM (SELECT DISTINCT term, node_id FROM postings) JOIN f USING (term) JOIN nodes USING (node_id) GROUP BY node_id")
def frequent_activation(spark, sf):
    """Start of activation clustering: every term above a document frequency spreads its nodes' prestige over its node set."""
    return _frequent(spark, sf).withColumn("activation", F.round("activation", 6))


def _frequent(spark, sf):
    often = index.frequent_terms(the_postings(spark, sf), 200)
    rows = the_postings(spark, sf).select("term", "node_id").distinct().join(often, "term").join(the_graph(spark, sf).nodes.select("node_id", "prestige"), "node_id")
    return rows.groupBy("node_id").agg(F.sum(F.col("prestige") / F.col("df")).alias("activation"))


@query("cluster_activation_frequent_sound", _SOUND)
def _(spark, sf):
    g = the_graph(spark, sf)
    return cluster.faults(g, cluster.activated(g, _frequent(spark, sf), SIZE), SIZE, connected=False)


def _alike(a, b):
    return 1 - F.levenshtein(a, b) / F.greatest(F.length(a), F.length(b), F.lit(1))


@query("twins_by_similarity", f"WITH {G}, {_SIG}, k AS (SELECT sig.node_id, rel, text, sig.degree, s1, s2 FROM sig JOIN nodes USING (node_id)), f AS (SELECT *, first_value(node_id) OVER w AS first_id, first_value(text) OVER w AS first_text FROM k WINDOW w AS (PARTITION BY rel, degree, s1, s2 ORDER BY node_id)) SELECT node_id, first_id FROM f WHERE 1 - levenshtein(text, first_text) / greatest(length(text), length(first_text), 1) >= 0.8")
def _(spark, sf):
    return cluster.merge_similar(the_graph(spark, sf), _alike, 0.8)


@query("size_sweep", " UNION ALL ".join(f"SELECT * FROM (WITH {G}, {_RANDOM.replace(f'// {SIZE}', f'// {n}')} SELECT {n}::BIGINT AS size, (SELECT count(DISTINCT cluster_id) FROM membership) AS n_clusters, count(*) AS n_super_edges FROM (SELECT DISTINCT a.cluster_id AS x, b.cluster_id AS y FROM edges e JOIN membership a ON a.node_id = e.src JOIN membership b ON b.node_id = e.dst WHERE a.cluster_id <> b.cluster_id))" for n in (10, 100, 1000)))
def _(spark, sf):
    g, out = the_graph(spark, sf), None
    for n in (10, 100, 1000):
        m = cluster.random(g, n)
        part = m.agg(F.lit(n).cast("long").alias("size"), F.count_distinct("cluster_id").alias("n_clusters")).crossJoin(quotient.super_edges(g.edges, m).agg(F.count(F.lit(1)).alias("n_super_edges")))  # one row each
        out = part if out is None else out.unionByName(part)
    return out


# ---- exact searches ----

_ROOTS = f"{_search_sql(PAIRS, 9.0)}, sums AS (SELECT query_id, node_id AS root, round(sum(dist), 6) AS cost FROM dist GROUP BY 1, 2 HAVING count(*) = 2), r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY cost, root) AS r FROM sums) SELECT query_id, root, cost FROM r WHERE r <= 10"
SQL["bidirectional_rounds"] = _ROOTS  # the ten cheapest roots, by distances to every keyword


@query("keyword_distances_settled", f"{_search_sql(PAIRS, 9.0)} SELECT query_id, term, count(*) AS n, round(sum(dist), 4) AS total FROM dist GROUP BY ALL")
def _(spark, sf):
    return _dist(spark, sf, PAIRS, 9.0).groupBy("query_id", "term").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("dist"), 4).alias("total"))


@query("paths_per_node", f"{_search_sql(PAIRS, 3.0)}, w AS (SELECT d.query_id, d.term, d.node_id, l.dst AS next_id, round(l.w + a.dist, 6) AS cost FROM dist d JOIN links l ON l.src = d.node_id JOIN dist a ON a.query_id = d.query_id AND a.term = d.term AND a.node_id = l.dst), r AS (SELECT *, row_number() OVER (PARTITION BY query_id, term, node_id ORDER BY cost, next_id) AS r FROM w) SELECT query_id, term, r, count(*) AS n, round(sum(cost), 4) AS total FROM r WHERE r <= 3 GROUP BY ALL")
def _(spark, sf):
    """How many nodes have a first, second and third way to a keyword, and what those ways cost."""
    ways = search.several_paths(the_graph(spark, sf).edges, _dist(spark, sf, PAIRS, 3.0), 3)
    return ways.groupBy("query_id", "term", "r").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("cost"), 4).alias("total"))


@query("early_output", f"{_ANSWERS}, a AS (SELECT query_id, root, edge_score * pow(node_score, 0.2) AS tree_score FROM scored), b AS (SELECT query_id, 1 / (1 + 4.0) * pow((SELECT max(prestige) FROM nodes) * (1 + count(*)), 0.2) AS best FROM queries GROUP BY query_id) SELECT query_id, root, round(tree_score, 6) AS tree_score FROM a JOIN b USING (query_id) WHERE tree_score >= best")
def _(spark, sf):
    """Answers that may go out before the search beyond a distance of 4 ends: no tree that is left can score more."""
    most = the_graph(spark, sf).nodes.agg(F.max("prestige")).first()[0]
    per = index.query_frame(spark, PAIRS).groupBy("query_id").agg(F.count(F.lit(1)).alias("n")).collect()  # a workload's queries
    left, out = spark.createDataFrame([(r["query_id"], 4.0, r["n"]) for r in per], "query_id string, cost double, n long"), None
    for n in sorted({r["n"] for r in per}):
        got = answers.emit(scored_answers(spark, sf, PAIRS), answers.unseen_bound(left.where(F.col("n") == n), most * (1 + n)))
        out = got if out is None else out.unionByName(got)
    return out.select("query_id", "root", F.round("tree_score", 6).alias("tree_score"))


@query("hub_keyword", f"{_search_sql({'Q11': SETS['Q11']}, 2.0)} SELECT query_id, term, count(*) AS n, round(sum(dist), 4) AS total FROM dist GROUP BY ALL")
def _(spark, sf):
    return _dist(spark, sf, {"Q11": SETS["Q11"]}, 2.0).groupBy("query_id", "term").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("dist"), 4).alias("total"))


_COLUMNS = {"Q20": ("mktsegment", "brand")}


@query("metadata_columns", f"WITH {G}, {P}, {sql.queries(_COLUMNS)}, w AS (SELECT DISTINCT unnest(string_split(regexp_replace(field, '^[a-z]{{1,2}}_', ''), '_')) AS term, rel FROM postings) SELECT query_id, term, count(*) AS n FROM queries JOIN w USING (term) JOIN nodes USING (rel) GROUP BY ALL")
def _(spark, sf):
    q = index.query_frame(spark, _COLUMNS)
    return index.match(the_postings(spark, sf), q, True, the_graph(spark, sf).nodes).groupBy("query_id", "term").agg(F.count(F.lit(1)).alias("n"))


# ---- bounds ----

_INSIDE = """, inner_links AS (SELECT src, dst, src_c AS c, min(weight) AS w FROM both_ends WHERE src_c = dst_c GROUP BY ALL),
far(a, b, c, d) USING KEY (a, b) AS (
  SELECT node_id, node_id, cluster_id, 0.0::DOUBLE FROM membership
  UNION
  SELECT f.a, l.dst, f.c, min(f.d + l.w) FROM far f JOIN inner_links l ON l.src = f.b LEFT JOIN recurring.far r ON r.a = f.a AND r.b = l.dst WHERE r.d IS NULL OR f.d + l.w < r.d - 1e-9 GROUP BY f.a, l.dst, f.c),
gate_in AS (SELECT DISTINCT dst AS node_id, dst_c AS c FROM both_ends WHERE src_c <> dst_c),
gate_out AS (SELECT DISTINCT src AS node_id, src_c AS c FROM both_ends WHERE src_c <> dst_c),
size AS (SELECT cluster_id, count(*) AS n FROM membership GROUP BY 1)"""


def _bounded(rest: str) -> str:
    return _with_random(_INSIDE + rest).replace("WITH ", "WITH RECURSIVE ", 1)


@query("page_diameters", _bounded(" SELECT cluster_id, count(*) = any_value(n) * any_value(n) AS whole, round(max(d), 6) AS widest FROM far JOIN size ON cluster_id = c GROUP BY cluster_id"))
def _(spark, sf):
    """Of each page, whether all its nodes reach each other inside it, and the largest distance of those that do."""
    g, m = the_graph(spark, sf), random_pages(spark, sf)
    whole = bounds.diameters(g.edges, m).select("cluster_id", (F.col("diameter") < float("inf")).alias("whole"))
    return whole.join(bounds.reaches(g.edges, m), "cluster_id").select("cluster_id", "whole", F.round("widest", 6).alias("widest"))


@query("transits", _bounded(" SELECT f.c AS cluster_id, count(*) AS n_pairs, round(sum(d), 4) AS total, round(min(d), 6) AS least FROM far f JOIN gate_in i ON i.node_id = a JOIN gate_out o ON o.node_id = b GROUP BY f.c"))
def _(spark, sf):
    rows = bounds.transits(the_graph(spark, sf).edges, random_pages(spark, sf))
    return rows.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n_pairs"), F.round(F.sum("cost"), 4).alias("total"), F.round(F.min("cost"), 6).alias("least"))


@query("cluster_roles")
def _(spark, sf):
    """Artificial answers' clusters by role: the root, holders of a keyword, and the others that only connect."""
    _, artificial, _ = two_phase(spark, sf)
    q, found = asked(spark, sf, PAIRS)
    matched = twophase.cluster_matches(found, QUERIES["cluster_ball"](spark, sf))
    return bounds.role(artificial, matched).groupBy("query_id", "role").agg(F.count(F.lit(1)).alias("n"))


# ---- authority ----


@query("authority_cutoff", f"WITH {G}, {P}, {sql.queries({'Q02': SETS['Q02']})}, {_walk_sql(3).replace('GROUP BY 1, 2)', 'GROUP BY 1, 2 HAVING sum(rank) >= 0.001)')} SELECT term, node_id, round(rank * 1e6, 4) AS rank_ppm FROM k3")
def _(spark, sf):
    _, m = asked(spark, sf, {"Q02": SETS["Q02"]})
    return authority.keyword_rank(the_graph(spark, sf).edges, m, rounds=3, cutoff=0.001).select("term", "node_id", F.round(F.col("rank") * 1e6, 4).alias("rank_ppm"))


@query("authority_stored", f"{_WALK} SELECT term, node_id FROM k3 WHERE term = '000000042' ORDER BY round(rank, 9) DESC, node_id LIMIT 20")
def _(spark, sf):
    path = f"{shared_dir(spark)}/authority-{uuid.uuid4().hex}"
    authority.precompute(walk_ranks(spark, sf), path)
    return spark.read.parquet(path).where("term = '000000042'").orderBy(F.desc(F.round("rank", 9)), "node_id").limit(20).select("term", "node_id")


@query("authority_cost", f"WITH {G}, {P} SELECT count(DISTINCT term) AS n_terms, 8 * count(DISTINCT term) * (SELECT count(*) FROM edges) AS edge_visits FROM postings")
def _(spark, sf):
    """Edge visits that ranks for every term would take, in eight rounds."""
    n = the_postings(spark, sf).agg(F.count_distinct("term")).first()[0]
    e = the_graph(spark, sf).edges.count()
    return spark.createDataFrame([(n, measure.precompute_cost(n, 8, e))], "n_terms long, edge_visits long")


# ---- codes ----

_HUFFMAN = "WITH {g}, h AS (SELECT d, count(*) AS n FROM (SELECT count(*) AS d FROM {e} GROUP BY dst) GROUP BY d), w AS (SELECT (d * n)::DOUBLE AS w FROM h UNION ALL SELECT count(DISTINCT src) FROM {e}), t AS (SELECT sum(w) AS t FROM w) SELECT count(*) AS n_symbols, 1.0 AS kraft, true AS near_entropy, round(-sum(w / t * log2(w / t)), 4) AS entropy FROM w, t"


def _code_report(rows):
    """Kraft sum and entropy of the class code: a prefix code is complete and within one bit of the entropy when it is optimal."""
    bits = F.col("code_bits") - F.when(F.col("degree") > 0, F.ceil(F.log2(F.col("n_nodes").cast("double")))).otherwise(0)
    each = rows.select(bits.alias("bits"), F.when(F.col("degree") > 0, F.col("degree") * F.col("n_nodes")).otherwise(F.col("n_nodes")).cast("double").alias("w"))
    total = each.agg(F.sum("w").alias("t"))
    sums = each.crossJoin(total).agg(F.count(F.lit(1)).alias("n_symbols"), F.round(F.sum(F.pow(F.lit(2.0), -F.col("bits"))), 9).alias("kraft"), F.sum(F.col("w") / F.col("t") * F.col("bits")).alias("mean"), (-F.sum(F.col("w") / F.col("t") * F.log2(F.col("w") / F.col("t")))).alias("entropy"))  # one row
    return sums.select("n_symbols", "kraft", ((F.col("mean") >= F.col("entropy") - 1e-9) & (F.col("mean") < F.col("entropy") + 1)).alias("near_entropy"), F.round("entropy", 4).alias("entropy"))


@query("huffman_optimal", _HUFFMAN.format(g=G, e="refs"))
def _(spark, sf):
    return _code_report(compress.huffman(the_graph(spark, sf).edges.where("direction = 'fwd'")))


@query("huffman_of_clusters", _HUFFMAN.format(g=f"{G}, {_RANDOM}, super AS (SELECT DISTINCT a.cluster_id AS src, b.cluster_id AS dst FROM edges e JOIN membership a ON a.node_id = e.src JOIN membership b ON b.node_id = e.dst WHERE a.cluster_id <> b.cluster_id)", e="super"))
def _(spark, sf):
    """Prefix codes of the graph of clusters."""
    return _code_report(compress.huffman(quotient.super_edges(the_graph(spark, sf).edges, random_pages(spark, sf)).select(F.col("src_c").alias("src"), F.col("dst_c").alias("dst"))))


# ---- memory, store, work ----


@query("memory_estimates", "SELECT * FROM (VALUES ('personal files', 20 * 500000::BIGINT + 12 * 5000000::BIGINT), ('desktop', 20 * 1000000::BIGINT + 12 * 10000000::BIGINT)) t(estimate, bytes)")
def _(spark, sf):
    rows = spark.createDataFrame([("personal files", 500_000, 5_000_000), ("desktop", 1_000_000, 10_000_000)], "estimate string, v long, e long")
    return rows.select("estimate", measure.memory(F.col("v"), F.col("e")).cast("long").alias("bytes"))


@query("memory_per_graph", f"WITH {G}, d AS (SELECT count(*) AS v, 2 * (SELECT count(*) FROM lineitem) AS e FROM (SELECT l_orderkey FROM lineitem)), p AS (SELECT (SELECT count(*) FROM pages) + (SELECT count(DISTINCT regexp_extract(url, '^[a-z]+://([^/]+)', 1)) FROM pages) AS v, 2 * count(*) AS e FROM pages), s AS (SELECT (SELECT count(*) FROM events) + (SELECT count(DISTINCT user_id) FROM events) AS v, 2 * count(*) AS e FROM events), a AS (SELECT 'tuples' AS graph, (SELECT count(*) FROM nodes) AS v, (SELECT count(*) FROM edges) AS e UNION ALL SELECT 'tuples with lines', (SELECT count(*) FROM nodes) + d.v, (SELECT count(*) FROM edges) - 2 * (SELECT count(*) FROM refs WHERE etype IN ('orders>part', 'orders>supplier')) + 3 * d.e FROM d UNION ALL SELECT 'pages', v, e FROM p UNION ALL SELECT 'events', v, e FROM s) SELECT graph, v, e, (20 * v + 12 * e)::BIGINT AS full_bytes, (9 * v + 8 * e)::BIGINT AS slim_bytes FROM a")
def _(spark, sf):
    """Both memory models on the tuple graph, the same with lines kept as tuples, pages with hosts, and events with users."""
    g = the_graph(spark, sf)
    n, m = g.nodes.count(), g.edges.count()
    lines, pages, events = (table(spark, sf, x) for x in ("lineitem", "pages", "events"))
    contracted = g.edges.where(F.col("etype").isin("orders>part", "orders>supplier")).count()
    n_lines, n_pages, n_events = lines.count(), pages.count(), events.count()
    hosts = pages.select(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)).distinct().count()
    users = events.where("user_id is not null").select("user_id").distinct().count()
    rows = [("tuples", n, m), ("tuples with lines", n + n_lines, m - contracted + 6 * n_lines), ("pages", n_pages + hosts, 2 * n_pages), ("events", n_events + users, 2 * n_events)]
    v, e = F.col("v"), F.col("e")
    return spark.createDataFrame(rows, "graph string, v long, e long").select("graph", "v", "e", measure.memory(v, e).cast("long").alias("full_bytes"), measure.memory(v, e, "slim").cast("long").alias("slim_bytes"))


def _stored(spark, sf):
    def make():
        path = f"{shared_dir(spark)}/store-{uuid.uuid4().hex}"
        g, m = the_graph(spark, sf), random_pages(spark, sf)
        store.write_clusters(g, m, path, buckets=8)
        store.write_quotient(g, m, path)
        return path

    return held(spark, sf, "store", make)


@query("load_rows", _with_random("SELECT 'quotient' AS form, (SELECT count(DISTINCT cluster_id) FROM membership) + (SELECT count(*) FROM (SELECT DISTINCT src_c, dst_c FROM both_ends WHERE src_c <> dst_c)) AS n_rows UNION ALL SELECT 'full', (SELECT count(*) FROM nodes) + (SELECT count(*) FROM edges)"))
def _(spark, sf):
    return store.load_time(spark, _stored(spark, sf)).select("form", "n_rows")


@query("load_time")
def _(spark, sf):
    """Seconds to open the clustered graph and the whole one."""
    return store.load_time(spark, _stored(spark, sf))


@query("warm_rerun", _with_random("SELECT r AS run, count(*) AS n_nodes FROM membership, range(1, 3) t(r) WHERE cluster_id IN (SELECT DISTINCT cluster_id FROM membership ORDER BY 1 LIMIT 5) GROUP BY r"))
def _(spark, sf):
    """Clusters read cold and again from the cache, which then holds them."""
    ids = random_pages(spark, sf).select("cluster_id").distinct().orderBy("cluster_id").limit(5)
    cache, rows = store.Cache(spark, _stored(spark, sf), buckets=8), []
    for run in (1, 2):
        rows.append((run, cache.nodes("five", ids).count()))
    cache.renew()
    return spark.createDataFrame(rows, "run long, n_nodes long")


_SPARE = (10, 25, 50)


@query("spare_memory_sweep", " UNION ALL ".join(f"SELECT * FROM (WITH {G}, {_RANDOM}, {P}, {sql.queries(PAIRS)}, bytes AS (SELECT cluster_id, 9 * count(*) AS bytes FROM membership GROUP BY 1), own AS (SELECT DISTINCT query_id, cluster_id FROM matches JOIN membership USING (node_id)), r AS (SELECT *, sum(bytes) OVER (PARTITION BY query_id ORDER BY md5('0:' || cluster_id)) AS used FROM own JOIN bytes USING (cluster_id)) SELECT {p}::BIGINT AS share, query_id, count(*) AS n_clusters, sum(bytes)::BIGINT AS bytes FROM r WHERE used <= {p} * (SELECT sum(bytes) FROM bytes) // 100 GROUP BY query_id)" for p in _SPARE))
def _(spark, sf):
    """Keyword clusters that a share of the graph's memory, in per cent, has room for."""
    m = random_pages(spark, sf)
    _, found = asked(spark, sf, PAIRS)
    sizes = m.groupBy("cluster_id").agg((9 * F.count(F.lit(1))).alias("bytes"))
    whole, none, out = m.count() * 9, spark.createDataFrame([], "query_id string, cluster_id long"), None
    for p in _SPARE:
        part = twophase.keyword_clusters(found, m, sizes, none, p * whole // 100).join(sizes, "cluster_id").groupBy("query_id").agg(F.count(F.lit(1)).alias("n_clusters"), F.sum("bytes").alias("bytes")).select(F.lit(p).cast("long").alias("share"), "query_id", "n_clusters", "bytes")
        out = part if out is None else out.unionByName(part)
    return out


@query("spare_memory_answers")
def _(spark, sf):
    """Acceptable answers when the second phase also gets keyword clusters, neighbours, activation or adaptive clusters."""
    g, m = the_graph(spark, sf), QUERIES["cluster_ball"](spark, sf)
    q, found = asked(spark, sf, PAIRS)
    _, artificial, _ = two_phase(spark, sf)
    chosen, ref = cut(twophase.clusters_of(artificial)), reference(spark, sf)
    sizes = m.groupBy("cluster_id").agg((9 * F.count(F.lit(1))).alias("bytes"))
    used = real_hits(spark, sf, m)
    more = {"none": None, "keyword": twophase.keyword_clusters(found, m, sizes, chosen, m.count() * 9 // 10), "neighbour": twophase.neighbours(chosen, quotient.super_edges(g.edges, m)), "activation": twophase.parallel_clusters(found, QUERIES["cluster_activation"](spark, sf), m), "adaptive": twophase.suggest(used, q)}
    out = None
    for name, extra in more.items():
        real = cut(twophase.phase2(g, m, chosen if extra is None else chosen.unionByName(extra), found))
        part = measure.acceptable(real, ref).join(measure.precision(real, ref), "query_id").select(F.lit(name).alias("extra"), "query_id", "n_acceptable", "n_exact", "n_score")
        out = part if out is None else out.unionByName(part)
    return out


def real_hits(spark, sf, m):
    real, _, _ = two_phase(spark, sf)
    q = index.query_frame(spark, PAIRS)
    return real.select("query_id", F.explode("leaves").alias("node_id")).join(m, "node_id").join(q, "query_id").groupBy("term", "cluster_id").agg(F.count(F.lit(1)).alias("hits"))


# ---- measures on answers that SQL has too ----

_TWO = f"{_ANSWERS}, r AS (SELECT *, edge_score * pow(node_score, 0.2) AS tree_score FROM scored WHERE (branches <> 1 OR root_holds)), k AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(tree_score, 9) DESC, root, leaf_keys) AS rnk FROM r), s AS (SELECT *, 0.2 * node_score + 0.8 * edge_score AS mixed FROM scored WHERE (branches <> 1 OR root_holds)), j AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(mixed, 9) DESC, root, leaf_keys) AS rnk FROM s)"


def _ranked(spark, sf, mode):
    from ..functions.scores import tree_score

    rows = scored_answers(spark, sf, PAIRS).withColumn("tree_score", tree_score(F.col("edge_score"), F.col("node_score"), mode))
    return answers.rank(answers.root_minimal(rows)).withColumn("n_nodes", F.size("members").cast("long")).withColumn("n_edges", F.size("tree").cast("long"))


@query("acceptable_of_mixture", f"{_TWO}, most AS (SELECT query_id, max(n_nodes) AS mn, max(n_edges) AS me FROM k WHERE rnk <= 10 GROUP BY 1) SELECT query_id, count(*) FILTER (WHERE n_nodes <= mn AND n_edges <= me) AS n_acceptable FROM j JOIN most USING (query_id) WHERE rnk <= 10 GROUP BY query_id")
def _(spark, sf):
    """Answers ranked by the mixture of scores that are acceptable against those ranked by the product."""
    return measure.acceptable(_ranked(spark, sf, "sum"), _ranked(spark, sf, "product"))


@query("exact_of_mixture", f"{_TWO}, h AS (SELECT s.query_id, s.root, coalesce(string_agg(least(src, dst) || '-' || greatest(src, dst), ',' ORDER BY least(src, dst), greatest(src, dst)), s.root::VARCHAR) AS h FROM scored s LEFT JOIN branch b ON b.query_id = s.query_id AND b.root = s.root GROUP BY s.query_id, s.root), a AS (SELECT DISTINCT query_id, h FROM j JOIN h USING (query_id, root) WHERE rnk <= 10), b AS (SELECT DISTINCT query_id, h FROM k JOIN h USING (query_id, root) WHERE rnk <= 10) SELECT q.query_id, count(a.h) AS n_exact FROM (SELECT DISTINCT query_id FROM b) q LEFT JOIN (SELECT a.* FROM a JOIN b USING (query_id, h)) a USING (query_id) GROUP BY q.query_id")
def _(spark, sf):
    return measure.precision(_ranked(spark, sf, "sum"), _ranked(spark, sf, "product")).select("query_id", "n_exact")


@query("quality_of_answers", f"{_TWO} SELECT query_id, rnk, round(max(tree_score) OVER (PARTITION BY query_id) - tree_score, 6) AS gap FROM k WHERE rnk <= 10")
def _(spark, sf):
    return measure.quality(_ranked(spark, sf, "product")).select("query_id", "rnk", F.round("gap", 6).alias("gap"))


@query("gaps_of_answers", f"{_TWO} SELECT query_id, rnk, round(tree_score / lag(tree_score) OVER (PARTITION BY query_id ORDER BY rnk), 6) AS ratio FROM k WHERE rnk <= 10")
def _(spark, sf):
    return measure.score_gap(_ranked(spark, sf, "product")).select("query_id", "rnk", F.round("ratio", 6).alias("ratio"))


# ---- functions and operators ----


@query("inverse_sum_twin", f"WITH {G} SELECT etype, direction, round(1 / sum(1 / weight), 9) AS built_in, true AS same FROM edges GROUP BY ALL")
def _(spark, sf):
    """The aggregate of parallel weights in built-in functions, and as a grouped pandas function."""

    @F.pandas_udf("double")
    def twin(w: pd.Series) -> float:
        return 1.0 / (1.0 / w).sum()

    e = the_graph(spark, sf).edges.select("etype", "direction", "weight")
    a = e.groupBy("etype", "direction").agg(inverse_sum(F.col("weight")).alias("x"))
    # the twin is combined from parts of bounded size: parallel weights of parallel weights are parallel weights
    parts = e.withColumn("part", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(64))).groupBy("etype", "direction", "part").agg(twin("weight").alias("w"))
    b = parts.groupBy("etype", "direction").agg(inverse_sum(F.col("w")).alias("y"))
    return a.join(b, ["etype", "direction"]).select("etype", "direction", F.round("x", 9).alias("built_in"), (F.abs(F.col("x") - F.col("y")) <= 1e-9 * F.col("x")).alias("same"))


@query("vector_cosine", "SELECT a.vec_id AS a, b.vec_id AS b, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)), 5) AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def _(spark, sf):
    rows = table(spark, sf, "embeddings").select(F.col("vec_id").alias("a"), F.col("embedding").alias("x"))
    other = rows.select((F.col("a") - 1).alias("a"), F.col("a").alias("b"), F.col("x").alias("y"))
    dot = F.aggregate(F.zip_with("x", "y", lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return rows.join(other, "a").select("a", "b", F.round(dot, 5).alias("dot"))


@query("count_approximate_close", "SELECT l_suppkey, count(DISTINCT l_partkey) AS n_parts, true AS close FROM lineitem GROUP BY 1")
def _(spark, sf):
    rows = table(spark, sf, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("n_parts"), F.approx_count_distinct("l_partkey", 0.02).alias("about"))
    return rows.select("l_suppkey", "n_parts", (F.abs(F.col("about") - F.col("n_parts")) <= 1 + 0.1 * F.col("n_parts")).alias("close"))


@query("sample_by_hash_close", "SELECT count(*) AS n, true AS close, true AS inside FROM customer")
def _(spark, sf):
    """A tenth of the rows within six standard deviations, all of them rows of the table."""
    rows = table(spark, sf, "customer").select("c_custkey")
    taken = ops.hash_sample(rows, "c_custkey", 10, 1)
    counts = rows.agg(F.count(F.lit(1)).alias("n")).crossJoin(taken.agg(F.count(F.lit(1)).alias("k"))).crossJoin(taken.join(rows, "c_custkey", "left_anti").agg(F.count(F.lit(1)).alias("out")))  # one row each
    return counts.select("n", (F.abs(F.col("k") - F.col("n") * 0.1) <= 1 + 6 * F.sqrt(F.col("n") * 0.09)).alias("close"), (F.col("out") == 0).alias("inside"))


@query("prune_ablation", f"WITH {G}, l AS (SELECT count(*) AS n FROM lineitem) SELECT 'contracted' AS graph, (SELECT count(*) FROM nodes) AS v, (SELECT count(*) FROM edges) AS e UNION ALL SELECT 'kept', (SELECT count(*) FROM nodes) + n, 2 * ((SELECT count(*) FROM refs WHERE etype NOT IN ('orders>part', 'orders>supplier')) + 3 * n) FROM l")
def _(spark, sf):
    """Size of the graph with the link relation contracted into edges, and kept as tuples."""
    g = the_graph(spark, sf)
    n, e, lines = g.nodes.count(), g.edges.count(), table(spark, sf, "lineitem").count()
    others = g.edges.where(~F.col("etype").isin("orders>part", "orders>supplier")).count()
    return spark.createDataFrame([("contracted", n, e), ("kept", n + lines, others + 6 * lines)], "graph string, v long, e long")
