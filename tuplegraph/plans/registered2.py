"""Registered queries on clusters, the clustered graph, two-phase search, baselines, measures and compression."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from functools import reduce
from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import udf
from ..operators import activation, answers, authority, bounds, browse, cluster, compress, graph, index, jointree, measure, quotient, search
from ..operators.components import components
from ..sources import store
from ..session import shared_dir
from ..sources.catalog import table
from . import sql, twophase
from .loop import cut
from .registered import G, P, PAIRS, QUERIES, SETS, SQL, _ASKED, _dist, _local, _search_sql, asked, held, query, the_graph, the_postings

SIZE = 25

# ---- clusters ----

_HASH = lambda x, half=0: f"('0x' || substr(md5({x}), {1 + 16 * half}, 15))::BIGINT"
_ENTRY = "dst || ':' || round(weight * 1e6)::BIGINT"
_SIG = f"sig AS (SELECT node_id, prestige, coalesce(degree, 0) AS degree, coalesce(s1, 0) AS s1, coalesce(s2, 0) AS s2 FROM nodes LEFT JOIN (SELECT src AS node_id, count(*) AS degree, sum({_HASH(_ENTRY)}) AS s1, sum({_HASH(_ENTRY, 1)}) AS s2 FROM edges GROUP BY src) USING (node_id))"
_RANDOM = f"pages AS (SELECT node_id, (row_number() OVER (ORDER BY {_HASH('node_key')}, node_id) - 1) // {SIZE} AS g FROM nodes), membership AS (SELECT node_id, min(node_id) OVER (PARTITION BY g) AS cluster_id FROM pages)"


def _with_random(rest: str) -> str:
    return f"WITH {G}, {_RANDOM}, both_ends AS (SELECT e.*, a.cluster_id AS src_c, b.cluster_id AS dst_c FROM edges e JOIN membership a ON a.node_id = e.src JOIN membership b ON b.node_id = e.dst) {rest}"


def random_pages(spark, sf):
    return held(spark, sf, "random", lambda: cut(cluster.random(the_graph(spark, sf), SIZE)))


@query("cluster_adjacency", f"WITH {G}, {_SIG}, n AS (SELECT *, (row_number() OVER (PARTITION BY prestige, degree, s1, s2 ORDER BY node_id) - 1) // {SIZE} AS k FROM sig) SELECT node_id, min(node_id) OVER (PARTITION BY prestige, degree, s1, s2, k) AS cluster_id FROM n")
def _(spark, sf):
    return cluster.adjacency(the_graph(spark, sf), SIZE)


@query("cluster_random", f"WITH {G}, {_RANDOM} SELECT node_id, cluster_id FROM membership")
def _(spark, sf):
    return random_pages(spark, sf)


@query("cluster_similar_adjacency")
def _(spark, sf):
    return cluster.similar_adjacency(the_graph(spark, sf), SIZE)


@query("cluster_connection")
def _(spark, sf):
    return held(spark, sf, "connection", lambda: cut(cluster.connection(the_graph(spark, sf), SIZE)))


@query("cluster_ratio")
def _(spark, sf):
    return held(spark, sf, "ratio", lambda: cut(cluster.ratio(the_graph(spark, sf), SIZE)))


@query("cluster_ratio_seed_scan")
def _(spark, sf):
    return cluster.ratio(the_graph(spark, sf), SIZE, scan="seed")


def small_graph(spark, sf):
    """Nations, regions, customers and suppliers only."""
    g = the_graph(spark, sf)
    few = g.nodes.where(F.col("rel").isin("region", "nation", "customer", "supplier"))
    edges = g.edges.where(F.col("etype").isin("nation>region", "customer>nation", "supplier>nation"))
    return graph.Graph(few, edges)


@query("cluster_diameter")
def _(spark, sf):
    return cluster.ratio(small_graph(spark, sf), 8, criterion="diameter")


@query("cluster_ball")
def _(spark, sf):
    return held(spark, sf, "ball", lambda: cut(cluster.greedy_ball(the_graph(spark, sf), SIZE)))


@query("cluster_rounds_connection")
def _(spark, sf):
    return held(spark, sf, "rounds connection", lambda: cut(cluster.rounds(the_graph(spark, sf), SIZE, "connection")))


@query("cluster_rounds_ball")
def _(spark, sf):
    return held(spark, sf, "rounds ball", lambda: cut(cluster.rounds(the_graph(spark, sf), SIZE, "ball")))


@query("cluster_rounds_ratio")
def _(spark, sf):
    return held(spark, sf, "rounds ratio", lambda: cut(cluster.rounds(the_graph(spark, sf), SIZE, "ratio")))


@query("cluster_activation")
def _(spark, sf):
    g = the_graph(spark, sf)
    q, m = asked(spark, sf, PAIRS)
    act = activation.seed(m, g.nodes).groupBy("node_id").agg(F.sum("activation").alias("activation"))
    return cluster.activated(g, act, SIZE)


@query("cluster_correlation")
def _(spark, sf):
    g = the_graph(spark, sf)
    return cluster.correlation(g.nodes, g.edges)


@query("coarse_partition", f"WITH RECURSIVE {G}, l AS (SELECT src AS a, dst AS b FROM edges WHERE weight <= 3.0 UNION SELECT dst, src FROM edges WHERE weight <= 3.0), c(node_id, label) USING KEY (node_id) AS (SELECT node_id, node_id FROM nodes UNION SELECT l.b, min(c.label) FROM c JOIN l ON l.a = c.node_id JOIN recurring.c r ON r.node_id = l.b WHERE c.label < r.label GROUP BY l.b) SELECT node_id, label AS cluster_id FROM c")
def _(spark, sf):
    return cluster.coarse_by_links(the_graph(spark, sf), 3.0)


def page_graph(spark, sf):
    """Pages, hosts and the words of links: edges from pages to both."""
    pages = table(spark, sf, "pages")
    host = F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)
    words = pages.select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))).alias("w"))
    links = pages.select("page_id", F.concat(F.lit("host:"), host).alias("to")).unionByName(words.select("page_id", F.concat(F.lit("word:"), "w").alias("to")))
    number = lambda c: cluster.hash60(F.col(c))
    edges = links.select(F.concat(F.lit("page:"), F.col("page_id").cast("string")).alias("a"), F.col("to").alias("b"))
    edges = edges.select(number("a").alias("src"), number("b").alias("dst"), F.lit("page>x").alias("etype"), F.lit("fwd").alias("direction"), F.lit(1.0).alias("weight"), F.lit(1.0).alias("priority"), "a", "b")
    nodes = edges.select(F.col("src").alias("node_id"), F.col("a").alias("node_key"), F.lit("page").alias("rel")).union(edges.select("dst", "b", F.split("b", ":")[0])).distinct().withColumn("prestige", F.lit(1.0)).withColumn("text", F.lit(""))
    start = edges.where("b like 'host:%'").select(F.col("src").alias("node_id"), F.col("dst").alias("cluster_id"))
    rest = nodes.join(start, "node_id", "left_anti").select("node_id", F.col("node_id").alias("cluster_id"))
    return graph.Graph(cut(nodes), cut(edges.drop("a", "b"))), start.unionByName(rest)


@query("page_host_edges", """SELECT 'page:' || page_id AS page, 'host:' || regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM pages""")
def _(spark, sf):
    return table(spark, sf, "pages").select(F.concat(F.lit("page:"), F.col("page_id").cast("string")).alias("page"), F.concat(F.lit("host:"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)).alias("host"))


@query("cluster_refined")
def _(spark, sf):
    g, start = page_graph(spark, sf)
    return cluster.refine(g, start, "largest")


@query("cluster_refined_random")
def _(spark, sf):
    g, start = page_graph(spark, sf)
    return cluster.refine(g, start, "random")


@query("cluster_levels")
def _(spark, sf):
    g, out = the_graph(spark, sf), None
    ball = lambda at, n: QUERIES["cluster_ball"](spark, sf) if at.nodes is g.nodes else cluster.greedy_ball(at, n)
    for i, m in enumerate(cluster.levels(g, SIZE, fit=100, technique=ball)):
        part = m.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)).alias("n_clusters"), F.max("n").alias("largest")).withColumn("level", F.lit(i))
        out = part if out is None else out.unionByName(part)
    return out


@query("cluster_layout", _with_random("SELECT cluster_id, n_nodes, coalesce(sum(n_nodes) OVER (ORDER BY cluster_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS \"offset\" FROM (SELECT cluster_id, count(*) AS n_nodes FROM membership GROUP BY 1)"))
def _(spark, sf):
    return cluster.represent(random_pages(spark, sf))[1]


@query("twins_merged", f"WITH {G}, {_SIG} SELECT rel, min(node_id) AS first_id, count(*) AS n_nodes, array_to_string(list_sort(list(DISTINCT text)), ' | ') AS text FROM sig JOIN nodes USING (node_id) GROUP BY rel, sig.degree, s1, s2")
def _(spark, sf):
    return cluster.merge_twins(the_graph(spark, sf))


@query("tightness", _with_random("SELECT m.node_id, m.cluster_id, round(coalesce(w, 0) / n, 6) AS tightness, coalesce(w, 0) / n >= 0.1 AS tight FROM membership m JOIN (SELECT cluster_id, count(*) AS n FROM membership GROUP BY 1) USING (cluster_id) LEFT JOIN (SELECT src AS node_id, sum(weight) AS w FROM both_ends WHERE src_c = dst_c GROUP BY 1) USING (node_id)"))
def _(spark, sf):
    return measure.tightness(the_graph(spark, sf).edges, random_pages(spark, sf), 0.1).withColumn("tightness", F.round("tightness", 6))


@query("cluster_cut_report", _with_random("SELECT CASE WHEN src_c = dst_c THEN 'inside' ELSE 'across' END AS place, count(*) AS n_edges, round(avg(weight), 6) AS mean_weight FROM both_ends GROUP BY 1"))
def _(spark, sf):
    return measure.cut_report(the_graph(spark, sf).edges, random_pages(spark, sf))


@query("cluster_objective", _with_random("SELECT (SELECT count(DISTINCT cluster_id) FROM membership) AS n_clusters, (SELECT max(n) FROM (SELECT count(*) AS n FROM membership GROUP BY cluster_id)) AS largest, 9 * (SELECT count(DISTINCT cluster_id) FROM membership) + 8 * (SELECT count(*) FROM (SELECT DISTINCT src_c, dst_c FROM both_ends WHERE src_c <> dst_c)) AS slim_bytes"))
def _(spark, sf):
    return measure.objective(the_graph(spark, sf), random_pages(spark, sf))


@query("cluster_keyword_map", f"WITH {G}, {_RANDOM}, {P} SELECT term, count(DISTINCT cluster_id) AS n_clusters FROM postings JOIN membership USING (node_id) GROUP BY term")
def _(spark, sf):
    return index.cluster_postings(the_postings(spark, sf), random_pages(spark, sf)).groupBy("term").agg(F.count(F.lit(1)).alias("n_clusters"))


# ---- graph of clusters ----

for _name, _value in (("inverse", "1 / sum(1 / weight)"), ("harmonic", "count(*) / sum(1 / weight)"), ("min", "min(weight)")):
    _mode = {"inverse": "inverse_sum"}.get(_name, _name)
    QUERIES[f"super_edges_{_name}"] = lambda spark, sf, mode=_mode: quotient.super_edges(the_graph(spark, sf).edges, random_pages(spark, sf), mode).select("src_c", "dst_c", "n_links", F.round("weight", 6).alias("weight"))
    SQL[f"super_edges_{_name}"] = _with_random(f"SELECT src_c, dst_c, count(*) AS n_links, round({_value}, 6) AS weight FROM both_ends WHERE src_c <> dst_c GROUP BY 1, 2")
for _name in ("sum", "max", "avg"):
    QUERIES[f"cluster_prestige_{_name}"] = lambda spark, sf, how=_name: quotient.cluster_nodes(the_graph(spark, sf).nodes, random_pages(spark, sf), how).withColumn("prestige", F.round("prestige", 6))
    SQL[f"cluster_prestige_{_name}"] = _with_random(f"SELECT cluster_id, count(*) AS n_nodes, round({_name}(prestige), 6) AS prestige FROM nodes JOIN membership USING (node_id) GROUP BY 1")


@query("intranode", _with_random("SELECT src_c AS cluster_id, count(*) AS n_inner FROM both_ends WHERE src_c = dst_c GROUP BY 1"))
def _(spark, sf):
    return bounds.crossing_pairs(the_graph(spark, sf).edges, random_pages(spark, sf))


@query("superedge_polarity", _with_random(", size AS (SELECT cluster_id, count(*) AS n FROM membership GROUP BY 1) SELECT src_c, dst_c, p AS n_positive, a.n * b.n - p AS n_negative, CASE WHEN p <= a.n * b.n - p THEN 'positive' ELSE 'negative' END AS chosen FROM (SELECT src_c, dst_c, count(*) AS p FROM (SELECT DISTINCT src, dst, src_c, dst_c FROM both_ends WHERE src_c <> dst_c) GROUP BY 1, 2) JOIN size a ON a.cluster_id = src_c JOIN size b ON b.cluster_id = dst_c"))
def _(spark, sf):
    return quotient.polarity(the_graph(spark, sf).edges, random_pages(spark, sf))


_PAIR = "top AS (SELECT src_c, dst_c FROM both_ends WHERE src_c <> dst_c GROUP BY 1, 2 ORDER BY count(*) DESC, 1, 2 LIMIT 1)"


def _superedge(spark, sf, f):
    e, m = the_graph(spark, sf).edges, random_pages(spark, sf)
    top = quotient.super_edges(e, m).orderBy(F.desc("n_links"), "src_c", "dst_c").first()
    return f(e, m, top["src_c"], top["dst_c"])


@query("superedge_positive", _with_random(f", {_PAIR} SELECT DISTINCT src, dst FROM both_ends JOIN top USING (src_c, dst_c)"))
def _(spark, sf):
    return _superedge(spark, sf, quotient.positive)


@query("superedge_negative", _with_random(f", {_PAIR} SELECT a.node_id AS src, b.node_id AS dst FROM top JOIN membership a ON a.cluster_id = src_c JOIN membership b ON b.cluster_id = dst_c WHERE NOT EXISTS (SELECT 1 FROM edges e WHERE e.src = a.node_id AND e.dst = b.node_id)"))
def _(spark, sf):
    return _superedge(spark, sf, quotient.negative)


@query("superedges_updated", _with_random("SELECT src_c, dst_c, count(*) AS n_links FROM both_ends WHERE src_c <> dst_c GROUP BY 1, 2"))
def _(spark, sf):
    e, m = the_graph(spark, sf).edges, random_pages(spark, sf)
    touched = m.select("cluster_id").distinct().where("cluster_id % 7 = 0")
    return quotient.update(quotient.super_edges(e, m), e, m, touched).select("src_c", "dst_c", "n_links")


@query("link_histogram", _with_random("SELECT floor(log2(n))::BIGINT AS log_links, count(*) AS n FROM (SELECT count(*) AS n FROM both_ends WHERE src_c <> dst_c GROUP BY src_c, dst_c) GROUP BY 1"))
def _(spark, sf):
    return measure.link_histogram(quotient.super_edges(the_graph(spark, sf).edges, random_pages(spark, sf)))


@query("diameters")
def _(spark, sf):
    return bounds.diameters(the_graph(spark, sf).edges, QUERIES["cluster_ball"](spark, sf))


@query("bound_coverage")
def _(spark, sf):
    """Share of two-phase answers whose cost lies within the bounds of the artificial answer that has the same clusters."""
    g, m = the_graph(spark, sf), QUERIES["cluster_ball"](spark, sf)
    real, artificial, _ = two_phase(spark, sf)
    least = quotient.super_edges(g.edges, m, "min").select("src_c", "dst_c", F.col("weight").alias("least"))
    limits = bounds.of_answers(artificial, least, bounds.diameters(g.edges, m)).groupBy("query_id", "clusters").agg(F.min("lower").alias("lower"), F.max("upper").alias("upper"))
    ends = F.flatten(F.transform("tree", lambda e: F.split(e, ">").cast("array<long>")))
    each = real.select("query_id", "rnk", (1 / F.col("edge_score") - 1).alias("cost"), F.explode(F.array_union(F.array("root"), ends)).alias("node_id")).join(m, "node_id")
    own = each.groupBy("query_id", "rnk", "cost").agg(F.array_sort(F.collect_set("cluster_id")).alias("clusters"))
    return measure.bound_coverage(own.join(limits, ["query_id", "clusters"]).select("lower", "cost", "upper"))


@query("bidirectional_rounds")
def _(spark, sf):
    g = the_graph(spark, sf)
    q, m = asked(spark, sf, PAIRS)
    found = held(spark, sf, "rounds", lambda: cut(search.bidirectional_rounds(g, m, q)))
    return search.roots(found.select("query_id", "term", "node_id", "dist"), q, 10)


@query("answers_in_rounds")
def _(spark, sf):
    """The trees of the ten cheapest roots, as searches above one task find them."""
    g = the_graph(spark, sf)
    q, m = asked(spark, sf, PAIRS)
    return search.whole_search(g, index.complete(m, q), q, rows=0).drop("touched", "explored")


# ---- two phases ----


def two_phase(spark, sf):
    def make():
        g, m = the_graph(spark, sf), QUERIES["cluster_ball"](spark, sf)
        q, found = asked(spark, sf, PAIRS)
        return twophase.two_phase(g, m, found, q)

    return held(spark, sf, "two phase", make)


@query("two_phase_topk")
def _(spark, sf):
    return two_phase(spark, sf)[0]


@query("two_phase_trace")
def _(spark, sf):
    return two_phase(spark, sf)[2]


@query("two_phase_backward_first")
def _(spark, sf):
    g, m = the_graph(spark, sf), QUERIES["cluster_ball"](spark, sf)
    q, found = asked(spark, sf, {"Q02": SETS["Q02"]})
    return twophase.two_phase(g, m, found, q, limit=30, algorithms=("backward", "bidirectional"))[0]


@query("phase1_clusters")
def _(spark, sf):
    return twophase.clusters_of(two_phase(spark, sf)[1])


@query("clusters_read")
def _(spark, sf):
    return twophase.clusters_read(twophase.clusters_of(two_phase(spark, sf)[1]), the_graph(spark, sf), QUERIES["cluster_ball"](spark, sf))


@query("fetch_trigger")
def _(spark, sf):
    return twophase.should_fetch(two_phase(spark, sf)[0])


@query("first_phase_limits", f"{_ASKED}, o AS (SELECT query_id, term, count(DISTINCT node_id) AS origin FROM queries LEFT JOIN matches USING (query_id, term) GROUP BY ALL) SELECT query_id, CASE WHEN max(origin) >= 1000 THEN 400 ELSE 100 END AS n_limit FROM o GROUP BY query_id")
def _(spark, sf):
    q, m = asked(spark, sf, SETS)
    return twophase.limit_for(index.origin_size(m, q), cut_at=1000)


@query("interleaved")
def _(spark, sf):
    g, m = the_graph(spark, sf), QUERIES["cluster_ball"](spark, sf)
    q, found = asked(spark, sf, {"Q02": SETS["Q02"]})
    return twophase.interleaved(g, m, found, q, max_rounds=2)


_BYTES = "bytes AS (SELECT cluster_id, 9 * count(*) AS bytes FROM membership GROUP BY 1)"


@query("keyword_cluster_budget", f"WITH {G}, {_RANDOM}, {P}, {sql.queries(PAIRS)}, {_BYTES}, own AS (SELECT DISTINCT query_id, cluster_id FROM matches JOIN membership USING (node_id)), r AS (SELECT *, sum(bytes) OVER (PARTITION BY query_id ORDER BY md5('0:' || cluster_id)) AS used FROM own JOIN bytes USING (cluster_id)) SELECT query_id, cluster_id, 'keyword' AS reason FROM r WHERE used <= 5000")
def _(spark, sf):
    m = random_pages(spark, sf)
    q, found = asked(spark, sf, PAIRS)
    sizes = m.groupBy("cluster_id").agg((9 * F.count(F.lit(1))).alias("bytes"))
    return twophase.keyword_clusters(found, m, sizes, spark.createDataFrame([], "query_id string, cluster_id long"), 5000)


@query("keyword_nodes", f"WITH {P}, {sql.queries(PAIRS)} SELECT DISTINCT query_id, node_id FROM matches")
def _(spark, sf):
    return twophase.keyword_nodes(asked(spark, sf, PAIRS)[1])


@query("neighbour_expansion", _with_random(", s AS (SELECT src_c, dst_c, 1 / sum(1 / weight) AS w FROM both_ends WHERE src_c <> dst_c GROUP BY 1, 2), c AS (SELECT min(cluster_id) AS cluster_id FROM membership), r AS (SELECT dst_c, row_number() OVER (PARTITION BY src_c ORDER BY round(w, 9), dst_c) AS r FROM s JOIN c ON c.cluster_id = src_c) SELECT 'Q' AS query_id, dst_c AS cluster_id, 'neighbour' AS reason FROM r WHERE r <= 3"))
def _(spark, sf):
    m = random_pages(spark, sf)
    chosen = m.agg(F.min("cluster_id").alias("cluster_id")).select(F.lit("Q").alias("query_id"), "cluster_id")
    return twophase.neighbours(chosen, quotient.super_edges(the_graph(spark, sf).edges, m).withColumn("weight", F.round("weight", 9)), 3)


@query("parallel_clusters")
def _(spark, sf):
    _, found = asked(spark, sf, {"Q02": SETS["Q02"]})
    return twophase.parallel_clusters(found, QUERIES["cluster_activation"](spark, sf), random_pages(spark, sf))


@query("mixed_granularity", _with_random(", open_c AS (SELECT min(cluster_id) AS c FROM membership), place AS (SELECT node_id, CASE WHEN cluster_id = c THEN node_id ELSE cluster_id END AS p FROM membership, open_c) SELECT a.p AS src, b.p AS dst, round(1 / sum(1 / weight), 6) AS weight FROM edges JOIN place a ON a.node_id = src JOIN place b ON b.node_id = dst WHERE a.p <> b.p GROUP BY 1, 2"))
def _(spark, sf):
    m = random_pages(spark, sf)
    return twophase.mixed(the_graph(spark, sf), m, m.agg(F.min("cluster_id").alias("cluster_id"))).edges.select("src", "dst", F.round("weight", 6).alias("weight"))


@query("mixed_normalised")
def _(spark, sf):
    g, m = the_graph(spark, sf), random_pages(spark, sf)
    opened = m.agg(F.min("cluster_id").alias("cluster_id"))
    return twophase.normalised(twophase.mixed(g, m, opened), m.join(opened, "cluster_id").select("node_id")).nodes.select("node_id", F.round("prestige", 6).alias("prestige"))


@query("mixed_iterated")
def _(spark, sf):
    q, found = asked(spark, sf, {"Q02": SETS["Q02"]})
    return twophase.iterate_mixed(the_graph(spark, sf), QUERIES["cluster_ball"](spark, sf), found, q, rounds=2)


@query("phantoms")
def _(spark, sf):
    real, artificial, _ = two_phase(spark, sf)
    return twophase.phantoms(artificial, real)


def history(spark, sf):
    real, _, _ = two_phase(spark, sf)
    m = QUERIES["cluster_ball"](spark, sf)
    q = index.query_frame(spark, PAIRS)
    used = real.select("query_id", F.explode("leaves").alias("node_id")).join(m, "node_id").join(q, "query_id")
    return used.groupBy("term", "cluster_id").agg(F.count(F.lit(1)).alias("hits"))


@query("adaptive_choice")
def _(spark, sf):
    return twophase.suggest(history(spark, sf), index.query_frame(spark, PAIRS))


# ---- baselines ----

_FURNITURE = "list_contains(regexp_extract_all(lower(c_mktsegment), '[a-z0-9]+'), 'furniture')"
_WIDGET = "list_contains(regexp_extract_all(lower(p_name), '[a-z0-9]+'), 'widget')"


@query("join_tree_rows", f"SELECT DISTINCT 3::BIGINT AS n_joins, 'customer+lineitem+orders+part' AS relations, 'customer:' || c_custkey || ',lineitem:' || l_orderkey || '-' || l_partkey || '-' || l_suppkey || '-' || l_linenumber || ',orders:' || o_orderkey || ',part:' || p_partkey AS keys FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON p_partkey = l_partkey WHERE {_FURNITURE} AND {_WIDGET}")
def _(spark, sf):
    return jointree.search(spark, sf, index.build_symbols(the_postings(spark, sf)), list(SETS["Q01"]))


@query("join_tree_ranked", SQL["join_tree_rows"].replace("SELECT DISTINCT", "SELECT * FROM (SELECT DISTINCT") + ") ORDER BY n_joins, relations, keys LIMIT 10")
def _(spark, sf):
    return jointree.rank(QUERIES["join_tree_rows"](spark, sf), 10)


@query("join_trees_found", "SELECT * FROM (VALUES (3, 'customer+lineitem+orders+part', 'furniture=customer,widget=part')) t(n_joins, relations, choice)")
def _(spark, sf):
    found = jointree.enumerate_trees(jointree.keyword_relations(index.build_symbols(the_postings(spark, sf)), list(SETS["Q01"])))
    return spark.createDataFrame([(t.joins, "+".join(sorted(t.relations)), ",".join(f"{k}={v}" for k, v in sorted(c.items()))) for t, c in found], "n_joins int, relations string, choice string")


def _walk_sql(rounds: int) -> str:
    steps = ["deg AS (SELECT src, count(*) AS deg FROM edges GROUP BY src), share AS (SELECT src, dst, count(*) / any_value(deg) AS s FROM edges JOIN deg USING (src) GROUP BY src, dst), base AS (SELECT term, node_id, 1.0 / count(*) OVER (PARTITION BY term) AS b FROM (SELECT DISTINCT term, node_id FROM matches)), k0 AS (SELECT term, node_id, b AS rank FROM base)"]
    for i in range(1, rounds + 1):
        steps.append(f"k{i} AS (SELECT term, node_id, sum(rank) AS rank FROM (SELECT term, dst AS node_id, 0.85 * rank * s AS rank FROM k{i - 1} JOIN share ON src = node_id UNION ALL SELECT term, node_id, 0.15 * b FROM base) GROUP BY 1, 2)")
    return ", ".join(steps)


_WALK = f"WITH {G}, {P}, {sql.queries({'Q02': SETS['Q02']})}, {_walk_sql(3)}"


def walk_ranks(spark, sf):
    _, m = asked(spark, sf, {"Q02": SETS["Q02"]})
    return held(spark, sf, "walk", lambda: cut(authority.keyword_rank(the_graph(spark, sf).edges, m, rounds=3)))


@query("authority_keyword", f"{_WALK} SELECT term, node_id, round(rank * 1e6, 4) AS rank_ppm FROM k3 WHERE rank > 0.001")
def _(spark, sf):
    return walk_ranks(spark, sf).where("rank > 0.001").select("term", "node_id", F.round(F.col("rank") * 1e6, 4).alias("rank_ppm"))


@query("authority_combined", f"{_WALK} SELECT query_id, node_id, round(log10(product(rank)), 6) AS log_score FROM k3 JOIN queries USING (term) GROUP BY 1, 2 HAVING count(*) = 2")
def _(spark, sf):
    q = index.query_frame(spark, {"Q02": SETS["Q02"]})
    rows = authority.combine(walk_ranks(spark, sf).withColumnRenamed("rank", "score"), q)
    return rows.select("query_id", "node_id", F.round(F.log10("score"), 6).alias("log_score"))


@query("authority_scores", f"{_WALK} SELECT term, count(*) AS n, round(sum(0.5 * rank + 0.5 * prestige / 1000), 6) AS mixed FROM k3 JOIN nodes USING (node_id) GROUP BY term")
def _(spark, sf):
    overall = the_graph(spark, sf).nodes.select("node_id", (F.col("prestige") / 1000).alias("rank"))
    return authority.score(walk_ranks(spark, sf), overall, "sum").groupBy("term").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("score"), 6).alias("mixed"))


@query("steiner_small")
def _(spark, sf):
    from ..operators.kernels import Adjacency, steiner

    g = the_graph(spark, sf)
    q, m = asked(spark, sf, {"Q02": SETS["Q02"]})
    rows = g.edges.select("src", "dst", "weight").crossJoin(F.broadcast(q.select("query_id").distinct()))
    sets = m.groupBy("query_id", "term").agg(F.collect_list("node_id").alias("s")).groupBy("query_id").agg(F.map_from_entries(F.collect_list(F.struct("term", "s"))).alias("sets"))  # a fixture's few matches
    rows = rows.join(F.broadcast(sets), "query_id")

    def one(key, frame):
        import pandas as pd

        got = steiner(Adjacency(zip(frame.src.tolist(), frame.dst.tolist(), frame.weight.tolist(), strict=True)), {t: set(v) for t, v in dict(frame.sets.iloc[0]).items()})
        return pd.DataFrame([(key[0], *got)] if got else [], columns=["query_id", "cost", "root"])

    return rows.groupBy("query_id").applyInPandas(one, "query_id string, cost double, root long")


# ---- measures ----


@query("memory_models", f"WITH {G}, c AS (SELECT (SELECT count(*) FROM nodes) AS v, (SELECT count(*) FROM edges) AS e) SELECT 'full' AS metric, (20 * v + 12 * e)::BIGINT AS bytes FROM c UNION ALL SELECT 'slim', 9 * v + 8 * e FROM c UNION ALL SELECT 'slim+map', 13 * v + 8 * e FROM c UNION ALL SELECT 'full-degrees', 12 * v + 12 * e FROM c")
def _(spark, sf):
    c, v, e = measure.counts(the_graph(spark, sf)), F.col("n_nodes"), F.col("n_edges")
    forms = [("full", measure.memory(v, e)), ("slim", measure.memory(v, e, "slim")), ("slim+map", measure.memory(v, e, "slim", True)), ("full-degrees", measure.memory(v, e, drop=2))]
    return c.select(F.explode(F.array(*[F.struct(F.lit(n).alias("metric"), x.cast("long").alias("bytes")) for n, x in forms])).alias("r")).select("r.*")


@query("graph_reduction", _with_random("SELECT round((SELECT count(*) FROM nodes) / (SELECT count(DISTINCT cluster_id) FROM membership), 6) AS node_ratio, round((SELECT count(*) FROM edges) / (SELECT count(*) FROM (SELECT DISTINCT src_c, dst_c FROM both_ends WHERE src_c <> dst_c)), 6) AS edge_ratio"))
def _(spark, sf):
    g = the_graph(spark, sf)
    r = measure.reduction(g, quotient.quotient(g, random_pages(spark, sf)))
    return r.select(F.round("node_ratio", 6).alias("node_ratio"), F.round("edge_ratio", 6).alias("edge_ratio"))


def reference(spark, sf):
    return QUERIES["bidirectional_topk"](spark, sf)


@query("precision_at_10")
def _(spark, sf):
    return measure.precision(two_phase(spark, sf)[0], reference(spark, sf))


@query("acceptable_at_10")
def _(spark, sf):
    return measure.acceptable(two_phase(spark, sf)[0], reference(spark, sf))


@query("answer_quality")
def _(spark, sf):
    return measure.quality(two_phase(spark, sf)[0])


@query("score_gaps")
def _(spark, sf):
    return measure.score_gap(two_phase(spark, sf)[0])


@query("minimality_violations")
def _(spark, sf):
    return measure.minimality(two_phase(spark, sf)[0])


@query("work_compared")
def _(spark, sf):
    """Nodes touched and explored by the reference and by two-phase search, both phases together."""
    a = reference(spark, sf).groupBy("query_id").agg(F.max("touched").alias("ref_touched"), F.max("explored").alias("ref_explored"))
    b = two_phase(spark, sf)[2].groupBy("query_id").agg(F.sum("touched").alias("touched"), F.sum("explored").alias("explored"))
    return a.join(b, "query_id")


#: The published cluster size and first-phase limits.
WIDE, LIMITS = 100, (100, 400)
#: Queries of the published sweep of limits: two with a frequent and a rarer set, two with sets of like size.
SWEPT = ("Q04", "Q05", "Q06", "Q07")
TECHNIQUES = {
    "adjacency": lambda g: cluster.adjacency(g, WIDE),
    "connection": lambda g: cluster.connection(g, WIDE),
    "ratio": lambda g: cluster.ratio(g, WIDE),
    "ball": lambda g: cluster.greedy_ball(g, WIDE),
    "random": lambda g: cluster.random(g, WIDE),
}


def wide(spark, sf, name):
    return held(spark, sf, f"wide {name}", lambda: cut(TECHNIQUES[name](the_graph(spark, sf))))


def compared(spark, sf):
    """(clustering, query_id, n_exact, n_score, n_acceptable, quality_sum, seconds, bytes) at the published size and limit."""

    def make():
        g, (q, found), ref, out = the_graph(spark, sf), asked(spark, sf, PAIRS), reference(spark, sf), None
        for name in TECHNIQUES:
            m = wide(spark, sf, name)
            real, seconds = measure.timed(lambda m=m: twophase.two_phase(g, m, found, q, limit=LIMITS[0])[0])
            pairs = quotient.super_edges(g.edges, m).count()
            best = real.where("rnk <= 5").groupBy("query_id").agg(F.round(F.sum("tree_score"), 6).alias("quality_sum"))
            part = measure.precision(real, ref).join(measure.acceptable(real, ref), "query_id").join(best, "query_id", "left").select(F.lit(name).alias("clustering"), "query_id", "n_exact", "n_score", "n_acceptable", "quality_sum", F.lit(seconds).alias("seconds"), F.lit(int(measure.memory(m.select("cluster_id").distinct().count(), pairs, "slim"))).alias("bytes"))
            out = part if out is None else out.unionByName(part)
        return cut(out)

    return held(spark, sf, "compared", make)


@query("clusterings_compared")
def _(spark, sf):
    """By the five best answers of all queries, less time first among equals; clusterings above the memory limit, the slim
    size of the whole graph, do not take part."""
    rows = compared(spark, sf).withColumn("rnk", F.lit(1)).withColumnRenamed("quality_sum", "tree_score")
    limit = measure.counts(the_graph(spark, sf)).select(measure.memory(F.col("n_nodes"), F.col("n_edges"), "slim")).first()[0]
    return measure.compare_clusterings(rows, int(limit))


@query("clusterings_accuracy")
def _(spark, sf):
    """Exact and acceptable answers of ten for each clustering and query."""
    return compared(spark, sf).select("clustering", "query_id", "n_exact", "n_score", "n_acceptable")


@query("weight_grid")
def _(spark, sf):
    """Acceptable answers for each way to weigh super-edges and clusters, two queries, at the published size and limit."""
    g, m = the_graph(spark, sf), wide(spark, sf, "ball")
    q, found = asked(spark, sf, {n: SETS[n] for n in ("Q01", "Q02")})
    ref = reference(spark, sf).where("query_id in ('Q01', 'Q02')")

    def one(pair):
        weight, prestige = pair
        real, _, _ = twophase.two_phase(g, m, found, q, limit=LIMITS[0], weight=weight, prestige=prestige)
        return cut(measure.acceptable(real, ref).select(F.lit(weight).alias("weight"), F.lit(prestige).alias("prestige"), "query_id", "n_acceptable"))

    # a search keeps one task a query busy, so combinations run beside each other
    with ThreadPoolExecutor(4) as pool:
        parts = list(pool.map(one, product(("min", "harmonic", "inverse_sum"), ("sum", "max", "avg"))))
    return reduce(DataFrame.unionByName, parts)


@query("limit_sweep")
def _(spark, sf):
    """Acceptable answers of four queries at both published limits of the first phase."""
    g, m = the_graph(spark, sf), wide(spark, sf, "ball")
    sets = {q: SETS[q] for q in SWEPT}
    q, found = asked(spark, sf, sets)
    ref = cut(_local(spark, sf, "bidirectional", sets))
    return measure.limit_sweep({n: twophase.two_phase(g, m, found, q, limit=n)[0] for n in LIMITS}, ref)


# ---- compression ----


def sorted_lists(spark, sf):
    return graph.to_adjacency(the_graph(spark, sf).edges.where("direction = 'fwd'")).select("node_id", "targets")


@query("gap_lists", f"WITH {G}, l AS (SELECT src AS node_id, list(dst ORDER BY dst) AS t FROM edges WHERE direction = 'fwd' GROUP BY src) SELECT node_id, array_to_string(list_transform(t, lambda x, i: CASE WHEN i = 1 THEN x ELSE x - t[i - 1] END), ',') AS gaps FROM l")
def _(spark, sf):
    return sorted_lists(spark, sf).select("node_id", F.array_join(compress.gaps(F.col("targets")).cast("array<string>"), ",").alias("gaps"))


@query("gap_round_trip", f"WITH {G} SELECT count(DISTINCT src) AS n, true AS same FROM refs")
def _(spark, sf):
    rows = sorted_lists(spark, sf)
    return rows.agg(F.count(F.lit(1)).alias("n"), F.bool_and(compress.ungap(compress.gaps(F.col("targets"))) == F.col("targets")).alias("same"))


_LISTS = "l AS (SELECT src AS node_id, list_sort(list(dst)) AS t FROM edges WHERE direction = 'fwd' AND src >= (6::BIGINT << 56) GROUP BY src), p AS (SELECT node_id, lag(node_id) OVER (ORDER BY node_id) AS ref_id FROM l)"


def _coding(spark, sf):
    from ..plans.loop import cut as stored
    from pyspark.sql import Window

    rows = stored(sorted_lists(spark, sf).where(F.col("node_id") >= 6 << 56))
    bucket = F.shiftright("node_id", 12)
    pairs = rows.select("node_id").withColumn("ref_id", F.lag("node_id").over(Window.partitionBy(bucket).orderBy("node_id"))).where("ref_id is not null")
    return rows, pairs


@query("reference_coding", f"WITH {G}, {_LISTS.replace('OVER (ORDER BY node_id)', 'OVER (PARTITION BY node_id >> 12 ORDER BY node_id)')} SELECT p.node_id, p.ref_id, len(list_intersect(a.t, b.t))::BIGINT AS n_shared, len(list_filter(a.t, lambda x: NOT list_contains(b.t, x)))::BIGINT AS n_extra FROM p JOIN l a ON a.node_id = p.node_id JOIN l b ON b.node_id = p.ref_id")
def _(spark, sf):
    return compress.reference_sizes(*_coding(spark, sf))


@query("reference_round_trip", "SELECT true AS same")
def _(spark, sf):
    rows, pairs = _coding(spark, sf)
    both = pairs.join(rows, "node_id").join(rows.select(F.col("node_id").alias("ref_id"), F.col("targets").alias("ref")), "ref_id").withColumn("c", compress.against(F.col("ref"), F.col("targets")))
    return both.agg(F.bool_and(compress.restore(F.col("ref"), F.col("c.bits"), F.col("c.extras")) == F.array_sort("targets")).alias("same"))


@query("reference_choice")
def _(spark, sf):
    return compress.choose_reference(sorted_lists(spark, sf), QUERIES["cluster_ball"](spark, sf))


@query("huffman_bits")
def _(spark, sf):
    return compress.huffman(the_graph(spark, sf).edges.where("direction = 'fwd'"))


@query("huffman_without_stop")
def _(spark, sf):
    return compress.huffman(the_graph(spark, sf).edges.where("direction = 'fwd'"), side="src", stop=False)


@query("huffman_codes", "SELECT * FROM (VALUES ('a', 1, '0'), ('b', 2, '10'), ('c', 3, '110'), ('d', 3, '111')) t(symbol, length, code)")
def _(spark, sf):
    return compress.huffman_codes(spark, {"a": 4, "b": 2, "c": 1, "d": 1})


@query("bits_per_edge")
def _(spark, sf):
    e = the_graph(spark, sf).edges.where("direction = 'fwd'")
    return measure.bits_per_edge(compress.huffman(e), e)


@query("run_lengths", "SELECT * FROM (VALUES ('10111', '1:1,1,3'), ('000', '0:3'), ('0110', '0:1,2,1')) t(bits, coded)")
def _(spark, sf):
    return spark.createDataFrame([("10111",), ("000",), ("0110",)], "bits string").select("bits", compress.runs(F.col("bits")).alias("coded"))


@query("degree_exponent", f"WITH {G}, h AS (SELECT d, count(*) AS n FROM (SELECT count(*) AS d FROM refs GROUP BY dst) GROUP BY d) SELECT round(regr_slope(log2(n), log2(d)), 6) AS slope, count(*) AS n_degrees FROM h")
def _(spark, sf):
    return measure.degree_exponent(the_graph(spark, sf).edges.where("direction = 'fwd'")).withColumn("slope", F.round("slope", 6))


# ---- store, browsing, SQL surface ----


@query("store_round_trip", _with_random("SELECT count(*) AS n_nodes, (SELECT count(*) FROM both_ends WHERE src_c = (SELECT min(cluster_id) FROM membership)) AS n_edges FROM membership WHERE cluster_id = (SELECT min(cluster_id) FROM membership)"))
def _(spark, sf):
    g, m, path = the_graph(spark, sf), random_pages(spark, sf), f"{shared_dir(spark)}/store"
    store.write_clusters(g, m, path, buckets=8)
    store.write_quotient(g, m, path)
    first = m.agg(F.min("cluster_id").alias("cluster_id"))
    n = store.read_clusters(spark, path, first, "nodes", 8).agg(F.count(F.lit(1)).alias("n_nodes"))
    return n.crossJoin(store.read_clusters(spark, path, first, "edges", 8).agg(F.count(F.lit(1)).alias("n_edges")))


@query("store_quotient", _with_random("SELECT (SELECT count(DISTINCT cluster_id) FROM membership) AS n_clusters, count(*) AS n_edges FROM (SELECT DISTINCT src_c, dst_c FROM both_ends WHERE src_c <> dst_c)"))
def _(spark, sf):
    path = f"{shared_dir(spark)}/store_q"
    store.write_quotient(the_graph(spark, sf), random_pages(spark, sf), path)
    small = store.read_quotient(spark, path)
    return small.nodes.agg(F.count(F.lit(1)).alias("n_clusters")).crossJoin(small.edges.agg(F.count(F.lit(1)).alias("n_edges")))


@query("browse_tuple", f"WITH {G}, o AS (SELECT node_id AS src FROM nodes WHERE node_key = 'customer:42') SELECT etype, direction, node_key FROM edges JOIN o USING (src) JOIN nodes ON node_id = dst ORDER BY 1, 2, 3 LIMIT 20")
def _(spark, sf):
    return browse.neighbours(the_graph(spark, sf), "customer:42")


@query("browse_relations", f"WITH {G} SELECT rel, count(*) AS n_nodes FROM nodes GROUP BY rel")
def _(spark, sf):
    return browse.relations(the_graph(spark, sf).nodes)


@query("sql_views", f"WITH {G} SELECT rel, count(*) AS n FROM nodes JOIN edges ON dst = node_id WHERE direction = 'fwd' GROUP BY rel")
def _(spark, sf):
    udf.views(the_graph(spark, sf))
    return spark.sql("SELECT rel, count(*) AS n FROM nodes JOIN edges ON dst = node_id WHERE direction = 'fwd' GROUP BY rel")


@query("sql_keyword_search")
def _(spark, sf):
    udf.register(spark)
    q, m = asked(spark, sf, {"Q02": SETS["Q02"]})
    edges, nodes = search.for_queries(the_graph(spark, sf), q)
    udf.query_rows(edges, nodes, m).createOrReplaceTempView("query_graph")
    return spark.sql("SELECT * FROM keyword_search(TABLE(query_graph) PARTITION BY query_id)")
