"""Registered queries on the graph methods, each beside the SQL that checks it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scores import edge_score, tree_score
from ..operators import activation, answers, authority, bounds, browse, cluster, compress, graph, index, jointree, measure, quotient, search
from ..sources import catalog
from ..sources.catalog import table
from . import sql, twophase
from .loop import cut

QUERIES: dict = {}
SQL: dict[str, str] = {}
# Keyword queries on the given tables (see FIXTURES.md).
SETS = {
    "Q01": ("furniture", "widget"),
    "Q02": ("000000042", "000000007"),
    "Q03": ("000000042", "widget"),
    "Q04": ("urgent", "widget"),
    "Q05": ("high", "anvil"),
    "Q06": ("medium", "furniture"),
    "Q07": ("promo", "economy"),
    "Q08": ("asia", "widget", "furniture"),
    "Q09": ("asia", "urgent", "widget", "furniture"),
    "Q10": ("customer", "widget"),
    "Q11": ("7", "widget"),
    "Q12": ("furniture",),
    "Q13": ("furniture", "zzzz"),
}
PAIRS = {q: SETS[q] for q in ("Q01", "Q02", "Q03")}
G, P = sql.NODES, sql.POSTINGS


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            SQL[name] = oracle.strip()
        return f

    return add


_held: dict = {}


def held(spark: SparkSession, sf_dir: str, kind: str, make):
    """Intermediate tables that several queries start from, once for each session and input."""
    key = (spark.sparkContext.applicationId, sf_dir, kind)
    if key not in _held:
        _held[key] = make()
    return _held[key]


def the_graph(spark, sf_dir) -> graph.Graph:
    return held(spark, sf_dir, "graph", lambda: graph.build(spark, sf_dir))


def the_postings(spark, sf_dir) -> DataFrame:
    return held(spark, sf_dir, "postings", lambda: cut(index.build_postings(spark, sf_dir)))


def asked(spark, sf_dir, sets) -> tuple[DataFrame, DataFrame]:
    q = index.query_frame(spark, sets)
    return q, index.match(the_postings(spark, sf_dir), q)


def keyed(df: DataFrame, nodes: DataFrame, **columns: str) -> DataFrame:
    """Columns of node ids as node keys, under new names."""
    for old, new in columns.items():
        df = df.join(nodes.select(F.col("node_id").alias(old), F.col("node_key").alias(new)), old).drop(old)
    return df


# ---- graph ----


@query("nodes_by_relation", f"WITH {G} SELECT rel, count(*) AS n_nodes, sum(length(text))::BIGINT AS n_chars FROM nodes GROUP BY rel")
def _(spark, sf):
    return graph.build_nodes(spark, sf).groupBy("rel").agg(F.count(F.lit(1)).alias("n_nodes"), F.sum(F.length("text")).alias("n_chars"))


@query("node_table", f"WITH {G} SELECT node_key, rel, indeg, outdeg, prestige FROM nodes")
def _(spark, sf):
    return the_graph(spark, sf).nodes.select("node_key", "rel", "indeg", "outdeg", "prestige")


@query("edges_by_type", f"WITH {G} SELECT etype, direction, count(*) AS n_edges FROM edges GROUP BY ALL")
def _(spark, sf):
    return the_graph(spark, sf).edges.groupBy("etype", "direction").agg(F.count(F.lit(1)).alias("n_edges"))


@query("forward_edges", f"WITH {G} SELECT src, dst, etype FROM refs WHERE etype NOT IN ('orders>part', 'orders>supplier')")
def _(spark, sf):
    return graph.forward_edges(spark, sf)


@query("forward_weights", f"WITH {G} SELECT etype, count(*) AS n_edges, round(sum(CASE etype WHEN 'orders>customer' THEN 0.5 WHEN 'orders>part' THEN 2.0 ELSE 1.0 END), 6) AS total FROM refs GROUP BY etype")
def _(spark, sf):
    edges = graph.forward_edges(spark, sf).unionByName(graph.contract_relation(spark, sf).drop("n_links"))
    weighed = graph.forward_weight(edges, {"orders>customer": 0.5, "orders>part": 2.0})
    return weighed.groupBy("etype").agg(F.count(F.lit(1)).alias("n_edges"), F.round(F.sum("weight"), 6).alias("total"))


@query("reverse_weights", f"WITH {G} SELECT s.node_key AS src_key, d.node_key AS dst_key, etype, round(weight, 6) AS weight FROM edges e JOIN nodes s ON s.node_id = e.src JOIN nodes d ON d.node_id = e.dst WHERE direction = 'back' AND etype <> 'orders>part' AND etype <> 'orders>supplier'")
def _(spark, sf):
    g = the_graph(spark, sf)
    rows = g.edges.where("direction = 'back' and etype not in ('orders>part', 'orders>supplier')").select("src", "dst", "etype", F.round("weight", 6).alias("weight"))
    return keyed(rows, g.nodes, src="src_key", dst="dst_key")


@query("reverse_weights_by_type", f"WITH {G}, t AS (SELECT dst, etype, count(*) AS n FROM refs GROUP BY ALL) SELECT etype, count(*) AS n_edges, round(max(log2(1.0 + n)), 6) AS most FROM refs JOIN t USING (dst, etype) GROUP BY etype")
def _(spark, sf):
    back = graph.with_reverse(graph.references(spark, sf), per_type=True).where("direction = 'back'")
    return back.groupBy("etype").agg(F.count(F.lit(1)).alias("n_edges"), F.round(F.max("weight"), 6).alias("most"))


@query("reverse_weights_unit", f"WITH {G} SELECT direction, count(*) AS n_edges, round(sum(1.0), 6) AS total FROM edges GROUP BY direction")
def _(spark, sf):
    return graph.with_reverse(graph.references(spark, sf), "unit").groupBy("direction").agg(F.count(F.lit(1)).alias("n_edges"), F.round(F.sum("weight"), 6).alias("total"))


@query("prestige_indegree", f"WITH {G} SELECT node_key, indeg FROM nodes WHERE indeg > 0")
def _(spark, sf):
    return the_graph(spark, sf).nodes.where("indeg > 0").select("node_key", "indeg")


@query("prestige_damped", f"WITH {G} SELECT node_key, round(log2(1 + prestige), 6) AS log_prestige, round(prestige / (SELECT max(prestige) FROM nodes), 6) AS share FROM nodes")
def _(spark, sf):
    n = the_graph(spark, sf).nodes
    a = graph.damp_prestige(n).select("node_key", F.round("prestige", 6).alias("log_prestige"))
    return a.join(graph.damp_prestige(n, "max").select("node_key", F.round("prestige", 6).alias("share")), "node_key")


@query("weights_damped", f"WITH {G} SELECT etype, direction, round(max(log2(1 + weight / (SELECT min(weight) FROM edges))), 6) AS most FROM edges GROUP BY ALL")
def _(spark, sf):
    return graph.damp_weights(the_graph(spark, sf).edges).groupBy("etype", "direction").agg(F.round(F.max("weight"), 6).alias("most"))


@query("edge_priorities", f"WITH {G} SELECT etype, count(*) AS n_edges, CASE etype WHEN 'orders>part' THEN 2.0 ELSE 1.0 END::DOUBLE AS priority FROM edges WHERE etype <> 'nation>region' GROUP BY etype")
def _(spark, sf):
    e = graph.priority(the_graph(spark, sf).edges.drop("priority"), {"orders>part": 2.0}, forbid=("nation>region",))
    return e.groupBy("etype", "priority").agg(F.count(F.lit(1)).alias("n_edges"))


def _rank_sql(rounds: int, damping: float = 0.85) -> str:
    steps = [f"deg AS (SELECT src, count(*) AS deg FROM refs GROUP BY src), share AS (SELECT src, dst, count(*) / any_value(deg) AS s FROM refs JOIN deg USING (src) GROUP BY src, dst), r0 AS (SELECT node_id, 1.0 / (SELECT count(*) FROM nodes) AS rank FROM nodes)"]
    for i in range(1, rounds + 1):
        steps.append(
            f"g{i} AS (SELECT dst AS node_id, sum(rank * s) AS got FROM r{i - 1} JOIN share ON src = node_id GROUP BY dst), l{i} AS (SELECT coalesce(sum(rank), 0) AS lost FROM r{i - 1} WHERE node_id NOT IN (SELECT src FROM deg)), "
            f"r{i} AS (SELECT node_id, {1 - damping} / (SELECT count(*) FROM nodes) + {damping} * (coalesce(got, 0) + lost / (SELECT count(*) FROM nodes)) AS rank FROM nodes LEFT JOIN g{i} USING (node_id), l{i})"
        )
    return ", ".join(steps)


@query("prestige_authority", f"WITH {G}, {_rank_sql(5)} SELECT node_key, round(rank * 1e6, 4) AS rank_ppm FROM r5 JOIN nodes USING (node_id) WHERE rel IN ('region', 'nation', 'supplier')")
def _(spark, sf):
    g = the_graph(spark, sf)
    ranked = authority.global_rank(g.nodes, g.edges.where("direction = 'fwd'"), rounds=5)
    return ranked.join(g.nodes.where(F.col("rel").isin("region", "nation", "supplier")).select("node_id", "node_key"), "node_id").select("node_key", F.round(F.col("rank") * 1e6, 4).alias("rank_ppm"))


@query("contracted_edges", f"SELECT {sql.node(6, 'l_orderkey')} AS src, {sql.node(5, 'l_partkey')} AS dst, 'orders>part' AS etype, count(*) AS n_links FROM lineitem GROUP BY ALL UNION ALL SELECT {sql.node(6, 'l_orderkey')}, {sql.node(4, 'l_suppkey')}, 'orders>supplier', count(*) FROM lineitem GROUP BY ALL")
def _(spark, sf):
    return graph.contract_relation(spark, sf)


@query("transitive_relations", "SELECT * FROM (VALUES ('nation', 1, 0, false), ('customer', 1, 0, false), ('supplier', 1, 0, false), ('orders', 1, 0, false), ('lineitem', 3, 3, true)) t(rel, n_references, n_key_references, transitive)")
def _(spark, sf):
    return graph.find_transitive(spark, sf)


@query(
    "uncontracted_references",
    "SELECT etype, count(*) AS n_edges, count(DISTINCT src_key) AS n_src FROM (SELECT 'nation>region' AS etype, 'n' || n_nationkey AS src_key FROM nation UNION ALL SELECT 'customer>nation', 'c' || c_custkey FROM customer UNION ALL SELECT 'supplier>nation', 's' || s_suppkey FROM supplier UNION ALL SELECT 'orders>customer', 'o' || o_orderkey FROM orders "
    "UNION ALL SELECT e, 'l' || row_number() OVER (PARTITION BY e) FROM lineitem, (VALUES ('lineitem>orders'), ('lineitem>part'), ('lineitem>supplier')) v(e)) GROUP BY etype",
)
def _(spark, sf):
    return graph.uncontracted_references(spark, sf).groupBy("etype").agg(F.count(F.lit(1)).alias("n_edges"), F.count_distinct("src_key").alias("n_src"))


@query("inclusion_edges", "SELECT 'events:' || event_id AS src_key, 'customer:' || user_id AS dst_key FROM events WHERE user_id IN (SELECT c_custkey FROM customer) UNION ALL SELECT 'labels:' || doc_id, 'documents:' || doc_id FROM labels WHERE doc_id IN (SELECT doc_id FROM documents)")
def _(spark, sf):
    return graph.inclusion_edges(spark, sf)


@query(
    "inclusions_found",
    "SELECT 'events' AS child, 'user_id' AS column_name, 'customer' AS parent, 'c_custkey' AS parent_key, count(DISTINCT user_id) AS n_values, count(DISTINCT user_id) FILTER (WHERE user_id NOT IN (SELECT c_custkey FROM customer)) AS missing, bool_and(user_id IN (SELECT c_custkey FROM customer)) AS holds FROM events "
    "UNION ALL SELECT 'customer', 'c_custkey', 'events', 'user_id', count(DISTINCT c_custkey), count(DISTINCT c_custkey) FILTER (WHERE c_custkey NOT IN (SELECT user_id FROM events)), bool_and(c_custkey IN (SELECT user_id FROM events)) FROM customer",
)
def _(spark, sf):
    return catalog.discover_references(spark, sf, [("events", "user_id", "customer", "c_custkey"), ("customer", "c_custkey", "events", "user_id")])


@query("relation_keys", "SELECT 'orders' AS rel, (SELECT count(*) = count(DISTINCT o_orderkey) FROM orders) AS single_key UNION ALL SELECT 'lineitem', (SELECT count(*) = count(DISTINCT (l_orderkey, l_linenumber)) FROM lineitem)")
def _(spark, sf):
    rows = [("orders", catalog.is_key(table(spark, sf, "orders"), ("o_orderkey",))), ("lineitem", catalog.is_key(table(spark, sf, "lineitem"), ("l_orderkey", "l_linenumber")))]
    return spark.createDataFrame(rows, "rel string, single_key boolean")


@query("relation_graph", "SELECT * FROM (VALUES ('nation', 'region'), ('region', 'nation'), ('customer', 'nation'), ('nation', 'customer'), ('supplier', 'nation'), ('nation', 'supplier'), ('orders', 'customer'), ('customer', 'orders'), ('lineitem', 'orders'), ('orders', 'lineitem'), ('lineitem', 'part'), ('part', 'lineitem'), ('lineitem', 'supplier'), ('supplier', 'lineitem')) t(relation, neighbour)")
def _(spark, sf):
    return catalog.relation_graph(spark)


@query("passage_edges", "SELECT 'benchmark:' || item_id AS src_key, 'documents:' || doc_id AS dst_key FROM benchmark b JOIN documents d ON contains(d.text, b.text) WHERE len(string_split(b.text, ' ')) > 8")
def _(spark, sf):
    return graph.passage_edges(spark, sf)


@query("copy_edges", "SELECT 'documents:' || doc_id AS src_key, 'documents:' || first AS dst_key FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS first FROM documents) WHERE doc_id <> first")
def _(spark, sf):
    return graph.copy_edges(spark, sf)


_PATTERN = "concat_ws('', " + ", ".join(f"CASE WHEN embedding[(t * 4 + {k}) % 64 + 1] >= 0 THEN '1' ELSE '0' END" for k in range(4)) + ")"


@query(
    "similarity_edges",
    f"WITH k AS (SELECT vec_id, embedding, t || ':' || {_PATTERN} AS key FROM embeddings, range(16) r(t)), p AS (SELECT DISTINCT a.vec_id AS a, b.vec_id AS b FROM k a JOIN k b USING (key) WHERE a.vec_id <> b.vec_id), w AS (SELECT a, b, greatest(0.001, 1 - list_sum(list_transform(list_zip(x.embedding, y.embedding), lambda z: z[1]::DOUBLE * z[2]::DOUBLE))) AS weight FROM p JOIN embeddings x ON x.vec_id = a JOIN embeddings y ON y.vec_id = b) "
    "SELECT a, b, round(weight, 6) AS weight FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY weight, b) AS r FROM w) WHERE r <= 3",
)
def _(spark, sf):
    return graph.similarity_edges(spark, sf).select("a", "b", F.round("weight", 6).alias("weight"))


@query("object_graph", "SELECT 'orders:' || o_orderkey AS node_key, count(l_orderkey) AS n_lines, count(DISTINCT l_partkey) AS n_parts, count(DISTINCT l_suppkey) AS n_suppliers FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey")
def _(spark, sf):
    return graph.objectify(spark, sf)


@query("hub_report", f"WITH {G} SELECT rel, count(*) AS n_nodes, max(indeg) AS max_indeg, round(avg(indeg), 6) AS avg_indeg, quantile_cont(indeg, 0.5)::DOUBLE AS median_indeg FROM nodes GROUP BY rel")
def _(spark, sf):
    return graph.hub_report(the_graph(spark, sf).nodes)


@query("adjacency_lists", f"WITH {G} SELECT node_key, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS targets, count(*) AS n FROM edges JOIN nodes ON node_id = src GROUP BY node_key")
def _(spark, sf):
    g = the_graph(spark, sf)
    return graph.to_adjacency(g.edges).join(g.nodes.select("node_id", "node_key"), "node_id").select("node_key", F.array_join(F.col("targets").cast("array<string>"), ",").alias("targets"), F.size("targets").cast("long").alias("n"))


@query("offset_layout", f"WITH {G}, d AS (SELECT src AS node_id, count(*) AS n FROM edges GROUP BY src) SELECT node_id, n, coalesce(sum(n) OVER (ORDER BY node_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS \"offset\" FROM d")
def _(spark, sf):
    lists = graph.to_adjacency(the_graph(spark, sf).edges).select("node_id", F.size("targets").cast("long").alias("n"))
    return graph.offsets(lists, "n", "node_id")


@query("degree_from_offsets", f"WITH {G} SELECT node_id, (count(*) // 2)::BIGINT AS degree, (count(*) - any_value(coalesce(indeg, 0)))::BIGINT AS out_degree FROM (SELECT src AS node_id FROM edges) LEFT JOIN ins USING (node_id) GROUP BY node_id")
def _(spark, sf):
    g = the_graph(spark, sf)
    lists = graph.to_adjacency(g.edges)
    return graph.degrees_from_offsets(lists, "symmetric").join(graph.degrees_from_offsets(lists, "directed", g.nodes.select("node_id", "indeg")).withColumnRenamed("degree", "out_degree"), "node_id")


# ---- index ----


@query("postings", f"WITH {P} SELECT term, node_key, field, tf FROM postings")
def _(spark, sf):
    return index.build_postings(spark, sf).select("term", "node_key", "field", "tf")


@query("symbol_table", f"WITH {P} SELECT term, rel, field, count(DISTINCT node_id) AS n_rows FROM postings GROUP BY ALL")
def _(spark, sf):
    return index.build_symbols(the_postings(spark, sf))


@query("symbol_granularity", f"WITH {P} SELECT term, rel, field, count(DISTINCT node_id)::BIGINT AS n_rows, NULL::VARCHAR AS node_key FROM postings WHERE field IN ('c_mktsegment', 'o_orderpriority') GROUP BY ALL UNION ALL SELECT term, rel, field, 1::BIGINT, node_key FROM postings WHERE field NOT IN ('c_mktsegment', 'o_orderpriority')")
def _(spark, sf):
    return index.symbol_table(the_postings(spark, sf), ("c_mktsegment", "o_orderpriority")).select("term", "rel", "field", "n_rows", "node_key")


@query("symbol_compaction", f"WITH {P}, l AS (SELECT term, count(*) AS n_rows, string_agg(node_id::VARCHAR, ',' ORDER BY node_id) AS s FROM (SELECT DISTINCT term, node_id FROM postings) GROUP BY term) SELECT min(term) AS first_term, count(*) AS n_terms, n_rows FROM l GROUP BY s, n_rows")
def _(spark, sf):
    return index.compact_symbols(the_postings(spark, sf))


_ASKED = f"WITH {P}, {sql.queries(SETS)}"


@query("origin_sizes", f"{_ASKED} SELECT query_id, term, count(DISTINCT node_id) AS origin FROM queries LEFT JOIN matches USING (query_id, term) GROUP BY ALL")
def _(spark, sf):
    q, m = asked(spark, sf, SETS)
    return index.origin_size(m, q)


@query("query_classes", f"{_ASKED}, o AS (SELECT query_id, term, count(DISTINCT node_id) AS origin FROM queries LEFT JOIN matches USING (query_id, term) GROUP BY ALL) SELECT query_id, string_agg(CASE WHEN origin > 100 THEN 'high' ELSE 'low' END, '/' ORDER BY origin, term) AS klass FROM o GROUP BY query_id")
def _(spark, sf):
    q, m = asked(spark, sf, SETS)
    return index.classify(index.origin_size(m, q), 100)


@query("metadata_match", f"WITH {G}, {P}, {sql.queries({'Q10': SETS['Q10']})} SELECT query_id, term, count(DISTINCT node_key) AS n FROM (SELECT query_id, term, node_key FROM matches UNION ALL SELECT query_id, term, node_key FROM nodes JOIN queries ON rel = term) GROUP BY ALL")
def _(spark, sf):
    q = index.query_frame(spark, {"Q10": SETS["Q10"]})
    m = index.match(the_postings(spark, sf), q, metadata=True, nodes=the_graph(spark, sf).nodes)
    return m.groupBy("query_id", "term").agg(F.count_distinct("node_key").alias("n"))


@query("complete_queries", f"{_ASKED} SELECT query_id, count(*) AS n_matches FROM matches WHERE query_id IN (SELECT query_id FROM complete) GROUP BY query_id")
def _(spark, sf):
    q, m = asked(spark, sf, SETS)
    return index.complete(m, q).groupBy("query_id").agg(F.count(F.lit(1)).alias("n_matches"))


@query("frequent_terms", f"WITH {P} SELECT term, count(DISTINCT node_id) AS df FROM postings GROUP BY term HAVING count(DISTINCT node_id) > 200")
def _(spark, sf):
    return index.frequent_terms(the_postings(spark, sf), 200)


# ---- search ----


def _search_sql(sets, cost, **options):
    return f"WITH RECURSIVE {G}, {P}, {sql.queries(sets)}, {sql.distances(cost, **options)}"


def _dist(spark, sf, sets, cost, **options):
    g = the_graph(spark, sf)
    q, m = asked(spark, sf, sets)
    return search.keyword_distances(g.edges, index.complete(m, q), cost, **options)


@query("keyword_distances", f"{_search_sql(PAIRS, 4.0)} SELECT query_id, term, node_key, round(dist, 6) AS dist FROM dist JOIN nodes USING (node_id)")
def _(spark, sf):
    g = the_graph(spark, sf)
    return _dist(spark, sf, PAIRS, 4.0).join(g.nodes.select("node_id", "node_key"), "node_id").select("query_id", "term", "node_key", F.round("dist", 6).alias("dist"))


@query("edge_type_limited", f"""{_search_sql(PAIRS, 3.0, allowed="etype IN ('orders>part', 'orders>customer')")} SELECT query_id, term, count(*) AS n, round(max(dist), 6) AS farthest FROM dist GROUP BY ALL""")
def _(spark, sf):
    d = _dist(spark, sf, PAIRS, 3.0, allowed=("orders>part", "orders>customer"))
    return d.groupBy("query_id", "term").agg(F.count(F.lit(1)).alias("n"), F.round(F.max("dist"), 6).alias("farthest"))


@query("near_objects", f"{_search_sql(PAIRS, 3.0, unit=True)} SELECT query_id, node_key, count(*) AS n_terms, round(sum(dist), 6) AS cost FROM dist JOIN nodes USING (node_id) WHERE rel = 'customer' GROUP BY ALL")
def _(spark, sf):
    g = the_graph(spark, sf)
    d = _dist(spark, sf, PAIRS, 3.0, unit=True)
    return authority.near_objects(d, g.nodes, "customer").join(g.nodes.select("node_id", "node_key"), "node_id").select("query_id", "node_key", "n_terms", F.round("cost", 6).alias("cost"))


@query("keyword_distances_weighted_start", f"WITH RECURSIVE {G}, {P}, {sql.queries(PAIRS)}, {sql.distances(3.0).replace('SELECT query_id, term, node_id, 0.0::DOUBLE FROM matches', 'SELECT query_id, term, node_id, (1 / (1 + prestige))::DOUBLE FROM matches JOIN nodes USING (node_id)')} SELECT query_id, term, count(*) AS n, round(sum(dist), 4) AS total FROM dist GROUP BY ALL")
def _(spark, sf):
    g = the_graph(spark, sf)
    start = g.nodes.select("node_id", (1 / (1 + F.col("prestige"))).alias("start"))
    return _dist(spark, sf, PAIRS, 3.0, start=start).groupBy("query_id", "term").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("dist"), 4).alias("total"))


def scored_answers(spark, sf, sets, cost=4.0, pool=50) -> DataFrame:
    def make():
        g = the_graph(spark, sf)
        q, m = asked(spark, sf, sets)
        ways = search.backward_rounds(g, m, q, cost, pool)
        return cut(answers.score(answers.assemble(ways, g.edges, g.nodes)))

    return held(spark, sf, f"answers {sorted(sets)} {cost} {pool}", make)


_ANSWERS = f"{_search_sql(PAIRS, 4.0)}, {sql.answers(50)}"
_MINIMAL = "(branches <> 1 OR root_holds)"


@query("backward_topk", f"{_ANSWERS}, r AS (SELECT *, edge_score * pow(node_score, 0.2) AS tree_score FROM scored WHERE {_MINIMAL}), k AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(tree_score, 9) DESC, root, leaf_keys) AS rnk FROM r) SELECT query_id, rnk, root_key, leaf_keys, n_nodes, n_edges, round(node_score, 6) AS node_score, round(edge_score, 6) AS edge_score, round(tree_score, 6) AS tree_score FROM k WHERE rnk <= 10")
def backward_topk(spark, sf):
    return answers.report(answers.rank(answers.root_minimal(scored_answers(spark, sf, PAIRS))))


@query("root_minimal", f"{_ANSWERS} SELECT query_id, count(*) AS n, count(*) FILTER (WHERE {_MINIMAL}) AS n_minimal FROM scored GROUP BY query_id")
def _(spark, sf):
    a = scored_answers(spark, sf, PAIRS)
    kept = answers.root_minimal(a).groupBy("query_id").agg(F.count(F.lit(1)).alias("n_minimal"))
    return a.groupBy("query_id").agg(F.count(F.lit(1)).alias("n")).join(kept, "query_id", "left").fillna(0)


@query("steiner_minimal", f"{_ANSWERS}, own AS (SELECT query_id, root, list_sort(list(DISTINCT node_id)) AS m FROM members GROUP BY ALL) SELECT a.query_id, count(*) AS n_minimal FROM own a WHERE NOT EXISTS (SELECT 1 FROM own b WHERE b.query_id = a.query_id AND len(b.m) < len(a.m) AND list_has_all(a.m, b.m)) GROUP BY a.query_id")
def _(spark, sf):
    return answers.subset_minimal(scored_answers(spark, sf, PAIRS)).groupBy("query_id").agg(F.count(F.lit(1)).alias("n_minimal"))


_MODES = [(m, e) for m in ("product", "sum") for e in ("proximity", "printed")]


@query(
    "tree_scores_grid",
    f"{_ANSWERS}, pair AS (SELECT query_id, root_key, node_score, edge_score AS proximity, CASE WHEN total = 0 THEN 0 ELSE 1 / (1 + 1 / total) END AS printed FROM scored) "
    + " UNION ALL ".join(f"SELECT query_id, '{m}' AS mode, '{e}' AS edge_mode, count(*) AS n, round(max({f'{e} * pow(node_score, 0.2)' if m == 'product' else f'0.2 * node_score + 0.8 * {e}'}), 6) AS best FROM pair GROUP BY query_id" for m, e in _MODES),
)
def _(spark, sf):
    a, out = scored_answers(spark, sf, PAIRS), None
    for m, e in _MODES:
        part = a.withColumn("t", tree_score(edge_score(F.col("total"), e), F.col("node_score"), m)).groupBy("query_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.max("t"), 6).alias("best")).select("query_id", F.lit(m).alias("mode"), F.lit(e).alias("edge_mode"), "n", "best")
        out = part if out is None else out.unionByName(part)
    return out


@query("answers_deduped", f"{_ANSWERS}, h AS (SELECT s.query_id, s.root, coalesce(string_agg(least(src, dst) || '-' || greatest(src, dst), ',' ORDER BY least(src, dst), greatest(src, dst)), s.root::VARCHAR) AS h FROM scored s LEFT JOIN branch b ON b.query_id = s.query_id AND b.root = s.root GROUP BY s.query_id, s.root) SELECT query_id, count(DISTINCT h) AS n_trees FROM h GROUP BY query_id")
def _(spark, sf):
    return answers.dedupe(scored_answers(spark, sf, PAIRS)).groupBy("query_id").agg(F.count(F.lit(1)).alias("n_trees"))


@query("answer_text", f"{_ANSWERS}, r AS (SELECT *, edge_score * pow(node_score, 0.2) AS tree_score FROM scored WHERE {_MINIMAL}), k AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(tree_score, 9) DESC, root, leaf_keys) AS rnk FROM r) SELECT k.query_id, rnk, n.node_key, n.text FROM k JOIN members m ON m.query_id = k.query_id AND m.root = k.root JOIN nodes n ON n.node_id = m.node_id WHERE rnk <= 10")
def _(spark, sf):
    g = the_graph(spark, sf)
    return answers.render(answers.rank(answers.root_minimal(scored_answers(spark, sf, PAIRS))), g.nodes)


_SEED = "seed AS (SELECT query_id, term, node_id, prestige / count(*) OVER (PARTITION BY query_id, term) AS activation FROM matches JOIN nodes USING (node_id))"


@query("activation_seed", f"WITH {G}, {P}, {sql.queries(PAIRS)}, {_SEED} SELECT query_id, term, node_key, round(activation, 6) AS activation FROM seed JOIN nodes USING (node_id)")
def _(spark, sf):
    g = the_graph(spark, sf)
    _, m = asked(spark, sf, PAIRS)
    return activation.seed(m, g.nodes).join(g.nodes.select("node_id", "node_key"), "node_id").select("query_id", "term", "node_key", F.round("activation", 6).alias("activation"))


def _spread_sql(how: str, giver: str = "dst", taker: str = "src") -> str:
    return f"WITH {G}, {P}, {sql.queries(PAIRS)}, {_SEED}, pull AS (SELECT {giver} AS g, sum(1 / weight) AS p FROM edges GROUP BY 1), share AS (SELECT {giver} AS g, {taker} AS t, sum(1 / weight) / any_value(p) AS s FROM edges JOIN pull ON g = {giver} GROUP BY 1, 2), got AS (SELECT query_id, term, node_id, activation * 0.5 AS a FROM seed UNION ALL SELECT query_id, term, t, 0.5 * activation * s FROM seed JOIN share ON g = node_id) SELECT query_id, term, node_key, round({how}(a), 6) AS activation FROM got JOIN nodes USING (node_id) GROUP BY ALL"


def _spread(spark, sf, how, direction="in"):
    g = the_graph(spark, sf)
    _, m = asked(spark, sf, PAIRS)
    s = activation.spread(activation.seed(m, g.nodes), g.edges, 0.5, direction, how)
    return s.join(g.nodes.select("node_id", "node_key"), "node_id").select("query_id", "term", "node_key", F.round("activation", 6).alias("activation"))


QUERIES["activation_spread_max"], SQL["activation_spread_max"] = lambda spark, sf: _spread(spark, sf, "max"), _spread_sql("max")
QUERIES["activation_spread_sum"], SQL["activation_spread_sum"] = lambda spark, sf: _spread(spark, sf, "sum"), _spread_sql("sum")
QUERIES["activation_spread_out"], SQL["activation_spread_out"] = lambda spark, sf: _spread(spark, sf, "max", "out"), _spread_sql("max", "src", "dst")


@query("activation_priority", f"WITH {G}, {P}, {sql.queries(PAIRS)}, {_SEED} SELECT query_id, node_id, round(sum(activation), 6) AS total FROM seed GROUP BY ALL")
def _(spark, sf):
    _, m = asked(spark, sf, PAIRS)
    return activation.priority(activation.seed(m, the_graph(spark, sf).nodes)).select("query_id", "node_id", F.round("total", 6).alias("total"))


@query("activation_rounds")
def _(spark, sf):
    g = the_graph(spark, sf)
    _, m = asked(spark, sf, PAIRS)
    return activation.spread_rounds(activation.seed(m, g.nodes), g.edges, rounds=4, batch=50)


def _local(spark, sf, algorithm, sets=PAIRS, **options):
    g = the_graph(spark, sf)
    q, m = asked(spark, sf, sets)
    return search.whole_search(g, index.complete(m, q), q, algorithm, **options)


@query("bidirectional_topk")
def _(spark, sf):
    return held(spark, sf, "reference", lambda: cut(_local(spark, sf, "bidirectional")))


@query("bidirectional_sum")
def _(spark, sf):
    return _local(spark, sf, "bidirectional", combine="sum")


@query("backward_local")
def _(spark, sf):
    return _local(spark, sf, "backward", max_cost=4.0)


@query("backward_weighted_start")
def _(spark, sf):
    return _local(spark, sf, "backward", origin_weight=True, max_cost=4.0)


@query("backward_combinations")
def _(spark, sf):
    return _local(spark, sf, "backward", per_root=2, max_cost=4.0)
