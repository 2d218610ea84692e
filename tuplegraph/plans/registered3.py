"""Registered queries on relational operators and streams."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import browse, ops
from ..operators.components import components
from ..session import shared_dir
from ..sources.catalog import table as t
from ..streaming import streams
from . import sql
from .registered import G, P, QUERIES, SQL, query, the_graph, the_postings
from .registered2 import history


def both(name: str, text: str):
    """A query whose SQL both engines take as it stands."""

    @query(name, text)
    def run(spark, sf):
        for x in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"):
            t(spark, sf, x).createOrReplaceTempView(x)
        return spark.sql(text)


def simple(name: str, oracle: str, make):
    QUERIES[name], SQL[name] = make, oracle


simple("scan_pruned", "SELECT c_custkey, c_name FROM customer", lambda s, d: t(s, d, "customer").select("c_custkey", "c_name"))
for _f in ("csv", "json", "orc"):
    simple(f"round_trip_{_f}", "SELECT * FROM nation", lambda s, d, f=_f: ops.round_trip(s, d, f))
simple("filters", "SELECT p_partkey FROM part WHERE p_name LIKE '%widget%' AND p_size BETWEEN 1 AND 10 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#21', 'Brand#22') AND p_type IS NOT NULL", lambda s, d: t(s, d, "part").where(F.col("p_name").contains("widget") & F.col("p_size").between(1, 10) & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#21", "Brand#22") & F.col("p_type").isNotNull()).select("p_partkey"))
simple("computed_columns", "SELECT l_orderkey, l_partkey, l_suppkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS revenue FROM lineitem", lambda s, d: t(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("revenue")))
simple("join_broadcast", "SELECT c_custkey, n_name FROM customer JOIN nation ON n_nationkey = c_nationkey", lambda s, d: t(s, d, "customer").join(F.broadcast(t(s, d, "nation")), F.col("n_nationkey") == F.col("c_nationkey")).select("c_custkey", "n_name"))
for _f in ("shuffle_hash", "merge"):
    simple(f"join_{_f}", "SELECT o_orderkey, count(*) AS n_lines FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey", lambda s, d, f=_f: t(s, d, "orders").hint(f).join(t(s, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("n_lines")))
for _f in ("left", "right", "full"):
    simple(f"join_{_f}_outer", f"SELECT count(*) AS n, count(l_orderkey) AS n_lines, count(o_orderkey) AS n_orders FROM orders {_f.upper()} JOIN lineitem ON l_orderkey = o_orderkey", lambda s, d, f=_f: t(s, d, "orders").join(t(s, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), f).agg(F.count(F.lit(1)).alias("n"), F.count("l_orderkey").alias("n_lines"), F.count("o_orderkey").alias("n_orders")))
simple("join_semi", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem JOIN part ON p_partkey = l_partkey WHERE p_name LIKE '%widget%')", lambda s, d: t(s, d, "orders").join(t(s, d, "lineitem").join(t(s, d, "part").where(F.col("p_name").contains("widget")), F.col("p_partkey") == F.col("l_partkey")), F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").select("o_orderkey"))
simple("join_anti", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)", lambda s, d: t(s, d, "orders").join(t(s, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").select("o_orderkey"))


@query("join_self", "SELECT DISTINCT a.l_orderkey, a.l_partkey AS p, b.l_partkey AS q FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey")
def _(spark, sf):
    a = t(spark, sf, "lineitem").select("l_orderkey", F.col("l_partkey").alias("p")).distinct()
    return a.join(a.withColumnRenamed("p", "q"), "l_orderkey").where("p < q")


simple("join_band", "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey AND abs(a.p_retailprice - b.p_retailprice) <= 0.05", lambda s, d: ops.band_join(t(s, d, "part")))
simple("join_cross_bounded", "SELECT r_name, q FROM region, (VALUES ('x'), ('y'), ('z')) v(q)", lambda s, d: t(s, d, "region").crossJoin(F.broadcast(s.createDataFrame([("x",), ("y",), ("z",)], "q string"))).select("r_name", "q"))
simple("join_as_of", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_purchase FROM events", lambda s, d: ops.as_of(t(s, d, "events")))
simple("join_interval", "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR", lambda s, d: ops.interval_join(t(s, d, "events")))
simple("aggregate_hash", "SELECT l_partkey, count(*) AS n, round(sum(l_quantity), 4) AS quantity FROM lineitem GROUP BY 1", lambda s, d: t(s, d, "lineitem").groupBy("l_partkey").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 4).alias("quantity")))
simple("aggregate_list", "SELECT l_orderkey, array_to_string(list_sort(list(DISTINCT l_partkey)), ',') AS parts FROM lineitem GROUP BY 1", lambda s, d: t(s, d, "lineitem").groupBy("l_orderkey").agg(F.array_join(F.array_sort(F.collect_set("l_partkey")).cast("array<string>"), ",").alias("parts")))
simple("count_distinct", "SELECT l_suppkey, count(DISTINCT l_partkey) AS n_parts FROM lineitem GROUP BY 1", lambda s, d: t(s, d, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("n_parts")))
QUERIES["count_approximate"] = lambda s, d: t(s, d, "lineitem").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey", 0.02).alias("n_parts"))
both("rollup_region", "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)")
both("cube_orders", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
both("grouping_sets", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_mktsegment, c_nationkey))")
simple("pivot_events", "SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) FILTER (WHERE event_type = 'view') AS \"view\", count(*) FILTER (WHERE event_type = 'purchase') AS purchase FROM events GROUP BY 1", lambda s, d: t(s, d, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).pivot("event_type", ["view", "purchase"]).agg(F.count(F.lit(1))).fillna(0))
both("having_orders", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12")
both("min_max_by", "SELECT p_brand, min_by(p_partkey, p_retailprice * 100000 + p_partkey) AS cheapest, max_by(p_partkey, p_retailprice * 100000 + p_partkey) AS dearest FROM part GROUP BY p_brand")
simple("percentiles", "SELECT p_brand, round(quantile_cont(p_retailprice, 0.9), 6) AS p90 FROM part GROUP BY 1", lambda s, d: t(s, d, "part").groupBy("p_brand").agg(F.round(F.percentile("p_retailprice", 0.9), 6).alias("p90")))
both("regression", "SELECT round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM lineitem")
both("window_ranks", "SELECT p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS rn, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS rk, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS dr FROM part")
both("window_shares", "SELECT p_partkey, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS quarter, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_size), 6) AS pr, round(cume_dist() OVER (PARTITION BY p_brand ORDER BY p_size), 6) AS cd FROM part")
both("window_lag_lead", "SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after FROM events")
both("window_running", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n, sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS running FROM events")
SQL["window_running"] = SQL["window_running"].replace("sum(event_id)", "(sum(event_id)").replace("CURRENT ROW) AS running", "CURRENT ROW))::BIGINT AS running")
both("window_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL '1' HOUR PRECEDING AND CURRENT ROW) AS n FROM events")
both("window_first", "SELECT event_id, first_value(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS first_event, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_event FROM events")
both("sort_limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10")
both("top_per_group", "SELECT p_brand, p_partkey FROM (SELECT p_brand, p_partkey, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS r FROM part) WHERE r <= 3")
both("union_names", "SELECT n_name AS name FROM nation UNION ALL SELECT r_name FROM region UNION ALL SELECT s_name FROM supplier")
both("intersect_all_parts", "SELECT l_partkey FROM lineitem WHERE l_suppkey = 1 INTERSECT ALL SELECT l_partkey FROM lineitem WHERE l_quantity > 5")
both("except_all_parts", "SELECT l_partkey FROM lineitem WHERE l_suppkey <= 5 EXCEPT ALL SELECT l_partkey FROM lineitem WHERE l_suppkey = 1")
both("distinct_pairs", "SELECT DISTINCT l_orderkey, l_partkey FROM lineitem")
simple("string_functions", "SELECT p_partkey, upper(trim(p_name)) AS u, substr(p_type, 1, 3) AS s, strpos(p_name, ' ')::INT AS space, md5(p_brand) AS h, length(p_name) AS n FROM part", lambda s, d: t(s, d, "part").select("p_partkey", F.upper(F.trim("p_name")).alias("u"), F.substring("p_type", 1, 3).alias("s"), F.instr("p_name", " ").alias("space"), F.md5(F.col("p_brand").cast("binary")).alias("h"), F.length("p_name").alias("n")))
simple("edit_distance", "SELECT DISTINCT term AS value, levenshtein(term, 'widgit') AS distance FROM (SELECT unnest(string_split(p_name, ' ')) AS term FROM part) WHERE levenshtein(term, 'widgit') <= 2", lambda s, d: ops.edit_matches(t(s, d, "part").select(F.explode(F.split("p_name", " ")).alias("value")).distinct(), "widgit", 2))
both("date_functions", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m FROM orders")
simple("date_gaps", "SELECT o_custkey, date_diff('day', min(o_orderdate)::DATE, max(o_orderdate)::DATE)::INT AS days FROM orders GROUP BY 1", lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.datediff(F.max("o_orderdate"), F.min("o_orderdate")).alias("days")))
both("math_functions", "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS r, round(exp(p_size / 100.0), 6) AS e, greatest(p_size, 10) AS g, least(p_size, 10) AS l, abs(p_size - 25) AS a FROM part")
simple("array_functions", "SELECT l_orderkey, len(list_filter(x, lambda v: v > 100))::INT AS n_large, list_sum(list_transform(x, lambda v: v % 7))::BIGINT AS total FROM (SELECT l_orderkey, list(l_partkey) AS x FROM lineitem GROUP BY 1)", lambda s, d: t(s, d, "lineitem").groupBy("l_orderkey").agg(F.collect_list("l_partkey").alias("x")).select("l_orderkey", F.size(F.filter("x", lambda v: v > 100)).alias("n_large"), F.aggregate(F.transform("x", lambda v: v % 7), F.lit(0).cast("long"), lambda a, b: a + b).alias("total")))
simple("map_functions", "SELECT user_id, count(*) FILTER (WHERE event_type = 'view') * 2 AS views FROM events GROUP BY 1", lambda s, d: t(s, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select("user_id", F.coalesce(F.try_element_at(F.transform_values("m", lambda k, v: v * 2), F.lit("view")), F.lit(0)).alias("views")))
simple("json_functions", "SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events", lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))
simple("explode_positions", "SELECT p_partkey, unnest(range(len(w)))::INT AS pos, unnest(w) AS word FROM (SELECT p_partkey, string_split(p_name, ' ') AS w FROM part)", lambda s, d: t(s, d, "part").select("p_partkey", F.posexplode(F.split("p_name", " ")).alias("pos", "word")))
simple("nested_structs", "SELECT o_custkey, max(o_totalprice) AS price FROM orders GROUP BY 1", lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.max(F.struct(F.col("o_totalprice").alias("price"), "o_orderkey")).alias("m")).select("o_custkey", "m.price"))
simple("k_hops", f"WITH RECURSIVE {G}, h(node_id, hop) USING KEY (node_id) AS (SELECT {sql.node(5, '7')}, 0 UNION SELECT dst, min(h.hop + 1) FROM h JOIN edges ON src = h.node_id LEFT JOIN recurring.h r ON r.node_id = dst WHERE h.hop < 2 AND r.hop IS NULL GROUP BY dst) SELECT node_id, hop FROM h", lambda s, d: ops.hops(the_graph(s, d).edges, s.createDataFrame([((5 << 56) | 7,)], "node_id long"), 2))


@query("components_of_copies", "SELECT doc_id, first AS label FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS first, count(*) OVER (PARTITION BY text) AS n FROM documents) WHERE n > 1")
def _(spark, sf):
    docs = t(spark, sf, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("h"))
    links = docs.join(docs.groupBy("h").agg(F.max("doc_id").alias("b")), "h").where("doc_id <> b").select(F.col("doc_id").alias("a"), "b")
    return components(links).select(F.col("node").alias("doc_id"), "label")


QUERIES["sample_by_hash"] = lambda s, d: ops.hash_sample(t(s, d, "customer").select("c_custkey"), "c_custkey", 10, 1)
QUERIES["sample_stratified"] = lambda s, d: t(s, d, "orders").sampleBy("o_orderstatus", {"F": 0.1, "O": 0.2}, 7).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))
both("subqueries", "SELECT c_custkey FROM customer c WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer) AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c.c_custkey AND o_orderstatus = 'F') AND c_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)")
both("recursive_paths", "WITH RECURSIVE p(n, d) AS (SELECT 1, 0 UNION ALL SELECT n * 2, d + 1 FROM p WHERE d < 6) SELECT n, d FROM p")
both("conditionals", "SELECT o_orderkey, CASE WHEN o_totalprice > 300000 THEN 'large' WHEN o_totalprice > 100000 THEN 'middle' ELSE 'small' END AS size_class FROM orders")
simple("exact_sums", "SELECT l_returnflag, sum(l_extendedprice::DECIMAL(18, 4))::VARCHAR AS total FROM lineitem GROUP BY 1", lambda s, d: t(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,4)")).cast("string").alias("total")))
simple("vector_distance", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) AS norm FROM embeddings", lambda s, d: t(s, d, "embeddings").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 5).alias("norm")))

# ---- streams, run to the end of the events file ----

simple("stream_tumbling", "SELECT strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY ALL", lambda s, d: streams.drain(streams.tumbling(streams.events(s, d))).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n"))
simple("stream_sliding", "SELECT strftime(time_bucket(INTERVAL 1 DAY, ts) - k * INTERVAL 1 DAY, '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events, range(2) r(k) GROUP BY ALL", lambda s, d: streams.drain(streams.sliding(streams.events(s, d))).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n"))
simple("stream_sessions", "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, new DESC ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, count(*) AS n FROM s GROUP BY user_id, k", lambda s, d: streams.drain(streams.sessions(streams.events(s, d))).select("user_id", "n"))
simple("stream_degrees", "SELECT user_id, count(*) AS indeg FROM events GROUP BY 1", lambda s, d: streams.drain(streams.degrees(streams.events(s, d, None))))
simple("stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id", lambda s, d: streams.drain(streams.with_customers(streams.events(s, d), t(s, d, "customer")), "append").select("event_id", "c_mktsegment"))
simple("stream_interval_join", SQL["join_interval"], lambda s, d: streams.drain(streams.views_then_purchases(streams.events(s, d), streams.events(s, d)), "append"))
simple("stream_unique", "SELECT DISTINCT user_id, event_type FROM events", lambda s, d: streams.drain(streams.unique(streams.events(s, d, "3650 days"), ["user_id", "event_type"]), "append").select("user_id", "event_type"))
simple("stream_user_state", "SELECT user_id, count(*) AS n FROM events GROUP BY 1", lambda s, d: streams.drain(streams.decayed(streams.events(s, d, None)), "update").select("user_id", "n"))


@query("stream_incremental_edges", "SELECT user_id, count(*) AS indeg FROM events GROUP BY 1")
def _(spark, sf):
    import uuid

    path = f"{shared_dir(spark)}/degrees-{uuid.uuid4().hex}"
    streams.incremental_edges(spark, streams.events(spark, sf, None), path)
    return streams.newest(spark, path)


@query("stream_query_log")
def _(spark, sf):
    import uuid

    path = f"{shared_dir(spark)}/log-{uuid.uuid4().hex}"
    history(spark, sf).write.parquet(f"{path}/in")
    log = spark.readStream.schema("term string, cluster_id long, hits long").parquet(f"{path}/in")
    streams.log_statistics(spark, log, f"{path}/out")
    return streams.newest(spark, f"{path}/out")
