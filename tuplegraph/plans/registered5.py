"""Registered queries on constrained search, folded objects, splits of clusters, late rows and idle users."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..operators import activation, graph, quotient, search
from ..session import shared_dir
from ..sources.catalog import table
from ..streaming import streams
from .registered import G, PAIRS, _search_sql, asked, query, the_graph
from .registered2 import _RANDOM, random_pages

_TYPES = ("orders>part", "orders>customer")
_NAMED = {q: PAIRS[q] for q in ("Q01", "Q03")}


@query("bidirectional_limited", f"""{_search_sql(_NAMED, 9.0, allowed="etype IN ('orders>part', 'orders>customer')")}, sums AS (SELECT query_id, node_id AS root, round(sum(dist), 6) AS cost FROM dist GROUP BY 1, 2 HAVING count(*) = 2), r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY cost, root) AS r FROM sums) SELECT query_id, root, cost FROM r WHERE r <= 10""")
def _(spark, sf):
    """The bidirectional search along two types of edges only."""
    q, m = asked(spark, sf, _NAMED)
    found = search.bidirectional_rounds(the_graph(spark, sf), m, q, allowed=_TYPES)
    return search.roots(found.select("query_id", "term", "node_id", "dist"), q, 10)


@query("shares_by_priority", f"WITH {G}, e AS (SELECT src, dst, CASE etype WHEN 'orders>part' THEN 3.0 ELSE 1.0 END / weight AS pull FROM edges WHERE etype <> 'orders>supplier'), t AS (SELECT dst, sum(pull) AS total FROM e GROUP BY 1), s AS (SELECT dst, src, sum(pull) / any_value(total) AS share FROM e JOIN t USING (dst) GROUP BY 1, 2) SELECT dst >> 56 AS relation, count(*) AS n, round(sum(share), 4) AS total, round(sum(share * share), 4) AS squares FROM s GROUP BY 1")
def _(spark, sf):
    """What nodes pass on when one type of edge is preferred and another forbidden."""
    e = graph.priority(the_graph(spark, sf).edges.drop("priority"), {"orders>part": 3.0}, ("orders>supplier",))
    s = activation.shares(e).groupBy(F.shiftright("giver", 56).alias("relation"))
    return s.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("share"), 4).alias("total"), F.round(F.sum(F.col("share") * F.col("share")), 4).alias("squares"))


def _objects(spark, sf):
    lines = graph.link_nodes(spark, sf)
    nodes = graph.build_nodes(spark, sf).select("node_key", "text").unionByName(lines.select("node_key", "text"))
    owners = lines.select("node_key", graph.node_key("orders", F.col("l_orderkey")).alias("owner_key"))
    return graph.fold(nodes, graph.uncontracted_references(spark, sf).drop("etype"), owners)


@query("object_nodes", f"WITH {G}, t AS (SELECT node_key, text FROM nodes UNION ALL SELECT 'orders:' || l_orderkey, concat_ws(' ', l_returnflag, l_linestatus) FROM lineitem) SELECT node_key, count(*) - 1 AS n_folded, string_agg(DISTINCT text, ' | ' ORDER BY text) AS text FROM t GROUP BY 1")
def _(spark, sf):
    """Orders with their lines folded into them, beside all other nodes."""
    return _objects(spark, sf)[0]


@query(
    "object_edges",
    "SELECT src_key, dst_key, count(*) AS n_links FROM (SELECT 'nation:' || n_nationkey AS src_key, 'region:' || n_regionkey AS dst_key FROM nation UNION ALL SELECT 'customer:' || c_custkey, 'nation:' || c_nationkey FROM customer UNION ALL SELECT 'supplier:' || s_suppkey, 'nation:' || s_nationkey FROM supplier "
    "UNION ALL SELECT 'orders:' || o_orderkey, 'customer:' || o_custkey FROM orders UNION ALL SELECT 'orders:' || l_orderkey, 'part:' || l_partkey FROM lineitem UNION ALL SELECT 'orders:' || l_orderkey, 'supplier:' || l_suppkey FROM lineitem) GROUP BY 1, 2",
)
def _(spark, sf):
    return _objects(spark, sf)[1]


@query("superedges_after_split", f"WITH {G}, {_RANDOM}, split AS (SELECT node_id, CASE WHEN cluster_id % 7 = 0 AND node_id % 2 = 1 THEN -cluster_id - 1 ELSE cluster_id END AS cluster_id FROM membership) SELECT a.cluster_id AS src_c, b.cluster_id AS dst_c, count(*) AS n_links FROM edges e JOIN split a ON a.node_id = e.src JOIN split b ON b.node_id = e.dst WHERE a.cluster_id <> b.cluster_id GROUP BY 1, 2")
def _(spark, sf):
    """Some clusters are split in two; only super-edges that touch them are computed anew."""
    e, old = the_graph(spark, sf).edges, random_pages(spark, sf)
    parted = (F.col("cluster_id") % 7 == 0) & (F.col("node_id") % 2 == 1)
    new = old.withColumn("cluster_id", F.when(parted, -F.col("cluster_id") - 1).otherwise(F.col("cluster_id")))
    touched = old.where("cluster_id % 7 = 0").select("cluster_id").union(new.where("cluster_id < 0").select("cluster_id")).distinct()
    return quotient.update(quotient.super_edges(e, old), e, new, touched).select("src_c", "dst_c", "n_links")


@query("stream_late_rows", "WITH f AS (SELECT date_trunc('millisecond', max(ts)) - INTERVAL 10 DAY AS mark FROM events WHERE event_type = 'purchase') SELECT count(*) FILTER (WHERE event_type = 'purchase' OR ts > mark) AS n_kept, count(*) FILTER (WHERE event_type <> 'purchase' AND ts <= mark) AS n_late FROM events, f")
def _(spark, sf):
    """Purchases are delivered first, then all other events: those behind the watermark are dropped and counted."""
    path = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    rows, late = table(spark, sf, "events"), 0
    for first in (True, False):
        rows.where((F.col("event_type") == "purchase") == first).write.mode("append").parquet(f"{path}/in")
        late += streams.deliver(streams.unique(streams.events(spark, f"{path}/in", "10 days", "*.parquet"), ["event_id"]), path)
    return spark.read.parquet(f"{path}/rows").agg(F.count(F.lit(1)).alias("n_kept"), F.lit(late).cast("long").alias("n_late"))


@query("stream_idle_users", "WITH g AS (SELECT user_id, event_id, ts, CASE WHEN ts - lag(ts) OVER w > INTERVAL 3 DAY THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM g) SELECT user_id, count(*) AS n FROM s JOIN (SELECT user_id, max(k) AS k FROM s GROUP BY 1) USING (user_id, k) GROUP BY 1")
def _(spark, sf):
    """Events of each user since a pause of more than three days; idle users leave the state."""
    return streams.drain(streams.decayed(streams.events(spark, sf), idle=3 * 86400.0), "update").select("user_id", "n")


@query("sample_stratified_close", "SELECT o_orderstatus, count(*) AS n, true AS close FROM orders WHERE o_orderstatus IN ('F', 'O') GROUP BY 1")
def _(spark, sf):
    """A stratified sample has its share of each stratum within six standard deviations, and nothing of others."""
    share = {"F": 0.1, "O": 0.2}
    rows = table(spark, sf, "orders")
    taken = rows.sampleBy("o_orderstatus", share, 7).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("k"))
    part = F.when(F.col("o_orderstatus") == "F", share["F"]).otherwise(share["O"])
    counts = rows.where(F.col("o_orderstatus").isin(list(share))).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n")).join(taken, "o_orderstatus", "full_outer")
    return counts.select("o_orderstatus", "n", (F.abs(F.coalesce("k", F.lit(0)) - F.col("n") * part) <= 1 + 6 * F.sqrt(F.col("n") * part * (1 - part))).alias("close"))
