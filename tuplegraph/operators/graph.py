"""Relations as a directed weighted graph.

A node id is the relation's code above the integer key, so references become edges without a join. A link relation that
holds only keys is contracted: its rows become edges between the rows they link. Weights are small where tuples are
close; a reverse edge costs the logarithm of the in-degree of the tuple it leaves, so that paths through hubs are dear.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.loop import cut, drop, sweep
from ..sources.catalog import KEY_BITS, LINK, LINK_REFERENCES, REFERENCES, RELATIONS, Reference, Relation, table


@dataclass
class Graph:
    """nodes (node_id, node_key, rel, text, indeg, outdeg, prestige); edges (src, dst, etype, direction, weight, priority).

    pairs: the edges by the pairs of their ends (``cluster.two_way``), where they are stored.
    """

    nodes: DataFrame
    edges: DataFrame
    pairs: DataFrame | None = None


def node_id(relation: Relation | str, key: Column) -> Column:
    code = (RELATIONS[relation] if isinstance(relation, str) else relation).code
    return F.shiftleft(F.lit(code).cast("long"), KEY_BITS).bitwiseOR(key.cast("long"))


def node_key(relation: str, *key: Column) -> Column:
    return F.concat(F.lit(f"{relation}:"), F.concat_ws("-", *[k.cast("string") for k in key]))


def build_nodes(spark: SparkSession, sf_dir: str, relations: tuple[Relation, ...] = tuple(RELATIONS.values())) -> DataFrame:
    """(node_id, node_key, rel, text): one node for each row."""
    parts = []
    for r in relations:
        rows, key = table(spark, sf_dir, r.name), F.col(r.key[0])
        parts.append(rows.select(node_id(r, key).alias("node_id"), node_key(r.name, key).alias("node_key"), F.lit(r.name).alias("rel"), F.concat_ws(" ", *r.text).alias("text")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def contract_relation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges (src, dst, etype, n_links) that replace the link relation: order to part and order to supplier."""
    lines = table(spark, sf_dir, LINK.name)
    parts = []
    for parent, column in (("part", "l_partkey"), ("supplier", "l_suppkey")):
        pairs = lines.groupBy("l_orderkey", column).agg(F.count(F.lit(1)).alias("n_links"))
        parts.append(pairs.select(node_id("orders", F.col("l_orderkey")).alias("src"), node_id(parent, F.col(column)).alias("dst"), F.lit(f"orders>{parent}").alias("etype"), "n_links"))
    return parts[0].unionByName(parts[1])


def forward_edges(spark: SparkSession, sf_dir: str, references: tuple[Reference, ...] = REFERENCES) -> DataFrame:
    """(src, dst, etype) of references whose column is not null."""
    parts = []
    for r in references:
        rows = table(spark, sf_dir, r.child).where(F.col(r.column).isNotNull())
        parts.append(rows.select(node_id(r.child, F.col(RELATIONS[r.child].key[0])).alias("src"), node_id(r.parent, F.col(r.column)).alias("dst"), F.lit(r.etype).alias("etype")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def similarity_table(spark: SparkSession, similarity: dict[str, float]) -> DataFrame:
    """Similarity of relation pairs by link type; a few rows."""
    return spark.createDataFrame(sorted(similarity.items()), "etype string, sim double")


def forward_weight(edges: DataFrame, similarity: dict[str, float] | None = None) -> DataFrame:
    """Weight of a reference: the similarity of its type, 1 where none is given."""
    if not similarity:
        return edges.withColumn("weight", F.lit(1.0))
    sims = F.broadcast(similarity_table(edges.sparkSession, similarity))
    return edges.join(sims, "etype", "left").withColumn("weight", F.coalesce("sim", F.lit(1.0))).drop("sim")


def indegree(edges: DataFrame, per_type: bool = False) -> DataFrame:
    """(node_id, [etype,] indeg) from forward edges."""
    keys = ["dst", "etype"] if per_type else ["dst"]
    return edges.groupBy(*keys).agg(F.count(F.lit(1)).alias("indeg")).withColumnRenamed("dst", "node_id")


def with_reverse(edges: DataFrame, back_weight: str = "log_indegree", per_type: bool = False, table_: dict[str, float] | None = None) -> DataFrame:
    """Forward edges (src, dst, etype, weight) and a reverse of each, with direction and weight."""
    forward = edges.select("src", "dst", "etype", F.lit("fwd").alias("direction"), "weight")
    turned = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "etype", F.lit("back").alias("direction"), "weight")
    if back_weight == "unit":
        back = turned
    elif back_weight == "table":
        back = turned.withColumn("weight", F.coalesce(F.create_map(*[F.lit(x) for p in sorted((table_ or {}).items()) for x in p])[F.col("etype")] if table_ else F.lit(None).cast("double"), F.col("weight")))
    elif back_weight == "log_indegree":
        degree = indegree(edges, per_type).withColumnRenamed("node_id", "src")
        back = turned.join(degree, ["src", "etype"] if per_type else ["src"]).withColumn("weight", F.col("weight") * F.log2(1.0 + F.col("indeg"))).drop("indeg").select(*forward.columns)
    else:
        raise ValueError(back_weight)
    return forward.unionByName(back)


def priority(edges: DataFrame, values: dict[str, float] | None = None, forbid: tuple[str, ...] = ()) -> DataFrame:
    """Edges without forbidden types, with a priority by type (1 where none is given)."""
    kept = edges.where(~F.col("etype").isin(list(forbid))) if forbid else edges
    if not values:
        return kept.withColumn("priority", F.lit(1.0))
    known = F.create_map(*[F.lit(x) for p in sorted(values.items()) for x in p])
    return kept.withColumn("priority", F.coalesce(known[F.col("etype")], F.lit(1.0)))


def damp_weights(edges: DataFrame) -> DataFrame:
    """Weights on a log scale of the least weight."""
    least = edges.agg(F.min("weight").alias("m"))
    return edges.crossJoin(F.broadcast(least)).withColumn("weight", F.log2(1 + F.col("weight") / F.col("m"))).drop("m")  # one row


def damp_prestige(nodes: DataFrame, mode: str = "log") -> DataFrame:
    if mode == "log":
        return nodes.withColumn("prestige", F.log2(1 + F.col("prestige")))
    most = nodes.agg(F.greatest(F.max("prestige"), F.lit(1e-300)).alias("m"))
    return nodes.crossJoin(F.broadcast(most)).withColumn("prestige", F.col("prestige") / F.col("m")).drop("m")  # one row


def references(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All forward edges of the contracted graph, (src, dst, etype, weight)."""
    edges = forward_edges(spark, sf_dir).unionByName(contract_relation(spark, sf_dir).drop("n_links"))
    return forward_weight(edges)


def build(spark: SparkSession, sf_dir: str, back_weight: str = "log_indegree", stored: bool = True) -> Graph:
    """The contracted graph with reverse edges, in-degree as prestige. Stored edges lie in buckets of their target."""
    forward = references(spark, sf_dir)
    if stored:
        forward = cut(forward)
        sweep(spark)
    into = indegree(forward)
    out = forward.groupBy(F.col("src").alias("node_id")).agg(F.count(F.lit(1)).alias("outdeg"))
    nodes = build_nodes(spark, sf_dir).join(into, "node_id", "left").join(out, "node_id", "left")
    nodes = nodes.select("node_id", "node_key", "rel", "text", F.coalesce("indeg", F.lit(0)).alias("indeg"), F.coalesce("outdeg", F.lit(0)).alias("outdeg"), F.coalesce("indeg", F.lit(0)).cast("double").alias("prestige"))
    edges = priority(with_reverse(forward, back_weight))
    if not stored:
        return Graph(nodes, edges)
    kept = cut(nodes)
    sweep(spark)
    out = Graph(kept, cut(edges, "dst", 2 * forward.count()))
    drop(forward)
    return out


def link_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(node_key, l_orderkey, l_partkey, l_suppkey, text) of the link relation kept as nodes; its key columns do not suffice, so a
    number over the other columns tells equal ones apart."""
    lines = table(spark, sf_dir, LINK.name)
    rest = [c for c in lines.columns if c not in LINK.key]
    number = F.row_number().over(Window.partitionBy(*LINK.key).orderBy(*rest))
    return lines.withColumn("n", number).select(node_key("lineitem", *[F.col(k) for k in LINK.key], F.col("n")).alias("node_key"), "l_orderkey", "l_partkey", "l_suppkey", F.concat_ws(" ", "l_returnflag", "l_linestatus").alias("text"))


def uncontracted_references(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src_key, dst_key, etype) with the link relation kept as nodes."""
    out = None
    for r in REFERENCES:
        rows = table(spark, sf_dir, r.child).where(F.col(r.column).isNotNull())
        part = rows.select(node_key(r.child, F.col(RELATIONS[r.child].key[0])).alias("src_key"), node_key(r.parent, F.col(r.column)).alias("dst_key"), F.lit(r.etype).alias("etype"))
        out = part if out is None else out.unionByName(part)
    links = link_nodes(spark, sf_dir)
    for r in LINK_REFERENCES:
        out = out.unionByName(links.select(F.col("node_key").alias("src_key"), node_key(r.parent, F.col(r.column)).alias("dst_key"), F.lit(r.etype).alias("etype")))
    return out


def find_transitive(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = ("nation", "customer", "supplier", "orders", "lineitem")) -> DataFrame:
    """Relations whose own key is made of references only: candidates for contraction. From schemas alone."""
    own = {r.name: r for r in (*RELATIONS.values(), LINK)}
    refs = {n: {r.column for r in REFERENCES + LINK_REFERENCES if r.child == n} for n in names}
    rows = [(n, len(refs[n]), sum(c in refs[n] for c in own[n].key), len(refs[n]) > 1 and sum(c in refs[n] for c in own[n].key) > 1) for n in names]
    return spark.createDataFrame(rows, "rel string, n_references int, n_key_references int, transitive boolean")


def inclusion_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src_key, dst_key) of value containments that are no declared references."""
    events = table(spark, sf_dir, "events").join(table(spark, sf_dir, "customer").select("c_custkey"), F.col("user_id") == F.col("c_custkey"), "left_semi")
    labels = table(spark, sf_dir, "labels").join(table(spark, sf_dir, "documents").select(F.col("doc_id").alias("d")), F.col("doc_id") == F.col("d"), "left_semi")
    return events.select(node_key("events", F.col("event_id")).alias("src_key"), node_key("customer", F.col("user_id")).alias("dst_key")).unionByName(
        labels.select(node_key("labels", F.col("doc_id")).alias("src_key"), node_key("documents", F.col("doc_id")).alias("dst_key"))
    )


def passage_edges(spark: SparkSession, sf_dir: str, words: int = 8) -> DataFrame:
    """(src_key, dst_key): benchmark passages inside document texts. A shingle join finds candidates, ``contains`` confirms."""
    shingle = lambda t: F.transform(F.sequence(F.lit(0), F.size(t) - words), lambda i: F.xxhash64(F.slice(t, i + 1, words)))
    parts = lambda c: F.split(F.col(c), " ")
    items = table(spark, sf_dir, "benchmark").withColumn("t", parts("text")).where(F.size("t") > words)  # the first word of a passage may be glued to what stands before it
    items = items.select("item_id", F.col("text").alias("passage"), F.element_at(shingle(F.col("t")), 2).alias("h"))
    docs = table(spark, sf_dir, "documents").withColumn("t", parts("text")).where(F.size("t") >= words)
    hits = docs.select("doc_id", F.explode(F.array_distinct(shingle(F.col("t")))).alias("h")).join(items.select("h", "item_id"), "h")
    pairs = hits.select("doc_id", "item_id").distinct()
    full = pairs.join(table(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id").join(items.select("item_id", "passage"), "item_id")
    return full.where(F.contains("text", "passage")).select(node_key("benchmark", F.col("item_id")).alias("src_key"), node_key("documents", F.col("doc_id")).alias("dst_key"))


def similarity_edges(spark: SparkSession, sf_dir: str, n: int = 3, tables: int = 16, bits: int = 4) -> DataFrame:
    """(a, b, weight): for each vector its n nearest among those that share a sign pattern of a few dimensions in some table.

    Patterns block the vectors, so only pairs within a block are compared; a pair in several blocks counts once. Recall of
    the 3 nearest against brute force is 0.93 on the given vectors at sf0.01 and sf0.1 (0.91 and 0.86 with 12 tables); they
    are close to random, so fewer comparisons cost recall.
    """
    rows = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    pattern = lambda t: F.concat_ws("", *[F.when(F.element_at("embedding", (t * bits + k) % 64 + 1) >= 0, "1").otherwise("0") for k in range(bits)])
    keyed = rows.select("vec_id", "embedding", F.explode(F.array(*[F.concat(F.lit(f"{t}:"), pattern(t)) for t in range(tables)])).alias("key"))
    other = keyed.select(F.col("vec_id").alias("b"), F.col("embedding").alias("eb"), "key")
    pairs = keyed.withColumnRenamed("vec_id", "a").join(other, "key").where("a <> b").select("a", "b", "embedding", "eb").dropDuplicates(["a", "b"])
    cosine = F.aggregate(F.zip_with("embedding", "eb", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    near = pairs.select("a", "b", F.greatest(F.lit(0.001), 1 - cosine).alias("weight"))
    return near.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy("weight", "b"))).where(F.col("r") <= n).drop("r")


def copy_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(src_key, dst_key): each document whose text occurred before points at the first of its copies."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.md5(F.col("text").cast("binary")).alias("h"))
    first = docs.groupBy("h").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1")
    return docs.join(first, "h").where("doc_id <> first").select(node_key("documents", F.col("doc_id")).alias("src_key"), node_key("documents", F.col("first")).alias("dst_key"))


def objectify(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as objects that own their lines: (node_key, n_lines, n_parts, n_suppliers)."""
    lines = table(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.count(F.lit(1)).alias("n_lines"), F.count_distinct("l_partkey").alias("n_parts"), F.count_distinct("l_suppkey").alias("n_suppliers"))
    orders = table(spark, sf_dir, "orders").select("o_orderkey").join(lines, "o_orderkey", "left")
    return orders.select(node_key("orders", F.col("o_orderkey")).alias("node_key"), *[F.coalesce(c, F.lit(0)).alias(c) for c in ("n_lines", "n_parts", "n_suppliers")])


def fold(nodes: DataFrame, edges: DataFrame, owners: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(node_key, n_folded, text) and (src_key, dst_key, n_links): nodes that have an owner become part of its object.

    nodes (node_key, text); edges (src_key, dst_key); owners (node_key, owner_key). An object's text is the set of its
    members' texts; edges inside an object go, parallel ones are counted.
    """
    owned = owners.select(F.col("node_key").alias("member"), "owner_key")
    named = nodes.join(owned, F.col("node_key") == F.col("member"), "left").select(F.coalesce("owner_key", "node_key").alias("node_key"), "text")
    sizes = named.groupBy("node_key").agg((F.count(F.lit(1)) - 1).alias("n_folded"))
    texts = named.distinct().groupBy("node_key").agg(F.array_join(F.array_sort(F.collect_list("text")), " | ").alias("text"))
    for end in ("src_key", "dst_key"):
        edges = edges.join(owned, F.col(end) == F.col("member"), "left").withColumn(end, F.coalesce("owner_key", end)).drop("member", "owner_key")
    links = edges.where("src_key <> dst_key").groupBy("src_key", "dst_key").agg(F.count(F.lit(1)).alias("n_links"))
    return sizes.join(texts, "node_key"), links


def hub_report(nodes: DataFrame) -> DataFrame:
    """In-degree by relation: nodes, largest, mean, median."""
    return nodes.groupBy("rel").agg(F.count(F.lit(1)).alias("n_nodes"), F.max("indeg").alias("max_indeg"), F.round(F.avg("indeg"), 6).alias("avg_indeg"), F.percentile("indeg", 0.5).alias("median_indeg"))


def to_adjacency(edges: DataFrame) -> DataFrame:
    """(node_id, targets, weights, priorities): lists in order of target."""
    packed = edges.groupBy(F.col("src").alias("node_id")).agg(F.array_sort(F.collect_list(F.struct("dst", "weight", "priority"))).alias("l"))
    return packed.select("node_id", F.col("l.dst").alias("targets"), F.col("l.weight").cast("array<float>").alias("weights"), F.col("l.priority").cast("array<float>").alias("priorities"))


def offsets(lists: DataFrame, length: str, order: str, buckets: int = 64) -> DataFrame:
    """``offset``: running sum of lengths before a row, in order. Bucket totals are summed first, so no window spans all rows."""
    edges = lists.select(F.percentile_approx(order, [k / buckets for k in range(1, buckets)], 10_000)).first()[0] or []
    bucket = sum((F.when(F.col(order) > e, 1).otherwise(0) for e in sorted(set(edges))), F.lit(0))
    rows = lists.withColumn("_b", bucket)
    totals = rows.groupBy("_b").agg(F.sum(length).alias("s"))  # ``buckets`` rows
    before = totals.withColumn("base", F.coalesce(F.sum("s").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("s")
    own = F.coalesce(F.sum(length).over(Window.partitionBy("_b").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return rows.withColumn("_o", own).join(F.broadcast(before), "_b").withColumn("offset", (F.col("base") + F.col("_o")).cast("long")).drop("_b", "_o", "base")


def degrees_from_offsets(lists: DataFrame, mode: str, indeg: DataFrame | None = None) -> DataFrame:
    """(node_id, degree): half the list length where every edge has its reverse; list length less in-degree in the directed form."""
    if mode == "symmetric":
        return lists.select("node_id", (F.size("targets") / 2).cast("long").alias("degree"))
    return lists.join(indeg, "node_id", "left").select("node_id", (F.size("targets") - F.coalesce("indeg", F.lit(0))).cast("long").alias("degree"))
