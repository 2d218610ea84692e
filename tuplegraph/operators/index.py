"""The keyword index: postings by tuple, symbols by column, and what queries match."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import tokenize
from ..sources.catalog import RELATIONS, Relation, table
from .graph import node_id, node_key


def build_postings(spark: SparkSession, sf_dir: str, relations: tuple[Relation, ...] = tuple(RELATIONS.values())) -> DataFrame:
    """(term, node_id, node_key, rel, field, tf): one row for each term of each field of each tuple."""
    out = None
    for r in relations:
        rows = table(spark, sf_dir, r.name)
        key = F.col(r.key[0])
        fields = F.explode(F.array(*[F.struct(F.lit(c).alias("field"), F.col(c).alias("value")) for c in r.text]))
        terms = rows.select(node_id(r, key).alias("node_id"), node_key(r.name, key).alias("node_key"), F.lit(r.name).alias("rel"), fields.alias("f"))
        part = terms.select("node_id", "node_key", "rel", "f.field", F.explode(tokenize(F.col("f.value"))).alias("term"))
        out = part if out is None else out.unionByName(part)
    return out.groupBy("term", "node_id", "node_key", "rel", "field").agg(F.count(F.lit(1)).alias("tf"))


def build_symbols(postings: DataFrame) -> DataFrame:
    """(term, rel, field, n_rows): in which columns a term occurs."""
    return postings.groupBy("term", "rel", "field").agg(F.count_distinct("node_id").alias("n_rows"))


def symbol_table(postings: DataFrame, indexed: tuple[str, ...]) -> DataFrame:
    """Column granularity for indexed fields, row granularity for the others: (term, rel, field, node_key or null, n_rows)."""
    column = build_symbols(postings.where(F.col("field").isin(list(indexed)))).withColumn("node_key", F.lit(None).cast("string"))
    row = postings.where(~F.col("field").isin(list(indexed))).select("term", "rel", "field", F.lit(1).cast("long").alias("n_rows"), "node_key")
    return column.unionByName(row)


def compact_symbols(postings: DataFrame, chunk: int = 1000) -> DataFrame:
    """(signature, n_terms, n_rows): terms with equal row sets share one list.

    The signature of a set is an order-free sum of its members' hashes with its size, so no list is gathered.
    """
    half = lambda seed: F.sum((F.xxhash64(F.lit(seed), "node_id") % 1_000_003_579).cast("decimal(20,0)"))
    lists = postings.select("term", "node_id").distinct().groupBy("term").agg(F.count(F.lit(1)).alias("n_rows"), half(1).alias("s1"), half(2).alias("s2"))
    return lists.groupBy("n_rows", "s1", "s2").agg(F.count(F.lit(1)).alias("n_terms"), F.min("term").alias("first_term")).select("first_term", "n_terms", "n_rows")


def frequent_terms(postings: DataFrame, least: int) -> DataFrame:
    """(term, df) with more than ``least`` tuples."""
    return postings.groupBy("term").agg(F.count_distinct("node_id").alias("df")).where(F.col("df") > least)


def query_frame(spark: SparkSession, queries: dict[str, tuple[str, ...]]) -> DataFrame:
    rows = [(q, t) for q, terms in sorted(queries.items()) for t in dict.fromkeys(terms)]
    return spark.createDataFrame(rows, "query_id string, term string")


def column_words(postings: DataFrame) -> DataFrame:
    """(term, rel): the words of the names of each relation's text columns, without a leading prefix letter."""
    words = F.split(F.regexp_replace("field", "^[a-z]{1,2}_", ""), "_")
    return postings.select("rel", "field").distinct().select(F.explode(words).alias("term"), "rel").distinct()


def match(postings: DataFrame, queries: DataFrame, metadata: bool = False, nodes: DataFrame | None = None) -> DataFrame:
    """(query_id, term, node_id, node_key): the node set of each keyword. A query's terms are few and broadcast.

    ``metadata``: a term that names a relation, or a word of a column's name, also selects all tuples of the relation.
    """
    hits = postings.join(F.broadcast(queries), "term").select("query_id", "term", "node_id", "node_key")
    if metadata:
        names = column_words(postings).unionByName(nodes.select(F.col("rel").alias("term"), "rel").distinct()).distinct().join(F.broadcast(queries), "term")
        hits = hits.unionByName(nodes.join(F.broadcast(names), "rel").select("query_id", "term", "node_id", "node_key"))
    return hits.distinct()


def origin_size(matches: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, term, origin): size of each keyword's node set, zero included."""
    sizes = matches.groupBy("query_id", "term").agg(F.count_distinct("node_id").alias("origin"))
    return queries.join(sizes, ["query_id", "term"], "left").select("query_id", "term", F.coalesce("origin", F.lit(0)).alias("origin"))


def classify(sizes: DataFrame, cut_at: int) -> DataFrame:
    """(query_id, klass): high and low by origin size, in ascending order of size."""
    kind = F.when(F.col("origin") > cut_at, "high").otherwise("low")
    return sizes.groupBy("query_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("origin", kind.alias("k")))), lambda x: x["k"]), "/").alias("klass"))


def complete(matches: DataFrame, queries: DataFrame) -> DataFrame:
    """Matches of queries of which every term has a node."""
    wanted = queries.groupBy("query_id").agg(F.count_distinct("term").alias("n"))
    found = matches.groupBy("query_id").agg(F.count_distinct("term").alias("n"))
    return matches.join(F.broadcast(wanted.join(found, ["query_id", "n"]).select("query_id")), "query_id", "left_semi")


def cluster_postings(postings: DataFrame, membership: DataFrame) -> DataFrame:
    """(term, cluster_id): in which clusters a term occurs."""
    return postings.join(membership, "node_id").select("term", "cluster_id").distinct()
