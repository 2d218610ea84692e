"""Join-tree search: relations that hold the keywords, trees of joins that connect them, and their rows."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from itertools import product

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import tokenize
from ..sources.catalog import LINK, LINK_REFERENCES, REFERENCES, RELATIONS, Reference, table
from .graph import node_key


@dataclass(frozen=True)
class JoinTree:
    relations: frozenset[str]
    references: frozenset[Reference]

    @property
    def joins(self) -> int:
        return len(self.references)


def enumerate_trees(keyword_relations: dict[str, set[str]], max_size: int = 4, references: tuple[Reference, ...] = REFERENCES + LINK_REFERENCES) -> list[tuple[JoinTree, dict[str, str]]]:
    """Trees of at most ``max_size`` relations, with the relation that each keyword is taken from.

    Trees grow by one reference at a time from the relations of the rarest keyword; a tree is kept when all its leaves hold
    a keyword. Fewer joins first; equal ones by name.
    """
    terms = sorted(keyword_relations, key=lambda t: (len(keyword_relations[t]), t))
    seen: set[JoinTree] = set()
    queue = [JoinTree(frozenset([r]), frozenset()) for r in sorted(set().union(*keyword_relations.values()))]
    for tree in queue:
        if tree in seen:
            continue
        seen.add(tree)
        if len(tree.relations) < max_size:
            for ref in references:
                if (ref.child in tree.relations) != (ref.parent in tree.relations):
                    queue.append(JoinTree(tree.relations | {ref.child, ref.parent}, tree.references | {ref}))
    found = []
    for tree in seen:
        degree = {r: sum(r in (x.child, x.parent) for x in tree.references) for r in tree.relations}
        leaves = {r for r, d in degree.items() if d <= 1}
        for choice in product(*[sorted(keyword_relations[t] & tree.relations) for t in terms]):
            if len(set(choice)) == len(terms) and leaves <= set(choice):
                found.append((tree, dict(zip(terms, choice, strict=True))))
    return sorted(found, key=lambda f: (f[0].joins, sorted(f[0].relations), sorted(f[1].items())))


def keyword_relations(symbols: DataFrame, terms: list[str]) -> dict[str, set[str]]:
    """Which relations hold each term; a term has as many rows here as there are relations."""
    rows = symbols.where(F.col("term").isin(terms)).select("term", "rel").distinct().collect()
    return {t: {r["rel"] for r in rows if r["term"] == t} for t in terms}


def holds(relation: str, term: str) -> Column:
    own = RELATIONS.get(relation, LINK)
    return reduce(lambda a, b: a | b, [F.array_contains(tokenize(F.col(c)), term) for c in own.text])


def rows_of(spark: SparkSession, sf_dir: str, tree: JoinTree, terms: dict[str, str], share: dict | None = None) -> DataFrame:
    """(n_joins, relations, keys): rows of a join tree that hold all its keywords, most selective relations first.

    ``share``: filtered relations that several trees use, by relation and terms, so they are planned once.
    """
    share = {} if share is None else share
    parts = {}
    for name in sorted(tree.relations):
        own = tuple(sorted(t for t, r in terms.items() if r == name))
        if (name, own) not in share:
            frame = table(spark, sf_dir, name)
            share[name, own] = reduce(lambda f, t, name=name: f.where(holds(name, t)), own, frame)
        parts[name] = share[name, own]
    order = sorted(tree.relations, key=lambda r: (r not in terms.values(), r))
    done, out, left = {order[0]}, parts[order[0]], set(tree.references)
    while left:
        ref = min((r for r in left if (r.child in done) != (r.parent in done)), key=lambda r: r.etype)
        new = ref.parent if ref.child in done else ref.child
        out = out.join(parts[new], F.col(ref.column) == F.col(RELATIONS[ref.parent].key[0]))
        done.add(new)
        left.discard(ref)
    keys = F.concat_ws(",", *[node_key(r, *[F.col(k) for k in RELATIONS.get(r, LINK).key]) for r in sorted(tree.relations)])
    return out.select(F.lit(tree.joins).cast("long").alias("n_joins"), F.lit("+".join(sorted(tree.relations))).alias("relations"), keys.alias("keys"))


def search(spark: SparkSession, sf_dir: str, symbols: DataFrame, terms: list[str], max_size: int = 4, share: bool = True) -> DataFrame:
    """Rows of all join trees for the terms; fewer joins rank first, equal ones by key."""
    found = enumerate_trees(keyword_relations(symbols, terms), max_size)
    held: dict = {}
    parts = [rows_of(spark, sf_dir, tree, choice, held if share else None) for tree, choice in found]
    empty = spark.createDataFrame([], "n_joins long, relations string, keys string")
    return reduce(lambda a, b: a.unionByName(b), parts, empty).distinct()


def rank(rows: DataFrame, k: int) -> DataFrame:
    return rows.orderBy("n_joins", "relations", "keys").limit(k)
