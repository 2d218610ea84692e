"""Benchmark decontamination by spaced seeds, in DataFrame functions only.

Texts become lower-cased runs of letters and digits. A mask names the token positions of a window that count; the others
are ignored, so a substituted token spoils only the windows where it falls on a counted position. Windows of the test
items and of the documents are hashed under every mask, equal hashes give a diagonal (document position minus item
position), and on that diagonal the aligned tokens are compared: a pair is contaminated when some stretch of
``stretch`` item tokens (or the whole item, where it is shorter) agrees in ``agree`` of its positions.

Scale: with up to ``inline_seeds`` item seeds (checked by counting), the seeds are part of the plan and each document keeps
only its hit positions. Beyond that the document seeds are joined with the item seeds by hash. Either way only documents
with enough hits on a diagonal are fetched again, by broadcast keys up to ``BROADCAST_DOCS`` of them; the rows are the same.

No accepted pair is without a seed: the agreeing tokens of an accepted stretch lie in one run more than it has
substitutions, so some run holds three tokens and the first mask hits. Only in the lengths where three need not be adjacent
(4, 5 and 8 tokens by the default rule) the items are sought under the other masks too. A substitution spoils three windows
at most, which also gives the least number of hits on a diagonal; diagonals with fewer are not compared.

Results for odd input: null or empty texts and items match nothing; items of fewer than ``shortest`` tokens are never
reported; rows that are equal in id and text give one pair with an item; extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, let, prepare

#: Counted positions are 1. Every mask starts and ends with a counted position.
MASKS = ("111", "1101", "1011")
STRETCH, AGREE, SHORTEST = 16, 0.75, 4
INLINE_SEEDS = 200_000
#: Keys of documents with enough hits that are broadcast when they were counted; beyond it the documents are shuffled.
BROADCAST_DOCS = 1_000_000


def tokens(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda t: t != "")


def _windows(t: Column, masks: tuple[str, ...]) -> Column:
    """array<struct<seed, pos>> of all windows of a token array; t must be bound (a column or a lambda variable)."""
    parts = []
    for number, mask in enumerate(masks):
        at = [k for k, c in enumerate(mask) if c == "1"]
        last = F.size(t) - len(mask)
        places = F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))
        parts.append(F.transform(places, _seed(lambda i, at=at, number=number: F.xxhash64(F.lit(number), *[F.get(t, i + k) for k in at]))))
    return F.concat(*parts)


def _seed(hashed):
    """A lambda of one position that gives its hash and itself."""
    return lambda i: F.struct(hashed(i).alias("seed"), i.alias("pos"))



def rule(n: int, stretch: int = STRETCH, agree: float = AGREE) -> tuple[int, bool]:
    """Least hits of the first mask on an accepted diagonal of an item of n tokens, and whether it may have none."""
    width = min(n, stretch)
    least = math.ceil(width * agree)
    wrong = width - least
    return max(1, width - 2 - 3 * wrong), math.ceil(least / (wrong + 1)) < 3


def item_seeds(items: DataFrame, masks: tuple[str, ...] = MASKS, stretch: int = STRETCH, agree: float = AGREE, shortest: int = SHORTEST) -> tuple[DataFrame, tuple[str, ...]]:
    """(item_id, seed, ipos, itoks, need) and the masks in use; the masks after the first serve only lengths that need them."""
    toks = cut(items.select("item_id", tokens(F.col("text")).alias("itoks")).where(F.size("itoks") >= shortest))
    lengths = range(shortest, stretch + 1)
    width = F.least(F.size("itoks"), F.lit(stretch))
    more = width.isin([n for n in lengths if rule(n, stretch, agree)[1]] or [-1])
    need = F.create_map(*[F.lit(x) for n in lengths for x in (n, 1 if rule(n, stretch, agree)[1] else rule(n, stretch, agree)[0])])[width]
    first = toks.select("item_id", "itoks", need.alias("need"), F.explode(_windows(F.col("itoks"), masks[:1])).alias("w"))
    every = toks.where(more).select("item_id", "itoks", F.lit(1).alias("need"), F.explode(_windows(F.col("itoks"), masks)).alias("w"))
    seeds = first.unionByName(every).select("item_id", "itoks", "need", F.col("w.seed").alias("seed"), F.col("w.pos").alias("ipos"))
    return cut(seeds.distinct()), masks if toks.where(more).limit(1).count() else masks[:1]


def _best(doc: Column, item: Column, diagonal: Column, stretch: int, agree: float) -> Column:
    """Most agreeing positions among ``stretch`` (or all) adjacent item positions on a diagonal, 0 where the whole item has too few."""
    n = F.size(item)
    same = F.transform(item, lambda x, i: F.when((i + diagonal >= 0) & (F.get(doc, F.greatest(i + diagonal, F.lit(0))) == x), 1).otherwise(0))
    width = F.least(n, F.lit(stretch))

    def widest(s):
        enough = F.aggregate(s, F.lit(0), lambda a, b: a + b) >= F.ceil(width * agree)
        return F.when(enough, most(s)).otherwise(0)

    def most(s):
        return F.array_max(F.transform(F.sequence(F.lit(1), n - width + 1), lambda k: F.aggregate(F.slice(s, k, width), F.lit(0), lambda a, b: a + b)))

    return let(same, widest)


def overlaps(docs: DataFrame, items: DataFrame, masks: tuple[str, ...] = MASKS, stretch: int = STRETCH, agree: float = AGREE, inline_seeds: int = INLINE_SEEDS) -> DataFrame:
    """(doc_id, item_id, diagonal, agreeing, stretch) of each contaminated pair, by its best diagonal; th is a hash of the row's text."""
    prepare(docs.sparkSession)
    seeds, masks = item_seeds(items, masks, stretch, agree)
    # id and text together name a row
    rows = docs.select(F.col("doc_id"), F.xxhash64("text").alias("th"), "text")
    values = [r[0] for r in seeds.select("seed").distinct().limit(inline_seeds + 1).collect()]
    if not values:
        return docs.sparkSession.createDataFrame([], "doc_id long, th long, item_id long, diagonal int, agreeing int, stretch int")
    toks = tokens(F.col("text"))
    if len(values) <= inline_seeds:
        hits = F.expr(f"filter(w, x -> x.seed in ({','.join(map(str, values))}))")  # parsed as SQL, which is fast for a long list
        found = rows.withColumn("w", let(toks, lambda t: _windows(t, masks))).withColumn("hits", hits).where(F.size("hits") > 0)
        pairs = cut(found.select("doc_id", "th", "hits")).select("doc_id", "th", F.explode("hits").alias("h")).select("doc_id", "th", "h.seed", "h.pos")
    else:
        spread = rows.select("doc_id", "th", F.explode(let(toks, lambda t: _windows(t, masks))).alias("h"))
        pairs = cut(spread.select("doc_id", "th", "h.seed", "h.pos").join(seeds.select("seed").distinct(), "seed", "left_semi"))
    lines = pairs.join(seeds.drop("itoks"), "seed").groupBy("doc_id", "th", "item_id", (F.col("pos") - F.col("ipos")).alias("diagonal")).agg(F.count_distinct("pos").alias("hits"), F.min("need").alias("need"))
    lines = cut(lines.where("hits >= need").drop("hits", "need"))
    where = lines.select("doc_id", "th").distinct()
    where = F.broadcast(where) if where.limit(BROADCAST_DOCS + 1).count() <= BROADCAST_DOCS else where
    found = rows.join(where, (rows.th == where.th) & rows.doc_id.eqNullSafe(where.doc_id), "left_semi").select("doc_id", "th", toks.alias("toks"))
    found = found.dropDuplicates(["doc_id", "th"]).select(F.col("doc_id").alias("d"), F.col("th").alias("h"), "toks")
    texts = seeds.select(F.col("item_id").alias("iid"), "itoks").distinct()
    aligned = lines.join(texts, lines.item_id.eqNullSafe(texts.iid)).join(found, (F.col("th") == F.col("h")) & F.col("doc_id").eqNullSafe(F.col("d")))
    size = F.least(F.size("itoks"), F.lit(stretch))
    scored = aligned.select("doc_id", "th", "item_id", "diagonal", _best(F.col("toks"), F.col("itoks"), F.col("diagonal"), stretch, agree).alias("agreeing"), size.alias("stretch"))
    scored = scored.where(F.col("agreeing") >= F.ceil(F.col("stretch") * agree))
    best = scored.groupBy("doc_id", "th", "item_id").agg(F.max(F.struct("agreeing", (-F.col("diagonal")).alias("back"), "stretch")).alias("m"))
    return best.select("doc_id", "th", "item_id", (-F.col("m.back")).alias("diagonal"), "m.agreeing", "m.stretch")


def clean(docs: DataFrame, items: DataFrame, **options) -> DataFrame:
    """The rows of ``docs`` that overlap with no item, all columns kept."""
    bad = overlaps(docs, items, **options).select(F.col("doc_id").alias("bad_id"), F.col("th").alias("bad_th")).distinct()
    return docs.join(bad, (F.xxhash64(docs["text"]) == bad.bad_th) & docs["doc_id"].eqNullSafe(bad.bad_id), "left_anti")
