"""Document fingerprints by order MinHash, in DataFrame functions only.

The k-mers of a text are runs of ``k`` words. A k-mer that occurs again gets the number of its occurrence, so repeats are
different elements. The elements are dealt to ``m`` sketches by their hash; each sketch keeps its ``l`` minimal elements,
puts them back into text order and hashes the tuple. Two texts agree in a sketch only if they share its minimal elements
in the same order, so the share of equal sketches falls with the edit distance, not only with the sets' difference.

All steps work on arrays inside one row: sorting, running maxima in log2 passes, and filters. Nothing is shuffled for a
fingerprint. The neighbour of a document in the order of ids is found with one shuffle by id ranges; the first row of a
range is also sent to the range before, so no global window is needed.

Results for odd input: a null or empty text has the empty fingerprint, and two empty fingerprints are alike (1.0), an
empty and another are not (0.0); with fewer than k words the whole sequence is one k-mer; rows without doc_id come last in
the order, rows with equal ids are ordered by a hash of the text; a single row is its own neighbour; extra columns are
ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_BREAK, let, partitions

K, SKETCH_BITS, L = 3, 6, 2
#: Low bits of a packed element that hold its place in the text.
PLACE_BITS = 24


def _powers(n: Column) -> Column:
    """1, 2, 4, ... below n."""
    rounds = F.when(n > 1, F.ceil(F.log2(n)).cast("int")).otherwise(0)
    return F.transform(F.when(rounds > 0, F.sequence(F.lit(0), rounds - 1)).otherwise(F.array().cast("array<int>")), lambda r: F.pow(F.lit(2.0), r).cast("int"))


def _running_max(values: Column) -> Column:
    return F.aggregate(_powers(F.size(values)), values, lambda acc, j: F.transform(acc, lambda x, i: F.when(i >= j, F.greatest(x, F.get(acc, i - j))).otherwise(x)))


def _pack(h: Column, place: Column) -> Column:
    """The high bits of a hash above a place; places beyond the field share its last value."""
    return F.shiftleft(F.shiftright(h, PLACE_BITS), PLACE_BITS).bitwiseOR(F.least(place, F.lit(2**PLACE_BITS - 1)).cast("long"))


def _elements(kmers: Column) -> Column:
    """Packed elements of an array of k-mer hashes, with occurrences numbered."""

    def numbered(sorted_kmers):
        first = F.transform(sorted_kmers, lambda x, i: F.when((i > 0) & (F.get(sorted_kmers, i - 1)["h"] == x["h"]), 0).otherwise(i))
        return let(_running_max(first), lambda f: F.transform(sorted_kmers, lambda x, i: _pack(F.xxhash64(x["h"], i - F.get(f, i)), x["i"])))

    plain = F.transform(kmers, lambda x, i: _pack(F.xxhash64(x, F.lit(0)), i))
    repeated = let(F.array_sort(F.transform(kmers, lambda x, i: F.struct(x.alias("h"), i.alias("i")))), numbered)
    return F.when(F.size(F.array_distinct(kmers)) == F.size(kmers), plain).otherwise(repeated)


def sketches(text: Column, k: int = K, bits: int = SKETCH_BITS, l: int = L) -> Column:  # noqa: E741
    """array<string> of ``sketch:hash`` for the sketches that have an element, in the order of sketches."""

    def of_words(w):
        n = F.size(w)
        runs = F.transform(F.sequence(F.lit(0), n - k), lambda i: F.xxhash64(*[F.get(w, i + j) for j in range(k)]))
        return F.when(n >= k, runs).otherwise(F.array(F.xxhash64(w)))

    bucket = lambda x: F.shiftright(x, 64 - bits)
    place = lambda x: x.bitwiseAND(F.lit(2**PLACE_BITS - 1))

    def minimal(s):
        return F.filter(s, lambda x, i: (i < l) | (bucket(F.get(s, i - l)) != bucket(x)))

    def tuples(s):
        firsts = F.filter(F.transform(s, lambda x, i: F.when((i == 0) | (bucket(F.get(s, i - 1)) != bucket(x)), i)), lambda i: i.isNotNull())

        def one(i):
            own = F.filter(F.slice(s, i + 1, l), lambda y: bucket(y) == bucket(F.get(s, i)))
            ordered = F.transform(F.array_sort(F.transform(own, lambda y: F.struct(place(y).alias("p"), F.shiftright(y, PLACE_BITS).alias("h")))), lambda y: y["h"])
            return F.concat_ws(":", (bucket(F.get(s, i)) + 2 ** (bits - 1)).cast("string"), F.lower(F.hex(F.xxhash64(ordered))))

        return F.transform(firsts, one)

    words = F.split(F.btrim(text, F.lit(" \t\n\x0b\x0c\r")), WORD_BREAK)
    chosen = let(let(let(words, of_words), lambda m: F.array_sort(_elements(m))), minimal)
    bare = F.length(F.btrim(F.coalesce(text, F.lit("")), F.lit(" \t\n\x0b\x0c\r"))) == 0
    return F.when(bare, F.array().cast("array<string>")).otherwise(let(chosen, tuples))


def likeness(a: Column, b: Column) -> Column:
    """Share of equal sketches among those that either text has."""
    sketch = lambda x: F.transform(x, lambda s: F.substring_index(s, ":", 1))
    either = F.size(F.array_union(sketch(a), sketch(b)))
    return F.when(either == 0, F.lit(1.0)).otherwise(F.size(F.array_intersect(a, b)) / F.greatest(either, F.lit(1)))


def with_next(docs: DataFrame, columns: list[str], key: str = "doc_id", parts: int | None = None) -> DataFrame:
    """Rows with ``next_<c>``: the column's value in the next row by key, cyclically."""
    parts = parts or partitions(docs.sparkSession)
    order = F.coalesce(F.col(key).cast("long"), F.lit(2**63 - 1))
    tie = F.xxhash64("text") if "text" in docs.columns else F.xxhash64(*docs.columns)
    rows = docs.withColumn("_o", order)
    shares = [k / parts for k in range(parts)]
    found = rows.agg(F.min("_o").alias("m"), F.percentile_approx("_o", shares, 10_000).alias("p")).first()
    if found["m"] is None:
        return docs.select("*", *[F.lit(None).cast(docs.schema[c].dataType).alias(f"next_{c}") for c in columns])
    edges = sorted({found["m"], *found["p"]})  # ``parts`` values at most
    known = F.array(*[F.lit(e) for e in edges])
    bucket = sum((F.when(F.col("_o") >= e, 1).otherwise(0) for e in edges[1:]), F.lit(0)).cast("int")
    rows = rows.withColumn("_b", bucket)
    own = F.struct(F.col("_b").alias("b"), F.lit(0).alias("tail"))
    before = F.struct(F.pmod(F.col("_b") - 1, F.lit(len(edges))).cast("int").alias("b"), F.lit(1).alias("tail"))
    rows = rows.withColumn("_c", F.explode(F.when(F.array_contains(known, F.col("_o")), F.array(own, before)).otherwise(F.array(own))))
    window = Window.partitionBy("_c.b").orderBy("_c.tail", "_o", tie)
    led = rows.select("*", *[F.lead(c).over(window).alias(f"next_{c}") for c in columns])
    return led.where("_c.tail = 0").drop("_o", "_b", "_c")


def compare(docs: DataFrame) -> DataFrame:
    """The contract's columns: each text, its edited form, and how alike their fingerprints are."""
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("f", sketches(F.col("text")))
    rows = with_next(rows, ["text", "f"])
    half = F.floor(F.length("text") / 2).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), F.length("text") - half), F.substring(F.col("next_text"), F.lit(1), half))
    rows = rows.select("doc_id", F.length("text").cast("long").alias("n_chars"), edited.alias("edited"), "f", "next_f")
    rows = rows.withColumn("g", sketches(F.col("edited")))
    return rows.select(
        "doc_id",
        "n_chars",
        F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        F.array_join("f", ",").alias("fingerprint"),
        F.array_join("g", ",").alias("edited_fingerprint"),
        likeness(F.col("f"), F.col("g")).alias("near_edited"),
        likeness(F.col("f"), F.col("next_f")).alias("near_next"),
    )
