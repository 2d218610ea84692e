"""Sharding by minimax contiguous partition, in DataFrame functions only.

Equal texts form atomic groups, ordered by a 128-bit hash of the text. The smallest capacity for which a greedy walk over
the ordered groups needs no more than the wanted number of shards is found by binary search; the shards end where that
walk cuts. As the order is a hash order, a document finds its shard by comparing its hash with the cuts: nothing is
joined.

Scale: the driver holds size totals of hash bins, never groups. Bins that a cut may fall into are split into finer ones by
one aggregation a round, until the capacity that is feasible with whole bins equals the one that no walk can beat; that
is the exact optimum. Slots are numbered by fine buckets of (shard, hash, salt), whose counts are bounded by
``SLOT_BINS * SALTS`` rows, so a group of any size is spread over many tasks.

Results for odd input: a null text has size 1 and is grouped with the empty text; repeated rows get a slot each; an empty
table gives no rows; with fewer groups than shards some shards stay empty; extra columns are ignored by ``assign``.
"""

from __future__ import annotations

from bisect import bisect_right
from itertools import accumulate

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut

SHARDS = 8
#: Bits of the hash that the first bins leave open, and bits by which a round splits a bin.
OPEN_BITS, SPLIT_BITS = 52, 8
SLOT_BITS, SALTS = 54, 128


class Bins:
    """Ordered bins of group sizes: (start in hash order, open bits, total size, groups)."""

    def __init__(self, rows: list[tuple[int, int, int, int]]):
        self.rows = sorted(rows)
        self.ends = list(accumulate(r[2] for r in self.rows))
        self.total = self.ends[-1] if self.ends else 0

    def atomic(self, k: int) -> bool:
        return self.rows[k][3] <= 1 or self.rows[k][1] == 0

    def walk(self, capacity: int, shards: int, whole: bool) -> list[int] | None:
        """Size before each cut of a greedy walk, or None if the shards don't suffice.

        ``whole``: a bin is never divided. Otherwise a bin of several groups is divided wherever the capacity ends, which
        no division into groups can beat.
        """
        cuts, base = [], 0
        for _ in range(shards):
            if base + capacity >= self.total:
                return cuts
            k = bisect_right(self.ends, base + capacity)  # the first bin that does not fit
            start = self.ends[k - 1] if k else 0
            at = start if whole or self.atomic(k) else base + capacity
            if at <= base:
                return None
            cuts.append(at)
            base = at
        return None

    def least(self, shards: int, whole: bool) -> int:
        low, high = -(-self.total // shards) if self.total else 0, self.total
        while low < high:
            middle = (low + high) // 2
            low, high = (low, middle) if self.walk(middle, shards, whole) is not None else (middle + 1, high)
        return low

    def doubtful(self, low: int, high: int, shards: int) -> list[int]:
        """Bins of several groups that a cut may fall into, for a capacity from low to high."""
        found: set[int] = set()
        first, last = 0, 0
        for _ in range(shards):
            last = min(self.total, last + high)
            k, top = bisect_right(self.ends, first + low), bisect_right(self.ends, last)
            first = min(first + low, self.ends[k - 1] if k else 0) if k < len(self.rows) else self.total
            found |= {b for b in range(max(0, k - 1), min(top + 1, len(self.rows))) if not self.atomic(b)}
        return sorted(found)


def plan(docs: DataFrame, shards: int = SHARDS) -> tuple[int, list[int]]:
    """(capacity, hash values at which shards 1, 2, ... begin) for documents with ``text``."""
    sized = docs.select(F.xxhash64(F.coalesce("text", F.lit(""))).alias("h1"), F.xxhash64(F.lit(7), F.coalesce("text", F.lit(""))).alias("h2"), (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"))
    groups = cut(sized.groupBy("h1", "h2").agg(F.sum("size").alias("size")))

    def summed(open_bits: int, inside: tuple[int, list[int]] | None = None) -> list[tuple[int, int, int, int]]:
        rows = groups if inside is None else groups.where(F.shiftright("h1", inside[0]).isin(inside[1]))
        got = rows.groupBy(F.shiftright("h1", open_bits).alias("b")).agg(F.sum("size").alias("s"), F.count(F.lit(1)).alias("n")).collect()
        return [(r["b"] << open_bits, open_bits, r["s"], r["n"]) for r in got]

    bins = Bins(summed(OPEN_BITS))
    while True:
        low, high = bins.least(shards, whole=False), bins.least(shards, whole=True)
        doubtful = bins.doubtful(low, high, shards) if low < high else []
        if not doubtful:
            break
        rows = [r for k, r in enumerate(bins.rows) if k not in set(doubtful)]
        for width in sorted({bins.rows[k][1] for k in doubtful}):
            starts = [bins.rows[k][0] >> width for k in doubtful if bins.rows[k][1] == width]
            for at in range(0, len(starts), 512):
                rows += summed(max(0, width - SPLIT_BITS), (width, starts[at : at + 512]))
        bins = Bins(rows)
    cuts = bins.walk(high, shards, whole=True) or []
    return high, [bins.rows[bins.ends.index(c) + 1][0] for c in cuts]


def assign(docs: DataFrame, shards: int = SHARDS) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for each document."""
    _, starts = plan(docs, shards)
    text = F.coalesce("text", F.lit(""))
    rows = docs.select("doc_id", (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("h1"), F.xxhash64(F.lit(7), text).alias("h2"))
    shard = sum((F.when(F.col("h1") >= s, 1).otherwise(0) for s in starts), F.lit(0))
    rows = rows.withColumn("shard", shard.cast("int")).withColumn("bin", F.shiftright("h1", SLOT_BITS)).withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int"))
    place = ["shard", "bin", "salt"]
    counts = rows.groupBy(*place).agg(F.count(F.lit(1)).alias("n"))  # at most 2^(64 - SLOT_BITS) * SALTS rows and a few at cuts
    before = counts.withColumn("before", F.sum("n").over(Window.partitionBy("shard").orderBy("bin", "salt").rowsBetween(Window.unboundedPreceding, -1)))
    before = before.select(*[F.col(c).alias(f"_{c}") for c in place], F.coalesce("before", F.lit(0)).alias("before"))
    within = F.row_number().over(Window.partitionBy(*place).orderBy("h1", "h2", "doc_id")) - 1
    numbered = rows.withColumn("within", within).join(F.broadcast(before), (F.col("shard") == F.col("_shard")) & (F.col("bin") == F.col("_bin")) & (F.col("salt") == F.col("_salt")))
    return numbered.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("before") + F.col("within")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def write(docs: DataFrame, path: str, shards: int = SHARDS) -> None:
    """All columns of the documents as Parquet, one folder a shard."""
    _, starts = plan(docs, shards)
    h1 = F.xxhash64(F.coalesce("text", F.lit("")))
    shard = sum((F.when(h1 >= s, 1).otherwise(0) for s in starts), F.lit(0))
    docs.withColumn("shard", shard.cast("int")).write.partitionBy("shard").parquet(path)
