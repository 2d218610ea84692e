"""Removal of byte strings that repeat anywhere in the corpus, by column-wise suffix sorting of text segments.

Every window of ``width`` bytes has an anchor, the leftmost of its least-hashed ``GRAM``-byte strings. A run of windows
with one anchor is a segment. Equal windows have equal anchors at equal places, so repeats can only be among segments of
one anchor, and a segment whose anchor occurs once needs no more work. Equal segments are repeats as a whole. The
different segments of an anchor form a collection, aligned at the anchor, in which suffixes are sorted column by column:
each round goes one column to the left and inserts one symbol of every segment; a stable sort by that symbol turns the
order of the last round's suffixes into the next (the collection's transform of that column), and the common prefixes of
neighbours are updated from the range minima of the last round's. As all occurrences of a repeat are aligned, only
suffixes of one round have to be ordered among themselves, so a round costs the number of segments, not of all suffixes
so far. Neighbours that share ``width`` bytes are repeats. Rounds stream over collections in order of their anchor; a task
holds ``TASK_BYTES`` of them.

Scale: what is counted over the corpus is one row for each segment (about 90 bytes of text), combined before the
shuffle; texts travel once, and only the segments of shared anchors follow them. An anchor with more than ``hot``
different segments (say, the edge of a passage that very many documents hold) is not gathered: its windows are counted
one by one by a 128-bit hash instead.

Results for odd input: a null or empty text has no bytes and the hash of the empty string; a text below ``width`` bytes
keeps all; rows that repeat a document repeat each other's windows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, mix64, partitions, prepare

WIDTH, GRAM, HOT = 200, 32, 20_000
TASK_BYTES = 8_000_000
_LETTER = np.random.default_rng(5).integers(0, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def grams(data: np.ndarray, size: int = GRAM) -> np.ndarray:
    """A 64-bit hash of each string of ``size`` bytes (a power of two), by doubling."""
    h, n = _LETTER[data], 1
    with np.errstate(over="ignore"):
        while n < size:
            h = h[:-n] * np.uint64(0x9E3779B97F4A7C15 + 2 * n) + h[n:]
            h ^= h >> np.uint64(29)
            n *= 2
    return mix64(h)


def segments(data: np.ndarray, width: int = WIDTH, size: int = GRAM) -> list[tuple[int, int, int, int]]:
    """(anchor hash, anchor place, first window, last window) of each segment."""
    if len(data) < width:
        return []
    h, reach = grams(data, size), width - size + 1
    n = len(h) - reach + 1
    tiles = np.concatenate([h, np.full(-len(h) % reach, 2**64 - 1, np.uint64)]).reshape(-1, reach)
    ahead = np.minimum.accumulate(tiles[:, ::-1], axis=1)[:, ::-1].ravel()[:n]
    behind = np.minimum.accumulate(tiles, axis=1).ravel()[reach - 1 : reach - 1 + n]
    least = np.minimum(ahead, behind)
    starts = np.flatnonzero(np.concatenate(([True], least[1:] != least[:-1])))
    ends = np.concatenate((starts[1:], [n])) - 1
    out = []
    for value, s, e in zip(least[starts], starts.tolist(), ends.tolist(), strict=True):
        at = np.flatnonzero(h[s : e + reach] == value)
        if len(at) == 1:
            out.append((int(value), s + int(at[0]), s, e))
            continue
        for place in (at + s).tolist():  # the same string again within reach: a new segment from the byte after it
            if s > e:
                break
            if place >= s:
                out.append((int(value), place, s, min(e, place)))
                s = place + 1
    return out


def _signed(x: int) -> int:
    return x - 2**64 if x >= 2**63 else x


def sort_columns(texts: list[bytes], anchors: list[int], groups: np.ndarray, width: int = WIDTH) -> np.ndarray:
    """Whether the window at each place of each segment occurs in another segment of its group.

    texts: segments; anchors: the place of the anchor in each; groups: non-decreasing group numbers. The result has one row
    a segment and a column for each window start, counted from the segment's start.
    """
    n = len(texts)
    lengths, anchors = np.array([len(t) for t in texts]), np.array(anchors)
    lead = int(anchors.max())
    columns = int((lengths - anchors).max()) + lead
    # symbols by column; outside its text, a segment has a symbol of its own, which equals no other
    grid = np.broadcast_to((256 + np.arange(n, dtype=np.int64))[:, None], (n, columns)).astype(np.int32)
    flat = np.frombuffer(b"".join(texts), np.uint8)
    row = np.repeat(np.arange(n), lengths)
    column = np.arange(len(flat)) - np.repeat(np.cumsum(lengths) - lengths, lengths) + np.repeat(lead - anchors, lengths)
    grid[row, column] = flat
    grid = np.ascontiguousarray(grid.T)
    order = np.arange(n)
    common = np.zeros(n + 1, np.int16)  # with the neighbour before, in this order
    base = groups.astype(np.int64) << 32
    found = np.zeros((n, columns), bool)
    for q in range(columns - 1, -1, -1):
        symbol = grid[q]
        key = base[order] + symbol[order]
        turn = np.argsort(key, kind="stable")
        key = key[turn]
        same = np.concatenate(([False], key[1:] == key[:-1]))
        fresh = np.zeros(n + 1, np.int16)
        k = np.flatnonzero(same)
        if len(k):
            low, high = turn[k - 1] + 1, turn[k]  # what lies between two neighbours in the last order
            pairs = np.stack([low, high + 1], axis=1).ravel()
            fresh[k] = np.minimum.reduceat(common, pairs)[::2] + 1
        order, common = order[turn], fresh
        hit = common >= width
        if hit.any():
            found[order[hit[:-1] | hit[1:]], q] = True
    shift = lead - anchors
    out = np.zeros((n, max(1, int(lengths.max()) - width + 1)), bool)
    for k in np.flatnonzero(found.any(axis=1)):
        own = found[k, shift[k] : shift[k] + out.shape[1]]
        out[k, : len(own)] = own
    return out


def _rows(docs: DataFrame, width: int) -> DataFrame:
    """One row for each different segment of a document: doc_id, th, a (anchor), d (segment), s (its starts), lead, size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 512):
                part = batch.slice(start, 512)
                rows: list[list] = [[] for _ in range(7)]
                for doc, th, text in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    data = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
                    view, own = memoryview(data), {}
                    for value, place, s, e in segments(data, width):
                        d = xxhash.xxh3_64_intdigest(view[s : e + width])
                        if (known := own.get((value, d))) is None:
                            own[value, d] = ([s], place - s, e + width - s)
                        else:
                            known[0].append(s)
                    for (value, d), (at, lead, size) in own.items():
                        for column, x in zip(rows, (doc, th, _signed(value), _signed(d), at, lead, size), strict=True):
                            column.append(x)
                types = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.int32(), pa.int32()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, types, strict=True)], ["doc_id", "th", "a", "d", "s", "lead", "size"])

    return docs.where(F.octet_length("text") >= width).mapInArrow(run, "doc_id long, th long, a long, d long, s array<int>, lead int, size int")


def _cut_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(a, d, nd, c, lead, doc_id, th, s, bytes) from texts and the lists of their wanted segments."""
    for batch in batches:
        for start in range(0, batch.num_rows, 128):
            part = batch.slice(start, 128)
            rows: list[list] = [[] for _ in range(9)]
            for doc, th, text, wanted in zip(*(c.to_pylist() for c in part.columns), strict=True):
                data = text.encode("utf-8", "surrogatepass")
                for w in wanted:
                    for column, x in zip(rows, (w["a"], w["d"], w["nd"], w["c"], w["lead"], doc, th, w["s"], data[w["s"] : w["s"] + w["size"]]), strict=True):
                        column.append(x)
            types = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, types, strict=True)], ["a", "d", "nd", "c", "lead", "doc_id", "th", "s", "bytes"])


def _sorter(width: int, task_bytes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by anchor; whole groups are gathered up to ``task_bytes``."""
        held: dict[tuple, tuple] = {}
        size, last = 0, None

        def close() -> pa.RecordBatch | None:
            rows = list(held.values())
            held.clear()
            if len(rows) < 2:
                return None
            groups = np.concatenate(([0], np.cumsum([x[0] != y[0] for x, y in zip(rows[1:], rows, strict=False)])))
            found = sort_columns([r[6] for r in rows], [r[2] for r in rows], groups, width)
            out: list[list] = [[], [], [], []]
            for k in np.flatnonzero(found.any(axis=1)):
                _, c, _, doc, th, s, _ = rows[k]
                if c > 1:
                    continue  # repeats as a whole
                edge = np.diff(np.concatenate(([0], found[k].astype(np.int8), [0])))
                for first, end in zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True):
                    for column, x in zip(out, (doc, th, s + first, s + end - 1 + width), strict=True):
                        column.append(x)
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, [pa.int64(), pa.int64(), pa.int32(), pa.int32()], strict=True)], ["doc_id", "th", "x", "y"])

        for batch in batches:
            for a, d, _, c, lead, doc, th, s, data in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                if size > task_bytes and a != last:
                    if (got := close()) is not None:
                        yield got
                    size = 0
                if (a, d) not in held:
                    held[a, d] = (a, c, lead, doc, th, s, data)
                    size += len(data)
                last = a
        if (got := close()) is not None:
            yield got

    return run


def _windows(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """(w1, w2, c, doc_id, th, x) for each window of hot anchors."""
        for batch in batches:
            for _, _, _, c, _, doc, th, s, data in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                view = memoryview(data)
                got = [xxhash.xxh3_128_intdigest(view[k : k + width]) for k in range(len(data) - width + 1)]
                n = len(got)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([_signed(g >> 64) for g in got], pa.int64()), pa.array([_signed(g & (2**64 - 1)) for g in got], pa.int64()), pa.array([c] * n, pa.int64()), pa.array([doc] * n, pa.int64()), pa.array([th] * n, pa.int64()), pa.array(range(s, s + n), pa.int32())],
                    ["w1", "w2", "c", "doc_id", "th", "x"],
                )

    return run


def spans(docs: DataFrame, width: int = WIDTH, hot: int = HOT, task_bytes: int = TASK_BYTES) -> DataFrame:
    """(doc_id, th, x, y): byte ranges that are covered by repeated strings; ranges of one text may overlap."""
    spark = prepare(docs.sparkSession)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), "text")
    rows = _rows(texts, width)
    # segments of an anchor that occurs more than once; only these are counted apart
    shared = rows.groupBy("a").agg(F.sum(F.size("s")).alias("all")).where("`all` > 1").select("a")
    near = cut(rows.join(shared, "a"))
    counted = near.groupBy("a", "d").agg(F.sum(F.size("s")).alias("c"))
    kinds = counted.groupBy("a").agg(F.count(F.lit(1)).alias("nd"))
    picked = cut(near.join(counted.join(kinds, "a"), ["a", "d"]))
    whole = picked.where("c > 1").select("doc_id", "th", F.explode("s").alias("x"), "size").select("doc_id", "th", "x", (F.col("x") + F.col("size")).alias("y"))

    wanted = picked.where("nd > 1").dropDuplicates(["a", "d"]).select("doc_id", "th", F.struct("a", "d", "nd", "c", "lead", F.element_at("s", 1).alias("s"), "size").alias("w"))
    lists = wanted.groupBy("doc_id", "th").agg(F.collect_list("w").alias("w")).select(F.col("doc_id").alias("id"), F.col("th").alias("h"), "w")
    match = (F.col("th") == F.col("h")) & F.col("doc_id").eqNullSafe(F.col("id"))
    pieces = texts.join(lists, match).select("doc_id", "th", "text", "w").mapInArrow(_cut_out, "a long, d long, nd long, c long, lead int, doc_id long, th long, s int, bytes binary")
    gathered = pieces.where(F.col("nd") <= hot).repartition(partitions(spark), "a").sortWithinPartitions("a", "d", "doc_id", "th")
    sorted_ = gathered.mapInArrow(_sorter(width, task_bytes), "doc_id long, th long, x int, y int")
    result = whole.union(sorted_)
    if picked.where(F.col("nd") > hot).isEmpty():
        return result
    each = pieces.where(F.col("nd") > hot).mapInArrow(_windows(width), "w1 long, w2 long, c long, doc_id long, th long, x int")
    often = each.groupBy("w1", "w2").agg(F.sum("c").alias("n")).where("n > 1").drop("n")
    return result.union(each.where("c = 1").join(often, ["w1", "w2"], "left_semi").select("doc_id", "th", "x", (F.col("x") + width).alias("y")))


def remove(docs: DataFrame, width: int = WIDTH, hot: int = HOT, task_bytes: int = TASK_BYTES) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept binary) for each document."""
    found = spans(docs, width, hot, task_bytes).groupBy(F.col("doc_id").alias("id"), F.col("th").alias("h")).agg(F.collect_list(F.struct("x", "y")).alias("w"))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), "text")
    joined = texts.join(found, (F.col("th") == F.col("h")) & F.col("doc_id").eqNullSafe(F.col("id")), "left").select("doc_id", "text", F.col("w.x").alias("x"), F.col("w.y").alias("y"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 256):
                part = batch.slice(start, 256)
                out: list[list] = [[] for _ in range(5)]
                for doc, text, x, y in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    data = (text or "").encode("utf-8", "surrogatepass")
                    kept, removed, n, at = [], 0, 0, 0
                    end = -1
                    for s, e in sorted(zip(x or (), y or (), strict=True)):
                        if s > end:  # ranges that touch are one run
                            n += 1
                            kept.append(data[at:s])
                            removed += e - s
                        elif e > end:
                            removed += e - end
                        end = max(end, e)
                        at = end
                    kept.append(data[at:])
                    for column, v in zip(out, (doc, len(data), removed, n, b"".join(kept)), strict=True):
                        column.append(v)
                types = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types, strict=True)], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept"])

    return joined.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary")


def digest(removed: DataFrame) -> DataFrame:
    """The contract's columns."""
    return removed.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def brute(texts: list[bytes], width: int = WIDTH) -> list[tuple[int, int, str]]:
    """(removed bytes, spans, hash of the rest) of each text, by a table of all windows; for tests."""
    seen: dict[bytes, int] = {}
    for t in texts:
        for k in range(len(t) - width + 1):
            seen[t[k : k + width]] = seen.get(t[k : k + width], 0) + 1
    out = []
    for t in texts:
        gone = bytearray(len(t))
        for k in range(len(t) - width + 1):
            if seen[t[k : k + width]] > 1:
                gone[k : k + width] = b"\1" * width
        n = sum(1 for k in range(len(t)) if gone[k] and not (k and gone[k - 1]))
        out.append((sum(gone), n, hashlib.sha256(bytes(c for c, g in zip(t, gone, strict=True) if not g)).hexdigest()))
    return out
