"""Near-duplicate detection with SetSketch registers.

A document's set is its distinct five-word shingles (64-bit hashes of A-Z-lower-cased words). Every shingle emits the
points of one Poisson process; a register holds the least time at which any shingle of the set hits it, on an exponential
scale. Registers are mergeable by maximum and locality-sensitive. Documents that agree on a band of registers are
candidates: the least set of a band's bucket is its hub, and the sets that meet at one hub form a star. Inside a star a
pair's similarity is first estimated from both sketches jointly, by likelihood, and pairs that are not excluded are
confirmed on the full sets.

Scale: exact copies collapse before anything else, and only texts of sets with a partner travel. Stars are compared one by
one, so chains of false candidates never join into one large group. A star above ``block_shingles`` is dealt into blocks
that each hold the hub: sets that a block links with the hub are settled, and only the others meet the rest, block by
block. So a star of near copies costs one pass, however large, and no task holds an unbounded star. Each task returns a
forest of links, never all pairs.

Results for odd input: a null or empty text has an empty set and is linked with nothing; below five words the whole
sequence is one shingle; rows that repeat a doc_id share its node when their sets are equal; a row without doc_id is
linked like any other but is never named, so a group of only such rows has a null ``component_id`` and its rows count as
kept. Extra columns are ignored by ``link``.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import components, cut, mix64, partitions, prepare

WIDTH = 5
SIMILAR = 75  # per cent
#: Registers, their scale and rate. At this scale equal registers are about as likely as in MinHash.
BANDS, ROWS = 40, 3
M, BASE, RATE, TOP = BANDS * ROWS, 1.001, 20.0, 2**16 - 1
#: How far above the expected last register the processes are followed; later times count as truncated (register 0).
SLACK = 14.0
#: Shingles of a star, or of a block of it, that one task holds.
BLOCK_SHINGLES = 800_000
BLOCK_SETS = 3_000
#: Ids of candidate texts that are broadcast when they were counted; beyond it texts and ids are shuffled.
BROADCAST_TEXTS = 1_000_000
#: A pair is excluded without its sets when the likelihood of SIMILAR falls this far (in nats) below the best one.
EXCLUDED = 24.0
#: With fewer equal registers than this share, a similarity of SIMILAR is always that far below; such pairs need no likelihood.
FEW_EQUAL = 0.41
#: Sets that are sketched at once.
SKETCHED = 96

_ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], np.uint64)
_ONE = np.uint64(1)


def shingles(text: str | None) -> np.ndarray:
    """The sorted distinct shingle hashes of a text."""
    if not text:
        return np.empty(0, np.uint64)
    words = text.encode("utf-8", "surrogatepass").lower().split()
    n = len(words)
    if not n:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, n)
    with np.errstate(over="ignore"):
        if n < WIDTH:
            return mix64((h * _ODD[:n]).sum(keepdims=True, dtype=np.uint64) + np.uint64(n))
        s = h[: n - WIDTH + 1] * _ODD[0]
        for k in range(1, WIDTH):
            s = s + h[k : n - WIDTH + 1 + k] * _ODD[k]
    return np.unique(mix64(s))


def registers(sets: list[np.ndarray]) -> np.ndarray:
    """SetSketch registers (uint16, one row a set); an empty set has zeros."""
    out = np.full(len(sets) * M, np.inf)
    sizes = np.array([len(s) for s in sets])
    horizon = (math.log(M) + SLACK) / (RATE * np.maximum(sizes, 1))
    owner = np.repeat(np.arange(len(sets)), sizes)
    seed = np.concatenate(sets) if len(sets) else np.empty(0, np.uint64)
    at, step = np.zeros(len(seed)), np.zeros(len(seed), np.uint64)
    total = M * RATE
    with np.errstate(over="ignore"):
        while len(seed):
            left = (horizon[owner] - at) * total  # points still expected
            count = np.maximum(1, np.ceil(left)).astype(np.int64)
            ends = np.cumsum(count)
            line = np.repeat(np.arange(len(seed)), count)
            j = (np.arange(ends[-1]) - np.repeat(ends - count, count)).astype(np.uint64)
            key = mix64(seed[line] + (step[line] + j + _ONE) * _ODD[0])
            gap = np.cumsum(-np.log1p(-(key >> np.uint64(11)).astype(np.float64) * 2.0**-53))
            base = np.repeat(np.concatenate(([0.0], gap[ends[:-1] - 1])), count)
            time = at[line] + (gap - base) / total
            register = ((mix64(key ^ _ODD[1]) & np.uint64(0xFFFFFFFF)) * np.uint64(M)) >> np.uint64(32)
            who = owner[line]
            near = time < horizon[who]
            np.minimum.at(out, who[near] * M + register[near].astype(np.int64), time[near])
            last = time[ends - 1]
            go = last < horizon[owner]
            seed, owner, at, step = seed[go], owner[go], last[go], (step + count.astype(np.uint64))[go]
    with np.errstate(divide="ignore"):
        scale = np.where(np.isinf(out), 0, np.clip(np.floor(1 - np.log(out) / math.log(BASE)), 1, TOP))
    return scale.astype(np.uint16).reshape(len(sets), M)


def bands(regs: str) -> Column:
    """One 64-bit key for each band of the registers in a binary column."""
    size = 2 * ROWS
    return F.transform(F.sequence(F.lit(0), F.lit(BANDS - 1)), lambda k: F.xxhash64(k, F.substring(F.col(regs), k * size + 1, F.lit(size))))


def _gap(x: np.ndarray) -> np.ndarray:
    return -np.log1p(-np.clip(x, 0, 1) * (BASE - 1) / BASE) / math.log(BASE)


def not_excluded(above: np.ndarray, below: np.ndarray, same: np.ndarray, n_a: int, n_b: np.ndarray, similar: float) -> np.ndarray:
    """Whether the joint likelihood of two sketches leaves ``similar`` or more possible.

    above, below, same: registers in which the first is larger, smaller, equal. The likelihood of a similarity j has the
    probabilities of these three events, which follow from j and the two exact set sizes.
    """
    u, v = n_a / (n_a + n_b), n_b / (n_a + n_b)
    most = np.minimum(u / v, v / u)
    grid = np.linspace(0.02, 1.0, 50)[None, :] * most[:, None]

    def log_likelihood(j):
        up, down = _gap(u[:, None] - v[:, None] * j), _gap(v[:, None] - u[:, None] * j)
        tiny = 1e-12
        return above[:, None] * np.log(up + tiny) + below[:, None] * np.log(down + tiny) + same[:, None] * np.log(np.maximum(1 - up - down, tiny))

    every = log_likelihood(grid)
    best = every.max(axis=1)
    top = grid[np.arange(len(grid)), every.argmax(axis=1)]
    at = log_likelihood(np.minimum(similar, most)[:, None])[:, 0]
    return (most >= similar - 1e-9) & ((top >= similar) | (best - at < EXCLUDED))


def sketch(docs: DataFrame) -> DataFrame:
    """(doc_id, th, n_shingles, digest, regs) for each row: th is a hash of the text, digest of the set."""
    prepare(docs.sparkSession)
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, SKETCHED):
                part = batch.slice(start, SKETCHED)
                sets = [shingles(t) for t in part.column(2).to_pylist()]
                regs = registers(sets)
                yield pa.RecordBatch.from_arrays(
                    [
                        part.column(0),
                        part.column(1),
                        pa.array([len(s) for s in sets], pa.int64()),
                        pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary()),
                        pa.array([r.tobytes() for r in regs], pa.binary()),
                    ],
                    ["doc_id", "th", "n_shingles", "digest", "regs"],
                )

    return slim.mapInArrow(run, "doc_id long, th long, n_shingles long, digest binary, regs binary")


def forest_of(sets: list[np.ndarray], regs: np.ndarray, block: np.ndarray, similar: int = SIMILAR) -> list[tuple[int, int]]:
    """Links that span the similarity graph of these sets, from the first set of each tree to its others; only pairs of
    different blocks count where there are two."""
    n = len(sets)
    tree = np.arange(n)  # the tree that each set is in so far
    sizes = np.array([len(s) for s in sets])
    crossing = len(set(block.tolist())) > 1
    flat = np.concatenate(sets)
    starts = np.concatenate(([0], np.cumsum(sizes)[:-1]))
    ids = None
    for i in range(n - 1):
        keep = tree[i + 1 :] != tree[i]
        if crossing:
            keep &= block[i + 1 :] != block[i]
        keep &= 100 * np.minimum(sizes[i + 1 :], sizes[i]) >= similar * np.maximum(sizes[i + 1 :], sizes[i])
        rest = np.flatnonzero(keep) + i + 1
        if not len(rest):
            continue
        same = (regs[i] == regs[rest]).sum(axis=1)
        rest, same = rest[same >= FEW_EQUAL * M], same[same >= FEW_EQUAL * M]
        if not len(rest):
            continue
        above = (regs[i] > regs[rest]).sum(axis=1)
        rest = rest[not_excluded(above, M - above - same, same, sizes[i], sizes[rest], similar / 100)]
        if len(rest) > 16:
            if ids is None:  # set elements as small numbers, once
                _, ids = np.unique(flat, return_inverse=True)
                ids = ids.astype(np.int32)
                mark = np.zeros(int(ids.max()) + 1, np.int8)
            own = ids[starts[i] : starts[i] + sizes[i]]
            mark[own] = 1
            both = np.add.reduceat(mark[ids], starts, dtype=np.int64)[rest]
            mark[own] = 0
        else:
            both = np.array([len(np.intersect1d(sets[i], sets[j], assume_unique=True)) for j in rest.tolist()], np.int64)
        for j in rest[100 * both >= similar * (sizes[i] + sizes[rest] - both)].tolist():
            if tree[i] != tree[j]:
                tree[tree == tree[j]] = tree[i]
    _, first, back = np.unique(tree, return_index=True, return_inverse=True)
    return [(int(first[k]), j) for j, k in enumerate(back.tolist()) if first[k] != j]


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows come sorted by task (hub, x, y), then digest; one task is held at a time."""
    state: dict = {"key": None, "rows": {}}

    def close() -> pa.RecordBatch | None:
        rows = list(state["rows"].items())
        state["rows"] = {}
        if len(rows) < 2:
            return None
        links = forest_of([r[1][0] for r in rows], np.stack([r[1][1] for r in rows]), np.array([r[1][2] for r in rows]))
        if not links:
            return None
        return pa.RecordBatch.from_arrays([pa.array([state["key"][0]] * len(links), pa.binary()), pa.array([rows[i][0] for i, _ in links], pa.binary()), pa.array([rows[j][0] for _, j in links], pa.binary())], ["hub", "a", "b"])

    for batch in batches:
        for hub, x, y, digest, regs, block, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if (hub, x, y) != state["key"]:
                if (out := close()) is not None:
                    yield out
                state["key"] = (hub, x, y)
            if digest not in state["rows"]:
                own = shingles(text)
                if xxhash.xxh3_128_digest(own.tobytes()) == digest:
                    state["rows"][digest] = (own, np.frombuffer(regs, np.uint16), block)
    if (out := close()) is not None:
        yield out


def _confirmed(tasks: DataFrame) -> DataFrame:
    tasks = tasks.select("hub", "x", "y", "digest", "regs", "block", "text")
    return tasks.repartition(partitions(tasks.sparkSession), "hub", "x", "y").sortWithinPartitions("hub", "x", "y", "digest").mapInArrow(_confirm, "hub binary, a binary, b binary")


def _with_texts(members: DataFrame, docs: DataFrame) -> DataFrame:
    """``members`` (with rid, rth) and the text of each."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), "text").where(F.length(F.trim("text")) > 0)
    wanted = members.select(F.col("rth").alias("w")).distinct()
    if wanted.limit(BROADCAST_TEXTS + 1).count() <= BROADCAST_TEXTS:
        texts = texts.join(F.broadcast(wanted), F.col("th") == F.col("w"), "left_semi")
    return members.join(texts, (F.col("rth") == F.col("th")) & F.col("rid").eqNullSafe(F.col("doc_id"))).drop("rid", "rth", "th", "doc_id")


def _links(classes: DataFrame, docs: DataFrame, block_shingles: int, block_sets: int) -> DataFrame:
    """Confirmed links (a, b) that span the similarity graph of the classes' sets."""
    keyed = classes.select(F.explode(bands("regs")).alias("key"), "digest")
    shared = keyed.groupBy("key").agg(F.min("digest").alias("hub"), F.count(F.lit(1)).alias("c")).where("c > 1").drop("c")
    near = keyed.join(shared, "key").groupBy("digest").agg(F.collect_set("hub").alias("hubs"))  # BANDS at most
    members = cut(near.join(classes.select("digest", F.col("r.doc_id").alias("rid"), F.col("r.th").alias("rth"), "n", "regs"), "digest"))
    stars = members.select(F.explode("hubs").alias("hub"), "n").groupBy("hub").agg(F.sum("n").alias("s"), F.count(F.lit(1)).alias("c"))
    many = F.greatest(F.ceil(F.col("s") / block_shingles), F.ceil(F.col("c") / block_sets)).cast("int")
    large = cut(stars.withColumn("k", many).where("k > 1").select("hub", "k"))
    spread = _with_texts(members, docs).select(F.explode("hubs").alias("hub"), "digest", "regs", "n", "text")
    spread = spread.join(large, "hub", "left").withColumn("k", F.coalesce("k", F.lit(1)))
    # the hub goes to every block of its star
    place = F.explode(F.when(F.col("digest") == F.col("hub"), F.sequence(F.lit(0), F.col("k") - 1)).otherwise(F.array(F.pmod(F.xxhash64("digest"), F.col("k")).cast("int"))))
    found = cut(_confirmed(spread.withColumn("x", place).withColumn("y", F.col("x")).withColumn("block", F.lit(0))))
    if large.isEmpty():
        return found.select("a", "b")
    # in stars of several blocks, sets that are not linked with the hub meet all others
    settled = found.where("a = hub").select("hub", F.col("b").alias("digest"), F.lit(True).alias("settled"))
    rest = members.select(F.explode("hubs").alias("hub"), "digest", "regs", "n", "rid", "rth").join(large.select("hub"), "hub").join(settled, ["hub", "digest"], "left")
    rest = rest.withColumn("open", F.col("settled").isNull() & (F.col("digest") != F.col("hub"))).drop("settled")
    parts = lambda yes: F.greatest(F.ceil(F.sum(F.when(yes, F.col("n"))) / block_shingles), F.ceil(F.sum(yes.cast("int")) / block_sets), F.lit(0)).cast("int")
    deal = rest.groupBy("hub").agg(parts(F.col("open")).alias("f"), parts(~F.col("open")).alias("t")).where("f > 0")
    dealt = rest.join(deal, "hub").withColumn("block", F.when(F.col("open"), F.pmod(F.xxhash64("digest"), F.col("f"))).otherwise(F.col("f") + F.pmod(F.xxhash64("digest"), F.greatest("t", F.lit(1)))).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.when(F.col("open"), F.col("f") + F.col("t")).otherwise(F.col("f")) - 1)))
    tasks = _with_texts(dealt.withColumn("x", F.least("block", "other")).withColumn("y", F.greatest("block", "other")), docs)
    return found.select("a", "b").union(cut(_confirmed(tasks)).select("a", "b"))


def link(docs: DataFrame, block_shingles: int = BLOCK_SHINGLES, block_sets: int = BLOCK_SETS) -> DataFrame:
    """One row for each document: doc_id, n_shingles, component_id, kept, and th and class_id for joining back."""
    rows = cut(sketch(docs))
    first = F.min_by(F.struct("doc_id", "th"), F.struct(F.col("doc_id").isNull(), "doc_id", "th"))
    classes = cut(rows.where("n_shingles > 0").groupBy("digest").agg(first.alias("r"), F.first("n_shingles").alias("n"), F.first("regs").alias("regs")))
    joined = components(_links(classes, docs, block_shingles, block_sets)).withColumnRenamed("node", "digest").withColumnRenamed("label", "root")

    reps = classes.select("digest", F.col("r.doc_id").alias("rep"))
    named = joined.join(reps, "digest")
    named = named.join(named.groupBy("root").agg(F.min("rep").alias("least")), "root").select("digest", "root", "least")
    final = reps.join(named, "digest", "left").select("digest", F.coalesce("root", "digest").alias("root"), F.when(F.col("root").isNull(), F.col("rep")).otherwise(F.col("least")).alias("component_id"))
    out = rows.select("doc_id", "th", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("digest")).alias("digest")).join(final, "digest", "left")
    named = F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id"))
    return out.select("doc_id", "n_shingles", named.alias("component_id"), F.coalesce(F.col("doc_id") == named, named.isNull()).alias("kept"), "th", F.hex("root").alias("class_id"))
