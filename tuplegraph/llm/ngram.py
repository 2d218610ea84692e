"""An n-gram language model in Elias-Fano tries, and the scores of texts under it.

Tokens are A-Z-lower-cased words and one end for each text. The trie has three levels. The first is the vocabulary, in the
order of 64-bit word hashes, with exact counts. A node of the second level is a pair (u, v); pairs of a shard are one
monotone sequence u * (V + 2) + v, so the pointer to the successors of u and their ids are fused. A node of the third
level below pair j is the rank of w among the successors of v, not w itself: the rank is small, so the monotone sequence
j * W + rank is compact, and a query first finds w among the successors of the shorter context and then searches for that
rank among the successors of the longer one. Both sequences are Elias-Fano coded; probabilities and back-off weights are
quantised to a byte. All arrays are files that are mapped into memory.

Smoothing is interpolated absolute discounting with discounts from the counts of counts; the unigram's discounted mass is
the probability of an unknown word. Counts cover all training texts, and every trigram has a node; with ``keep`` above 1,
trigrams below that many occurrences get none, and their mass goes to their context's back-off.

Scale: a task counts its texts and hands each shard one compressed block, so the shuffle carries distinct n-grams of a
task, not occurrences. The driver holds one row of totals for each shard. A shard holds the pairs of the words whose
number is its own modulo the shards; it grows with the vocabulary's successors, not with occurrences, so a word that
makes up a third of all tokens is no larger than its distinct successors. Files go to the shared checkpoint folder under
names that a repeated task writes again with equal content; with a store that is not a file system, a worker copies what
it opens to an unlinked local file first.

Results for odd input: a null text is empty and has one token, the end; without training texts every token is unknown and
all probabilities are 1; repeated rows count as often as they occur; extra columns are ignored.
"""

from __future__ import annotations

import gc
import math
import os
import tempfile
import uuid
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fold, partitions, prepare, shared_dir

KEEP = 1
STEP = 0.04  # of a quantised log10 value
BATCH_CHARS = 5_000_000
END = np.uint64(0x8E5D3A1B00C0FFEE)  # stands for the end in place of a word's hash


# ---- files ----


def _system(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri) if ":" in uri else (pafs.LocalFileSystem(), uri)


def put(uri: str, name: str, array: np.ndarray) -> None:
    system, path = _system(uri)
    system.create_dir(path, recursive=True)
    part = f"{path}/.{name}-{uuid.uuid4().hex}"
    with system.open_output_stream(part) as out:
        out.write(np.ascontiguousarray(array).tobytes() or b"")
    system.move(part, f"{path}/{name}")


def opened(uri: str, name: str, kind) -> np.ndarray:
    system, path = _system(uri)
    path = f"{path}/{name}"
    if isinstance(system, pafs.LocalFileSystem):
        return np.asarray(np.memmap(path, kind, "r")) if os.path.getsize(path) else np.empty(0, kind)
    with system.open_input_stream(path) as source, tempfile.TemporaryFile() as copy:
        while block := source.read(1 << 24):
            copy.write(block)
        copy.flush()
        return np.asarray(np.memmap(copy, kind, "r")) if copy.tell() else np.empty(0, kind)


def put_columns(uri: str, name: str, *columns: np.ndarray) -> None:
    """Columns of whole numbers of one length, compressed; a column that does not fall is stored as its steps."""
    parts = [np.array([len(columns[0])], np.int64).tobytes()]
    for c in columns:
        c = c.astype(np.int64)
        rising = bool(len(c) and (c[1:] >= c[:-1]).all())
        steps = np.diff(c, prepend=0) if rising else c
        kind = next(k for k in (np.uint8, np.uint16, np.uint32, np.int64) if k is np.int64 or (int(steps.max(initial=0)) <= np.iinfo(k).max and int(steps.min(initial=0)) >= 0))
        parts += [bytes([rising, np.dtype(kind).itemsize]), steps.astype(kind).tobytes()]
    put(uri, name, np.frombuffer(zstandard.ZstdCompressor(level=1).compress(b"".join(parts)), np.uint8))


def columns_of(uri: str, name: str) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(opened(uri, name, np.uint8).tobytes())
    n, at, out = int(np.frombuffer(raw, np.int64, 1)[0]), 8, []
    while at < len(raw):
        rising, size = raw[at], raw[at + 1]
        c = np.frombuffer(raw, {1: np.uint8, 2: np.uint16, 4: np.uint32, 8: np.int64}[size], n, at + 2).astype(np.int64)
        out.append(np.cumsum(c) if rising else c)
        at += 2 + n * size
    return out


def remove(uri: str, name: str) -> None:
    system, path = _system(uri)
    if exists(uri, name):
        system.delete_file(f"{path}/{name}")


def exists(uri: str, name: str) -> bool:
    system, path = _system(uri)
    return system.get_file_info(f"{path}/{name}").type == pafs.FileType.File


# ---- Elias-Fano ----


class EliasFano:
    """A monotone sequence of 64-bit numbers: low bits packed, high bits in unary with a directory of zeros."""

    PARTS = (("low", np.uint64), ("up", np.uint64), ("zeros", np.int64), ("head", np.int64))

    def __init__(self, low, up, zeros, head):
        self.low, self.up, self.zeros = low, up, zeros
        self.n, self.bits = int(head[0]), int(head[1])

    @classmethod
    def build(cls, values: np.ndarray) -> EliasFano:
        values = values.astype(np.uint64)
        n = len(values)
        top = int(values[-1]) if n else 0
        bits = max(0, (max(1, top) // max(1, n)).bit_length() - 1)
        low = np.zeros(n * bits // 64 + 2, np.uint64)
        if bits:
            small = values & np.uint64((1 << bits) - 1)
            at = np.arange(n, dtype=np.int64) * bits
            word, off = at >> 6, (at & 63).astype(np.uint64)
            np.bitwise_or.at(low, word, small << off)
            over = (at & 63) + bits > 64
            np.bitwise_or.at(low, word[over] + 1, small[over] >> (np.uint64(64) - off[over]))
        high = (values >> np.uint64(bits)).astype(np.int64)
        places = high + np.arange(n)
        size = (int(places[-1]) if n else 0) + 2
        flags = np.zeros(-(-size // 64) * 64, np.uint8)
        flags[places] = 1
        up = np.packbits(flags, bitorder="little").view(np.uint64)
        zeros = np.concatenate(([0], np.cumsum(64 - np.bitwise_count(up).astype(np.int64))))
        return cls(low, up, zeros, np.array([n, bits]))

    def save(self, uri: str, name: str) -> None:
        for part, value in (("low", self.low), ("up", self.up), ("zeros", self.zeros), ("head", np.array([self.n, self.bits], np.int64))):
            put(uri, f"{name}.{part}", value)

    @classmethod
    def load(cls, uri: str, name: str) -> EliasFano:
        return cls(*[opened(uri, f"{name}.{part}", kind) for part, kind in cls.PARTS])

    def _low(self, i: np.ndarray) -> np.ndarray:
        if not self.bits:
            return np.zeros(len(i), np.uint64)
        at = i * self.bits
        word, off = at >> 6, (at & 63).astype(np.uint64)
        first = self.low[word] >> off
        rest = np.where(off > 0, self.low[word + 1] << ((np.uint64(64) - off) & np.uint64(63)), np.uint64(0))
        return (first | rest) & np.uint64((1 << self.bits) - 1)

    def _zero(self, k: np.ndarray) -> np.ndarray:
        """Place of the zero number k (from 0)."""
        word = np.searchsorted(self.zeros, k, "right") - 1
        left = k - self.zeros[word]
        inside = ~self.up[np.minimum(word, len(self.up) - 1)]
        place = np.zeros(len(k), np.int64)
        for width in (32, 16, 8, 4, 2, 1):  # halve the word around the zero
            ones = np.bitwise_count((inside >> place.astype(np.uint64)) & np.uint64((1 << width) - 1)).astype(np.int64)
            go = ones <= left
            left = left - np.where(go, ones, 0)
            place = place + np.where(go, width, 0)
        return word * 64 + place

    def _zero_after(self, at: np.ndarray, k: np.ndarray) -> np.ndarray:
        """Place of the first zero at or after a place; it is zero number k, which is searched for where its word is another."""
        word, off = at >> 6, (at & 63).astype(np.uint64)
        rest = ~self.up[np.minimum(word, len(self.up) - 1)] >> off
        near = at + np.bitwise_count((rest & (~rest + np.uint64(1))) - np.uint64(1)).astype(np.int64)
        far = np.flatnonzero((rest == 0) | (word >= len(self.up)))
        near[far] = self._zero(k[far])
        return near

    def locate(self, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(number of elements below q, whether q is an element), best for sorted q."""
        if not self.n:
            return np.zeros(len(q), np.int64), np.zeros(len(q), bool)
        q = q.astype(np.uint64)
        high, small = (q >> np.uint64(self.bits)).astype(np.int64), q & np.uint64((1 << self.bits) - 1)
        total = int(self.zeros[-1])
        outside = high >= total
        high = np.minimum(high, total - 1)
        before = np.where(high > 0, self._zero(np.maximum(high - 1, 0)), -1)
        start = before + 1 - high
        end = np.minimum(self._zero_after(before + 1, high) - high, self.n)
        start = np.minimum(start, end)
        low, top = start.copy(), end.copy()
        active = np.flatnonzero(low < top)
        while len(active):
            middle = (low[active] + top[active]) >> 1
            less = self._low(middle) < small[active]
            low[active] = np.where(less, middle + 1, low[active])
            top[active] = np.where(less, top[active], middle)
            active = active[low[active] < top[active]]
        found = np.zeros(len(q), bool)
        inside = np.flatnonzero((low < end) & ~outside)
        found[inside] = self._low(low[inside]) == small[inside]
        return np.where(outside, self.n, low), found


def quantised(values: np.ndarray) -> np.ndarray:
    """log10 values at most 0 as bytes."""
    return np.clip(np.rint(-values / STEP), 0, 255).astype(np.uint8)


# ---- tokens ----


def _parts(batches: Iterator[pa.RecordBatch], column: int) -> Iterator[pa.RecordBatch]:
    """Batches of at most BATCH_CHARS characters or one text."""
    for batch in batches:
        sizes = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64) + 1)
        start = 0
        while start < batch.num_rows:
            done = sizes[start - 1] if start else 0
            end = max(start + 1, int(np.searchsorted(sizes, done + BATCH_CHARS, "right")))
            yield batch.slice(start, end - start)
            start = end


_LOWER = bytes(32 if 9 <= b <= 13 else b + 32 if 65 <= b <= 90 else b for b in range(256))


def tokens(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hashes of the distinct tokens, tokens as numbers into these, text of each token); a text's last token is the end."""
    plain = pa.array([(t or "").encode("utf-8", "surrogatepass").translate(_LOWER) for t in texts.to_pylist()], pa.large_binary())
    words = pc.split_pattern(plain, b" ")
    offsets = words.offsets.to_numpy().astype(np.int64)
    flat = words.flatten().dictionary_encode()
    codes = flat.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    names = flat.dictionary.to_pylist()
    owner = np.repeat(np.arange(len(texts)), np.diff(offsets))
    empty = [i for i, w in enumerate(names) if not w]
    if empty:
        full = codes != empty[0]
        codes, owner = codes[full], owner[full]
    hashes = np.array([xxhash.xxh3_64_intdigest(w) for w in names] + [int(END)], np.uint64)
    counts = np.bincount(owner, minlength=len(texts)) + 1
    ends = np.cumsum(counts) - 1
    out = np.full(int(counts.sum()), len(names), np.int64)
    inner = np.ones(len(out), bool)
    inner[ends] = False
    out[inner] = codes
    return hashes, out, np.repeat(np.arange(len(texts)), counts)


def _steps(keys: np.ndarray) -> np.ndarray:
    """Sorted keys as their differences, which compress well."""
    return np.diff(keys, prepend=keys.dtype.type(0))


def _distinct(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values and each value's place among them."""
    code, kinds = pd.factorize(values)
    order = np.argsort(kinds)
    place = np.empty(len(kinds), np.int64)
    place[order] = np.arange(len(kinds))
    return kinds[order], place[code]


def _pack(*arrays: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(b"".join(np.ascontiguousarray(a).tobytes() for a in arrays))


def _summed(keys: list[np.ndarray], counts: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """Sorted distinct rows of keys (the first is the most significant) and their summed counts."""
    order = np.argsort(keys[0], kind="stable") if len(keys) == 1 else np.lexsort(keys[::-1])
    keys, counts = [k[order] for k in keys], counts[order]
    new = np.ones(len(counts), bool)
    if len(counts):
        new[1:] = np.logical_or.reduce([k[1:] != k[:-1] for k in keys])
    starts = np.flatnonzero(new)
    return [k[starts] for k in keys], np.add.reduceat(counts, starts) if len(starts) else counts


def _counted(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of sorted keys and how often each occurs."""
    starts = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    return keys[starts], np.diff(np.append(starts, len(keys)))


def _steps_back(steps: np.ndarray) -> np.ndarray:
    return np.cumsum(steps, dtype=steps.dtype)


def release(spark: SparkSession) -> None:
    """Lets the driver find shuffles that nothing refers to any more, so that their files go before the next stage writes."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


# ---- model ----


class Model:
    def __init__(self, uri: str, shards: int, offsets: tuple[int, ...], total: int, discounts: tuple[float, float, float], widest: int):
        self.uri, self.shards, self.offsets, self.total, self.discounts, self.widest = uri, shards, offsets, total, discounts, widest
        self.size = offsets[-1]
        self._open: dict = {}

    def __getstate__(self):
        return self.__dict__ | {"_open": {}}

    def _file(self, name: str, kind) -> np.ndarray:
        if name not in self._open:
            self._open[name] = opened(self.uri, name, kind)
        return self._open[name]

    def _trie(self, name: str) -> EliasFano:
        if name not in self._open:
            self._open[name] = EliasFano.load(self.uri, name)
        return self._open[name]

    def numbers(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(number in the vocabulary or -1, count) of each word hash."""
        number, count = np.full(len(hashes), -1, np.int64), np.zeros(len(hashes), np.int64)
        order = np.argsort(hashes)
        ordered = hashes[order]
        edges = np.searchsorted(vocabulary_shard(ordered, self.shards), np.arange(self.shards + 1))
        for s in np.flatnonzero(np.diff(edges)).tolist():
            known, own = self._file(f"v{s}.hash", np.uint64), slice(edges[s], edges[s + 1])
            if not len(known):
                continue
            at = np.minimum(np.searchsorted(known, ordered[own]), len(known) - 1)
            hit = np.flatnonzero(known[at] == ordered[own])
            number[order[own][hit]] = at[hit] + self.offsets[s]
            count[order[own][hit]] = self._file(f"v{s}.count", np.int64)[at[hit]]
        return number, count

    def _by_shard(self, part: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """Each shard that occurs and the places of its members, in their order."""
        order = np.argsort(part.astype(np.uint16) if self.shards < 1 << 16 else part, kind="stable")
        edges = np.searchsorted(part[order], np.arange(self.shards + 1))
        for s in np.flatnonzero(np.diff(edges)).tolist():
            yield s, order[edges[s] : edges[s + 1]]

    def pair_keys(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        return (u // self.shards).astype(np.uint64) * np.uint64(self.size + 2) + v.astype(np.uint64)

    def find_pairs(self, u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For pairs: (shard, place in the shard's sequence, found)."""
        part, key = u % self.shards, self.pair_keys(u, v)
        place, found = np.zeros(len(u), np.int64), np.zeros(len(u), bool)
        # pairs that come sorted by (u, v) stay so within a shard; others are sorted there
        for s, own in self._by_shard(part):
            if len(own) > 1 and (key[own[1:]] < key[own[:-1]]).any():
                own = own[np.argsort(key[own])]
            place[own], found[own] = self._trie(f"p{s}").locate(key[own])
        return part, place, found

    def gather(self, name: str, kind, part: np.ndarray, place: np.ndarray) -> np.ndarray:
        out = np.zeros(len(part), kind)
        for s, own in self._by_shard(part):
            out[own] = self._file(name.format(s) if "{}" in name else f"{name}{s}", kind)[place[own]]
        return out

    def unigram(self, count: np.ndarray) -> np.ndarray:
        """log10 probabilities of words by their counts; 0 is unknown."""
        if not self.total:
            return np.zeros(len(count))
        d = self.discounts[0]
        return np.log10(np.where(count > 0, np.maximum(count - d, 1e-9) / self.total, max(d * self.size, 0.5) / self.total))

    def log_probability(self, code: np.ndarray, doc: np.ndarray, number: np.ndarray, count: np.ndarray) -> np.ndarray:
        """log10 probability of each token; code indexes number and count."""
        w, single = number[code], self.unigram(count)[code]
        if not self.size:
            return single
        begin = self.size
        first = np.concatenate(([True], doc[1:] != doc[:-1]))
        v = np.where(first, begin, np.concatenate(([begin], w[:-1])))
        # each distinct pair is searched for once
        both = (v >= 0) & (w >= 0)
        key = np.where(both, v * np.int64(begin + 2) + w, -1)
        distinct, back = _distinct(key)
        real = distinct >= 0
        pu, pw = distinct[real] // (begin + 2), distinct[real] % (begin + 2)
        part, place, found = self.find_pairs(pu, pw)
        n = len(distinct)
        d_part, d_place, d_found = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, bool)
        d_part[real], d_place[real], d_found[real] = part, place, found
        pair = np.zeros(n)
        pair[d_found] = -STEP * self.gather("pp", np.uint8, d_part[d_found], d_place[d_found])
        seen = d_found[back]
        out = single.copy()
        # back-off of a context word that the training texts hold
        context = np.unique(v[v >= 0])
        slack = -STEP * self.gather("pb", np.uint8, context % self.shards, context // self.shards)
        weight = np.where(v >= 0, slack[np.minimum(np.searchsorted(context, v), len(context) - 1)], 0.0)
        out = np.where(seen, pair[back], out + weight)
        # the longer context is the pair found one token before
        before = np.concatenate(([-1], back[:-1]))
        usable = ~first & (before >= 0)
        usable[usable] = d_found[before[usable]]
        if not usable.any():
            return out
        t = np.flatnonzero(usable)
        j_part, j_place = d_part[before[t]], d_place[before[t]]
        loose = self.gather("tb", np.uint8, j_part, j_place)  # 255: no third level below
        has = loose != 255
        t, j_part, j_place, loose = t[has], j_part[has], j_place[has], loose[has]
        rank_known = d_found[back[t]]
        start = np.zeros(len(t), np.int64)
        if rank_known.any():
            head, inverse = _distinct(v[t])
            _, begins, _ = self.find_pairs(head, np.zeros(len(head), np.int64))
            start = begins[inverse]
        rank = d_place[back[t]] - start
        query = j_place * np.int64(self.widest) + rank
        hit, triple = np.zeros(len(t), bool), np.zeros(len(t))
        asked = np.flatnonzero(rank_known)
        for s, own in self._by_shard(j_part[asked]):
            own = asked[own]
            own = own[np.argsort(query[own])]
            where, ok = self._trie(f"t{s}").locate(query[own])
            hit[own] = ok
            triple[own[ok]] = -STEP * self._file(f"tp{s}", np.uint8)[where[ok]]
        out[t] = np.where(hit, triple, out[t] - STEP * loose)
        return out


def vocabulary_shard(hashes: np.ndarray, shards: int) -> np.ndarray:
    """Shards of equal hash ranges, in hash order."""
    return ((hashes >> np.uint64(32)) * np.uint64(shards) >> np.uint64(32)).astype(np.int64)


@lru_cache(maxsize=1)
def _cached(uri: str, shards: int, offsets: tuple[int, ...], total: int, discounts: tuple, widest: int) -> Model:
    return Model(uri, shards, offsets, total, discounts, widest)


def _discount(once: int, twice: int) -> float:
    return once / (once + 2 * twice) if once and twice else 0.5


def train(docs: DataFrame, shards: int | None = None, keep: int = KEEP) -> Model:
    """A model of all texts of ``docs`` (column ``text``), with its files in the shared folder."""
    spark = prepare(docs.sparkSession)
    shards = shards or partitions(spark)
    uri = f"{shared_dir(spark)}/ngram-{uuid.uuid4().hex}"
    texts = docs.select("text")

    def word_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def merged():
            (keys,), counts = _summed([np.concatenate([h for h, _ in held])], np.concatenate([c for _, c in held]))
            return keys, counts

        for part in _parts(batches, 0):
            hashes, code, _ = tokens(part.column(0))
            count = np.bincount(code, minlength=len(hashes))
            held.append((hashes[count > 0], count[count > 0]))
            if len(held) > 16:
                held = [merged()]
        if held:
            keys, counts = merged()
            edges = np.searchsorted(vocabulary_shard(keys, shards), np.arange(shards + 1))
            for s in range(shards):
                a, b = edges[s], edges[s + 1]
                if b > a:
                    yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([int(b - a)], pa.int64()), pa.array([_pack(keys[a:b], counts[a:b])], pa.binary())], ["shard", "n", "block"])

    def by_shard(batches: Iterator[pa.RecordBatch], kinds: list, finish, apart: int = 0) -> Iterator[tuple]:
        """Blocks come sorted by shard; ``finish`` gets a shard and its columns, the first ``apart`` as lists of blocks."""
        state: dict = {"shard": None, "held": []}

        def close():
            if state["shard"] is None:
                return None
            columns = [own if k < apart else np.concatenate(own) for k in range(len(kinds)) for own in [[h[k] for h in state["held"]]]]
            state["held"] = []
            return finish(state["shard"], columns)

        for batch in batches:
            for s, n, block in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if s != state["shard"]:
                    if (row := close()) is not None:
                        yield row
                    state["shard"] = s
                raw, at, columns = zstandard.ZstdDecompressor().decompress(block), 0, []
                for kind in kinds:
                    columns.append(np.frombuffer(raw, kind, n, at))
                    at += n * np.dtype(kind).itemsize
                state["held"].append(columns)
        if (row := close()) is not None:
            yield row

    def table_of(rows: Iterator[tuple], names: list[str]) -> Iterator[pa.RecordBatch]:
        for row in rows:
            yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in row], names)

    def dealt(blocks: DataFrame) -> DataFrame:
        return blocks.repartition(shards, "shard").sortWithinPartitions("shard")

    def vocabulary(batches):
        def finish(s, columns):
            (keys,), counts = _summed([columns[0]], columns[1])
            put(uri, f"v{s}.hash", keys)
            put(uri, f"v{s}.count", counts.astype(np.int64))
            return s, len(keys), int(counts.sum()), int((counts == 1).sum()), int((counts == 2).sum())

        return table_of(by_shard(batches, [np.uint64, np.int64], finish), ["shard", "words", "tokens", "once", "twice"])

    blocks = dealt(texts.mapInArrow(word_blocks, "shard int, n long, block binary"))
    rows = {r["shard"]: r for r in blocks.mapInArrow(vocabulary, "shard long, words long, tokens long, once long, twice long").collect()}
    sizes = [rows[s]["words"] if s in rows else 0 for s in range(shards)]
    offsets = tuple(int(x) for x in np.concatenate(([0], np.cumsum(sizes))))
    total = sum(r["tokens"] for r in rows.values())
    d1 = _discount(sum(r["once"] for r in rows.values()), sum(r["twice"] for r in rows.values()))
    if not total:
        return Model(uri, shards, (0,), 0, (d1, 0.5, 0.5), 1)
    for s in range(shards):
        if s not in rows:
            put(uri, f"v{s}.hash", np.empty(0, np.uint64))
            put(uri, f"v{s}.count", np.empty(0, np.int64))
    size = offsets[-1]
    base = size + 2
    one_key = (size // shards + 1) * base * base < 2**64  # a trigram's number within its shard fits a word
    numbering = (uri, shards, offsets, total, (d1, 0.5, 0.5), 1)

    def gram_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Counts of (u, v, w) by the shard of u; the pair (last word, end) is followed by the number size + 1."""
        model = _cached(*numbering)
        held: list = []
        waiting = 0

        def flush():
            part, keys = np.concatenate([h[0] for h in held]), [np.concatenate([h[k] for h in held]) for k in range(1, len(held[0]))]
            order = np.argsort(part.astype(np.uint16) if shards < 1 << 16 else part, kind="stable")
            edges = np.searchsorted(part[order], np.arange(shards + 1))
            for s in np.flatnonzero(np.diff(edges)).tolist():
                own = order[edges[s] : edges[s + 1]]
                if len(keys) == 1:
                    first, counts = _counted(np.sort(keys[0][own]))
                    columns = [first]
                else:
                    columns, counts = _summed([k[own] for k in keys], np.ones(len(own), np.int64))
                yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([len(counts)], pa.int64()), pa.array([_pack(_steps(columns[0]), *columns[1:], counts.astype(np.uint32))], pa.binary())], ["shard", "n", "block"])

        for part in _parts(batches, 0):
            hashes, code, doc = tokens(part.column(0))
            number, _ = model.numbers(hashes)
            w = number[code]
            first = np.concatenate(([True], doc[1:] != doc[:-1]))
            u = np.where(first, size, np.concatenate(([size], w[:-1])))
            nxt = np.where(np.concatenate((first[1:], [True])), size + 1, np.concatenate((w[1:], [size + 1]))).astype(np.uint64)
            pair = (u // shards).astype(np.uint64) * np.uint64(base) + w.astype(np.uint64)
            held.append((u % shards, pair * np.uint64(base) + nxt) if one_key else (u % shards, pair, nxt))
            waiting += len(w)
            if waiting > 6_000_000:
                yield from flush()
                held, waiting = [], 0
        if held:
            yield from flush()

    def levels(batches):
        def finish(s, columns):
            keys, counts = _summed([np.concatenate([_steps_back(c) for c in columns[0]]), *columns[1:-1]], columns[-1].astype(np.int64))
            pairs, w = (keys[0] // np.uint64(base), (keys[0] % np.uint64(base)).astype(np.int64)) if one_key else (keys[0], keys[1].astype(np.int64))
            start = np.flatnonzero(np.concatenate(([True], pairs[1:] != pairs[:-1])))
            pair, pair_count = pairs[start], np.add.reduceat(counts, start)
            EliasFano.build(pair).save(uri, f"p{s}")
            real = w <= size
            kept = real & (counts >= keep)
            fall = np.add.reduceat(kept.astype(np.int64), start)  # trigrams below each pair
            put_columns(uri, f"x{s}.pair", pair, pair_count, fall)
            put_columns(uri, f"x{s}.third", w[kept], counts[kept])
            u = pair // np.uint64(base)
            runs = np.flatnonzero(np.concatenate(([True], u[1:] != u[:-1], [True])))
            return s, len(pair), int(np.diff(runs).max()), int((pair_count == 1).sum()), int((pair_count == 2).sum()), int((real & (counts == 1)).sum()), int((real & (counts == 2)).sum())

        kinds = [np.uint64, np.uint32] if one_key else [np.uint64, np.uint64, np.uint32]
        return table_of(by_shard(batches, kinds, finish, apart=1), ["shard", "pairs", "widest", "p1", "p2", "t1", "t2"])

    release(spark)
    blocks = dealt(texts.mapInArrow(gram_blocks, "shard int, n long, block binary"))
    rows = {r["shard"]: r for r in blocks.mapInArrow(levels, "shard long, pairs long, widest long, p1 long, p2 long, t1 long, t2 long").collect()}
    sums = {k: sum(r[k] for r in rows.values()) for k in ("p1", "p2", "t1", "t2")}
    model = Model(uri, shards, offsets, total, (d1, _discount(sums["p1"], sums["p2"]), _discount(sums["t1"], sums["t2"])), max(r["widest"] for r in rows.values()) + 1)
    made = set(rows)
    setup = (uri, shards, offsets, total, model.discounts, model.widest)

    def second(batches):
        """Probabilities of pairs and back-off weights of words; the probabilities also unrounded, for the next level."""
        model = _cached(*setup)
        d2 = model.discounts[1]
        for s in shards_of(batches):
            contexts = (size + 2 - s + shards - 1) // shards  # words u with u % shards == s, the begin among them
            if s not in made:
                EliasFano.build(np.empty(0, np.uint64)).save(uri, f"p{s}")
                put(uri, f"pb{s}", np.zeros(max(1, contexts), np.uint8))
                put(uri, f"pp{s}", np.empty(0, np.uint8))
                continue
            pair, count, _ = columns_of(uri, f"x{s}.pair")
            local, v = pair // base, pair % base
            outside = np.bincount(local, weights=count, minlength=contexts)
            slack = d2 * np.bincount(local, minlength=contexts) / np.maximum(outside, 1)
            put(uri, f"pb{s}", quantised(np.log10(np.clip(slack, 1e-10, 1.0))))
            p = (count - d2) / outside[local] + slack[local] * 10 ** model.unigram(counts_of(model, v))
            put(uri, f"pp{s}", quantised(np.log10(p)))
            put(uri, f"x{s}.p", p.astype(np.float32))
        yield done()

    def third(batches):
        """The third level of the shards that a task is given. Its input goes once its output is there."""
        model = _cached(*setup)
        d3 = model.discounts[2]
        for s in shards_of(batches):
            if s not in made:
                EliasFano.build(np.empty(0, np.uint64)).save(uri, f"t{s}")
                for name in ("tb", "tp"):
                    put(uri, f"{name}{s}", np.empty(0, np.uint8))
                continue
            if exists(uri, f"t{s}.done"):  # by a task that was lost after its work
                continue
            pair, count, fall = columns_of(uri, f"x{s}.pair")
            w, c = columns_of(uri, f"x{s}.third")
            of = np.repeat(np.arange(len(pair)), fall)
            loose = np.clip(1 - np.bincount(of, weights=c - d3, minlength=len(pair)) / count, 1e-10, 1.0)
            put(uri, f"tb{s}", np.where(fall > 0, np.minimum(quantised(np.log10(loose)), 254), 255).astype(np.uint8))
            mid = (pair % base)[of]
            head, inverse = _distinct(mid)
            _, begins, _ = model.find_pairs(head, np.zeros(len(head), np.int64))
            part, place, _ = model.find_pairs(mid, w)
            key = of * np.int64(model.widest) + place - begins[inverse]
            # interpolated with the unrounded probability of the shorter context
            p = (c - d3) / count[of] + loose[of] * model.gather("x{}.p", np.float32, part, place)
            order = np.argsort(key, kind="stable")
            EliasFano.build(key[order].astype(np.uint64)).save(uri, f"t{s}")
            put(uri, f"tp{s}", quantised(np.log10(p))[order])
            put(uri, f"t{s}.done", np.ones(1, np.uint8))
            for name in ("pair", "third"):
                remove(uri, f"x{s}.{name}")
        yield done()

    def shards_of(batches):
        return [s for batch in batches for s in batch.column(0).to_pylist()]

    def done():
        return pa.RecordBatch.from_arrays([pa.array([1], pa.int64())], ["n"])

    def counts_of(model, number):
        out = np.zeros(len(number), np.int64)
        part = np.searchsorted(np.array(offsets), number, "right") - 1
        for s in np.unique(part).tolist():
            own = np.flatnonzero(part == s)
            out[own] = opened(uri, f"v{s}.count", np.int64)[number[own] - offsets[s]]
        return out

    del blocks
    release(spark)
    for level in (second, third):
        spark.range(0, shards, 1, shards).mapInArrow(level, "n long").agg(F.sum("n")).collect()
    for s in sorted(made):  # what only the build needed
        remove(uri, f"x{s}.p")
    return model


def score(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, n_tokens, n_known, train_tokens, base_score, score) for each document."""
    prepare(docs.sparkSession)
    setup = (model.uri, model.shards, model.offsets, model.total, model.discounts, model.widest)
    size, total = model.size, model.total

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = _cached(*setup)
        for part in _parts(batches, 1):
            hashes, code, doc = tokens(part.column(1))
            number, count = model.numbers(hashes) if size else (np.full(len(hashes), -1, np.int64), np.zeros(len(hashes), np.int64))
            n = part.num_rows
            base = np.log10((count + 1.0) / (total + size + 1))[code]
            mine = model.log_probability(code, doc, number, count)
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array(np.bincount(doc, minlength=n), pa.int64()), pa.array(np.bincount(doc, weights=(count > 0)[code], minlength=n).astype(np.int64), pa.int64()), pa.array(np.full(n, total), pa.int64()), pa.array(np.bincount(doc, weights=base, minlength=n)), pa.array(np.bincount(doc, weights=mine, minlength=n))],
                ["doc_id", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def held_out_model(docs: DataFrame, parts: int = 7, part: int = 2) -> Model:
    """The model of all texts outside one fold of the ids; rows without id are in no fold and are learned from."""
    return train(docs.where(F.coalesce(fold("doc_id", parts), F.lit(-1)) != part))
