"""Byte-level BPE encoding and decoding from a public vocabulary file.

A word is a doubly linked list of symbols. A heap holds the merges that are possible now, by rank and then by place;
an entry whose symbols have changed since it was pushed is stale and skipped. Decoding concatenates the vocabulary's
byte strings. The vocabulary file is a parameter; only its path travels with the plan, and each Python worker loads it once.

Results for odd input: a null text is the empty text (no ids, the empty string); a text of any length is encoded whole;
repeated rows give repeated rows; extra columns are kept by ``encode`` unless they have the name of one of its outputs,
which then replaces them.
"""

from __future__ import annotations

import heapq
import json
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import prepare

# The pre-tokenisation pattern of the public byte-level format.
WORDS = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

#: Words of which a worker remembers the encoding. When the store is full it starts anew, so memory stays bounded.
REMEMBERED = 400_000


def byte_letters() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabulary files."""
    plain = {*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class Codec:
    """Encoder and decoder of one vocabulary."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        vocab = spec["model"]["vocab"]
        letters = byte_letters()
        byte_of = {c: b for b, c in enumerate(letters)}
        self.first = [vocab.get(c) for c in letters]
        self.bytes_of: dict[int, bytes] = {i: bytes(byte_of[c] for c in s) for s, i in vocab.items() if all(c in byte_of for c in s)}
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, pair in enumerate(spec["model"]["merges"]):
            left, right = pair.split(" ") if isinstance(pair, str) else pair
            self.merges.setdefault((vocab[left], vocab[right]), (rank, vocab[left + right]))
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.bytes_of.update({i: s.encode() for s, i in self.special.items()})
        self.cut = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.words = regex.compile(WORDS)
        self.known: dict[str, tuple[list[int], bytes]] = {}

    def word(self, word: str) -> list[int]:
        symbols: list[int] = [self.first[b] for b in word.encode()]
        n = len(symbols)
        if n == 1:
            return symbols
        merges = self.merges
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(found[0], i, symbols[i], symbols[i + 1], found[1]) for i in range(n - 1) if (found := merges.get((symbols[i], symbols[i + 1])))]
        heapq.heapify(heap)
        while heap:
            _, i, left, right, made = heapq.heappop(heap)
            j = after[i]
            if j >= n or symbols[i] != left or symbols[j] != right:
                continue
            symbols[i], symbols[j] = made, -1
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                if found := merges.get((made, symbols[k])):
                    heapq.heappush(heap, (found[0], i, made, symbols[k], found[1]))
            h = before[i]
            if h >= 0 and (found := merges.get((symbols[h], made))):
                heapq.heappush(heap, (found[0], h, symbols[h], made, found[1]))
        return [s for s in symbols if s >= 0]

    def _learn(self, word: str) -> tuple[list[int], bytes]:
        if len(self.known) >= REMEMBERED:
            self.known.clear()
        ids = self.word(word)
        self.known[word] = entry = (ids, b"".join(map(self.bytes_of.__getitem__, ids)))
        return entry

    def entries(self, text: str) -> list[tuple[list[int], bytes]]:
        """Ids and bytes of each word and special token of the text."""
        if self.cut and self.cut.search(text):
            out = []
            for k, piece in enumerate(self.cut.split(text)):
                out += [([self.special[piece]], piece.encode())] if k % 2 else self.entries(piece)
            return out
        words = self.words.findall(text)
        found = list(map(self.known.get, words))
        if not all(found):
            learn, get = self._learn, self.known.get
            found = [e or get(w) or learn(w) for e, w in zip(found, words, strict=True)]
        return found

    def both(self, text: str) -> tuple[list[int], bytes]:
        """Ids of the text, and the bytes that decoding these ids gives."""
        found = self.entries(text)
        return [i for e in found for i in e[0]], b"".join([e[1] for e in found])

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")


@lru_cache(maxsize=2)
def codec(path: str) -> Codec:
    return Codec(path)


def encode(df: DataFrame, path: str, text: str = "text", decoded: bool = True) -> DataFrame:
    """All columns of ``df`` with ``n_tokens`` long, ``ids`` array<int> and, if asked for, ``decoded`` string."""
    prepare(df.sparkSession)
    outputs = ["n_tokens", "ids"] + ["decoded"] * decoded
    df = df.drop(*[c for c in outputs if c in df.columns and c != text])
    schema = T.StructType([*df.schema.fields, T.StructField("n_tokens", T.LongType()), T.StructField("ids", T.ArrayType(T.IntegerType()))] + [T.StructField("decoded", T.StringType())] * decoded)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool = codec(path)
        for batch in batches:
            for start in range(0, batch.num_rows, 128):
                part = batch.slice(start, 128)
                texts = [x or "" for x in part.column(part.schema.get_field_index(text)).to_pylist()]
                found = [tool.entries(x) for x in texts]
                ids = [np.fromiter(chain.from_iterable([e[0] for e in f]), np.int32) for f in found]
                sizes = np.array([len(i) for i in ids], np.int64)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))), pa.int32()), pa.array(np.concatenate(ids)))
                arrays = [*part.columns, pa.array(sizes), lists]
                if decoded:
                    arrays.append(pa.array([b"".join([e[1] for e in f]).decode("utf-8", "replace") for f in found], pa.string()))
                yield pa.RecordBatch.from_arrays(arrays, [*part.schema.names, *outputs])

    return df.mapInArrow(run, schema)


def decode(df: DataFrame, path: str, ids: str = "ids", output: str = "decoded") -> DataFrame:
    """All columns of ``df`` with the text that ``ids`` stand for; null ids give the empty string."""
    prepare(df.sparkSession)

    @F.pandas_udf("string")
    def text_of(column):
        tool = codec(path)
        return column.map(lambda x: "" if x is None else tool.decode(list(x)))

    return df.withColumn(output, text_of(ids))


def digests(encoded: DataFrame) -> DataFrame:
    """The contract's digest columns of an encoded and decoded table."""
    return encoded.select(
        "doc_id",
        "n_tokens",
        F.sha2(F.concat_ws(",", F.col("ids").cast("array<string>")), 256).alias("ids_sha256"),
        F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"),
    )
