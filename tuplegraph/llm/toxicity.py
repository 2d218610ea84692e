"""Toxicity by a weighted lexicon, matched with an Aho-Corasick automaton on folded text.

Folding maps look-alike letters, digits and symbols inside words to one letter each (i, l, 1, ! and | are one class), so a
disguised word is the same string as the plain one; plain whole words are also looked for without accents. An entry is a
whole word or a stem that starts a word, and a match inside an exception phrase is dropped. A document's evidence is the
weight of its matches, also per word of its text; a logistic map turns both into a score.

The seed lexicon has prior weights. Labelled documents add the words and stems that mark toxic texts, in any language,
and set weights by smoothed log-odds; copies among them (texts of one least
shingle hash) share the weight of one. At most ``sample`` labelled documents are used,
the first by a hash of their id, and at most ``lexicon`` entries are kept, so what reaches the driver is bounded.
Everything else covers all documents.

Results for odd input: a null or empty text has no matches and gets the score of an unmatched text; texts are scanned
whole; labels that are null or conflict for an id are dropped; without labels the seed lexicon and the prior map are
used; repeated rows give repeated rows; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
import unicodedata
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fold as fold_of
from .common import cut, prepare
from .near_dup import shingles

# Seed words with prior weights, and phrases in which they are harmless.
SEEDS = {"idiot": 2.0, "idiots": 2.0, "moron": 2.0, "morons": 2.0, "stupid": 1.5, "dumb": 1.0, "scum": 2.0, "trash": 1.0, "garbage": 0.8, "loser": 1.5, "losers": 1.5, "pathetic": 1.5, "worthless": 1.5, "disgusting": 1.2, "clown": 1.2, "imbecile": 2.0, "vermin": 1.5, "bastard": 2.0, "asshole": 2.5, "bitch": 2.5, "fuck": 2.5, "fucking": 2.0, "shit": 2.0, "retard": 2.5, "dumbass": 2.5}
EXCEPTIONS = ("clown fish", "circus clown", "clown car", "trash can", "trash bin", "trash bag", "take out the trash", "garbage collection", "garbage collector", "garbage truck", "sore loser rule")
# Look-alikes of Latin letters in other scripts, and digits and symbols that stand for letters.
LOOKALIKES = {"а": "a", "е": "e", "о": "o", "р": "p", "с": "c", "у": "y", "х": "x", "к": "k", "м": "m", "т": "t", "н": "h", "в": "b", "і": "i", "ј": "j", "ѕ": "s", "ԁ": "d", "ո": "n", "ɡ": "g", "α": "a", "ο": "o", "ε": "e", "ι": "i", "κ": "k", "ν": "v", "ρ": "p", "τ": "t", "υ": "u", "χ": "x", "ı": "i", "ł": "l", "ß": "ss"}
DIGITS = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g"}
SYMBOLS = {"@": "a", "$": "s", "!": "i", "|": "i"}
HIDDEN = "­​‌‍⁠﻿"

SAMPLE, LEXICON, LEAST, SHARE = 10_000, 512, 5, 0.02
#: Entries that a task counts before it hands them on.
COUNTED = 150_000
#: Characters that count as a word at least, for scripts that write no spaces.
UNSPACED = 12
#: Lengths of stems.
STEMS = range(3, 11)
#: Prior of the logistic map: (bias, weight of log evidence, weight of log evidence per hundred words).
PRIOR = (-3.0, 3.0, 0.5)


def _plain(c: int) -> str | None:
    plain = "".join(x for x in unicodedata.normalize("NFKD", chr(c)).lower() if not unicodedata.combining(x))
    return plain.replace("l", "i") if plain and plain.isascii() and plain.isalnum() else None


TABLE: dict[int, str | None] = {ord(a): b.replace("l", "i") for a, b in {**LOOKALIKES, **DIGITS, "l": "i"}.items()}
TABLE |= {c: t for c in range(0xFF01, 0xFF5F) if (t := _plain(c))}
TABLE |= dict.fromkeys([*map(ord, HIDDEN), *range(0x300, 0x370)])
#: One letter for one, so places stay.
ACCENTS = {c: t for c in [*range(0xC0, 0x250), *range(0x1E00, 0x1F00)] if c not in TABLE and (t := _plain(c)) and len(t) == 1}
ACCENTED = re.compile(f"[{''.join(map(chr, ACCENTS))}]")
DISGUISE = re.compile(r"(?<=\w)[!|@$](?=\w)|(?<!\S)[@$](?=\w)")
WORD = re.compile(r"[^\W_]+")


def folded(text: str | None) -> str:
    text = (text or "").lower()
    if "@" in text or "$" in text or "!" in text or "|" in text:
        text = DISGUISE.sub(lambda m: SYMBOLS[m.group()], text)
    return text.translate(TABLE)


@lru_cache(maxsize=4)
def automaton(lexicon: tuple[tuple[str, float], ...], exceptions: tuple[str, ...]) -> ahocorasick.Automaton:
    """Values are (length, weight or None for an exception, whether it is a stem). A stem is written with a final ``*``."""
    found = ahocorasick.Automaton()
    for phrase in exceptions:
        found.add_word(folded(phrase), (len(folded(phrase)), None, False))
    for word, weight in lexicon:
        plain = word.rstrip("*")
        found.add_word(plain, (len(plain), weight, word.endswith("*")))
    found.make_automaton()
    return found


def evidence(text: str | None, lexicon: tuple, exceptions: tuple) -> tuple[float, int, int]:
    """(weight of the matches, number of matches, number of words) of a text."""
    text = folded(text)
    find, n, hits, safe = automaton(lexicon, exceptions).iter, len(text), {}, []
    views = [text, text.translate(ACCENTS)] if ACCENTED.search(text) else [text]
    for number, view in enumerate(views):
        for end, (size, weight, stem) in find(view):
            start = end + 1 - size
            if (start and view[start - 1].isalnum()) or (not stem and end + 1 < n and view[end + 1].isalnum()) or (number and stem):
                continue
            if weight is None:
                safe.append((start, end))
            elif weight > hits.get(start, (0, 0.0))[1]:
                hits[start] = (end, weight)
    kept = [w for s, (e, w) in hits.items() if not any(a <= s and e <= b for a, b in safe)]
    return sum(kept), len(kept), max(len(text.split()), n // UNSPACED, 1)


def _slices(batches: Iterator[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for start in range(0, batch.num_rows, rows):
            yield batch.slice(start, rows)


def _features(weight, words):
    weight = np.maximum(np.asarray(weight, float), 0)
    return np.stack([np.ones_like(weight), np.log1p(weight), np.log1p(100 * weight / np.maximum(np.asarray(words, float), 1))], axis=-1)


def calibrate(weight, words, label, share=None, rounds: int = 25) -> tuple[float, ...]:
    """Logistic map by Newton steps, drawn to the prior; ``share`` weighs the texts."""
    prior = np.array(PRIOR)
    x, y, w = _features(weight, words), np.asarray(label, float), prior.copy()
    many = np.ones(len(y)) if share is None else np.asarray(share, float)

    def loss(w):
        z = np.clip(x @ w, -500, 500)
        return many @ np.logaddexp(0, z) - (many * y) @ z + ((w - prior) ** 2).sum() / 2

    for _ in range(rounds if len(y) else 0):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        slope = x.T @ (many * (y - p)) - (w - prior)
        step = np.linalg.solve((x * (many * p * (1 - p))[:, None]).T @ x + np.eye(3), slope)
        while loss(w + step) > loss(w) and np.abs(step).max() > 1e-9:
            step = step / 2
        w = w + step
    return tuple(float(v) for v in w)


def _entries(text: str | None) -> set[str]:
    """The words of a text, each with a final ``$``, and their stems."""
    words = set(WORD.findall(folded(text)))
    return {w + "$" for w in words if len(w) >= STEMS.start} | {w[:k] for w in words for k in STEMS if len(w) >= k}


def _marking_words(rows: DataFrame, seeds: dict[str, float], size: int, least: int) -> dict[str, float]:
    """Weights of seed words and of words and stems that mark toxic texts among ``rows`` (toxic, text, share).

    An entry marks when at least SHARE of the toxic texts hold it, far more often than clean ones do. Of entries that
    start alike only the best is kept; a stem that is nearly always one word becomes that word.
    """

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by = {0: Counter(), 1: Counter()}

        def flush():
            words = sorted(by[0].keys() | by[1].keys())
            columns = [pa.array(words), pa.array([by[1][w] for w in words], pa.float64()), pa.array([by[0][w] for w in words], pa.float64())]
            by[0].clear()
            by[1].clear()
            return pa.RecordBatch.from_arrays(columns, ["word", "t", "c"])

        for batch in _slices(batches):
            for toxic, text, share in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                own = by[toxic]
                for entry in (*_entries(text), ""):  # the empty entry counts the texts
                    own[entry] += share
                if len(by[0]) + len(by[1]) > COUNTED:
                    yield flush()
        yield flush()

    counts = cut(rows.mapInArrow(counted, "word string, t double, c double").groupBy("word").agg(F.round(F.sum("t"), 6).alias("t"), F.round(F.sum("c"), 6).alias("c")).where(f"t >= {least} or word = '' or word in ({', '.join(repr(w + '$') for w in seeds)})"))
    whole = counts.where("word = ''").collect()
    n_t, n_c = (whole[0]["t"], whole[0]["c"]) if whole else (0, 0)
    gain = F.log((F.col("t") + 0.5) / (n_t + 1.0)) - F.log((F.col("c") + 0.5) / (n_c + 1.0))
    marking = (F.col("t") >= max(least, SHARE * n_t)) & (gain > 2.0)
    kept = counts.where("word <> ''").withColumn("gain", gain).where(marking | F.col("word").isin([w + "$" for w in seeds]))
    kept = kept.orderBy(F.desc(F.col("t") * F.least("gain", F.lit(5.0))), F.desc(F.length("word")), "word").limit(4 * size).collect()
    texts = {r["word"]: r["t"] for r in kept}
    chosen: dict[str, float] = {}
    for r in kept:
        plain = r["word"].rstrip("$")
        if any(plain.startswith(c.rstrip("*")) or c.startswith(plain) for c in chosen) or len(chosen) >= size:
            continue
        one_word = r["word"].endswith("$") or texts.get(plain + "$", 0) >= 0.9 * r["t"]
        seen = r["t"] + r["c"]
        chosen[plain if one_word else plain + "*"] = (3 * seeds.get(plain, 0.0) + min(r["gain"], 5.0) * seen) / (3 + seen)
    return chosen


def learn(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, size: int = LEXICON, least: int = LEAST) -> tuple[tuple, tuple]:
    """(lexicon, map) from labelled documents (doc_id, text) and (doc_id, toxic)."""
    prepare(docs.sparkSession)
    marked = labels.where("toxic is not null and doc_id is not null").groupBy("doc_id").agg(F.min("toxic").alias("toxic"), F.max("toxic").alias("most")).where("toxic = most")
    marked = marked.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample).select("doc_id", "toxic")  # bounded by ``sample``


    def one_shingle(texts: pa.Array) -> list[int]:
        """The least shingle hash: equal for copies and, as often as they are similar, for near copies."""
        return [int(s[0] >> np.uint64(1)) if len(s := shingles(t)) else 0 for t in texts.to_pylist()]

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(one_shingle(batch.column(1)), pa.int64())], ["toxic", "text", "key"])

    rows = docs.select("doc_id", "text").join(F.broadcast(marked), "doc_id").select(F.col("toxic").cast("int").alias("toxic"), "text")
    keys = rows.mapInArrow(keyed, "toxic int, text string, key long")
    # copies share the weight of one text, so that a text that is often copied does not make the lexicon
    rows = cut(keys.withColumn("share", 1.0 / F.count(F.lit(1)).over(Window.partitionBy("key", "toxic"))).select("toxic", "text", "share"))

    seeds = {folded(w): v for w, v in SEEDS.items()}
    lexicon: dict[str, float] = dict(seeds)
    lexicon |= _marking_words(rows, seeds, size, least)
    lexicon = tuple(sorted((w, round(v, 6)) for w, v in lexicon.items() if v > 0.2 and (w.endswith("*") or w + "*" not in lexicon)))
    exceptions = EXCEPTIONS

    def weighed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            got = [evidence(t, lexicon, exceptions) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([g[0] for g in got], pa.float64()), pa.array([g[2] for g in got], pa.int64()), batch.column(2)], ["toxic", "weight", "words", "share"])

    fit = rows.mapInArrow(weighed, "toxic int, weight double, words long, share double")
    fit = fit.groupBy("toxic", "weight", "words").agg(F.round(F.sum("share"), 6).alias("share")).orderBy("toxic", "weight", "words").collect()  # numbers of the sampled texts
    return lexicon, calibrate([r["weight"] for r in fit], [r["words"] for r in fit], [r["toxic"] for r in fit], [r["share"] for r in fit])


def score(docs: DataFrame, lexicon: tuple, weights: tuple, exceptions: tuple = EXCEPTIONS) -> DataFrame:
    """All columns of ``docs`` with ``score`` double, ``predicted`` int and ``n_hits`` long (replaced where they exist)."""
    prepare(docs.sparkSession)
    docs = docs.drop("score", "predicted", "n_hits")
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            got = [evidence(t, lexicon, exceptions) for t in batch.column(at).to_pylist()]
            p = 1 / (1 + np.exp(-_features([g[0] for g in got], [g[2] for g in got]) @ np.array(weights)))
            added = [pa.array(p, pa.float64()), pa.array((p >= 0.5).astype(np.int32)), pa.array([g[1] for g in got], pa.int64())]
            yield pa.RecordBatch.from_arrays([*batch.columns, *added], [*batch.schema.names, "score", "predicted", "n_hits"])

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType()), T.StructField("n_hits", T.LongType())]))


def held_out_model(docs: DataFrame, labels: DataFrame, parts: int = 5, part: int = 0) -> tuple[tuple, tuple]:
    """The model of all labelled documents outside one fold of the ids."""
    train = docs.where(fold_of("doc_id", parts) != part)
    return learn(train, labels.where(fold_of("doc_id", parts) != part))
