"""The pipeline on small odd documents: who stays, and what the last stage returns."""

import hashlib
import itertools
import math
import re

import numpy as np
import pytest
import regex
from conftest import SF

pytest.importorskip("tuplegraph.llm")
import corpus_pipeline as cp  # noqa: E402
from test_operators import base_spans, shingle_set  # noqa: E402
from tuplegraph.llm import toxicity  # noqa: E402
from tuplegraph.llm.queries import tokenizer_path  # noqa: E402


def test_stages_on_odd_rows(spark):
    item = spark.read.parquet(f"{SF}/benchmark.parquet").first().text
    text = " ".join(f"w{k}" for k in range(50))
    rows = [(1, text), (1, text), (2, text + " more"), (3, None), (4, ""), (5, "you idiot moron scum"), (6, f"in front {item} behind"), (7, "write to a.b@example.com soon please"), (None, "no id but five words here")]
    rows = [(d and 900_000 + d, t) for d, t in rows]  # ids that the table of labels does not have
    docs = spark.createDataFrame([(d, t, "en", "s", len(t or ""), 9) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long, ids int")
    for _, stage in cp.STAGES[:-1]:
        docs = stage(spark, docs, SF)
        assert {"doc_id", "text", "lang", "source", "n_chars"} <= set(docs.columns)
    got = {r.doc_id: r for r in docs.collect()}
    assert len(got) == docs.count() and set(got) == {900_001, 900_003, 900_004, 900_007, None}
    assert "<EMAIL>" in got[900_007].text
    last = cp.STAGES[-1][1](spark, docs, SF)
    assert last.count() == len(got) and {"n_tokens", "ids_sha256"} <= set(last.columns)


def test_empty_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in cp.STAGES:
        docs = stage(spark, docs, SF)
    assert docs.count() == 0


def contaminated(text, items):
    """Some stretch of 16 item tokens, or a whole shorter item, agrees with the text in three quarters, on any diagonal."""
    words = lambda t: [w for w in regex.split(r"[^\p{L}\p{N}]+", (t or "").lower()) if w]
    doc = words(text)
    for item in map(words, items):
        n = len(item)
        if n < 4:
            continue
        width = min(n, 16)
        padded = np.array([""] * n + doc + [""] * n, dtype=object)
        same = np.array([padded[k : len(padded) - n + k + 1] == w for k, w in enumerate(item)], dtype=int)
        sums = np.vstack([np.zeros((1, same.shape[1]), int), same.cumsum(0)])
        if (sums[width:] - sums[:-width]).max() >= math.ceil(0.75 * width):
            return True
    return False


def test_run_against_brute_force(spark):
    table = spark.read.parquet(f"{SF}/documents.parquet")
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    model = toxicity.held_out_model(table.select("doc_id", "text"), labels)
    texts = {r.doc_id: r.text or "" for r in toxicity.score(table, *model).where("score < 0.5").collect()}
    toxic = {r.doc_id for r in labels.where("toxic = 1").collect()}
    # with so few labels only the seed words work (see the README): 4 of 11 toxic documents pass; accuracy is tested at sf0.1
    assert len(set(texts) & toxic) <= 4
    sets = {d: shingle_set(t) for d, t in texts.items()}
    group = {d: d for d in texts}
    for a, b in itertools.combinations(sorted(texts), 2):
        both = len(sets[a] & sets[b])
        if both and 100 * both >= 75 * (len(sets[a]) + len(sets[b]) - both) and group[a] != group[b]:
            low, high = sorted((group[a], group[b]))
            group = {d: low if g == high else g for d, g in group.items()}
    kept = {d for d, g in group.items() if d == g}
    assert len(kept) < len(texts)
    items = [r.text for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    clean = {d for d in kept if not contaminated(texts[d], items)}
    assert len(clean) < len(kept)
    got = {r.doc_id: r for r in cp.run(spark, SF).collect()}
    assert set(got) == clean
    from tokenizers import Tokenizer

    tool = Tokenizer.from_file(tokenizer_path())
    for d, r in got.items():
        assert base_spans(r.text) == ""
        at = 0
        for piece in re.split(r"<[A-Z_]+>", r.text):  # what is left stands in the document, in its order
            at = texts[d].index(piece, at) + len(piece)
        ids = tool.encode(r.text, add_special_tokens=False).ids
        assert r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(tool.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    assert any("<EMAIL>" in r.text for r in got.values())


def test_callers_columns_of_any_name(spark):
    text = " ".join(f"w{k}" for k in range(50))
    names = ["score", "predicted", "n_hits", "digit", "base", "more", "spans", "_id", "id", "th", "carried", "x", "hub", "class_id", "bad_id"]
    rows = [(900_000 + k, f"{text} a.b@example.com {k} " + "y " * k * 40, *[f"{n}-{k}" for n in names]) for k in range(4)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, " + ", ".join(f"{n} string" for n in names))
    done = docs
    for _, stage in cp.STAGES[:-1]:
        done = stage(spark, done, SF)
        assert done.columns == docs.columns
    got = [r.asDict() for r in done.collect()]
    assert got and all(r[n] == f"{n}-{r['doc_id'] - 900_000}" for r in got for n in names)
    assert all("<EMAIL>" in r["text"] for r in got)
