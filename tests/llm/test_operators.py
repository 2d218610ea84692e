"""The text operators on small odd tables, each against a brute-force version or an exact property."""

import hashlib
import itertools
import math
import re
import tempfile
import zlib
from collections import Counter

import numpy as np
import pytest
from conftest import SF
from pyspark.sql import functions as F

pytest.importorskip("tuplegraph.llm")
from tuplegraph.llm import bpe, decontam, near_dup, ngram, order_minhash, pii, quality, queries, repeats, sharding, toxicity  # noqa: E402
from tuplegraph.llm.common import components, fold  # noqa: E402

WORDS = [f"w{k}" for k in range(40)]
LONG = " ".join(WORDS)
ODD = [
    (1, None),
    (2, ""),
    (3, " \t\n"),
    (4, LONG),
    (5, LONG),
    (5, LONG),  # a row again
    (6, LONG.replace("w20", "x20")),
    (7, "one two"),
    (8, "ONE two"),
    (9, "é😀 mail me at a.b@c-d.example.org or +1 (017) 555-7713, 4111 1111 1111 1111, 10.0.0.255 and 10.0.0.256"),
    (None, "a text without id " * 3),
    (10, "ab" * 700),
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", "s", len(t or ""), 0.5) for i, t in ODD]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score double")


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("doc_id = -1")


@pytest.fixture(scope="module")
def labels(spark):
    rows = [(k, k % 2, 1 - k % 2) for k in range(4, 10)] + [(4, 1, 0), (5, None, None), (None, 1, 1)]
    return spark.createDataFrame(rows, "doc_id long, quality int, toxic int")


def shingle_set(t):
    w = (t or "").encode().lower().split()
    return frozenset([tuple(w)] if 0 < len(w) < 5 else [tuple(w[i : i + 5]) for i in range(len(w) - 4)])


def test_near_duplicates(docs, empty):
    got = near_dup.link(docs).collect()
    assert len(got) == len(ODD)
    by = {r.doc_id: r for r in got}
    assert [by[k].component_id for k in (4, 5, 7, 8)] == [4, 4, 7, 7]
    assert by[6].component_id == 4 if len(shingle_set(LONG) & shingle_set(ODD[6][1])) / len(shingle_set(LONG) | shingle_set(ODD[6][1])) >= 0.75 else by[6].component_id == 6
    assert by[2].component_id == 2 and by[2].kept and by[1].n_shingles == 0 and by[None].component_id is None and by[None].kept
    assert near_dup.link(empty).count() == 0


def test_near_duplicates_in_blocks(spark):
    base = [f"v{k}" for k in range(60)]
    rows = [(n, " ".join(base[:n] + [f"q{n}"] + base[n + 1 :])) for n in range(0, 60, 3)] + [(100, "other words that are alone here")]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    whole = {r.doc_id: r.component_id for r in near_dup.link(table).collect()}
    split = {r.doc_id: r.component_id for r in near_dup.link(table, block_shingles=100, block_sets=3).collect()}
    sets = {d: shingle_set(t) for d, t in rows}
    up = {d: d for d, _ in rows}
    for _ in rows:
        for a in sets:
            for b in sets:
                if 4 * len(sets[a] & sets[b]) >= 3 * len(sets[a] | sets[b]):
                    up[a] = up[b] = min(up[a], up[b])
    assert whole == split == up


def test_sketch_estimates():
    a, b = (np.unique(np.random.default_rng(k).integers(0, 2**63, 600).astype(np.uint64)) for k in (1, 2))
    mixed = np.unique(np.concatenate([a[:500], b[:100]]))
    regs = near_dup.registers([a, mixed, a[:300], np.empty(0, np.uint64)])
    assert not regs[3].any()
    assert (near_dup.registers([a[:300], a[300:]]).max(axis=0) == near_dup.registers([a])[0]).mean() > 0.97  # mergeable
    same = (regs[0] == regs[1]).mean()
    assert abs(same - 500 / 700) < 0.15


def test_components(spark):
    links = spark.createDataFrame([(k, k + 1) for k in range(20)] + [(50, 60), (7, 7)], "a long, b long")
    got = {r.node: r.label for r in components(links).collect()}
    assert all(got[k] == 0 for k in range(21)) and got[60] == 50


def test_bpe(docs, empty):
    path = queries.tokenizer_path()
    from tokenizers import Tokenizer

    tool = Tokenizer.from_file(path)
    done = bpe.encode(docs, path)
    assert set(docs.columns) <= set(done.columns)
    for r in done.collect():
        want = tool.encode(r.text or "", add_special_tokens=False).ids
        assert r.ids == want and r.n_tokens == len(want) and r.decoded == tool.decode(want, skip_special_tokens=False)
    assert bpe.decode(done, path, output="again").where("again <> decoded").count() == 0
    assert bpe.encode(empty, path).count() == 0
    codec = bpe.Codec(path)
    for t in ("<|endoftext|> a<|endoftext|><|endo", "aaaa" * 50, "\x1c\x85  x 　y", "it's they'll'd"):
        assert codec.both(t)[0] == tool.encode(t, add_special_tokens=False).ids


BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def luhn(d):
    total = 0
    for i, c in enumerate(reversed(d)):
        v = int(c) * (2 if i % 2 else 1)
        total += v - 9 if v > 9 else v
    return total % 10 == 0


def base_spans(t):
    out = []
    for kind, p in BASE.items():
        for m in re.finditer(p, t or ""):
            d = re.sub("[^0-9]", "", m.group())
            if {"email": lambda: True, "ip": lambda: all(int(x) <= 255 for x in m.group().split(".")), "card": lambda: 13 <= len(d) <= 19 and luhn(d), "phone": lambda: 9 <= len(d) <= 15}[kind]():
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return ",".join(out)


def test_personal_data(spark, docs, empty):
    odd = ["a@b.c_d@e.f", "1.2.3.4.5.6.7.8", "+1 (017) 555-7713 +1+22222222222", "0" * 20000, "a" * 20000, "a@b." * 500, "+1" + " " * 500 + "2", 'token = "9b0b3c6a43eb78aa99cbd7049c572391524f37a8"', "300.1.1.1 001.002.003.0004"]
    table = docs.select("doc_id", "text").unionByName(spark.createDataFrame([(100 + i, t) for i, t in enumerate(odd)], "doc_id long, text string"))
    texts = dict(table.collect())
    for r in pii.report(pii.find(table, keep_text=False)).collect():
        want = base_spans(texts[r.doc_id])
        assert hashlib.sha256(want.encode()).hexdigest() == r.base_sha256, r.doc_id
        assert set(filter(None, want.split(","))) <= set(r.spans.split(","))
    clean = {r.doc_id: r.text for r in pii.redact(pii.find(table)).select("doc_id", "text").collect()}
    assert "<EMAIL>" in clean[9] and "<PHONE>" in clean[9] and "<CARD>" in clean[9] and "<IP>" in clean[9] and "10.0.0.256" in clean[9]
    assert clean[4] == LONG and clean[1] == ""
    assert pii.find(empty).count() == 0


def test_vote_model():
    p = pii.estimate({"card|++++0": 50, "card|0-000": 60, "card|+-0+0": 5})
    assert p["card|++++0"] > 0.9 and p["card|0-000"] < 0.1


def test_decontamination(spark, docs, empty):
    item = " ".join(f"b{k}" for k in range(30))
    changed = item.replace("b7", "z7").replace("b16", "z16").replace("b25", "z25")
    items = spark.createDataFrame([(1, item), (2, "tiny"), (3, "just five short words here"), (4, None), (5, "")], "item_id long, text string")
    rows = docs.select("doc_id", "text").unionByName(spark.createDataFrame([(20, f"x y {item} z"), (21, f"before {changed} after"), (22, " ".join(f"b{k}" for k in range(0, 30, 2))), (23, "so JUST five, short words here!"), (24, " ".join(reversed(item.split())))], "doc_id long, text string"))
    one = {(r.doc_id, r.item_id) for r in decontam.overlaps(rows, items).collect()}
    assert one == {(20, 1), (21, 1), (23, 3)}
    assert {(r.doc_id, r.item_id) for r in decontam.overlaps(rows, items, inline_seeds=0).collect()} == one
    assert decontam.clean(rows, items).count() == rows.count() - 3
    assert decontam.overlaps(empty, items).count() == 0 and decontam.overlaps(docs, items.limit(0)).count() == 0


def test_every_accepted_substitution_has_a_seed(spark):
    rng = np.random.default_rng(5)
    items, rows, want = [], [], set()
    for n in (*range(4, 17), 20, 27):
        item = [f"i{n}x{k}" for k in range(n)]
        items.append((n, " ".join(item)))
        width = min(n, 16)
        wrong = width - math.ceil(width * 0.75)
        patterns = {c for c in itertools.combinations(range(width), wrong)}
        chosen = sorted(patterns) if len(patterns) < 60 else [sorted(patterns)[k] for k in rng.choice(len(patterns), 60, replace=False)]
        more = [tuple(range(3, width, 4))[:wrong], *[tuple(rng.choice(n, max(1, n // 4), replace=False).tolist()) for _ in range(20)]]
        for spoiled in [*chosen, *more, *[(*c, rng.integers(width)) for c in chosen[:10]]]:
            doc = ["x", *[f"z{k}" if k in spoiled else w for k, w in enumerate(item)], "y"]
            same = [doc[k + 1] == w for k, w in enumerate(item)]
            rows.append((len(rows), " ".join(doc)))
            if max(sum(same[a : a + width]) for a in range(n - width + 1)) >= math.ceil(0.75 * width):
                want.add((rows[-1][0], n))
    docs, items = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    for inline in (200_000, 0):
        assert {(r.doc_id, r.item_id) for r in decontam.overlaps(docs, items, inline_seeds=inline).collect()} == want


def test_sharding(docs, empty):
    got = sharding.assign(docs).collect()
    texts = Counter(t or "" for _, t in ODD)
    assert len(got) == len(ODD) and {r.law for r in got} == {"bytes"}
    place = {}
    for r, in [(r,) for r in got]:
        assert r.text_crc32 in {zlib.crc32(t.encode()) for t in texts}
        assert place.setdefault(r.text_crc32, r.shard) == r.shard
    for s in {r.shard for r in got}:
        assert sorted(r.slot for r in got if r.shard == s) == list(range(sum(r.shard == s for r in got)))
    assert sharding.assign(empty).count() == 0


def test_capacity_is_least(spark):
    sizes = np.random.default_rng(3).integers(1, 400, 300).tolist()
    table = spark.createDataFrame([(i, f"{i}:" + "y" * n) for i, n in enumerate(sizes)], "doc_id long, text string")
    rows = table.select(F.xxhash64("text").alias("h"), (F.octet_length("text") + 1).alias("s")).orderBy("h").collect()

    def fits(c):
        shards, used = 1, 0
        for r in rows:
            if r.s > c:
                return False
            if used + r.s > c:
                shards, used = shards + 1, 0
            used += r.s
        return shards <= 8

    assert sharding.plan(table)[0] == next(c for c in range(1, 10**6) if fits(c))


def test_fingerprints(docs, empty):
    got = order_minhash.compare(docs).collect()
    assert len(got) == len(ODD)
    by = {}
    for r in got:
        by.setdefault(r.doc_id, r)
    assert by[4].fingerprint == by[5].fingerprint != by[6].fingerprint and by[1].fingerprint == "" == by[2].fingerprint
    assert by[1].near_next == 1.0 and by[1].edited_sha256 == hashlib.sha256(b"").hexdigest()
    t, n = ODD[6][1], ODD[7][1]  # document 6 and the next one
    half = len(t) // 2
    assert by[6].edited_sha256 == hashlib.sha256((t[: len(t) - half] + n[:half]).encode()).hexdigest()
    assert all(0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1 for r in got)
    assert order_minhash.compare(empty).count() == 0


def test_fingerprint_sees_order_and_repeats(spark):
    a = " ".join(f"w{k}" for k in range(300))
    swapped = " ".join([f"w{k}" for k in range(150, 300)] + [f"w{k}" for k in range(150)])
    rows = spark.createDataFrame([(a, swapped, a + " w0 w1 w2 tail")], "a string, b string, c string")
    f = lambda c: order_minhash.sketches(F.col(c))
    r = rows.select(order_minhash.likeness(f("a"), f("a")).alias("same"), order_minhash.likeness(f("a"), f("b")).alias("swapped"), order_minhash.likeness(f("a"), f("c")).alias("near"), F.size(order_minhash.sketches(F.lit("x y z " * 200))).alias("n")).first()
    assert r.same == 1.0 and r.swapped < r.near and r.n > 30  # repeats are elements of their own


def test_repeats(spark, docs, empty):
    rows = [(i, t) for i, t in ODD if i is not None] + [(30, "Q" * 150 + "ab" * 300), (31, "x" + LONG + LONG), (32, "z" * 199), (33, "é" * 130)]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    want = sorted((d, len((t or "").encode()), *b) for (d, t), b in zip(rows, repeats.brute([(t or "").encode() for _, t in rows]), strict=True))
    for options in ({}, {"hot": 1}, {"task_bytes": 400}):
        got = repeats.digest(repeats.remove(table, **options))
        assert sorted((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got.collect()) == want
    assert repeats.digest(repeats.remove(empty)).count() == 0
    assert repeats.remove(docs).count() == len(ODD)


def test_elias_fano():
    v = np.unique(np.concatenate([np.random.default_rng(1).integers(0, 10**9, 3000), np.arange(400) + 5_000_000])).astype(np.uint64)
    coded = ngram.EliasFano.build(v)
    q = np.sort(np.concatenate([v, v + np.uint64(1), np.array([0, 2**40], np.uint64)]))
    place, found = coded.locate(q)
    assert (place == np.searchsorted(v, q)).all() and (found == np.isin(q, v)).all()
    assert len(coded.low) * 8 + len(coded.up) * 8 < len(v) * 4


def test_language_model(spark, docs, empty):
    table = docs.select("doc_id", "text")
    model = ngram.train(table, shards=3)
    tokens = {d: (t or "").encode().lower().split() + [None] for d, t in ODD}
    counts = Counter(w for _, t in ODD for w in (t or "").encode().lower().split() + [None])
    n, v = sum(counts.values()), len(counts)
    total = 0.0
    for r in ngram.score(table, model).collect():
        own = tokens[r.doc_id]
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(own), len(own), n)
        assert r.base_score == pytest.approx(sum(math.log10((counts[w] + 1) / (n + v + 1)) for w in own))
        total += r.score
        assert r.score <= 0
    fresh = ngram.score(spark.createDataFrame([(1, "never seen")], "doc_id long, text string"), model).first()
    assert fresh.n_known == 1 and fresh.score < 0
    assert ngram.score(empty, model).count() == 0
    none = ngram.train(empty, shards=2)
    assert ngram.score(table, none).where("n_known > 0 or train_tokens > 0").count() == 0


def test_language_model_keeps_trigrams_seen_once(spark):
    table = spark.createDataFrame([(1, "a b c"), (2, "x b d"), (3, "y b d")], "doc_id long, text string")
    text = table.where("doc_id = 1")
    whole, cut = (ngram.score(text, m).first().score for m in (ngram.train(table, shards=2), ngram.train(table, shards=2, keep=2)))
    assert whole > cut + 0.1  # c follows a b, though only once
    for high in (7, 2**33):
        uri = tempfile.mkdtemp()
        columns = [np.array([0, 1, 1]), np.array([9, 6, 300]), np.array([1, high, high])]
        ngram.put_columns(uri, "c", *columns)
        assert [c.tolist() for c in ngram.columns_of(uri, "c")] == [c.tolist() for c in columns]
        ngram.remove(uri, "c")
        assert not ngram.exists(uri, "c")


def test_language_model_against_brute_force(spark, docs):
    """The score is the interpolated model's, but for the rounding of stored values."""
    table = docs.select("doc_id", "text").where("doc_id is not null")
    model = ngram.train(table, shards=3)
    begin, texts = "^", {d: [*(w.decode() for w in (t or "").encode().lower().split()), "$"] for d, t in ODD if d is not None}
    rows = [[*(w.decode() for w in (t or "").encode().lower().split()), "$"] for d, t in ODD if d is not None]
    one, two, three = Counter(w for r in rows for w in r), Counter(), Counter()
    for r in rows:
        two.update(zip([begin, *r], r))
        three.update(zip([begin, *r], r, r[1:]))
    twos, threes = Counter(), Counter()
    for (u, _), n in two.items():
        twos[u, 0] += n
        twos[u, 1] += 1
    for (u, v, _), n in three.items():
        threes[u, v, 0] += n
        threes[u, v, 1] += 1
    off = lambda c: (lambda a, b: a / (a + 2 * b) if a and b else 0.5)(sum(n == 1 for n in c.values()), sum(n == 2 for n in c.values()))
    d1, d2, d3 = off(one), off(two), off(three)
    total = sum(one.values())
    p1 = lambda w: (one[w] - d1) / total
    p2 = lambda u, w: max(two[u, w] - d2, 0) / twos[u, 0] + d2 * twos[u, 1] / twos[u, 0] * p1(w)

    def p3(u, v, w):
        if not threes[u, v, 0]:
            return p2(v, w)
        return max(three[u, v, w] - d3, 0) / two[u, v] + (1 - (threes[u, v, 0] - d3 * threes[u, v, 1]) / two[u, v]) * p2(v, w)

    for r in ngram.score(table, model).collect():
        t = texts[r.doc_id]
        want = sum(math.log10(p2(begin, w) if not k else p3(t[k - 2] if k > 1 else begin, t[k - 1], w)) for k, w in enumerate(t))
        assert r.score == pytest.approx(want, abs=0.05 * len(t)), r.doc_id


def test_toxicity(spark, docs, labels, empty):
    lexicon = tuple((toxicity.folded(w), v) for w, v in toxicity.SEEDS.items())
    hits = lambda t: toxicity.evidence(t, lexicon, toxicity.EXCEPTIONS)[1]
    assert [hits(t) for t in ("you 1d10t", "L0SER!", "$tupid", "mоrоn", "ídiot", "a clown fish", "therapist scumble", "", None)] == [1, 1, 1, 1, 1, 0, 0, 0, 0]
    assert toxicity.evidence("loweist lowei", (("iowei*", 1.0),), ())[1] == 2
    model = toxicity.learn(docs, labels)
    got = toxicity.score(docs, *model).collect()
    assert len(got) == len(ODD) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in got)
    assert toxicity.score(empty, *toxicity.learn(empty, labels)).count() == 0
    assert toxicity.learn(docs, labels.limit(0))[1] == tuple(map(float, toxicity.PRIOR))


def test_quality(spark, docs, labels, empty):
    assert sum(int((c != quality.PAD).sum()) for c in quality.chunks("x" * 1000)) >= 1000
    net = quality.learn(docs, labels)
    got = quality.score(docs, net).collect()
    assert len(got) == len(ODD) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in got)
    assert quality.score(empty, quality.learn(empty, labels.limit(0))).count() == 0
    good, bad = ["plain words make a line of text " * 4] * 60, ["x%%% y&&& z$$$ q*** " * 6] * 60
    net = quality.train(good + bad, [1] * 60 + [0] * 60, [1.0] * 120, epochs=4)
    p = quality.probability(net, [good[0], bad[0], ""])
    assert p[0] > 0.7 > 0.5 > p[1]


def slow_probability(net, text):
    """The network's formula, window by window."""
    data = list((text or "").encode())
    tops = []
    for start in range(0, max(1, len(data) - quality.OVERLAP), quality.CHUNK - quality.OVERLAP):
        part = data[start : start + quality.CHUNK]
        codes = part + [quality.PAD] * (quality.CHUNK - len(part))
        best = np.full(quality.FILTERS, -1e9, np.float32)
        for at in range(0, quality.CHUNK - quality.STEP, quality.STEP):
            if at < len(part):
                first, second = (np.concatenate([net["bytes"][c] for c in codes[p : p + quality.STEP]]) for p in (at, at + quality.STEP))
                best = np.maximum(best, first @ net["filters"][:, : quality.FILTERS] + second @ net["filters"][:, quality.FILTERS :])
        tops.append(np.maximum(best + net["bias"], 0))
    x = np.concatenate([np.max(tops, axis=0), np.mean(tops, axis=0), [1.0]])
    return 1 / (1 + np.exp(-(x @ net["out"])))


def test_quality_against_loops():
    rng = np.random.default_rng(2)
    net = quality.initial()
    net["out"] = rng.normal(0, 0.3, len(net["out"])).astype(np.float32)
    texts = ["", "short", "plain words " * 30, "é" * 1500, "".join(chr(c) for c in rng.integers(32, 126, 5000))]
    assert quality.probability(net, texts) == pytest.approx([slow_probability(net, t) for t in texts], abs=1e-4)


def test_fingerprints_against_brute_force(spark):
    """Registers of order MinHash are the same for texts with the same numbered k-mers in the same order, long ones too."""
    long = " ".join(f"w{k % 50}" for k in range(5000))
    rows = [(1, long), (2, long), (3, long.replace("w7 ", "q ")), (4, "a b c d e f"), (5, "f e d c b a")]
    got = {r.doc_id: r for r in order_minhash.compare(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1].fingerprint == got[2].fingerprint and got[1].near_next == 1.0
    assert got[2].near_next < 1.0 and got[4].near_next < 1.0
    for k, (d, t) in enumerate(rows):
        nxt, half = rows[(k + 1) % len(rows)][1], len(t) // 2
        assert got[d].edited_sha256 == hashlib.sha256((t[: len(t) - half] + nxt[:half]).encode()).hexdigest() and got[d].n_chars == len(t)


@pytest.mark.parametrize(("operator", "column", "parts", "part", "least"), [(toxicity, "toxic", 5, 0, 0.93), (quality, "quality", 4, 2, 0.8)])
def test_held_out_accuracy(spark, operator, column, parts, part, least):
    """On the fold that was not learned from."""
    docs = spark.read.parquet(f"{SF.replace('0.001', '0.1')}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{SF.replace('0.001', '0.1')}/labels.parquet")
    model = operator.held_out_model(docs, labels)
    args = model if operator is toxicity else (model,)
    rows = operator.score(docs.where(fold("doc_id", parts) == part), *args).join(labels.where(f"{column} is not null"), "doc_id").select("predicted", column).collect()
    right = np.mean([r.predicted == r[column] for r in rows])
    print(operator.__name__, len(rows), round(right, 4))
    assert len(rows) > 500 and right > least
