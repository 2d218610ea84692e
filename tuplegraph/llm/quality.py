"""Document quality by a byte-level convolutional network in numpy.

A document is cut into overlapping chunks of bytes that cover all of it. In each chunk, learned byte vectors go through
learned filters over windows of ``2 * STEP`` bytes, every ``STEP`` bytes; each filter's response is max-pooled over the
chunk. The largest and the mean response over all chunks of the document are combined by a logistic layer into one
probability.

The network is trained on the driver on at most ``sample`` labelled documents of each class (the first by a hash of
their id, one text an id), on every chunk of each, weighted back to the classes' true shares. Scoring reads every chunk of
every document.

Results for odd input: a null or empty text has one chunk without windows and gets the probability of zero responses;
labels that are null or conflict for an id are dropped; without labels of both classes every document gets the share of
good ones (one half without labels); repeated rows give repeated rows; extra columns are kept by ``score``, whose outputs
replace columns of the same name.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import fold, prepare

CHUNK, OVERLAP, STEP, WIDE, FILTERS = 512, 64, 4, 8, 24
SAMPLE, EPOCHS, BATCH, RATE = 1500, 8, 24, 0.004
THRESHOLD = 0.7
BLOCK = 256  # chunks that are scored at once
PAD = 256


def chunks(text: str | None) -> np.ndarray:
    """Byte codes of the chunks of a text, one row each; PAD fills the last."""
    data = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
    step = CHUNK - OVERLAP
    count = max(1, -(-max(0, len(data) - OVERLAP) // step))
    out = np.full((count, CHUNK), PAD, np.int16)
    for k in range(count):
        part = data[k * step : k * step + CHUNK]
        out[k, : len(part)] = part
    return out


def initial(seed: int = 7) -> dict[str, np.ndarray]:
    random = np.random.default_rng(seed)
    return {
        "bytes": random.normal(0, 0.5, (PAD + 1, WIDE)).astype(np.float32),
        "filters": random.normal(0, 0.25, (STEP * WIDE, 2 * FILTERS)).astype(np.float32),
        "bias": np.zeros(FILTERS, np.float32),
        "out": np.zeros(2 * FILTERS + 1, np.float32),
    }


def pooled(net: dict[str, np.ndarray], codes: np.ndarray):
    """Max-pooled responses of each chunk, where each maximum is, and the blocks of byte vectors."""
    n = len(codes)
    blocks = net["bytes"][codes].reshape(n, CHUNK // STEP, STEP * WIDE)
    both = blocks.reshape(-1, STEP * WIDE) @ net["filters"]
    both = both.reshape(n, CHUNK // STEP, 2 * FILTERS)
    answer = both[:, :-1, :FILTERS] + both[:, 1:, FILTERS:]
    started = codes[:, : CHUNK - STEP : STEP] != PAD
    answer[~started] = -1e9
    place = answer.argmax(axis=1)
    top = np.take_along_axis(answer, place[:, None, :], axis=1)[:, 0] + net["bias"]
    return np.maximum(top, 0), place, blocks


def train(texts: list[str], labels: list[int], weights: list[float], epochs: int = EPOCHS, seed: int = 7) -> dict[str, np.ndarray]:
    """Adam on the weighted log loss."""
    net = initial(seed)
    net["bytes"][PAD] = 0
    random = np.random.default_rng(seed)
    data = [chunks(t) for t in texts]
    y, w = np.array(labels, np.float32), np.array(weights, np.float32)
    moment = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in net.items()}
    step = 0
    for epoch in range(epochs):
        order = random.permutation(len(data))
        for at in range(0, len(order), BATCH):
            own = order[at : at + BATCH]
            codes = np.concatenate([data[i] for i in own])
            sizes = np.array([len(data[i]) for i in own])
            starts = np.concatenate(([0], np.cumsum(sizes)[:-1]))
            top, place, blocks = pooled(net, codes)
            most, mean = np.maximum.reduceat(top, starts), np.add.reduceat(top, starts) / sizes[:, None]
            x = np.concatenate([most, mean, np.ones((len(own), 1), np.float32)], axis=1)
            p = 1 / (1 + np.exp(-np.clip(x @ net["out"], -30, 30)))
            error = ((p - y[own]) * w[own] / w[own].sum()).astype(np.float32)
            back = error[:, None] * net["out"][None, :-1]
            owner = np.repeat(np.arange(len(own)), sizes)
            # the maximum over chunks passes its slope to the chunk that has it
            best = top == most[owner]
            slope = back[:, :FILTERS][owner] * best / np.maximum(np.add.reduceat(best.astype(np.float32), starts)[owner], 1) + (back[:, FILTERS:] / sizes[:, None])[owner]
            slope = slope * (top > 0)
            rows = np.arange(len(codes))[:, None]
            first, second = blocks[rows, place], blocks[rows, place + 1]  # chunk, filter, block
            filters = np.concatenate([np.einsum("cf,cfb->bf", slope, first), np.einsum("cf,cfb->bf", slope, second)], axis=1)
            vectors = np.zeros_like(net["bytes"])
            for half, at_block in ((net["filters"][:, :FILTERS], place), (net["filters"][:, FILTERS:], place + 1)):
                into = (slope[:, :, None] * half.T[None]).reshape(-1, STEP, WIDE)
                which = codes.reshape(len(codes), CHUNK // STEP, STEP)[rows, at_block].reshape(-1)
                np.add.at(vectors, which, into.reshape(-1, WIDE))
            vectors[PAD] = 0
            step += 1
            rate = RATE * (0.5 if epoch >= epochs - 2 else 1.0)
            for key, g in (("bytes", vectors), ("filters", filters), ("bias", slope.sum(axis=0)), ("out", x.T @ error + 1e-4 * net["out"])):
                m, v = moment[key]
                m += 0.1 * (g - m)
                v += 0.001 * (g * g - v)
                net[key] -= rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    return net


def probability(net: dict[str, np.ndarray], texts: list[str | None]) -> np.ndarray:
    """One probability for each text; all chunks count, and memory holds BLOCK of them."""
    out, codes, waiting = np.zeros(len(texts)), [], []
    most, total, count = np.zeros((len(texts), FILTERS), np.float32), np.zeros((len(texts), FILTERS), np.float32), np.zeros(len(texts))

    def flush():
        if not codes:
            return
        top, _, _ = pooled(net, np.concatenate(codes))
        owner = np.concatenate(waiting)
        starts = np.flatnonzero(np.concatenate(([True], owner[1:] != owner[:-1])))
        who = owner[starts]
        most[who] = np.maximum(most[who], np.maximum.reduceat(top, starts))
        total[who] += np.add.reduceat(top, starts)
        count[who] += np.diff(np.concatenate((starts, [len(owner)])))
        codes.clear()
        waiting.clear()

    held = 0
    for i, text in enumerate(texts):
        own = chunks(text)
        for at in range(0, len(own), BLOCK):
            codes.append(own[at : at + BLOCK])
            waiting.append(np.full(len(codes[-1]), i))
            held += len(codes[-1])
            if held >= BLOCK:
                flush()
                held = 0
    flush()
    if len(texts):
        x = np.concatenate([most, total / np.maximum(count, 1)[:, None], np.ones((len(texts), 1))], axis=1)
        out = 1 / (1 + np.exp(-np.clip(x @ net["out"], -30, 30)))
    return out


def learn(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, epochs: int = EPOCHS) -> dict[str, np.ndarray]:
    """A network from labelled documents (doc_id, text) and (doc_id, quality)."""
    marked = labels.where("quality is not null and doc_id is not null").groupBy("doc_id").agg(F.min("quality").alias("quality"), F.max("quality").alias("most")).where("quality = most")
    shares = {int(r["quality"]): r["count"] for r in marked.groupBy("quality").count().collect()}
    net = initial()
    if not shares.get(0) or not shares.get(1):
        share = (shares.get(1, 0) + 0.5) / (sum(shares.values()) + 1)
        net["filters"][:] = 0
        net["out"][-1] = np.log(share / (1 - share))
        return net
    picked = None
    for y in (0, 1):
        part = marked.where(F.col("quality") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample).select("doc_id", "quality")
        picked = part if picked is None else picked.union(part)
    # one whole text an id, so at most 2 * sample rows reach the driver
    picked_docs = docs.join(F.broadcast(picked), "doc_id").groupBy("doc_id", "quality").agg(F.min_by(F.struct("text"), F.struct(F.xxhash64("text"), "text")).alias("t"))
    rows = picked_docs.select("doc_id", "quality", F.col("t.text").alias("text")).collect()
    rows.sort(key=lambda r: (r["doc_id"], r["text"] or ""))
    got = {y: sum(r["quality"] == y for r in rows) for y in (0, 1)}
    if not got[0] or not got[1]:
        return net
    weight = {y: shares[y] / sum(shares.values()) * len(rows) / got[y] for y in (0, 1)}
    return train([r["text"] for r in rows], [int(r["quality"]) for r in rows], [weight[r["quality"]] for r in rows], epochs)


def score(docs: DataFrame, net: dict[str, np.ndarray], threshold: float = THRESHOLD) -> DataFrame:
    """All columns of ``docs`` with ``score`` double and ``predicted`` int."""
    prepare(docs.sparkSession)
    docs = docs.drop("score", "predicted")
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            p = probability(net, batch.column(at).to_pylist())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(p, pa.float64()), pa.array((p >= threshold).astype(np.int32))], [*batch.schema.names, "score", "predicted"])

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())]))


def held_out_model(docs: DataFrame, labels: DataFrame, parts: int = 4, part: int = 2) -> dict[str, np.ndarray]:
    """The network of all labelled documents outside one fold of the ids."""
    return learn(docs.where(fold("doc_id", parts) != part), labels.where(fold("doc_id", parts) != part))
