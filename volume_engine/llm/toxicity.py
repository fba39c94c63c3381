"""Toxicity by a factorization machine over hashed terms.

Terms are the distinct lower-cased words of a text, their prefixes of four to seven letters and a
term for the text's length class, hashed into 2^20 slots; a term's value is ln(1 + its count).
Besides a weight per term the machine learns a short vector per term, and every pair of terms
interacts through the product of their vectors, so that an insult next to a group mention, or a
single hit in a very long text, can count for more or less than the sum of its parts.

The model is fitted on a bounded sample of the labelled rows (``positives`` and ``negatives``, by
hash of doc_id) whose labels may be learned from; scoring covers every whole text.

Defined results: null, blank and letterless texts have only the length term and still get a score;
equal texts score equally; rows that repeat stay; without labels of both kinds every score is the
share of toxic labels (0 if there are none); an empty table gives an empty result.  Labels, language,
source and doc_id are never inputs of a score.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import _BASE, _BASE_INV, _BYTE_CODE, _power_table, crc_bucket, mix64, text_batches

SLOT_BITS = 20
PREFIXES = (4, 5, 6, 7)
SLICE = 1 << 20
_LETTER = np.zeros(256, dtype=bool)
_LETTER[np.r_[65:91, 97:123, 128:256]] = True


def terms(batch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document, slot and count of every distinct term of the batch, in document order.

    Letters are ASCII letters and all bytes of multi-byte characters; A-Z are lowered and the
    two-byte Latin capitals (second byte 0x80-0x9E after 0xC3) too.
    """
    data = batch.data.copy()
    latin = np.flatnonzero((data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E)) + 1 if len(data) else np.zeros(0, int)
    data[latin] += 32
    solid = _LETTER[data]
    edge = np.ones(len(solid) + 1, dtype=bool)
    edge[1:-1] = solid[1:] != solid[:-1]
    edge[batch.bounds] = True
    cuts = np.flatnonzero(edge)
    starts, ends = (cuts[:-1], cuts[1:]) if len(solid) else (cuts[:0], cuts[:0])
    keep = solid[starts] if len(solid) else np.zeros(0, bool)
    starts, ends = starts[keep], ends[keep]
    counts = np.diff(np.searchsorted(starts, batch.bounds))
    doc = np.repeat(np.arange(batch.n), counts)
    sums = np.zeros(len(data) + 1, dtype=np.uint64)
    np.cumsum(_BYTE_CODE[data] * _power_table(_BASE, len(data))[: len(data)], out=sums[1:])
    inverse = _power_table(_BASE_INV, len(data) + 1)
    # prefixes are cut at characters: count the bytes that do not continue one
    heads = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
    head_at = np.append(np.flatnonzero((data & 0xC0) != 0x80), len(data))
    docs, slots = [], []
    for length in (*PREFIXES, None):
        if length is None:
            s, e, d, kind = starts, ends, doc, 0
        else:
            long_enough = heads[ends] - heads[starts] > length
            s, d, kind = starts[long_enough], doc[long_enough], length
            e = head_at[heads[s] + length]
        key = mix64((sums[e] - sums[s]) * inverse[s] + np.uint64(kind))
        docs.append(d)
        slots.append((key >> np.uint64(64 - SLOT_BITS)).astype(np.int64))
    size = (1 << SLOT_BITS) + np.minimum(np.floor(np.log2(1 + counts)).astype(np.int64), 31)
    docs.append(np.arange(batch.n))
    slots.append(size)
    doc, slot = np.concatenate(docs), np.concatenate(slots)
    codes, pair = pd.factorize(doc * (1 << (SLOT_BITS + 1)) + slot)
    tally = np.bincount(codes, minlength=len(pair))
    order = np.argsort(pair, kind="stable")
    return pair[order] >> (SLOT_BITS + 1), pair[order] & ((1 << (SLOT_BITS + 1)) - 1), tally[order]


@dataclass(frozen=True)
class Machine:
    """``slots`` are the kept term slots, sorted; ``weights`` and ``vectors`` go with them."""

    bias: float
    slots: np.ndarray
    weights: np.ndarray
    vectors: np.ndarray

    def margins(self, doc: np.ndarray, slot: np.ndarray, count: np.ndarray, n: int) -> np.ndarray:
        out = np.full(n, self.bias)
        if not len(self.slots):
            return out
        at = np.minimum(np.searchsorted(self.slots, slot), len(self.slots) - 1)
        known = self.slots[at] == slot
        at, doc, value = at[known], doc[known], np.log1p(count[known])
        out += np.bincount(doc, self.weights[at] * value, n)
        for f in range(self.vectors.shape[1]):
            part = self.vectors[at, f] * value
            out += 0.5 * (np.bincount(doc, part, n) ** 2 - np.bincount(doc, part * part, n))
        return out


def select(doc, slot, labels, most: int, least_docs: int) -> np.ndarray:
    """The ``most`` slots whose presence separates the labels best, among those in ``least_docs`` texts or more."""
    names, at = np.unique(slot, return_inverse=True)
    toxic = np.bincount(at, labels[doc], len(names))
    all_docs = np.bincount(at, minlength=len(names))
    n1, n0 = labels.sum(), len(labels) - labels.sum()
    p1, p0 = (toxic + 0.5) / (n1 + 1), (all_docs - toxic + 0.5) / (n0 + 1)
    z = np.abs(p1 - p0) / np.sqrt(p1 * (1 - p1) / n1 + p0 * (1 - p0) / n0)
    z[all_docs < least_docs] = -1
    length = names >= 1 << SLOT_BITS
    z[length] = np.inf
    best = np.argsort(-z, kind="stable")[:most]
    return np.sort(names[best[z[best] > 1.5]])


def fit(doc, slot, count, labels, share: float, factors: int = 4, most: int = 4096, least_docs: int = 4, epochs: int = 30, rate: float = 0.03, decay: float = 2e-4, seed: int = 7) -> Machine:
    """Fit on terms in document order; ``share`` is the share of toxic labels before sampling."""
    n = len(labels)
    kept = select(doc, slot, labels, most, least_docs)
    at = np.minimum(np.searchsorted(kept, slot), max(len(kept) - 1, 0))
    known = kept[at] == slot if len(kept) else np.zeros(len(slot), bool)
    doc, at, value = doc[known], at[known], np.log1p(count[known])
    begin = np.searchsorted(doc, np.arange(n + 1))
    rng = np.random.RandomState(seed)
    theta = np.zeros((len(kept) + 1, factors + 1))
    theta[:-1, 1:] = rng.normal(0, 0.01, (len(kept), factors))
    prior = math.log(labels.mean() / (1 - labels.mean()))
    theta[-1, 0] = prior
    first, second = np.zeros_like(theta), np.zeros_like(theta)
    step = 0
    for epoch in range(epochs):
        for rows in np.array_split(rng.permutation(n), max(1, n // 256)):
            step += 1
            size = begin[rows + 1] - begin[rows]
            where = np.repeat(begin[rows] - (np.cumsum(size) - size), size) + np.arange(size.sum())
            owner, term, x = np.repeat(np.arange(len(rows)), size), at[where], value[where]
            v = theta[term, 1:] * x[:, None]
            sums = np.stack([np.bincount(owner, v[:, f], len(rows)) for f in range(factors)], axis=1)
            squares = np.bincount(owner, (v * v).sum(axis=1), len(rows))
            margin = theta[-1, 0] + np.bincount(owner, theta[term, 0] * x, len(rows)) + 0.5 * ((sums**2).sum(axis=1) - squares)
            error = 1 / (1 + np.exp(-np.clip(margin, -30, 30))) - labels[rows]
            gradient = np.zeros_like(theta)
            scaled = error[owner] * x
            gradient[:-1, 0] = np.bincount(term, scaled, len(kept))
            pulls = scaled[:, None] * (sums[owner] - v)
            for f in range(factors):
                gradient[:-1, f + 1] = np.bincount(term, pulls[:, f], len(kept))
            gradient[-1, 0] = error.sum()
            gradient = gradient / len(rows) + decay * np.r_[theta[:-1], np.zeros((1, factors + 1))]
            first = 0.9 * first + 0.1 * gradient
            second = 0.999 * second + 0.001 * gradient**2
            move = rate * (1 - epoch / epochs) * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.999**step)) + 1e-8)
            theta -= move
    # the sample holds more toxic texts than the corpus: put the prior back
    bias = theta[-1, 0] + math.log(share / (1 - share)) - prior
    return Machine(bias, kept, theta[:-1, 0].copy(), theta[:-1, 1:].copy())


def _term_rows(batches):
    for batch in batches:
        for first, texts in text_batches(batch["text"], SLICE):
            doc, slot, count = terms(texts)
            begin = np.searchsorted(doc, np.arange(texts.n + 1)).astype(np.int32)
            yield pa.record_batch({
                "label": batch["label"].slice(first, texts.n),
                "slots": pa.ListArray.from_arrays(pa.array(begin), pa.array(slot.astype(np.int32))),
                "counts": pa.ListArray.from_arrays(pa.array(begin), pa.array(count.astype(np.int32))),
            })


def learn(docs: DataFrame, labels: DataFrame, positives: int = 3000, negatives: int = 5000) -> Machine:
    """Fit on at most ``positives`` + ``negatives`` rows of ``docs`` joined with ``labels`` (doc_id, label 0/1), drawn by hash."""
    usable = labels.filter("label is not null").groupBy("doc_id").agg(F.max("label").alias("label"))
    totals = {r["label"]: r["count"] for r in usable.groupBy("label").count().collect()}
    n1, n0 = totals.get(1, 0), totals.get(0, 0)
    share = n1 / (n1 + n0) if n1 + n0 else 0.0
    if not n1 or not n0:
        return Machine(30.0 if n1 else -30.0, np.zeros(0, np.int64), np.zeros(0), np.zeros((0, 1)))
    draw = [usable.filter(F.col("label") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most) for y, most in ((1, positives), (0, negatives))]
    sample = F.broadcast(draw[0].unionByName(draw[1]))
    drawn = docs.join(sample, "doc_id").select("text", "label").mapInArrow(_term_rows, "label int, slots array<int>, counts array<int>")
    table = drawn.toArrow().sort_by("label")
    sizes = pc.list_value_length(table["slots"]).to_numpy()
    doc = np.repeat(np.arange(table.num_rows), sizes)
    slot, count = (pc.list_flatten(table[k]).to_numpy().astype(np.int64) for k in ("slots", "counts"))
    y = table["label"].to_numpy().astype(float)
    if not 0 < y.sum() < len(y):
        return Machine(math.log(share / (1 - share)), np.zeros(0, np.int64), np.zeros(0), np.zeros((0, 1)))
    return fit(doc, slot, count, y, share)


def _scores(model):
    def run(batches):
        machine = Machine(*model.value)
        for batch in batches:
            for first, texts in text_batches(batch["text"], SLICE):
                doc, slot, count = terms(texts)
                score = 1 / (1 + np.exp(-np.clip(machine.margins(doc, slot, count, texts.n), -30, 30)))
                yield pa.record_batch({"doc_id": batch["doc_id"].slice(first, texts.n), "held_out": batch["held_out"].slice(first, texts.n), "score": pa.array(score)})

    return run


def score_toxicity(docs: DataFrame, labels: DataFrame, held_out, positives: int = 3000, negatives: int = 5000) -> DataFrame:
    """doc_id, held_out, score and predicted of every row of ``docs`` (doc_id, text); learns outside ``held_out`` only."""
    docs, labels = docs.select("doc_id", "text"), labels.select("doc_id", "label")
    fitted = learn(docs, labels.filter(~held_out), positives, negatives)
    # broadcast as plain values: executors need no copy of this package to read them
    model = docs.sparkSession.sparkContext.broadcast((fitted.bias, fitted.slots, fitted.weights, fitted.vectors))
    scored = docs.select("doc_id", "text", held_out.alias("held_out")).mapInArrow(_scores(model), "doc_id long, held_out boolean, score double")
    return scored.withColumn("predicted", F.when(F.col("score") >= 0.5, 1).otherwise(0))


def op9_factorization_toxicity(spark, sf_dir) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", F.col("toxic").alias("label"))
    return score_toxicity(docs, labels, crc_bucket("doc_id", 5) == 0)
