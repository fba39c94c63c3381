"""Context-tree weighting over bytes, learned and applied with distributed context tables.

A text is read as its words (A-Z lowered) joined by one space and closed by one end byte, so a
probability of the byte sequence is a probability of the word sequence.  Every byte is coded as
eight binary decisions; each decision, under each of the contexts of 0 to ``depth`` preceding
bytes, has a Krichevsky-Trofimov estimate from the training texts, and the estimates of all depths
are mixed with the context tree's own posterior weights.  A context that training never showed
ends the mixture at the deepest context that it did show, so unseen contexts cost no blind bits.

Layout: texts are dealt into blocks; a block sends each distinct (context, byte) gram and each
distinct word once, with its training count.  Grams are summed, weighted within the subtree of
their last three context bytes, and sent back to the blocks that hold them; words likewise.  No table
of the corpus is collected or broadcast except the top of the tree: the nodes of contexts of at most
two bytes, of which there are no more than 256 * 256 * 255 whatever the corpus.

Defined results: a null text is empty; an empty text is its end alone and is still scored; equal
texts score equally; an empty table gives an empty result; with no training text every estimate is
one half and the unigram base is that of an empty vocabulary.  Extra columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import _IS_SPACE, TextBatch, crc_bucket, materialise, scan_bytes, text_batches

DEPTH = 5
SUBTREE = 3  # context bytes that name a subtree
END = 10
SLICE = 1 << 20  # bytes of text worked on at once
LOG_HALF = math.log(0.5)
#: Words and grams share the tables; the end token's own fingerprint.
END_WORD = np.uint64(0x51ED270B0A1CE5D3)


def normal_bytes(batch: TextBatch) -> tuple[np.ndarray, np.ndarray]:
    """The batch's texts as words joined by one space, each closed by the end byte; and their lengths."""
    n = batch.n
    tail = batch.bounds[1:] + np.arange(n)  # a blank is put after each text
    body = np.ones(len(batch.data) + n, dtype=bool)
    body[tail] = False
    wide = np.full(len(body), 32, dtype=np.uint8)
    wide[body] = batch.data
    solid = ~_IS_SPACE[wide]
    wide[~solid] = 32
    keep = solid.copy()
    keep[1:] |= solid[:-1]
    _, _, counts = batch.words()
    keep[tail[counts == 0]] = True
    lengths = np.diff(np.concatenate([[0], np.cumsum(keep, dtype=np.int64)[tail]]))
    out = wide[keep]
    out[np.cumsum(lengths) - 1] = END
    return out, lengths


def gram_keys(batch: TextBatch, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """One key per byte: the nearest context byte on top, the coded byte lowest."""
    data, lengths = normal_bytes(batch)
    first = np.cumsum(lengths) - lengths
    cells = np.zeros((len(data), 8), dtype=np.uint8)  # little-endian 64-bit keys
    cells[:, 0] = data
    for j in range(1, depth + 1):
        place = depth + 1 - j
        cells[j:, place] = data[:-j]
        for r in range(j):
            cells[(first + r)[lengths > r], place] = END
    return cells.reshape(-1).view("<u8"), lengths


def log_gamma(x: np.ndarray) -> np.ndarray:
    """ln of the gamma function for x >= 0.5 (shifted Stirling series)."""
    z = x + 7.0
    series = (z - 0.5) * np.log(z) - z + 0.9189385332046727 + 1 / (12 * z) - 1 / (360 * z**3) + 1 / (1260 * z**5)
    product = x * (x + 1) * (x + 2) * (x + 3) * (x + 4) * (x + 5) * (x + 6)
    return series - np.log(product)


_half_gamma = log_gamma(np.arange(4096) + 0.5)
_full_gamma = log_gamma(np.arange(8192) + 1.0)


def log_kt(n0: np.ndarray, n1: np.ndarray) -> np.ndarray:
    """ln of the Krichevsky-Trofimov probability of a sequence with those counts."""
    out = log_gamma(n0 + 0.5) + log_gamma(n1 + 0.5) - log_gamma(n0 + n1 + 1.0) - math.log(math.pi) if max(n0.max(initial=0), n1.max(initial=0)) >= 4096 else None
    if out is None:
        out = _half_gamma[n0.astype(np.int64)] + _half_gamma[n1.astype(np.int64)] - _full_gamma[(n0 + n1).astype(np.int64)] - math.log(math.pi)
    return out


class Nodes:
    """Binary nodes of one depth and bit: sorted ids (context << 8 | prefix), counts and ln evidence."""

    def __init__(self, ids, n0, n1):
        self.ids, self.n0, self.n1 = ids, n0, n1
        self.kt = log_kt(n0, n1)
        self.weighted = self.kt
        self.stop = np.ones(len(ids))

    def mix(self, children: np.ndarray) -> None:
        self.weighted = np.logaddexp(LOG_HALF + self.kt, LOG_HALF + children)
        self.stop = np.exp(LOG_HALF + self.kt - self.weighted)

    @classmethod
    def ready(cls, ids, n0, n1, stop) -> Nodes:
        """Nodes that are only looked up, from their plain arrays."""
        out = cls.__new__(cls)
        out.ids, out.n0, out.n1, out.stop = ids, n0, n1, stop
        return out

    def lookup(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(self.ids):
            return np.zeros(len(ids), np.int64), np.zeros(len(ids), bool)
        at = np.minimum(np.searchsorted(self.ids, ids), len(self.ids) - 1)
        return at, self.ids[at] == ids


def nodes_of(ctx_sym: np.ndarray, counts: np.ndarray, bit: int) -> Nodes:
    """Nodes of ``bit`` from sorted (context << 8 | byte) grams."""
    if not len(ctx_sym):
        return Nodes(ctx_sym, counts, counts)
    ids = node_ids(ctx_sym, bit)
    one = ((ctx_sym >> np.uint64(7 - bit)) & np.uint64(1)).astype(bool)
    at = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
    return Nodes(ids[at], np.add.reduceat(np.where(one, 0.0, counts), at), np.add.reduceat(np.where(one, counts, 0.0), at))


def node_ids(ctx_sym: np.ndarray, bit: int) -> np.ndarray:
    sym = ctx_sym & np.uint64(255)
    return (ctx_sym ^ sym) | (sym >> np.uint64(8 - bit)) | np.uint64(1 << bit)


def shorten(keys: np.ndarray, depth: int, to: int) -> np.ndarray:
    """(context of ``to`` bytes << 8 | byte) of each gram key."""
    sym = keys & np.uint64(255)
    return (keys >> np.uint64(8 * (depth - to) + 8) << np.uint64(8)) | sym


def parent_ids(ids: np.ndarray) -> np.ndarray:
    return (ids >> np.uint64(16) << np.uint64(8)) | (ids & np.uint64(255))


def build(keys: np.ndarray, counts: np.ndarray, depth: int, top: int) -> list[list[Nodes]]:
    """Weighted nodes of depths ``top`` to ``depth`` for sorted distinct grams with training counts."""
    seen = counts > 0
    keys, counts = keys[seen], counts[seen].astype(float)
    levels: list[list[Nodes]] = []
    below: list[Nodes] | None = None
    for d in range(depth, top - 1, -1):
        short = shorten(keys, depth, d)
        if d < depth:
            order = np.argsort(short, kind="stable")
            short, sized = short[order], counts[order]
            at = np.flatnonzero(np.r_[True, short[1:] != short[:-1]]) if len(short) else np.zeros(0, np.int64)
            short, sized = short[at], np.add.reduceat(sized, at) if len(at) else sized[:0]
        else:
            sized = counts
        level = [nodes_of(short, sized, bit) for bit in range(8)]
        if below is not None:
            for own, child in zip(level, below, strict=True):
                at, _ = own.lookup(parent_ids(child.ids))
                own.mix(np.bincount(at, weights=child.weighted, minlength=len(own.ids)))
        levels.append(level)
        below = level
    return levels


def predict(keys: np.ndarray, depth: int, top: int, levels: list[list[Nodes]], upper: list[list[Nodes]]) -> np.ndarray:
    """ln probability of each gram's byte after its context; ``upper`` holds depths top - 1 to 0."""
    total = np.zeros(len(keys))
    for bit in range(8):
        one = ((keys >> np.uint64(7 - bit)) & np.uint64(1)).astype(bool)
        p = np.full(len(keys), 0.5)
        have = np.zeros(len(keys), dtype=bool)
        for d, level in zip(range(depth, -1, -1), [*levels, *upper], strict=True):
            nodes = level[bit]
            at, found = nodes.lookup(node_ids(shorten(keys, depth, d), bit))
            if not found.any():
                continue
            at = at[found]
            n0, n1 = nodes.n0[at], nodes.n1[at]
            kt = (np.where(one[found], n1, n0) + 0.5) / (n0 + n1 + 1.0)
            stop = np.where(have[found], nodes.stop[at], 1.0)
            p[found] = stop * kt + (1 - stop) * p[found]
            have |= found
        total += np.log(p)
    return total


def whole_model(keys: np.ndarray, counts: np.ndarray, depth: int) -> np.ndarray:
    """The undistributed form: ln probability of every gram of a sorted table (brute force for tests)."""
    return predict(keys, depth, 0, build(keys, counts, depth, 0), [])


SIGN = np.uint64(1 << 63)  # set on word keys, clear on gram keys


def _merge(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    if not keys:
        return np.zeros(0, np.uint64), np.zeros(0)
    k, c = np.concatenate(keys), np.concatenate(counts)
    order = np.argsort(k, kind="stable")
    k, c = k[order], c[order]
    at = np.flatnonzero(np.r_[True, k[1:] != k[:-1]])
    return k[at], np.add.reduceat(c, at)


def _word_keys(batch: TextBatch) -> tuple[np.ndarray, np.ndarray]:
    """Word fingerprints followed by one end token per document, and the document of each."""
    starts, ends, counts = batch.words()
    words = np.concatenate([batch.fingerprints(starts, ends), np.full(batch.n, END_WORD)]) | SIGN
    return words, np.concatenate([np.repeat(np.arange(batch.n), counts), np.arange(batch.n)])


def _distinct(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    codes, seen = pd.factorize(keys)
    return codes, seen.astype(np.uint64)


def _block_tokens(depth: int):
    def run(table: pa.Table) -> pa.Table:
        block = table["block"][0].as_py()
        trains = (~table["held_out"].to_numpy()).astype(float)
        keys, counts = [], []
        for first, batch in text_batches(table["text"], SLICE):
            grams, lengths = gram_keys(batch, depth)
            words, word_doc = _word_keys(batch)
            for values, docs in ((grams, np.repeat(np.arange(batch.n), lengths)), (words, word_doc)):
                codes, seen = _distinct(values)
                keys.append(seen)
                counts.append(np.bincount(codes, weights=trains[first + docs], minlength=len(seen)))
            if len(keys) >= 16:  # keep the pending slices small
                merged = _merge(keys, counts)
                keys, counts = [merged[0]], [merged[1]]
        k, c = _merge(keys, counts)
        return pa.table({"block": np.full(len(k), block, np.int32), "key": k.view(np.int64), "n": c.astype(np.int64)})

    return run


def _upper_rows(depth: int):
    def run(table: pa.Table) -> pa.Table:
        keys, counts = _merge([table["key"].to_numpy().astype(np.uint64)], [table["n"].to_numpy().astype(float)])
        top = build(keys, counts, depth, SUBTREE)[-1]
        parts = {name: np.concatenate([getattr(level, name) for level in top]) for name in ("ids", "n0", "n1", "weighted")}
        bit = np.repeat(np.arange(8), [len(level.ids) for level in top])
        return pa.table({"bit": bit.astype(np.int32), "id": parts["ids"].astype(np.int64), "n0": parts["n0"], "n1": parts["n1"], "weighted": parts["weighted"]})

    return run


def _upper_levels(rows: pd.DataFrame) -> list[list[Nodes]]:
    """Depths SUBTREE - 1 to 0 from the sums (bit, id, n0, n1, weighted) over the subtree roots below each node of the first of them."""
    below = []
    for bit in range(8):
        part = rows[rows.bit == bit].sort_values("id")
        level = Nodes(part.id.to_numpy().astype(np.uint64), part.n0.to_numpy(float), part.n1.to_numpy(float))
        level.mix(part.weighted.to_numpy(float))
        below.append(level)
    out = [below]
    for _ in range(SUBTREE - 1):
        level = []
        for child in below:
            ids, back = np.unique(parent_ids(child.ids), return_inverse=True)
            own = Nodes(ids, np.bincount(back, child.n0, len(ids)), np.bincount(back, child.n1, len(ids)))
            own.mix(np.bincount(back, child.weighted, len(ids)))
            level.append(own)
        out.append(level)
        below = level
    return out


def _gram_scores(depth: int, upper):
    def run(table: pa.Table) -> pa.Table:
        keys, counts = _merge([table["key"].to_numpy().astype(np.uint64)], [table["n"].to_numpy().astype(float)])
        values = predict(keys, depth, SUBTREE, build(keys, counts, depth, SUBTREE), [[Nodes.ready(*plain) for plain in level] for level in upper.value])
        return pa.table({"key": keys.astype(np.int64), "value": values})

    return run


def _block_scores(depth: int, total: int, vocabulary: int):
    rest = math.log10(total + 0.5 * (vocabulary + 1))

    def run(docs: pa.Table, known: pa.Table) -> pa.Table:
        keys = known["key"].to_numpy().view(np.uint64)
        order = np.argsort(keys)
        keys, values = keys[order], known["value"].to_numpy()[order]
        out = {c: [] for c in ("n_tokens", "n_known", "n_bytes", "base_score", "score")}
        for _, batch in text_batches(docs["text"], SLICE):
            grams, lengths = gram_keys(batch, depth)
            codes, seen = _distinct(grams)
            out["score"].append(np.bincount(np.repeat(np.arange(batch.n), lengths), values[np.searchsorted(keys, seen)][codes], batch.n) / math.log(10))
            words, doc = _word_keys(batch)
            codes, seen = _distinct(words)
            count = values[np.searchsorted(keys, seen)]
            out["base_score"].append(np.bincount(doc, (np.log10(count + 0.5) - rest)[codes], batch.n))
            out["n_known"].append(np.bincount(doc, (count > 0)[codes], batch.n).astype(np.int64))
            out["n_tokens"].append(np.bincount(doc, minlength=batch.n).astype(np.int64))
            out["n_bytes"].append(lengths)
        columns = {c: np.concatenate(v) for c, v in out.items()}
        return pa.table({"doc_id": docs["doc_id"], "held_out": docs["held_out"], **columns})

    return run


def score_texts(docs: DataFrame, held_out, depth: int = DEPTH, block_bytes: int = 16 << 20, least_blocks: int = 12, bucket_grams: int = 500_000) -> DataFrame:
    """Score every text of ``docs`` (doc_id, text) by a context tree learned from the rows outside ``held_out``.

    ``held_out`` is a boolean column expression, ``depth`` at most 6 (a key holds the context and the coded
    byte in 63 bits).  Returns doc_id, held_out, n_tokens, n_known,
    n_bytes, train_tokens, base_score (add-half unigram, log10), score (context tree, log10) and
    bits_per_byte, the tree's code length per byte.
    """
    if not SUBTREE <= depth <= 6:
        raise ValueError(f"depth must be from {SUBTREE} to 6")
    spark = docs.sparkSession
    if not docs.inputFiles():  # only tables in files have a known size
        docs = materialise(docs.select("doc_id", "text"), "ctw-docs")
    # files may be packed tighter than texts are long: both bound what a block holds
    chars = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(least_blocks, -(-scan_bytes(docs) // block_bytes), -(-chars // (3 * block_bytes)))
    dealt = docs.select("doc_id", F.col("text"), held_out.alias("held_out"), F.pmod(F.xxhash64("doc_id"), F.lit(blocks)).cast("int").alias("block"))
    tokens = materialise(dealt.groupBy("block").applyInArrow(_block_tokens(depth), "block int, key long, n long"), "ctw-tokens")
    totals = materialise(tokens.groupBy("key").agg(F.sum("n").alias("n")), "ctw-totals")
    words, grams = totals.filter("key < 0"), totals.filter("key >= 0")
    total, vocabulary, n_grams = totals.agg(*(F.coalesce(x, F.lit(0)) for x in (F.sum(F.expr("if(key < 0, n, 0)")), F.count_if(F.expr("key < 0 and n > 0")), F.count_if(F.expr("key >= 0"))))).first()
    # whole subtrees of the last context bytes are weighted together, several of them at a time
    buckets = max(4 * least_blocks, -(-n_grams // bucket_grams))
    subtree = F.shiftright("key", 8 * (depth + 1 - SUBTREE))
    by_subtree = grams.withColumn("bucket", F.pmod(F.xxhash64(subtree), F.lit(buckets)).cast("int")).groupBy("bucket")
    roots = by_subtree.applyInArrow(_upper_rows(depth), "bit int, id long, n0 double, n1 double, weighted double")
    above = roots.groupBy("bit", F.expr("shiftleft(shiftright(id, 16), 8) | (id & 255)").alias("id")).agg(*(F.sum(k).alias(k) for k in ("n0", "n1", "weighted")))
    # at most 256^2 contexts of 255 nodes, whatever the corpus: the driver may hold them
    # broadcast as plain arrays: executors need no copy of this package to read them
    upper = spark.sparkContext.broadcast([[(n.ids, n.n0, n.n1, n.stop) for n in level] for level in _upper_levels(above.toPandas())])
    model = by_subtree.applyInArrow(_gram_scores(depth, upper), "key long, value double").unionByName(words.select("key", F.col("n").cast("double").alias("value")))
    known = tokens.select("block", "key").join(model, "key").select("block", "key", "value")
    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, n_bytes long, base_score double, score double"
    scored = dealt.groupBy("block").cogroup(known.groupBy("block")).applyInArrow(_block_scores(depth, total, vocabulary), schema)
    bits = -F.col("score") * F.lit(math.log2(10)) / F.col("n_bytes")
    return scored.select("doc_id", "held_out", "n_tokens", "n_known", "n_bytes", F.lit(total).cast("long").alias("train_tokens"), "base_score", "score", bits.alias("bits_per_byte"))


def op2_context_tree_score(spark, sf_dir) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return score_texts(docs, crc_bucket("doc_id", 5) == 1)
