"""Language identification by mixture inference over character n-grams.

Training texts give each language a smoothed distribution over hashed byte trigrams of the text's
lower-cased letters.  A document is a mixture of languages: expectation-maximisation finds the
proportions under which its trigrams are likeliest, and the set of languages is the one with the
best penalised likelihood (each further language must pay half the log of the number of trigrams).
The predicted language is the largest proportion of the chosen mixture.

Defined results: a null text or one without letters is ``und`` with score 0; with no training
texts every text is ``und``; ties go to the first language by name; equal texts get equal results;
an empty table gives an empty result; extra columns are ignored.  The driver holds one row of
2^15 counts per language, whatever the corpus.
"""

from __future__ import annotations


import numpy as np
import pandas as pd
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_bucket

BINS = 1 << 15
SLICE = 1 << 20
UNKNOWN = "und"
_OTHER = regex.compile(r"[^\p{L}\p{M}]+")


def trigrams(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed trigrams of all texts, and the number of trigrams of each (0: no letters)."""
    joined = "\x1e".join(_OTHER.sub(" ", t).lower() for t in texts)
    data = np.frombuffer((" " + joined + " ").encode("utf-8", "surrogatepass"), dtype=np.uint8)
    breaks = np.flatnonzero(data == 0x1E)
    data = np.where(data == 0x1E, 32, data).astype(np.uint32)
    code = (data[:-2] * np.uint32(0x9E3779B1)) ^ (data[1:-1] * np.uint32(0x85EBCA77)) ^ (data[2:] * np.uint32(0xC2B2AE3D))
    code = ((code ^ (code >> np.uint32(15))) * np.uint32(0x2C1B3C6D)) >> np.uint32(17)
    middle_blank = (data[1:-1] == 32) & ((data[:-2] == 32) | (data[2:] == 32))
    owner = np.searchsorted(breaks, np.arange(1, len(data) - 1), side="right")
    code, owner = code[~middle_blank], owner[~middle_blank]
    counts = np.bincount(owner, minlength=len(texts))
    return code.astype(np.int64), counts


def _slices(table: pa.Table):
    texts = table["text"].to_pylist()
    first, size = 0, 0
    for i, t in enumerate(texts):
        size += len(t or "")
        if size >= SLICE or i + 1 == len(texts):
            yield first, [t or "" for t in texts[first : i + 1]]
            first, size = i + 1, 0


def _count(batches):
    held: dict[str, np.ndarray] = {}
    for batch in batches:
        table = pa.Table.from_batches([batch])
        langs = table["lang"].to_pylist()
        for first, texts in _slices(table):
            code, counts = trigrams(texts)
            owner = np.repeat(np.arange(len(texts)), counts)
            own = langs[first : first + len(texts)]
            for lang in set(own):
                is_lang = np.array([x == lang for x in own])
                held.setdefault(lang, np.zeros(BINS, np.int64))
                held[lang] += np.bincount(code[is_lang[owner]], minlength=BINS)
    for lang, counts in held.items():
        at = np.flatnonzero(counts)
        yield pa.record_batch({"lang": pa.array([lang] * len(at), pa.string()), "bin": pa.array(at.astype(np.int32)), "n": pa.array(counts[at])})


def learn(labelled: DataFrame, smooth: float = 0.5) -> tuple[list[str], np.ndarray]:
    """Languages and their ln probabilities of the trigram bins, from all rows of (text, lang)."""
    counted = labelled.select("text", "lang").mapInArrow(_count, "lang string, bin int, n long").groupBy("lang", "bin").agg(F.sum("n").alias("n")).toPandas()
    langs = sorted(counted.lang.unique())
    table = np.full((max(len(langs), 1), BINS), smooth)
    for i, lang in enumerate(langs):
        own = counted[counted.lang == lang]
        table[i, own.bin.to_numpy()] += own.n.to_numpy()
    return langs, np.log(table / table.sum(axis=1, keepdims=True))


def infer(code: np.ndarray, counts: np.ndarray, ln_prob: np.ndarray, rounds: int = 10) -> np.ndarray:
    """Language proportions of each document (rows), zero outside its chosen language set."""
    n_docs, n_langs = len(counts), len(ln_prob)
    owner = np.repeat(np.arange(n_docs), counts)
    codes, pair = pd.factorize(owner * BINS + code)  # in order of appearance, so documents stay in order
    weight = np.bincount(codes, minlength=len(pair)).astype(np.float32)
    owner, code = pair // BINS, pair % BINS
    like = np.exp(ln_prob - ln_prob.max(axis=0)).astype(np.float32)[:, code]
    edges = np.searchsorted(owner, np.arange(n_docs))
    filled = counts > 0

    def total(values: np.ndarray) -> np.ndarray:
        out = np.zeros(n_docs)
        out[filled] = np.add.reduceat(values, edges[filled]) if len(values) else 0
        return out

    def fit(share: np.ndarray, steps: int) -> tuple[np.ndarray, np.ndarray]:
        share = share.astype(np.float32)
        for _ in range(steps):
            joint = share[:, owner] * like
            joint *= weight / np.maximum(joint.sum(axis=0), 1e-30)
            share = np.stack([total(j) for j in joint])
            share = (share / np.maximum(share.sum(axis=0), 1e-30)).astype(np.float32)
        mixed = np.einsum("lp,lp->p", share[:, owner], like)
        return share, total(weight * np.log(np.maximum(mixed, 1e-30)))

    # backward selection: start with all languages, drop the weakest while the penalised likelihood gains
    price = 0.5 * np.log(np.maximum(counts, 2))
    best, value = fit(np.full((n_langs, n_docs), 1 / max(n_langs, 1)), rounds)
    value = value - price * (n_langs - 1)
    current = best
    for left in range(n_langs - 1, 0, -1):
        weakest = np.where(current > 0, current, np.inf).argmin(axis=0)
        current = current.copy()
        current[weakest, np.arange(n_docs)] = 0
        lost = current.sum(axis=0) <= 0  # expectation-maximisation had already emptied all others
        current[:, lost] = best[:, lost]
        current /= np.maximum(current.sum(axis=0), 1e-30)
        current, fitted = fit(current, rounds // 2 if left > 1 else 0)
        fitted = fitted - price * (left - 1)
        better = fitted >= value
        best = np.where(better, current, best)
        value = np.where(better, fitted, value)
    return best


def _predictor(model):
    def run(batches):
        langs, ln_prob = model.value
        for batch in batches:
            table = pa.Table.from_batches([batch])
            preds, scores, mixtures = [], [], []
            for _, texts in _slices(table):
                code, counts = trigrams(texts)
                has_letters = np.array([regex.search(r"\p{L}", t) is not None for t in texts]) & (counts > 0)
                if not langs:
                    has_letters[:] = False
                share = infer(code, counts, ln_prob)
                for i in range(len(texts)):
                    if not has_letters[i]:
                        preds.append(UNKNOWN)
                        scores.append(0.0)
                        mixtures.append([])
                        continue
                    k = int(share[:, i].argmax())
                    preds.append(langs[k])
                    scores.append(min(1.0, float(share[k, i])))
                    mixtures.append([{"lang": x, "share": float(s)} for x, s in zip(langs, share[:, i], strict=True) if s > 0])
            kind = pa.list_(pa.struct([("lang", pa.string()), ("share", pa.float64())]))
            yield pa.record_batch({"doc_id": batch["doc_id"], "held_out": batch["held_out"], "lang_pred": pa.array(preds, pa.string()), "score": pa.array(scores, pa.float64()), "mixture": pa.array(mixtures, kind)})

    return run


def identify(docs: DataFrame, held_out, lang: str = "lang") -> DataFrame:
    """Language mixture of every text of ``docs`` (doc_id, text); learns from labelled rows outside ``held_out``.

    Returns doc_id, held_out, lang_pred, score (its share) and mixture, the chosen languages with shares.
    """
    spark = docs.sparkSession
    model = spark.sparkContext.broadcast(learn(docs.filter(~held_out & F.col(lang).isNotNull()).select("text", F.col(lang).alias("lang"))))
    schema = "doc_id long, held_out boolean, lang_pred string, score double, mixture array<struct<lang: string, share: double>>"
    return docs.select("doc_id", "text", held_out.alias("held_out")).mapInArrow(_predictor(model), schema)


def op1_language_mixture(spark, sf_dir) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    return identify(docs, crc_bucket("doc_id", 4) == 2).select("doc_id", "held_out", "lang_pred", "score")
