"""Toxicity: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Every text becomes a set of hashed features: words, pairs of neighbouring words, and pairs with one
word skipped between them. Training runs over a bounded sample of labelled rows in one task, with a
rate of its own for every coordinate; the L1 term leaves most weights at exactly zero, so the model
is a short (index, weight) list that is broadcast for scoring.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from proxigraph.llm.textops import LONG, WORD, chunks, mix64, segments, word_hashes
from proxigraph.runtime import map_arrow, with_fields

BITS = 22
#: Expected number of labelled rows to train on, at any size of the corpus.
SAMPLE_ROWS = 16_000
#: Rates, terms, epochs and class weight: of twelve settings the one with the least log loss on an inner
#: fold, learnt on the other folds that are not held out.
EPOCHS = 5
ALPHA, BETA, L1, L2 = 4.0, 1.0, 16.0, 1.0
#: Weight of a row with label 1, the rarer one.
POSITIVE = 4.0
CHUNK_BYTES = 1 << 18
FOLDS = 5

_PAIR, _SKIP = np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA5A5A5A5DEADBEEF | 1)


def fold(id_col: str = "doc_id") -> Column:
    """crc32 of the id as text, modulo 5; rows with 0 are held out. A null id is never held out."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % FOLDS, F.lit(1))


def features(texts: list[str | None]) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """For ranges lo..hi of texts: lo, hi, and the index in the range and hashed feature of every
    word, pair and skip pair of the whole texts. A very long text comes in several parts."""
    raw = [(t or "").lower().encode("utf-8", "surrogatepass") for t in texts]
    shift = np.uint64(64 - BITS)
    for lo, hi in chunks(np.fromiter((len(t) for t in raw), np.int64, len(raw)), CHUNK_BYTES):
        parts = [raw[lo:hi]] if len(raw[lo]) <= LONG else ([x] for x in segments(raw[lo], CHUNK_BYTES, 2, WORD))
        for part in parts:
            h, doc = word_hashes(part)
            idx, owner = [h >> shift], [doc]
            with np.errstate(over="ignore"):
                for gap, salt in ((1, _PAIR), (2, _SKIP)):
                    same = doc[gap:] == doc[:-gap]
                    idx.append((mix64(h[:-gap] * salt + h[gap:]) >> shift)[same])
                    owner.append(doc[gap:][same])
            yield lo, hi, np.concatenate(owner), np.concatenate(idx).astype(np.int64)


def train(rows: list[tuple[np.ndarray, int]]) -> tuple[np.ndarray, np.ndarray]:
    """FTRL-proximal over (feature indices, label) rows, in their order -> non-zero (index, weight);
    index 2**BITS is the bias."""
    z, n = np.zeros((1 << BITS) + 1), np.zeros((1 << BITS) + 1)

    def weights(i: np.ndarray) -> np.ndarray:
        short = np.abs(z[i]) <= L1
        w = -(z[i] - np.sign(z[i]) * L1) / ((BETA + np.sqrt(n[i])) / ALPHA + L2)
        return np.where(short, 0.0, w)

    for _ in range(EPOCHS):
        for i, y in rows:
            w = weights(i)
            g = 1.0 / (1.0 + np.exp(-np.clip(w.sum(), -35, 35))) - y
            g *= POSITIVE if y else 1.0
            root = np.sqrt(n[i])
            n[i] += g * g
            z[i] += g - (np.sqrt(n[i]) - root) / ALPHA * w
    at = np.flatnonzero(np.abs(z) > L1)
    return at, weights(at)


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", sample_rows: int = SAMPLE_ROWS) -> tuple[np.ndarray, np.ndarray]:
    """Sparse weights learnt from labelled rows outside the held-out fold.

    The sample takes rows whose hashed id falls under sample_rows / (rows that have a label), so
    about sample_rows of them at most; ids labelled twice count as 1 if any label is 1; of several
    documents with one id the one with the least text is learnt; null labels and ids are ignored; with
    no labelled row, or too few, the model is empty and scores 0.
    """
    known = (
        labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y"))
        .filter("doc_id is not null and y is not null").groupBy("doc_id").agg(F.max("y").alias("y")).filter(fold() != 0)
    )
    share = min(1.0, sample_rows / max(1, known.count()))
    bound = min(int(share * (1 << 32)), (1 << 32) - 1)
    chosen = known.filter(F.xxhash64("doc_id").bitwiseAND(0xFFFFFFFF) <= bound)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(chosen), "doc_id")
    rows = rows.groupBy("doc_id").agg(F.min("text").alias("text"), F.max("y").alias("y"))

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = []
        for batch in batches:
            ids, texts, ys = batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()
            sets: dict[int, list[np.ndarray]] = {}
            for lo, hi, owner, idx in features(texts):
                pairs = np.unique(owner << (BITS + 1) | idx)
                cuts = np.searchsorted(pairs >> (BITS + 1), np.arange(hi - lo + 1))
                for k in range(lo, hi):
                    sets.setdefault(k, []).append(pairs[cuts[k - lo]: cuts[k - lo + 1]] & ((1 << (BITS + 1)) - 1))
            for k, own in sets.items():
                used = own[0] if len(own) == 1 else np.unique(np.concatenate(own))
                kept.append((ids[k], zlib.crc32((texts[k] or "").encode("utf-8", "surrogatepass")), np.append(used, 1 << BITS).astype(np.int32), ys[k]))
        kept.sort(key=lambda r: (int(mix64(np.array([r[0]], np.int64).view(np.uint64))[0]), r[1]))
        at, w = train([(r[2], r[3]) for r in kept]) if kept else (np.empty(0, np.int64), np.empty(0))
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(w)], ["i", "w"])

    model = map_arrow(rows.repartition(1), learn, "i long, w double").toPandas().sort_values("i")
    return model["i"].to_numpy(np.int64), model["w"].to_numpy(float)


def score_texts(texts: list[str | None], at: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Probability of the positive label for each whole text; 0 under an empty model."""
    if not len(at):
        return np.zeros(len(texts))
    hot = np.zeros((1 << BITS) + 1, dtype=bool)
    hot[at] = True
    out = np.full(len(texts), w[at == 1 << BITS].sum())
    pairs = [np.empty(0, np.int64)]
    for lo, _, owner, idx in features(texts):
        use = hot[idx]
        pairs.append(np.unique((owner[use] + lo) << (BITS + 1) | idx[use]))
    each = np.unique(np.concatenate(pairs))
    got = w[np.searchsorted(at, each & ((1 << (BITS + 1)) - 1))]
    out += np.bincount(each >> (BITS + 1), weights=got, minlength=len(texts))
    return 1.0 / (1.0 + np.exp(-np.clip(out, -35, 35)))


def score(docs: DataFrame, model: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """docs plus `score` (double, 0 to 1) and `predicted` (1 from 0.5 on); a null or empty text gets
    the bias's score. Columns of docs that have these names are replaced."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    plain = docs.drop("score", "predicted")
    place = plain.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, w = shared.value
        for batch in batches:
            p = score_texts(batch.column(place).to_pylist(), at, w)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(p), pa.array((p >= 0.5).astype(np.int32))], [*batch.schema.names, "score", "predicted"])

    return map_arrow(plain, run, with_fields(plain, "score double, predicted int"))
