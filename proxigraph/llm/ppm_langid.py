"""Language identification by prediction by partial matching.

For each language a byte context tree up to order 3 is counted on a bounded sample of labelled
texts and then frozen. The code length of a byte in its context follows method C: the share of the
counts, or an escape to the next shorter context with the bytes already excluded, down to a uniform
choice among all bytes not excluded. As the statistics are frozen, every (context, byte) has one
fixed code length; these are tabulated for all languages over one shared set of contexts, and a
text's code length is the sum of them, in double precision, over all its bytes. The frozen trees hold
the contexts that the whole sample has at least LEAST_CONTEXT times; that is part of the model.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from proxigraph.llm.textops import LONG, chunks
from proxigraph.llm.toxicity_ftrl import fold
from proxigraph.runtime import broadcast_if_small, map_arrow, settle, with_fields

ORDER = 3
#: Expected number of labelled texts per language to learn from, at any size of the corpus.
SAMPLE_PER_LANGUAGE = 1500
#: Contexts seen fewer times in the whole sample fall back to their shorter suffix.
LEAST_CONTEXT = 12
#: The table of code lengths is broadcast. With so many languages that it would be larger than this, the
#: least count of a context is doubled until it fits.
MODEL_BYTES = 512 << 20
#: A text is recognised if its best language codes it in at most half of eight bits a byte, apart from
#: the first bytes, which have no full context yet.
MOST_NATS = math.log(256) / 2
CHUNK_BYTES = 1 << 18
COUNT_BYTES = 1 << 18
UNDETERMINED = "und"


def count_contexts(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Packed (order, context, byte) keys of all texts and their counts; only full contexts count."""
    key, count = np.empty(0, np.int64), np.empty(0, np.int64)
    for lo, hi in chunks(np.fromiter((len(t) for t in texts), np.int64, len(texts)), COUNT_BYTES):
        more, n = _count(texts[lo:hi])
        key, back = np.unique(np.concatenate([key, more]), return_inverse=True)
        count = np.bincount(back, weights=np.concatenate([count, n]), minlength=len(key)).astype(np.int64)
    return key, count


def _count(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    keys, counts = [], []
    raw = np.frombuffer(b"".join(texts), dtype=np.uint8).astype(np.int64)
    size = np.fromiter((len(t) for t in texts), np.int64, len(texts))
    begin = np.arange(len(raw)) - np.repeat(np.cumsum(size) - size, size)  # place in its own text
    packed = raw.copy()
    for order in range(ORDER + 1):
        if order:
            packed[order:] += raw[:-order] << (8 * order)
        k, c = np.unique(packed[begin >= order] | (order << 40), return_counts=True)
        keys.append(k)
        counts.append(c)
    return np.concatenate(keys), np.concatenate(counts)


class Model:
    """Frozen code lengths: alphabet of the bytes seen, contexts, nats per (context, byte, language)."""

    def __init__(self, langs: list[str], key: np.ndarray, lang: np.ndarray, count: np.ndarray):
        self.langs = langs
        order, byte = key >> 40, key & 0xFF
        context = (key & ((1 << 40) - 1)) >> 8
        seen = np.unique(byte)
        self.symbol = np.zeros(256, dtype=np.int32)  # 0: a byte never seen, or before the text
        self.symbol[seen] = np.arange(1, len(seen) + 1)
        a = self.size = len(seen) + 1
        whole = order << 40 | context
        names, back = np.unique(whole, return_inverse=True)
        total = np.bincount(back, weights=count, minlength=len(names))
        least = LEAST_CONTEXT
        while np.count_nonzero(total >= least) * a * max(1, len(langs)) * 8 > MODEL_BYTES:
            least *= 2
        kept = names[(total >= least) | (names == 0)]
        if not len(kept) or kept[0] != 0:
            kept = np.insert(kept, 0, 0)
        node_of = {int(x): i for i, x in enumerate(kept)}
        orders = kept >> 40
        parent = np.zeros(len(kept), dtype=np.int64)
        for i, x in enumerate(kept.tolist()):
            o, c = x >> 40, x & ((1 << 40) - 1)
            while o:
                o -= 1
                c &= (1 << 8 * o) - 1
                if (o << 40 | c) in node_of:
                    parent[i] = node_of[o << 40 | c]
                    break
        self.cost = np.zeros((len(kept) * a, max(1, len(langs))), dtype=np.float64)
        row = np.searchsorted(kept, whole)
        row[row == len(kept)] = 0
        fits = kept[row] == whole
        for j in range(len(langs)):
            counts = np.zeros((len(kept), a))
            own = fits & (lang == j)
            np.add.at(counts, (row[own], self.symbol[byte[own]]), count[own])
            self.cost[:, j] = self._code_lengths(counts, parent, orders).reshape(-1)
        self.context = self._automaton(kept, a)

    def _code_lengths(self, counts: np.ndarray, parent: np.ndarray, orders: np.ndarray) -> np.ndarray:
        """Nats of every byte class in every context, one order of the tree after the other."""
        nodes, a = counts.shape
        out = np.zeros((nodes, a))
        free = np.ones((nodes, a), dtype=bool)  # bytes not yet coded or excluded
        paid = np.zeros(nodes)  # nats of the escapes so far
        at = np.arange(nodes)
        active = np.ones(nodes, dtype=bool)
        for _ in range(ORDER + 1):
            c = counts[at] * free
            n, d = c.sum(axis=1), (c > 0).sum(axis=1)
            use = active & (n > 0)
            hit = (c > 0) & use[:, None]
            with np.errstate(divide="ignore", invalid="ignore"):
                code = paid[:, None] - np.log(c) + np.log((n + d)[:, None])
                out = np.where(hit, code, out)
                paid = np.where(use, paid - np.log(d / (n + d)), paid)
            free &= ~hit
            active &= at != 0
            at = parent[at]
        left = 256 - (a - 1 - free[:, 1:].sum(axis=1))
        return np.where(free, paid[:, None] + np.log(np.maximum(left, 1))[:, None], out)

    def _automaton(self, kept: np.ndarray, a: int) -> np.ndarray:
        """Longest kept suffix of every three preceding byte classes, shortest contexts first."""
        found = np.zeros((a, a, a), dtype=np.int32)
        for i, x in enumerate(kept.tolist()):
            o, c = x >> 40, x & ((1 << 40) - 1)
            s = [int(self.symbol[c >> 8 * k & 0xFF]) for k in range(o)]  # nearest byte first
            if o == 1:
                found[:, :, s[0]] = i
            elif o == 2:
                found[:, s[1], s[0]] = i
            elif o == 3:
                found[s[2], s[1], s[0]] = i
        return found.reshape(-1)

    def _nats(self, sym: np.ndarray, out: np.ndarray | None = None) -> np.ndarray:
        """Nats of each byte class after the first ORDER ones, under each language."""
        a = self.size
        node = self.context[(sym[:-3] * a + sym[1:-2]) * a + sym[2:-1]]
        return np.take(self.cost, node * a + sym[3:], axis=0, out=out, mode="clip")

    def code_lengths(self, texts: list[str | None]) -> np.ndarray:
        """Nats of each whole text under each language."""
        raw = [(t or "").encode("utf-8", "surrogatepass") for t in texts]
        out = np.zeros((len(raw), self.cost.shape[1]))
        lengths = np.fromiter((len(t) for t in raw), np.int64, len(raw))
        for lo, hi in chunks(lengths, CHUNK_BYTES):
            size = lengths[lo:hi]
            if not size.sum():
                continue
            if size[0] > LONG:
                for at in range(0, int(size[0]), CHUNK_BYTES):
                    before = np.frombuffer(raw[lo][max(0, at - ORDER): at], dtype=np.uint8)
                    own = self.symbol[np.frombuffer(raw[lo][at: at + CHUNK_BYTES], dtype=np.uint8)]
                    sym = np.concatenate([np.zeros(ORDER - len(before), np.int32), self.symbol[before], own])
                    out[lo] += self._nats(sym).sum(axis=0, dtype=np.float64)
                continue
            stop = np.cumsum(size + ORDER)
            buf = np.frombuffer(b"".join(b + b"\0" * ORDER for b in raw[lo:hi]), dtype=np.uint8)
            sym = np.concatenate([np.zeros(ORDER, np.int32), self.symbol[buf]])
            for k in range(ORDER):  # what stands before a text is no byte
                sym[stop - k + ORDER - 1] = 0
            ends = np.zeros((len(sym) - ORDER + 1, out.shape[1]))
            np.cumsum(self._nats(sym, ends[1:]), axis=0, out=ends[1:])
            begin = stop - size - ORDER
            out[lo:hi] = ends[begin + size] - ends[begin]
        return out


def fit(docs: DataFrame, per_language: int = SAMPLE_PER_LANGUAGE) -> Model:
    """Model of the languages named in docs.lang outside the held-out fold, from about per_language
    texts of each at most, chosen by hashed id. Null or empty lang and null text are not learnt."""
    known = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "lang").filter("lang is not null and lang <> '' and text is not null").filter(fold() != 0)
    rates = known.groupBy("lang").count().select("lang", (F.lit(float(per_language)) / F.col("count") * F.lit(float(1 << 32))).alias("bound"))
    rates = broadcast_if_small(settle(rates, "language-rates"))  # one row a language
    chosen = known.join(rates, "lang").filter(F.coalesce(F.xxhash64("doc_id", F.lit(10)).bitwiseAND(0xFFFFFFFF), F.lit(0)) < F.col("bound"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            langs, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for lang in sorted(set(langs)):
                k, c = count_contexts([t.encode("utf-8", "surrogatepass") for x, t in zip(langs, texts, strict=True) if x == lang])
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(k)), pa.array(k), pa.array(c)], ["lang", "k", "c"])

    table = settle(map_arrow(chosen.select("lang", "text"), count, "lang string, k long, c long").groupBy("lang", "k").agg(F.sum("c").alias("c")), "language-contexts")
    context = F.col("k").bitwiseAND(~0xFF)  # without the byte that follows
    often = table.groupBy(context.alias("x")).agg(F.sum("c").alias("n")).filter((F.col("n") >= LEAST_CONTEXT) | (F.col("x") == 0)).select("x")
    table = table.join(often, context == F.col("x"), "left_semi").toPandas()
    langs = sorted(table["lang"].unique())
    return Model(langs, table["k"].to_numpy(np.int64), table["lang"].map({x: i for i, x in enumerate(langs)}).to_numpy(np.int64), table["c"].to_numpy(np.int64))


def has_letter(text: str | None) -> bool:
    return text is not None and any(map(str.isalpha, text))


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """docs plus lang_pred (string), score (double) and nats (double): the language with the shortest code
    for the whole text, its share among all languages' likelihoods, and the length of that code. `und`
    with score and nats 0 if the text is null or has no letter, or no language was learnt; ties go to
    the first in code point order. Columns of docs that have these names are replaced."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    plain = docs.drop("lang_pred", "score", "nats")
    place = plain.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value
        for batch in batches:
            texts = batch.column(place).to_pylist()
            nats = known.code_lengths(texts)
            best = nats.argmin(axis=1)
            p = 1.0 / np.exp(np.clip(nats.min(axis=1, keepdims=True) - nats, -700, 0)).sum(axis=1)
            real = np.fromiter((bool(known.langs) and has_letter(t) for t in texts), bool, len(texts))
            pred = [known.langs[b] if r else UNDETERMINED for b, r in zip(best, real, strict=True)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(pred, pa.string()), pa.array(np.where(real, p, 0.0)), pa.array(np.where(real, nats.min(axis=1), 0.0))], [*batch.schema.names, "lang_pred", "score", "nats"])

    return map_arrow(plain, run, with_fields(plain, "lang_pred string, score double, nats double"))


def recognised() -> Column:
    """Condition on what predict returns: a learnt language, in which the text codes well."""
    return (F.col("lang_pred") != UNDETERMINED) & (F.col("nats") <= F.octet_length("text") * MOST_NATS + ORDER * math.log(256))
