"""SimHash near-duplicates, with pivot distance tables in front of every exact comparison.

Fingerprints within `radius` bits of each other are found without comparing all pairs:

* copies of a fingerprint are one row from the start;
* every fingerprint is dealt to one bucket for each choice of 8 - radius of its 8 bytes. Two
  fingerprints that differ in `radius` bits or fewer agree on such a choice, and a bucket fixes so
  many bits that it never holds more than 2**(8 * radius) members, whatever the data;
* in a bucket, a table holds each member's Hamming distance to fixed reference fingerprints (the
  pivots). Sorted by the first pivot, a member is only paired while that distance differs by at
  most `radius`; a pair whose largest coordinate difference over all pivots exceeds `radius` is
  discarded (triangle inequality); survivors are verified exactly.

Each task returns a spanning forest of what it found, and star contraction in Spark joins these.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxigraph.llm.components import components, local_components
from proxigraph.llm.textops import LONG, chunks, mix64, segments, xxh64_slices
from proxigraph.runtime import broadcast_if_small, map_arrow, settle

SHINGLE_WORDS = 3
SEED = 42
RADIUS = 2
N_PIVOTS = 16
#: Ids that are broadcast, at most (16 MB).
MOST_IDS = 2_000_000
CHUNK_BYTES = 1 << 18

#: Sets byte k of a 64-bit lane for bit k of a byte, to count eight bits in one addition.
_SPREAD = (np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.uint64) << (np.arange(8, dtype=np.uint64) * np.uint64(8))).sum(axis=1, dtype=np.uint64)

_NO_SPACE = np.arange(256) != 32


def pivots(n: int = N_PIVOTS) -> np.ndarray:
    """n fixed reference fingerprints, drawn by a seeded mixer."""
    return mix64(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def _counts(hashes: np.ndarray, doc: np.ndarray, n_docs: int) -> tuple[np.ndarray, np.ndarray]:
    """For each document, how many of its hashes have each bit, and how many hashes it has (doc is
    ascending)."""
    counts, total = np.zeros((n_docs, 64), dtype=np.int64), np.zeros(n_docs, dtype=np.int64)
    if not len(hashes):
        return counts, total
    first = np.flatnonzero(np.diff(doc, prepend=-1))
    many = np.diff(np.append(first, len(doc)))
    inside = np.arange(len(doc)) - np.repeat(first, many)
    block = np.flatnonzero(inside % 255 == 0)  # a lane counts to 255
    per_doc = np.searchsorted(block, first)
    lanes = hashes.view(np.uint8).reshape(-1, 8)
    total[doc[first]] = many
    for k in range(8):
        sums = np.add.reduceat(_SPREAD[lanes[:, k]], block)
        counts[doc[first], 8 * k: 8 * k + 8] = np.add.reduceat(sums.view(np.uint8).reshape(-1, 8).astype(np.int64), per_doc, axis=0)
    return counts, total


def normal(text: str | None) -> bytes:
    """The words of a text in lower case (A-Z only), with single spaces between them."""
    return b" ".join((text or "").encode("utf-8", "surrogatepass").lower().split())


def shingle_slices(norm: list[bytes], shingle_words: int) -> tuple[bytes, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of texts with single spaces between words: all of them in one buffer, the starts and stops of its words, and of
    each shingle its first word, its last one and its text."""
    buf = b"\n".join(norm) + b"\n"
    raw = np.frombuffer(buf, dtype=np.uint8)
    stop = np.flatnonzero((raw == 32) | (raw == 10))  # ends of words, and of empty texts
    start = np.append(0, stop[:-1] + 1)
    doc = np.searchsorted(np.flatnonzero(raw == 10), start)
    real = stop > start
    start, stop, doc = start[real], stop[real], doc[real]
    n = len(start)
    first = np.flatnonzero(np.diff(doc, prepend=-1))
    size = np.diff(np.append(first, n))
    last = np.minimum(np.arange(n) + shingle_words - 1, np.repeat(first + size - 1, size))
    whole = np.flatnonzero(np.arange(n) - np.repeat(first, size) <= np.maximum(np.repeat(size, size) - shingle_words, 0))
    return buf, start, stop, whole, last[whole], doc[whole]


def shingle_hashes(norm: list[bytes], shingle_words: int) -> tuple[np.ndarray, np.ndarray]:
    """XXH64 of the shingles of texts with single spaces between words, and each one's text."""
    buf, start, stop, begin, last, doc = shingle_slices(norm, shingle_words)
    return xxh64_slices(buf, start[begin], stop[last], SEED), doc


def fingerprint_texts(texts: list[str | None], shingle_words: int = SHINGLE_WORDS) -> np.ndarray:
    """SimHash fingerprints (uint64) of whole texts; see `fingerprints`."""
    norm = [normal(t) for t in texts]
    out = np.zeros(len(texts), dtype=np.uint64)
    for lo, hi in chunks(np.fromiter((len(t) for t in norm), np.int64, len(norm)), CHUNK_BYTES):
        if len(norm[lo]) <= LONG:
            counts, total = _counts(*shingle_hashes(norm[lo:hi], shingle_words), hi - lo)
        else:
            counts, total = np.zeros((1, 64), dtype=np.int64), np.zeros(1, dtype=np.int64)
            for part in segments(norm[lo], CHUNK_BYTES, shingle_words - 1, _NO_SPACE):
                more = _counts(*shingle_hashes([part], shingle_words), 1)
                counts, total = counts + more[0], total + more[1]
        bits = (counts * 2 > total[:, None]).astype(np.uint64)
        out[lo:hi] = (bits << np.arange(64, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)
    return out


def fingerprint_hashes(sets: list[np.ndarray]) -> np.ndarray:
    """The SimHash of each set of shingle hashes; 0 for an empty one."""
    if not sets:
        return np.empty(0, dtype=np.uint64)
    counts, total = _counts(np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(s) for s in sets]), len(sets))
    bits = (counts * 2 > total[:, None]).astype(np.uint64)
    return (bits << np.arange(64, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle_words: int = SHINGLE_WORDS) -> DataFrame:
    """(doc_id, fp long): the SimHash of every text.

    A-Z are lower-cased; words are runs other than [\\x20\\x09-\\x0D]; a shingle is `shingle_words`
    consecutive words, repeats included; fewer words form one shingle; a null, empty or blank text has
    fingerprint zero. A bit is set if it is set in over half of the shingles' XXH64 (seed 42).
    Null ids are kept; further columns of docs play no part.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = fingerprint_texts(batch.column(1).to_pylist(), shingle_words)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp.view(np.int64))], ["doc_id", "fp"])

    return map_arrow(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")), run, "doc_id long, fp long")


def _close_pairs(key: np.ndarray, fp: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of one key whose fingerprints differ in `radius` bits or fewer, and not in none."""
    ref = pivots()
    near = np.bitwise_count(fp ^ ref[0]).astype(np.int16)
    order = np.lexsort((near, key))
    key, fp = key[order], fp[order]
    table = np.stack([np.bitwise_count(fp ^ p).astype(np.int16) for p in ref])
    left = np.flatnonzero(key[1:] == key[:-1])
    found, shift = [], 1
    while len(left):
        right = left + shift
        ok = right < len(key)
        left, right = left[ok], right[ok]
        ok = (key[left] == key[right]) & (table[0][right] - table[0][left] <= radius)
        left, right = left[ok], right[ok]
        a, b = left, right
        for row in table[1:]:
            if not len(a):
                break
            ok = np.abs(row[a] - row[b]) <= radius
            a, b = a[ok], b[ok]
        if len(a):
            ok = np.bitwise_count(fp[a] ^ fp[b]) <= radius
            found.append((order[a[ok]], order[b[ok]]))
        shift += 1
    if not found:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    return np.concatenate([x for x, _ in found]), np.concatenate([x for _, x in found])


def _forest(key: np.ndarray, fp: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links (u, v) that span what the rows of each key connect."""
    a, b = _close_pairs(key, fp, radius)
    if not len(a):
        return fp[:0], fp[:0]
    used, back = np.unique(np.concatenate([a, b]), return_inverse=True)
    label = local_components(len(used), back[: len(a)], back[len(a):])
    off = np.flatnonzero(label != np.arange(len(used)))
    return fp[used[off]], fp[used[label[off]]]


def links(distinct: DataFrame, radius: int = RADIUS) -> DataFrame:
    """distinct(fp long) -> links (u, v) spanning all pairs within `radius` bits of each other."""
    if not 0 < radius < 8:
        raise ValueError("radius must be 1 to 7")
    masks = []
    for free in combinations(range(8), radius):
        mask = (1 << 64) - 1
        for k in free:
            mask &= ~(0xFF << 8 * k)
        masks.append(mask - (1 << 64) if mask >> 63 else mask)
    keys = F.array(*[F.xxhash64(F.lit(k), F.col("fp").bitwiseAND(F.lit(m).cast("long"))) for k, m in enumerate(masks)])
    dealt = distinct.select(F.explode(keys).alias("k"), "fp").repartition("k").sortWithinPartitions("k")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        n = 0

        def flush(final: bool) -> Iterator[pa.RecordBatch]:
            nonlocal held, n
            k, fp = (np.concatenate([x[i] for x in held]) for i in (0, 1))
            cut = len(k) if final else int(np.searchsorted(k, k[-1]))
            held, n = [(k[cut:], fp[cut:])], len(k) - cut
            u, v = _forest(k[:cut], fp[:cut].view(np.uint64), radius)
            yield pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(v.view(np.int64))], ["u", "v"])

        for batch in batches:
            held.append((batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)))
            n += len(held[-1][0])
            if n >= 200_000:
                yield from flush(False)
        if n:
            yield from flush(True)

    return map_arrow(dealt, run, "u long, v long").distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, shingle_words: int = SHINGLE_WORDS) -> DataFrame:
    """(doc_id, fp long, component_id): documents whose fingerprints are linked, directly or not, by
    steps of `radius` bits or fewer get one component_id, the smallest doc_id among them.

    Rows with a null doc_id keep their fingerprint's component; repeated rows give repeated rows;
    an empty table gives an empty result.
    """
    prints = settle(fingerprints(docs, id_col, text_col, shingle_words), "fingerprints")
    distinct = settle(prints.groupBy("fp").agg(F.min("doc_id").alias("low")), "distinct-fingerprints")
    roots = components(links(distinct.select("fp"), radius))
    rooted = distinct.join(roots, distinct["fp"] == roots["u"], "left").select("fp", "low", F.coalesce("v", "fp").alias("root"))
    lowest = rooted.groupBy("root").agg(F.min("low").alias("component_id"))
    named = rooted.join(lowest, "root").select("fp", "component_id")
    return prints.join(named, "fp").select("doc_id", "fp", "component_id")


def hex_fingerprint(column: str = "fp") -> F.col:
    return F.lower(F.lpad(F.hex(F.col(column)), 16, "0"))


def keep_one(docs: DataFrame, radius: int = RADIUS, shingle_words: int = SHINGLE_WORDS, least_jaccard: float | None = None) -> DataFrame:
    """The rows of docs without near-duplicates: of each component the row with the smallest doc_id
    stays (of several rows with that id, one). Rows with a null doc_id cannot be named and stay.

    Near-duplicates are fingerprints within `radius` bits or, where `least_jaccard` is given, sets of
    shingles of that similarity or more. The fingerprints then only lead the search (`shingle_sets`),
    which loses no such pair: at 0.8 about ten of 64 bits differ, more than pivot distances can tell
    from unrelated texts."""
    named = docs.filter("doc_id is not null")
    if least_jaccard is None:
        groups = near_duplicates(named, radius=radius, shingle_words=shingle_words)
    else:
        from proxigraph.llm import shingle_sets

        groups = shingle_sets.similar(named, shingle_words, least_jaccard)
    ids = settle(groups.groupBy("doc_id").agg(F.min("component_id").alias("low"), F.count("*").alias("n")), "grouped-ids")
    gone = settle(ids.filter("low <> doc_id").select("doc_id"), "dropped-ids")  # fewer than those that stay
    again = ids.filter("low = doc_id AND n > 1").select("doc_id")
    out = named.join(broadcast_if_small(gone, MOST_IDS), "doc_id", "left_anti")
    if not again.isEmpty():  # repeated ids: one of their rows, the least by its columns' text
        out = out.join(broadcast_if_small(again, MOST_IDS), "doc_id", "left_anti")
        repeated = docs.join(broadcast_if_small(again, MOST_IDS), "doc_id", "left_semi").select("doc_id", F.struct(*docs.columns).alias("_sp_row"))
        repeated = repeated.withColumn("_sp_text", F.to_json("_sp_row", {"ignoreNullFields": "false"}))
        out = out.unionByName(repeated.groupBy("doc_id").agg(F.min_by("_sp_row", "_sp_text").alias("_sp_row")).select("_sp_row.*"))
    return out.select(*docs.columns).unionByName(docs.filter("doc_id is null"))
