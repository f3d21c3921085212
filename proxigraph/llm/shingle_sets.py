"""Groups of documents whose sets of word shingles are similar, without losing a pair.

Candidates come from two searches, and each pair of texts is compared at most once:

* SimHash fingerprints of the sets, searched by pivot distance tables (`simhash_pivots`), find copies
  with few changes; every fingerprint's nearest ones are compared first.
* Two sets with Jaccard similarity of at least `least` share so many members that, under any one order
  of all shingles, the first n - ceil(least * n) + 1 members of each (n: its size) have one in common.
  So every text is dealt to the keys of its first members. The order puts shingles that a
  sample of documents holds often last, so lines shared by many documents are rarely keys, and before
  them those of frequent words, which texts share by chance; what the sample holds changes the cost,
  never the result.

Before texts are sent to be compared, a pair must pass its sketches. A sketch has a bit for each hash
value modulo its length, the parity of the members there; the bits that differ between two sketches
are at most the members that only one of the sets has, which bounds the similarity from above.

The texts of a key are joined in rounds: in each, a key has one hub, and every text outside the hub's
group is compared with the one hub whose fingerprint is nearest. That gathers large groups of near
copies with few comparisons a text. What then remains are pairs of different groups; each is
compared under the first key that it shares, unless the sizes of the two, or their places in the
order, rule the similarity out. A shingle stands for its 64-bit hash throughout: two texts of ten
thousand shingles would have to meet some hundred billion times for one chance equality.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from proxigraph.llm.components import components
from proxigraph.llm.simhash_pivots import CHUNK_BYTES, MOST_IDS, SEED, fingerprint_hashes, links, normal, shingle_hashes, shingle_slices
from proxigraph.llm.textops import chunks, xxh64_slices
from proxigraph.runtime import broadcast_if_small, discard, map_arrow, settle

#: Tolerance of comparisons with the least similarity, far below the step between two shares.
TINY = 1e-9
#: Documents of the sample: so many, or of large tables this share, as what is rare in a sample of fixed size
#: grows with the table, and the pairs that meet there with its square.
SAMPLE_DOCS = 8192
SAMPLE_SHARE = 32
#: A shingle of so many sampled documents is ordered by that count; at most MOST_COMMON of them.
COMMON = 3
MOST_COMMON = 250_000
#: Words of the sample whose counts order the other shingles.
MOST_WORDS = 50_000
#: Postings that a task packs at once, and that a part of the keys holds, about.
PACKED = 500_000
#: Rounds of comparisons with hubs before all remaining pairs are compared, and the most bits of the
#: fingerprints that differ there (a similarity of 0.8 makes about ten of 64 differ).
HUB_ROUNDS = 2
HUB_BITS = 18
#: Texts of either side that meet in one cell of comparisons, about.
CELL_TEXTS = 256
#: Rows of two numbers that are broadcast, at most (32 MB).
MOST_NARROW = 2_000_000
#: So many of a text's earlier keys are looked at to see whether a pair was met before; if it was earlier
#: still, it is met again, and made one.
EARLIER_KEYS = 4


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Similarity of two sets of distinct hashes."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both) if len(a) or len(b) else 1.0


def _sets(texts: list[str | None], size: int) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    norm = [normal(t) for t in texts]
    for lo, hi in chunks(np.fromiter((len(t) for t in norm), np.int64, len(norm)), CHUNK_BYTES):
        h, doc = shingle_hashes(norm[lo:hi], size)
        cut = np.searchsorted(doc, np.arange(hi - lo + 1))
        for a, b in zip(cut, cut[1:], strict=False):
            yield np.unique(h[a:b])


def _counted(hashes: np.ndarray, table: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The count of each hash in a table of sorted hashes and counts; 0 if it is not there."""
    if not len(table[0]):
        return np.zeros(len(hashes), dtype=np.int64)
    at = np.minimum(np.searchsorted(table[0], hashes), len(table[0]) - 1)
    return np.where(table[0][at] == hashes, table[1][at], 0)


def _scored_sets(texts: list[str | None], size: int, words: tuple[np.ndarray, np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """_sets, with a score of each member: the sum of its words' logarithms of their counts, in eighths of a bit."""
    norm = [normal(t) for t in texts]
    for lo, hi in chunks(np.fromiter((len(t) for t in norm), np.int64, len(norm)), CHUNK_BYTES):
        buf, start, stop, begin, last, doc = shingle_slices(norm[lo:hi], size)
        h = xxh64_slices(buf, start[begin], stop[last], SEED)
        each = np.floor(8 * np.log2(1 + _counted(xxh64_slices(buf, start, stop, SEED), words))).astype(np.int64)
        sums = np.append(0, np.cumsum(each))
        score = sums[last + 1] - sums[begin]
        cut = np.searchsorted(doc, np.arange(hi - lo + 1))
        for a, b in zip(cut, cut[1:], strict=False):
            members, at = np.unique(h[a:b], return_index=True)
            yield members, score[a:b][at]


def sketch(members: np.ndarray) -> bytes:
    """Parities of the members by their hash modulo a power of two of bits, at least as many as there are members."""
    bits = max(64, 1 << max(0, len(members) - 1).bit_length())
    odd = np.bincount((members & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def least_apart(a: bytes, b: bytes) -> int:
    """A lower bound on the members that only one of two sets holds, by their sketches; the longer one is folded."""
    x, y = (np.frombuffer(s, dtype=np.uint64) for s in (a, b))
    while len(x) != len(y):
        if len(x) < len(y):
            x, y = y, x
        x = x[: len(x) // 2] ^ x[len(x) // 2:]
    return int(np.bitwise_count(x ^ y).sum())


def _node(members: np.ndarray) -> int:
    return int.from_bytes(blake2b(members.tobytes(), digest_size=8).digest(), "little", signed=True)


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))


def common_shingles(rows: DataFrame, size: int) -> tuple[tuple[np.ndarray, np.ndarray], tuple[np.ndarray, np.ndarray]]:
    """Hashes (sorted) of the shingles met most often in a sample, and their counts; the same of its words."""
    step = max(1, min(rows.count() // SAMPLE_DOCS, SAMPLE_SHARE))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            norm = [normal(t) for t in batch.column(0).to_pylist()]
            for lo, hi in chunks(np.fromiter((len(t) for t in norm), np.int64, len(norm)), CHUNK_BYTES):
                buf, start, stop, begin, last, doc = shingle_slices(norm[lo:hi], size)
                h = xxh64_slices(buf, start[begin], stop[last], SEED)
                for of in np.split(h, np.flatnonzero(np.diff(doc)) + 1):
                    k = np.unique(of)
                    yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(k), np.int32)), pa.array(k.view(np.int64)), pa.array(np.ones(len(k), np.int64))], ["kind", "k", "n"])
                w, n = np.unique(xxh64_slices(buf, start, stop, SEED), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(np.ones(len(w), np.int32)), pa.array(w.view(np.int64)), pa.array(n.astype(np.int64))], ["kind", "k", "n"])

    part = rows.filter(F.pmod(F.xxhash64("doc_id"), F.lit(step)) == 0).select("text")
    met = map_arrow(part, run, "kind int, k long, n long").groupBy("kind", "k").agg(F.sum("n").alias("n")).filter(F.col("n") >= COMMON)
    spent: list[str] = []
    met = settle(met, "shingle-common", spent)
    tables = []
    for kind, most in enumerate((MOST_COMMON, MOST_WORDS)):
        top = met.filter(F.col("kind") == kind).select("k", "n").orderBy(F.desc("n"), "k").limit(most).toArrow()
        k, n = top["k"].to_numpy().view(np.uint64), top["n"].to_numpy()
        order = np.argsort(k)
        tables.append((k[order], n[order]))
    discard(rows.sparkSession, spent)
    return tables[0], tables[1]


def first_members(members: np.ndarray, score: np.ndarray, least: float, common: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, int]:
    """The members that a similar set must hold one of among its own first ones, in the order; and how often
    the sample holds the set's members on average, in thousandths."""
    n = len(members)
    keep = n - int(np.ceil(least * n - TINY)) + 1 if n else 0
    count = _counted(members, common)
    return members[np.lexsort((members, score, count))[:keep]], int(count.sum()) * 1000 // max(1, n)


def nodes_of(rows: DataFrame, size: int, least: float, common: tuple[np.ndarray, np.ndarray], words: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """(doc_id, node long, n int, fp long, met int, sketch, keys array<long>) of every row; met tells how often
    the sample holds its shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            scored = list(_scored_sets(batch.column(1).to_pylist(), size, words))
            sets = [s for s, _ in scored]
            fp = fingerprint_hashes(sets)
            firsts = [first_members(*s, least, common) for s in scored]
            columns = [
                batch.column(0), pa.array([_node(s) for s in sets], pa.int64()), pa.array([len(s) for s in sets], pa.int32()), pa.array(fp.view(np.int64)),
                pa.array([m for _, m in firsts], pa.int32()), pa.array([sketch(s) for s in sets], pa.binary()), pa.array([k.view(np.int64) for k, _ in firsts], pa.list_(pa.int64())),
            ]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "node", "n", "fp", "met", "sketch", "keys"])

    return map_arrow(rows, run, "doc_id long, node long, n int, fp long, met int, sketch binary, keys array<long>", 256)


def _repeated(keyed: DataFrame, parts: int) -> DataFrame:
    """(k, node, place): the keys (node, keys) of all rows that more than one row holds. They are shuffled once,
    packed by parts of the range of hashes; a task holds keys of a part met once so far, and lets the others go."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def flush() -> pa.RecordBatch:
            k, node, place = (np.concatenate(x) for x in zip(*held, strict=True))
            part = ((k.view(np.uint64) >> np.uint64(32)) * np.uint64(parts)) >> np.uint64(32)
            order = np.argsort(part, kind="stable")
            names, first = np.unique(part[order], return_index=True)
            packed = [b"".join(x[at].tobytes() for x in (k, node, place)) for at in np.split(order, first[1:])]
            return pa.RecordBatch.from_arrays([pa.array(names.astype(np.int64)), pa.array(packed, pa.binary())], ["part", "packed"])

        for batch in batches:
            keys = batch.column(1)
            size = keys.value_lengths().to_numpy(zero_copy_only=False)
            place = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            held.append((keys.flatten().to_numpy(zero_copy_only=False), np.repeat(batch.column(0).to_numpy(zero_copy_only=False), size), place.astype(np.int32)))
            n += len(place)
            if n >= PACKED:
                yield flush()
                held, n = [], 0
        if n:
            yield flush()

    def again(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held, n, seen = None, [], 0, np.empty(0, np.int64)

        def sift() -> pa.RecordBatch:
            nonlocal held, n, seen
            k, node, place = (np.concatenate(x) for x in zip(*held, strict=True))
            names, back, many = np.unique(k, return_inverse=True, return_counts=True)
            more = (many > 1) | np.isin(names, seen, assume_unique=True)
            seen = np.union1d(seen, names[more])
            out = more[back]
            held, n = [(k[~out], node[~out], place[~out])], 0
            return pa.RecordBatch.from_arrays([pa.array(x[out]) for x in (k, node, place)], ["k", "node", "place"])

        for batch in batches:
            for part, packed in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if part != now:
                    if held:
                        yield sift()
                    now, held, n, seen = part, [], 0, seen[:0]
                raw = packed.as_buffer()
                m = raw.size // 20
                held.append((np.frombuffer(raw, np.int64, m), np.frombuffer(raw, np.int64, m, 8 * m), np.frombuffer(raw, np.int32, m, 16 * m)))
                n += m
                if n >= 2 * PACKED:
                    yield sift()
        if held:
            yield sift()

    spark = keyed.sparkSession
    packed = map_arrow(keyed.select("node", "keys"), pack, "part long, packed binary")
    many = [parts] if parts > int(spark.conf.get("spark.sql.shuffle.partitions")) else []
    return map_arrow(packed.repartition(*many, "part").sortWithinPartitions("part"), again, "k long, node long, place int", 64)


def _sketched(pairs: DataFrame, nodes: DataFrame, least: float) -> DataFrame:
    """Those of the pairs (u, v, at) whose sketches allow the least similarity."""
    both = pairs
    for x in ("u", "v"):
        both = both.join(nodes.select(F.col("node").alias(x), F.col("n").alias(f"{x}_n"), F.col("sketch").alias(f"{x}_sketch")), x)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.column(3).to_numpy().astype(np.int64) + batch.column(4).to_numpy()
            apart = np.array([least_apart(a.as_py(), b.as_py()) for a, b in zip(batch.column(5), batch.column(6), strict=True)], dtype=np.int64)
            good = (n - apart) / 2 >= n * (least / (1 + least)) - TINY  # the members of both sets, at most
            yield pa.RecordBatch.from_arrays(batch.columns[:3], ["u", "v", "at"]).filter(pa.array(good))

    return map_arrow(both.select("u", "v", "at", "u_n", "v_n", "u_sketch", "v_sketch"), run, "u long, v long, at long")


def _compared(pairs: DataFrame, rows: DataFrame, nodes: DataFrame, size: int, least: float) -> DataFrame:
    """Those of the pairs (u, v, at) of nodes whose texts have the least similarity; nodes holds a doc_id of
    each. The sketches rule most pairs out. Of the others, those with one `at` meet in one cell (or, if there are many, in a grid of cells by hashed u and
    v), to which each text that they name is sent once, not once a pair."""
    spark, spent = rows.sparkSession, []
    pairs = settle(_sketched(pairs, nodes, least), "shingle-sketched", spent)

    def with_node(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            node = [_node(s) for s in _sets(batch.column(0).to_pylist(), size)]
            yield pa.RecordBatch.from_arrays([pa.array(node, pa.int64()), batch.column(0)], ["node", "text"])

    wide = pairs.groupBy("at").agg(F.ceil(F.count_distinct("v") / CELL_TEXTS).alias("b"), F.ceil(F.count_distinct("u") / CELL_TEXTS).alias("c"))
    cell = F.xxhash64("at", F.pmod(F.xxhash64("v"), F.col("b")), F.pmod(F.xxhash64("u", F.lit(1)), F.col("c")))
    placed = settle(pairs.join(wide, "at").select(cell.alias("cell"), "u", "v"), "shingle-cells", spent)
    needed = settle(placed.select("cell", F.col("u").alias("node")).union(placed.select("cell", "v")).distinct(), "shingle-needed", spent)
    ids = settle(nodes.join(needed.select("node").distinct(), "node", "left_semi").select("doc_id").distinct(), "shingle-asked", spent)
    found = map_arrow(rows.join(broadcast_if_small(ids, MOST_NARROW), "doc_id", "left_semi").select("text"), with_node, "node long, text string")
    sent = found.join(broadcast_if_small(needed, MOST_NARROW), "node").select("cell", F.lit(0).alias("kind"), F.col("node").alias("u"), F.lit(None).cast("long").alias("v"), "text")
    both = sent.unionByName(placed.select("cell", F.lit(1).alias("kind"), "u", "v", F.lit(None).cast("string").alias("text")))

    def similar(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held, sets = None, {}, {}
        for batch in batches:
            good = []
            cells, kinds, us, vs, own = (c.to_pylist() for c in batch.columns)
            for at, kind, u, v, text in zip(cells, kinds, us, vs, own, strict=True):
                if at != now:
                    now, held, sets = at, {}, {}
                if kind == 0:
                    held[u] = text
                else:
                    for x in (u, v):
                        if x not in sets:
                            sets[x] = next(_sets([held.pop(x)], size))
                    if jaccard(sets[u], sets[v]) >= least - TINY:
                        good.append((u, v))
            columns = list(zip(*good, strict=True)) or [[], []]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["u", "v"])

    dealt = both.repartition("cell").sortWithinPartitions("cell", "kind", "u")
    links_ = settle(map_arrow(dealt, similar, "u long, v long", 128), "shingle-links")
    discard(spark, spent)
    return links_


def _may_be_similar(least: float, place: str, other_place: str):
    """Condition on two postings of one key, (n, place) and (m, other place): their sizes, and the members
    from their places on, allow the similarity (true of the first key that a similar pair shares)."""
    n, m = F.col("n"), F.col("m")
    sizes = F.least(n, m) >= F.greatest(n, m) * least - TINY
    return sizes & (F.least(n - F.col(place), m - F.col(other_place)) >= (n + m) * (least / (1 + least)) - TINY)


def _by_fingerprint(nodes: DataFrame) -> DataFrame:
    """(u, v): every node with the smallest one of its fingerprint, and the smallest ones of
    fingerprints that the pivot tables find close."""
    leads = settle(nodes.groupBy("fp").agg(F.min("node").alias("lead")), "shingle-leads")
    same = nodes.join(leads, "fp").filter("node <> lead").select(F.col("lead").alias("u"), F.col("node").alias("v"))
    close = links(leads.select("fp"))
    a, b = leads.select(F.col("fp").alias("u"), F.col("lead").alias("x")), leads.select(F.col("fp").alias("v"), F.col("lead").alias("y"))
    return same.unionByName(close.join(a, "u").join(b, "v").select(F.col("x").alias("u"), F.col("y").alias("v")))


def _rooted(rows: DataFrame, roots: DataFrame) -> DataFrame:
    """rows with the root of their node; only nodes that are linked have a row in roots."""
    known = broadcast_if_small(roots.select(F.col("u").alias("node"), F.col("v").alias("root")))
    return rows.join(known, "node", "left").withColumn("root", F.coalesce("root", "node"))


def similar(docs: DataFrame, size: int, least: float, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, component_id): documents linked, directly or not, by a Jaccard similarity of at least
    `least` of their sets of `size`-word shingles get one component_id, the smallest doc_id among them.

    Words are as in the fingerprints; fewer words form one shingle; null, empty and blank texts are
    equal. Rows with a null doc_id are left out; repeated rows give repeated rows.
    """
    if not 0 < least <= 1:
        raise ValueError("least must be above 0 and at most 1")
    spark, spent = docs.sparkSession, []
    rows = _rows(docs, id_col, text_col).filter("doc_id is not null")
    keyed = settle(nodes_of(rows, size, least, *common_shingles(rows, size)), "shingle-keys", spent)
    named = settle(keyed.select("doc_id", "node", "fp"), "shingle-nodes")
    per_node = [F.min("doc_id").alias("doc_id"), *[F.first(c).alias(c) for c in ("n", "met", "fp", "sketch")]]
    nodes = settle(keyed.groupBy("node").agg(*per_node), "shingle-distinct")

    copies = settle(named.select("doc_id", "node").join(nodes.select("node", F.col("doc_id").alias("lead")), "node").filter("doc_id <> lead").select("doc_id", "node"), "shingle-copies", spent)
    parts = 1 + int(keyed.agg(F.coalesce(F.sum(F.col("n") * (1 - least) + 1), F.lit(0))).first()[0]) // PACKED
    own = keyed.join(broadcast_if_small(copies, MOST_IDS), ["doc_id", "node"], "left_anti")
    again = settle(_repeated(own, parts), "shingle-again", spent)
    held: list[str] = []
    postings = again.join(nodes.select("node", "n", "met"), "node").dropDuplicates(["k", "node"])
    postings = settle(postings.select("k", "node", "n", "met", "place"), "shingle-postings", held)
    discard(spark, spent)

    done: list[str] = []  # read until the last pairs are compared
    tested = [settle(_by_fingerprint(nodes).groupBy("u", "v").agg(F.min("u").alias("at")), "shingle-pairs", done)]
    roots = components(_compared(tested[0], rows, nodes, size, least))
    open_ = postings
    for rnd in range(HUB_ROUNDS):
        now: list[str] = []
        open_ = _open(open_, roots, now)
        discard(spark, held)
        held = now
        pairs = settle(_with_hubs(open_, nodes, rnd, least), "shingle-pairs", spent)
        tested.append(settle(_new(pairs, tested), "shingle-pairs", done))
        discard(spark, spent)
        roots = components(roots.unionByName(_compared(tested[-1], rows, nodes, size, least)))
    now = []
    open_ = _open(open_, roots, now)
    discard(spark, held)
    met = settle(_remaining(open_, least, now), "shingle-pairs", spent)
    discard(spark, now)
    pairs = settle(_new(met, tested), "shingle-pairs", done)
    discard(spark, spent)
    roots = settle(components(roots.unionByName(_compared(pairs, rows, nodes, size, least))), "shingle-roots")
    discard(spark, done)
    rooted = settle(_rooted(named.select("doc_id", "node"), roots).select("doc_id", "root"), "shingle-rooted")
    return rooted.join(rooted.groupBy("root").agg(F.min("doc_id").alias("component_id")), "root").select("doc_id", "component_id")


def _open(postings: DataFrame, roots: DataFrame, spent: list[str] | None = None) -> DataFrame:
    """Postings with the root of their node, of the keys that hold more than one root."""
    rooted = _rooted(postings.drop("root"), roots)
    ends = rooted.groupBy("k").agg(F.min("root").alias("r0"), F.max("root").alias("r1")).filter("r0 <> r1").select("k")
    return settle(rooted.join(ends, "k", "left_semi"), "shingle-open", spent)


def _new(pairs: DataFrame, tested: list[DataFrame]) -> DataFrame:
    """The pairs that were not tested before, either way round, each once."""
    before = tested[0].select("u", "v")
    for t in tested[1:]:
        before = before.unionByName(t.select("u", "v"))
    before = before.unionByName(before.select(F.col("v").alias("u"), F.col("u").alias("v")))
    new = pairs.join(before, ["u", "v"], "left_anti")
    low, high = F.least("u", "v").alias("low"), F.greatest("u", "v").alias("high")
    return new.groupBy(low, high).agg(F.min(F.struct("u", "v", "at")).alias("x")).select("x.u", "x.v", "x.at")


def _with_hubs(open_: DataFrame, nodes: DataFrame, rnd: int, least: float) -> DataFrame:
    """(u, v, at): every node outside the groups of the hubs of its keys, with one of these hubs: of those
    that may be similar, the one whose fingerprint is nearest, if it is within HUB_BITS.

    First, a key's hub is the node whose shingles are met most often: of copies with changes, most likely
    what they are copies of. Later it is drawn, for each key anew."""
    first = F.xxhash64("node", "k", F.lit(rnd)) if rnd else -F.col("met").cast("long")
    hubs = open_.groupBy("k").agg(F.min(F.struct(first.alias("h"), "node", "n", "place", "root")).alias("hub"))
    hubs = hubs.select("k", *[F.col(f"hub.{c}").alias(x) for c, x in (("node", "hub"), ("n", "m"), ("place", "spot"), ("root", "its"))])
    met = open_.join(hubs, "k").filter((F.col("root") != F.col("its")) & _may_be_similar(least, "place", "spot")).select("node", "hub").distinct()
    prints = nodes.select("node", "fp")
    met = met.join(prints, "node").join(prints.select(F.col("node").alias("hub"), F.col("fp").alias("its")), "hub")
    nearest = met.groupBy("node").agg(F.min(F.struct(F.bit_count(F.col("fp").bitwiseXOR(F.col("its"))).alias("d"), "hub")).alias("x")).filter(F.col("x.d") <= HUB_BITS)
    return nearest.select(F.col("node").alias("u"), F.col("x.hub").alias("v"), F.col("x.hub").alias("at"))


def _remaining(open_: DataFrame, least: float, spent: list[str] | None = None) -> DataFrame:
    """(u, v, at): the pairs of nodes of different roots that share a key and may be similar, each under the
    first key that it shares.

    In a key, only the nodes outside its most frequent root are joined with the others. `before` holds
    the last of a node's earlier keys that are open as well; a pair that shares one of them was met there.
    """
    order = Window.partitionBy("node").orderBy("place").rowsBetween(-EARLIER_KEYS, -1)
    open_ = settle(open_.withColumn("before", F.collect_list("k").over(order)), "shingle-open", spent)
    main = open_.groupBy("k", "root").count().groupBy("k").agg(F.max(F.struct("count", "root")).alias("x")).select("k", F.col("x.root").alias("main"))
    a = open_.join(main, "k").filter("root <> main")
    b = open_.select("k", F.col("node").alias("other"), F.col("n").alias("m"), F.col("place").alias("spot"), F.col("root").alias("its"), F.col("before").alias("past"))
    once = (F.col("its") == F.col("main")) | (F.col("node") < F.col("other"))
    apart = (F.col("root") != F.col("its")) & once & _may_be_similar(least, "place", "spot") & ~F.arrays_overlap("before", "past")
    return a.join(b, "k").filter(apart).groupBy(F.col("node").alias("u"), F.col("other").alias("v")).agg(F.min("k").alias("at"))
