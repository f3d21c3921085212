import numpy as np
import pandas as pd
import pytest

import corpus_pipeline
from proxigraph.llm import shingle_sets, simhash_pivots

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def words(text):
    low = bytes(c + 32 if 65 <= c <= 90 else c for c in (text or "").encode())
    return low.split()


def brute_sets(texts, size=5):
    out = []
    for t in texts:
        w = words(t)
        out.append({b" ".join(w[i: i + size]) for i in range(max(1, len(w) - size + 1))} if w else set())
    return out


def brute_components(ids, sets, least=0.8):
    label = list(range(len(ids)))

    def root(i):
        while label[i] != i:
            i = label[i]
        return i

    for i in range(len(ids)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if (not sets[i] and not sets[j]) or (both and both >= least * (len(sets[i]) + len(sets[j]) - both) - 1e-9):
                a, b = root(i), root(j)
                label[max(a, b)] = min(a, b)
    low = {}
    for i, k in enumerate(ids):
        low[root(i)] = min(low.get(root(i), k), k)
    return {k: low[root(i)] for i, k in enumerate(ids)}


def near_texts():
    """Chains and groups of near copies about the limit, copies, and texts that share a common line."""
    base = [f"w{i}" for i in range(120)]
    out = []
    for step in range(8):  # neighbours differ in `step + 1` words; shingles lost: up to 5 a word
        t = list(base)
        for k in range(step + 1):
            t[10 + 11 * k] = f"x{step}"
        out.append(" ".join(t))
    chain = [f"c{i}" for i in range(100)]
    for step in range(6):
        out.append(" ".join(chain[4 * step:] + [f"c{100 + i}" for i in range(4 * step)]))
    line = "this line is on every page of the site "
    out += [line + " ".join(f"t{d}{i}" for i in range(40)) for d in range(30)]
    out += [out[0].upper(), "one two three four", "One  two\tthree four", "one two three", "", None, " \n"]
    # sizes where the similarity is exactly 0.8: four of five shingles
    return [*out, "a b c d e f g h", "a b c d e f g h i"]


@pytest.mark.parametrize("sampled", [True, False])
def test_near_copies_equal_brute_force(spark, monkeypatch, sampled):
    if not sampled:
        monkeypatch.setattr(shingle_sets, "COMMON", 1 << 40)
    texts = near_texts()
    ids = [7 * i % 101 for i in range(len(texts))]
    want = brute_components(ids, brute_sets(texts))
    assert len(set(want.values())) < len(ids) - 8
    rows = spark.createDataFrame([(i, t, "en", "a", 0) for i, t in zip(ids, texts, strict=True)], DOCS)
    got = {r["doc_id"]: r["component_id"] for r in shingle_sets.similar(rows, 5, 0.8).collect()}
    assert got == want


def test_stage_drops_near_copies_that_fingerprints_pass(spark, small_dir):
    d = pd.read_parquet(f"{small_dir.replace('0.001', '0.01')}/documents.parquet")
    copies = d[d.doc_id.isin([2, 56])]
    rows = spark.createDataFrame([(int(r.doc_id), r.text, r.lang, r.source, int(r.n_chars)) for r in copies.itertuples()], DOCS)
    assert simhash_pivots.keep_one(rows).count() == 2
    assert [r["doc_id"] for r in corpus_pipeline.drop_near_duplicates(spark, rows, small_dir).collect()] == [2]


def test_all_documents_equal_brute_force(spark, small_dir):
    d = spark.read.parquet(f"{small_dir}/documents.parquet")
    plain = d.toPandas()
    want = brute_components(plain.doc_id.tolist(), brute_sets(plain.text))
    got = {r["doc_id"]: r["component_id"] for r in shingle_sets.similar(d, 5, 0.8).collect()}
    assert got == want
    assert shingle_sets.similar(d.limit(0), 5, 0.8).count() == 0


def test_odd_rows_stay_whole(spark, small_dir):
    rows = spark.createDataFrame([(1, None, "en", "a", None), (2, "", "en", "a", 0), (None, "no id", "en", "a", 5), (None, "no id", "en", "a", 5), (3, "x", None, None, 1), (3, "x", None, None, 1)], DOCS)
    kept = corpus_pipeline.drop_near_duplicates(spark, rows, small_dir)
    assert kept.columns == rows.columns and sorted(r["doc_id"] or -1 for r in kept.collect()) == [-1, -1, 1, 3]


def test_only_texts_that_may_be_similar_are_sent(spark, monkeypatch):
    """A line that many texts share makes no pair of them travel (before: texts went to cells for every pair that
    shared an early key, whose number grows with the square of the table)."""
    monkeypatch.setattr(shingle_sets, "COMMON", 1 << 40)
    line = "this line is on every page of the site and never changes "
    texts = [line + " ".join(f"t{d}x{i}" for i in range(60)) for d in range(40)]
    sent, settle = [], shingle_sets.settle

    def noted(df, name, *more):
        out = settle(df, name, *more)
        if name == "shingle-needed":
            sent.append(out.count())
        return out

    monkeypatch.setattr(shingle_sets, "settle", noted)
    rows = spark.createDataFrame([(i, t, "en", "a", 0) for i, t in enumerate([*texts, texts[7] + " end"])], DOCS)
    got = {r["doc_id"]: r["component_id"] for r in shingle_sets.similar(rows, 5, 0.8).collect()}
    assert got == {i: i for i in range(40)} | {40: 7}
    assert sent and sum(sent) == 2


@pytest.mark.parametrize("n", [1, 40, 900, 5000])
def test_sketches_bound_what_only_one_set_holds(n):
    rng = np.random.default_rng(n)
    a = np.unique(rng.integers(0, 1 << 64, n, dtype=np.uint64))
    for kept in (0, 0.5, 0.9, 1):
        b = np.unique(np.append(a[: int(len(a) * kept)], rng.integers(0, 1 << 64, max(1, n // 7), dtype=np.uint64)))
        apart = len(np.setxor1d(a, b))
        bound = shingle_sets.least_apart(shingle_sets.sketch(a), shingle_sets.sketch(b))
        assert bound <= apart and bound == shingle_sets.least_apart(shingle_sets.sketch(b), shingle_sets.sketch(a))
    other = np.unique(rng.integers(0, 1 << 64, n, dtype=np.uint64))  # an unrelated set of that size cannot have 0.8
    assert n < 40 or shingle_sets.least_apart(shingle_sets.sketch(a), shingle_sets.sketch(other)) > (len(a) + len(other)) / 9


@pytest.mark.parametrize("packed", [500_000, 16])
def test_keys_of_several_rows(spark, monkeypatch, packed):
    """The keys that rows share, in any order and however many are held at once."""
    monkeypatch.setattr(shingle_sets, "PACKED", packed)
    rng = np.random.default_rng(5)
    keys = [[int(k) for k in rng.choice(400, size=rng.integers(0, 9), replace=False)] for _ in range(120)]
    keys = [[(k * 0x9E3779B97F4A7C15 + 77) % (1 << 64) - (1 << 63) for k in [*ks, 1000]] for ks in keys]
    rows = spark.createDataFrame(list(enumerate(keys)), "node long, keys array<long>").repartition(3)
    every = [(k, node, place) for node, ks in enumerate(keys) for place, k in enumerate(ks)]
    many = pd.Series([k for k, _, _ in every]).value_counts()
    for parts in (1, 7):
        got = [tuple(r) for r in shingle_sets._repeated(rows, parts).collect()]
        assert sorted(got) == sorted(x for x in every if many[x[0]] > 1)
    assert shingle_sets._repeated(rows.limit(0), 1).count() == 0
