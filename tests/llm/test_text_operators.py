import hashlib
import html
import time
import zlib

import numpy as np
import pandas as pd
import pytest
import regex
import xxhash
from pyspark.sql import functions as F

from proxigraph.llm import html_templates, license_patience, packing, pareto_mix, ppm_langid, simhash_pivots, token_files, token_ids, toxicity_ftrl

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, rows):
    return spark.createDataFrame([(i, t, lang, src, None if t is None else len(t)) for i, t, lang, src in rows], DOCS)


def odd_rows():
    """Nulls in any column, empty and blank texts, ties, repeated rows and a long text."""
    return [
        (1, None, "en", "a"), (2, "", "en", "a"), (3, " \t\n ", None, None), (4, "One two Three four five.", "en", "a"), (4, "One two Three four five.", "en", "a"),
        (5, "one two three four five.", "de", "b"), (None, "no id at all here", "fr", "b"), (6, "word " * 60_000, "en", None), (7, "日本語 text é ñ", "es", "c"), (8, "x", None, "c"),
    ]


def brute_fingerprint(text):
    low = bytes(c + 32 if 65 <= c <= 90 else c for c in (text or "").encode())
    words = regex.findall(rb"[^\x20\x09-\x0D]+", low)
    if not words:
        return 0
    shingles = [b" ".join(words[i: i + 3]) for i in range(max(1, len(words) - 2))]
    counts = [0] * 64
    for s in shingles:
        h = xxhash.xxh64_intdigest(s, 42)
        for b in range(64):
            counts[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * counts[b] > len(shingles))


def brute_components(ids, prints):
    label = list(range(len(ids)))
    changed = True
    while changed:
        changed = False
        for i in range(len(ids)):
            for j in range(i):
                if (prints[i] ^ prints[j]).bit_count() <= 2 and label[i] != label[j]:
                    label[i] = label[j] = min(label[i], label[j])
                    changed = True
    low = {}
    for i, k in enumerate(label):
        if ids[i] is not None:
            low[k] = min(low.get(k, ids[i]), ids[i])
    return [low.get(k) for k in label]


def test_fingerprints_equal_brute_force(spark, small_dir):
    texts = pd.read_parquet(f"{small_dir}/documents.parquet").text.tolist()[:80] + [t for _, t, _, _ in odd_rows()] + ["A b", "É Ö"]
    assert [int(x) for x in simhash_pivots.fingerprint_texts(texts)] == [brute_fingerprint(t) for t in texts]


def test_near_duplicates_equal_brute_force(spark, small_dir):
    base = spark.read.parquet(f"{small_dir}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars")
    rows = base.unionByName(docs_of(spark, [(i + 1000 if i else i, t, a, b) for i, t, a, b in odd_rows()])).withColumn("fp", F.lit(1)).withColumn("component_id", F.lit("x"))
    got = simhash_pivots.near_duplicates(rows).toPandas()
    plain = rows.toPandas()
    prints = [brute_fingerprint(t) for t in plain.text]
    ids = [None if pd.isna(i) else int(i) for i in plain.doc_id]
    want = sorted(zip([-1 if i is None else i for i in ids], prints, [-1 if c is None else c for c in brute_components(ids, prints)], strict=True))
    have = sorted((-1 if pd.isna(a) else int(a), int(b) & (1 << 64) - 1, -1 if pd.isna(c) else int(c)) for a, b, c in got[["doc_id", "fp", "component_id"]].itertuples(index=False))
    assert have == want


def test_links_lose_nothing_in_a_dense_ball(spark):
    rng = np.random.default_rng(0)
    centre = int(rng.integers(1 << 62))
    prints = {centre} | {centre ^ (1 << a) for a in range(40)} | {centre ^ (1 << a) ^ (1 << b) for a in range(12) for b in range(a)} | {int(x) for x in rng.integers(1 << 62, size=500)}
    chain = [centre ^ 0xFFFF << 40]
    for k in range(10):
        chain.append(chain[-1] ^ (3 << 2 * k))
    prints = sorted(prints | set(chain))
    df = spark.createDataFrame([(p, i) for i, p in enumerate(prints)], "fp long, n long")
    from proxigraph.llm.components import components

    roots = {r["u"]: r["v"] for r in components(simhash_pivots.links(df.select("fp"))).collect()}
    got = {}
    for i, p in enumerate(prints):
        got.setdefault(roots.get(p, p), []).append(i)
    want = {}
    for i, c in enumerate(brute_components(list(range(len(prints))), prints)):
        want.setdefault(c, []).append(i)
    assert sorted(got.values()) == sorted(want.values())


def test_keep_one(spark):
    rows = docs_of(spark, odd_rows())
    kept = simhash_pivots.keep_one(rows)
    assert kept.columns == rows.columns
    assert sorted((r["doc_id"] or -1) for r in kept.collect()) == [-1, 1, 4, 6, 7, 8]
    none = simhash_pivots.keep_one(docs_of(spark, []))
    assert none.count() == 0 and simhash_pivots.near_duplicates(docs_of(spark, [])).count() == 0


def test_toxicity_held_out(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "text"), spark.read.parquet(f"{d}/labels.parquet")
    model = toxicity_ftrl.fit(docs, labels)
    out = toxicity_ftrl.score(docs, model).withColumn("held", toxicity_ftrl.fold() == 0).join(labels.select("doc_id", "toxic"), "doc_id").filter("held").toPandas()
    hit = out[out.toxic == 1].predicted.mean()
    wrong = out[out.toxic == 0].predicted.mean()
    assert hit >= 0.8 and wrong <= 0.01
    assert len(model[0]) < 50_000
    assert [zlib.crc32(str(i).encode()) % 5 == 0 for i in out.doc_id] == [True] * len(out)


def test_toxicity_odd_tables(spark):
    labels = spark.createDataFrame([(4, 1), (4, 0), (5, 0), (None, 1), (8, None), (77, 1)], "doc_id long, toxic int")
    rows = docs_of(spark, odd_rows()).withColumn("score", F.lit("x")).withColumn("a b", F.lit(1))
    out = toxicity_ftrl.score(rows, toxicity_ftrl.fit(rows, labels)).toPandas()
    assert len(out) == len(odd_rows()) and out.score.between(0, 1).all() and "a b" in out.columns
    nothing = toxicity_ftrl.fit(rows, labels.filter("false"))
    assert set(toxicity_ftrl.score(rows, nothing).toPandas().score) == {0.0}
    assert toxicity_ftrl.score(docs_of(spark, []), nothing).count() == 0


def test_training_equals_plain_loops(spark):
    """FTRL-proximal coordinate by coordinate, with dicts."""
    rng = np.random.default_rng(6)
    rows = [(np.append(np.unique(rng.integers(0, 60, size=12)), 1 << toxicity_ftrl.BITS).astype(np.int32), int(rng.random() < 0.4)) for _ in range(300)]
    z, n = {}, {}

    def weight(i):
        if abs(z.get(i, 0.0)) <= toxicity_ftrl.L1:
            return 0.0
        sign = 1.0 if z[i] > 0 else -1.0
        return -(z[i] - sign * toxicity_ftrl.L1) / ((toxicity_ftrl.BETA + n[i] ** 0.5) / toxicity_ftrl.ALPHA + toxicity_ftrl.L2)

    for _ in range(toxicity_ftrl.EPOCHS):
        for features, y in rows:
            w = {int(i): weight(int(i)) for i in features}
            g = (1 / (1 + np.exp(-sum(w.values()))) - y) * (toxicity_ftrl.POSITIVE if y else 1.0)
            for i, wi in w.items():
                old = n.get(i, 0.0)
                n[i] = old + g * g
                z[i] = z.get(i, 0.0) + g - (n[i] ** 0.5 - old ** 0.5) / toxicity_ftrl.ALPHA * wi
    want = {i: weight(i) for i in sorted(z) if abs(z[i]) > toxicity_ftrl.L1}
    at, w = toxicity_ftrl.train(rows)
    assert want and at.tolist() == list(want) and np.allclose(w, list(want.values()))


def test_repeated_ids_are_learnt_once(spark):
    labels = spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id long, toxic int")
    rows = docs_of(spark, [(i, "bad words here" if i % 2 else "good words there", "en", "a") for i in range(40)])
    again = docs_of(spark, [(1, "bad words here", "en", "a")] * 200)
    a, b = toxicity_ftrl.fit(rows, labels), toxicity_ftrl.fit(rows.unionByName(again), labels)
    assert a[0].tolist() == b[0].tolist() and a[1].tolist() == b[1].tolist()


def test_junk_is_not_recognised(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = ppm_langid.fit(docs)
    rows = docs_of(spark, [
        (1, "BE!! SCUM!! SCUM!! TION!! A.!! " * 9, "en", "a"), (2, 'token = "2abc3ff2ca8fb1e4c565a0eb63815530a948bdde" 4761598977407687 8316107434564120', "en", "a"), (3, "A.", "en", "a"), (4, "Re.", "en", "a"),
        (5, None, "en", "a"), (6, "123 456", "en", "a"),
    ])
    out = ppm_langid.predict(rows.unionByName(docs), model).withColumn("ok", ppm_langid.recognised()).toPandas()
    assert out[out.doc_id.isin([3, 4])][out.text.isin(["A.", "Re."])].ok.all()
    assert not out.iloc[:6][out.iloc[:6].doc_id.isin([1, 2, 5, 6])].ok.any()
    assert out.ok.mean() > 0.98


def test_many_languages_make_a_smaller_model(spark, monkeypatch):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    big = ppm_langid.fit(docs)
    monkeypatch.setattr(ppm_langid, "MODEL_BYTES", big.cost.nbytes // 3)
    small = ppm_langid.fit(docs)
    assert small.cost.nbytes <= big.cost.nbytes // 3 and small.langs == big.langs


def test_language_held_out(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    out = ppm_langid.predict(docs.select("doc_id", "text", "lang"), ppm_langid.fit(docs)).withColumn("held", toxicity_ftrl.fold() == 0).filter("held").toPandas()
    assert (out.lang == out.lang_pred).mean() > 0.97 and out.score.between(0, 1).all()


def brute_ppm(texts_by_lang, langs):
    """Counts of every context as dicts, and method C with exclusion byte by byte."""
    counts = {lang: {} for lang in langs}
    seen = set()
    for lang, texts in texts_by_lang.items():
        for t in texts:
            for i in range(len(t)):
                seen.add(t[i])
                for o in range(min(i, 3) + 1):
                    counts[lang].setdefault(t[i - o: i], {}).setdefault(t[i], 0)
                    counts[lang][t[i - o: i]][t[i]] += 1
    total = {}
    for lang in langs:
        for c, table in counts[lang].items():
            total[c] = total.get(c, 0) + sum(table.values())
    kept = {c for c, n in total.items() if n >= ppm_langid.LEAST_CONTEXT} | {b""}

    def nats(lang, text):
        out = 0.0
        for i, sym in enumerate(text):
            gone = set()
            for o in range(min(i, 3), -1, -1):
                c = text[i - o: i]
                if c not in kept or any(b not in seen for b in c):
                    continue
                table = {s: n for s, n in counts[lang].get(c, {}).items() if s not in gone}
                if not table:
                    continue
                n, d = sum(table.values()), len(table)
                if sym in table:
                    out -= np.log(table[sym] / (n + d))
                    break
                out -= np.log(d / (n + d))
                gone |= set(table)
            else:
                out += np.log(256 - len(gone))
        return out

    return nats


def test_code_lengths_equal_brute_force(spark):
    texts = {"aa": [b"the cat sat on the mat and the hat " * 4, b"that cat"], "bb": [b"der hund und die katze und der hut " * 4]}
    langs = ["aa", "bb"]
    parts = [(j, *ppm_langid.count_contexts(texts[lang])) for j, lang in enumerate(langs)]
    model = ppm_langid.Model(langs, np.concatenate([k for _, k, _ in parts]), np.concatenate([np.full(len(k), j) for j, k, _ in parts]), np.concatenate([c for _, _, c in parts]))
    nats = brute_ppm(texts, langs)
    probes = ["the cat and the hut", "und ZZ the", "", "x", "é der"]
    got = model.code_lengths([*probes, None])
    want = [[nats(lang, p.encode()) for lang in langs] for p in probes] + [[0.0, 0.0]]
    assert np.allclose(got, want, atol=1e-3)


def test_language_odd_tables(spark):
    rows = docs_of(spark, [*odd_rows(), (9, "12345 !!", "en", "a")]).withColumn("lang_pred", F.lit(3))
    out = ppm_langid.predict(rows, ppm_langid.fit(rows)).toPandas()
    pred = {(-1 if pd.isna(i) else int(i)): p for i, p in zip(out.doc_id, out.lang_pred, strict=True)}
    assert pred[1] == pred[2] == pred[3] == pred[9] == "und" and pred[4] != "und"
    empty = ppm_langid.fit(docs_of(spark, []))
    assert set(ppm_langid.predict(rows, empty).toPandas().lang_pred) == {"und"}


def library_ids(texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(token_ids.default_vocabulary())
    t.encode_special_tokens = True
    return [e.ids for e in t.encode_batch([x or "" for x in texts], add_special_tokens=False)]


def test_ids_equal_the_library(spark, small_dir):
    texts = pd.read_parquet(f"{small_dir}/documents.parquet").text.tolist()[:60] + [t for _, t, _, _ in odd_rows()]
    texts += ["it's a dog's  life\n\n\n x", "tab\t\tx  \n y ", "²3½ a_b __ c", "<|endoftext|> hi", "a\x1cb c\xa0d", "ﬁ ̈x", "I'll've 'tis '  ''s", "don't 's 're y'll's ''s a,'s 9'd \n'm\n\n't r'r", "x  ", "\n", " a", "a\n \nb \n", "a\x00b", "é'l'llx"]
    got = []
    for _, _, ids, sizes in token_ids.Encoder(token_ids.default_vocabulary()).encode(texts):
        ends = np.cumsum(sizes)
        got += [ids[a - n: a].tolist() for a, n in zip(ends, sizes, strict=True)]
    assert got == library_ids(texts)


def test_forgetting_changes_nothing(spark, monkeypatch):
    monkeypatch.setattr(token_ids, "MOST_REMEMBERED", 50)
    texts = [f"some words number {i} and word{i} again{i * 7}" for i in range(300)]
    monkeypatch.setattr(token_ids, "CHUNK_BYTES", 400)
    got = []
    for _, _, ids, sizes in token_ids.Encoder(token_ids.default_vocabulary()).encode(texts):
        ends = np.cumsum(sizes)
        got += [ids[a - n: a].tolist() for a, n in zip(ends, sizes, strict=True)]
    assert got == library_ids(texts)


def crc(ids):
    return zlib.crc32(np.array(ids, dtype="<u4").tobytes())


def test_packing_of_odd_tables(spark):
    rows = docs_of(spark, odd_rows()).withColumn("slice", F.lit(1))
    out = packing.pack_documents(rows, capacity=64).toPandas()
    want = {}
    for (i, t, _, _), ids in zip(odd_rows(), library_ids([t for _, t, _, _ in odd_rows()]), strict=True):
        full = [*ids, 0]
        first = len(full) % 64 or 64
        cuts = [0, *range(first, len(full) + 1, 64)]
        for p, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
            want.setdefault((i, p, a, b - a, crc(full[a:b])), 0)
            want[(i, p, a, b - a, crc(full[a:b]))] += 1
    got = {}
    for r in out.itertuples():
        key = (None if pd.isna(r.doc_id) else int(r.doc_id), r.piece, r.start, r.length, r.ids_crc32)
        got[key] = got.get(key, 0) + 1
    assert got == want
    for _, g in out.groupby("sequence_id"):
        at = 0
        for r in g.sort_values("offset").itertuples():
            assert r.offset == at
            at += r.length
        assert at <= 64
    assert packing.pack_documents(docs_of(spark, [])).count() == 0


@pytest.mark.parametrize("seed", range(30))
def test_plans_are_whole_and_tight(seed):
    rng = np.random.default_rng(seed)
    capacity = int(rng.choice([6, 12, 30, 100, 2048]))
    sizes = rng.integers(1, capacity + 1, size=min(capacity, 60))
    counts = {int(s): int(n) for s, n in zip(sizes, rng.integers(0, 40, size=len(sizes)), strict=True)}
    p = packing.plan(counts, capacity)
    fill = {}
    seg = list(zip(p.length.tolist(), p.rank.tolist(), p.first.tolist(), p.offset.tolist(), strict=True))
    for i, (size, rank, first, offset) in enumerate(seg):
        stop = seg[i + 1][1] if i + 1 < len(seg) and seg[i + 1][0] == size else counts[size]
        for k in range(stop - rank):
            fill.setdefault(first + k, []).append((offset, size))
    assert sum(map(len, fill.values())) == sum(counts.values())
    for items in fill.values():
        at = 0
        for offset, size in sorted(items):
            assert offset == at
            at += size
        assert at <= capacity
    # never more sequences than first-fit by decreasing length on the pieces one by one
    bins = []
    for s in sorted((s for s, n in counts.items() for _ in range(n)), reverse=True):
        for k, b in enumerate(bins):
            if b + s <= capacity:
                bins[k] += s
                break
        else:
            bins.append(s)
    assert p.sequences <= len(bins) + 1


def test_token_files_round_trip(spark, tmp_path):
    rows = docs_of(spark, odd_rows()).withColumn("start", F.lit("x")).repartition(3)
    folder = f"file://{tmp_path}/files"
    manifest = token_files.write(rows, folder)
    out = token_files.read(spark, folder, with_ids=True).toPandas().sort_values("start")
    plain = sorted(odd_rows(), key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or ""))
    ids = library_ids([t for _, t, _, _ in plain])
    at = 0
    for r, (i, _, _, _), own in zip(out.itertuples(), plain, ids, strict=True):
        assert (None if pd.isna(r.doc_id) else r.doc_id) == i
        assert (r.start, r.n_tokens, r.ids_crc32, list(r.ids)) == (at, len(own) + 1, crc([*own, 2]), [*own, 2])
        at += len(own) + 1
    assert manifest["ids"] == at and manifest["docs"] == len(plain)
    empty = f"file://{tmp_path}/none"
    assert token_files.write(docs_of(spark, []), empty)["shards"] == [] and token_files.read(spark, empty).count() == 0


def test_mixing_odd_tables(spark):
    rows = docs_of(spark, odd_rows()).withColumn("copies", F.lit("x")).withColumn("extra", F.lit(1)).withColumn("part", F.lit(2))
    a = pareto_mix.mix(rows)
    out = a.toPandas()
    assert {"copies", "extra", "part"} <= set(out.columns)
    assert len(out) == len(odd_rows()) and (out.taken <= 2 * out["size"]).all()
    total = out["size"].sum() * 1.5
    by = out.fillna({"source": "~"}).groupby("source").agg(target=("target", "first"), size=("source_size", "first"), taken=("taken", "sum"))
    assert abs(by.target.sum() - min(total, 2 * by["size"].sum())) < 1e-6 and (by.target <= 2 * by["size"] + 1e-9).all()
    again = pareto_mix.mix(rows.repartition(7)).toPandas()
    assert sorted(out.taken) == sorted(again.taken)
    assert pareto_mix.mix(docs_of(spark, [])).count() == 0
    copies = pareto_mix.repeated(rows)
    assert copies.columns == rows.columns and copies.count() == out[pareto_mix.TIMES].sum()


def test_mixing_reaches_targets(spark, small_dir):
    out = pareto_mix.mix(spark.read.parquet(f"{small_dir.replace('0.001', '0.1')}/documents.parquet").select("doc_id", "source", "text")).toPandas()
    for _, g in out.groupby("source", dropna=False):
        assert abs(g.taken.sum() - g.target.iloc[0]) <= g["size"].max()


def test_inclusion_odds_are_unequal(spark):
    rng = np.random.default_rng(4)
    sizes = {i: int(s) for i, s in enumerate(rng.integers(1, 100, size=3000))}
    rows = spark.createDataFrame([(i, "a", s) for i, s in sizes.items()], "doc_id long, source string, size long")
    out = pareto_mix.mix(rows, weights=(1,), share=0.4).toPandas().set_index("doc_id")
    mean, part = sum(sizes.values()) / len(sizes), 0.4
    u = {i: (int(hashlib.md5(f"42:{i}".encode()).hexdigest()[:13], 16) + 0.5) / (1 << 52) for i in sizes}
    order = sorted(sizes, key=lambda i: (u[i] / (1 - u[i]) / (part / (1 - part) * (sizes[i] / mean)), i))
    goal, at, want = 0.4 * sum(sizes.values()), 0, set()
    for i in order:
        if at + sizes[i] > goal and at + sizes[i] - goal >= goal - at:
            break
        at += sizes[i]
        want.add(i)
    assert set(out.index[out.taken > 0]) == want
    long, short = ([i for i in sizes if a <= sizes[i] < b] for a, b in ((75, 100), (1, 25)))
    assert sum(i in want for i in long) / len(long) > 2 * sum(i in want for i in short) / len(short)


def test_boosted_documents_are_taken_more_often(spark):
    rows = spark.createDataFrame([(i, "a", 10) for i in range(2000)] + [(5000 + i, "b", 10) for i in range(8000)], "doc_id long, source string, size long")
    boost = F.when(F.col("doc_id") % 2 == 0, 5.0).otherwise(1.0)
    out = pareto_mix.mix(rows, weights=(1, 4), share=0.5, boost=boost).toPandas()
    share = out.groupby(out.doc_id % 2).apply(lambda g: (g.taken > 0).mean(), include_groups=False)
    assert share[0] > 1.5 * share[1]


def brute_text(page):
    article = regex.search(r"<article>(.*?)</article>", page, regex.S)[1]
    blocks = (" ".join(html.unescape(regex.sub(r"<[^>]*>", " ", b)).split()) for b in regex.split(r"</?(?:p|h1|div|br)>", article))
    return "\n".join(b for b in blocks if b)


def test_pages_equal_their_articles(spark, small_dir):
    pages = spark.read.parquet(f"{small_dir.replace('0.001', '0.01')}/pages.parquet")
    got = {r["page_id"]: r["text"] for r in html_templates.extract(pages).collect()}
    assert got == {r["page_id"]: brute_text(r["html"]) for r in pages.collect()}


def test_page_structures(spark):
    page = """<html><body class="has-sidebar"><header><h1>Site</h1></header><div id=cookie-notice>we use cookies</div><main><article><header class="entry-header"><h1>Title &eacute;</h1>
    <span>by me</span></header><p>One <b>two</b>&nbsp;three<p>Four<ul><li>a<li>b</ul><div class="share">tweet</div><section id="comments"><article class="comment"><p>nice</p></article></section>
    <form><p>x</p></form></article><aside>rel</aside></main><footer>f</footer><script>var t="</p>";</script></body></html>"""
    assert html_templates.Page(page).text(frozenset()) == ["Title é", "One two three", "Four", "a", "b"]
    assert html_templates.Page("plain & simple &lt; <!-- x").text(frozenset()) == ["plain & simple <"]


def test_recurring_subtrees_go_and_copies_stay(spark):
    def page(body):
        return f"<html><body><div><span>Home of things</span> <span>About us</span></div><div><p>{body}</p></div><table><tr><td>All rights</td></tr></table></body></html>"

    rows = [(i, "http://h.example/x", page(f"Story number {i} tells its own tale.")) for i in range(20)] + [(i, "http://h.example/y", page("The same story again.")) for i in range(20, 30)]
    rows += [(98, None, None), (99, "http://h.example/", ""), (97, "other", page("Alone."))]
    out = {r["page_id"]: r["text"] for r in html_templates.extract(spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("hash", F.lit(1))).collect()}
    assert all(out[i] == f"Story number {i} tells its own tale." for i in range(20))
    assert all(out[i] == "The same story again." for i in range(20, 30))
    assert out[98] == "" and out[99] == "" and "Alone." in out[97] and "Home" in out[97]
    none = spark.createDataFrame([], "page_id long, url string, html string")
    assert html_templates.extract(none).count() == 0


def test_templates_decide(spark, monkeypatch):
    """Pages without declared roles, and blocks in articles: what is not counted as template stays."""
    def plain(i):
        return f"<html><body><div><p>Welcome to the site of things and more</p><ul><li>All stories</ul></div><div><p>Story {i} is told here at length.</p><p>It goes on {i * 7}.</p></div><div><p>Read us daily</p></div></body></html>"

    def article(i, site, quote=""):
        return f"<html><body><article><h1>Title {i}</h1><p>By the desk of {site}</p><p>Part one of {i} {site}.</p><p>Part two of {i}{quote}.</p><p>Part three {i}.</p><p>Part four {i}.</p><p>Part five {i}.</p><p>Follow {site} for more</p></article></body></html>"

    rows = [(i, "http://plain.example/a", plain(i)) for i in range(30)]
    rows += [(100 + i, "http://one.example/a", article(i, "one")) for i in range(30)] + [(200 + i, "http://two.example/a", article(i, "two")) for i in range(30)]
    # near copies of one article, and a first paragraph that articles of many hosts share
    rows += [(300 + i, "http://near.example/a", article(5, "near", f" edit {i}")) for i in range(40)]
    rows += [(400 + i, f"http://h{i % 4}.example/a", f"<article><h1>T{i}</h1><p>The shared opening line.</p><p>a{i}</p><p>b{i}</p><p>c{i}</p><p>d{i}</p><p>e{i}</p><p>f{i}</p></article>") for i in range(40)]
    # a quoted passage at changing places of one host's articles
    for i in range(40):
        parts = [f"<p>x{i}-{j}</p>" for j in range(7)]
        parts.insert(i % 8, "<p>As the saying goes, nothing is new.</p>")
        rows.append((500 + i, "http://quote.example/a", "<article><h1>Q</h1>" + "".join(parts) + "</article>"))
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    out = {r["page_id"]: r["text"] for r in html_templates.extract(pages).collect()}
    for i in range(30):
        assert out[i] == f"Story {i} is told here at length.\nIt goes on {i * 7}."
        assert out[100 + i] == f"Title {i}\nPart one of {i} one.\nPart two of {i}.\nPart three {i}.\nPart four {i}.\nPart five {i}."
        assert out[200 + i].count("\n") == 5 and "desk" not in out[200 + i]
    assert all("desk of near" in out[300 + i] and f"edit {i}" in out[300 + i] for i in range(40))
    assert all("shared opening" in out[400 + i] for i in range(40)) and all("nothing is new" in out[500 + i] for i in range(40))
    none = {r["page_id"]: r["text"] for r in html_templates.extract(pages, least_pages=1 << 30).collect()}
    assert sum(none[i] != out[i] for i in out) == 90  # with no template every page of the three hosts changes
    monkeypatch.setattr(html_templates, "BROADCAST_BYTES", 0)  # the joined way
    assert {r["page_id"]: r["text"] for r in html_templates.extract(pages).collect()} == out


def test_long_malformed_pages_take_linear_time(spark):
    for text in ('<a "' * 100_000, "<i>" * 50_000 + "</b>" * 50_000, "<a x='" * 50_000, "<" * 300_000, "<p>" * 100_000, "<b>" * 30_000 + "<li>" * 30_000, "<script>" * 30_000):
        began = time.perf_counter()
        html_templates.Page(text).text(frozenset())
        assert time.perf_counter() - began < 10


def longest_common(a, b):
    table = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i in range(len(a)):
        for j in range(len(b)):
            table[i + 1][j + 1] = table[i][j] + 1 if a[i] == b[j] else max(table[i][j + 1], table[i + 1][j])
    return table[-1][-1]


def test_patience_alignment():
    rng = np.random.default_rng(1)
    for _ in range(200):
        a, b = (list(rng.choice(list("abcdefghijklmnop"), size=rng.integers(0, 14))) for _ in range(2))
        pairs = license_patience.align(a, b)
        assert all(a[i] == b[j] for i, j in pairs) and all(x < y and u < v for (x, u), (y, v) in zip(pairs, pairs[1:], strict=False))
        assert len(pairs) <= longest_common(a, b)
        if len(set(a)) == len(a) and len(set(b)) == len(b):
            assert len(pairs) == longest_common(a, b)


def test_license_scan(spark, small_dir):
    rows = [
        (1, "words before. Released under the MIT License. words after"), (2, "Licensed under CC BY-NC 4.0."), (3, None), (4, ""), (5, "nothing here"), (5, "nothing here"),
        (6, "x " * 30_000 + license_patience.TEMPLATES["BSD-3-Clause"][0].replace("source and", "source or") + " y" * 30_000), (7, "Licensed under the Apache License, Version 2.0. Released under the MIT License."),
        (8, "Released publicly under a license"),
    ]
    out = license_patience.scan(spark.createDataFrame(rows, "doc_id long, text string").withColumn("license", F.lit(1))).collect()
    found = {}
    for r in out:
        found.setdefault(r["doc_id"], []).append(r["license"])
    assert {k: sorted(v, key=str) for k, v in found.items()} == {1: ["MIT"], 2: ["CC-BY-NC-4.0"], 3: [None], 4: [None], 5: [None, None], 6: ["BSD-3-Clause"], 7: ["Apache-2.0", "MIT"], 8: [None]}
    assert license_patience.scan(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_license_filter_loses_nothing(spark):
    docs = pd.read_parquet("/root/testdata/sf0.01/documents.parquet")
    known = license_patience.compiled()
    everything = regex.compile("")
    import re

    found_by = re.compile("|".join(re.escape(w) for w in sorted({w for t in known for w in t.starts})))
    for text in docs.text[:300]:
        assert license_patience.scan_text(text, found_by, known, 0.8) == license_patience.scan_text(text, everything, known, 0.8)


def test_licenses_equal_a_plain_scan(spark, small_dir):
    """Every window of every template, and the whole text, aligned without any filter."""
    known = license_patience.compiled()
    mit, apache = license_patience.TEMPLATES["MIT"][1], license_patience.TEMPLATES["Apache-2.0"][1]
    half = len(mit.split()) // 2
    torn = " ".join([*mit.split()[:half], *(f"clause{i}" for i in range(300)), *mit.split()[half:]])
    texts = pd.read_parquet(f"{small_dir}/documents.parquet").text.str.slice(0, 3000).tolist()[:60]
    texts += [torn, f"a b {apache} c d {apache} e", f"{mit} {mit}", "Released under the MIT License " * 3, "Licensed under CC BY-NC 4.0 and Licensed under CC BY 4.0"]
    import re

    found_by = re.compile("|".join(re.escape(w) for w in sorted({w for t in known for w in t.starts})))
    places = 0
    for text in texts:
        own = license_patience.words(text or "")
        plain = set()
        for t in known:
            n, slack = len(t.words), max(2, len(t.words) // 4)
            spans = [(max(0, b - slack), b + n + slack) for b in range(-n, len(own) + 1)] + [(0, len(own))]
            if any(len(license_patience.align(own[a:b], list(t.words))) >= 0.8 * n - 1e-9 for a, b in spans):
                plain.add(t.license)
        got = license_patience.scan_text(text, found_by, known, 0.8)
        assert {x[0] for x in got} <= plain
        for name in plain - {x[0] for x in got}:  # only where a better one lies over it
            assert any(x[1] >= 0.8 for x in got), (name, text[:80])
        spans = sorted((x[3], x[4]) for x in got)
        assert all(a[1] <= b[0] for a, b in zip(spans, spans[1:], strict=False))
        places += len(got)
    count = {i: [x[0] for x in license_patience.scan_text(t, found_by, known, 0.8)] for i, t in enumerate(texts[-5:])}
    assert count == {0: ["MIT"], 1: ["Apache-2.0"] * 2, 2: ["MIT"] * 2, 3: ["MIT"] * 3, 4: ["CC-BY-NC-4.0", "CC-BY-4.0"]}


def test_long_texts_in_segments_give_the_same(spark, monkeypatch, small_dir):
    texts = pd.read_parquet(f"{small_dir}/documents.parquet").text.tolist()[:40] + ["one-word " + "x" * 5000, "y" * 9000, "a\n b  c " * 700]
    models = {}
    docs = spark.read.parquet(f"{small_dir}/documents.parquet")
    models["lang"] = ppm_langid.fit(docs, 20)
    at = np.unique(np.random.default_rng(0).integers(0, 1 << toxicity_ftrl.BITS, size=400_000))
    w = np.random.default_rng(1).standard_normal(len(at)) * 0.01

    def everything():
        ids = []
        for _, _, own, sizes in token_ids.Encoder(token_ids.default_vocabulary()).encode(texts):
            ends = np.cumsum(sizes)
            ids += [own[a - n: a].tolist() for a, n in zip(ends, sizes, strict=True)]
        return simhash_pivots.fingerprint_texts(texts), toxicity_ftrl.score_texts(texts, at, w), models["lang"].code_lengths(texts), ids

    want = everything()
    for module in (simhash_pivots, toxicity_ftrl, ppm_langid, token_ids):
        monkeypatch.setattr(module, "LONG", 300)
        monkeypatch.setattr(module, "CHUNK_BYTES", 250)
    got = everything()
    assert np.array_equal(got[0], want[0]) and np.allclose(got[1], want[1]) and np.allclose(got[2], want[2], rtol=1e-6) and got[3] == want[3]
