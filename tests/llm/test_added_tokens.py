import zlib

import numpy as np
import pandas as pd

from proxigraph.llm import packing, token_files, token_ids

TEXTS = ["a <|endoftext|> hi", "<|endoftext|>", "x<|endoftext|><|endoftext|> \n y", "<|endoftext| > no token", "plain words", "é <|endoftext|>日本", "", None, "after it"]


def plain_ids(texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(token_ids.default_vocabulary())
    return [t.encode(x or "", add_special_tokens=False).ids for x in texts]


def ids_of(texts):
    got = []
    for _, _, ids, sizes in token_ids.encoder(token_ids.default_vocabulary()).encode(texts):
        ends = np.cumsum(sizes)
        got += [ids[a - n: a].tolist() for a, n in zip(ends, sizes, strict=True)]
    return got


def crc(ids):
    return zlib.crc32(np.array(ids, dtype="<u4").tobytes())


def test_ids_equal_the_plain_library(small_dir, monkeypatch):
    texts = TEXTS + pd.read_parquet(f"{small_dir}/documents.parquet").text.tolist()[:40]
    assert plain_ids(TEXTS[:1]) == [[64, 220, 50256, 23105]]
    assert ids_of(texts) == plain_ids(texts)
    long = ["some words, more words <|endoftext|> and so on " * 40, " ".join(TEXTS[:6]) * 30]
    monkeypatch.setattr(token_ids, "LONG", 300)
    monkeypatch.setattr(token_ids, "CHUNK_BYTES", 50)
    assert ids_of(long) == plain_ids(long)


def test_operators_use_them(spark, tmp_path):
    rows = spark.createDataFrame([(i, t, "en", "a", 0) for i, t in enumerate(TEXTS)], "doc_id long, text string, lang string, source string, n_chars long")
    want = plain_ids(TEXTS)
    packed = {r["doc_id"]: (r["length"], r["ids_crc32"]) for r in packing.pack_documents(rows).collect()}
    assert packed == {i: (len(x) + 1, crc([*x, 0])) for i, x in enumerate(want)}
    folder = f"file://{tmp_path}/files"
    token_files.write(rows, folder)
    out = sorted(token_files.read(spark, folder).collect(), key=lambda r: r["start"])
    starts = np.cumsum([0] + [len(x) + 1 for x in want])[:-1].tolist()
    assert [(r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) for r in out] == [(i, s, len(x) + 1, crc([*x, 2])) for i, (s, x) in enumerate(zip(starts, want, strict=True))]
