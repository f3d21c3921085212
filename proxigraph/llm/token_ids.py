"""Token ids of whole texts by the tokenizers library, each distinct pre-token encoded once per worker."""

from __future__ import annotations

import os
import re
import unicodedata
from collections.abc import Iterator
from itertools import chain

import numpy as np

from proxigraph.llm.textops import LONG, chunks, mix64, slice_hashes
from proxigraph.runtime import kept

VOCABULARY = "byte_bpe_50k.json"
CHUNK_BYTES = 1 << 19
#: Pre-tokens remembered by a worker; beyond that it starts anew, so its memory stays bounded.
MOST_REMEMBERED = 600_000

#: Pre-tokens handed to the library at once.
ENCODE_WORDS = 4096

#: Below this code point the vocabulary's character classes are tabulated; a text with a character
#: beyond, or one of the few control characters on whose class libraries differ, is encoded whole.
_TABLED = 0x250
_LETTER, _NUMBER, _SPACE, _SIGN, _END = range(5)


def _classes() -> np.ndarray:
    out = np.full(_TABLED, _SIGN, dtype=np.int8)
    for c in range(_TABLED):
        kind = unicodedata.category(chr(c))[0]
        out[c] = _LETTER if kind == "L" else _NUMBER if kind == "N" else _SIGN
    out[[9, 10, 11, 12, 13, 32, 0x85, 0xA0]] = _SPACE
    out[0] = _END
    return out


_CLASS = _classes()
_SALT = mix64(np.arange(_TABLED, dtype=np.uint64) + np.uint64(77))
_INNER_SPACE = re.compile(r"[A-Za-z.,;:!?] [A-Za-z]")
_BEYOND = re.compile("[^\t\n\r\x20-\x7e\xa1-\u024f]")


def pre_tokens(code: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and stops of the pre-tokens of texts given as code points, each text ended by a 0.

    The public pattern of this vocabulary: contractions; runs of letters, of numbers and of other
    signs, each with one space before it; runs of white space, without the character before a word.
    """
    kind = _CLASS[code]
    n = len(code)
    cut = np.ones(n + 1, dtype=bool)
    cut[1:n] = kind[1:] != kind[:-1]
    cut[1:n] |= kind[1:] == _END
    # the last white space before a word: a space joins the word, anything else stands alone
    before = np.flatnonzero((kind[:-1] == _SPACE) & (kind[1:] < _END) & (kind[1:] != _SPACE))
    cut[before] = True
    cut[before[code[before] == 32] + 1] = False
    quote = np.flatnonzero((code == 39) & cut[:n])
    if len(quote):
        one = np.append(code, [0, 0])[quote + 1]
        two = np.append(code, [0, 0])[quote + 2]
        short = np.isin(one, [ord(c) for c in "stmd"])
        long = ((two == ord("e")) & ((one == ord("r")) | (one == ord("v")))) | ((one == ord("l")) & (two == ord("l")))
        cut[quote[short | long] + 1] = False
        cut[quote[short] + 2] = True
        cut[quote[long] + 3] = True
        cut[quote[long] + 2] = False
    at = np.flatnonzero(cut)
    start, stop = at[:-1], at[1:]
    real = kind[start] != _END
    return start[real], stop[real]


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY)


class Encoder:
    """encode(texts) -> (ids, lengths): all texts' ids in one array, and how many each text has.

    Equal to the library's encode_batch(texts, add_special_tokens=False): the vocabulary merges within
    pre-tokens only, so a text's ids are its pre-tokens' ids in order. With added_tokens, the strings
    of the vocabulary's added tokens give their own ids, as is the library's default, and texts that
    hold one are encoded whole; without, these strings are read as ordinary text.
    """

    def __init__(self, path: str, added_tokens: bool = False):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.whole = _BEYOND
        if added_tokens:
            added = [re.escape(t.content) for t in self.tokenizer.get_added_tokens_decoder().values()]
            self.whole = re.compile("|".join([_BEYOND.pattern, *sorted(added)]))
        else:
            self.tokenizer.encode_special_tokens = True
        self._forget()

    def _forget(self) -> None:
        self.keys = np.empty(0, dtype=np.uint64)  # hashes of the known pre-tokens, sorted
        self.order = np.empty(0, dtype=np.int64)  # where each stands in start and proof
        self.flat = np.empty(1 << 16, dtype=np.uint32)
        self.start = np.zeros(1 << 16, dtype=np.int64)
        self.proof = np.zeros(1 << 16, dtype=np.uint64)
        self.used = 0

    def _learn(self, words: list[str], proof: np.ndarray) -> None:
        ids = []
        for at in range(0, len(words), ENCODE_WORDS):  # the library's own results are large
            ids += [e.ids for e in self.tokenizer.encode_batch_fast(words[at: at + ENCODE_WORDS], add_special_tokens=False)]
        n, more = len(self.keys), len(words)
        sizes = np.fromiter(map(len, ids), np.int64, more)
        need = self.used + int(sizes.sum())
        if need > len(self.flat):
            self.flat = np.concatenate([self.flat[: self.used], np.empty(need, dtype=np.uint32)])
        if n + more + 1 > len(self.start):
            self.start = np.concatenate([self.start[: n + 1], np.zeros(n + more + 1, dtype=np.int64)])
            self.proof = np.concatenate([self.proof[:n], np.zeros(n + more + 2, dtype=np.uint64)])
        self.flat[self.used: need] = np.fromiter(chain.from_iterable(ids), np.uint32, need - self.used)
        self.start[n + 1: n + 1 + more] = self.used + np.cumsum(sizes)
        self.proof[n: n + more] = proof
        self.used = need

    def _whole(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        ids = [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        sizes = np.fromiter(map(len, ids), np.int64, len(ids))
        return np.fromiter(chain.from_iterable(ids), np.uint32, int(sizes.sum())), sizes

    def _encode_chunk(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        odd = [i for i, t in enumerate(texts) if self.whole.search(t)]
        if odd:
            skip = set(odd)
            ids, sizes = self._encode_plain(["" if i in skip else t for i, t in enumerate(texts)])
            more, more_sizes = self._whole([texts[i] for i in odd])
            stops = np.cumsum(sizes)
            ids = np.insert(ids, np.repeat(stops[odd], more_sizes), more)
            sizes[odd] = more_sizes
            return ids, sizes
        return self._encode_plain(texts)

    def _encode_plain(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        joined = "\0".join(texts) + "\0"
        code = np.frombuffer(joined.encode("utf-32-le"), dtype=np.uint32)
        start, stop = pre_tokens(code)
        if not len(start):
            return np.empty(0, np.uint32), np.zeros(len(texts), np.int64)
        key, proof = slice_hashes(code, start, stop, _SALT)
        fresh, first, back = np.unique(key, return_index=True, return_inverse=True)
        if len(self.keys) + len(fresh) > MOST_REMEMBERED:
            self._forget()
        place = np.searchsorted(self.keys, fresh)
        known = place < len(self.keys)
        known[known] = self.keys[place[known]] == fresh[known]
        at = np.empty(len(fresh), dtype=np.int64)
        at[known] = self.order[place[known]]
        new = np.flatnonzero(~known)
        if len(new):
            n = len(self.keys)
            begin, end = start[first[new]].tolist(), stop[first[new]].tolist()
            self._learn([joined[a:b] for a, b in zip(begin, end, strict=True)], proof[first[new]])
            at[new] = np.arange(n, n + len(new))
            self.keys = np.insert(self.keys, place[new], fresh[new])
            self.order = np.insert(self.order, place[new], at[new])
        at = at[back]
        if not np.array_equal(self.proof[at], proof):  # two pre-tokens of one hash
            return self._whole(texts)
        begin, size = self.start[at], self.start[at + 1] - self.start[at]
        ends = np.cumsum(size)
        ids = self.flat[np.arange(int(ends[-1])) + np.repeat(begin - (ends - size), size)]
        upto = np.concatenate([[0], ends])
        last = np.searchsorted(start, np.flatnonzero(code == 0))
        return ids, np.diff(upto[last], prepend=0)

    def encode(self, texts: list[str | None]):
        """Yields (lo, hi, ids, lengths) for consecutive ranges of texts; null counts as empty."""
        whole = [t or "" for t in texts]
        for lo, hi in chunks(np.fromiter(map(len, whole), np.int64, len(whole)), CHUNK_BYTES):
            if len(whole[lo]) <= LONG:
                yield lo, hi, *self._encode_chunk(whole[lo:hi])
            else:
                ids = np.concatenate([self._encode_chunk([x])[0] for x in _cut(whole[lo])])
                yield lo, hi, ids, np.array([len(ids)])


def _cut(text: str) -> Iterator[str]:
    """Parts of a very long text. A space between a sign or letter and a letter always begins a
    pre-token, and lies in or beside no added token of the vocabulary, so the parts' ids in a row are
    the text's."""
    start = 0
    while len(text) - start > CHUNK_BYTES:
        m = _INNER_SPACE.search(text, start + CHUNK_BYTES)
        if not m:
            break
        yield text[start: m.start() + 1]
        start = m.start() + 1
    yield text[start:]


def encoder(path: str) -> Encoder:
    """The encoder to the library's default ids, which the worker keeps while it runs one kernel."""
    return kept(f"encoder {path}", lambda: Encoder(path, added_tokens=True))
