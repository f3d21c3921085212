"""Vectorised helpers over batches of texts, shared by the text operators."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

#: The primes of the public XXH64 definition.
XXH_P1 = np.uint64(11400714785074694791)
XXH_P2 = np.uint64(14029467366897019727)
XXH_P3 = np.uint64(1609587929392839161)
XXH_P4 = np.uint64(9650029242287828579)
XXH_P5 = np.uint64(2870177450012600261)


def chunks(sizes: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Index ranges whose sizes sum to about `most`; a larger single item is a range of its own."""
    start, held = 0, 0
    for i, s in enumerate(sizes.tolist()):
        if i > start and held + s > most:
            yield start, i
            start, held = i, 0
        held += s
    if start < len(sizes):
        yield start, len(sizes)


#: A longer text is handled in segments, so that memory does not grow with it.
LONG = 4 << 20


def segments(raw: bytes, most: int, words_back: int, is_word: np.ndarray) -> Iterator[bytes]:
    """Slices of a long text that end at spaces; each begins `words_back` words before the last one's
    end, so that every run of words_back + 1 words lies whole in one of them. is_word tells word bytes."""
    start = 0
    while start < len(raw):
        if len(raw) - start <= most:
            yield raw[start:]
            return
        stop = raw.rfind(b" ", start + most // 2, start + most)
        if stop < 0:
            stop = raw.find(b" ", start + most)
        if stop < 0:
            yield raw[start:]
            return
        yield raw[start:stop]
        back = stop
        for _ in range(words_back):
            while back > start and not is_word[raw[back - 1]]:
                back -= 1
            while back > start and is_word[raw[back - 1]]:
                back -= 1
        start = back if back > start else stop


def mix64(h: np.ndarray) -> np.ndarray:
    """A bijective finaliser: every input bit moves about half of the output bits."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def _rotl(x: np.ndarray, r: int) -> np.ndarray:
    return (x << np.uint64(r)) | (x >> np.uint64(64 - r))


def _round(acc: np.ndarray, lane: np.ndarray) -> np.ndarray:
    return _rotl(acc + lane * XXH_P2, 31) * XXH_P1


def xxh64_slices(buf: bytes, starts: np.ndarray, ends: np.ndarray, seed: int) -> np.ndarray:
    """XXH64 of every slice buf[starts[i]:ends[i]], all slices of one length at a time."""
    raw = np.frombuffer(buf + b"\0" * 8, dtype=np.uint8)
    n = len(raw)
    words8 = np.ndarray((n - 7,), dtype="<u8", buffer=raw.data, strides=(1,))
    words4 = np.ndarray((n - 3,), dtype="<u4", buffer=raw.data, strides=(1,))
    lengths = ends - starts
    order = np.argsort(lengths, kind="stable")
    by_len = lengths[order]
    cuts = np.flatnonzero(np.diff(by_len)) + 1
    out = np.empty(len(starts), dtype=np.uint64)
    with np.errstate(over="ignore"):
        s0 = np.uint64(seed)
        for rows in np.split(order, cuts) if len(order) else []:
            size = int(lengths[rows[0]])
            at = starts[rows].astype(np.int64)
            left = size
            if size >= 32:
                lanes = [np.full(len(rows), v) for v in (s0 + XXH_P1 + XXH_P2, s0 + XXH_P2, s0, s0 - XXH_P1)]
                while left >= 32:
                    for k in range(4):
                        lanes[k] = _round(lanes[k], words8[at + 8 * k])
                    at, left = at + 32, left - 32
                h = _rotl(lanes[0], 1) + _rotl(lanes[1], 7) + _rotl(lanes[2], 12) + _rotl(lanes[3], 18)
                for lane in lanes:
                    h = (h ^ _round(np.zeros_like(lane), lane)) * XXH_P1 + XXH_P4
            else:
                h = np.full(len(rows), s0 + XXH_P5)
            h = h + np.uint64(size)
            while left >= 8:
                h = _rotl(h ^ _round(np.zeros_like(h), words8[at]), 27) * XXH_P1 + XXH_P4
                at, left = at + 8, left - 8
            if left >= 4:
                h = _rotl(h ^ (words4[at].astype(np.uint64) * XXH_P1), 23) * XXH_P2 + XXH_P3
                at, left = at + 4, left - 4
            while left:
                h = _rotl(h ^ (raw[at].astype(np.uint64) * XXH_P5), 11) * XXH_P1
                at, left = at + 1, left - 1
            h = (h ^ (h >> np.uint64(33))) * XXH_P2
            h = (h ^ (h >> np.uint64(29))) * XXH_P3
            out[rows] = h ^ (h >> np.uint64(32))
    return out


_POWER = np.uint64(0x9E3779B97F4A7C15)  # odd, so it has an inverse modulo 2**64
_INVERSE = np.uint64(pow(int(_POWER), -1, 1 << 64))
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _grown(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        with np.errstate(over="ignore"):
            for k, base in enumerate((_POWER, _INVERSE)):
                full = np.full(n, base)
                full[0] = 1
                _powers[k] = np.cumprod(full, dtype=np.uint64)
    return _powers[0], _powers[1]


def slice_hashes(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, salt: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two independent 64-bit hashes of every slice values[starts[i]:ends[i]]; salt holds a random
    number for each possible value."""
    power, inverse = _grown(len(values) + 1)
    out = []
    with np.errstate(over="ignore"):
        for salted in (values.astype(np.uint64) + np.uint64(1), salt[values]):
            sums = np.zeros(len(values) + 1, dtype=np.uint64)
            np.cumsum(salted * power[: len(values)], out=sums[1:])
            out.append(mix64((sums[ends] - sums[starts]) * inverse[starts] + (ends - starts).astype(np.uint64)))
    return out[0], out[1]


#: Bytes of the words of lower-cased texts: digits, letters and all of non-ASCII characters.
WORD = np.zeros(256, dtype=bool)
WORD[[*range(48, 58), *range(97, 123), *range(128, 256)]] = True


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the words (letters, digits and non-ASCII bytes) of lower-cased texts, in
    order, and the index of each word's text."""
    buf = np.frombuffer(b"\n".join(texts) + b"\n", dtype=np.uint8)
    power, inverse = _grown(len(buf) + 1)
    inside = WORD[buf]
    edge = np.flatnonzero(np.diff(inside, prepend=False, append=False))
    starts, ends = edge[0::2], edge[1::2]
    with np.errstate(over="ignore"):
        sums = np.zeros(len(buf) + 1, dtype=np.uint64)
        np.cumsum((buf.astype(np.uint64) + np.uint64(1)) * power[: len(buf)], out=sums[1:])
        h = mix64((sums[ends] - sums[starts]) * inverse[starts])
    stops = np.cumsum(np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts)))
    return h, np.searchsorted(stops, starts, side="right")
