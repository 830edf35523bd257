"""Words, shingles and super-minwise signatures of whole texts, as flat numpy arrays."""

from __future__ import annotations

import numpy as np

from .common import mix64

SHINGLE = 5
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_U = np.uint64
#: A 64-bit value for every byte, and odd multipliers whose inverses exist modulo 2^64.
_BYTE = mix64(np.arange(1, 257, dtype=np.uint64))
_BASE = _U(0x9E3779B97F4A7C15)
_INVERSE = _U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def _powers(base, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    if n:
        out[0] = 1
    return np.multiply.accumulate(out)


def word_hashes(texts: list[bytes], chunk: int = 1 << 20) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all words (A-Z lower-cased, split at ASCII white space) and the number of words of each text.

    The texts are gone through in chunks that end at white space, so that beside the text only the hashes grow with its length.
    """
    raw = np.frombuffer(b" ".join(texts) + b" ", np.uint8)
    found, begins, lo = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)], 0
    while lo < len(raw):
        hi = min(len(raw), lo + chunk)
        while hi < len(raw):
            gaps = np.flatnonzero(_SPACE[raw[hi - 1 : hi + 65535]])
            hi = min(len(raw), hi + int(gaps[0])) if len(gaps) else min(len(raw), hi + 65536)
            if len(gaps):
                break
        h, starts = _hash_chunk(_LOWER[raw[lo:hi]])
        found.append(h), begins.append(starts + lo)
        lo = hi
    bounds = np.cumsum([len(t) + 1 for t in texts])
    return np.concatenate(found), np.diff(np.concatenate(([0], np.searchsorted(np.concatenate(begins), bounds))))


def _hash_chunk(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes and begins of the words of bytes that end with white space (or with the last word)."""
    edge = np.diff(np.concatenate(([True], _SPACE[data], [True])).astype(np.int8))
    starts, ends = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
    # a polynomial in the byte values, shifted back to the word's start
    total = np.concatenate((np.zeros(1, np.uint64), np.cumsum(_BYTE[data] * _powers(_BASE, len(data)), dtype=np.uint64)))
    return mix64((total[ends] - total[starts]) * _powers(_INVERSE, len(data))[starts] + (ends - starts).astype(np.uint64)), starts


def shingles(h: np.ndarray, counts: np.ndarray, k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct k-word shingles: (text number, hash) sorted, and a hash of each text's whole word sequence.

    A text with fewer than k words has its whole sequence as one shingle; one without words has none.
    """
    doc = np.repeat(np.arange(len(counts), dtype=np.int32), counts)
    begin = np.cumsum(counts) - counts
    seq, some = np.zeros(len(counts), np.uint64), np.flatnonzero(counts)
    if len(some):
        weighted = _powers(_INVERSE, int(counts.max()))[np.arange(len(h)) - np.repeat(begin, counts)]
        weighted *= h
        seq[some] = np.add.reduceat(weighted, begin[some])
        del weighted
    seq = mix64(seq + counts.astype(np.uint64))
    n = max(0, len(h) - k + 1)
    s = np.zeros(n, np.uint64)
    for j, power in enumerate(_powers(_BASE, k)):
        s += h[j : j + n] * power
    ok = doc[k - 1 :][:n] == doc[:n]
    short = np.flatnonzero((counts > 0) & (counts < k))
    e = np.concatenate((mix64(s[ok]), mix64(~seq[short])))
    d = np.concatenate((doc[:n][ok], short.astype(np.int32)))
    del s, doc, ok
    order = np.argsort(e) if len(counts) == 1 else np.lexsort((e, d))
    d, e = d[order].astype(np.int64), e[order]
    del order
    new = np.ones(len(d), bool)
    new[1:] = (d[1:] != d[:-1]) | (e[1:] != e[:-1])
    return d[new], e[new], seq


def super_minhash(d: np.ndarray, e: np.ndarray, texts: int, m: int) -> np.ndarray:
    """Super-minwise signatures, (texts, m) of uint32; the number of texts' elements may be any.

    Every element draws a random permutation of the m slots step by step and offers rank + fraction to the slot
    it meets; a text stops at the first step after which no later rank can lower any of its slots. Ranks of one
    element are all different, which correlates the slots and lowers the variance of the estimate.
    """
    sig = np.full((texts, m), 0xFFFFFFFF, np.uint32)
    flat = sig.ravel()
    chunk = 1 << 17
    open_ = np.ones(texts, bool)
    first = np.searchsorted(d, np.arange(texts + 1))
    # texts go in runs of bounded numbers of elements; a longer text fills a run of its own
    start = 0
    while start < texts:
        stop = max(start + 1, int(np.searchsorted(first, first[start] + chunk, "right")) - 1)
        lo, hi = first[start], first[stop]
        for a in range(lo, hi, chunk):  # a very long text: parts, each started again from step 0
            b = min(hi, a + chunk)
            _offer(flat, sig, d[a:b], e[a:b], m, open_)
        start = stop
    return sig


def _offer(flat, sig, d, e, m, open_) -> None:
    perm = np.empty((len(d), m), np.uint8 if m <= 256 else np.uint16)
    perm[:] = np.arange(m)
    rows = np.arange(len(d))
    for j in range(m):
        x = mix64(e + _U((j + 1) * int(_BASE) & 0xFFFFFFFFFFFFFFFF))
        at = j + (x & _U(0xFFFFFFFF)).astype(np.int64) % (m - j)
        slot = perm[rows, at]
        perm[rows, at] = perm[:, j]
        value = (_U(j) << _U(24)) | (x >> _U(40))
        np.minimum.at(flat, d * m + slot, value.astype(np.uint32))
        texts = np.unique(d)
        done = sig[texts].max(axis=1) < ((j + 1) << 24)
        if done.any():
            open_[texts[done]] = False
            stay = open_[d]
            d, e, perm = d[stay], e[stay], perm[stay]
            open_[texts[done]] = True
            if not len(d):
                return
            rows = np.arange(len(d))


def band_hashes(sig: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """One signed 64-bit hash for each band of each signature."""
    out = np.empty((len(sig), bands), np.uint64)
    for b in range(bands):
        h = np.full(len(sig), _U((b + 1) * int(_BASE) & 0xFFFFFFFFFFFFFFFF))
        for r in range(rows):
            h = mix64(h ^ sig[:, b * rows + r].astype(np.uint64))
        out[:, b] = h
    return out.astype(np.int64)
