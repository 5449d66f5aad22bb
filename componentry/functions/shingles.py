"""Vectorised word and shingle kernels: words are runs of bytes other than those that separate them."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SPACE = (0x20, *range(0x09, 0x0E))
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
# odd multipliers of the polynomial and shingle hashes
_P = np.uint64(0x9E3779B97F4A7C15)
_Q = np.uint64(0xC2B2AE3D27D4EB4F)
_P_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def text_blocks(batch: pa.RecordBatch, column: str = "text", most: int = 2 << 20, rows: int = 30_000) -> Iterator[tuple[int, int]]:
    """Row ranges of a batch with at most ``most`` bytes of text (a longer text is alone in its range)."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    start = total = 0
    for i, n in enumerate(sizes):
        if i > start and (total + n > most or i - start >= rows):
            yield start, i
            start, total = i, 0
        total += n
    if len(sizes) > start:
        yield start, len(sizes)


def buffer_of(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts, each followed by one space, and the start of each text (with the end of all last)."""
    raw = [t or b"" for t in texts.cast(pa.binary()).to_pylist()]
    data = np.frombuffer(b" ".join(raw) + b" ", dtype=np.uint8)
    starts = np.zeros(len(raw) + 1, np.int64)
    np.cumsum([len(t) + 1 for t in raw], out=starts[1:])
    return data, starts


def _powers(base: np.uint64, n: int) -> np.ndarray:
    """base^0 .. base^n modulo 2^64, by doubling."""
    out = np.empty(n + 1, np.uint64)
    out[0] = 1
    filled = 1
    with np.errstate(over="ignore"):
        while filled <= n:
            take = min(filled, n + 1 - filled)
            out[filled : filled + take] = out[:take] * (out[filled - 1] * base)
            filled += take
    return out


class Words:
    """Words of many texts: byte ``start`` and ``end`` of each, its text's number ``doc``, and 64-bit hashes."""

    def __init__(self, data: np.ndarray, starts: np.ndarray, lower: bool, space: tuple = SPACE):
        self.data, self.starts = data, starts
        between = np.zeros(256, bool)
        between[list(space)] = True
        inside = ~between[data]
        edge = np.flatnonzero(np.diff(inside, prepend=False))  # the last byte is a space
        self.start, self.end = edge[0::2], edge[1::2]
        self.doc = np.searchsorted(starts, self.start, "right") - 1
        self.lower = lower

    def hashes(self) -> np.ndarray:
        """Polynomial hash of each word modulo 2^64, by prefix sums over blocks of bytes, then finalised."""
        data = _LOWER[self.data] if self.lower else self.data
        n = len(data)
        total = np.zeros(n + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * _powers(_P, n)[:n], out=total[1:])
        span = total[self.end] - total[self.start]
        span = span * _powers(_P_INVERSE, n)[self.start]  # the same for a word wherever it stands
        return mix(span ^ (self.end - self.start).astype(np.uint64) * _Q)


def shingle_sets(texts: pa.Array, size: int = 5, lower: bool = True, space: tuple = SPACE, whole_short: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Distinct ``size``-word shingles of each text: (hashes sorted within a text, offsets). ``lower``: ASCII letters in lower case.

    A text with fewer words has its whole sequence as one shingle (none without ``whole_short``); one without words has none.
    """
    data, starts = buffer_of(texts)
    n_docs = len(starts) - 1
    words = Words(data, starts, lower, space)
    h, doc = words.hashes(), words.doc
    count = np.bincount(doc, minlength=n_docs)
    first = np.concatenate([[0], np.cumsum(count)])
    out = np.zeros(max(0, len(h) - size + 1), np.uint64)
    for k in range(size):
        out = out * _Q + mix(h[k : k + len(out)] + np.uint64(k + 1))
    whole = doc[: len(out)] == doc[size - 1 :] if len(out) else np.zeros(0, bool)
    hashes, docs = mix(out[whole]), doc[: len(out)][whole]
    short = np.flatnonzero((count > 0) & (count < size) & whole_short)
    if len(short):
        own = np.empty(len(short), np.uint64)
        for j, d in enumerate(short):
            acc = np.uint64(count[d])
            with np.errstate(over="ignore"):
                for x in h[first[d] : first[d + 1]]:
                    acc = acc * _Q + x
            own[j] = acc
        hashes, docs = np.concatenate([hashes, mix(own * _P)]), np.concatenate([docs, short])
    order = np.lexsort((hashes, docs))
    hashes, docs = hashes[order], docs[order]
    keep = np.ones(len(hashes), bool)
    keep[1:] = (hashes[1:] != hashes[:-1]) | (docs[1:] != docs[:-1])
    hashes, docs = hashes[keep], docs[keep]
    return hashes, np.concatenate([[0], np.cumsum(np.bincount(docs, minlength=n_docs))]).astype(np.int64)


def set_key(sorted_hashes: np.ndarray) -> bytes:
    """128-bit identity of a set."""
    return hashlib.blake2b(sorted_hashes.tobytes(), digest_size=16).digest()
