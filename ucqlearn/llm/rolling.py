"""Vectorised word and window hashes over batches of byte strings (numpy, 64-bit wrap-around).

Polynomials modulo 2**64 collide on long sequences of a certain build whatever their base, so they are used for runs of at most
``LONGEST`` items only; longer words, whole documents and windows that decide a result get BLAKE2b digests of their bytes."""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np

U = np.uint64


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


@lru_cache(maxsize=6)
def _powers(base: int, log2: int) -> tuple[np.ndarray, np.ndarray]:
    def run(b):
        out = np.full(1 << log2, b, dtype=U)
        out[0] = 1
        return np.multiply.accumulate(out)

    return run(base), run(pow(base, -1, 1 << 64))


def _spans(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, base: int) -> np.ndarray:
    """Polynomial hash of values[start:end] for each span, by differences of prefix sums. Spans come in order of
    their ends and are taken a stretch at a time, so that the tables of powers stay small however long a text is."""
    out = np.zeros(len(starts), dtype=U)
    at = 0
    while at < len(starts):
        low = int(starts[at])
        to = max(at + 1, int(np.searchsorted(ends, low + STRETCH, side="right")))
        part = values[low : int(ends[to - 1])]
        up, down = _powers(base, max(STRETCH_LOG, len(part).bit_length()))
        total = np.zeros(len(part) + 1, dtype=U)
        np.cumsum(part * up[: len(part)], out=total[1:])
        out[at:to] = mix((total[ends[at:to] - low] - total[starts[at:to] - low]) * down[starts[at:to] - low])
        at = to
    return out


LONGEST = 256
STRETCH_LOG = 20
STRETCH = (1 << STRETCH_LOG) - 1
BASES = (0x9E3779B97F4A7C15, 0xD1B54A32D192ED03)  # of bytes in a word, of words in a window


class Words:
    """The words of several documents in one buffer. ``first[d]`` is the number of document d's first word."""

    def __init__(self, documents: list[list[bytes]]):
        sizes = np.array([len(w) for w in documents], dtype=np.int64)
        self.first = np.concatenate([[0], np.cumsum(sizes)])
        self.n = int(self.first[-1])
        joined = b" ".join(b" ".join(w) for w in documents if w)
        self.bytes = np.frombuffer(joined, dtype=np.uint8)
        gaps = np.flatnonzero(self.bytes == 32)
        self.starts = np.concatenate([[0], gaps + 1]) if self.n else np.zeros(0, dtype=np.int64)
        self.ends = np.concatenate([gaps, [len(self.bytes)]]) if self.n else np.zeros(0, dtype=np.int64)
        self.doc = np.repeat(np.arange(len(documents)), sizes)

    def hashes(self) -> np.ndarray:
        out = _spans(self.bytes.astype(U) + U(1), self.starts, self.ends, BASES[0])
        for i in np.flatnonzero(self.ends - self.starts > LONGEST):
            out[i] = int.from_bytes(hashlib.blake2b(self.bytes[self.starts[i] : self.ends[i]], digest_size=8).digest(), "little")
        return out

    def windows(self, hashes: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        """(place, hash) of each run of ``size`` words inside one document."""
        if size > LONGEST:
            raise ValueError(f"windows of more than {LONGEST} words need digests")
        place = np.flatnonzero(np.arange(self.n) + size <= self.first[self.doc + 1]) if self.n else np.zeros(0, dtype=np.int64)
        return place, _spans(hashes, place, place + size, BASES[1])

    def digests(self, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """128-bit digest, in two halves, of the words from number start up to end, joined by one space. The words of an
        empty range are the empty string."""
        raw = self.bytes.tobytes()
        low = np.where(starts < ends, np.append(self.starts, 0)[starts], 0).tolist()
        high = np.where(starts < ends, np.append(self.ends, 0)[ends - 1], 0).tolist()
        found = b"".join(hashlib.blake2b(raw[a:b], digest_size=16).digest() for a, b in zip(low, high))
        halves = np.frombuffer(found, dtype=np.int64).reshape(-1, 2)
        return halves[:, 0].copy(), halves[:, 1].copy()

    def documents(self) -> tuple[np.ndarray, np.ndarray]:
        """Digest of each document's whole word sequence."""
        return self.digests(self.first[:-1], self.first[1:])


def sliding_min(x: np.ndarray, size: int) -> np.ndarray:
    """min(x[i : i + size]) for each i with a full window."""
    if len(x) < size:
        return x[:0]
    width, low = 1, x
    while 2 * width <= size:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    rest = size - width
    return np.minimum(low[: len(low) - rest], low[rest:]) if rest else low


def covered(places: np.ndarray, size: int, n: int) -> np.ndarray:
    """Boolean mask of the n words that lie in a window of ``size`` words at one of the places."""
    steps = np.zeros(n + 1, dtype=np.int64)
    np.add.at(steps, places, 1)
    np.add.at(steps, np.minimum(places + size, n), -1)
    return np.cumsum(steps[:-1]) > 0


def grouped(items, weight, most: int):
    """Lists of consecutive items whose weights add up to about ``most``."""
    out, total = [], 0
    for x in items:
        out.append(x)
        total += weight(x)
        if total >= most:
            yield out
            out, total = [], 0
    if out:
        yield out
