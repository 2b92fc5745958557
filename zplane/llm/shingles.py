"""Word shingles of many texts at once: words, their 62-bit hashes and distinct k-word shingle sets.

Two hashes of byte ranges: prefix_hash / range_hash works modulo 2^64, is cheap and good for dealing out and
for tables that compare bytes afterwards, but different strings of some shapes (Thue-Morse words and their
complements) agree by construction whatever the base. RangeHash works modulo two primes, for which no such
strings are known in advance; shingle sets rest on it.
"""

from __future__ import annotations

import numpy as np

_U = np.uint64
_ODD = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit values."""
    h = (h ^ (h >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> _U(27))) * _U(0x94D049BB133111EB)
    return h ^ (h >> _U(31))


_BYTE = mix(np.arange(1, 257, dtype=np.uint64) * _U(_ODD))
_BASE = 0xD6E8FEB86659FD93  # odd, so powers can be inverted modulo 2^64
_INVERSE = pow(_BASE, -1, 1 << 64)


class _Powers:
    """Powers of a base modulo 2^64, extended as longer buffers come."""

    def __init__(self, base: int):
        self.base, self.out = base, np.ones(1, np.uint64)

    def __call__(self, n: int) -> np.ndarray:
        while len(self.out) < n:
            step = pow(self.base, len(self.out), 1 << 64)
            self.out = np.concatenate([self.out, self.out * _U(step)])
        return self.out[:n]


_UP, _DOWN = _Powers(_BASE), _Powers(_INVERSE)


def prefix_hash(buf: np.ndarray) -> np.ndarray:
    """P with range_hash(P, s, e) = a hash of buf[s:e] that doesn't depend on where the range lies."""
    out = np.zeros(len(buf) + 1, np.uint64)
    np.cumsum(_BYTE[buf] * _UP(len(buf)), out=out[1:])
    return out


def range_hash(p: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return mix((p[end] - p[start]) * _DOWN(len(p))[start])


_PRIMES, _BASES = (2147483647, 2147483629), (1102563731, 1735948963)
_BLOCK = 1 << 20


class _PrimePowers:
    """Powers of a base modulo a prime below 2^31, extended as longer buffers come."""

    def __init__(self, base: int, prime: int):
        self.base, self.prime, self.out = base, prime, np.ones(1, np.int64)

    def __call__(self, n: int) -> np.ndarray:
        while len(self.out) < n:
            step = pow(self.base, len(self.out), self.prime)
            self.out = np.concatenate([self.out, self.out * step % self.prime])
        return self.out[:n]


_RISE = [_PrimePowers(b, p) for b, p in zip(_BASES, _PRIMES)]
_FALL = [_PrimePowers(pow(b, -1, p), p) for b, p in zip(_BASES, _PRIMES)]


class RangeHash:
    """Hashes of ranges of a buffer that don't depend on where a range lies: polynomials modulo two primes, 62 bits together."""

    def __init__(self, buf: np.ndarray):
        self.sums = []
        for rise, prime in zip(_RISE, _PRIMES):
            out = np.zeros(len(buf) + 1, np.int64)
            power = rise(min(len(buf), _BLOCK))
            for lo in range(0, len(buf), _BLOCK):  # a block's sums stay below 2^60
                part = buf[lo : lo + _BLOCK].astype(np.int64) + 1
                up = power[: len(part)] if lo == 0 else power[: len(part)] * pow(rise.base, lo, prime) % prime
                np.cumsum(part * up, out=out[lo + 1 : lo + len(part) + 1])
                out[lo + 1 : lo + len(part) + 1] += out[lo] % prime if lo else 0
            self.sums.append(out)

    def __call__(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        one, two = ((s[end] - s[start]) % p * fall(len(s))[start] % p for s, p, fall in zip(self.sums, _PRIMES, _FALL))
        return mix((one << 31 | two).astype(np.uint64))


def words(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word, index of the first word of each text and the total): words are runs of bytes
    other than blank and the controls 9 to 13."""
    buf = np.frombuffer(b" ".join([*texts, b""]), np.uint8)
    gap = np.empty(len(buf) + 2, bool)
    gap[0] = gap[-1] = True
    gap[1:-1] = (buf == 32) | ((buf >= 9) & (buf <= 13))
    edge = np.flatnonzero(gap[1:] != gap[:-1])
    start, end = edge[::2], edge[1::2]
    begins = np.concatenate([[0], np.cumsum([len(t) + 1 for t in texts])])
    h = RangeHash(buf)(start, end) ^ (end - start).astype(np.uint64)
    return h, np.searchsorted(start, begins)


def shingle_sets(texts: list[bytes], k: int) -> list[np.ndarray]:
    """The sorted distinct hashes of each text's k-word shingles; a text of fewer words (but some) has its whole sequence as one."""
    h, first = words(texts)
    n = np.diff(first)
    s = mix(h + _U(1)) if len(h) else h
    full = s[: max(0, len(h) - k + 1)].copy()
    for j in range(1, k):
        full = mix(full * _U(_ODD) + s[j : j + len(full)])
    out = []
    for a, m in zip(first[:-1].tolist(), n.tolist()):
        if m >= k:
            out.append(np.unique(full[a : a + m - k + 1]))
        elif m:
            x = int(s[a])
            for j in range(1, m):
                x = int(mix(np.array([(x * _ODD + int(s[a + j])) & _MASK], np.uint64))[0])
            out.append(np.array([x ^ m], np.uint64))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def lowered(text: str | None) -> bytes:
    """UTF-8 with A-Z in lower case; null is empty."""
    return (text or "").encode("utf-8", "surrogatepass").lower()


def in_groups(texts: list[bytes], most: int = 1 << 20):
    """Slices of at most `most` bytes (or one longer text), so that working arrays stay small."""
    lo, room = 0, 0
    for i, t in enumerate(texts):
        if room and room + len(t) > most:
            yield slice(lo, i)
            lo, room = i, 0
        room += len(t)
    if texts:
        yield slice(lo, len(texts))
