"""Word shingles: texts as bytes in, sorted arrays of 63-bit shingle hashes out.

Words are runs of bytes other than blank and 0x09-0x0D, which is how Python splits bytes; A-Z count as a-z. Every
word has a 128-bit digest (BLAKE2b), found once for each different word while it is remembered. A shingle's hash
mixes the first halves of its five words' digests; the second halves make a further hash, by which links are
confirmed. So no text can be built to collide with another but by inverting the digest, and two different
shingles of a comparison agree in both hashes with a chance of 2**-127.
"""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np

WIDTH = 5
_MIX = np.array([0xBF58476D1CE4E5B9, 0x94D049BB133111EB], dtype=np.uint64)  # fixed values: the usual 64-bit finaliser


@lru_cache(maxsize=1)
def _weights() -> np.ndarray:
    return np.random.default_rng(20).integers(1, 1 << 63, (2, WIDTH), dtype=np.uint64) | np.uint64(1)


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * _MIX[0]
    h = (h ^ (h >> np.uint64(27))) * _MIX[1]
    return h ^ (h >> np.uint64(31))


class _Words(dict):
    """Word -> its row in a table of digests; a word that is missing gets one."""

    ROOM = 400_000

    def __init__(self):
        super().__init__()
        self.digests = bytearray()

    def __missing__(self, word: bytes) -> int:
        at = self[word] = len(self)
        self.digests += hashlib.blake2b(word, digest_size=16).digest()
        return at

    def table(self) -> np.ndarray:
        return np.frombuffer(bytes(self.digests), dtype=np.uint64).reshape(-1, 2)


_words = _Words()


def _hashed(texts: list[bytes]) -> list[np.ndarray]:
    """Per text an array (shingle, 2) of both hashes, in the order of the text."""
    global _words
    if len(_words) > _Words.ROOM:
        _words = _Words()
    split = [t.lower().split() for t in texts]
    sizes = np.array([len(w) for w in split], dtype=np.int64)
    at = np.fromiter((x for w in split for x in map(_words.__getitem__, w)), dtype=np.int64, count=int(sizes.sum()))
    words, weights = _words.table()[at], _weights()
    n = len(words)
    if n >= WIDTH:
        full = n - WIDTH + 1
        sums = words[:full] * weights[:, 0]
        for j in range(1, WIDTH):
            sums += words[j : j + full] * weights[:, j]
        hashes = mix(sums) >> np.uint64(1)
    out, a = [], 0
    for z in np.cumsum(sizes).tolist():
        if z - a >= WIDTH:
            out.append(hashes[a : z - WIDTH + 1])
        elif z > a:
            whole = (words[a:z] * weights[:, : z - a].T).sum(axis=0, dtype=np.uint64) + np.uint64(z - a)
            out.append((mix(whole) >> np.uint64(1)).reshape(1, 2))
        else:
            out.append(np.empty((0, 2), dtype=np.uint64))
        a = z
    return out


def shingle_sets(texts: list[bytes]) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text; fewer than five words make one shingle, none an empty set."""
    return [np.unique(h[:, 0]) for h in _hashed(texts)]


def confirmed_sets(texts: list[bytes]) -> list[tuple[np.ndarray, np.ndarray]]:
    """The same sets with the further hash of each shingle."""
    out = []
    for h in _hashed(texts):
        first, where = np.unique(h[:, 0], return_index=True)
        out.append((first, h[where, 1]))
    return out


def chunks(texts: list[bytes], limit: int = 1 << 20):
    """Runs of whole texts of about ``limit`` bytes, as (first, end)."""
    first, size = 0, 0
    for i, t in enumerate(texts):
        if size and size + len(t) > limit:
            yield first, i
            first, size = i, 0
        size += len(t) + 1
    if first < len(texts):
        yield first, len(texts)
