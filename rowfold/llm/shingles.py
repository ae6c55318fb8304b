"""Hashes of word shingles, in numpy over whole Arrow batches."""

from __future__ import annotations

import numpy as np

U = np.uint64
BASE = U(0x9E3779B97F4A7C15)
INV = U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
PLACES = np.array([0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3], U)
_powers: dict[str, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """A one-to-one scrambling of 64-bit numbers."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE and its inverse to the powers 0 to n."""
    if len(_powers.get("up", ())) <= n:
        for k, b in (("up", BASE), ("down", INV)):
            x = np.full(n + 1, b, U)
            x[0] = 1
            _powers[k] = np.cumprod(x, dtype=U)
    return _powers["up"], _powers["down"]


LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True


def words(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash of each word, its start, words of each text). raw: UTF-8 bytes; off: where texts begin, and the end."""
    raw, off = raw[off[0] : off[-1]], off - off[0]
    n = len(raw)
    if not n:
        return np.zeros(0, U), np.zeros(0, np.int64), np.zeros(len(off) - 1, np.int64)
    black = ~SPACE[raw]
    cut = np.zeros(n + 1, bool)
    cut[off] = True
    starts = np.flatnonzero(black & np.concatenate([[True], ~black[:-1]] ) | (black & cut[:-1]))
    ends = np.flatnonzero(black & (np.concatenate([~black[1:], [True]]) | cut[1:])) + 1
    up, down = powers(n)
    s = np.zeros(n + 1, U)
    np.cumsum((LOWER[raw].astype(U) + U(1)) * down[:n], out=s[1:], dtype=U)
    h = mix((s[ends] - s[starts]) * up[starts] + (ends - starts).astype(U) * PLACES[0])
    return h, starts, np.diff(np.searchsorted(starts, off))


def shingle_sets(raw: np.ndarray, off: np.ndarray, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of each text, texts one after another and hashes in order, and each text's number.

    A text with fewer than k words has one shingle, all its words; without words none."""
    h, _, n = words(raw, off)
    first = np.cumsum(n) - n
    size = np.where(n >= k, n - k + 1, (n > 0).astype(np.int64))
    doc = np.repeat(np.arange(len(n)), size)
    at = np.arange(size.sum()) + np.repeat(first - (np.cumsum(size) - size), size)
    length = np.minimum(n, k)[doc]
    g = length.astype(U) * PLACES[1]
    for i in range(k):
        inside = length > i
        g[inside] += h[at[inside] + i] * PLACES[i]
    g = mix(g)
    order = np.lexsort((g, doc))
    g, doc = g[order], doc[order]
    new = np.ones(len(g), bool)
    new[1:] = (g[1:] != g[:-1]) | (doc[1:] != doc[:-1])
    return g[new], np.bincount(doc[new], minlength=len(n))


def set_keys(g: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """One 64-bit key for each set, from a sum over its members that heeds no order; 0 for empty sets."""
    upto = np.concatenate([np.zeros(1, U), np.cumsum(mix(g ^ PLACES[2]), dtype=U)])
    ends = np.cumsum(counts)
    key = mix(upto[ends] - upto[ends - counts] + counts.astype(U) * PLACES[3])
    return np.where(counts > 0, np.where(key == 0, U(1), key), U(0))
