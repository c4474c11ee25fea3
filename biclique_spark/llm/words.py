"""Words of whole texts as pairs of 64-bit numbers, and runs of words hashed at once.

A word's bytes are mixed, eight at a time, into two 64-bit states by bijections under a key that is drawn for each
run, so nobody can build words that collide, and what collides in one state doesn't in the other; words of equal
length up to eight bytes never do. Words over LONG bytes are hashed by keyed BLAKE2b. A run's hash is a polynomial of
its words' numbers modulo 2^64; runs are short and the numbers random, so two runs agree with a probability of 2^-64.
"""

from __future__ import annotations

import secrets
from hashlib import blake2b

import numpy as np

_BASE = 0x9E3779B97F4A7C15 | 1
_INSIDE = np.append((np.uint64(1) << (np.arange(8, dtype=np.uint64) * np.uint64(8))) - np.uint64(1), ~np.uint64(0))
#: Bytes of the longest words that are mixed in array operations.
LONG = 32


def new_key() -> bytes:
    """A key for a run; results depend on it only where 64 bits collide."""
    return secrets.token_bytes(32)


def word_codes(text: bytes, key: bytes, lower: bool = False) -> np.ndarray:
    """Two 64-bit numbers for each word, as rows; words end at the six ASCII white space bytes. lower: A-Z count as a-z."""
    text = text.lower() if lower else text
    raw = np.frombuffer(b" " + text + b" " * 8, np.uint8)
    gap = (raw == 32) | (raw - np.uint8(9) < 5)
    edge = np.flatnonzero(gap[1:] != gap[:-1]) + 1
    start, size = edge[::2], edge[1::2] - edge[::2]
    eight = np.lib.stride_tricks.as_strided(raw[:8].view(np.uint64), (len(raw) - 7,), (1,))
    halves = []
    own, still, left = start, None, size
    keys = np.frombuffer(key, np.uint64)
    for at in range(0, LONG, 8):
        block = eight[own + at] & _INSIDE[np.minimum(left, 8)]
        if still is None:
            halves = [mixed(block ^ (keys[k] + size.astype(np.uint64) * (keys[k + 2] | np.uint64(1)))) for k in (0, 1)]
        else:
            for h, k in zip(halves, keys, strict=False):
                h[still] = mixed((h[still] ^ block) * np.uint64(_BASE) + k)
        more = np.flatnonzero(left > 8)
        if not len(more):
            break
        own, left = own[more], left[more] - 8
        still = more if still is None else still[more]
    out = np.stack(halves, axis=1)
    for i in np.flatnonzero(size > LONG).tolist():
        word = text[start[i] - 1 : start[i] - 1 + size[i]]
        out[i] = np.frombuffer(blake2b(word, digest_size=16, key=key).digest(), np.uint64)
    return out


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def runs(codes: np.ndarray, n: int, half: int = 0) -> np.ndarray:
    """A 64-bit hash of each run of n words, in order, from one half of their numbers; of all words at once where there
    are fewer, none for none. Hashes of the two halves have nothing in common."""
    if not len(codes):
        return np.zeros(0, np.uint64)
    n = min(n, len(codes))
    own, m = np.ascontiguousarray(codes[:, half]), len(codes) - n + 1
    out = own[n - 1 :].copy()
    for k in range(n - 2, -1, -1):
        out *= np.uint64(_BASE)
        out += own[k : k + m]
    return mixed(out)
