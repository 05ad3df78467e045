"""Word shingles of many texts at once, as 64-bit hashes in numpy.

Words are what ASCII white space separates, with A-Z lower-cased.  A word's hash
is a polynomial of its bytes modulo 2^64 (all words of a batch come from one
running sum), mixed with its length; a shingle's hash chains its words' hashes.
"""

from __future__ import annotations

import numpy as np

RADIX = np.uint64(0x9E3779B97F4A7C15)
#: Bytes of text hashed at a time: arrays of this size stay in a core's cache.
CHUNK = 1 << 18
_powers: dict[str, np.ndarray] = {}


def _power_table(n: int, inverse: bool) -> np.ndarray:
    name = "inverse" if inverse else "power"
    table = _powers.get(name)
    if table is None or len(table) < n:
        base = np.uint64(pow(int(RADIX), -1, 1 << 64)) if inverse else RADIX
        table = np.full(max(n, 2 * CHUNK), base, dtype=np.uint64)
        table[0] = 1
        np.multiply.accumulate(table, out=table)
        _powers[name] = table
    return table


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambler of 64-bit words."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def word_hashes(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word, index of each text's first word, one more at the end)."""
    raw = [t.encode("utf-8", "surrogatepass").lower() for t in texts]
    hashes, first, n = [np.zeros(0, dtype=np.uint64)], [np.zeros(1, dtype=np.int64)], 0
    lo = size = 0
    for i, r in enumerate(raw):
        size += len(r)
        if size >= CHUNK or i + 1 == len(raw):
            words, starts = _chunk_hashes(raw[lo : i + 1])
            hashes.append(words)
            first.append(starts[1:] + n)
            n += len(words)
            lo, size = i + 1, 0
    return np.concatenate(hashes), np.concatenate(first)


def _chunk_hashes(raw: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    data = np.frombuffer(b"\n" + b"\n".join(raw) + b"\n", dtype=np.uint8)
    ends_of = np.cumsum(np.fromiter((len(r) + 1 for r in raw), dtype=np.int64, count=len(raw)))
    white = (data == 32) | ((data >= 9) & (data <= 13))
    edge = np.flatnonzero(white[1:] != white[:-1]) + 1
    start, end = edge[0::2], edge[1::2]
    total = np.zeros(len(data) + 1, dtype=np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * _power_table(len(data), False)[: len(data)], out=total[1:])
    words = (total[end] - total[start]) * _power_table(len(data), True)[start]
    words = mix(words + (end - start).astype(np.uint64) * np.uint64(0xD1B54A32D192ED03))
    return words, np.concatenate([[0], np.searchsorted(start, ends_of)])


def shingle_sets(texts: list[str], k: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text; a text of fewer than k words is one shingle."""
    words, first = word_hashes(texts)
    chain = np.zeros(max(0, len(words) - k + 1), dtype=np.uint64)
    for j in range(k):
        chain = chain * np.uint64(0xFF51AFD7ED558CCD) + words[j : j + len(chain)]
    chain = mix(chain)
    out = []
    for i, j in zip(first[:-1], first[1:]):
        if j - i >= k:
            out.append(np.unique(chain[i : j - k + 1]))
        elif j > i:
            h = np.zeros(1, dtype=np.uint64)
            for w in words[i:j]:
                h = h * np.uint64(0xFF51AFD7ED558CCD) + w
            out.append(mix(h + np.uint64(j - i)))
        else:
            out.append(chain[:0])
    return out
