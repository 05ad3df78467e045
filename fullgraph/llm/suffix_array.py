"""Suffix sorting by bucket-pointer refinement, in numpy.

Suffixes start in buckets of equal q-grams.  A bucket is refined by sorting its
suffixes on the bucket identifiers found at a later offset; the identifiers that
a pass assigns are the keys of the next, so the sorted depth doubles each time.
Only suffixes that a deeper level will look at are kept in play, and suffixes
alone in their bucket are final.
"""

from __future__ import annotations

import numpy as np

Q = 8


def first_buckets(text: np.ndarray) -> np.ndarray:
    """Rank of the q-gram at every place (the text's end is padded with zeros)."""
    padded = np.concatenate([text, np.zeros(Q, dtype=np.uint8)])
    gram = np.zeros(len(text), dtype=np.uint64)
    for j in range(Q):
        gram = (gram << np.uint64(8)) | padded[j : j + len(text)].astype(np.uint64)
    return np.unique(gram, return_inverse=True)[1].astype(np.int64)


def offsets(depth: int, q: int = Q) -> list[int]:
    """Offsets of the refinement passes from q to ``depth``: each at most doubles what is sorted."""
    out, h = [], q
    while h < depth:
        out.append(min(h, depth - h))
        h += out[-1]
    return out


def bucket_ids(text: np.ndarray, starts: np.ndarray, depth: int, q: int = Q, gram=None) -> np.ndarray:
    """Identifiers of the strings of ``depth`` bytes at ``starts``; equal strings share one.

    ``gram`` gives a value per q-gram at the places it is asked for.  Without it the
    q-grams' own order is used, and the identifiers are ranks.
    """
    passes = offsets(depth, q)
    wanted = [np.unique(starts)]
    for step in reversed(passes):
        wanted.append(np.unique(np.concatenate([wanted[-1], wanted[-1] + step])))
    ids = np.zeros(len(text), dtype=np.int64)
    if gram is None:
        ids = first_buckets(text)
    else:
        ids[wanted[-1]] = np.unique(gram(wanted[-1]), return_inverse=True)[1]
    for step, places in zip(passes, reversed(wanted[:-1])):
        here, later = ids[places], ids[places + step]
        width = int(ids.max()) + 1
        size = np.bincount(here, minlength=width)
        new = (np.cumsum(size) - size)[here]  # where a bucket's ranks begin
        shared = np.flatnonzero(size[here] > 1)
        if len(shared):
            keys, back = np.unique(here[shared] * np.int64(width) + later[shared], return_inverse=True)
            bucket = keys // width
            within = np.arange(len(keys)) - np.searchsorted(bucket, bucket, side="left")
            new[shared] += within[back]
        ids = np.zeros(len(text), dtype=np.int64)
        ids[places] = new
    return ids[starts]


def suffix_array(text: bytes) -> np.ndarray:
    """The full suffix array of a byte string without zero bytes, by refinement to its length."""
    data = np.frombuffer(text, dtype=np.uint8)
    if not len(data):
        return np.zeros(0, dtype=np.int64)
    depth = Q
    while depth < len(data):
        depth *= 2
    padded = np.concatenate([data, np.zeros(2 * depth, dtype=np.uint8)])
    return np.argsort(bucket_ids(padded, np.arange(len(data)), depth), kind="stable")
