"""Sets of word shingles as 64-bit hashes, computed for a batch of texts at once.

Words are what lies between ASCII white space, after lower-casing A-Z. A text with fewer words
than a shingle has its whole word sequence as its only shingle; without words the set is empty.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

M1, M2, M3 = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93))


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * M3
    x = (x ^ (x >> np.uint64(29))) * M2
    return x ^ (x >> np.uint64(32))


def word_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word, offsets of the texts); null is empty."""
    texts = pc.ascii_lower(pc.fill_null(texts, "")).cast(pa.large_string())
    split = pc.ascii_split_whitespace(texts)
    at = np.asarray(split.offsets, dtype=np.int64)
    at = at - at[0]
    coded = pc.dictionary_encode(split.flatten())
    words = coded.dictionary.cast(pa.large_binary()).to_pylist()
    table = np.fromiter((xxhash.xxh64_intdigest(w) for w in words), np.uint64, len(words))
    index = np.asarray(coded.indices, dtype=np.int64)
    empty = np.fromiter((not w for w in words), bool, len(words))
    if empty.any():  # white space at an end of a text
        keep = ~empty[index]
        at = np.concatenate(([0], np.cumsum(keep)))[at]
        index = index[keep]
    return table[index], at


def shingle_hashes(texts: pa.Array, words: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of all shingles, repeats included, offsets of the texts)."""
    w, at = word_hashes(texts)
    n = np.diff(at)
    out_n = np.where(n >= words, n - words + 1, np.minimum(n, 1))
    ends = np.zeros(len(n) + 1, np.int64)
    np.cumsum(out_n, out=ends[1:])
    start = np.repeat(at[:-1] - ends[:-1], out_n) + np.arange(ends[-1])
    with np.errstate(over="ignore"):
        h = np.full(len(start), M1, np.uint64)
        padded = np.concatenate([w, np.zeros(words, np.uint64)])
        for k in range(words):
            h = mix(h * M1 + padded[start + k])
        for i in np.flatnonzero((n > 0) & (n < words)):  # the whole sequence, and its length
            x = np.array([M2], np.uint64) * np.uint64(n[i])
            for v in w[at[i] : at[i + 1]]:
                x = mix(x * M1 + v)
            h[ends[i]] = x[0]
    return h, ends


def shingle_sets(texts: pa.Array, words: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    h, at = shingle_hashes(texts, words)
    return [np.unique(h[a:b]) for a, b in zip(at[:-1], at[1:], strict=True)]
