"""Word hashes of whole blocks of text by array arithmetic.

A word is read eight bytes at a time (A-Z as a-z), all words of a block at once, so there is
no object per word; words of more than ``LONG`` bytes are hashed one by one. Of the mixed 64
bits the upper 48 are kept: words are told apart by 48 bits.
"""

from __future__ import annotations

import numpy as np
import xxhash

from .common import mix64

BITS = np.uint64(48)
LOW = np.uint64((1 << 48) - 1)
LONG = 64
#: The first k of eight bytes.
MASK = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)


def hashed_words(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Hash and first place of every word of some bytes in lower case."""
    n = len(data)
    padded = np.frombuffer(data + bytes(8), np.uint8)
    inside = np.zeros(n + 2, bool)
    text = padded[:n]
    np.logical_not((text == 32) | (text - np.uint8(9) <= 4), out=inside[1:-1])
    edge = np.flatnonzero(inside[1:] != inside[:-1])
    start, size = edge[::2], edge[1::2] - edge[::2]
    eight = np.ndarray((n + 1,), "<u8", padded, strides=(1,))  # the eight bytes from each place on
    h = mix64((eight[start] & MASK[np.minimum(size, 8)]) ^ (size.astype(np.uint64) << np.uint64(56)))
    more, k = np.flatnonzero(size > 8), 8
    while len(more) and k < LONG:
        h[more] = mix64(h[more] + (eight[start[more] + k] & MASK[np.minimum(size[more] - k, 8)]))
        k += 8
        more = more[size[more] > k]
    for i in more.tolist():
        h[i] = xxhash.xxh64_intdigest(data[start[i] : start[i] + size[i]])
    return h >> np.uint64(16), start


def words_by_part(texts: list[bytes], by_line: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word hashes of all texts, words of each part, and parts of each text; a part is a line or a text."""
    data = b"\n".join([*texts, b""]).lower()
    h, at = hashed_words(data)
    if by_line:
        cuts = np.flatnonzero(np.frombuffer(data, np.uint8) == 10)
        parts = np.fromiter((t.count(b"\n") + 1 for t in texts), np.int64, len(texts))
    else:
        cuts = np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)) + 1) - 1
        parts = np.ones(len(texts), np.int64)
    return h, np.diff(np.searchsorted(at, cuts), prepend=0), parts
