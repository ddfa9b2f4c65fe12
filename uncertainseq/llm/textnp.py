"""Vectorised work on Arrow string columns: word spans, 64-bit word hashes, and hashes of runs of k words.

A word is a longest run of ASCII letters, ASCII digits and bytes of non-ASCII characters; ASCII letters count as lower
case. All arithmetic is modulo 2**64. Bytes are hashed in blocks, so memory does not grow with the longest text.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

U64 = np.uint64
BLOCK = 1 << 20
BASE = 0x9E3779B97F4A7C15
BASE_INVERSE = pow(BASE, -1, 1 << 64)
SALT = 0xD6E8FEB86659FD93

WORD_BYTE = np.zeros(256, dtype=bool)
WORD_BYTE[48:58] = WORD_BYTE[65:91] = WORD_BYTE[97:123] = WORD_BYTE[128:] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def string_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string column laid end to end, and the n + 1 offsets of its values (null: empty)."""
    column = column.fill_null("") if column.null_count else column
    wide = column.cast(pa.large_string())
    if not len(wide):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = wide.buffers()
    offsets = np.frombuffer(offsets, np.int64)[wide.offset : wide.offset + len(wide) + 1]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(column: pa.Array, most: int = 2 * BLOCK):
    """Ranges of rows of about ``most`` bytes each; a longer value is a range of its own."""
    sizes = column.cast(pa.large_string())
    lengths = np.diff(string_bytes(sizes)[1])
    begin, held = 0, 0
    for i, n in enumerate(lengths):
        if held and held + n > most:
            yield begin, i
            begin, held = i, 0
        held += n
    if begin < len(lengths):
        yield begin, len(lengths)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads every bit."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


_powers: list[np.ndarray] = []


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n powers of BASE and of its inverse."""
    if not _powers or len(_powers[0]) < n:
        size = max(n, 2 * BLOCK)
        out = []
        for base in (BASE, BASE_INVERSE):
            p = np.full(size, U64(base))
            p[0] = 1
            out.append(np.multiply.accumulate(p))
        _powers[:] = out
    return _powers[0][:n], _powers[1][:n]


def word_spans(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First byte and end of every word, and the n + 1 offsets of each text's words among them."""
    inside = WORD_BYTE[data]
    opens, closes = inside.copy(), inside.copy()
    opens[1:] &= ~inside[:-1]
    closes[:-1] &= ~inside[1:]
    cuts = offsets[1:-1]
    cuts = cuts[(cuts > 0) & (cuts < len(data))]
    opens[cuts] = inside[cuts]
    closes[cuts - 1] = inside[cuts - 1]
    first, end = np.flatnonzero(opens), np.flatnonzero(closes) + 1
    return first, end, np.searchsorted(first, offsets)


def span_hashes(data: np.ndarray, first: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of the bytes of each span, ASCII letters in lower case. Spans are in order and do not overlap."""
    out = np.empty(len(first), U64)
    at = 0
    while at < len(first):
        to = max(at + 1, int(np.searchsorted(end, first[at] + BLOCK, side="right")))
        low, high = int(first[at]), int(end[to - 1])
        up, down = powers(high - low + 1)
        sums = np.zeros(high - low + 1, U64)
        np.cumsum((LOWER[data[low:high]].astype(U64) + U64(1)) * up[:-1], out=sums[1:])
        f, e = first[at:to] - low, end[at:to] - low
        out[at:to] = mix((sums[e] - sums[f]) * down[f] + (e - f).astype(U64) * U64(SALT))
        at = to
    return out


def word_hashes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every word in order, and the n + 1 offsets of each text's words."""
    data, offsets = string_bytes(column)
    first, end, texts = word_spans(data, offsets)
    return span_hashes(data, first, end), texts


def shingle_hashes(words: np.ndarray, texts: np.ndarray, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every run of k words within a text, and each text's n + 1 offsets. A text of 1 to k - 1 words has one run, all its words."""
    n = len(words)
    lengths = np.diff(texts)
    counts = np.where(lengths >= k, lengths - k + 1, (lengths > 0).astype(lengths.dtype))
    offsets = np.concatenate([[0], np.cumsum(counts)])
    if not n:
        return np.zeros(0, U64), offsets
    ends = np.repeat(texts[1:], lengths)
    at = np.arange(n)
    keep = (at + k <= ends) | (at == np.repeat(texts[:-1], lengths))
    at, ends = at[keep], ends[keep]
    total = np.zeros(len(at), U64)
    for j in range(k):
        to = at + j
        total = total * U64(BASE) + np.where(to < ends, words[np.minimum(to, n - 1)], U64(j + 1))
    return mix(total), offsets
