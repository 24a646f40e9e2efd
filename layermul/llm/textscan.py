"""Words, word hashes and word shingles of whole Arrow text batches, by numpy over the UTF-8 bytes.

A 64-bit hash stands for a word or shingle: each byte is mapped to a random 64-bit number, words are
polynomials of those over an odd base, shingles polynomials of the mixed word hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_RNG = np.random.Generator(np.random.PCG64(20260101))
_BYTE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_BASE, _NEXT = (int(x) | 1 for x in _RNG.integers(2**62, 2**63, 2, dtype=np.uint64))
_SEGMENT = 1 << 19  # bytes hashed at once
_U = np.uint64


def _powers(base: int, n: int) -> np.ndarray:
    out = np.empty(n, _U)
    out[0] = 1
    filled, step = 1, base
    while filled < n:  # doubling: out[filled:2*filled] = out[:filled] * base**filled
        m = min(filled, n - filled)
        np.multiply(out[:m], _U(step), out=out[filled : filled + m])
        step, filled = step * step % 2**64, filled + m
    return out


class _Tables:
    size = 0

    @classmethod
    def get(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        if n > cls.size:
            cls.size = max(n, _SEGMENT + 4096)
            cls.up, cls.down = _powers(_BASE, cls.size + 1), _powers(pow(_BASE, -1, 2**64), cls.size + 1)
        return cls.up, cls.down


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finalizer of 64-bit numbers."""
    x = x ^ (x >> _U(30))
    x *= _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    x ^= x >> _U(31)
    return x


def byte_class(inside: bytes | None = None, outside: bytes | None = None) -> np.ndarray:
    """256 booleans: the bytes of words."""
    out = np.full(256, inside is None)
    for b in inside if inside is not None else outside:
        out[b] = inside is not None
    return out


#: Words by white space, and words of letters and digits; both keep every byte of a non-ASCII character.
SPACED = byte_class(outside=b" \t\n\x0b\x0c\r")
ALNUM = byte_class(inside=b"0123456789abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ" + bytes(range(128, 256)))
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_FOLDED = _BYTE[LOWER]


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and n + 1 offsets; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None and len(column) else np.empty(0, np.uint8)
    return raw[off[0] : off[-1]] if len(off) else raw, off - off[0] if len(off) else np.zeros(1, np.int64)


def find_words(data: np.ndarray, offsets: np.ndarray, inside: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of all words, and for each of the n + 1 offsets the number of words before it."""
    w = np.zeros(len(data) + 2, bool)
    w[1:-1] = inside[data]
    edge = w[1:] != w[:-1]
    starts, ends = edge[:-1] & w[1:-1], edge[1:] & w[1:-1]
    inner = offsets[1:-1]
    if len(inner):  # a word never runs on into the next text
        inner = inner[(inner > 0) & (inner < len(data))]
        cut = inner[w[inner] & w[inner + 1]]
        starts[cut] = True
        ends[cut - 1] = True
    first, last = np.flatnonzero(starts), np.flatnonzero(ends) + 1
    return first, last, np.searchsorted(first, offsets)


def hash_words(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, fold: bool = True) -> np.ndarray:
    """Hash of every word, A-Z lower-cased if fold."""
    out, table, i = np.empty(len(starts), _U), _FOLDED if fold else _BYTE, 0
    while i < len(starts):
        j = max(int(np.searchsorted(ends, starts[i] + _SEGMENT, "right")), i + 1)
        lo, hi = int(starts[i]), int(ends[j - 1])
        up, down = _Tables.get(hi - lo)
        total = np.zeros(hi - lo + 1, _U)
        np.cumsum(table[data[lo:hi]] * up[: hi - lo], out=total[1:])
        out[i:j] = (total[ends[i:j] - lo] - total[starts[i:j] - lo]) * down[starts[i:j] - lo]
        i = j
    return mix(out)


def shingles(words: np.ndarray, bounds: np.ndarray, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the k-word shingles of every text, and their bounds. A text of 1 to k - 1 words has
    its whole sequence as its one shingle; a text without words has none."""
    counts = np.diff(bounds)
    n = np.where(counts >= k, counts - k + 1, (counts > 0).astype(np.int64))
    at = np.concatenate([[0], np.cumsum(n)])
    total = len(words)
    rolled = np.zeros(max(total - k + 1, 0), _U)
    for j in range(k):
        rolled += words[j : total - k + 1 + j] * _U(pow(_NEXT, j, 2**64)) if len(rolled) else rolled
    out = np.empty(at[-1], _U)
    long = counts >= k
    # positions of the first words of full shingles: all but the last k - 1 of each long text
    pick = np.ones(total, bool)
    if total:
        pick[np.repeat(~long, counts)] = False
        for j in range(1, k):
            pick[bounds[1:][long] - j] = False
    slot = np.repeat(long, n)
    out[slot] = rolled[np.flatnonzero(pick)] if pick.any() else np.empty(0, _U)
    for d in np.flatnonzero((counts > 0) & ~long):
        own = words[bounds[d] : bounds[d + 1]]
        out[at[d]] = sum(int(w) * pow(_NEXT, j + 7 * len(own), 2**64) for j, w in enumerate(own)) % 2**64
    return mix(out), at


def text_shingles(column: pa.Array, inside: np.ndarray, k: int = 5) -> tuple[np.ndarray, np.ndarray]:
    data, offsets = text_bytes(column)
    starts, ends, bounds = find_words(data, offsets, inside)
    return shingles(hash_words(data, starts, ends), bounds, k)


def small_batches(batches: Iterator[pa.RecordBatch], column: str, most: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of the batches with at most `most` bytes in a text or binary column, one row at least:
    what numpy holds at once doesn't grow with Spark's batch size."""
    for batch in batches:
        c = batch.column(batch.schema.get_field_index(column))
        if c.nbytes <= most or batch.num_rows < 2:
            if batch.num_rows:
                yield batch
            continue
        size = np.concatenate([[0], np.cumsum(np.asarray(pc.fill_null(pc.binary_length(c), 0), dtype=np.int64))])
        i = 0
        while i < batch.num_rows:
            j = max(i + 1, int(np.searchsorted(size, size[i] + most, "right")) - 1)
            yield batch.slice(i, j - i)
            i = j


def grams(words: np.ndarray, bounds: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all runs of `length` words, equal to what shingles() gives a whole text of that many
    words, and the text of each."""
    first = np.arange(max(len(words) - length + 1, 0))
    text = np.searchsorted(bounds, first, "right") - 1
    inside = first + length <= bounds[text + 1] if len(first) else np.empty(0, bool)
    first, text = first[inside], text[inside]
    rolled = np.zeros(len(first), _U)
    for j in range(length):
        rolled += words[first + j] * _U(pow(_NEXT, j + 7 * length, 2**64))
    return mix(rolled), text
