"""Vectorised word, line and shingle kernels over Arrow batches of texts (numpy only, whole texts, no Python loop over words).

All hashes are 64-bit and the same on every machine. Null texts are empty texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

# --- fixed values -----------------------------------------------------------------------------------------------------
#: Odd multiplier of the polynomial word hash, and the finaliser's constants (public 64-bit mixer).
BASE = 0x9E3779B97F4A7C15 | 1
MIX_A, MIX_B = 0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53
WHITE = bytes([0x20, *range(0x09, 0x0E)])
# ----------------------------------------------------------------------------------------------------------------------

_U = np.uint64
_rng = np.random.Generator(np.random.PCG64(20_240_607))
BYTE_CODE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * _U(2) + _U(1)
STEP = _rng.integers(1, 2**63, 16, dtype=np.uint64) * _U(2) + _U(1)
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def table(members: bytes) -> np.ndarray:
    out = np.zeros(256, dtype=bool)
    out[list(members)] = True
    return out


WHITE_TABLE = table(WHITE)
#: Everything in ASCII but digits and letters.
PUNCT_TABLE = table(bytes(b for b in range(128) if not chr(b).isalnum()))
_powers = np.ones(1, dtype=np.uint64)


def powers(n: int) -> np.ndarray:
    """BASE to the powers 0..n-1, modulo 2**64."""
    global _powers
    if len(_powers) < n:
        full = np.full(max(n, 1024), BASE, dtype=np.uint64)
        full[0] = 1
        full = np.multiply.accumulate(full)
        if n > 1 << 20:
            return full
        _powers = full
    return _powers


def mix(x: np.ndarray) -> np.ndarray:
    """Spreads every bit of x over the word."""
    x = x ^ (x >> _U(33))
    x = x * _U(MIX_A)
    x = x ^ (x >> _U(33))
    x = x * _U(MIX_B)
    return x ^ (x >> _U(33))


@dataclass
class Texts:
    """UTF-8 bytes of many texts, end to end; text i is data[bounds[i]:bounds[i + 1]]."""

    data: np.ndarray
    bounds: np.ndarray

    def __len__(self) -> int:
        return len(self.bounds) - 1


def texts_of(column: pa.Array) -> Texts:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    column = column.fill_null("").cast(pa.large_string())
    _, offsets, data = column.buffers()
    bounds = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, dtype=np.uint8)[bounds[0] : bounds[-1]] if data is not None else np.empty(0, np.uint8)
    return Texts(raw, bounds - bounds[0])


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """The rows in slices of about limit bytes of text (one longer text makes a slice of its own), which bounds memory."""
    for batch in batches:
        texts = batch.column(column).cast(pa.large_string()) if batch.num_rows else None
        if texts is None:
            continue
        sizes = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1]
        at = 0
        while at < batch.num_rows:
            end = int(np.searchsorted(sizes, sizes[at] + limit, side="right")) - 1
            end = min(max(end, at + 1), batch.num_rows)
            yield batch.slice(at, end - at)
            at = end


@dataclass
class Words:
    """One entry for each word: the text it is in, its byte range and its hash. first[i]:first[i + 1] are text i's words."""

    doc: np.ndarray
    start: np.ndarray
    end: np.ndarray
    hash: np.ndarray
    first: np.ndarray


def runs(texts: Texts, gap: np.ndarray, lower: bool = True) -> Words:
    """Maximal runs of bytes that aren't in the gap table, within each text; A-Z is lower-cased for the hash."""
    data, bounds, n = texts.data, texts.bounds, len(texts.data)
    if not n:
        none = np.empty(0, np.int64)
        return Words(none, none, none, np.empty(0, np.uint64), np.zeros(len(texts) + 1, np.int64))
    inside = ~gap[data]
    edge = np.zeros(n + 1, dtype=bool)  # a new text starts here
    edge[bounds] = True
    change = np.empty(n, dtype=bool)
    change[0] = True
    np.not_equal(inside[1:], inside[:-1], out=change[1:])
    change |= edge[:n]
    marks = np.append(np.flatnonzero(change), n)
    keep = inside[marks[:-1]]
    start, end = marks[:-1][keep], marks[1:][keep]
    doc = np.searchsorted(bounds, start, side="right") - 1
    first = np.searchsorted(doc, np.arange(len(texts) + 1))
    if not len(start):
        return Words(doc, start, end, np.empty(0, np.uint64), first)
    size = end - start
    at = np.flatnonzero(inside)
    offset = at - np.repeat(start, size)
    codes = BYTE_CODE[LOWER[data[at]] if lower else data[at]]
    codes *= powers(int(size.max()) + 1)[offset]
    begins = np.concatenate(([0], np.cumsum(size)[:-1]))
    code = np.add.reduceat(codes, begins) + size.astype(np.uint64) * STEP[15]
    return Words(doc, start, end, mix(code), first)


def sequence_hash(h: np.ndarray, n: int) -> np.ndarray:
    """A hash of each n words in a row, at the place of the first; the last n - 1 places are left out."""
    m = len(h) - n + 1
    if m <= 0:
        return np.empty(0, np.uint64)
    out = h[:m] * STEP[0]
    for k in range(1, n):
        out = out + h[k : k + m] * STEP[k]
    return mix(out + _U(n))


def shingle_sets(words: Words, n: int = 5) -> list[np.ndarray]:
    """For each text its sorted distinct n-word shingles; with fewer words, the whole sequence as one."""
    grams, out = sequence_hash(words.hash, n), []
    for a, b in zip(words.first[:-1].tolist(), words.first[1:].tolist(), strict=True):
        if b - a >= n:
            out.append(np.unique(grams[a : b - n + 1]))
        elif b > a:
            out.append(sequence_hash(words.hash[a:b], b - a))
        else:
            out.append(np.empty(0, np.uint64))
    return out
