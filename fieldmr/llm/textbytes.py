"""Words, shingles and rolling hashes over the UTF-8 bytes of a whole Arrow batch.

All functions work on one concatenated byte buffer and the offsets of its
documents, so the cost per word is a few vector operations and not a Python call.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Documents are taken together until their bytes pass this size; one longer document stands alone.
SLICE_BYTES = 2 << 20
#: Bytes of words that are hashed at a time; one longer word stands alone.
HASH_BYTES = 256 << 10

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
#: Byte classes: words of everything but blanks, and words of ASCII letters, digits and non-ASCII characters.
NON_SPACE = ~_SPACE
ALNUM = np.zeros(256, dtype=bool)
ALNUM[0x30:0x3A] = True
ALNUM[0x41:0x5B] = True
ALNUM[0x61:0x7B] = True
ALNUM[0x80:] = True

#: A-Z to a-z, all else unchanged.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32

_BASE = 0x9E3779B97F4A7C15
_GRAM = 0xD6E8FEB86659FD93
_MASK = (1 << 64) - 1


def _powers(base: int, n: int) -> np.ndarray:
    out, p = np.empty(n, dtype=np.uint64), 1
    for i in range(n):
        out[i] = p
        p = p * base & _MASK
    return out


_WORD_POWERS = _powers(_BASE, 256)


def mix64(x: np.ndarray) -> np.ndarray:
    """A full-avalanche bijection of 64-bit integers (the finaliser of a published splittable generator)."""
    x = x ^ (x >> np.uint64(30))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def gram_power(t: int) -> np.uint64:
    """The weight of word t in the hash of a run of words."""
    return np.uint64(pow(_GRAM, t, 1 << 64))


def text_column(batch: pa.RecordBatch, name: str = "text") -> pa.Array:
    col = batch.column(batch.schema.get_field_index(name))
    return col.fill_null("") if col.null_count else col


def buffers(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (from 0) of a string column without nulls."""
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    _, offs, data = col.buffers()
    offsets = np.frombuffer(offs, dtype=np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.empty(0, dtype=np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(col: pa.Array, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) of runs of rows of about ``limit`` bytes."""
    n = len(col)
    if not n:
        return
    data, offsets = buffers(col)
    i = 0
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, side="right")) - 1)
        j = min(j, n)
        yield i, j, data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        i = j


class Words:
    """Words of some documents: byte starts and ends, owning document, and 64-bit hashes."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, kind: np.ndarray, lower: bool = True, cuts: np.ndarray | None = None):
        """``kind``: which bytes words are of; ``cuts``: bytes of words before which a new word begins."""
        self.data = LOWER[data] if lower else data
        self.offsets = offsets
        n_docs = len(offsets) - 1
        inside = kind[data]
        edge = np.zeros(len(data) + 1, dtype=bool)
        edge[offsets] = True
        first = inside.copy()
        first[1:] &= ~inside[:-1] | edge[1:-1]
        last = inside.copy()
        last[:-1] &= ~inside[1:] | edge[1:-1]
        if cuts is not None and len(cuts):
            first[cuts] = True
            last[cuts - 1] = True
        self.starts = np.flatnonzero(first)
        self.ends = np.flatnonzero(last) + 1
        bounds = np.searchsorted(self.starts, offsets)
        #: bounds[d] to bounds[d + 1]: the words of document d
        self.bounds = bounds
        self.per_doc = np.diff(bounds)
        self.doc = np.repeat(np.arange(n_docs), self.per_doc)
        self._hashes: np.ndarray | None = None

    def __len__(self) -> int:
        return len(self.starts)

    @property
    def hashes(self) -> np.ndarray:
        if self._hashes is None:
            global _WORD_POWERS
            if not len(self.starts):
                self._hashes = np.empty(0, dtype=np.uint64)
                return self._hashes
            lens = self.ends - self.starts
            if (most := int(lens.max())) > len(_WORD_POWERS):
                powers = _powers(_BASE, most)
                if most <= 1 << 16:
                    _WORD_POWERS = powers
            else:
                powers = _WORD_POWERS
            upto = np.concatenate(([0], np.cumsum(lens)))
            out = np.empty(len(lens), dtype=np.uint64)
            i = 0
            while i < len(lens):  # some arrays of 8 bytes a byte of text live at once
                j = max(i + 1, int(np.searchsorted(upto, upto[i] + HASH_BYTES, side="right")) - 1)
                begin = upto[i:j] - upto[i]
                at = np.arange(int(upto[j] - upto[i]), dtype=np.int64) - np.repeat(begin, lens[i:j])
                where = at + np.repeat(self.starts[i:j], lens[i:j])
                terms = powers[at]
                terms *= self.data[where].astype(np.uint64) + np.uint64(1)
                out[i:j] = np.add.reduceat(terms, begin)
                i = j
            self._hashes = mix64(out + lens.astype(np.uint64))
        return self._hashes

    def grams(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all runs of k words, and which of them stay in one document."""
        h = self.hashes
        n = len(h) - k + 1
        if n <= 0:
            return np.empty(0, dtype=np.uint64), np.empty(0, dtype=bool)
        out = h[:n].copy()
        p = 1
        for t in range(1, k):
            p = p * _GRAM & _MASK
            out += h[t : t + n] * np.uint64(p)
        return mix64(out), self.doc[:n] == self.doc[k - 1 : k - 1 + n]

    def text(self, i: int, j: int) -> bytes:
        """Words i to j joined by one blank, as normalised."""
        return b" ".join(self.data[s:e].tobytes() for s, e in zip(self.starts[i:j], self.ends[i:j], strict=True))


def shingle_sets(words: Words, k: int = 5) -> list[np.ndarray]:
    """Per document the sorted distinct hashes of its k-word runs; with fewer words the whole sequence as one."""
    grams, _ = words.grams(k)
    h, out = words.hashes, []
    for d in range(len(words.offsets) - 1):
        a, b = int(words.bounds[d]), int(words.bounds[d + 1])
        if b - a >= k:
            out.append(np.unique(grams[a : b - k + 1]))
        elif b > a:
            x = np.array([b - a], dtype=np.uint64)
            for t in range(a, b):
                x = mix64(x * np.uint64(_GRAM) + h[t : t + 1])
            out.append(x)
        else:
            out.append(np.empty(0, dtype=np.uint64))
    return out


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """min of x[i : i + w] for every i where that fits."""
    n = len(x) - w + 1
    if n <= 0:
        return x[:0]
    m, have = x, 1
    while have * 2 <= w:
        m = np.minimum(m[:-have], m[have:])
        have *= 2
    return np.minimum(m[:n], m[w - have : w - have + n]) if have < w else m[:n]
