"""Static range asymmetric numeral systems over token ids, in independent interleaved blocks.

A segment has one frequency table for all its blocks.  Token i of a block goes to lane i mod ``LANES``, so a
step codes one token in every lane at once.  The checkpoint of a block holds where its words begin, the lanes'
states and a checksum of its tokens: any block decodes alone, in any order, on any machine.

States are 64-bit integers of at least 2^31, refilled 32 bits at a time (published form of the coder).
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

LANES = 512
BLOCK = 1 << 17
_LOW = np.uint64(1 << 31)
_W32 = np.uint64(32)
_MAGIC = b"FMTS\x01"
_HEAD = struct.Struct("<5sBHIQQII")
_POINT = np.dtype([("tokens", "<u4"), ("words", "<u8"), ("crc32", "<u4")])


def frequencies(counts: np.ndarray, bits: int) -> np.ndarray:
    """Positive integers in proportion to ``counts`` (all positive) that add up to 2^bits."""
    total = 1 << bits
    f = np.maximum(1, counts.astype(np.float64) * (total / counts.sum())).astype(np.int64)
    over = int(f.sum()) - total
    if over < 0:
        f[np.argmax(f)] -= over
    order = np.argsort(-f, kind="stable")
    while over > 0:  # rounding up rare ones is paid for by frequent ones
        for i in order:
            cut = min(over, int(f[i]) // 2)
            f[i] -= cut
            over -= cut
            if over <= 0 or f[i] <= 1:
                break
        order = np.argsort(-f, kind="stable")
    return f


def _encode_block(rank: np.ndarray, freq: np.ndarray, start: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    n = len(rank)
    states = np.full(LANES, _LOW, dtype=np.uint64)
    limit = np.uint64(1 << (31 - bits + 32))
    shift = np.uint64(bits)
    f_all, c_all = freq[rank], start[rank]
    words: list[np.ndarray] = []
    for at in range((n - 1) // LANES * LANES, -1, -LANES):
        f, c = f_all[at : at + LANES], c_all[at : at + LANES]
        x = states[: len(f)]
        full = x >= f * limit
        words.append(x[full].astype(np.uint32))
        x = np.where(full, x >> _W32, x)
        q = x // f
        states[: len(f)] = (q << shift) + (x - q * f) + c
    return states, np.concatenate(words[::-1]) if words else np.empty(0, np.uint32)


def _decode_block(n: int, states: np.ndarray, words: np.ndarray, symbols: np.ndarray, slots: np.ndarray, freq: np.ndarray, start: np.ndarray, bits: int) -> np.ndarray:
    out = np.empty(n, dtype=np.uint32)
    states, mask, shift, used = states.copy(), np.uint64((1 << bits) - 1), np.uint64(bits), 0
    for at in range(0, n, LANES):
        x = states[: min(LANES, n - at)]
        slot = x & mask
        rank = slots[slot.astype(np.int64)]
        out[at : at + LANES] = symbols[rank]
        x = freq[rank] * (x >> shift) + slot - start[rank]
        low = np.flatnonzero(x < _LOW)
        x[low] = (x[low] << _W32) | words[used : used + len(low)].astype(np.uint64)
        used += len(low)
        states[: len(x)] = x
    return out


def encode(ids: np.ndarray, doc_ids: np.ndarray, doc_lengths: np.ndarray) -> bytes:
    """One segment: the tokens of some whole documents, with their ids and lengths."""
    ids = np.ascontiguousarray(ids, dtype="<u4")
    counts = np.bincount(ids, minlength=1)
    symbols = np.flatnonzero(counts)
    bits = max(12, min(20, int(len(symbols)).bit_length() + 3))
    freq = frequencies(counts[symbols], bits) if len(symbols) else np.empty(0, np.int64)
    rank_of = np.zeros(len(counts), dtype=np.int64)
    rank_of[symbols] = np.arange(len(symbols))
    f = freq.astype(np.uint64)
    start = (np.cumsum(freq) - freq).astype(np.uint64)
    points, states, words, at = [], [], [], 0
    for i in range(0, len(ids), BLOCK):
        block = slice(i, i + BLOCK)
        s, w = _encode_block(rank_of[ids[block]], f, start, bits)
        points.append((len(ids[block]), at, zlib.crc32(ids[block].tobytes())))
        states.append(s)
        words.append(w)
        at += len(w)
    gaps = np.diff(symbols, prepend=0).astype("<u4")
    tables = zlib.compress(doc_ids.astype("<i8").tobytes() + doc_lengths.astype("<u8").tobytes() + gaps.tobytes() + freq.astype("<u4").tobytes(), 6)
    body = b"".join([np.array(points, dtype=_POINT).tobytes(), *(s.astype("<u8").tobytes() for s in states), *(w.astype("<u4").tobytes() for w in words)])
    head = _HEAD.pack(_MAGIC, bits, LANES, BLOCK, len(ids), len(doc_ids), len(symbols), len(tables))
    return head + tables + struct.pack("<I", zlib.crc32(head + tables)) + body


class Segment:
    """An encoded segment, opened for reading; blocks are decoded on demand."""

    def __init__(self, raw: bytes):
        magic, self.bits, lanes, self.block, self.n_tokens, n_docs, n_symbols, size = _HEAD.unpack_from(raw)
        if magic != _MAGIC or lanes != LANES:
            raise ValueError("not a token segment of this format")
        at = _HEAD.size + size
        if struct.unpack_from("<I", raw, at)[0] != zlib.crc32(raw[:at]):
            raise ValueError("the segment's tables are damaged")
        tables = zlib.decompress(raw[_HEAD.size : at])
        self.doc_ids = np.frombuffer(tables, "<i8", n_docs)
        self.doc_lengths = np.frombuffer(tables, "<u8", n_docs, 8 * n_docs).astype(np.int64)
        self.symbols = np.cumsum(np.frombuffer(tables, "<u4", n_symbols, 16 * n_docs).astype(np.int64)).astype(np.uint32)
        freq = np.frombuffer(tables, "<u4", n_symbols, 16 * n_docs + 4 * n_symbols).astype(np.int64)
        self.slots = np.repeat(np.arange(n_symbols), freq)
        self.freq, self.start = freq.astype(np.uint64), (np.cumsum(freq) - freq).astype(np.uint64)
        self.n_blocks, at = -(-self.n_tokens // self.block), at + 4
        self.points = np.frombuffer(raw, _POINT, self.n_blocks, at)
        at += _POINT.itemsize * self.n_blocks
        self.states = np.frombuffer(raw, "<u8", LANES * self.n_blocks, at).reshape(-1, LANES)
        self.words = np.frombuffer(raw, "<u4", -1, at + 8 * LANES * self.n_blocks)

    def read(self, k: int) -> np.ndarray:
        """Tokens of block k, checked."""
        point = self.points[k]
        end = int(self.points[k + 1]["words"]) if k + 1 < self.n_blocks else len(self.words)
        out = _decode_block(int(point["tokens"]), self.states[k], self.words[int(point["words"]) : end], self.symbols, self.slots, self.freq, self.start, self.bits)
        if zlib.crc32(out.astype("<u4").tobytes()) != int(point["crc32"]):
            raise ValueError(f"block {k} is damaged")
        return out

    def tokens(self) -> np.ndarray:
        return np.concatenate([self.read(k) for k in range(self.n_blocks)]) if self.n_blocks else np.empty(0, np.uint32)
