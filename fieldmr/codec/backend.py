"""Quantiser and lossless back end shared by all codecs.

Integer codes are zigzagged, cut to the narrowest width, split into byte planes and compressed.
Values that the quantiser cannot hold within the bound go to an exact list of outliers.
"""

from __future__ import annotations

import struct

import numpy as np
import zstandard

#: Codes at or beyond this magnitude become outliers.
RADIUS = 1 << 20
OUTLIER = RADIUS
_LEVEL = 6


def quantize(value: np.ndarray, pred: np.ndarray, eb: float) -> tuple[np.ndarray, np.ndarray]:
    """(codes, reconstruction): the reconstruction is within ``eb`` of the value or, with code OUTLIER, the value itself."""
    if eb <= 0:
        return np.full(value.shape, OUTLIER, dtype=np.int64), value.copy()
    with np.errstate(invalid="ignore", over="ignore", divide="ignore"):
        q = np.floor((value - pred) / (2 * eb) + 0.5)
        ok = np.abs(q) < RADIUS
        q = np.where(ok, q, 0)
        made = pred + q * (2 * eb)
        ok &= np.abs(made - value) <= eb
    return np.where(ok, q, OUTLIER).astype(np.int64), np.where(ok, made, value)


def dequantize(codes: np.ndarray, pred: np.ndarray, eb: float, outliers: np.ndarray) -> np.ndarray:
    """Reconstruction from codes; ``outliers``: the exact values at OUTLIER codes, in order."""
    with np.errstate(invalid="ignore", over="ignore"):
        made = pred + codes * (2 * eb)
    made = np.array(made, dtype=np.float64)
    made[codes == OUTLIER] = outliers
    return made


def pack(codes: np.ndarray, extra: bytes = b"") -> bytes:
    """Signed integers and some raw bytes as one compressed string."""
    z = ((codes.astype(np.int64) << 1) ^ (codes.astype(np.int64) >> 63)).astype(np.uint64)
    top = int(z.max()) if len(z) else 0
    width = 1 if top < 1 << 8 else 2 if top < 1 << 16 else 4 if top < 1 << 32 else 8
    planes = z.astype(f"<u{width}").view(np.uint8).reshape(-1, width).T.tobytes()
    return struct.pack("<BII", width, len(z), len(extra)) + zstandard.ZstdCompressor(level=_LEVEL, write_checksum=False).compress(planes + extra)


def unpack(raw: bytes) -> tuple[np.ndarray, bytes]:
    width, n, extra = struct.unpack_from("<BII", raw)
    body = zstandard.ZstdDecompressor().decompress(raw[9:], max_output_size=width * n + extra + 1)
    z = np.frombuffer(body, np.uint8, width * n).reshape(width, -1).T.copy().view(f"<u{width}").reshape(-1).astype(np.uint64)
    codes = (z >> np.uint64(1)).astype(np.int64) ^ -(z & np.uint64(1)).astype(np.int64)
    return codes, body[width * n :]


def shannon_bits(codes: np.ndarray) -> float:
    """Order-0 entropy of all codes, in bits; a diagnostic, since it ignores runs."""
    if not len(codes):
        return 0.0
    _, n = np.unique(codes, return_counts=True)
    return float(-(n * np.log2(n / len(codes))).sum())


def lossless(values: np.ndarray) -> bytes:
    """Byte planes of raw doubles, compressed: the lossless baseline."""
    planes = np.ascontiguousarray(values, dtype="<f8").view(np.uint8).reshape(-1, 8).T.tobytes()
    return zstandard.ZstdCompressor(level=_LEVEL).compress(planes)
