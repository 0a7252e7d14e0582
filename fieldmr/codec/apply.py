"""A codec configuration applied to one chunk: blocks of side u with their keys, encoded to bytes and back."""

from __future__ import annotations

import struct
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np

from ..arrange import kd_boxes
from ..pad import pad_short_axes
from .backend import lossless
from .blockpred import blockpred_decode, blockpred_encode
from .blockxform import blockxform_decode, blockxform_encode
from .interp import interp_decode, interp_encode
from .schedule import ALPHA, BETA


@dataclass(frozen=True)
class Codec:
    """``name``: interp, blockpred, blockxform or lossless; the other fields matter to some of them."""

    name: str = "interp"
    eb: float = 1.0
    arrange: str = "linear"
    pad: str = "none"
    order: str = "cubic"
    extrap: str = "copy"
    schedule: str = "flat"
    alpha: float = ALPHA
    beta: float = BETA
    block: int = 4
    predictor: str = "auto"
    transform: str = "lift"
    repair: str = "none"
    label: str = ""

    def at(self, eb: float) -> Codec:
        return replace(self, eb=eb)


def mrinterp(eb: float = 1.0, **more) -> Codec:
    """The multi-resolution interpolation codec: linear merge, linear padding, a bound per level."""
    return Codec("interp", eb, "linear", "linear", schedule="paper", **more)


def coordinates(keys: np.ndarray, nby: int, nbz: int) -> np.ndarray:
    return np.stack([keys // (nby * nbz), keys // nbz % nby, keys % nbz], axis=1)


def _z_codes(keys: np.ndarray, u: int, nby: int, nbz: int) -> np.ndarray:
    """The z-order code of all cells of the blocks."""
    base = coordinates(keys, nby, nbz) * u
    i = np.stack(np.meshgrid(*[np.arange(u)] * 3, indexing="ij"), axis=-1).reshape(-1, 3)
    at = (base[:, None, :] + i[None, :, :]).reshape(-1, 3).astype(np.uint64)
    code = np.zeros(len(at), dtype=np.uint64)
    for bit in range(20):
        for axis in range(3):
            code |= ((at[:, axis] >> np.uint64(bit)) & np.uint64(1)) << np.uint64(3 * bit + axis)
    return code


def _z_order(keys: np.ndarray, u: int, nby: int, nbz: int) -> np.ndarray:
    """Order of all cells of the blocks along the z-order curve."""
    return np.argsort(_z_codes(keys, u, nby, nbz), kind="stable")


def _hz_order(keys: np.ndarray, u: int, nby: int, nbz: int) -> np.ndarray:
    """Order of all cells along the hierarchical z-order: coarse sub-grids first, each in z-order.

    A cell's level is told by the lowest set bit of its code; the cell at the origin is the coarsest.
    """
    code = _z_codes(keys, u, nby, nbz)
    lowest = code & (~code + np.uint64(1))
    lowest[code == 0] = np.uint64(1 << 63)
    return np.lexsort((code, ~lowest))


_CURVES = {"zline": _z_order, "hzline": _hz_order}


def _arrays(keys: np.ndarray, u: int, nby: int, nbz: int, arrange: str) -> list[tuple[tuple[int, ...], np.ndarray]]:
    """Arrays to code as (shape in blocks, block numbers in row-major order)."""
    m = len(keys)
    if arrange == "linear":
        return [((1, 1, m), np.arange(m))]
    if arrange == "stack":
        side = 1
        while side**3 < m:
            side += 1
        depth = -(-m // side**2)
        return [((depth, side, side), np.minimum(np.arange(depth * side * side), m - 1))]
    if arrange == "kd":
        at = coordinates(keys, nby, nbz)
        low = at.min(axis=0)
        number = np.full(at.max(axis=0) - low + 1, -1, dtype=np.int64)
        number[tuple((at - low).T)] = np.arange(m)
        return [((x1 - x0, y1 - y0, z1 - z0), number[x0:x1, y0:y1, z0:z1].ravel()) for x0, x1, y0, y1, z0, z1 in kd_boxes(number >= 0)]
    raise ValueError(f"unknown arrangement {arrange!r}")


def _merge(vals: np.ndarray, shape: tuple[int, ...], which: np.ndarray) -> np.ndarray:
    u = vals.shape[1]
    return vals[which].reshape(*shape, u, u, u).transpose(0, 3, 1, 4, 2, 5).reshape(shape[0] * u, shape[1] * u, shape[2] * u)


def _scatter(out: np.ndarray, a: np.ndarray, shape: tuple[int, ...], which: np.ndarray) -> None:
    u = out.shape[1]
    out[which] = a.reshape(shape[0], u, shape[1], u, shape[2], u).transpose(0, 2, 4, 1, 3, 5).reshape(-1, u, u, u)


def _cubes(vals: np.ndarray, b: int) -> np.ndarray:
    """Sub-cubes of side b; blocks whose side is no multiple are filled by repeating their edge."""
    u = vals.shape[1]
    fill = -u % b
    if fill:
        vals = np.pad(vals, ((0, 0), *[(0, fill)] * 3), mode="edge")
    k = (u + fill) // b
    return vals.reshape(-1, k, b, k, b, k, b).transpose(0, 1, 3, 5, 2, 4, 6).reshape(-1, b, b, b)


def _uncubes(cubes: np.ndarray, m: int, u: int, b: int) -> np.ndarray:
    k = (u + -u % b) // b
    return cubes.reshape(m, k, k, k, b, b, b).transpose(0, 1, 4, 2, 5, 3, 6).reshape(m, k * b, k * b, k * b)[:, :u, :u, :u]


def _interp_options(c: Codec) -> dict:
    return {"order": c.order, "extrap": c.extrap, "schedule": c.schedule, "alpha": c.alpha, "beta": c.beta}


def prepared(keys: np.ndarray, vals: np.ndarray, c: Codec, nby: int, nbz: int) -> Iterator[tuple[tuple[int, ...], np.ndarray, np.ndarray]]:
    """The arrays that the interpolation codec is given: (shape in blocks, block numbers, merged and padded values)."""
    for shape, which in _arrays(keys, vals.shape[1], nby, nbz, c.arrange):
        a = _merge(vals, shape, which)
        yield shape, which, pad_short_axes(a, c.pad) if c.arrange == "linear" else a


def encode_chunk(keys: np.ndarray, vals: np.ndarray, c: Codec, nby: int, nbz: int) -> tuple[bytes, np.ndarray]:
    """(bytes, reconstruction) of (m, u, u, u) blocks."""
    u, m = vals.shape[1], len(vals)
    if c.name == "lossless":
        return lossless(vals.ravel()), vals.copy()
    if c.name == "blockpred":
        raw, made = blockpred_encode(_cubes(vals, c.block), c.eb, c.predictor)
        return raw, _uncubes(made, m, u, c.block)
    if c.name == "blockxform":
        raw, made = blockxform_encode(_cubes(vals, 4), c.eb, c.transform)
        return raw, _uncubes(made, m, u, 4)
    if c.arrange in _CURVES:
        order = _CURVES[c.arrange](keys, u, nby, nbz)
        raw, made = interp_encode(vals.reshape(-1)[order], c.eb, **_interp_options(c))
        flat = np.empty(vals.size)
        flat[order] = made
        return raw, flat.reshape(vals.shape)
    out, parts = np.empty(vals.shape), []
    for shape, which, padded in prepared(keys, vals, c, nby, nbz):
        raw, made = interp_encode(padded, c.eb, **_interp_options(c))
        _scatter(out, made[tuple(slice(0, n * u) for n in shape)], shape, which)
        parts.append(raw)
    return struct.pack(f"<I{len(parts)}I", len(parts), *map(len, parts)) + b"".join(parts), out


def decode_chunk(raw: bytes, keys: np.ndarray, u: int, c: Codec, nby: int, nbz: int) -> np.ndarray:
    m = len(keys)
    if c.name == "lossless":
        import zstandard

        planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), np.uint8)
        return planes.reshape(8, -1).T.copy().view("<f8").reshape(m, u, u, u)
    if c.name in ("blockpred", "blockxform"):
        b = c.block if c.name == "blockpred" else 4
        n = m * ((u + -u % b) // b) ** 3
        made = blockpred_decode(raw, n, b, c.eb, c.predictor) if c.name == "blockpred" else blockxform_decode(raw, n, c.eb, c.transform)
        return _uncubes(made, m, u, b)
    if c.arrange in _CURVES:
        flat = np.empty(m * u**3)
        flat[_CURVES[c.arrange](keys, u, nby, nbz)] = interp_decode(raw, (m * u**3,), c.eb, **_interp_options(c))
        return flat.reshape(m, u, u, u)
    out = np.empty((m, u, u, u))
    n = struct.unpack_from("<I", raw)[0]
    sizes = struct.unpack_from(f"<{n}I", raw, 4)
    at = 4 + 4 * n
    for (shape, which), size in zip(_arrays(keys, u, nby, nbz, c.arrange), sizes, strict=True):
        whole = tuple(s * u for s in shape)
        padded = pad_short_axes(np.zeros(whole), c.pad).shape if c.arrange == "linear" else whole
        made = interp_decode(raw[at : at + size], padded, c.eb, **_interp_options(c))
        _scatter(out, made[: whole[0], : whole[1], : whole[2]], shape, which)
        at += size
    return out
