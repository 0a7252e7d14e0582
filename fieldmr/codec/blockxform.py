"""Block-wise transform coding of 4x4x4 cubes, vectorised over all cubes.

``lift``: a common exponent per cube, an integer lifted transform per axis, low bit planes dropped as far as the bound allows.
``dct``: an orthonormal cosine transform with uniform quantisation.  Both check the bound on the reconstruction: a cube that
breaks it is coded finer, and cubes that no step can hold are kept exactly.
"""

from __future__ import annotations

import numpy as np

from .backend import pack, unpack

SIDE = 4
#: Bits of the scaled integers of the lifted transform.
_BITS = 40
#: Steps are halved at most so often before a cube is kept exactly.
_FINER = 8

_ORDER = np.argsort(np.add.outer(np.add.outer(np.arange(4), np.arange(4)), np.arange(4)).ravel(), kind="stable")
_COS = np.array([[np.sqrt((1 if u == 0 else 2) / SIDE) * np.cos(np.pi * (2 * x + 1) * u / (2 * SIDE)) for x in range(SIDE)] for u in range(SIDE)])


def _lift(x: np.ndarray) -> np.ndarray:
    """Two levels of an integer average-difference transform along the last axis; exactly invertible."""
    a, b, c, d = (x[..., i] for i in range(4))
    d0, d1 = b - a, d - c
    s0, s1 = a + (d0 >> 1), c + (d1 >> 1)
    t = s1 - s0
    s = s0 + (t >> 1)
    return np.stack([s, t, d0, d1], axis=-1)


def _unlift(y: np.ndarray) -> np.ndarray:
    s, t, d0, d1 = (y[..., i] for i in range(4))
    s0 = s - (t >> 1)
    s1 = s0 + t
    a, c = s0 - (d0 >> 1), s1 - (d1 >> 1)
    return np.stack([a, a + d0, c, c + d1], axis=-1)


def _over_axes(f, x: np.ndarray, axes: tuple[int, ...]) -> np.ndarray:
    for axis in axes:
        x = np.moveaxis(f(np.moveaxis(x, axis, -1)), -1, axis)
    return x


def _forward(cubes: np.ndarray, exponent: np.ndarray, transform: str) -> np.ndarray:
    if transform == "dct":
        return np.einsum("ai,bj,ck,nijk->nabc", _COS, _COS, _COS, cubes, optimize=True)
    whole = np.floor(np.ldexp(cubes, (_BITS - exponent)[:, None, None, None]) + 0.5).astype(np.int64)
    return _over_axes(_lift, whole, (1, 2, 3))


def _backward(kept: np.ndarray, step: np.ndarray, exponent: np.ndarray, transform: str) -> np.ndarray:
    """Values from quantised coefficients; ``step``: the quantum (dct) or the dropped planes (lift) per cube."""
    if transform == "dct":
        return np.einsum("ai,bj,ck,nabc->nijk", _COS, _COS, _COS, kept * step[:, None, None, None], optimize=True)
    planes = step.astype(np.int64)[:, None, None, None]
    whole = _over_axes(_unlift, kept << planes, (3, 2, 1))
    return np.ldexp(whole.astype(np.float64), (exponent - _BITS)[:, None, None, None])


def _steps(eb: float, exponent: np.ndarray, finer: np.ndarray, transform: str) -> np.ndarray:
    if transform == "dct":
        return 2.0 * eb * np.exp2(1.0 - finer)
    planes = np.floor(np.log2(max(eb, 1e-300))) + 1 + _BITS - exponent - finer
    return np.clip(planes, 0, _BITS + 2)


def _quantised(coef: np.ndarray, step: np.ndarray, transform: str) -> np.ndarray:
    if transform == "dct":
        return np.floor(coef / step[:, None, None, None] + 0.5).astype(np.int64)
    planes = step.astype(np.int64)[:, None, None, None]
    half = np.where(planes > 0, np.int64(1) << np.maximum(planes - 1, 0), 0)
    return (coef + half) >> planes


def blockxform_encode(cubes: np.ndarray, eb: float, transform: str = "lift") -> tuple[bytes, np.ndarray]:
    """``cubes``: (n, 4, 4, 4).  (packed bytes, reconstruction)."""
    cubes = np.asarray(cubes, dtype=np.float64)
    n = len(cubes)
    fine = np.isfinite(cubes).all(axis=(1, 2, 3)) if n else np.empty(0, bool)
    exact = ~fine if eb > 0 else np.ones(n, dtype=bool)
    safe = np.where(exact[:, None, None, None], 0.0, cubes)
    top = np.abs(safe).max(axis=(1, 2, 3)) if n else np.empty(0)
    exponent = np.where(top > 0, np.frexp(top)[1], 0).astype(np.int64)
    exact |= np.abs(exponent) > 900
    coef = _forward(np.where(exact[:, None, None, None], 0.0, safe), np.where(exact, 0, exponent), transform)
    exponent = np.where(exact, 0, exponent)
    finer = np.zeros(n)
    made, kept = np.zeros(cubes.shape), np.zeros(cubes.shape, dtype=np.int64)
    todo = np.flatnonzero(~exact)
    while len(todo):
        step = _steps(eb, exponent[todo], finer[todo], transform)
        kept[todo] = _quantised(coef[todo], step, transform)
        made[todo] = _backward(kept[todo], step, exponent[todo], transform)
        bad = todo[np.abs(made[todo] - cubes[todo]).max(axis=(1, 2, 3)) > eb]
        finer[bad] += 1
        exact[bad[finer[bad] > _FINER]] = True
        todo = bad[finer[bad] <= _FINER]
    kept[exact] = 0
    made[exact] = cubes[exact]
    codes = kept.reshape(n, -1)[:, _ORDER].T.ravel()
    side = pack(np.concatenate((exponent if transform == "lift" else np.zeros(n, np.int64), finer.astype(np.int64), exact.astype(np.int64))))
    return pack(codes, len(side).to_bytes(4, "little") + side + cubes[exact].astype("<f8").tobytes()), made


def blockxform_decode(raw: bytes, n: int, eb: float, transform: str = "lift") -> np.ndarray:
    codes, extra = unpack(raw)
    size = int.from_bytes(extra[:4], "little")
    side, _ = unpack(extra[4 : 4 + size])
    exponent, finer, exact = side[:n], side[n : 2 * n].astype(np.float64), side[2 * n :].astype(bool)
    flat = np.empty((n, SIDE**3), dtype=np.int64)
    flat[:, _ORDER] = codes.reshape(SIDE**3, n).T
    made = _backward(flat.reshape(n, SIDE, SIDE, SIDE), _steps(eb, exponent, finer, transform), exponent, transform) if n else np.zeros((0, 4, 4, 4))
    made[exact] = np.frombuffer(extra[4 + size :], "<f8").reshape(-1, SIDE, SIDE, SIDE)
    return made
