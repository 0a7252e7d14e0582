"""Global interpolation codec: strides halve, targets between known lattice points are predicted from reconstructed values.

At stride s the axes are swept in turn.  A target is an odd multiple of s on the swept axis; axes swept before it at this stride
are on the s lattice, the others on the 2s lattice.  A target with a known point on both sides is
interpolated, one past the last known point is extrapolated, which a line of 2^k + 1 points never needs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from .backend import OUTLIER, dequantize, pack, quantize, unpack
from .schedule import ALPHA, BETA, eb_schedule


def top_stride(n: int) -> int:
    """Exponent of the largest stride for a longest axis of n points, -1 if there is none."""
    k = -1
    while (1 << (k + 1)) < n - 1:
        k += 1
    return k if n > 2 else (0 if n == 2 else -1)


def interp_plan(n: int) -> list[tuple[int, int, int | None, int | None, str]]:
    """(level, index, left, right, kind) for every point of a line of n, in the order of coding."""
    rows: list[tuple[int, int, int | None, int | None, str]] = [(0, 0, None, None, "first")] if n else []
    if n > 1:
        rows.append((1, n - 1, 0, None, "last"))
    stride, level = 1 << max(0, top_stride(n)), 2
    while stride and n > 2:
        for at in range(stride, n - 1, 2 * stride):
            right = at + stride
            known = right < n
            rows.append((level, at, at - stride, right if known else None, "interpolated" if known else "extrapolated"))
        stride, level = stride // 2, level + 1
    return rows


def _sweeps(shape: tuple[int, ...]) -> Iterator[tuple[int, int, int, tuple[slice, ...]]]:
    """(exponent, stride, axis, lattice of the other axes) in the order of coding."""
    for k in range(top_stride(max(shape)), -1, -1):
        s = 1 << k
        for axis, n in enumerate(shape):
            if s < n:
                yield k, s, axis, tuple(slice(0, None, s if b < axis else 2 * s) if b != axis else slice(None) for b in range(len(shape)))


def _predict(known: np.ndarray, at: np.ndarray, s: int, order: str, extrap: str) -> np.ndarray:
    """Predictions on a line-first view; at most the last target has no right neighbour."""
    n = len(known)
    left = known[at - s]
    inner = at[at + s < n]
    out = np.empty_like(left)
    m = len(inner)
    out[:m] = 0.5 * (left[:m] + known[inner + s])
    if order == "cubic":
        full = np.flatnonzero((inner >= 3 * s) & (inner + 3 * s < n))
        if len(full):
            t = inner[full]
            out[full] = (9.0 * (known[t - s] + known[t + s]) - known[t - 3 * s] - known[t + 3 * s]) / 16.0
    if m < len(at):
        t = at[m]
        out[m] = 2.0 * known[t - s] - known[t - 3 * s] if extrap == "linear2" and t >= 3 * s else left[m]
    return out


def _bounds(shape: tuple[int, ...], eb: float, schedule: str, alpha: float, beta: float) -> list[float]:
    """Bound per exponent of the stride, the start lattice last."""
    top = top_stride(max(shape))
    return eb_schedule(top + 1, eb, alpha, beta, schedule)[::-1]


def _start(shape: tuple[int, ...]) -> tuple[slice, ...]:
    """The lattice of twice the largest stride: the origin, and far ends of axes of 2^k + 1 points."""
    step = 2 << max(0, top_stride(max(shape)))
    return tuple(slice(0, None, step) for _ in shape)


def interp_encode(a: np.ndarray, eb: float, order: str = "cubic", extrap: str = "copy", schedule: str = "paper", alpha: float = ALPHA, beta: float = BETA) -> tuple[bytes, np.ndarray]:
    """(packed bytes, reconstruction)."""
    a = np.asarray(a, dtype=np.float64)
    bounds = _bounds(a.shape, eb, schedule, alpha, beta)
    made = np.zeros(a.shape)
    codes: list[np.ndarray] = []
    odd: list[np.ndarray] = []

    def code(value: np.ndarray, pred: np.ndarray, bound: float) -> np.ndarray:
        q, back = quantize(value, pred, bound)
        codes.append(q.ravel())
        odd.append(value.ravel()[codes[-1] == OUTLIER])
        return back

    first = _start(a.shape)
    head = a[first].ravel()
    back = np.empty_like(head)
    back[:1] = code(head[:1], np.zeros(1), bounds[-1])
    back[1:] = code(head[1:], np.full(len(head) - 1, back[0]), bounds[-1])
    made[first] = back.reshape(a[first].shape)
    for k, s, axis, lattice in _sweeps(a.shape):
        view, source = np.moveaxis(made[lattice], axis, 0), np.moveaxis(a[lattice], axis, 0)
        at = np.arange(s, a.shape[axis], 2 * s)
        view[at] = code(source[at], _predict(view, at, s, order, extrap), bounds[k])
    return pack(np.concatenate(codes), np.concatenate(odd).astype("<f8").tobytes()), made


def interp_decode(raw: bytes, shape: tuple[int, ...], eb: float, order: str = "cubic", extrap: str = "copy", schedule: str = "paper", alpha: float = ALPHA, beta: float = BETA) -> np.ndarray:
    codes, extra = unpack(raw)
    odd = np.frombuffer(extra, "<f8")
    bounds = _bounds(shape, eb, schedule, alpha, beta)
    made = np.zeros(shape)
    at_code = at_odd = 0

    def value(pred: np.ndarray, bound: float) -> np.ndarray:
        nonlocal at_code, at_odd
        q = codes[at_code : at_code + pred.size].reshape(pred.shape)
        n = int(np.count_nonzero(q == OUTLIER))
        back = dequantize(q, pred, bound, odd[at_odd : at_odd + n])
        at_code, at_odd = at_code + pred.size, at_odd + n
        return back

    first = _start(shape)
    lattice_shape = made[first].shape
    head = np.empty(made[first].size)
    head[:1] = value(np.zeros(1), bounds[-1])
    head[1:] = value(np.full(len(head) - 1, head[0]), bounds[-1])
    made[first] = head.reshape(lattice_shape)
    for k, s, axis, lattice in _sweeps(shape):
        view = np.moveaxis(made[lattice], axis, 0)
        at = np.arange(s, shape[axis], 2 * s)
        view[at] = value(_predict(view, at, s, order, extrap), bounds[k])
    return made
