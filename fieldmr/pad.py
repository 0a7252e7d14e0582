"""One extrapolated layer on the two short axes of a merged array."""

from __future__ import annotations

import numpy as np

#: Arrays whose short axes have at most this many points are not padded.
GATE = 4


def next_value(last: np.ndarray, how: str) -> np.ndarray:
    """The value after the last ones (up to three along axis 0): constant, linear or quadratic continuation."""
    n = {"constant": 1, "linear": 2, "quadratic": 3}[how]
    tail = last[-min(n, len(last)) :]
    if len(tail) == 1:
        return tail[-1]
    if len(tail) == 2:
        return 2 * tail[1] - tail[0]
    return 3 * tail[2] - 3 * tail[1] + tail[0]


def pad_short_axes(a: np.ndarray, how: str, gate: int = GATE) -> np.ndarray:
    """x first, then y, so the new corner continues padded values; never the merged axis z."""
    if how == "none" or min(a.shape[:2]) <= gate:
        return a
    a = np.concatenate((a, next_value(a[-3:], how)[None]), axis=0)
    return np.concatenate((a, next_value(np.moveaxis(a[:, -3:], 1, 0), how)[:, None]), axis=1)
