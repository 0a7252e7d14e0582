"""Error-bounded repair of block faces: a quadratic curve through the neighbours, clamped around the decompressed value.

Two forms of one method: numpy on a dense array (absent points are NaN), and a DataFrame plan in which each axis is
one window of two neighbours.  Axes are processed one after the other; within an axis all reads see the state before it.
"""

from __future__ import annotations

from itertools import product

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Intensities to choose from, per codec (fixed values).
CANDIDATES = {
    "blockpred": (0.05, 0.10, 0.15, 0.20, 0.25, 0.30, 0.35, 0.40, 0.45, 0.50),
    "blockxform": (0.005, 0.010, 0.015, 0.020, 0.025, 0.030, 0.035, 0.040, 0.045, 0.050),
}
CANDIDATES["interp"] = CANDIDATES["blockpred"]
#: Share of the points that the fit may sample.
SAMPLE_RATE = 0.015
#: Blocks that it samples at most, however large the field is.
SAMPLE_BLOCKS = 1024


def bezier(l, c, r, t=0.5):
    """Quadratic curve with the neighbours as ends and the point as control; works on numbers, arrays and columns."""
    return l * ((1 - t) * (1 - t)) + c * (2 * t * (1 - t)) + r * (t * t)


def midpoint(l, c, r):
    return (l + 2 * c + r) / 4


def sweep(d: np.ndarray, axis: int, b: int, limit: float | None, t: float = 0.5) -> np.ndarray:
    """One axis: points at faces of blocks of side b whose two neighbours exist; ``limit`` None leaves the curve unclamped."""
    n = d.shape[axis]
    if n < 3:
        return d
    v = np.moveaxis(d, axis, 0)
    at = np.arange(1, n - 1)
    at = at[(at % b == 0) | (at % b == b - 1)]
    c = v[at]
    m = bezier(v[at - 1], c, v[at + 1], t)
    if limit is not None:
        m = np.clip(m, c - limit, c + limit)
    out = v.copy()
    out[at] = np.where(np.isfinite(m), m, c)
    return np.moveaxis(out, 0, axis)


def repair(d: np.ndarray, eb: float, a: tuple[float, float, float] | None, b: int, combine: str = "sequential", hard: bool = False) -> np.ndarray:
    """``a``: intensity per axis, None for the unclamped curve.

    ``combine="average"`` averages the three corrections of the unrepaired array; ``hard`` also clamps the sum of all axes
    to the largest intensity.
    """
    limits = [None if a is None else x * eb for x in (a or (0, 0, 0))]
    if combine == "average":
        return d + sum(sweep(d, axis, b, limits[axis]) - d for axis in range(3)) / 3
    out = d
    for axis in range(3):
        out = sweep(out, axis, b, limits[axis])
    if hard and a is not None:
        out = np.clip(out, d - max(a) * eb, d + max(a) * eb)
    return out


def face_mask(side: int, b: int) -> np.ndarray:
    """Which places along a block's edge lie at a face of its cubes of side b, the block's own ends included."""
    at = np.arange(side)
    return (at % b == 0) | (at % b == b - 1) | (at == side - 1)


def sweep_padded(p: np.ndarray, axis: int, b: int, limit: float | None, t: float = 0.5) -> np.ndarray:
    """One axis for many blocks (m, s + 2, s + 2, s + 2) that carry a layer of their neighbours, NaN where there is none."""
    side = p.shape[1] - 2
    at = np.flatnonzero(face_mask(side, b)) + 1
    v = np.moveaxis(p, axis + 1, 0)
    c = v[at]
    m = bezier(v[at - 1], c, v[at + 1], t)
    if limit is not None:
        m = np.clip(m, c - limit, c + limit)
    out = v.copy()
    out[at] = np.where(np.isfinite(m), m, c)
    return np.moveaxis(out, 0, axis + 1)


def repair_padded(p: np.ndarray, eb: float, a: tuple[float, float, float] | None, b: int) -> np.ndarray:
    """The repaired blocks without their layer; ``a`` None is the unclamped curve.

    A layer of one point on all 26 sides is enough: what an axis needs from the axes before it, it recomputes there.
    """
    for axis in range(3):
        if a is None or a[axis] > 0:
            p = sweep_padded(p, axis, b, None if a is None else a[axis] * eb)
    return p[:, 1:-1, 1:-1, 1:-1]


def sample_plan(shape: tuple[int, ...], b: int, rate: float = SAMPLE_RATE) -> tuple[int, int, list[tuple[int, int, int]]]:
    """(cubes per axis, side, origins): evenly placed cubes of a few blocks a side, within the rate if the field is large enough."""
    n = float(np.prod(shape))
    for j in (4, 3, 2):
        i = int((rate * n) ** (1 / 3) / (j * b))
        if i >= 1:
            break
    i = max(1, i)
    side = min(j * b, *[s // b * b for s in shape]) or min(shape)
    steps = []
    for s in shape:
        room = max(0, (s - side) // b)
        steps.append(sorted({int(round(room * (k + 0.5) / i)) * b if i > 1 else room // 2 * b for k in range(i)}))
    return i, side, [tuple(o) for o in product(*steps)]


def expected_gain(orig: np.ndarray, d: np.ndarray, moved: np.ndarray) -> tuple[float, float]:
    """(share of moves that do not go the wrong way, mean reduction of the absolute error)."""
    step = moved - d
    go = step != 0
    if not go.any():
        return 1.0, 0.0
    right = (step * (orig - d))[go] >= 0
    return float(right.mean()), float((np.abs(orig - d) - np.abs(orig - moved))[go].mean())


def _losses(pairs: list[tuple[np.ndarray, np.ndarray]], axis: int, b: int, eb: float, grid: tuple[float, ...]) -> np.ndarray:
    return np.array([sum(float(np.nansum((o - sweep(d, axis, b, a * eb)) ** 2)) for o, d in pairs) for a in grid])


def fit_intensity(pairs: list[tuple[np.ndarray, np.ndarray]], eb: float, b: int, grid: tuple[float, ...], method: str = "coordinate", include_zero: bool = False, seed: int = 7) -> tuple[float, float, float]:
    """Intensity per axis with the least squared error on sample cubes of (original, decompressed) values.

    ``coordinate`` fits an axis after the axes before it were repaired, ``grid`` every axis on the unrepaired sample, ``joint`` all
    triples, ``sgd`` steps along the grid on random batches of cubes.
    """
    grid = (0.0, *grid) if include_zero else tuple(grid)
    if method == "joint":
        score = lambda t: sum(float(np.nansum((o - repair(d, eb, t, b)) ** 2)) for o, d in pairs)
        return min(product(grid, repeat=3), key=score)
    if method == "sgd":
        return _descend(pairs, eb, b, grid, seed)
    found = []
    for axis in range(3):
        a = grid[int(np.argmin(_losses(pairs, axis, b, eb, grid)))]
        found.append(a)
        if method == "coordinate":
            pairs = [(o, sweep(d, axis, b, a * eb)) for o, d in pairs]
    return tuple(found)


def _descend(pairs, eb, b, grid, seed) -> tuple[float, float, float]:
    """Stochastic descent on grid indices, axis by axis; evaluations of an index are averaged over its last three batches."""
    rng, state, still = np.random.default_rng(seed), [len(grid) // 2] * 3, 0
    seen: dict[tuple[int, int], list[float]] = {}
    size = max(1, len(pairs) // 2)
    for step in range(6 * len(grid)):
        axis = step % 3
        batch = [pairs[i] for i in rng.choice(len(pairs), size, replace=False)]
        for earlier in range(axis):
            batch = [(o, sweep(d, earlier, b, grid[state[earlier]] * eb)) for o, d in batch]
        near = [k for k in (state[axis] - 1, state[axis], state[axis] + 1) if 0 <= k < len(grid)]
        losses = _losses(batch, axis, b, eb, tuple(grid[k] for k in near))
        for k, loss in zip(near, losses, strict=True):
            seen.setdefault((axis, k), []).append(float(loss))
        best = min(near, key=lambda k: float(np.mean(seen[axis, k][-3:])))
        still = 0 if best != state[axis] else still + 1
        state[axis] = best
        if still >= 9:
            break
    return tuple(grid[k] for k in state)


# DataFrame form


def with_neighbours(cells: DataFrame, axis: str) -> DataFrame:
    """``l`` and ``r``: values next to a cell on an axis, null where there is none; one window over a line of the grid."""
    w = Window.partitionBy(*[c for c in "xyz" if c != axis]).orderBy(axis)
    near = lambda f, d: F.when(f(F.col(axis)).over(w) == F.col(axis) + d, f("v").over(w))
    return cells.withColumn("l", near(F.lag, -1)).withColumn("r", near(F.lead, 1))


def is_face(axis: str, b: int) -> Column:
    return (F.col(axis) % b).isin(0, b - 1)


def sweep_cells(cells: DataFrame, axis: str, b: int, limit: Column | float | None) -> DataFrame:
    """One axis of the repair on (x, y, z, v)."""
    m = (F.col("l") + 2 * F.col("v") + F.col("r")) / 4
    if limit is not None:
        bound = F.lit(limit) if isinstance(limit, (int, float)) else limit
        m = F.least(F.greatest(m, F.col("v") - bound), F.col("v") + bound)
    able = is_face(axis, b) & F.col("l").isNotNull() & F.col("r").isNotNull()
    return with_neighbours(cells, axis).select("x", "y", "z", F.when(able, m).otherwise(F.col("v").cast("double")).alias("v"))


def repair_cells(cells: DataFrame, eb: float, a: tuple[float, float, float] | None, b: int, combine: str = "sequential") -> DataFrame:
    """The whole repair; sequential axes are three windows, ``average`` three independent ones."""
    limits = [None if a is None else x * eb for x in (a or (0, 0, 0))]
    if combine == "average":
        parts = [sweep_cells(cells, axis, b, limits[k]) for k, axis in enumerate("xyz")]
        return parts[0].unionByName(parts[1]).unionByName(parts[2]).groupBy("x", "y", "z").agg((F.sum("v") / 3).alias("v"))
    for k, axis in enumerate("xyz"):
        cells = sweep_cells(cells, axis, b, limits[k])
    return cells


def situations(pairs: DataFrame, axis: str, b: int) -> DataFrame:
    """How the curve moves face points relative to the original: wrong way, past it, or between; with the summed gain."""
    cells = with_neighbours(pairs.select("x", "y", "z", F.col("deco").alias("v"), "orig"), axis).where(is_face(axis, b) & F.col("l").isNotNull() & F.col("r").isNotNull())
    move, want = (F.col("l") + F.col("r") - 2 * F.col("v")) / 4, F.col("orig") - F.col("v")
    kind = F.when((move == 0) | (want == 0), "still").when(F.signum(move) != F.signum(want), "wrong way").when(F.abs(move) > F.abs(want), "overshoot").otherwise("between")
    return cells.select(kind.alias("kind"), (F.abs(want) - F.abs(want - move)).alias("gain")).groupBy("kind").agg(F.count("*").alias("n"), F.sum("gain").alias("gain"))


def fit_cells(pairs: DataFrame, axis: str, b: int, eb: float, grid: tuple[float, ...]) -> DataFrame:
    """(a, sse) per candidate on one axis: the grid is a literal of a few rows."""
    spark = pairs.sparkSession
    cells = with_neighbours(pairs.select("x", "y", "z", F.col("deco").alias("v"), "orig"), axis).where(is_face(axis, b) & F.col("l").isNotNull() & F.col("r").isNotNull())
    options = F.broadcast(spark.createDataFrame([(float(a),) for a in grid], "a double"))
    m = (F.col("l") + 2 * F.col("v") + F.col("r")) / 4
    near = F.least(F.greatest(m, F.col("v") - F.col("a") * eb), F.col("v") + F.col("a") * eb)
    return cells.crossJoin(options).groupBy("a").agg(F.sum((F.col("orig") - near) * (F.col("orig") - near)).alias("sse"), F.count("*").alias("n"))
