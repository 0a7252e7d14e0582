"""Smoothing filters that the repair is compared with: median, Gaussian, anisotropic diffusion."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Side of the cubes that filters of dense arrays work on.
TILE = 32


def median(a: np.ndarray) -> np.ndarray:
    """Median of the 3 x 3 x 3 neighbourhood, edges repeated."""
    p = np.pad(a, 1, mode="edge")
    n = a.shape
    return np.median(np.stack([p[i : i + n[0], j : j + n[1], k : k + n[2]] for i in range(3) for j in range(3) for k in range(3)]), axis=0)


def gaussian(a: np.ndarray) -> np.ndarray:
    """Binomial taps (1, 2, 1) / 4 along every axis, edges repeated."""
    for axis in range(a.ndim):
        p = np.pad(a, [(1, 1) if b == axis else (0, 0) for b in range(a.ndim)], mode="edge")
        n = a.shape[axis]
        take = lambda k: np.take(p, range(k, k + n), axis=axis)  # noqa: B023, E731
        a = (take(0) + 2 * take(1) + take(2)) / 4
    return a


def diffusion(a: np.ndarray, rounds: int = 5, kappa: float | None = None, step: float = 1 / 7) -> np.ndarray:
    """Gradient-dependent conductance exp(-(g / kappa)^2); kappa defaults to the mean absolute step."""
    if kappa is None:
        kappa = float(np.mean([np.abs(np.diff(a, axis=x)).mean() for x in range(a.ndim) if a.shape[x] > 1] or [1.0])) or 1.0
    for _ in range(rounds):
        flow = np.zeros_like(a)
        for axis in range(a.ndim):
            g = np.diff(a, axis=axis)
            g = g * np.exp(-((g / kappa) ** 2))
            flow += np.concatenate((g, np.zeros_like(np.take(a, [0], axis))), axis) - np.concatenate((np.zeros_like(np.take(a, [0], axis)), g), axis)
        a = a + step * flow
    return a


def gauss_cells(cells: DataFrame) -> DataFrame:
    """Gaussian filter as three windows of bounded frames; the borders repeat their own value."""
    for axis in "xyz":
        w = Window.partitionBy(*[c for c in "xyz" if c != axis]).orderBy(axis)
        l, r = F.coalesce(F.lag("v").over(w), "v"), F.coalesce(F.lead("v").over(w), "v")
        cells = cells.select("x", "y", "z", ((l + 2 * F.col("v") + r) / 4).alias("v"))
    return cells


def median_cells(cells: DataFrame) -> DataFrame:
    """Median of the neighbourhood inside the grid: every cell is sent to its 27 neighbours and each takes the middle."""
    around = lambda c: F.explode(F.array(F.col(c) - 1, F.col(c), F.col(c) + 1)).alias(f"n{c}")
    out = cells
    for c in "xyz":
        out = out.select("*", around(c))
    groups = out.groupBy(F.col("nx").alias("x"), F.col("ny").alias("y"), F.col("nz").alias("z")).agg(F.median("v").alias("v"))
    return groups.join(cells.select("x", "y", "z"), ["x", "y", "z"], "left_semi")


def mean_step(cells: DataFrame) -> float:
    """The mean over the axes of the mean absolute step: the default conductance scale of the diffusion."""
    steps = []
    for axis in "xyz":
        w = Window.partitionBy(*[c for c in "xyz" if c != axis]).orderBy(axis)
        steps.append(cells.select(F.abs(F.lead("v").over(w) - F.col("v")).alias("step")).agg(F.avg("step").alias("step")))
    return float(steps[0].unionByName(steps[1]).unionByName(steps[2]).agg(F.avg("step")).first()[0] or 1.0) or 1.0


def tiled(cells: DataFrame, edge: int, work: Callable[[np.ndarray], np.ndarray], reach: int, side: int = TILE) -> DataFrame:
    """A filter of dense arrays on the cells (x, y, z, v) of a full cubic field, in cubes with a margin of ``reach`` points.

    A task holds one cube; points within reach of several cubes are sent to each.  Cubes end at the edge of the field, where the
    filter sees its own edge.
    """
    n = -(-edge // side)
    of = lambda c: F.floor(c / side).cast("int")
    tile = lambda c: F.explode(F.sequence(F.greatest(F.lit(0), of(F.col(c) - reach)), F.least(F.lit(n - 1), of(F.col(c) + reach)))).alias(f"t{c}")
    out = cells.select("x", "y", "z", F.col("v").cast("double").alias("v"))
    for c in "xyz":
        out = out.select("*", tile(c))

    def apply(table: pa.Table) -> pa.Table:
        at = np.stack([table.column(c).to_numpy() for c in "xyz"], axis=1).astype(np.int64)
        low = at.min(axis=0)
        dense = np.empty(at.max(axis=0) - low + 1)
        dense[tuple((at - low).T)] = table.column("v").to_numpy()
        made = work(dense)[tuple((at - low).T)]
        own = (at // side == np.array([table.column(f"t{c}")[0].as_py() for c in "xyz"])).all(axis=1)
        return pa.table({**{c: pa.array(at[own, k], pa.int32()) for k, c in enumerate("xyz")}, "v": pa.array(made[own])})

    return out.groupBy("tx", "ty", "tz").applyInArrow(apply, "x int, y int, z int, v double")


#: How far each filter reaches.
REACH = {"median": 1, "gaussian": 1, "diffusion": 5}
FILTERS = {"median": median, "gaussian": gaussian, "diffusion": diffusion}
