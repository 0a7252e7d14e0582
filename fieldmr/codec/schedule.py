"""Error bounds per level of the interpolation predictor."""

from __future__ import annotations

from itertools import product

#: Growth and cap of the finer-to-coarser tightening that the method settles on (fixed values).
ALPHA, BETA = 2.25, 8.0
#: Grid of the tuned schedule (fixed values).
ALPHAS, BETAS = (1.0, 1.25, 1.5, 1.75, 2.0, 2.25, 2.5), (1.0, 2.0, 4.0, 8.0, 16.0)


def eb_schedule(maxlevel: int, eb: float, alpha: float = ALPHA, beta: float = BETA, kind: str = "paper") -> list[float]:
    """Bounds of levels 0 (coarsest) to ``maxlevel`` (finest, always ``eb``).

    ``paper`` divides by min(alpha^distance, beta), ``flat`` keeps one bound, ``coarse`` halves the bound on the coarser half.
    """
    if kind == "flat":
        return [eb] * (maxlevel + 1)
    if kind == "coarse":
        return [eb / 2 if 2 * level < maxlevel else eb for level in range(maxlevel + 1)]
    if kind != "paper":
        raise ValueError(f"unknown schedule {kind!r}")
    return [eb / min(alpha ** (maxlevel - level), beta) for level in range(maxlevel + 1)]


def schedule_grid() -> list[tuple[float, float]]:
    """The (alpha, beta) pairs that a trial-tuned schedule chooses from."""
    return [(a, b) for a, b in product(ALPHAS, BETAS) if (a > 1) == (b > 1) or (a, b) == (1.0, 1.0)]
