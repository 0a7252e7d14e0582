"""Blocks, regions of interest, levels and unit blocks, as DataFrame plans."""

from __future__ import annotations

from math import ceil

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .grid import block_key, offset

#: Buckets of a range histogram; the exact cut needs one pass over the bucket it falls in.
CUT_BUCKETS = 4096
#: Keys that may be broadcast as a region of interest.
BROADCAST_KEYS = 4_000_000


def check_side(b: int) -> None:
    """Cubes of interest have a side of 2^n with n over 2."""
    if b < 8 or b & (b - 1):
        raise ValueError(f"a block side must be a power of two of 8 or more, not {b}")


def to_blocks(cells: DataFrame, b: int, nby: int, nbz: int) -> DataFrame:
    """Cells to (key, n, vals): one row per cube with its values in row-major order.  A group is one cube of b^3 cells."""
    keyed = cells.select(block_key(b, nby, nbz).alias("key"), F.struct(offset(b).alias("off"), F.col("v").cast("double").alias("v")).alias("c"))
    packed = keyed.groupBy("key").agg(F.array_sort(F.collect_list("c")).alias("c"))
    return packed.select("key", F.size("c").alias("n"), F.transform("c", lambda c: c["v"]).alias("vals"))


def block_ranges(cells: DataFrame, b: int, nby: int, nbz: int) -> DataFrame:
    """(key, lo, hi, rng, total, n) per cube, combined before the shuffle."""
    v = F.col("v")
    out = cells.groupBy(block_key(b, nby, nbz).alias("key")).agg(F.min(v).alias("lo"), F.max(v).alias("hi"), F.sum(v).alias("total"), F.count("*").alias("n"))
    return out.withColumn("rng", F.col("hi") - F.col("lo"))


def roi_top(ranges: DataFrame, percent: float) -> DataFrame:
    """The ceil(percent of all) cubes of largest range, ties by key: one global rank, for small tables."""
    n = F.count("*").over(Window.partitionBy(F.lit(0)))
    place = F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc("rng"), F.asc("key")))
    return ranges.select("key", "rng", place.alias("place"), n.alias("n_all")).where(F.col("place") <= F.ceil(F.col("n_all") * percent / 100)).select("key", "rng", "place")


def roi_top_scalable(ranges: DataFrame, percent: float, buckets: int = CUT_BUCKETS) -> DataFrame:
    """The same set without a global sort: a histogram finds the bucket of the cut, and only that bucket is ranked."""
    lo, hi, n = ranges.agg(F.min("rng"), F.max("rng"), F.count("*")).first()
    keep = -(-int(n * percent * 1000) // 100_000) if n else 0
    if not keep:
        return ranges.select("key", "rng").limit(0)
    bucket = F.least(F.floor((F.col("rng") - lo) / max(hi - lo, 1) * buckets), F.lit(buckets - 1)).cast("int")
    counts = {r["bucket"]: r["count"] for r in ranges.groupBy(bucket.alias("bucket")).count().collect()}
    above, cut = 0, -1
    for k in sorted(counts, reverse=True):
        if above + counts[k] >= keep:
            cut = k
            break
        above += counts[k]
    sure = ranges.where(bucket > cut).select("key", "rng")
    edge = ranges.where(bucket == cut).orderBy(F.desc("rng"), F.asc("key")).limit(keep - above).select("key", "rng")
    return sure.unionByName(edge)


def level_of_rank_scalable(ranges: DataFrame, shares: list[float], buckets: int = CUT_BUCKETS) -> DataFrame:
    """The same levels as :func:`level_of_rank` without a global sort.

    One histogram tells how many cubes are in the buckets above each; a cube's place is that number plus its rank in its own
    bucket, and only buckets that hold a cut are ranked.  ``ranges`` should be a written table, as it is read three times.
    """
    lo, hi, n = ranges.agg(F.min("rng"), F.max("rng"), F.count("*")).first()
    if not n:
        return ranges.select("key", F.lit(0).alias("level"))
    bucket = F.least(F.floor((F.col("rng") - lo) / max(hi - lo, 1) * buckets), F.lit(buckets - 1)).cast("int")
    placed = ranges.select("key", "rng", bucket.alias("bucket"))
    counts = {r["bucket"]: r["count"] for r in placed.groupBy("bucket").count().collect()}
    upto, cuts = 0.0, []
    for share in shares[:-1]:
        upto += share
        cuts.append(ceil(n * upto / 100))
    above, level, split = 0, {}, {}
    for k in sorted(counts, reverse=True):
        first, last = (sum(place > cut for cut in cuts) for place in (above + 1, above + counts[k]))
        if first == last:
            level[k] = first
        else:
            split[k] = above
        above += counts[k]
    whole = F.lit(None).cast("int")
    for k in range(len(shares)):
        own = [b for b, at in level.items() if at == k]
        if own:
            whole = F.when(F.col("bucket").isin(own), F.lit(k)).otherwise(whole)
    if not split:
        return placed.select("key", whole.alias("level"))
    before = F.coalesce(*(F.when(F.col("bucket") == b, F.lit(at)) for b, at in split.items()))
    place = before + F.row_number().over(Window.partitionBy("bucket").orderBy(F.desc("rng"), F.asc("key")))
    ranked = placed.where(F.col("bucket").isin(list(split))).select("key", place.alias("place"))
    level_at = sum((F.when(F.col("place") > cut, 1).otherwise(0) for cut in cuts), F.lit(0))
    return placed.where(~F.col("bucket").isin(list(split))).select("key", whole.alias("level")).unionByName(ranked.select("key", level_at.cast("int").alias("level")))


def roi_threshold(ranges: DataFrame, least) -> DataFrame:
    """Cubes whose range reaches a fixed threshold."""
    return ranges.where(F.col("rng") >= least).select("key", "rng")


def refine_by_mean(ranges: DataFrame, above) -> DataFrame:
    """Cubes whose mean is above a threshold: the usual criterion of adaptive meshes."""
    return ranges.where(F.col("total") > above * F.col("n")).select("key", "total", "n")


def roi_mask(ranges: DataFrame, mask: DataFrame) -> DataFrame:
    """Cubes that a mask of keys names."""
    return ranges.join(mask.select("key").distinct(), "key", "left_semi").select("key", "rng")


def split_levels(cells: DataFrame, roi: DataFrame, b: int, nby: int, nbz: int, how: str = "mean", exact: bool = False) -> DataFrame:
    """(level, x, y, z, v): cells of the region stay at level 0, the others are coarsened by 2 to level 1."""
    keyed = cells.withColumn("key", block_key(b, nby, nbz))
    keys = roi.select("key")
    fine = keyed.join(keys, "key", "left_semi").select(F.lit(0).alias("level"), "x", "y", "z", "v")
    rest = coarsen(keyed.join(keys, "key", "left_anti"), 2, how, exact).select(F.lit(1).alias("level"), "x", "y", "z", "v")
    return fine.unionByName(rest)


def coarsen(cells: DataFrame, factor: int = 2, how: str = "mean", exact: bool = False) -> DataFrame:
    """Down-sampling by a factor per axis: the mean, the first corner or the largest of the children.

    ``exact`` keeps sum and count of integer fields instead of a mean.
    """
    at = [F.floor(F.col(c) / factor).cast("int").alias(c) for c in "xyz"]
    v = F.col("v")
    if how == "inject":
        corner = (F.col("x") % factor == 0) & (F.col("y") % factor == 0) & (F.col("z") % factor == 0)
        return cells.where(corner).select(*at, "v")
    if how == "max":
        return cells.groupBy(*at).agg(F.max(v).alias("v"))
    if how != "mean":
        raise ValueError(f"unknown down-sampling {how!r}")
    return cells.groupBy(*at).agg(F.sum(v).alias("v"), F.count("*").alias("n")) if exact else cells.groupBy(*at).agg(F.avg(v).alias("v"))


def level_of_rank(ranges: DataFrame, shares: list[float]) -> DataFrame:
    """(key, level) by the share of the ranking each level takes, finest first."""
    place = F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc("rng"), F.asc("key")))
    n = F.count("*").over(Window.partitionBy(F.lit(0)))
    level, upto = F.lit(len(shares) - 1), 0.0
    cuts = []
    for k, share in enumerate(shares[:-1]):
        upto += share
        cuts.append((k, upto))
    for k, cut in reversed(cuts):
        level = F.when(F.col("place") <= F.ceil(F.col("n_all") * cut / 100), F.lit(k)).otherwise(level)
    return ranges.select("key", "rng", place.alias("place"), n.alias("n_all")).select("key", level.cast("int").alias("level"))


def build_levels(cells: DataFrame, ranked: DataFrame, b: int, nby: int, nbz: int) -> DataFrame:
    """Cells at the level of their cube: level k is coarsened by 2^k."""
    keyed = cells.withColumn("key", block_key(b, nby, nbz)).join(ranked, "key")
    step = F.call_function("shiftleft", F.lit(1), F.col("level"))
    at = [F.floor(F.col(c) / step).cast("int").alias(c) for c in "xyz"]
    return keyed.groupBy("level", *at).agg(F.sum("v").alias("v"), F.count("*").alias("n"))


def flatten_nearest(levels: DataFrame) -> DataFrame:
    """A uniform grid again: every value is repeated over the fine cells it covers."""
    step = F.call_function("shiftleft", F.lit(1), F.col("level"))
    child = lambda c: F.explode(F.sequence(F.col(c) * step, F.col(c) * step + step - 1)).alias(f"f{c}")
    out = levels
    for c in "xyz":
        out = out.select("*", child(c))
    return out.select("level", F.col("fx").alias("x"), F.col("fy").alias("y"), F.col("fz").alias("z"), "v")


def flatten_trilinear(coarse: DataFrame, edge: int) -> DataFrame:
    """Cells at twice the resolution, each axis weighing 3 to 1 between its own and the next coarse cell; values are 64 times the mean."""
    out = coarse.select("x", "y", "z", "v")
    for axis in "xyz":
        w = Window.partitionBy(*[c for c in "xyz" if c != axis]).orderBy(axis)
        before, after = F.coalesce(F.lag("v").over(w), "v"), F.coalesce(F.lead("v").over(w), "v")
        halves = F.array(F.struct(F.lit(0).alias("h"), (3 * F.col("v") + before).alias("w")), F.struct(F.lit(1).alias("h"), (3 * F.col("v") + after).alias("w")))
        wide = out.select("x", "y", "z", halves.alias("halves")).select("x", "y", "z", F.inline("halves"))
        at = {c: (2 * F.col(c) + F.col("h")).cast("int") if c == axis else F.col(c) for c in "xyz"}
        out = wide.select(*(at[c].alias(c) for c in "xyz"), F.col("w").alias("v"))
    return out


def cover(levels: DataFrame) -> DataFrame:
    """How often each fine cell is covered."""
    return flatten_nearest(levels).groupBy("x", "y", "z").agg(F.count("*").alias("times"))


def level_density(levels: DataFrame, points: int) -> DataFrame:
    """Per level: stored cells and the fine cells they stand for, of ``points``."""
    return levels.groupBy("level").agg(F.count("*").alias("stored")).select("level", "stored", (F.col("stored") * F.pow(F.lit(8), F.col("level")).cast("long")).alias("covered"), F.lit(points).cast("long").alias("points"))


def unit_blocks(level_cells: DataFrame, u: int, nby: int, nbz: int) -> DataFrame:
    """Occupied cubes of one level; empty ones have no row."""
    return to_blocks(level_cells, u, nby, nbz)


def pad_overhead(u: Column) -> Column:
    """Share of extra points when the two short axes of u get one layer each."""
    return (u + 1) * (u + 1) / (u * u) - 1
