"""Rate, distortion, spectrum and cost measures."""

from __future__ import annotations

import time
from contextlib import contextmanager
from math import pi

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def distortion(pairs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """n, range, mse, psnr, largest error and L2 norm in one pass; psnr is null for no error or no range."""
    e = F.col("orig") - F.col("deco")
    out = pairs.groupBy(*by).agg(F.count("*").alias("n"), (F.max("orig") - F.min("orig")).alias("rng"), F.sum(e * e).alias("sse"), F.max(F.abs(e)).alias("max_err"))
    mse = F.col("sse") / F.col("n")
    psnr = F.when((mse > 0) & (F.col("rng") > 0), 20 * F.log10("rng") - 10 * F.log10(mse))
    return out.select(*by, "n", "rng", mse.alias("mse"), psnr.alias("psnr"), "max_err", F.sqrt("sse").alias("l2"))


def violations(pairs: DataFrame, eb: float) -> DataFrame:
    """How many points are further off than the bound."""
    return pairs.agg(F.count_if(F.abs(F.col("orig") - F.col("deco")) > eb * (1 + 1e-12)).alias("violations"), F.count("*").alias("n"))


def ssim_blocks(pairs: DataFrame, side: int = 8, rng: float | None = None) -> DataFrame:
    """Mean structural similarity over non-overlapping full cubes of a side; windows with no contrast and no difference count 1."""
    if rng is None:
        lo, hi = pairs.agg(F.min("orig"), F.max("orig")).first()
        rng = float((hi or 0) - (lo or 0))
    c1, c2 = (0.01 * rng) ** 2, (0.03 * rng) ** 2
    o, d = F.col("orig").cast("double"), F.col("deco").cast("double")
    at = [F.floor(F.col(c) / side).alias(f"w{c}") for c in "xyz"]
    w = pairs.groupBy(*at).agg(F.avg(o).alias("mo"), F.avg(d).alias("md"), F.var_pop(o).alias("vo"), F.var_pop(d).alias("vd"), F.covar_pop(o, d).alias("cov"), F.count("*").alias("n")).where(F.col("n") == side**3)
    top = (2 * F.col("mo") * F.col("md") + c1) * (2 * F.col("cov") + c2)
    low = (F.col("mo") ** 2 + F.col("md") ** 2 + c1) * (F.col("vo") + F.col("vd") + c2)
    return w.agg(F.avg(F.when(low == 0, 1.0).otherwise(top / low)).alias("ssim"), F.count("*").alias("windows"))


def ssim_sliding(pairs: DataFrame, side: int = 7, rng: float | None = None) -> DataFrame:
    """The same over all windows, by running sums along one axis after the other."""
    if rng is None:
        lo, hi = pairs.agg(F.min("orig"), F.max("orig")).first()
        rng = float((hi or 0) - (lo or 0))
    c1, c2 = (0.01 * rng) ** 2, (0.03 * rng) ** 2
    o, d = F.col("orig").cast("double"), F.col("deco").cast("double")
    names = ("o", "d", "oo", "dd", "od", "n")
    t = pairs.select("x", "y", "z", o.alias("o"), d.alias("d"), (o * o).alias("oo"), (d * d).alias("dd"), (o * d).alias("od"), F.lit(1).alias("n"))
    for axis in "xyz":
        w = Window.partitionBy(*[c for c in "xyz" if c != axis]).orderBy(axis).rowsBetween(0, side - 1)
        t = t.select("x", "y", "z", *(F.sum(c).over(w).alias(c) for c in names))
    t = t.where(F.col("n") == side**3)
    m = {c: F.col(c) / side**3 for c in names}
    top = (2 * m["o"] * m["d"] + c1) * (2 * (m["od"] - m["o"] * m["d"]) + c2)
    low = (m["o"] ** 2 + m["d"] ** 2 + c1) * (m["oo"] - m["o"] ** 2 + m["dd"] - m["d"] ** 2 + c2)
    return t.agg(F.avg(F.when(low == 0, 1.0).otherwise(top / low)).alias("ssim"), F.count("*").alias("windows"))


def power_spectrum(cells: DataFrame, edge: int, kmax: int = 10, contrast: bool = True) -> DataFrame:
    """(k, p) of shells 1 to kmax - 1 of a cubic field, by three sums that each contract one axis.

    A contraction multiplies by the cosines and sines of the few wanted modes, so rows shrink from N to N^(2/3) times the modes and
    no transform is ever transposed.  The table of modes has at most 2 kmax rows.
    """
    spark = cells.sparkSession
    mean = cells.agg(F.avg("v")).first()[0] or 1.0
    v = F.col("v") / mean - 1 if contrast and mean else F.col("v").cast("double")
    out = cells.select("x", "y", "z", v.alias("re"), F.lit(0.0).alias("im"))
    kept: list[str] = []
    for axis in "xyz":
        modes = F.broadcast(spark.range(-(kmax - 1), kmax).select(F.col("id").alias(f"k{axis}")))
        angle = -2 * pi / edge * F.col(f"k{axis}") * F.col(axis)
        c, s = F.cos(angle), F.sin(angle)
        rest = [a for a in "xyz" if a > axis]
        kept.append(f"k{axis}")
        out = out.crossJoin(modes).groupBy(*rest, *kept).agg(F.sum(F.col("re") * c - F.col("im") * s).alias("re"), F.sum(F.col("re") * s + F.col("im") * c).alias("im"))
    k = F.floor(F.sqrt(F.col("kx") ** 2 + F.col("ky") ** 2 + F.col("kz") ** 2) + 0.5).cast("int")
    return out.groupBy(k.alias("k")).agg(F.avg(F.col("re") ** 2 + F.col("im") ** 2).alias("p")).where((F.col("k") >= 1) & (F.col("k") < kmax))


def _modes(n: int, edge: int, kmax: int) -> np.ndarray:
    """(n, 2 kmax - 1) of e^(-2 pi i k c / edge) summed over the fine cells c of each of n equal cells of an axis."""
    fine = np.exp(-2j * pi / edge * np.outer(np.arange(edge), np.arange(1 - kmax, kmax)))
    return fine.reshape(n, edge // n, -1).sum(axis=1)


def power_spectrum_blocks(blocks: DataFrame, edge: int, nby: int, nbz: int, kmax: int = 10) -> DataFrame:
    """(k, p) of shells 1 to kmax - 1 of a field given as blocks (level, key, vals), coarse levels included, as contrast to its mean.

    Each task contracts its blocks with the few wanted modes and sends one array of (2 kmax - 1)^3 sums, so no cell leaves its
    block.  A coarse cell counts for all the fine cells that it covers.
    """
    shape = 2 * kmax - 1

    def work(batches):
        total, mean = np.zeros((shape,) * 3, dtype=np.complex128), 0.0
        for batch in batches:
            level, key, vals = (batch.column(batch.schema.get_field_index(c)) for c in ("level", "key", "vals"))
            for at, k, v in zip(level.to_pylist(), key.to_pylist(), vals, strict=True):
                v = v.values.to_numpy()
                side = round(len(v) ** (1 / 3))
                modes = _modes(edge >> at, edge, kmax)
                out = v.reshape(side, side, side)
                for c in (k // (nby * nbz), k // nbz % nby, k % nbz):
                    out = np.tensordot(out, modes[c * side : (c + 1) * side], axes=(0, 0))
                total += out
                mean += float(v.sum()) * 8.0**at
        yield pa.RecordBatch.from_arrays([pa.array([total.real.ravel()]), pa.array([total.imag.ravel()]), pa.array([mean])], names=["re", "im", "mass"])

    sums = blocks.select("level", "key", "vals").mapInArrow(work, "re array<double>, im array<double>, mass double")
    row = F.posexplode(F.arrays_zip("re", "im")).alias("at", "m")
    each = sums.select("mass", row).groupBy("at").agg(F.sum("m.re").alias("re"), F.sum("m.im").alias("im"), F.sum("mass").alias("mass"))
    axis = lambda step: F.floor(F.col("at") / step) % shape - (kmax - 1)
    k = F.floor(F.sqrt(axis(shape * shape) ** 2 + axis(shape) ** 2 + axis(1) ** 2) + 0.5).cast("int")
    scale = F.when(F.col("mass") == 0, 1.0).otherwise(F.col("mass") / float(edge) ** 3)
    return each.select(k.alias("k"), ((F.col("re") ** 2 + F.col("im") ** 2) / scale**2).alias("p")).groupBy("k").agg(F.avg("p").alias("p")).where((F.col("k") >= 1) & (F.col("k") < kmax))


def spectrum_error(p: DataFrame, q: DataFrame) -> DataFrame:
    """Mean and largest relative error of a spectrum, and whether it stays within one percent."""
    e = F.abs(F.col("q") / F.col("p") - 1)
    both = p.join(q.withColumnRenamed("p", "q"), "k").where("p > 0")
    return both.agg(F.avg(e).alias("mean_err"), F.max(e).alias("max_err")).withColumn("passes", F.col("max_err") <= 0.01)


def at_cr(points: DataFrame, crs: DataFrame, values: tuple[str, ...] = ("psnr", "ssim")) -> DataFrame:
    """Measures of each variant at given ratios, by the rule of :func:`psnr_at_cr`."""
    w = Window.partitionBy("variant").orderBy("cr")
    ends = [F.struct("cr", *values).alias("low"), F.lead(F.struct("cr", *values)).over(w).alias("high")]
    seg = points.select("variant", *ends).where("high.cr > low.cr")
    hit = seg.join(F.broadcast(crs), (F.col("at") >= F.col("low.cr")) & (F.col("at") <= F.col("high.cr")))
    t = (F.log("at") - F.log("low.cr")) / (F.log("high.cr") - F.log("low.cr"))
    return hit.groupBy("variant", "at").agg(*(F.max(F.col(f"low.{v}") + t * (F.col(f"high.{v}") - F.col(f"low.{v}"))).alias(v) for v in values))


def psnr_at_cr(points: DataFrame, crs: DataFrame) -> DataFrame:
    """PSNR of each variant at given ratios, linear in the logarithm of the ratio between the nearest measured points; null outside."""
    w = Window.partitionBy("variant").orderBy("cr")
    seg = points.select("variant", F.col("cr").alias("c0"), F.col("psnr").alias("p0"), F.lead("cr").over(w).alias("c1"), F.lead("psnr").over(w).alias("p1")).where("c1 > c0")
    t = (F.log("at") - F.log("c0")) / (F.log("c1") - F.log("c0"))
    hit = seg.join(F.broadcast(crs), (F.col("at") >= F.col("c0")) & (F.col("at") <= F.col("c1")))
    return hit.groupBy("variant", "at").agg(F.max(F.col("p0") + t * (F.col("p1") - F.col("p0"))).alias("psnr"))


def cr_at_psnr(points: DataFrame, psnrs: DataFrame) -> DataFrame:
    """Ratio of each variant at given PSNR, by the same rule."""
    w = Window.partitionBy("variant").orderBy("psnr")
    seg = points.select("variant", F.col("psnr").alias("p0"), F.col("cr").alias("c0"), F.lead("psnr").over(w).alias("p1"), F.lead("cr").over(w).alias("c1")).where("p1 > p0")
    t = (F.col("at") - F.col("p0")) / (F.col("p1") - F.col("p0"))
    hit = seg.join(F.broadcast(psnrs), (F.col("at") >= F.col("p0")) & (F.col("at") <= F.col("p1")))
    return hit.groupBy("variant", "at").agg(F.max(F.exp(F.log("c0") + t * (F.log("c1") - F.log("c0")))).alias("cr"))


def gain_at_psnr(points: DataFrame, ours: str, base: str, psnrs: DataFrame) -> DataFrame:
    at = cr_at_psnr(points, psnrs)
    left, right = at.where(F.col("variant") == ours), at.where(F.col("variant") == base)
    return left.select("at", F.col("cr").alias("ours")).join(right.select("at", F.col("cr").alias("base")), "at").withColumn("gain", F.col("ours") / F.col("base"))


def blockiness(cells: DataFrame, b: int, axis: str = "x") -> DataFrame:
    """Mean absolute step across block faces over the mean step inside blocks."""
    w = Window.partitionBy(*[c for c in "xyz" if c != axis]).orderBy(axis)
    step = F.abs(F.lead("v").over(w) - F.col("v"))
    rows = cells.select((F.col(axis) % b == b - 1).alias("face"), step.alias("step")).where("step is not null")
    return rows.agg(F.sum(F.when(F.col("face"), F.col("step"))).alias("across"), F.count_if("face").alias("n_across"), F.sum(F.when(~F.col("face"), F.col("step"))).alias("inside"), F.count_if(~F.col("face")).alias("n_inside"))


def roi_capture(cells: DataFrame, roi: DataFrame, key: Column, least) -> DataFrame:
    """Cells above a threshold and total mass, overall and inside the region."""
    inside = F.col("inside").isNotNull()
    rows = cells.withColumn("key", key).join(roi.select("key", F.lit(1).alias("inside")), "key", "left")
    high = F.col("v") >= least
    return rows.agg(F.count_if(high).alias("high"), F.count_if(high & inside).alias("high_inside"), F.sum("v").alias("mass"), F.sum(F.when(inside, F.col("v")).otherwise(0)).alias("mass_inside"))


def size_plan(points: int, fields: int, snapshots: int, runs: int, width: int = 8) -> dict[str, int]:
    """Bytes per field, snapshot and campaign."""
    per_field = points * width
    return {"field_bytes": per_field, "snapshot_bytes": per_field * fields, "campaign_bytes": per_field * fields * snapshots * runs}


def reduction_pct(ours: float, base: float) -> float:
    return 100 * (1 - ours / base)


class StageTimer:
    """Wall-clock seconds per named stage; each stage has to run an action."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def stage(self, name: str):
        began = time.perf_counter()
        yield
        self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began

    def overhead(self, extra: tuple[str, ...], base: tuple[str, ...]) -> float:
        return sum(self.seconds.get(s, 0.0) for s in extra) / max(1e-9, sum(self.seconds.get(s, 0.0) for s in base))
