"""Isosurface crossing under a normal error model taken from a sample."""

from __future__ import annotations

from collections.abc import Iterator
from math import sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Coefficients of the classical five-term rational-exponential fit of erf (fixed values).
ERF_P = 0.3275911
ERF_A = (0.254829592, -0.284496736, 1.421413741, -1.453152027, 1.061405429)
LEAST_SAMPLES = 64


def erf(z: Column) -> Column:
    """erf with an absolute error of at most 1.5e-7, as a column expression."""
    t = 1 / (1 + ERF_P * F.abs(z))
    poly = F.lit(0.0)
    for a in reversed(ERF_A):
        poly = (poly + a) * t
    value = 1 - poly * F.exp(-z * z)
    return F.when(z < 0, -value).otherwise(value)


def erf_np(z: np.ndarray) -> np.ndarray:
    t = 1 / (1 + ERF_P * np.abs(z))
    poly = np.zeros_like(t)
    for a in reversed(ERF_A):
        poly = (poly + a) * t
    return np.sign(z) * (1 - poly * np.exp(-z * z))


def p_above(d: Column, mu: Column, sigma: Column, iso: Column) -> Column:
    """Probability that the true value is above ``iso``; a step where sigma is 0."""
    z = (d + mu - iso) / (sigma * sqrt(2.0))
    return F.when(sigma > 0, 0.5 * (1 + erf(z))).otherwise(F.when(d + mu > iso, 1.0).otherwise(0.0))


def p_above_truncated(d: Column, mu: Column, sigma: Column, iso: Column, eb: float) -> Column:
    """The same with the error cut off at the bound, which the true value cannot pass."""
    phi = lambda x: 0.5 * (1 + erf(x / (sigma * sqrt(2.0))))
    low, high = phi(F.lit(-eb) - mu), phi(F.lit(eb) - mu)
    inside = (high - phi(F.least(F.greatest(iso - d, F.lit(-eb)), F.lit(eb)) - mu)) / (high - low)
    return F.when((sigma > 0) & (high > low), F.least(F.lit(1.0), F.greatest(F.lit(0.0), inside))).otherwise(F.when(d + mu > iso, 1.0).otherwise(0.0))


def error_model(pairs: DataFrame, iso: float | None = None, tau: float | None = None, by: list[str] | None = None) -> DataFrame:
    """(n, mu, sigma): mean and spread of orig - deco, near the isovalue if one is given."""
    if iso is not None and tau is not None:
        pairs = pairs.where(F.abs(F.col("deco") - iso) <= tau)
    e = F.col("orig") - F.col("deco")
    return pairs.groupBy(*(by or [])).agg(F.count("*").alias("n"), F.avg(e).alias("mu"), F.coalesce(F.stddev_samp(e), F.lit(0.0)).alias("sigma"))


def near_model(pairs: DataFrame, iso: float, eb: float, least: int = LEAST_SAMPLES) -> tuple[float, float, float, int]:
    """(mu, sigma, tau, n): the neighbourhood of the isovalue is doubled from two bounds until it has enough samples.

    All doublings are sums of one pass, so there is one small result and no loop of jobs.
    """
    e, far = F.col("orig") - F.col("deco"), F.abs(F.col("deco") - iso)
    taus = [2 * eb * 2**k for k in range(8)]
    aggs = []
    for k, tau in [*enumerate(taus), (len(taus), float("inf"))]:
        near = F.when(far <= tau, e)
        aggs += [F.count(near).alias(f"n{k}"), F.avg(near).alias(f"mu{k}"), F.stddev_samp(near).alias(f"sd{k}")]
    row = pairs.agg(*aggs).first()
    for k, tau in [*enumerate(taus), (len(taus), float("inf"))]:
        if row[f"n{k}"] >= least or k == len(taus):
            return row[f"mu{k}"] or 0.0, row[f"sd{k}"] or 0.0, tau, row[f"n{k}"]
    raise AssertionError


def error_shape(pairs: DataFrame, eb: float, bins: int = 20) -> DataFrame:
    """Histogram of the error over [-eb, eb] in ``bins`` buckets."""
    e = F.col("orig") - F.col("deco")
    bucket = F.least(F.lit(bins - 1), F.greatest(F.lit(0), F.floor((e + eb) / (2 * eb) * bins).cast("int")))
    return pairs.groupBy(bucket.alias("bucket")).agg(F.count("*").alias("n"))


def corners(cells: DataFrame) -> DataFrame:
    """``c``: the eight values of each grid cell whose corners all exist; three windows over lines."""
    out = cells.select("x", "y", "z", F.array(F.col("v").cast("double")).alias("c"))
    for axis in "xyz":
        w = Window.partitionBy(*[a for a in "xyz" if a != axis]).orderBy(axis)
        after = F.when(F.lead(axis).over(w) == F.col(axis) + 1, F.lead("c").over(w))
        out = out.select("x", "y", "z", F.concat("c", after).alias("c"))
    return out.where("c is not null")


def det_cells(cells: DataFrame, iso: float) -> DataFrame:
    """(x, y, z, above, crossed): how many corners are above, and whether not all are on one side."""
    above = F.size(F.filter("c", lambda v: v > iso))
    return corners(cells).select("x", "y", "z", above.alias("above"), ((above > 0) & (above < 8)).alias("crossed"))


def prob_cells(cells: DataFrame, mu: float, sigma: float, iso: float, eb: float | None = None) -> DataFrame:
    """(x, y, z, p): crossing probability with independent corners; with ``eb`` the errors are cut off at the bound."""
    one = lambda v: p_above(v, F.lit(mu), F.lit(sigma), F.lit(iso)) if eb is None else p_above_truncated(v, F.lit(mu), F.lit(sigma), F.lit(iso), eb)
    # the vertex probability is computed once per vertex, then spread to the cells around it
    vertex = cells.select("x", "y", "z", one(F.col("v").cast("double")).alias("v"))
    every = F.aggregate("c", F.lit(1.0), lambda a, p: a * p)
    none = F.aggregate("c", F.lit(1.0), lambda a, p: a * (1 - p))
    return corners(vertex).select("x", "y", "z", F.greatest(F.lit(0.0), 1 - every - none).alias("p"))


def prune_blocks(blocks: DataFrame, iso: float, margin: float) -> DataFrame:
    """Blocks whose range comes within the margin of the isovalue; the filter reaches stored min and max columns."""
    return blocks.where((F.col("vmin") <= iso + margin) & (F.col("vmax") >= iso - margin))


def recovery(orig: DataFrame, deco: DataFrame, prob: DataFrame, iso: float, theta: float = 0.05) -> DataFrame:
    """Cells crossed in the original, lost after decompression, and found again by p >= theta; and false ones."""
    o = det_cells(orig, iso).select("x", "y", "z", F.col("crossed").alias("true"))
    d = det_cells(deco, iso).select("x", "y", "z", F.col("crossed").alias("seen"))
    both = o.join(d, ["x", "y", "z"]).join(prob, ["x", "y", "z"])
    hit = F.col("p") >= theta
    return both.agg(
        F.count_if("true").alias("crossed"), F.count_if(F.col("true") & ~F.col("seen")).alias("lost"), F.count_if(F.col("true") & ~F.col("seen") & hit).alias("recovered"),
        F.count_if(F.col("true") & F.col("seen")).alias("kept"), F.count_if(~F.col("true") & hit).alias("false_hits"), F.count("*").alias("cells"),
    )


def edges(cells: DataFrame, mu: float, sigma: float, iso: float) -> DataFrame:
    """(x, y, z, axis, p): probability that the edge from a vertex along an axis is crossed."""
    vertex = cells.select("x", "y", "z", p_above(F.col("v").cast("double"), F.lit(mu), F.lit(sigma), F.lit(iso)).alias("q"))
    parts = []
    for axis in "xyz":
        w = Window.partitionBy(*[a for a in "xyz" if a != axis]).orderBy(axis)
        after = F.when(F.lead(axis).over(w) == F.col(axis) + 1, F.lead("q").over(w))
        parts.append(vertex.select("x", "y", "z", F.lit(axis).alias("axis"), (F.col("q") * (1 - after) + after * (1 - F.col("q"))).alias("p")).where("p is not null"))
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def _uniform(seed: int, x: np.ndarray, y: np.ndarray, z: np.ndarray, n: int) -> np.ndarray:
    """(cells, n) numbers in (0, 1), a function of seed, place and number alone: results do not depend on how cells are dealt out."""
    k = (np.uint64(seed) << np.uint64(60)) ^ (x << np.uint64(40)) ^ (y << np.uint64(20)) ^ z
    k = k[:, None] * np.uint64(0x9E3779B97F4A7C15) + (np.arange(n, dtype=np.uint64) + np.uint64(1)) * np.uint64(0xD1B54A32D192ED03)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        k = (k ^ (k >> np.uint64(shift))) * np.uint64(factor)
    return ((k ^ (k >> np.uint64(31))) >> np.uint64(11)).astype(np.float64) * 2.0**-53 + 2.0**-54


def _normal(seed: int, x: np.ndarray, y: np.ndarray, z: np.ndarray, draws: int) -> np.ndarray:
    """(cells, draws, 8) standard normal numbers, in pairs from two uniform ones each."""
    u = _uniform(seed, x, y, z, 8 * draws).reshape(len(x), draws, 2, 4)
    r, t = np.sqrt(-2 * np.log(u[:, :, 0])), 2 * np.pi * u[:, :, 1]
    return np.concatenate((r * np.cos(t), r * np.sin(t)), axis=2)


#: Cells that are drawn together.
DRAWN = 512


def mc_cells(cells: DataFrame, mu: float, sigma: float, iso: float, draws: int = 256, seed: int = 11, cholesky: np.ndarray | None = None, margin: float = 4.0) -> DataFrame:
    """Crossing probability by simulation, corners independent or with a given correlation; only cells near the isovalue are drawn."""
    factor = np.eye(8) * sigma if cholesky is None else cholesky
    near = corners(cells).where((F.array_min("c") <= iso - mu + margin * sigma) & (F.array_max("c") >= iso - mu - margin * sigma))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for a in range(0, len(whole), DRAWN):
                batch = whole.slice(a, DRAWN)
                x, y, z = (batch.column(batch.schema.get_field_index(c)).to_numpy().astype(np.uint64) for c in "xyz")
                c = batch.column(batch.schema.get_field_index("c")).flatten().to_numpy(zero_copy_only=False).reshape(-1, 1, 8)
                n = (c + mu + _normal(seed, x, y, z, draws) @ factor.T > iso).sum(axis=2)
                p = ((n > 0) & (n < 8)).mean(axis=1)
                yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index(k)) for k in "xyz"] + [pa.array(p)], names=["x", "y", "z", "p"])

    return near.mapInArrow(work, "x int, y int, z int, p double")


def corner_covariance(pairs: DataFrame) -> np.ndarray:
    """Lower Cholesky factor of the 8 x 8 covariance of the errors at the corners of sample cells, 36 numbers to the driver."""
    e = corners(pairs.select("x", "y", "z", (F.col("orig") - F.col("deco")).alias("v")))
    at = lambda i: F.get("c", F.lit(i))
    row = e.agg(*(F.covar_samp(at(i), at(j)).alias(f"c{i}{j}") for i in range(8) for j in range(i + 1))).first()
    m = np.array([[row[f"c{max(i, j)}{min(i, j)}"] or 0.0 for j in range(8)] for i in range(8)])
    return np.linalg.cholesky(m + np.eye(8) * (1e-12 + 1e-9 * np.trace(m)))


def case_entropy(cells: DataFrame, mu: float, sigma: float, iso: float) -> DataFrame:
    """(x, y, z, p, entropy): Shannon entropy of the 256 sign patterns of a cell, as a sum over independent corners."""
    vertex = cells.select("x", "y", "z", p_above(F.col("v").cast("double"), F.lit(mu), F.lit(sigma), F.lit(iso)).alias("v"))
    bit = lambda p: F.when((p > 0) & (p < 1), -(p * F.log2(p) + (1 - p) * F.log2(1 - p))).otherwise(0.0)
    every, none = (F.aggregate("c", F.lit(1.0), f) for f in (lambda a, p: a * p, lambda a, p: a * (1 - p)))
    return corners(vertex).select("x", "y", "z", (1 - every - none).alias("p"), F.aggregate("c", F.lit(0.0), lambda a, p: a + bit(p)).alias("entropy"))


def components(crossed: DataFrame, g: int) -> DataFrame:
    """(node, component) of face-connected crossed cells; nodes are row-major cell numbers."""
    from .graph import connected

    node = (F.col("x") * g * g + F.col("y") * g + F.col("z")).cast("long")
    nodes = crossed.select(node.alias("node"), "x", "y", "z")
    pairs = []
    for axis, step in (("x", g * g), ("y", g), ("z", 1)):
        pairs.append(nodes.where(F.col(axis) < g - 1).select(F.col("node").alias("a"), (F.col("node") + step).alias("b")))
    links = pairs[0].unionByName(pairs[1]).unionByName(pairs[2]).join(nodes.select(F.col("node").alias("b")), "b", "left_semi")
    return connected(nodes.select("node"), links)


def surface_parts(orig: DataFrame, deco: DataFrame, likely: DataFrame, g: int) -> DataFrame:
    """(component, cells, kept, pieces, found, state) of each connected part of the original surface.

    ``orig``, ``deco``: crossed cells; ``likely``: cells with a probability worth showing.  A part is vanished if none of its cells is left,
    cracked if what is left is in several parts, whole otherwise; ``found`` counts lost cells that are likely.
    """
    node = (F.col("x") * g * g + F.col("y") * g + F.col("z")).cast("long").alias("node")
    after = components(deco, g).select("node", F.col("component").alias("piece"))
    rows = components(orig, g).join(after, "node", "left").join(likely.select(node, F.lit(True).alias("likely")), "node", "left")
    out = rows.groupBy("component").agg(F.count("*").alias("cells"), F.count("piece").alias("kept"), F.count_distinct("piece").alias("pieces"), F.count_if(F.col("piece").isNull() & F.col("likely")).alias("found"))
    state = F.when(F.col("kept") == 0, "vanished").when(F.col("pieces") > 1, "cracked").otherwise("whole")
    return out.withColumn("state", state)
