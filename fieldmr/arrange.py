"""Orders in which unit blocks become arrays, and what they do to neighbourhoods."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .grid import morton, trailing_level

BLOCKS_PER_SLAB = 512


def dense_ordinal(blocks: DataFrame, by: list[str]) -> DataFrame:
    """``ordinal`` of each block in key order per level.

    Two levels of counting: ranks inside key ranges of bounded size, and a running count over the ranges, so
    no task ranks a whole level.
    """
    span = F.floor(F.col("key") / 65536)
    inside = F.row_number().over(Window.partitionBy(*by, "span").orderBy("key")) - 1
    counts = blocks.withColumn("span", span).groupBy(*by, "span").agg(F.count("*").alias("c"))
    ahead = counts.select(*by, "span", (F.sum("c").over(Window.partitionBy(*by).orderBy("span")) - F.col("c")).alias("ahead"))
    return blocks.withColumn("span", span).withColumn("inside", inside).join(ahead, [*by, "span"]).withColumn("ordinal", F.col("ahead") + F.col("inside")).drop("span", "inside", "ahead")


def arrange_linear(blocks: DataFrame, by: list[str], per_slab: int = BLOCKS_PER_SLAB) -> DataFrame:
    """(slab, position): blocks side by side along one axis."""
    return dense_ordinal(blocks, by).withColumn("slab", F.floor(F.col("ordinal") / per_slab)).withColumn("position", (F.col("ordinal") % per_slab).cast("int"))


def stack_side(total: Column) -> Column:
    """Side of the smallest cube that holds ``total`` blocks, in integers."""
    c = F.floor(F.pow(total.cast("double"), F.lit(1 / 3)))
    c = F.when((c + 1) * (c + 1) * (c + 1) <= total, c + 1).otherwise(c)
    return F.when(c * c * c < total, c + 1).otherwise(c).cast("long")


def arrange_stack(blocks: DataFrame, by: list[str]) -> DataFrame:
    """(px, py, pz): blocks piled in key order into a near-cube."""
    ordered = dense_ordinal(blocks, by)
    totals = blocks.groupBy(*by).agg(F.count("*").alias("total")).withColumn("side", stack_side(F.col("total")))
    m, c = F.col("ordinal"), F.col("side")
    return ordered.join(totals, by).select(*by, "key", F.floor(m / (c * c)).alias("px"), (F.floor(m / c) % c).alias("py"), (m % c).alias("pz"), "side")


def zline_key(levels: DataFrame) -> DataFrame:
    """Z-order key of each cell's finest corner; ties go by level."""
    step = F.call_function("shiftleft", F.lit(1), F.col("level"))
    return levels.withColumn("zkey", morton(*(F.col(c) * step for c in "xyz")))


def hzline_key(cells: DataFrame, bits: int) -> DataFrame:
    """Hierarchical order: coarse cells (many shared trailing zeros) first, z-order inside a class."""
    x, y, z = (F.col(c) for c in "xyz")
    return cells.withColumn("hlevel", trailing_level(x, y, z, bits)).withColumn("zkey", morton(x, y, z))


def roughness(slabs: DataFrame, faces: DataFrame, nbz: int) -> DataFrame:
    """Per arrangement: pairs of blocks that follow each other without being neighbours along z, and the steps between them.

    ``slabs``: (slab, position, key); ``faces``: (key, first, last) sums of a block's first and last layer.
    """
    w = Window.partitionBy("slab").orderBy("position")
    row = slabs.join(faces, "key").select("slab", "key", "first", "last", F.lag("key").over(w).alias("before"), F.lag("last").over(w).alias("before_last"))
    apart = ~((F.col("key") == F.col("before") + 1) & (F.col("key") % nbz != 0))
    pair = row.where("before is not null")
    return pair.agg(F.count("*").alias("faces"), F.count_if(apart).alias("apart"), F.sum(F.when(apart, F.abs(F.col("first") - F.col("before_last"))).otherwise(0)).alias("jump"))


def kd_boxes(occupied: np.ndarray) -> list[tuple[int, int, int, int, int, int]]:
    """Full boxes (x0, x1, y0, y1, z0, z1; ends excluded) that cover the occupied cells of one region.

    A box that is full is a leaf, an empty one vanishes, others are cut across their longest axis where the fill of the two
    sides differs most.
    """
    sums = np.zeros([n + 1 for n in occupied.shape], dtype=np.int64)
    sums[1:, 1:, 1:] = occupied.cumsum(0).cumsum(1).cumsum(2)

    def count(x0, x1, y0, y1, z0, z1):
        return (
            sums[x1, y1, z1] - sums[x0, y1, z1] - sums[x1, y0, z1] - sums[x1, y1, z0] + sums[x0, y0, z1] + sums[x0, y1, z0] + sums[x1, y0, z0] - sums[x0, y0, z0]
        )

    todo, leaves = [(0, occupied.shape[0], 0, occupied.shape[1], 0, occupied.shape[2])], []
    while todo:
        box = todo.pop()
        x0, x1, y0, y1, z0, z1 = box
        size = (x1 - x0) * (y1 - y0) * (z1 - z0)
        n = int(count(*box)) if size else 0
        if not n:
            continue
        if n == size:
            leaves.append(box)
            continue
        axis = int(np.argmax((x1 - x0, y1 - y0, z1 - z0)))
        best, where = -1.0, None
        for cut in range(box[2 * axis] + 1, box[2 * axis + 1]):
            low, high = list(box), list(box)
            low[2 * axis + 1] = high[2 * axis] = cut
            a, b = cut - box[2 * axis], box[2 * axis + 1] - cut
            other = size // (a + b)
            fill = abs(count(*low) / (a * other) - count(*high) / (b * other))
            if fill > best:
                best, where = fill, (tuple(low), tuple(high))
        todo.extend(where)
    return sorted(leaves)


#: Blocks per axis of a region whose boxes are cut in one task.
REGION = 32


def arrange_kd(blocks: DataFrame, by: list[str], nby: int, nbz: int) -> DataFrame:
    """(region, box, key): each region of at most 32^3 blocks is cut into full boxes on its own."""
    import pandas as pd

    k = F.col("key")
    bx, by_, bz = F.floor(k / (nby * nbz)), F.floor(k / nbz) % nby, k % nbz
    region = F.concat_ws(".", *[F.floor(c / REGION).cast("string") for c in (bx, by_, bz)])
    placed = blocks.select(*by, "key", region.alias("region"), (bx % REGION).cast("int").alias("i"), (by_ % REGION).cast("int").alias("j"), (bz % REGION).cast("int").alias("k"))
    kinds = {f.name: f.dataType.simpleString() for f in blocks.schema}

    def cut(p: pd.DataFrame) -> pd.DataFrame:
        full = np.zeros((REGION,) * 3, dtype=bool)
        full[p.i, p.j, p.k] = True
        owner = np.zeros(full.shape, dtype=np.int64)
        shape = {}
        for n, (x0, x1, y0, y1, z0, z1) in enumerate(kd_boxes(full)):
            owner[x0:x1, y0:y1, z0:z1] = n
            shape[n] = f"{x1 - x0}x{y1 - y0}x{z1 - z0}"
        box = owner[p.i, p.j, p.k]
        return pd.DataFrame({**{c: p[c] for c in by}, "key": p.key, "region": p.region, "box": box, "shape": [shape[b] for b in box]})

    return placed.groupBy(*by, "region").applyInPandas(cut, ", ".join([f"{c} {kinds[c]}" for c in by] + ["key long", "region string", "box long", "shape string"]))
