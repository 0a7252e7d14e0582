"""Coordinates, keys and neighbourhoods as column expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def block_key(b: int, nby: int, nbz: int, x: str = "x", y: str = "y", z: str = "z") -> Column:
    """Key of the cube of side b that holds a cell."""
    part = lambda c: F.floor(F.col(c) / b)
    return (part(x) * (nby * nbz) + part(y) * nbz + part(z)).cast("long")


def offset(b: int) -> Column:
    """Row-major place of a cell inside its cube."""
    return ((F.col("x") % b) * (b * b) + (F.col("y") % b) * b + F.col("z") % b).cast("int")


def _spread(c: Column) -> Column:
    """The low 10 bits of a number, two zero bits after each."""
    v = c.cast("long").bitwiseAND(0x3FF)
    for shift, mask in ((16, 0x30000FF), (8, 0x300F00F), (4, 0x30C30C3), (2, 0x9249249)):
        v = v.bitwiseOR(F.shiftleft(v, shift)).bitwiseAND(mask)
    return v


def morton(x: Column, y: Column, z: Column) -> Column:
    """Z-order key of coordinates under 1024: bits of x, y, z interleaved, x lowest."""
    return _spread(x).bitwiseOR(F.shiftleft(_spread(y), 1)).bitwiseOR(F.shiftleft(_spread(z), 2))


def trailing_level(x: Column, y: Column, z: Column, bits: int) -> Column:
    """Resolution class of a cell: trailing zero bits that all its coordinates share, at most ``bits``; coarse cells come first in hierarchical order."""
    low = x.bitwiseOR(y).bitwiseOR(z).cast("long")
    level = F.lit(bits)
    for k in range(bits - 1, -1, -1):
        level = F.when(low.bitwiseAND((1 << (k + 1)) - 1) != 0, F.lit(k)).otherwise(level)
    return level


def in_box(box: tuple[int, int, int, int, int, int], halo: int = 0) -> Column:
    """Cells of the box (x0, x1, y0, y1, z0, z1), ends included, widened by a halo."""
    x0, x1, y0, y1, z0, z1 = box
    return F.col("x").between(x0 - halo, x1 + halo) & F.col("y").between(y0 - halo, y1 + halo) & F.col("z").between(z0 - halo, z1 + halo)


def neighbour_keys(blocks: DataFrame, nbx: int, nby: int, nbz: int) -> DataFrame:
    """(key, axis, side, other): the up to six face neighbours of each block inside the domain."""
    k = F.col("key")
    at = {"x": F.floor(k / (nby * nbz)), "y": F.floor(k / nbz) % nby, "z": k % nbz}
    size, step = {"x": nbx, "y": nby, "z": nbz}, {"x": nby * nbz, "y": nbz, "z": 1}
    sides = [F.struct(F.lit(a).alias("axis"), F.lit(s).alias("side"), (k + s * step[a]).alias("other"), ((at[a] + s >= 0) & (at[a] + s < size[a])).alias("inside")) for a in "xyz" for s in (-1, 1)]
    return blocks.select("key", F.inline(F.array(*sides))).where("inside").drop("inside")


def key_in_box(key: Column, box: tuple[int, ...], b: int, nby: int, nbz: int) -> Column:
    """Whether a cube of side b has a cell in the box (x0, x1, y0, y1, z0, z1), ends included."""
    at = (F.floor(key / (nby * nbz)), F.floor(key / nbz) % nby, key % nbz)
    inside = F.lit(True)
    for k, c in enumerate(at):
        inside = inside & (c >= box[2 * k] // b) & (c <= box[2 * k + 1] // b)
    return inside
