"""Compression of block tables: chunks of blocks are encoded, decoded and measured in Arrow stages without a shuffle."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict
from itertools import product

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import repair as rp
from . import schema
from .arrange import BLOCKS_PER_SLAB, dense_ordinal
from .codec.apply import Codec, coordinates, decode_chunk, encode_chunk
from .tables import kept


def chunks(blocks: DataFrame, u: int, per_chunk: int = BLOCKS_PER_SLAB) -> DataFrame:
    """(level, chunk, keys, vals): runs of blocks in key order, the unit of coding.

    ``blocks``: (level, key, vals).  A chunk holds at most ``per_chunk`` blocks of u^3 values, so a group is bounded.  Each
    block is sorted by its place in the group and flattened.
    """
    placed = dense_ordinal(blocks.select("level", "key", "vals"), ["level"])
    packed = placed.groupBy("level", F.floor(F.col("ordinal") / per_chunk).alias("chunk")).agg(F.array_sort(F.collect_list(F.struct("key", "vals"))).alias("b"))
    return packed.select("level", "chunk", F.transform("b", lambda x: x["key"]).alias("keys"), F.flatten(F.transform("b", lambda x: x["vals"])).alias("vals"))


def _rows(batch: pa.RecordBatch, u: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    level, chunk, keys, vals = (batch.column(batch.schema.get_field_index(c)) for c in ("level", "chunk", "keys", "vals"))
    for i in range(len(batch)):
        k = keys[i].values.to_numpy()
        v = vals[i].values.to_numpy(zero_copy_only=False).astype(np.float64)
        yield level[i].as_py(), chunk[i].as_py(), k, v.reshape(len(k), -1, *[round((len(v) / len(k)) ** (1 / 3))] * 2) if len(k) else v.reshape(0, u, u, u)


def settings(codec: Codec, nby: int, nbz: int) -> str:
    """What decoding needs besides a packet's body: the codec, its bound, and the grid of blocks."""
    return json.dumps({**asdict(codec), "nby": nby, "nbz": nbz}, sort_keys=True)


def read_settings(text: str) -> tuple[Codec, int, int]:
    found = json.loads(text)
    nby, nbz = found.pop("nby"), found.pop("nbz")
    return Codec(**found), nby, nbz


def encode(chunked: DataFrame, codec: Codec, u: int, nby: int, nbz: int, intensities: dict[int, tuple[float, ...]] | None = None) -> DataFrame:
    """PACKET rows; ``body``, ``settings`` and ``intensity`` hold all that decoding and repair need.

    ``intensities``: by level, the repair's strength per axis (:func:`fit`); a codec with a fixed repair needs none.
    """
    header = settings(codec, nby, nbz)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for level, chunk, keys, vals in _rows(batch, u):
                raw, _ = encode_chunk(keys, vals, codec, nby, nbz)
                a = _strength(codec, (intensities or {}).get(level))
                out.append((level, chunk, codec.name, keys, raw, vals.nbytes, len(raw) + keys.nbytes + 8 * len(a or ()), float(np.nanmin(vals)), float(np.nanmax(vals)), header, a))
            kinds = [pa.int32(), pa.int64(), pa.string(), pa.list_(pa.int64()), pa.binary(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.string(), pa.list_(pa.float64())]
            names = ["level", "chunk", "codec", "keys", "body", "raw_bytes", "packed_bytes", "vmin", "vmax", "settings", "intensity"]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate(kinds)], names=names)

    return chunked.mapInArrow(work, schema.PACKET)


def _strength(codec: Codec, fitted: tuple[float, ...] | None) -> tuple[float, ...] | None:
    """Intensity per axis that goes with a packet; empty for the unclamped curve, None without repair."""
    if codec.repair == "none":
        return None
    if codec.repair == "free":
        return ()
    if codec.repair == "fit":
        if fitted is None:
            raise ValueError("a fitted repair needs its intensities before encoding")
        return tuple(fitted)
    return (1.0,) * 3 if codec.repair == "one" else (float(codec.repair),) * 3


def _decoded(row: dict) -> tuple[Codec, int, int, np.ndarray, np.ndarray]:
    codec, nby, nbz = read_settings(row["settings"])
    keys = np.array(row["keys"], dtype=np.int64)
    side = round((row["raw_bytes"] / 8 / max(1, len(keys))) ** (1 / 3))
    return codec, nby, nbz, keys, decode_chunk(row["body"], keys, side, codec, nby, nbz)


_DECODING = ("level", "keys", "body", "raw_bytes", "settings", "intensity")


def decode(packets: DataFrame) -> DataFrame:
    """BLOCK rows as the codec gives them, from packets alone; :func:`decode_repaired` also repairs them."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                _, _, _, keys, vals = _decoded(row)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), row["level"], np.int32)), pa.array(keys), pa.array(list(vals.reshape(len(keys), -1)), pa.list_(pa.float64()))], names=["level", "key", "vals"])

    return packets.select(*_DECODING).mapInArrow(work, schema.BLOCK)


def block_cells(blocks: DataFrame, u: int, nby: int, nbz: int) -> DataFrame:
    """Blocks back to (level, x, y, z, v); those of a coarse level may have a side under ``u``."""
    k = F.col("key")
    flat = blocks.select("level", F.least(F.lit(u), F.round(F.cbrt(F.size("vals"))).cast("int")).alias("u"), F.floor(k / (nby * nbz)).alias("bx"), (F.floor(k / nbz) % nby).alias("by"), (k % nbz).alias("bz"), F.posexplode("vals").alias("o", "v"))
    o, u = F.col("o"), F.col("u")
    at = lambda b, i: (F.col(b) * u + i).cast("int")
    return flat.select("level", at("bx", F.floor(o / (u * u))).alias("x"), at("by", F.floor(o / u) % u).alias("y"), at("bz", o % u).alias("z"), "v")


def pairs(original: DataFrame, decoded: DataFrame) -> DataFrame:
    """(level, x, y, z, orig, deco) of two cell tables."""
    left = original.select("level", "x", "y", "z", F.col("v").cast("double").alias("orig"))
    return left.join(decoded.select("level", "x", "y", "z", F.col("v").alias("deco")), ["level", "x", "y", "z"])


# repair: blocks meet a layer of their neighbours, wherever those were coded

_AROUND = [d for d in product((-1, 0, 1), repeat=3) if any(d)]
#: Blocks and layers of a bin meet in one group, so its size is bounded.
BIN = 512
_PARTS = "variant int, level int, bin long, kind int, keys binary, data binary, side int, cube int, bound double, intensity array<double>"
_NAMES = ("variant", "level", "bin", "kind", "keys", "data", "side", "cube", "bound", "intensity")
_WHOLE, _ORIGINAL = 26, 27


def _cube_side(codec: Codec, side: int) -> int:
    """The side of the cubes whose faces show; blocks smaller than the codec's are coded one by one."""
    return min({"blockpred": codec.block, "blockxform": 4}.get(codec.name, side), side)


def _layer(d: int, own: bool) -> slice:
    """Where a block's own (or its neighbour's padded) layer towards direction d lies."""
    if own:
        return {-1: slice(0, 1), 0: slice(None), 1: slice(-1, None)}[d]
    return {-1: slice(-1, None), 0: slice(1, -1), 1: slice(0, 1)}[d]


def _bins(variant: int, level: int, kind: int, keys: np.ndarray, data: np.ndarray, more: tuple) -> Iterator[tuple]:
    of = keys // BIN
    for k in np.unique(of):
        own = of == k
        yield (variant, level, int(k), kind, keys[own].tobytes(), np.ascontiguousarray(data[own]).tobytes(), *more)


def _parts(variant: int, level: int, keys: np.ndarray, vals: np.ndarray, made: np.ndarray | None, codec: Codec, a: tuple[float, ...], nby: int, nbz: int) -> Iterator[tuple]:
    """Rows of one chunk for the exchange: its decoded blocks (and the originals, to measure by) and the layers its neighbours need."""
    side = vals.shape[1]
    more = (side, _cube_side(codec, side), codec.eb, list(a))
    if made is not None:
        yield from _bins(variant, level, _ORIGINAL, keys, vals, more)
        vals = made
    yield from _bins(variant, level, _WHOLE, keys, vals, more)
    at = coordinates(keys, nby, nbz)
    for kind, d in enumerate(_AROUND):
        to = at + np.array(d)
        inside = ((to >= 0) & (to < np.array([1 << 40, nby, nbz]))).all(axis=1)
        if inside.any():
            layer = vals[inside][(slice(None), *(_layer(c, True) for c in d))]
            yield from _bins(variant, level, kind, (to[inside, 0] * nby + to[inside, 1]) * nbz + to[inside, 2], layer, more)


def _part_rows(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.int32(), pa.int32(), pa.float64(), pa.list_(pa.float64())]
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], names=list(_NAMES))


def _met(table: pa.Table) -> tuple[dict, np.ndarray, np.ndarray, np.ndarray, np.ndarray | None]:
    """(a row of the group, keys, decoded and repaired blocks, originals) of one bin."""
    every = table.to_pylist()
    rows, whole, original = ([r for r in every if low <= r["kind"] <= high] for low, high in ((0, _WHOLE - 1), (_WHOLE, _WHOLE), (_ORIGINAL, _ORIGINAL)))
    if not whole:
        return {}, np.empty(0, np.int64), np.empty((0, 1, 1, 1)), np.empty((0, 1, 1, 1)), None
    first = whole[0]
    s = first["side"]
    read = lambda r: (np.frombuffer(r["keys"], np.int64), np.frombuffer(r["data"], np.float64))

    def gathered(some: list[dict]) -> tuple[np.ndarray, np.ndarray]:
        keys = np.concatenate([read(r)[0] for r in some])
        order = np.argsort(keys, kind="stable")
        return keys[order], np.concatenate([read(r)[1].reshape(-1, s, s, s) for r in some])[order]

    keys, vals = gathered(whole)
    padded = np.full((len(keys), s + 2, s + 2, s + 2), np.nan)
    padded[:, 1:-1, 1:-1, 1:-1] = vals
    for r in rows:
        to, data = read(r)
        at = np.minimum(np.searchsorted(keys, to), len(keys) - 1)
        there = keys[at] == to
        place = tuple(_layer(c, False) for c in _AROUND[r["kind"]])
        padded[(at[there], *place)] = data.reshape(-1, *padded[0][place].shape)[there]
    a = tuple(first["intensity"]) or None
    fixed = rp.repair_padded(padded, first["bound"], a, first["cube"])
    return first, keys, vals, fixed, gathered(original)[1] if original else None


def decode_repaired(packets: DataFrame) -> DataFrame:
    """BLOCK rows, each repaired across all its faces as its packet says.

    One exchange: blocks and the outermost layers of their neighbours, in bins of ``BIN`` keys.  Packets without an
    intensity come back as decoded.
    """

    def offer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                codec, nby, nbz, keys, vals = _decoded(row)
                a = row["intensity"]
                rows = list(_parts(0, row["level"], keys, vals, None, codec, (0.0,) * 3 if a is None else tuple(a), nby, nbz))
                yield _part_rows(rows)

    def settle(table: pa.Table) -> pa.Table:
        first, keys, _, fixed, _ = _met(table)
        return pa.table({"level": pa.array([first["level"]] * len(keys) if first else [], pa.int32()), "key": pa.array(keys, pa.int64()), "vals": pa.array(list(fixed.reshape(len(keys), -1)) if first else [], pa.list_(pa.float64()))})

    met = packets.select(*_DECODING).mapInArrow(offer, _PARTS)
    return met.groupBy("variant", "level", "bin").applyInArrow(settle, schema.BLOCK)


# the fit, before the field is coded


def sample_blocks(chunked: DataFrame, rate: float = rp.SAMPLE_RATE, most: int = rp.SAMPLE_BLOCKS) -> tuple[dict[int, list[np.ndarray]], dict[int, int]]:
    """Per level: whole unit blocks, chosen by a hash of their keys, for about ``rate`` of the points and ``most`` blocks; and how many blocks there are.

    The sample is what reaches the driver; its size is bounded by ``most`` blocks a level.  Where one block is more than the rate
    allows, a corner of it stands in.
    """
    counts = {r["level"]: r["n"] for r in chunked.groupBy("level").agg(F.sum(F.size("keys")).alias("n")).collect()}
    wanted = {level: max(1, min(most, int(rate * n))) for level, n in counts.items()}
    keep = {level: min(1.0, (4 * wanted[level] + 60) / max(1, n)) for level, n in counts.items()}

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for level, _, keys, vals in _rows(batch, 0):
                h = (keys.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
                h ^= h >> np.uint64(32)
                h = (h * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(1)
                own = np.flatnonzero(h / 2.0**63 <= keep[level])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), level, np.int32)), pa.array(h[own].astype(np.int64)), pa.array(list(vals[own].reshape(len(own), -1)), pa.list_(pa.float64()))], names=["level", "h", "vals"])

    place = F.row_number().over(Window.partitionBy("level").orderBy("h"))
    limit = F.coalesce(*(F.when(F.col("level") == k, F.lit(n)) for k, n in wanted.items()), F.lit(0)) if wanted else F.lit(0)
    rows = chunked.mapInArrow(work, "level int, h long, vals array<double>").withColumn("place", place).where(F.col("place") <= limit).collect()
    out: dict[int, list[np.ndarray]] = {level: [] for level in counts}
    for r in rows:
        side = round(len(r["vals"]) ** (1 / 3))
        out[r["level"]].append(np.array(r["vals"]).reshape(side, side, side))
    return out, counts


def sample_pairs(blocks: list[np.ndarray], codec: Codec, n_blocks: int, rate: float = rp.SAMPLE_RATE) -> tuple[list[tuple[np.ndarray, np.ndarray]], int, int]:
    """(original, decompressed) of sampled blocks, coded on their own; the side of the cubes whose faces show; points sampled."""
    out, b = [], 1
    for block in blocks:
        side = block.shape[0]
        b = _cube_side(codec, side)
        if b == side and side >= 4:  # unit blocks are the cubes: halves of the block stand for them
            b = side // 2
        room = rate * n_blocks * side**3
        if len(blocks) == 1 and side**3 > room:
            side = max(2 * b, int(room ** (1 / 3)) // b * b)
            side = min(side, block.shape[0])
        cube = block[:side, :side, :side]
        k = side // b
        if b < _cube_side(codec, block.shape[0]):
            parts = cube[: k * b, : k * b, : k * b].reshape(k, b, k, b, k, b).transpose(0, 2, 4, 1, 3, 5).reshape(-1, b, b, b)
            cube = cube[: k * b, : k * b, : k * b]
            _, made = encode_chunk(np.arange(k**3), parts, codec, k, k)
            made = made.reshape(k, k, k, b, b, b).transpose(0, 3, 1, 4, 2, 5).reshape(cube.shape)
        else:
            _, made = encode_chunk(np.zeros(1, np.int64), cube[None], codec, 1, 1)
            made = made[0]
        out.append((cube, made))
    return out, b, sum(o.size for o, _ in out)


def fit(chunked: DataFrame, variants: list[Codec], method: str = "sgd") -> dict[tuple[int, int], tuple[tuple[float, ...], float]]:
    """{(variant's number, level): (intensity per axis, share of points sampled)} of the variants whose repair is fitted.

    The sample is taken once and coded with every variant; variants are fitted in parallel, one row each.  Intensity 0 is a
    candidate, so a repair that gains nothing on the sample is left out.
    """
    wanted = [k for k, c in enumerate(variants) if c.repair == "fit"]
    if not wanted:
        return {}
    samples, counts = sample_blocks(chunked)
    spark = chunked.sparkSession
    todo = spark.createDataFrame([(k, level) for k in wanted for level in counts], "variant int, level int").repartition(max(1, min(len(wanted) * len(counts), spark.sparkContext.defaultParallelism)))
    shared = spark.sparkContext.broadcast(samples)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for row in batch.to_pylist():
                codec, blocks = variants[row["variant"]], shared.value[row["level"]]
                a, points, size = (0.0,) * 3, 0, max(1, sum(x.size for x in blocks[:1]) * counts[row["level"]])
                if blocks and blocks[0].shape[0] >= 2:
                    pairs, b, points = sample_pairs(blocks, codec, counts[row["level"]])
                    a = rp.fit_intensity(pairs, codec.eb, b, rp.CANDIDATES[codec.name], method, include_zero=True)
                out.append((row["variant"], row["level"], [float(x) for x in a], points / size))
            kinds = [pa.int32(), pa.int32(), pa.list_(pa.float64()), pa.float64()]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate(kinds)], names=["variant", "level", "a", "rate"])

    rows = todo.mapInArrow(work, "variant int, level int, a array<double>, rate double").collect()
    return {(r["variant"], r["level"]): (tuple(r["a"]), r["rate"]) for r in rows}


MEASURES = schema.RDPOINT + ", sse_plain double, sampled double, a string, ssim_sum double, ssim_plain_sum double, windows long"
_MEASURE_NAMES = ["variant", "level", "eb", "n", "packed_bytes", "sse", "vmin", "vmax", "max_err", "sse_plain", "sampled", "a", "ssim_sum", "ssim_plain_sum", "windows"]
_MEASURE_KINDS = [pa.string(), pa.int32(), pa.float64(), pa.int64(), pa.int64(), *[pa.float64()] * 6, pa.string(), pa.float64(), pa.float64(), pa.int64()]


def ssim_sum(x: np.ndarray, y: np.ndarray, span: float | None) -> tuple[float | None, int]:
    """Structural similarity summed over the windows of the blocks, and how many windows; a window is a cube of side 8, 4, 2 or 1 that divides the block."""
    if not span:
        return None, 0
    side = next(w for w in (8, 4, 2, 1) if x.shape[1] % w == 0)
    k = x.shape[1] // side
    cut = lambda a: a.reshape(-1, k, side, k, side, k, side).transpose(0, 1, 3, 5, 2, 4, 6).reshape(-1, side**3)
    a, b = cut(x), cut(y)
    ma, mb = a.mean(axis=1), b.mean(axis=1)
    va, vb, cov = a.var(axis=1), b.var(axis=1), (a * b).mean(axis=1) - ma * mb
    c1, c2 = (0.01 * span) ** 2, (0.03 * span) ** 2
    return float(((2 * ma * mb + c1) * (2 * cov + c2) / ((ma**2 + mb**2 + c1) * (va + vb + c2))).sum()), len(a)


def _measure_rows(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate(_MEASURE_KINDS)], names=_MEASURE_NAMES)


def evaluate(chunked: DataFrame, variants: list[Codec], u: int, nby: int, nbz: int, span: float | None = None) -> DataFrame:
    """Partial measures per variant; similarity needs the field's ``span`` of values.

    Variants without repair take one pass over the chunks and no shuffle.  For the others the strength is fitted first, on a
    sample; then blocks meet their neighbours' layers once, as in :func:`decode_repaired`.
    """
    plain = [c for c in variants if c.repair == "none"]
    fixed = [c for c in variants if c.repair != "none"]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for level, _, keys, vals in _rows(batch, u):
                for c in plain:
                    raw, made = encode_chunk(keys, vals, c, nby, nbz)
                    err = vals - made
                    sse = float((err**2).sum())
                    out.append((c.label or c.name, level, c.eb, vals.size, len(raw) + keys.nbytes, sse, float(vals.min()), float(vals.max()), float(np.abs(err).max()), sse, 0.0, None, *(similar := ssim_sum(vals, made, span))[:1], *similar))
            yield _measure_rows(out)

    parts = [chunked.mapInArrow(work, MEASURES)] if plain else []
    if fixed:
        chunked = kept(chunked)
        fitted = fit(chunked, fixed)

        def offer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for level, _, keys, vals in _rows(batch, u):
                    for k, c in enumerate(fixed):
                        raw, made = encode_chunk(keys, vals, c, nby, nbz)
                        a = _strength(c, fitted.get((k, level), (None, 0.0))[0])
                        rows = list(_parts(k, level, keys, vals, made, c, a, nby, nbz))
                        # a row of kind -1 tells the size of the packet
                        rows.append((k, level, int(keys[0]) // BIN, -1, b"", np.array([len(raw) + keys.nbytes + 8 * len(a)]).tobytes(), 0, 0, c.eb, []))
                        yield _part_rows(rows)

        def settle(table: pa.Table) -> pa.Table:
            told = pc.equal(table.column("kind"), -1)
            size = sum(int(np.frombuffer(d, np.int64)[0]) for d in table.filter(told).column("data").to_pylist())
            k, level = table.column("variant")[0].as_py(), table.column("level")[0].as_py()
            first, _, made, vals, original = _met(table.filter(pc.invert(told)))
            if not first and not size:
                return pa.Table.from_batches([_measure_rows([])])
            c, rate = fixed[k], fitted.get((k, level), (None, 0.0))[1]
            before, after = (original - made, original - vals) if first else (np.zeros(1), np.zeros(1))
            low, high = (float(original.min()), float(original.max())) if first else (None, None)
            (plain_sum, windows), (fixed_sum, _) = (ssim_sum(original, x, span) if first else (None, 0) for x in (made, vals))
            row = (c.label or c.name, level, c.eb, original.size if first else 0, size, float((after**2).sum()), low, high, float(np.abs(after).max()), float((before**2).sum()), rate * (original.size if first else 0), repr(_strength(c, fitted.get((k, level), (None, 0.0))[0]) or None), fixed_sum, plain_sum, windows)
            return pa.Table.from_batches([_measure_rows([row])])

        parts.append(chunked.mapInArrow(offer, _PARTS).groupBy("variant", "level", "bin").applyInArrow(settle, MEASURES))
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def rd_points(partials: DataFrame, by: tuple[str, ...] = ("variant", "level", "eb")) -> DataFrame:
    """Compression ratio, bit rate, PSNR and similarity (before and after repair) and largest error per group; null PSNR for no error or no range."""
    rng, mse = F.max("vmax") - F.min("vmin"), F.sum("sse") / F.sum("n")
    psnr = lambda m: F.when((m > 0) & (rng > 0), 20 * F.log10(rng) - 10 * F.log10(m))
    return partials.groupBy(*by).agg(
        F.sum("n").alias("n"), F.sum("packed_bytes").alias("packed_bytes"), (8 * F.sum("n") / F.sum("packed_bytes")).alias("cr"), (8 * F.sum("packed_bytes") / F.sum("n")).alias("bitrate"),
        psnr(F.sum("sse_plain") / F.sum("n")).alias("psnr_plain"), psnr(mse).alias("psnr"),
        (F.sum("ssim_plain_sum") / F.sum("windows")).alias("ssim_plain"), (F.sum("ssim_sum") / F.sum("windows")).alias("ssim"), F.max("max_err").alias("max_err"), (F.sum("sampled") / F.sum("n")).alias("sample_rate"), F.concat_ws(" ", F.array_sort(F.collect_set(F.concat(F.lit("level "), F.col("level").cast("string"), F.lit(": "), "a")))).alias("a"),
    )


def field_chunks(cells: DataFrame, edge: int, u: int, percent: float | None = None, b: int | None = None, per_chunk: int = BLOCKS_PER_SLAB, shares: list[float] | None = None) -> DataFrame:
    """Chunks of a cubic field: uniform, with a region of interest and a coarse rest, or with a share of the ranking per level.

    Unit blocks have side u, or that of the cube of interest on their level where that is smaller, so every cube is whole blocks and
    no cell is left out.  A block with absent cells is an error.
    """
    from . import hierarchy as h

    if percent is None and shares is None:
        blocks = h.to_blocks(cells, u, edge // u, edge // u).select(F.lit(0).alias("level"), "key", "vals")
        return chunks(blocks, u, per_chunk)
    b = b or u
    nb = edge // b
    ranges = h.block_ranges(cells, b, nb, nb)
    ranked = h.level_of_rank_scalable(kept(ranges, "ranges"), shares or [percent, 100 - percent])
    levels = h.build_levels(cells, ranked, b, nb, nb).withColumn("v", F.col("v") / F.col("n"))
    out = None
    for k in range(len(shares or [0, 0])):
        side = min(u, b >> k)
        if not side:
            raise ValueError(f"cubes of side {b} have no level {k}")
        n = (edge >> k) // side
        whole = F.when(F.col("n") == side**3, F.col("vals")).otherwise(F.raise_error(F.lit(f"a block of level {k} has absent cells")))
        part = h.to_blocks(levels.where(F.col("level") == k), side, n, n).withColumn("vals", whole)
        part = chunks(part.select(F.lit(k).alias("level"), "key", "vals"), side, per_chunk)
        out = part if out is None else out.unionByName(part)
    return out
