"""The experiment workloads, on fields of the tables.

A workload sweeps codec variants over chunks of a field in one pass and reports rate-distortion points.
"""

from __future__ import annotations

import time
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import engine as en
from .. import fields as fl
from .. import filters as fi
from .. import grid as gr
from .. import hierarchy as h
from .. import metrics as me
from .. import repair as rp
from .. import streaming as st
from .. import uncert as un
from ..codec.apply import Codec, mrinterp, prepared
from ..codec.interp import interp_encode
from ..codec.schedule import schedule_grid
from ..registry import Registry
from ..schema import CHUNK
from ..tables import kept
from .core import _COUNTS, _PLAN, CUBE, LEDGER, core, halo, plan_table
from .sqltext import G, HALO, RANGES

work = Registry()
query = work.query

#: Relative bounds of a sweep.
BOUNDS = (1e-1, 3e-2, 1e-2, 3e-3, 1e-3, 1e-4)

LINEAR = Codec("interp", label="linear")
STACK = Codec("interp", arrange="stack", label="stack")
KD = Codec("interp", arrange="kd", label="kdmerge")
ZLINE = Codec("interp", arrange="zline", label="zline")
PAD = Codec("interp", pad="linear", label="pad")
OURS = mrinterp(label="pad+eb")
OURS_FIXED = mrinterp(label="pad+eb+repair", repair="fit")
HZLINE = Codec("interp", arrange="hzline", label="hzline")
#: The predictor is chosen block by block.
PRED4 = Codec("blockpred", block=4, label="blockpred4")
PRED6 = Codec("blockpred", block=6, label="blockpred6")
XFORM = Codec("blockxform", label="blockxform")


def with_repair(c: Codec) -> Codec:
    return replace(c, repair="fit", label=f"{c.label}+repair")


def cube(spark: SparkSession, sf: str, name: str) -> tuple[DataFrame, int]:
    g = fl.grid_edge(spark, sf)
    if name == "events":  # the sparse cube: as many users, types and hours as the grid has points
        return fl.event_grid(spark, sf, g), g
    return fl.CUBES[name](spark, sf, g), g


def value_range(cells: DataFrame) -> float:
    lo, hi = cells.agg(F.min("v"), F.max("v")).first()
    return float(hi - lo) or 1.0


def sweep(spark: SparkSession, sf: str, name: str, variants: list[Codec], bounds: tuple[float, ...] = BOUNDS, u: int | None = None, by: tuple[str, ...] = ("variant", "level", "eb"), **chunking) -> DataFrame:
    """Rate-distortion points of variants x relative bounds on a field, in one job."""
    cells, g = cube(spark, sf, name)
    u = u or max(8, g // 4)
    span = value_range(cells)
    table = en.field_chunks(cells, g, u, **chunking)
    every = [c.at(b * span) for c in variants for b in bounds]
    points = en.rd_points(en.evaluate(table, every, u, g // u, g // u, span), by)
    return points.withColumn("field", F.lit(name)).withColumn("rel_eb", F.col("eb") / span) if "eb" in by else points.withColumn("field", F.lit(name))


def packed(spark: SparkSession, sf: str, name: str, codec: Codec, rel: float, u: int | None = None, **chunking) -> tuple[DataFrame, DataFrame, Codec, int]:
    """(chunks, packets, codec with its bound, edge) of a field; a fitted repair is fitted before the field is coded."""
    cells, g = cube(spark, sf, name)
    u = u or max(8, g // 4)
    c = codec.at(rel * value_range(cells))
    table = kept(en.field_chunks(cells, g, u, **chunking), "chunks")
    fitted = {level: a for (_, level), (a, _) in en.fit(table, [c]).items()}
    return table, en.encode(table, c, u, g // u, g // u, fitted), c, g


def level_cells(blocks: DataFrame, g: int, u: int | None = None) -> DataFrame:
    u = u or max(8, g // 4)
    return en.block_cells(blocks, u, g // u, g // u)


def table_cells(table: DataFrame, g: int, u: int | None = None) -> DataFrame:
    """The cells (level, x, y, z, v) that chunks hold."""
    side3 = F.size("vals") / F.size("keys")
    blocks = table.select("level", F.posexplode("keys").alias("i", "key"), "vals", side3.cast("int").alias("n")).select("level", "key", F.slice("vals", F.col("i") * F.col("n") + 1, F.col("n")).alias("vals"))
    return level_cells(blocks, g, u)


def reconstruct(spark: SparkSession, sf: str, name: str, codec: Codec, rel: float, u: int | None = None) -> tuple[DataFrame, float, int]:
    """(pairs, bound, edge) of one full encode and decode through packets."""
    table, packets, c, g = packed(spark, sf, name, codec, rel, u)
    back = en.decode(packets) if c.repair == "none" else en.decode_repaired(packets)
    return en.pairs(table_cells(table, g, u), level_cells(back, g, u)), c.eb, g


def bound_at_cr(points: DataFrame, variant: str, cr: float) -> float:
    """The bound (relative) at which a variant reaches a ratio, between measured points; the nearest one outside of them."""
    at = sorted((r["cr"], r["rel_eb"]) for r in points.where(F.col("variant") == variant).select("cr", "rel_eb").collect())
    return float(np.exp(np.interp(np.log(cr), [np.log(c) for c, _ in at], [np.log(e) for _, e in at])))


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Multi-resolution compression of the lattice of parts: ratio, PSNR and largest error."""
    cells = fl.part_lattice(spark, sf)
    span = value_range(cells)
    blocks = h.to_blocks(cells.withColumn("y", F.col("y")).withColumn("z", F.col("z")), 8, 1, 1 << 20).where("n = 512").select(F.lit(0).alias("level"), "key", "vals")
    # a small table may have too few planes for a whole block: edge planes are repeated
    planes = cells.agg(F.max("z")).first()[0]
    fill = -(planes + 1) % 8
    if fill:
        last = cells.where(F.col("z") == planes)
        extra = last.crossJoin(spark.range(fill).select((F.col("id") + planes + 1).cast("int").alias("nz"))).select("x", "y", F.col("nz").alias("z"), "v")
        blocks = h.to_blocks(cells.unionByName(extra), 8, 1, 1 << 20).select(F.lit(0).alias("level"), "key", "vals")
    variants = [c.at(b * span) for c in (LINEAR, PAD, OURS, PRED4, XFORM) for b in (1e-2, 1e-3)]
    return en.rd_points(en.evaluate(en.chunks(blocks, 8), variants, 8, 1, 1 << 20))


@query(f"""WITH {HALO}, {RANGES}, p AS (SELECT unnest([5, 15, 35, 50]) AS pct), high AS (SELECT CAST(max(v) AS BIGINT) // 4 AS least FROM halo),
roi AS (SELECT pct, key, true AS fine FROM ranked, p WHERE place <= ceil(n_all * pct / 100)),
k AS (SELECT pct, x, y, z, v, CAST((x // 8) * (g // 8) * (g // 8) + (y // 8) * (g // 8) + z // 8 AS BIGINT) AS key FROM halo, g, p),
f AS (SELECT pct, x, y, z, v, fine, CASE WHEN fine THEN v::DOUBLE ELSE avg(v) OVER (PARTITION BY pct, x // 2, y // 2, z // 2) END AS d FROM k LEFT JOIN roi USING (pct, key)),
r AS (SELECT pow(0.01 * (max(v) - min(v)), 2) AS c1, pow(0.03 * (max(v) - min(v)), 2) AS c2 FROM halo),
w AS (SELECT pct, avg(v) AS mo, avg(d) AS md, var_pop(v) AS vo, var_pop(d) AS vd, covar_pop(v::DOUBLE, d) AS cv FROM f GROUP BY pct, x // 8, y // 8, z // 8),
s AS (SELECT pct, avg((2 * mo * md + c1) * (2 * cv + c2) / ((mo * mo + md * md + c1) * (vo + vd + c2))) AS ssim FROM w, r GROUP BY pct),
c AS (SELECT pct, count(*) FILTER (v >= least AND fine) / count(*) FILTER (v >= least) AS capture, sum(v) FILTER (fine) / sum(v) AS mass FROM f, high GROUP BY pct)
SELECT pct, CAST(floor(ssim * 1e5 + 0.5) AS BIGINT) AS ssim_e5, CAST(floor(capture * 1e6 + 0.5) AS BIGINT) AS capture_e6, CAST(floor(mass * 1e6 + 0.5) AS BIGINT) AS mass_e6 FROM s JOIN c USING (pct)""")
def wl_w01(s, d):
    """Share of the region of interest against similarity of the whole field and capture of dense cells."""
    cells, g = halo(s, d)
    r = kept(h.block_ranges(cells, 8, g // 8, g // 8), "ranges")
    least = cells.agg(F.max("v")).first()[0] // 4
    scaled = lambda c, k: F.floor(c * 10.0**k + 0.5).cast("long")
    out = None
    for pct in (5, 15, 35, 50):
        roi = h.roi_top_scalable(r, pct)
        flat = h.flatten_nearest(h.split_levels(cells, roi, 8, g // 8, g // 8))
        both = en.pairs(cells.withColumn("level", F.lit(0)), flat.withColumn("level", F.lit(0)))
        row = me.ssim_blocks(both).crossJoin(me.roi_capture(cells, roi, gr.block_key(8, g // 8, g // 8), least)).select(
            F.lit(pct).alias("pct"), scaled(F.col("ssim"), 5).alias("ssim_e5"), scaled(F.col("high_inside") / F.col("high"), 6).alias("capture_e6"), scaled(F.col("mass_inside") / F.col("mass"), 6).alias("mass_e6"),
        )
        out = row if out is None else out.unionByName(row)
    return out


@query()
def wl_w02(s, d):
    """Arrangements against the multi-resolution codec: PSNR and similarity at equal ratios."""
    points = sweep(s, d, "halo", [STACK, KD, OURS], (3e-1, *BOUNDS), by=("variant", "eb"), percent=50)
    return me.at_cr(points, s.createDataFrame([(30.0,), (60.0,), (100.0,), (163.0,)], "at double"))


work.add("wl_w03", core.queries["arrange_roughness"], core.sql["arrange_roughness"])
work.add("wl_w04", lambda s, d: plan_table(s).where("n in (4, 5, 8, 9, 16, 17)").groupBy("n").agg(F.count_if(F.col("kind").isin("interpolated", "extrapolated")).alias("inner_points"), F.count_if(F.col("kind") == "extrapolated").alias("extrapolated")), f"WITH {_PLAN} SELECT n, {_COUNTS} FROM plan WHERE n IN (4, 5, 8, 9, 16, 17) GROUP BY n")


@query()
def wl_w05(s, d):
    """Padding values, each with the bound per level."""
    kinds = [replace(OURS, pad=p, label=p) for p in ("none", "constant", "linear", "quadratic")]
    parts = [sweep(s, d, f, kinds, (1e-1, 3e-2, 1e-2), by=("variant", "eb"), percent=50).select("field", "variant", "rel_eb", "cr", "psnr") for f in ("halo", "ledger", "waves")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query()
def wl_w06(s, d):
    """Growth and cap of the bound per level."""
    grid = [replace(OURS, alpha=a, beta=b, label=f"{a}/{b}") for a, b in schedule_grid()]
    return sweep(s, d, "halo", grid, (3e-2, 1e-2), by=("variant", "eb"), percent=50).select("variant", "rel_eb", "cr", "psnr")


@query()
def wl_w07(s, d):
    """Similarity and PSNR before and after repair, on the waves with the transform codec and on the density with the predictor."""
    parts = [sweep(s, d, f, [with_repair(c)], (1e-1, 3e-2, 1e-2), by=("variant", "eb")).select("field", "variant", "rel_eb", "cr", "psnr_plain", "psnr", "ssim_plain", "ssim", "a") for f, c in (("waves", XFORM), ("halo", PRED4))]
    return parts[0].unionByName(parts[1])


@query()
def wl_w08(s, d):
    """Smoothing filters against the repair, on one decompressed field."""
    kinds = [replace(XFORM, label="decompressed"), replace(XFORM, repair="free", label="unclamped"), replace(XFORM, repair="fit", label="repair")]
    out = sweep(s, d, "waves", kinds, (0.03,), by=("variant", "eb")).select(F.col("variant").alias("method"), "psnr")
    p, _, g = reconstruct(s, d, "waves", XFORM, 0.03)
    p = kept(p.select("x", "y", "z", "orig", "deco"), "pairs")
    made = p.select("x", "y", "z", F.col("deco").alias("v"))
    kappa = fi.mean_step(made)
    for name, work_ in fi.FILTERS.items():
        smooth = fi.tiled(made, g, (lambda a: fi.diffusion(a, kappa=kappa)) if name == "diffusion" else work_, fi.REACH[name])
        both = smooth.withColumnRenamed("v", "deco").join(p.select("x", "y", "z", "orig"), ["x", "y", "z"])
        out = out.unionByName(me.distortion(both).select(F.lit(name).alias("method"), "psnr"))
    return out


@query()
def wl_w09(s, d):
    """Repair variants over six bounds: unclamped, plain, clamped at the bound, fitted."""
    kinds = [XFORM, replace(XFORM, repair="free", label="unclamped"), replace(XFORM, repair="one", label="a=1"), with_repair(XFORM)]
    return sweep(s, d, "waves", kinds, by=("variant", "eb")).select("variant", "rel_eb", "cr", "psnr", "sample_rate", "a")


work.add("wl_w10", core.queries["repair_situations"], core.sql["repair_situations"])


@query()
def wl_w11(s, d):
    """Repair of the prediction codec at seven bounds."""
    return sweep(s, d, "waves", [with_repair(PRED6)], (1e-1, 5e-2, 2e-2, 1e-2, 5e-3, 2e-3, 1e-3), by=("variant", "eb")).select("variant", "rel_eb", "cr", "psnr_plain", "psnr", "a")


def sampled_model(s, table: DataFrame, codec: Codec, iso: float) -> tuple[float, float]:
    """(mu, sigma) of the error near an isovalue, from the blocks that are sampled and coded before the field is."""
    blocks, counts = en.sample_blocks(table)
    pairs = [p for level, some in blocks.items() for p in en.sample_pairs(some, codec, counts[level])[0]]
    flat = [np.concatenate([p[k].ravel() for p in pairs]) for k in (0, 1)]
    mu, sigma, _, _ = un.near_model(s.createDataFrame(pa.table({"orig": flat[0], "deco": flat[1]})), iso, codec.eb)
    return mu, sigma


@query()
def wl_w12(s, d):
    """Isosurface cells lost by compression and found again by crossing probability, near a ratio of 240; the error model is the sample's."""
    out = None
    for name, q in (("layer", 0.5), ("halo", 0.9)):
        points = sweep(s, d, name, [XFORM], (1.0, 3e-1, 1e-1, 3e-2, 1e-2), by=("variant", "eb"))
        rel = bound_at_cr(points, XFORM.label, 240.0)
        table, packets, c, g = packed(s, d, name, XFORM, rel)
        cr = packets.agg(F.sum("raw_bytes") / F.sum("packed_bytes")).first()[0]
        p = kept(en.pairs(table_cells(table, g), level_cells(en.decode(packets), g)).select("x", "y", "z", "orig", "deco"), "pairs")
        iso = p.approxQuantile("orig", [q], 0.0)[0]
        mu, sigma = sampled_model(s, table, c, iso)
        o, r = (p.select("x", "y", "z", F.col(v).alias("v")) for v in ("orig", "deco"))
        found = un.recovery(o, r, un.prob_cells(r, mu, sigma, iso), iso)
        row = found.select(F.lit(name).alias("field"), F.lit(cr).alias("cr"), F.lit(iso).alias("iso"), "crossed", "lost", "recovered", "kept", "false_hits", ((F.col("kept") + F.col("recovered")) / F.col("crossed")).alias("recall"))
        out = row if out is None else out.unionByName(row)
    return out


@query()
def wl_w13(s, d):
    """Adaptive mesh of two levels (18 and 82 percent): five curves per level."""
    return sweep(s, d, "halo", [LINEAR, STACK, PAD, OURS, OURS_FIXED], percent=18).select("variant", "level", "rel_eb", "cr", "psnr", "max_err")


@query()
def wl_w14(s, d):
    """Output time per snapshot of a stream: arranging (and padding) and coding of the stacked and the multi-resolution form, at a large and a small bound.

    Three snapshots go through micro-batches; times are measured inside the tasks, so both forms start from the same chunks.
    """
    cells, g = cube(s, d, "halo")
    u, span = max(8, g // 4), value_range(cells)
    folder = st.scratch(s, "snapshots")
    en.field_chunks(cells, g, u, percent=18).coalesce(1).write.parquet(f"{folder}/0")
    for k in (1, 2):
        s.read.schema(CHUNK).parquet(f"{folder}/0").coalesce(1).write.parquet(f"{folder}/{k}")

    def timed(batches):
        for batch in batches:
            out = []
            for _, _, keys, vals in en._rows(batch, u):
                for rel in (1e-1, 5e-3):
                    for c in (STACK, OURS):
                        t0 = time.perf_counter()
                        arrays = [a for _, _, a in prepared(keys, vals, c, g // u, g // u)]
                        t1 = time.perf_counter()
                        size = sum(len(interp_encode(a, rel * span, c.order, c.extrap, c.schedule, c.alpha, c.beta)[0]) for a in arrays)
                        out.append((rel, c.label, t1 - t0, time.perf_counter() - t1, size))
            kinds = [pa.float64(), pa.string(), pa.float64(), pa.float64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in out], t) for k, t in enumerate(kinds)], names=["rel_eb", "variant", "prepare", "compress", "packed_bytes"])

    sink = st.scratch(s, "times")
    stream = s.readStream.schema(CHUNK).option("maxFilesPerTrigger", 1).parquet(f"{folder}/*")
    st.compress_batches(stream, sink, lambda batch: batch.mapInArrow(timed, "rel_eb double, variant string, prepare double, compress double, packed_bytes long"))
    times = s.read.parquet(sink).groupBy("batch", "rel_eb", "variant").agg(*(F.sum(c).alias(c) for c in ("prepare", "compress", "packed_bytes")))
    return times.groupBy("rel_eb", "variant").agg(F.count("*").alias("snapshots"), F.median("prepare").alias("prepare"), F.median("compress").alias("compress"), F.median(F.col("prepare") + F.col("compress")).alias("total"), F.max("packed_bytes").alias("packed_bytes"))


@query()
def wl_w15(s, d):
    """Repair of the prediction codec on both levels of the mesh."""
    return sweep(s, d, "halo", [with_repair(PRED4)], BOUNDS[:5], percent=18).select("level", "rel_eb", "cr", "psnr_plain", "psnr")


@query()
def wl_w16(s, d):
    """Waves with half of the cubes fine: PSNR and similarity of the baseline and of the multi-resolution codec at equal ratios."""
    points = sweep(s, d, "waves", [LINEAR, OURS], (3e-1, *BOUNDS), by=("variant", "eb"), percent=50)
    return me.at_cr(points, s.createDataFrame([(20.0,), (50.0,), (100.0,), (147.0,)], "at double"))


@query()
def wl_w17(s, d):
    """Adaptive data: baseline, padding, padding with the bound per level."""
    parts = [sweep(s, d, f, [LINEAR, PAD, OURS], by=("variant", "eb"), percent=p).select("field", "variant", "rel_eb", "cr", "psnr") for f, p in (("waves", 50), ("events", 35))]
    return parts[0].unionByName(parts[1])


@query()
def wl_w18(s, d):
    """Meshes of two and of three levels: five variants."""
    kinds = [LINEAR, STACK, KD, PAD, OURS]
    two = sweep(s, d, "halo", kinds, by=("variant", "eb"), percent=58)
    three = sweep(s, d, "layer", kinds, by=("variant", "eb"), shares=[15, 31, 54], u=8)
    return two.unionByName(three).select("field", "variant", "rel_eb", "cr", "psnr")


@query()
def wl_w19(s, d):
    """Error of the power spectrum of the flattened two-level mesh (58 and 42 percent) by variant, at the ratio that ours has at 1 percent.

    ``reduction_pct`` is how much smaller the mean error of ours is.
    """
    kinds = [LINEAR, STACK, KD, OURS]
    points = kept(sweep(s, d, "halo", kinds, (1e-1, 5e-2, 2e-2, 1e-2, 5e-3, 2e-3, 1e-3), by=("variant", "eb"), percent=58).select("variant", "rel_eb", "cr"), "points")
    cr = points.where((F.col("variant") == OURS.label) & (F.abs(F.col("rel_eb") - 1e-2) < 1e-9)).first()["cr"]
    out = base = None
    for c in kinds:
        table, packets, _, g = packed(s, d, "halo", c, bound_at_cr(points, c.label, cr), percent=58)
        u = max(8, g // 4)
        if base is None:
            blocks = table.select("level", F.posexplode("keys").alias("i", "key"), "vals", (F.size("vals") / F.size("keys")).cast("int").alias("n")).select("level", "key", F.slice("vals", F.col("i") * F.col("n") + 1, F.col("n")).alias("vals"))
            base = kept(me.power_spectrum_blocks(blocks, g, g // u, g // u), "spectrum")
        packets = kept(packets, "packets")
        size = packets.agg((F.sum("raw_bytes") / F.sum("packed_bytes")).alias("cr"))
        error = me.spectrum_error(base, me.power_spectrum_blocks(en.decode(packets), g, g // u, g // u))
        row = error.crossJoin(F.broadcast(size)).withColumn("variant", F.lit(c.label))
        out = row if out is None else out.unionByName(row)
    out = kept(out, "errors")
    ours = F.broadcast(out.where(F.col("variant") == OURS.label).select(F.col("mean_err").alias("ours")))
    return out.crossJoin(ours).select("variant", "cr", "mean_err", "max_err", "passes", (100 * (1 - F.col("ours") / F.col("mean_err"))).alias("reduction_pct"))


@query()
def wl_w20(s, d):
    """Repair on multi-resolution data: two codecs, two fields, six bounds."""
    parts = [sweep(s, d, f, [with_repair(XFORM), with_repair(PRED4)], by=("variant", "eb"), **k).select("field", "variant", "rel_eb", "cr", "psnr_plain", "psnr") for f, k in (("layer", {"shares": [15, 31, 54], "u": 8}), ("events", {"percent": 35}))]
    return parts[0].unionByName(parts[1])


@query()
def wl_w21(s, d):
    """Repair on uniform data: two codecs, two fields, six bounds."""
    parts = [sweep(s, d, f, [with_repair(XFORM), with_repair(PRED6)], by=("variant", "eb")).select("field", "variant", "rel_eb", "cr", "psnr_plain", "psnr") for f in ("ledger", "halo")]
    return parts[0].unionByName(parts[1])


@query()
def wl_w22(s, d):
    """Overhead of sampling, fitting and repairing over writing, coding and reading alone: wall-clock, in one task and in all."""
    cells, g = cube(s, d, "ledger")
    u, span = max(8, g // 4), value_range(cells)
    nb, rows = g // u, []
    table = kept(en.field_chunks(cells, g, u, per_chunk=8), "chunks")
    for mode, some in (("serial", table.coalesce(1)), ("parallel", table.repartition(8))):
        for c in (XFORM.at(1e-2 * span), PRED6.at(1e-2 * span)):
            fixed, timer = with_repair(c), me.StageTimer()
            with timer.stage("fit"):
                fitted = {level: a for (_, level), (a, _) in en.fit(some, [fixed]).items()}
            with timer.stage("code"):
                packets = kept(en.encode(some, fixed, u, nb, nb, fitted), "packets")
            with timer.stage("plain"):
                en.decode(packets).write.format("noop").mode("overwrite").save()
            with timer.stage("repaired"):
                en.decode_repaired(packets).write.format("noop").mode("overwrite").save()
            t = timer.seconds
            process = max(0.0, t["repaired"] - t["plain"])
            rows.append((c.label, mode, 1e-2, t["code"] + t["plain"], t["fit"], process, (t["fit"] + process) / (t["code"] + t["plain"])))
    return s.createDataFrame(rows, "codec string, mode string, rel_eb double, io_codec_s double, fit_s double, process_s double, overhead double")


_INVENTORY = "SELECT '{f}' AS field, g || 'x' || g || 'x' || g AS shape, CAST(g * g * g AS BIGINT) AS cells, (SELECT {n} FROM {t}) AS occupied, CAST(8 * g * g * g AS BIGINT) AS bytes FROM g"
_EVERY = " UNION ALL ".join(_INVENTORY.format(f=f, n=n, t=t) for f, n, t in (("halo", "count(*) FILTER (v <> 0)", "halo"), ("ledger", "count(*) FILTER (v <> 0)", "ledger"), ("waves", "CAST(g * g * g AS BIGINT)", "g"), ("layer", "CAST(g * g * g AS BIGINT)", "g")))


@query(f"WITH {HALO}, {LEDGER.removeprefix(G).lstrip(', ')}, {CUBE} {_EVERY} UNION ALL SELECT 'events', '16x5x720', count(*), count(*) FILTER (v <> 0), 8 * count(*) FROM cube_")
def wl_w23(s, d):
    """Every field with its shape, density and bytes."""
    g = fl.grid_edge(s, d)
    parts = []
    for name, make in fl.CUBES.items():
        parts.append(make(s, d, g).agg(F.count("*").alias("cells"), F.count_if(F.col("v") != 0).alias("occupied")).select(F.lit(name).alias("field"), F.lit(f"{g}x{g}x{g}").alias("shape"), "cells", "occupied"))
    parts.append(fl.event_cube(s, d).agg(F.count("*").alias("cells"), F.count_if(F.col("v") != 0).alias("occupied")).select(F.lit("events").alias("field"), F.lit("16x5x720").alias("shape"), "cells", "occupied"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.withColumn("bytes", 8 * F.col("cells"))


@query()
def wl_w23_levels(s, d):
    """The meshes of the workloads by level: cells, share of the domain, bytes."""
    out = None
    for name, how in (("halo", {"percent": 18}), ("halo", {"percent": 58}), ("waves", {"percent": 50}), ("events", {"percent": 35}), ("layer", {"shares": [15, 31, 54], "u": 8})):
        cells, g = cube(s, d, name)
        u = how.get("u") or max(8, g // 4)
        table = en.field_chunks(cells, g, u, **{k: v for k, v in how.items() if k != "u"})
        stored = table.groupBy("level").agg(F.sum(F.size("vals")).alias("cells"))
        row = stored.select(F.lit(name).alias("field"), F.lit(str(how.get("percent") or how["shares"])).alias("shares"), "level", "cells", (F.col("cells") * F.pow(F.lit(8.0), "level") / float(g**3)).alias("density"), (8 * F.col("cells")).alias("bytes"))
        out = row if out is None else out.unionByName(row)
    return out


work.add(
    "wl_w24",
    lambda s, d: s.createDataFrame([tuple(me.size_plan((1024**3 + 2048**3) // 2, 26, 200, 5).values())], "field_bytes long, snapshot_bytes long, campaign_bytes long"),
    "SELECT p * 8 AS field_bytes, p * 8 * 26 AS snapshot_bytes, p * 8 * 26 * 200 * 5 AS campaign_bytes FROM (SELECT CAST((1024::BIGINT ** 3 + 2048::BIGINT ** 3) / 2 AS BIGINT) AS p)",
)


@query()
def wl_w25(s, d):
    """Lossless coding of every cube field: the ratio without any error."""
    parts = [sweep(s, d, f, [Codec("lossless", label="lossless")], (0.0,), by=("variant",)).select("field", "cr", "max_err") for f in fl.CUBES]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query()
def wl_w26(s, d):
    """Noise: all codecs on embeddings taken as cubes."""
    cubes = s.read.parquet(f"{d}/embeddings.parquet").select(F.lit(0).alias("level"), F.col("vec_id").alias("key"), F.col("embedding").cast("array<double>").alias("vals"))
    variants = [replace(c, arrange="linear").at(e) for c in (LINEAR, OURS, PRED4, XFORM, Codec("lossless", label="lossless")) for e in (0.05, 0.005)]
    return en.rd_points(en.evaluate(en.chunks(cubes, 4), variants, 4, 1, 1 << 30), ("variant", "eb"))


# round trips and codec options

_SMALL = (3e-2, 1e-3)
#: How many cells each level has when half of the cubes (of a quarter of the edge) stay fine.
_HALF = "n AS (SELECT g, CAST(greatest(8, g // 4) AS BIGINT) AS u, CAST(g // greatest(8, g // 4) AS BIGINT) AS m FROM g), lv AS (SELECT 0 AS level, CAST(ceil(m * m * m * 0.5) AS BIGINT) * u * u * u AS n FROM n UNION ALL SELECT 1, (m * m * m - CAST(ceil(m * m * m * 0.5) AS BIGINT)) * u * u * u // 8 FROM n)"
_WHOLE = "lv AS (SELECT 0 AS level, CAST(g * g * g AS BIGINT) AS n FROM g)"


def _trip(name: str, variants: list[Codec], field: str = "halo", percent: float | None = None):
    """``name``: every cell comes back from packets within its bound, with SQL; ``name``_points: what it costs."""

    def exact(s, d):
        out = None
        for c in variants:
            for rel in _SMALL:
                table, packets, codec, g = packed(s, d, field, c, rel, **({} if percent is None else {"percent": percent}))
                # a repaired value stays within the sum of the intensities of all axes
                slack = 1.0 if c.repair == "none" else 1 + 3 * max(rp.CANDIDATES[c.name])
                back = en.decode(packets) if c.repair == "none" else en.decode_repaired(packets)
                both = en.pairs(table_cells(table, g), level_cells(back, g))
                off = F.abs(F.col("orig") - F.col("deco")) > slack * codec.eb * (1 + 1e-12)
                row = both.groupBy("level").agg(F.count("*").alias("n"), F.count_if(off).alias("violations")).select(F.lit(c.label).alias("variant"), F.lit(round(1e6 * rel)).cast("long").alias("rel_e6"), "level", "n", "violations")
                out = row if out is None else out.unionByName(row)
        return out

    names = ", ".join(f"'{c.label}'" for c in variants)
    sql = f"WITH {G}, {_WHOLE if percent is None else _HALF} SELECT variant, rel_e6, CAST(level AS INTEGER) AS level, n, CAST(0 AS BIGINT) AS violations FROM lv, unnest([{names}]) AS a(variant), unnest([{', '.join(f'{round(1e6 * r)}::BIGINT' for r in _SMALL)}]) AS b(rel_e6)"
    work.add(name, exact, sql)
    work.add(f"{name}_points", lambda s, d: sweep(s, d, field, variants, _SMALL, **({} if percent is None else {"percent": percent})))


_trip("interp3d_roundtrip", [LINEAR, replace(LINEAR, extrap="linear2", label="linear extrapolation")])
_trip("interp_cubic", [LINEAR, replace(LINEAR, order="linear", label="first order")], "ledger")
_trip("mrinterp_roundtrip", [OURS], percent=50)
_trip("mrinterp_ablation", [LINEAR, PAD, OURS, OURS_FIXED], percent=50)
_trip("bpred_roundtrip_4", [replace(PRED4, predictor=p, label=p) for p in ("lorenzo", "regression", "auto", "dual")])
_trip("bpred_roundtrip_6", [replace(PRED6, predictor=p, label=p) for p in ("lorenzo", "regression", "auto", "dual")], "ledger")
_trip("bxform_roundtrip", [XFORM, with_repair(XFORM)])
_trip("bxform_dct_roundtrip", [replace(XFORM, transform="dct", label="dct")])
_trip("arrange_zline_roundtrip", [ZLINE, replace(ZLINE, order="linear", label="zline first order")], percent=50)
_trip("arrange_hzline_roundtrip", [HZLINE], percent=50)
_trip("arrange_kd_roundtrip", [KD, STACK], percent=50)


@query()
def baseline_whole_array(s, d):
    """The codec on the whole uniform array, as one block, beside the same array in unit blocks."""
    cells, g = cube(s, d, "halo")
    whole = sweep(s, d, "halo", [replace(LINEAR, label="whole array")], BOUNDS, u=g, by=("variant", "eb"))
    blocks = sweep(s, d, "halo", [replace(LINEAR, label="unit blocks"), replace(HZLINE, label="hierarchical order")], BOUNDS, by=("variant", "eb"))
    return whole.unionByName(blocks).select("variant", "rel_eb", "cr", "psnr")


@query()
def wl_gains(s, d):
    """How much larger the ratio of the multi-resolution codec is at equal quality, by field: from the measured curves of the meshes."""
    out = None
    for field, base, share in (("halo", LINEAR, 18), ("halo", STACK, 58), ("waves", LINEAR, 50), ("events", LINEAR, 35)):
        points = kept(sweep(s, d, field, [base, OURS], (2e-1, 1e-1, 5e-2, 3e-2, 1e-2, 3e-3, 1e-3), by=("variant", "eb"), percent=share).select("variant", "cr", "psnr"), "points")
        ends = points.groupBy("variant").agg(F.min("psnr").alias("low"), F.max("psnr").alias("high")).agg(F.max("low").alias("low"), F.min("high").alias("high"))
        at = F.broadcast(ends.select(F.explode(F.array(*(F.col("low") + (F.col("high") - F.col("low")) * f for f in (0.1, 0.3, 0.5, 0.7, 0.9)))).alias("at")))
        row = me.gain_at_psnr(points, OURS.label, base.label, at).select(F.lit(field).alias("field"), F.lit(share).alias("percent"), F.lit(base.label).alias("base"), "at", "gain")
        out = row if out is None else out.unionByName(row)
    return out


work.add("lossless_ratio", lambda s, d: wl_w25(s, d))


@query()
def interp_trialeb(s, d):
    """The tuned schedule: of all pairs, the one with the best ratio among those that reach the best PSNR less half a dB, on a tenth of the chunks by hash, one at least."""
    grid = [replace(OURS, alpha=a, beta=b, label=f"{a}/{b}") for a, b in schedule_grid()]
    cells, g = cube(s, d, "halo")
    u, span = max(8, g // 4), value_range(cells)
    table = kept(en.field_chunks(cells, g, u, percent=50, per_chunk=8), "chunks")
    part = table.orderBy(F.xxhash64("level", "chunk")).limit(max(1, table.count() // 10))
    points = en.rd_points(en.evaluate(part, [c.at(1e-2 * span) for c in grid], u, g // u, g // u, span), ("variant", "eb"))
    return points.crossJoin(points.agg(F.max("psnr").alias("best"))).where("psnr >= best - 0.5").orderBy(F.desc("cr"), "variant").limit(1).select("variant", "cr", "psnr")


@query()
def metric_cr(s, d):
    return sweep(s, d, "halo", [OURS], (1e-2,), by=("level", "eb"), percent=50).select("level", "n", "packed_bytes", "cr")


@query()
def metric_bitrate(s, d):
    return sweep(s, d, "halo", [OURS], (1e-1, 1e-2, 1e-3), by=("variant", "eb"), percent=50).select("rel_eb", "bitrate")


@query()
def metric_overhead(s, d):
    return wl_w22(s, d).select("codec", "mode", "rel_eb", "overhead")


@query()
def filter_diffusion(s, d):
    return wl_w08(s, d).where("method = 'diffusion'")


@query()
def packets_random_access(s, d):
    """Only packets whose range meets an isovalue are decoded; the others are never read into Python."""
    cells, g = cube(s, d, "halo")
    u, span = 8, value_range(cells)
    c = OURS.at(1e-2 * span)
    table = en.field_chunks(cells, g, u, per_chunk=8)
    packets = en.encode(table, c, u, g // u, g // u)
    iso = float(cells.agg(F.max("v")).first()[0]) / 2
    near = packets.where((F.col("vmin") <= iso + c.eb) & (F.col("vmax") >= iso - c.eb))
    return en.decode(near).groupBy("level").agg(F.count("*").alias("blocks"), F.max(F.array_max("vals")).alias("top"))
