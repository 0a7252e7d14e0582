"""Repair, uncertainty, measures, plans and streams against plain versions."""

from itertools import product

import numpy as np
import pytest
from pyspark.sql import functions as F

from fieldmr import engine as en
from fieldmr import fields as fl
from fieldmr import filters as fi
from fieldmr import hierarchy as h
from fieldmr import metrics as me
from fieldmr import repair as rp
from fieldmr import uncert as un
from fieldmr.codec.apply import mrinterp

SF = "/root/testdata/sf0.001"
RNG = np.random.default_rng(1)


def cells(spark, a, name="v"):
    g = [i.ravel() for i in np.meshgrid(*[np.arange(n) for n in a.shape], indexing="ij")]
    rows = [(int(x), int(y), int(z), float(v)) for x, y, z, v in zip(*g, a.ravel(), strict=True)]
    return spark.createDataFrame(rows, f"x int, y int, z int, {name} double")


def dense(df, shape, name="v"):
    out = np.full(shape, np.nan)
    for r in df.collect():
        out[r.x, r.y, r.z] = r[name]
    return out


def test_midpoint_and_clamp():
    assert rp.bezier(0, 4, 0) == 2 == rp.midpoint(0, 4, 0)
    d = np.array([0.0, 0, 0, 0, 4, 0, 0, 0]).reshape(8, 1, 1)
    assert rp.sweep(d, 0, 4, 0.5)[4, 0, 0] == 3.5


def test_dataframe_repair_matches_numpy(spark):
    a = RNG.normal(size=(8, 8, 8)).cumsum(0)
    for combine in ("sequential", "average"):
        got = dense(rp.repair_cells(cells(spark, a), 1.0, (0.2, 0.3, 0.4), 4, combine), a.shape)
        assert np.allclose(got, rp.repair(a, 1.0, (0.2, 0.3, 0.4), 4, combine))


def test_repair_stays_within_its_limits():
    a, eb = RNG.normal(size=(12, 12, 12)), 0.1
    moved = rp.repair(a, eb, (0.5, 0.4, 0.3), 4)
    assert np.abs(moved - a).max() <= eb * 1.2 + 1e-12
    assert np.abs(rp.repair(a, eb, (0.5, 0.4, 0.3), 4, hard=True) - a).max() <= eb * 0.5 + 1e-12
    inner = np.ix_(*[[i for i in range(12) if i % 4 in (1, 2)]] * 3)
    assert np.array_equal(moved[inner], a[inner])


def test_fits_agree():
    o = np.sin(np.add.outer(np.add.outer(np.arange(16) / 3, np.arange(16) / 4), np.arange(16) / 5))
    d = np.floor(o / 0.4 + 0.5) * 0.4
    pairs = [(o[:8, :8, :8], d[:8, :8, :8]), (o[8:, 8:, 8:], d[8:, 8:, 8:])]
    grid = rp.CANDIDATES["blockpred"]
    loss = lambda a: sum(((x - rp.repair(y, 0.2, a, 4)) ** 2).sum() for x, y in pairs)
    best = min(loss(t) for t in product(grid, repeat=3))
    assert loss(rp.fit_intensity(pairs, 0.2, 4, grid, "joint")) == pytest.approx(best)
    assert loss(rp.fit_intensity(pairs, 0.2, 4, grid)) <= best * 1.05
    assert loss(rp.fit_intensity(pairs, 0.2, 4, grid, "sgd")) <= best * 1.05


def test_sample_plan_respects_rate():
    i, side, origins = rp.sample_plan((64, 64, 64), 4)
    assert (i * side) ** 3 / 64**3 <= 0.015 and len(origins) == i**3 and side >= 8


def test_filters_match(spark):
    a = RNG.normal(size=(6, 6, 6))
    assert np.allclose(dense(fi.gauss_cells(cells(spark, a)), a.shape), fi.gaussian(a))
    got = dense(fi.median_cells(cells(spark, a)), a.shape)
    assert np.allclose(got[1:-1, 1:-1, 1:-1], fi.median(a)[1:-1, 1:-1, 1:-1])


def test_uncertainty(spark):
    from math import erf

    z = np.linspace(-4, 4, 200)
    assert np.abs(un.erf_np(z) - [erf(v) for v in z]).max() < 2e-7
    a = np.zeros((2, 2, 2))
    a[0, 0, 0] = 1.0
    c = cells(spark, a)
    assert [r.crossed for r in un.det_cells(c, 0.5).collect()] == [True]
    p = un.prob_cells(c, 0.0, 1e-9, 0.5).first().p
    assert p == pytest.approx(1.0)
    assert un.prob_cells(cells(spark, np.ones((2, 2, 2))), 0.0, 0.0, 0.5).first().p == 0.0
    flat = np.full((2, 2, 2), 9.0)
    flat[0, 0, 0] = 0.5
    assert un.prob_cells(cells(spark, flat), 0.0, 0.01, 0.5).first().p == pytest.approx(0.5, abs=1e-6)
    noisy = RNG.normal(size=(4, 4, 4))
    closed = {(r.x, r.y, r.z): r.p for r in un.prob_cells(cells(spark, noisy), 0.0, 0.5, 0.2).collect()}
    drawn = un.mc_cells(cells(spark, noisy), 0.0, 0.5, 0.2, 4000).collect()
    assert max(abs(r.p - closed[r.x, r.y, r.z]) for r in drawn) < 0.05
    again = un.mc_cells(cells(spark, noisy).repartition(3), 0.0, 0.5, 0.2, 4000).collect()
    assert {(r.x, r.y, r.z): r.p for r in drawn} == {(r.x, r.y, r.z): r.p for r in again}


def test_components(spark):
    mask = RNG.random((5, 5, 5)) < 0.4
    rows = [(int(x), int(y), int(z)) for x, y, z in zip(*np.nonzero(mask), strict=True)]
    got = {r.node: r.component for r in un.components(spark.createDataFrame(rows, "x int, y int, z int"), 5).collect()}
    label = {p: p[0] * 25 + p[1] * 5 + p[2] for p in rows}
    for _ in range(len(rows)):
        for x, y, z in rows:
            for o in ((1, 0, 0), (0, 1, 0), (0, 0, 1)):
                q = (x + o[0], y + o[1], z + o[2])
                if q in label:
                    label[q] = label[x, y, z] = min(label[q], label[x, y, z])
    assert got == {x * 25 + y * 5 + z: label[x, y, z] for x, y, z in rows}


def test_spectrum_matches_fft(spark):
    a = 5 + RNG.normal(size=(8, 8, 8))
    got = {r.k: r.p for r in me.power_spectrum(cells(spark, a), 8, kmax=3).collect()}
    f = np.abs(np.fft.fftn(a / a.mean() - 1)) ** 2
    k = np.fft.fftfreq(8, 1 / 8)
    for shell in (1, 2):
        near = [f[i, j, m] for i, j, m in product(range(8), repeat=3) if max(abs(k[i]), abs(k[j]), abs(k[m])) < 3 and int(np.floor(np.sqrt(k[i] ** 2 + k[j] ** 2 + k[m] ** 2) + 0.5)) == shell]
        assert got[shell] == pytest.approx(np.mean(near))


def test_ssim_of_equal_fields_is_one(spark):
    a = RNG.normal(size=(8, 8, 8))
    both = cells(spark, a, "orig").withColumn("deco", F.col("orig"))
    assert me.ssim_blocks(both).first().ssim == pytest.approx(1.0)
    flat = cells(spark, np.full((8, 8, 8), 7.0), "orig").withColumn("deco", F.col("orig"))
    assert me.ssim_blocks(flat).first().ssim == 1.0
    assert me.distortion(flat).first().psnr is None


def test_packets_round_trip_and_partition_invariance(spark):
    field = fl.analytic(spark, 16, "wave")
    c = mrinterp(0.01)
    sizes = set()
    for parts in (1, 4, 17):
        packets = en.encode(en.field_chunks(field.repartition(parts), 16, 8), c, 8, 2, 2)
        sizes.add(packets.agg(F.sum("packed_bytes")).first()[0])
        back = en.block_cells(en.decode(packets), 8, 2, 2)
        both = en.pairs(field.withColumn("level", F.lit(0)), back)
        assert both.agg(F.count("*"), F.max(F.abs(F.col("orig") - F.col("deco")))).first()[0] == 4096
        assert both.agg(F.max(F.abs(F.col("orig") - F.col("deco")))).first()[0] <= 0.01
    assert len(sizes) == 1


def test_three_levels_keep_every_cell(spark):
    """Level 2 has cubes of side 2, alone or beside cubes of other levels: each is coded, measured and decoded."""
    from fieldmr.queries.workloads import KD, LINEAR, OURS, PRED4, STACK, XFORM, with_repair

    g, u, shares, eb = 32, 8, [15, 31, 54], 0.01
    field, nb = fl.mixing_layer(spark, SF, g).persist(), g // u
    ranked = h.level_of_rank(h.block_ranges(field, u, nb, nb), shares)
    levels = h.build_levels(field, ranked, u, nb, nb).select("level", "x", "y", "z", (F.col("v") / F.col("n")).alias("v")).persist()
    want = {r["level"]: r["count"] for r in levels.groupBy("level").count().collect()}
    assert set(want) == {0, 1, 2}
    table = en.field_chunks(field, g, u, shares=shares).persist()
    variants = [c.at(eb) for c in (LINEAR, STACK, KD, OURS, PRED4, XFORM, with_repair(PRED4), with_repair(XFORM))]
    points = en.rd_points(en.evaluate(table, variants, u, nb, nb)).collect()
    assert len(points) == 3 * len(variants)
    for r in points:
        assert r.n == want[r.level]
        assert r.max_err <= eb * (1 if "repair" not in r.variant else 1.5 + 1e-9)
    for c in (variants[0], variants[4], variants[5]):
        back = en.block_cells(en.decode(en.encode(table, c, u, nb, nb)), u, nb, nb)
        n, worst = en.pairs(levels, back).agg(F.count("*"), F.max(F.abs(F.col("orig") - F.col("deco")))).first()
        assert n == sum(want.values()) and worst <= eb


def test_blocks_with_absent_cells_are_an_error(spark):
    field = fl.analytic(spark, 16, "wave").where("x > 0 or y > 0 or z > 0")
    with pytest.raises(Exception, match="absent cells"):
        en.field_chunks(field, 16, 8, percent=50).collect()


def test_bound_per_level_raises_quality(spark):
    """The method's main effect on a smooth field at large bounds; size matters, so the field is a closed form."""
    from fieldmr.queries.workloads import OURS, PAD

    table = en.field_chunks(fl.analytic(spark, 32, "wave"), 32, 16)
    rows = {r.variant: r.psnr for r in en.rd_points(en.evaluate(table, [PAD.at(0.1), OURS.at(0.1)], 16, 2, 2)).collect()}
    assert rows["pad+eb"] > rows["pad"] + 2


def test_fitted_repair_does_not_lose(spark):
    from fieldmr.queries.workloads import XFORM, sweep, with_repair

    for r in sweep(spark, SF, "waves", [with_repair(XFORM)], (1e-1, 3e-2, 1e-2), by=("variant", "eb")).collect():
        assert r.psnr >= r.psnr_plain - 0.05


def test_cuts_are_exact_under_ties(spark):
    ranges = spark.createDataFrame([(i, int(v)) for i, v in enumerate(RNG.integers(0, 5, 300))], "key long, rng long")
    for pct in (0, 1, 15, 50, 99, 100):
        want = {r.key for r in h.roi_top(ranges, pct).collect()}
        assert {r.key for r in h.roi_top_scalable(ranges, pct, 3).collect()} == want


def test_block_side_is_checked():
    h.check_side(16)
    for b in (4, 12, 7):
        with pytest.raises(ValueError):
            h.check_side(b)


def test_plans_have_no_nested_loops(spark):
    from fieldmr.queries.core import core

    for name in ("grid_ledger_integral", "level_adaptive", "repair_fixed_a", "arrange_linear", "unc_prob_cells"):
        plan = core.queries[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
        # nested loops are over the kernel alone, whose size the grid fixes
        assert "CartesianProduct" not in plan


def test_scans_are_pruned(spark):
    plan = fl.order_density(spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "o_orderpriority" not in plan and "c_name" not in plan


def test_stream_equals_batch(spark):
    from fieldmr import streaming as st

    events = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    want = {tuple(r) for r in st.tumbling(events).collect()}
    got = {tuple(r) for r in st.drained(st.tumbling(st.event_stream(spark, SF)), "t", "complete").collect()}
    assert got == want


def test_repair_travels_with_packets(spark):
    """What packets say is what was fitted; faces between chunks are repaired as in the whole array; measuring and decoding agree."""
    from fieldmr import repair as rp
    from fieldmr.queries.workloads import XFORM, with_repair

    g, u, c = 16, 8, with_repair(XFORM).at(200.0)
    field = fl.nation_modes(spark, SF, g).persist()
    table = en.field_chunks(field, g, u, per_chunk=3).persist()
    assert table.count() > 2
    (a, rate), *_ = en.fit(table, [c]).values()
    packets = en.encode(table, c, u, 2, 2, {0: a}).persist()
    assert all(tuple(r.intensity) == a and "200.0" in r.settings for r in packets.collect())

    def dense(blocks):
        out = np.empty((g, g, g))
        for r in en.block_cells(blocks, u, 2, 2).collect():
            out[r.x, r.y, r.z] = r.v
        return out

    plain, fixed = dense(en.decode(packets)), dense(en.decode_repaired(packets))
    assert np.allclose(fixed, rp.repair(plain, c.eb, a, 4), atol=1e-9)
    orig = np.empty((g, g, g))
    for r in field.collect():
        orig[r.x, r.y, r.z] = r.v
    point = en.rd_points(en.evaluate(table, [c], u, 2, 2, 1.0)).first()
    mse = ((orig - fixed) ** 2).mean()
    assert point.psnr == pytest.approx(20 * np.log10(np.ptp(orig)) - 10 * np.log10(mse))
    assert point.n == g**3 and point.packed_bytes == packets.agg(F.sum("packed_bytes")).first()[0]
    with pytest.raises(ValueError, match="intensities"):
        en._strength(c, None)


def test_repair_leaves_out_what_gains_nothing():
    from fieldmr import repair as rp

    noise = RNG.normal(size=(8, 8, 8))
    pairs = [(noise, noise + RNG.normal(size=noise.shape) * 1e-3)]
    for method in ("coordinate", "grid", "sgd"):
        assert rp.fit_intensity(pairs, 1.0, 4, rp.CANDIDATES["blockpred"], method, include_zero=True) == (0.0, 0.0, 0.0)


def test_padded_blocks_repair_like_the_whole():
    from fieldmr import repair as rp

    a = RNG.normal(size=(12, 12, 12))
    want = rp.repair(a, 1.0, (0.3, 0.2, 0.1), 4)
    wide = np.pad(a, 1, constant_values=np.nan)
    blocks = np.stack([wide[x : x + 6, y : y + 6, z : z + 6] for x, y, z in product((0, 4, 8), repeat=3)])
    got = rp.repair_padded(blocks, 1.0, (0.3, 0.2, 0.1), 4)
    assert np.allclose(got, np.stack([want[x : x + 4, y : y + 4, z : z + 4] for x, y, z in product((0, 4, 8), repeat=3)]))


def test_levels_by_histogram_are_exact_under_ties(spark):
    ranges = spark.createDataFrame([(i, int(v)) for i, v in enumerate(RNG.integers(0, 5, 300))], "key long, rng long")
    for shares in ([50, 50], [15, 31, 54], [1, 98, 1], [100, 0], [0, 100]):
        want = {(r.key, r.level) for r in h.level_of_rank(ranges, shares).collect()}
        for buckets in (1, 3, 4096):
            assert {(r.key, r.level) for r in h.level_of_rank_scalable(ranges, shares, buckets).collect()} == want
    assert h.level_of_rank_scalable(ranges.limit(0), [50, 50]).count() == 0


def test_tiled_filters_equal_whole_ones(spark):
    from fieldmr import filters as fi

    a = RNG.normal(size=(12, 12, 12))
    field = cells(spark, a)
    kappa = fi.mean_step(field)
    assert kappa == pytest.approx(np.mean([np.abs(np.diff(a, axis=k)).mean() for k in range(3)]))
    for name, work in fi.FILTERS.items():
        run = (lambda x: fi.diffusion(x, kappa=kappa)) if name == "diffusion" else work
        got = np.empty_like(a)
        for r in fi.tiled(field, 12, run, fi.REACH[name], 5).collect():
            got[r.x, r.y, r.z] = r.v
        assert np.allclose(got, run(a)), name


def test_spectrum_of_a_mesh_is_that_of_its_flat_form(spark):
    field = fl.analytic(spark, 16, "wave")
    table = en.field_chunks(field, 16, 8, percent=50)
    from fieldmr.queries.workloads import table_cells

    flat = h.flatten_nearest(table_cells(table, 16, 8)).drop("level")
    want = {r.k: r.p for r in me.power_spectrum(flat, 16, kmax=4).collect()}
    blocks = en.decode(en.encode(table, mrinterp(1e-9), 8, 2, 2))
    got = {r.k: r.p for r in me.power_spectrum_blocks(blocks, 16, 2, 2, kmax=4).collect()}
    assert got == pytest.approx(want, rel=1e-4)


def test_surface_parts(spark):
    grid = lambda rows: spark.createDataFrame(rows, "x int, y int, z int")
    bar = [(0, 0, k) for k in range(5)]
    orig, deco = grid([*bar, (4, 4, 4), (6, 6, 6)]), grid([r for r in bar if r[2] != 2] + [(6, 6, 6)])
    got = {(r.cells, r.kept, r.pieces, r.found, r.state) for r in un.surface_parts(orig, deco, grid([(4, 4, 4), (0, 0, 2)]), 8).collect()}
    assert got == {(5, 4, 2, 1, "cracked"), (1, 0, 0, 1, "vanished"), (1, 1, 1, 0, "whole")}


def test_draws_do_not_depend_on_partitions(spark):
    field = fl.analytic(spark, 8, "wave")
    runs = [sorted(tuple(r) for r in un.mc_cells(field.repartition(n), 0.0, 0.05, 0.4, 64).collect()) for n in (1, 5)]
    assert runs[0] == runs[1] and len(runs[0]) > 0
    exact = {(r.x, r.y, r.z): r.p for r in un.prob_cells(field, 0.0, 0.05, 0.4).collect()}
    assert np.mean([abs(p - exact[x, y, z]) for x, y, z, p in runs[0]]) < 0.05
