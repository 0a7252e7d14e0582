"""Fields, blocks, regions, levels, arrangements, padding, predictors, repair, uncertainty and measures on the tables."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import arrange as ar
from .. import fields as fl
from .. import filters as fi
from .. import grid as gr
from .. import hierarchy as h
from .. import metrics as me
from .. import repair as rp
from .. import uncert as un
from ..codec.interp import interp_plan, top_stride
from ..codec.schedule import eb_schedule
from ..registry import Registry
from ..sources import table
from ..tables import kept
from .sqltext import DUAL, G, HALO, RANGES, SAMPLE, ZEROS

core = Registry()
query = core.query


def halo(spark: SparkSession, sf: str) -> tuple[DataFrame, int]:
    g = fl.grid_edge(spark, sf)
    return fl.halo_density(spark, sf, g), g


def ranges(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame, int]:
    cells, g = halo(spark, sf)
    return cells, h.block_ranges(cells, 8, g // 8, g // 8), g


def dual(spark: SparkSession, sf: str) -> tuple[DataFrame, int, int]:
    """Density with its prequantised values: (x, y, z, orig, q, deco), the bound and the edge."""
    cells, g = halo(spark, sf)
    lo, hi = cells.agg(F.min("v"), F.max("v")).first()
    eb = max(1, (hi - lo) // 100)
    q = F.floor((F.col("v") + eb) / F.lit(2 * eb)).cast("long")
    return cells.select("x", "y", "z", F.col("v").alias("orig"), q.alias("q"), (q * (2 * eb)).alias("deco")), eb, g


def deco(spark: SparkSession, sf: str) -> tuple[DataFrame, int, int]:
    d, eb, g = dual(spark, sf)
    return d.select("x", "y", "z", F.col("deco").alias("v")), eb, g


def micro(c: Column) -> Column:
    return F.floor(c * 1e6 + 0.5).cast("long")


# fields

core.add("grid_halo_density", lambda s, d: halo(s, d)[0], f"WITH {HALO} SELECT x, y, z, v FROM halo")
core.add(
    "grid_part_lattice",
    lambda s, d: fl.part_lattice(s, d),
    """WITH n AS (SELECT count(*) // 64 AS planes FROM part)
SELECT CAST(p_partkey % 8 AS INTEGER) AS x, CAST(p_partkey // 8 % 8 AS INTEGER) AS y, CAST(p_partkey // 64 AS INTEGER) AS z, CAST(floor(p_retailprice * 100 + 0.5) AS BIGINT) AS v
FROM part, n WHERE p_partkey // 64 < planes""",
)
LEDGER = f"""{G},
summed AS (SELECT l_partkey % g AS x, l_suppkey % g AS y, (year(o_orderdate) * 12 + month(o_orderdate)) % g AS z, CAST(sum(CAST(floor(l_quantity + 0.5) AS BIGINT)) AS BIGINT) AS v
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey, g GROUP BY ALL),
full_ AS (SELECT a.x, b.y, c.z, coalesce(v, 0) AS v FROM g, unnest(range(g)) AS a(x), unnest(range(g)) AS b(y), unnest(range(g)) AS c(z) LEFT JOIN summed s ON s.x = a.x AND s.y = b.y AND s.z = c.z),
sx AS (SELECT x, y, z, sum(v) OVER (PARTITION BY y, z ORDER BY x) AS v FROM full_),
sy AS (SELECT x, y, z, sum(v) OVER (PARTITION BY x, z ORDER BY y) AS v FROM sx),
ledger AS (SELECT CAST(x AS INTEGER) AS x, CAST(y AS INTEGER) AS y, CAST(z AS INTEGER) AS z, CAST(sum(v) OVER (PARTITION BY x, y ORDER BY z) AS BIGINT) AS v FROM sy)"""
core.add("grid_ledger_integral", lambda s, d: fl.ledger_integral(s, d), f"WITH {LEDGER} SELECT x, y, z, v FROM ledger")
core.add(
    "grid_order_density",
    lambda s, d: fl.order_density(s, d),
    """SELECT CAST(o_custkey % 16 AS INTEGER) AS x, c_nationkey AS y, CAST((year(o_orderdate) * 12 + month(o_orderdate)) % 80 AS INTEGER) AS z,
CAST(sum(CAST(floor(o_totalprice * 100 + 0.5) AS BIGINT)) AS BIGINT) AS v, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL""",
)
CUBE = """types AS (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS y FROM (SELECT DISTINCT event_type FROM events)),
first_ AS (SELECT date_trunc('day', min(ts)) AS t FROM events),
cube_ AS (SELECT CAST(user_id % 16 AS INTEGER) AS x, CAST(y AS INTEGER) AS y, CAST(floor((epoch_us(ts) // 1000000 - epoch_us(t) // 1000000) / 3600) AS INTEGER) AS z,
  CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT) AS v FROM events JOIN types USING (event_type), first_ GROUP BY ALL)"""
core.add("grid_event_cube", lambda s, d: fl.event_cube(s, d), f"WITH {CUBE} SELECT x, y, z, v FROM cube_")
core.add("grid_embedding_cubes", lambda s, d: fl.embedding_cubes(s, d), "SELECT vec_id, label, CAST(i - 1 AS INTEGER) AS off, embedding[i] AS v FROM embeddings, unnest(range(1, len(embedding) + 1)) AS t(i)")
core.add(
    "grid_text_profile",
    lambda s, d: fl.text_profile(s, d),
    "SELECT lang, source, CAST(row_number() OVER (PARTITION BY lang, source ORDER BY doc_id) - 1 AS INTEGER) AS rank, n_chars AS v, coalesce(quality, -1) AS quality FROM documents LEFT JOIN labels USING (doc_id)",
)
core.add(
    "grid_page_profile",
    lambda s, d: fl.page_profile(s, d),
    """SELECT axis, CAST(sum(size) AS BIGINT) AS v, count(*) AS n FROM (SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS axis, length(html) AS size FROM pages
UNION ALL SELECT role || '/' || turn, length(text) FROM conversations) GROUP BY axis""",
)


def rounded(cells: DataFrame, scale: float) -> DataFrame:
    """Cells with their values as whole numbers of 1 / ``scale``."""
    return cells.select("x", "y", "z", F.floor(F.col("v") * scale + 0.5).cast("long").alias("v"))


_AT = "CAST(x AS INTEGER) AS x, CAST(y AS INTEGER) AS y, CAST(z AS INTEGER) AS z"
core.add(
    "grid_nation_modes",
    lambda s, d: rounded(fl.nation_modes(s, d), 1e3),
    f"""WITH {G}, {ZEROS}, amp AS (SELECT c_nationkey AS k, avg(c_acctbal) AS b FROM customer GROUP BY 1),
m AS (SELECT n_nationkey % 3 + 1 AS kx, n_nationkey % 4 AS ky, n_nationkey % 5 AS kz, n_nationkey * 0.7::DOUBLE AS shift, coalesce(b, 1000.0::DOUBLE) / (1 + n_nationkey % 7) AS amp FROM nation JOIN region ON n_regionkey = r_regionkey LEFT JOIN amp ON k = n_nationkey)
SELECT {_AT}, CAST(floor(sum(amp * sin(6.283185307179586::DOUBLE / g * (kx * x + ky * y + kz * z) + shift)) * 1e3 + 0.5) AS BIGINT) AS v FROM zeros, m, g GROUP BY x, y, z, g""",
)
core.add(
    "grid_mixing_layer",
    lambda s, d: rounded(fl.mixing_layer(s, d), 1e6),
    f"""WITH {G}, {ZEROS}, m AS (SELECT s_nationkey % 4 + 1 AS kx, s_nationkey % 3 + 1 AS ky, s_nationkey * 1.3::DOUBLE AS shift, avg(s_acctbal) / 250000.0::DOUBLE AS amp FROM supplier GROUP BY s_nationkey),
h AS (SELECT a.x, b.y, sum(amp * sin(6.283185307179586::DOUBLE / g * (kx * a.x + ky * b.y) + shift)) + 0.5 AS h FROM g, m, unnest(range(g)) AS a(x), unnest(range(g)) AS b(y) GROUP BY a.x, b.y)
SELECT {_AT}, CAST(floor(tanh((z / g::DOUBLE - h) / 0.08::DOUBLE) * 1e6 + 0.5) AS BIGINT) AS v FROM zeros JOIN h USING (x, y), g""",
)
core.add(
    "grid_analytic",
    lambda s, d: rounded(fl.analytic(s, fl.grid_edge(s, d)), 1e6),
    f"""WITH {G}, {ZEROS}, u AS (SELECT x, y, z, x / g::DOUBLE AS a, y / g::DOUBLE AS b, z / g::DOUBLE AS c FROM zeros, g)
SELECT {_AT}, CAST(floor((exp(-20 * ((a - 0.5) * (a - 0.5) + (b - 0.4) * (b - 0.4) + (c - 0.6) * (c - 0.6))) + 0.5 * exp(-60 * ((a - 0.2) * (a - 0.2) + (b - 0.7) * (b - 0.7) + (c - 0.3) * (c - 0.3)))) * 1e6 + 0.5) AS BIGINT) AS v FROM u""",
)
core.add(
    "grid_halo_all_events",
    lambda s, d: fl.event_density(s, d),
    f"""WITH {G}, {ZEROS}, hashed AS (SELECT (event_id * 2654435761) % 4294967296 AS h, CAST(floor(value * 100 + 0.5) AS BIGINT) AS m FROM events),
masses AS (SELECT (h // 256) % g AS cx, (h // 65536) % g AS cy, (h // 16777216) % g AS cz, sum(m) AS m FROM hashed, g GROUP BY ALL),
kernel AS (SELECT dx, dy, dz, w * w AS w FROM (SELECT dx, dy, dz, 9 - dx * dx - dy * dy - dz * dz AS w FROM unnest(range(-3, 4)) AS a(dx), unnest(range(-3, 4)) AS b(dy), unnest(range(-3, 4)) AS c(dz)) WHERE w > 0)
SELECT {_AT}, CAST(sum(v) AS BIGINT) AS v FROM (SELECT (cx + dx + g) % g AS x, (cy + dy + g) % g AS y, (cz + dz + g) % g AS z, m * w AS v FROM masses, kernel, g UNION ALL SELECT x, y, z, 0 FROM zeros) GROUP BY x, y, z""",
)

# blocks and keys


@query(f"""WITH {HALO}, o AS (SELECT CAST((x // 8) * (g // 8) * (g // 8) + (y // 8) * (g // 8) + z // 8 AS BIGINT) AS key, (x % 8) * 64 + (y % 8) * 8 + z % 8 AS off, v FROM halo, g)
SELECT key, CAST(count(*) AS INTEGER) AS n, CAST(sum(v * (off + 1)) AS BIGINT) AS weighted, arg_min(v, off) AS first, arg_max(v, off) AS last FROM o GROUP BY key""")
def grid_blocks(s, d):
    cells, g = halo(s, d)
    b = h.to_blocks(cells, 8, g // 8, g // 8)
    weighted = F.aggregate(F.transform("vals", lambda v, i: v.cast("long") * (i + 1)), F.lit(0).cast("long"), lambda a, x: a + x)
    return b.select("key", "n", weighted.alias("weighted"), F.get("vals", F.lit(0)).cast("long").alias("first"), F.element_at("vals", -1).cast("long").alias("last"))


core.add("grid_block_range", lambda s, d: ranges(s, d)[1].select("key", "lo", "hi", "rng", "total", "n"), f"WITH {HALO}, {RANGES} SELECT key, lo, hi, rng, total, n FROM ranked")
_SPREAD = "list_sum([((({c} >> k) & 1) << (3 * k + {a})) FOR k IN range(10)])"
_MORTON = " + ".join(_SPREAD.format(c=c, a=a) for a, c in enumerate("xyz"))
core.add("grid_morton", lambda s, d: halo(s, d)[0].select("x", "y", "z", gr.morton(*map(F.col, "xyz")).alias("code")), f"WITH {HALO} SELECT x, y, z, CAST({_MORTON} AS BIGINT) AS code FROM halo")
core.add(
    "grid_hz_key",
    lambda s, d: ar.hzline_key(halo(s, d)[0], 4).select("x", "y", "z", "hlevel", F.col("zkey").alias("code")),
    f"WITH {HALO} SELECT x, y, z, CAST(CASE WHEN (x | y | z) % 2 <> 0 THEN 0 WHEN (x | y | z) % 4 <> 0 THEN 1 WHEN (x | y | z) % 8 <> 0 THEN 2 WHEN (x | y | z) % 16 <> 0 THEN 3 ELSE 4 END AS INTEGER) AS hlevel, CAST({_MORTON} AS BIGINT) AS code FROM halo",
)
core.add(
    "grid_neighbours",
    lambda s, d: (lambda c, r, g: gr.neighbour_keys(r, g // 8, g // 8, g // 8))(*ranges(s, d)),
    f"""WITH {HALO}, {RANGES}, nb AS (SELECT g // 8 AS m FROM g), pl AS (SELECT key, key // (m * m) AS a, key // m % m AS b, key % m AS c, m AS n FROM rng, nb)
SELECT key, axis, CAST(side AS INTEGER) AS side, CAST(other AS BIGINT) AS other FROM (
SELECT key, 'x' AS axis, s AS side, key + s * n * n AS other FROM pl, unnest([-1, 1]) AS t(s) WHERE a + s BETWEEN 0 AND n - 1
UNION ALL SELECT key, 'y', s, key + s * n FROM pl, unnest([-1, 1]) AS t(s) WHERE b + s BETWEEN 0 AND n - 1
UNION ALL SELECT key, 'z', s, key + s FROM pl, unnest([-1, 1]) AS t(s) WHERE c + s BETWEEN 0 AND n - 1)""",
)

# regions

_TOP = f"WITH {HALO}, {RANGES} SELECT key, rng FROM ranked WHERE place <= ceil(n_all * 15 / 100)"
core.add("roi_top_percent", lambda s, d: h.roi_top(ranges(s, d)[1], 15).select("key", "rng"), _TOP)
core.add("roi_top_percent_scalable", lambda s, d: h.roi_top_scalable(ranges(s, d)[1], 15), _TOP)


def _mean_rng(r: DataFrame) -> int:
    n, t = r.agg(F.count("*"), F.sum("rng")).first()
    return t // n


@query(f"WITH {HALO}, {RANGES} SELECT key, rng FROM ranked WHERE rng >= (SELECT CAST(sum(rng) AS BIGINT) // count(*) FROM ranked)")
def roi_threshold(s, d):
    r = ranges(s, d)[1]
    return h.roi_threshold(r, _mean_rng(r))


@query(f"WITH {HALO}, {RANGES}, m AS (SELECT CAST(sum(v) AS BIGINT) // count(*) AS m FROM halo) SELECT key, total, n FROM ranked, m WHERE total > m * n")
def roi_mean_refine(s, d):
    cells, r, _ = ranges(s, d)
    n, t = cells.agg(F.count("*"), F.sum("v")).first()
    return h.refine_by_mean(r, t // n)


@query(f"WITH {HALO}, {RANGES} SELECT key, rng FROM ranked WHERE key IN (SELECT doc_id % n_all FROM labels, (SELECT count(*) AS n_all FROM rng) WHERE quality = 0)")
def roi_label_mask(s, d):
    _, r, g = ranges(s, d)
    mask = table(s, d, "labels").where("quality = 0").select((F.col("doc_id") % (g // 8) ** 3).alias("key"))
    return h.roi_mask(r, mask)


@query(f"""WITH {HALO}, {RANGES}, top AS (SELECT key FROM ranked WHERE place <= ceil(n_all * 15 / 100)), high AS (SELECT CAST(max(v) AS BIGINT) // 4 AS least FROM halo),
k AS (SELECT CAST((x // 8) * (g // 8) * (g // 8) + (y // 8) * (g // 8) + z // 8 AS BIGINT) AS key, v FROM halo, g)
SELECT count(*) FILTER (v >= least) AS high, count(*) FILTER (v >= least AND key IN (SELECT key FROM top)) AS high_inside, CAST(sum(v) AS BIGINT) AS mass,
CAST(coalesce(sum(v) FILTER (key IN (SELECT key FROM top)), 0) AS BIGINT) AS mass_inside FROM k, high""")
def metric_roi_capture(s, d):
    cells, r, g = ranges(s, d)
    least = cells.agg(F.max("v")).first()[0] // 4
    return me.roi_capture(cells, h.roi_top_scalable(r, 15), gr.block_key(8, g // 8, g // 8), least)


# levels

core.add(
    "level_coarsen_mean",
    lambda s, d: h.coarsen(halo(s, d)[0], 2, "mean", exact=True),
    f"WITH {HALO} SELECT x // 2 AS x, y // 2 AS y, z // 2 AS z, CAST(sum(v) AS BIGINT) AS v, count(*) AS n FROM halo GROUP BY ALL",
)
core.add("level_coarsen_inject", lambda s, d: h.coarsen(halo(s, d)[0], 2, "inject"), f"WITH {HALO} SELECT x // 2 AS x, y // 2 AS y, z // 2 AS z, v FROM halo WHERE x % 2 = 0 AND y % 2 = 0 AND z % 2 = 0")
core.add("level_coarsen_max", lambda s, d: h.coarsen(halo(s, d)[0], 2, "max"), f"WITH {HALO} SELECT x // 2 AS x, y // 2 AS y, z // 2 AS z, max(v) AS v FROM halo GROUP BY ALL")
_THREE = "lv AS (SELECT key, CAST(CASE WHEN place <= ceil(n_all * 15 / 100) THEN 0 WHEN place <= ceil(n_all * 46 / 100) THEN 1 ELSE 2 END AS INTEGER) AS level FROM ranked)"
core.add("level_three_shares", lambda s, d: h.level_of_rank(ranges(s, d)[1], [15, 31, 54]), f"WITH {HALO}, {RANGES}, {_THREE} SELECT key, level FROM lv")
core.add("level_three_shares_scalable", lambda s, d: h.level_of_rank_scalable(kept(ranges(s, d)[1], "ranges"), [15, 31, 54]), core.sql["level_three_shares"])


def three_levels(s, d):
    cells, r, g = ranges(s, d)
    return h.build_levels(cells, h.level_of_rank(r, [15, 31, 54]), 8, g // 8, g // 8), g


_BUILT = f"""{HALO}, {RANGES}, {_THREE},
built AS (SELECT level, CAST(x // (1 << level) AS INTEGER) AS x, CAST(y // (1 << level) AS INTEGER) AS y, CAST(z // (1 << level) AS INTEGER) AS z, CAST(sum(v) AS BIGINT) AS v, count(*) AS n
  FROM halo, g, lv WHERE key = (x // 8) * (g // 8) * (g // 8) + (y // 8) * (g // 8) + z // 8 GROUP BY ALL)"""
core.add("level_build", lambda s, d: three_levels(s, d)[0], f"WITH {_BUILT} SELECT level, x, y, z, v, n FROM built")


@query(f"""WITH {HALO}, {RANGES}, top AS (SELECT key FROM ranked WHERE place <= ceil(n_all * 50 / 100)),
k AS (SELECT x, y, z, v, (x // 8) * (g // 8) * (g // 8) + (y // 8) * (g // 8) + z // 8 AS key FROM halo, g)
SELECT 0 AS level, x, y, z, v FROM k SEMI JOIN top USING (key) UNION ALL SELECT 1, x // 2, y // 2, z // 2, CAST(sum(v) AS BIGINT) FROM k ANTI JOIN top USING (key) GROUP BY ALL""")
def level_adaptive(s, d):
    cells, r, g = ranges(s, d)
    return h.split_levels(cells, h.roi_top_scalable(r, 50), 8, g // 8, g // 8, exact=True)


core.add(
    "level_flatten_nearest",
    lambda s, d: h.flatten_nearest(three_levels(s, d)[0]),
    f"""WITH {_BUILT} SELECT level, CAST(x * (1 << level) + a.i AS INTEGER) AS x, CAST(y * (1 << level) + b.i AS INTEGER) AS y, CAST(z * (1 << level) + c.i AS INTEGER) AS z, v
FROM built, unnest(range(1 << level)) AS a(i), unnest(range(1 << level)) AS b(i), unnest(range(1 << level)) AS c(i)""",
)
_TRI = []
for _a, _o in (("x", "y, z"), ("y", "x, z"), ("z", "x, y")):
    _from = "c0" if _a == "x" else f"t{ {'y': 'x', 'z': 'y'}[_a]}".replace(" ", "")
    _cols = ", ".join(f"2 * {c} + h AS {c}" if c == _a else c for c in "xyz")
    _TRI.append(
        f"t{_a} AS (SELECT {_cols}, 3 * v + CASE h WHEN 0 THEN lo ELSE hi END AS v FROM (SELECT *, coalesce(lag(v) OVER w, v) AS lo, coalesce(lead(v) OVER w, v) AS hi FROM {_from} WINDOW w AS (PARTITION BY {_o} ORDER BY {_a})), unnest([0, 1]) AS u(h))"
    )
core.add(
    "level_flatten_trilinear",
    lambda s, d: (lambda c: h.flatten_trilinear(h.coarsen(c[0], 2, "inject"), c[1]))(halo(s, d)),
    f"WITH {HALO}, c0 AS (SELECT x // 2 AS x, y // 2 AS y, z // 2 AS z, v FROM halo WHERE x % 2 = 0 AND y % 2 = 0 AND z % 2 = 0), {', '.join(_TRI)} SELECT CAST(x AS INTEGER) AS x, CAST(y AS INTEGER) AS y, CAST(z AS INTEGER) AS z, CAST(v AS BIGINT) AS v FROM tz",
)
_COVER = f"""WITH {_BUILT}, flat AS (SELECT x * (1 << level) + a.i AS x, y * (1 << level) + b.i AS y, z * (1 << level) + c.i AS z
FROM built, unnest(range(1 << level)) AS a(i), unnest(range(1 << level)) AS b(i), unnest(range(1 << level)) AS c(i))"""
core.add(
    "level_cover_gaps",
    lambda s, d: (lambda lv, g: h.cover(lv).agg(F.count("*").alias("covered"), F.count_if(F.col("times") > 1).alias("overlaps")).withColumn("gaps", F.lit(g**3).cast("long") - F.col("covered")))(*three_levels(s, d)),
    f"{_COVER} SELECT count(*) AS covered, count(*) FILTER (t > 1) AS overlaps, (SELECT CAST(g * g * g AS BIGINT) FROM g) - count(*) AS gaps FROM (SELECT count(*) AS t FROM flat GROUP BY x, y, z)",
)


@query(f"{_COVER} SELECT count(*) AS shared FROM (SELECT DISTINCT x, y, z FROM flat WHERE x < 0)")
def level_overlap(s, d):
    flat = h.flatten_nearest(three_levels(s, d)[0])
    fine, rest = (flat.where(c).select("x", "y", "z") for c in ("level = 0", "level > 0"))
    return fine.intersect(rest).agg(F.count("*").alias("shared"))


core.add(
    "level_density",
    lambda s, d: (lambda lv, g: h.level_density(lv, g**3))(*three_levels(s, d)),
    f"WITH {_BUILT} SELECT level, count(*) AS stored, CAST(count(*) * (1 << (3 * level)) AS BIGINT) AS covered, (SELECT CAST(g * g * g AS BIGINT) FROM g) AS points FROM built GROUP BY level",
)
core.add(
    "metric_hierarchy_ratio",
    lambda s, d: (lambda lv, g: lv.agg(F.count("*").alias("stored"), F.lit(g**3).cast("long").alias("points")).withColumn("ratio", F.col("stored") / F.col("points")))(*three_levels(s, d)),
    f"WITH {_BUILT} SELECT count(*) AS stored, (SELECT CAST(g * g * g AS BIGINT) FROM g) AS points, count(*) / (SELECT CAST(g * g * g AS DOUBLE) FROM g) AS ratio FROM built",
)

# arrangements

_FINE = f"{HALO}, {RANGES}, top AS (SELECT key, row_number() OVER (ORDER BY key) - 1 AS o, count(*) OVER () AS m FROM ranked WHERE place <= ceil(n_all * 50 / 100))"


def fine_blocks(s, d):
    _, r, g = ranges(s, d)
    return h.roi_top_scalable(r, 50).select(F.lit(0).alias("level"), "key"), g


core.add(
    "arrange_linear",
    lambda s, d: ar.arrange_linear(fine_blocks(s, d)[0], ["level"], 16).select("key", "slab", "position"),
    f"WITH {_FINE} SELECT key, CAST(o // 16 AS BIGINT) AS slab, CAST(o % 16 AS INTEGER) AS position FROM top",
)
core.add(
    "arrange_stack",
    lambda s, d: ar.arrange_stack(fine_blocks(s, d)[0], ["level"]).select("key", "px", "py", "pz", "side"),
    f"WITH {_FINE}, sd AS (SELECT min(c) AS c FROM unnest(range(1, 2000)) AS t(c) WHERE c * c * c >= (SELECT max(m) FROM top)) SELECT key, CAST(o // (c * c) AS BIGINT) AS px, CAST(o // c % c AS BIGINT) AS py, CAST(o % c AS BIGINT) AS pz, CAST(c AS BIGINT) AS side FROM top, sd",
)
_ZAT = _MORTON.replace("(x >>", "((x * (1 << level)) >>").replace("(y >>", "((y * (1 << level)) >>").replace("(z >>", "((z * (1 << level)) >>")
core.add("arrange_zline", lambda s, d: ar.zline_key(three_levels(s, d)[0]).select("level", "x", "y", "z", F.col("zkey").alias("code")), f"WITH {_BUILT} SELECT level, x, y, z, CAST({_ZAT} AS BIGINT) AS code FROM built")
core.add("arrange_kd", lambda s, d: (lambda b, g: ar.arrange_kd(b, ["level"], g // 8, g // 8))(*fine_blocks(s, d)))


def _layers(cells: DataFrame, g: int) -> DataFrame:
    n = g // 8
    return cells.groupBy(gr.block_key(8, n, n).alias("key")).agg(F.sum(F.when(F.col("z") % 8 == 0, F.col("v")).otherwise(0)).alias("first"), F.sum(F.when(F.col("z") % 8 == 7, F.col("v")).otherwise(0)).alias("last"))


def _roughness(s, d):
    cells, r, g = ranges(s, d)
    blocks = h.roi_top_scalable(r, 50).select(F.lit(0).alias("level"), "key")
    return ar.roughness(ar.arrange_linear(blocks, ["level"], 16), _layers(cells, g), g // 8)


core.add(
    "arrange_roughness",
    _roughness,
    f"""WITH {_FINE}, ly AS (SELECT (x // 8) * (g // 8) * (g // 8) + (y // 8) * (g // 8) + z // 8 AS key, sum(CASE WHEN z % 8 = 0 THEN v ELSE 0 END) AS f, sum(CASE WHEN z % 8 = 7 THEN v ELSE 0 END) AS l FROM halo, g GROUP BY ALL),
p AS (SELECT key, f, lag(key) OVER w AS pk, lag(l) OVER w AS pl FROM top JOIN ly USING (key) WINDOW w AS (PARTITION BY o // 16 ORDER BY o))
SELECT count(*) AS faces, count(*) FILTER (NOT near) AS apart, CAST(coalesce(sum(abs(f - pl)) FILTER (NOT near), 0) AS BIGINT) AS jump FROM (SELECT *, key = pk + 1 AND key % (g // 8) <> 0 AS near FROM p, g WHERE pk IS NOT NULL)""",
)

# padding, plans, schedules, one-dimensional codes


def pad_cells(cells: DataFrame, u: int, how: str, gate: int = 4) -> DataFrame:
    """The lattice with one more layer on x, then on y, as sums over each line's last cells."""
    if u <= gate:
        return cells
    weights = {"constant": {1: 1}, "linear": {1: 2, 2: -1}, "quadratic": {1: 3, 2: -3, 3: 1}}[how]
    for axis in "xy":
        others = [c for c in "xyz" if c != axis]
        weight = F.lit(0)
        for back, w in weights.items():
            weight = F.when(F.col(axis) == u - back, F.lit(w)).otherwise(weight)
        layer = cells.where(F.col(axis) >= u - 3).groupBy(*others).agg(F.sum(weight * F.col("v")).alias("v")).withColumn(axis, F.lit(u))
        cells = cells.unionByName(layer.select("x", "y", "z", "v"))
    return cells


_LATTICE = """n AS (SELECT count(*) // 64 AS planes FROM part), lat AS (SELECT CAST(p_partkey % 8 AS INTEGER) AS x, CAST(p_partkey // 8 % 8 AS INTEGER) AS y, CAST(p_partkey // 64 AS INTEGER) AS z,
CAST(floor(p_retailprice * 100 + 0.5) AS BIGINT) AS v FROM part, n WHERE p_partkey // 64 < planes)"""
_PAD = {"constant": "a", "linear": "2 * a - b", "quadratic": "3 * a - 3 * b + c"}
for _how, _expr in _PAD.items():
    core.add(
        f"pad_{_how}",
        lambda s, d, how=_how: pad_cells(fl.part_lattice(s, d), 8, how),
        f"""WITH {_LATTICE}, px AS (SELECT * FROM lat UNION ALL SELECT 8, y, z, {_expr} FROM (SELECT y, z, max(v) FILTER (x = 7) AS a, max(v) FILTER (x = 6) AS b, max(v) FILTER (x = 5) AS c FROM lat GROUP BY y, z)),
py AS (SELECT * FROM px UNION ALL SELECT x, 8, z, {_expr} FROM (SELECT x, z, max(v) FILTER (y = 7) AS a, max(v) FILTER (y = 6) AS b, max(v) FILTER (y = 5) AS c FROM px GROUP BY x, z)) SELECT x, y, z, CAST(v AS BIGINT) AS v FROM py""",
    )
core.add("pad_gate", lambda s, d: pad_cells(fl.part_lattice(s, d, 4), 4, "linear").agg(F.count("*").alias("cells")), "SELECT count(*) // 16 * 16 AS cells FROM part")
core.add(
    "pad_overhead",
    lambda s, d: s.createDataFrame([(4,), (8,), (16,), (32,)], "u int").select("u", h.pad_overhead(F.col("u")).alias("overhead")),
    "SELECT u, (u + 1) * (u + 1) / (u * u) - 1 AS overhead FROM unnest([4, 8, 16, 32]) AS t(u)",
)

_LENGTHS = (4, 5, 8, 9, 16, 17, 32, 33)


def plan_table(s: SparkSession) -> DataFrame:
    rows = [(n, level, at, -1 if lo is None else lo, -1 if hi is None else hi, kind) for n in _LENGTHS for level, at, lo, hi, kind in interp_plan(n)]
    return s.createDataFrame(rows, "n int, level int, idx int, lo int, hi int, kind string")


_PLAN = """lens AS (SELECT unnest([4, 5, 8, 9, 16, 17, 32, 33]) AS n),
st AS (SELECT n, k, (SELECT max(j) FROM unnest(range(10)) AS u(j) WHERE (1 << j) < n - 1) AS top FROM lens, unnest(range(10)) AS t(k) WHERE (1 << k) < n - 1),
plan AS (SELECT n, 0 AS level, 0 AS idx, NULL::INTEGER AS lo, NULL::INTEGER AS hi, 'first' AS kind FROM lens UNION ALL SELECT n, 1, n - 1, 0, NULL, 'last' FROM lens
UNION ALL SELECT n, 2 + top - k, i, i - (1 << k), CASE WHEN i + (1 << k) < n THEN i + (1 << k) END, CASE WHEN i + (1 << k) < n THEN 'interpolated' ELSE 'extrapolated' END
FROM st, unnest(range(1 << k, n - 1, 2 << k)) AS t(i))"""


def event_lines(s: SparkSession, d: str) -> DataFrame:
    """Users' series of events as lines of the codec: user, number of points, and a bound of a hundredth of the line's range in cents."""
    cents = fl.cents("value")
    eb = F.greatest(F.lit(1).cast("long"), F.expr("(hi - lo) div 100"))
    lines = table(s, d, "events").where("user_id is not null").groupBy(F.col("user_id").alias("line")).agg(F.count("*").alias("n"), F.min(cents).alias("lo"), F.max(cents).alias("hi"))
    return lines.select("line", "n", F.coalesce(eb, F.lit(1)).alias("eb"))


def _per_line(lines: DataFrame, one, names: list[str], fields: str) -> DataFrame:
    """Rows that ``one`` makes of a line's points and bound, beside the line and its points; made in tasks."""

    def run(batches):
        for batch in batches:
            for line, n, eb in zip(*(batch.column(c).to_pylist() for c in range(3)), strict=True):
                rows = one(n, eb)
                if rows:
                    columns = [pa.array([v] * len(rows), pa.int64()) for v in (line, n)] + list(map(pa.array, zip(*rows, strict=True)))
                    yield pa.RecordBatch.from_arrays(columns, names=["line", "n", *names])

    return lines.select("line", "n", "eb").mapInArrow(run, f"line long, n long, {fields}")


def line_plans(s: SparkSession, d: str) -> DataFrame:
    """The plan of every line, one row per point."""

    def plan(n, _):
        return [(level, at, -1 if lo is None else lo, -1 if hi is None else hi, kind) for level, at, lo, hi, kind in interp_plan(n)]

    return _per_line(event_lines(s, d), plan, ["level", "idx", "lo", "hi", "kind"], "level long, idx long, lo long, hi long, kind string")


_LINES = """lines AS (SELECT user_id AS line, count(*) AS n, coalesce(greatest(1, (max(CAST(floor(value * 100 + 0.5) AS BIGINT)) - min(CAST(floor(value * 100 + 0.5) AS BIGINT))) // 100), 1) AS eb
FROM events WHERE user_id IS NOT NULL GROUP BY user_id)"""
_LINE_PLANS = f"""{_LINES}, st AS (SELECT line, n, k, max(k) OVER (PARTITION BY line) AS top FROM lines, unnest(range(40)) AS t(k) WHERE (1::BIGINT << k) < n - 1),
plan AS (SELECT line, n, 0 AS level, 0 AS idx, NULL::BIGINT AS lo, NULL::BIGINT AS hi, 'first' AS kind FROM lines UNION ALL SELECT line, n, 1, n - 1, 0, NULL, 'last' FROM lines WHERE n > 1
UNION ALL SELECT line, n, 2 + top - k, i, i - (1::BIGINT << k), CASE WHEN i + (1::BIGINT << k) < n THEN i + (1::BIGINT << k) END, CASE WHEN i + (1::BIGINT << k) < n THEN 'interpolated' ELSE 'extrapolated' END
FROM st, unnest(range(1::BIGINT << k, n - 1, 2::BIGINT << k)) AS t(i))"""
core.add("interp_plan_n", line_plans, f"WITH {_LINE_PLANS} SELECT line, n, CAST(level AS BIGINT) AS level, CAST(idx AS BIGINT) AS idx, coalesce(lo, -1) AS lo, coalesce(hi, -1) AS hi, kind FROM plan")
_COUNTS = "count(*) FILTER (kind IN ('interpolated', 'extrapolated')) AS inner_points, count(*) FILTER (kind = 'extrapolated') AS extrapolated"
core.add(
    "interp_extrapolated_count",
    lambda s, d: line_plans(s, d).groupBy("n").agg(F.count_if(F.col("kind").isin("interpolated", "extrapolated")).alias("inner_points"), F.count_if(F.col("kind") == "extrapolated").alias("extrapolated")),
    f"WITH {_LINE_PLANS} SELECT n, {_COUNTS} FROM plan GROUP BY n",
)


def line_bounds(s: SparkSession, d: str, kind: str) -> DataFrame:
    """The bound of every level of every line, from the coarsest to the finest."""

    def bounds(n, eb):
        return [(level, float(e)) for level, e in enumerate(eb_schedule(top_stride(n), float(eb), kind=kind))]

    return _per_line(event_lines(s, d), bounds, ["level", "eb"], "level long, eb double").select("line", "level", micro(F.col("eb")).alias("micro"))


_LEVELS = f"""{_LINES}, tops AS (SELECT line, eb, CASE WHEN n = 2 THEN 0 ELSE (SELECT max(k) FROM unnest(range(40)) AS t(k) WHERE (1::BIGINT << k) < n - 1) END AS top FROM lines WHERE n > 1),
lv AS (SELECT line, level, top, eb::DOUBLE AS eb FROM tops, unnest(range(top + 1)) AS t(level))"""
for _kind, _sql in (("paper", "eb / least(2.25 ** (top - level), 8.0)"), ("flat", "eb"), ("coarse", "CASE WHEN 2 * level < top THEN eb / 2 ELSE eb END")):
    core.add(f"interp_schedule_{_kind}", lambda s, d, kind=_kind: line_bounds(s, d, kind), f"WITH {_LEVELS} SELECT line, level, CAST(floor(({_sql}) * 1e6 + 0.5) AS BIGINT) AS micro FROM lv")

_STEPS8 = ((7, 0, None, 4), (4, 0, None, 3), (2, 0, 4, 2), (6, 4, None, 2), (1, 0, 2, 1), (3, 2, 4, 1), (5, 4, 6, 1))
_STEPS9 = ((8, 0, None, 4), (4, 0, 8, 3), (2, 0, 4, 2), (6, 4, 8, 2), (1, 0, 2, 1), (3, 2, 4, 1), (5, 4, 6, 1), (7, 6, 8, 1))
_EB1D = 40


def _line_codes(s, d, padded: bool, adaptive: bool) -> DataFrame:
    """Closed-loop codes of lines of the lattice, one column per point, in whole numbers."""
    lines = fl.part_lattice(s, d).groupBy("y", "z").pivot("x", list(range(8))).agg(F.max("v"))
    lines = lines.select("y", "z", *(F.col(str(i)).alias(f"v{i}") for i in range(8)))
    if padded:
        lines = lines.withColumn("v8", 2 * F.col("v7") - F.col("v6"))
    bound = lambda k: int(_EB1D / min(2.25**k, 8.0)) if adaptive else _EB1D
    names = []

    def code(df: DataFrame, i: int, pred: Column, e: int) -> DataFrame:
        q = F.floor((F.col(f"v{i}") - pred + e) / F.lit(2 * e)).cast("long")
        names.append(i)
        return df.withColumn(f"q{i}", q).withColumn(f"r{i}", pred + F.col(f"q{i}") * (2 * e))

    out = code(lines, 0, F.lit(0).cast("long"), bound(4))
    for i, left, right, k in _STEPS9 if padded else _STEPS8:
        pred = F.col(f"r{left}") if right is None else F.floor((F.col(f"r{left}") + F.col(f"r{right}")) / 2).cast("long")
        out = code(out, i, pred, bound(k - 1 if k < 4 else 4))
    rows = F.array(*(F.struct(F.lit(i).alias("idx"), F.col(f"q{i}").alias("code"), F.col(f"r{i}").alias("recon")) for i in sorted(names)))
    return out.select("y", "z", F.inline(rows))


def _line_sql(padded: bool, adaptive: bool) -> str:
    bound = lambda k: int(_EB1D / min(2.25**k, 8.0)) if adaptive else _EB1D
    steps = ((0, None, None, 5), *(_STEPS9 if padded else _STEPS8))
    base = "l0 AS (SELECT y, z, " + ", ".join(f"max(v) FILTER (x = {i}) AS v{i}" for i in range(8)) + " FROM lat GROUP BY y, z)"
    ctes, last = [base, "l1 AS (SELECT *" + (", 2 * v7 - v6 AS v8" if padded else "") + " FROM l0)"], "l1"
    for n, (i, left, right, k) in enumerate(steps):
        e = bound(4 if k >= 4 else k - 1)
        pred = "0" if left is None else f"r{left}" if right is None else f"CAST(floor((r{left} + r{right}) / 2) AS BIGINT)"
        ctes.append(f"s{n} AS (SELECT *, CAST(floor((v{i} - ({pred}) + {e}) / {2 * e}) AS BIGINT) AS q{i}, ({pred}) + CAST(floor((v{i} - ({pred}) + {e}) / {2 * e}) AS BIGINT) * {2 * e} AS r{i} FROM {last})")
        last = f"s{n}"
    rows = " UNION ALL ".join(f"SELECT y, z, {i} AS idx, q{i} AS code, CAST(r{i} AS BIGINT) AS recon FROM {last}" for i in range(9 if padded else 8))
    return f"WITH {_LATTICE}, {', '.join(ctes)} {rows}"


for _name, _p, _ad in (("interp1d_codes", False, False), ("interp1d_padded_codes", True, False), ("interp1d_adaptive_codes", True, True)):
    core.add(_name, lambda s, d, p=_p, a=_ad: _line_codes(s, d, p, a), _line_sql(_p, _ad))

# block prediction in SQL form


def _axis_diff(cells: DataFrame, axis: str, b: int) -> DataFrame:
    w = Window.partitionBy(*[c for c in "xyz" if c != axis]).orderBy(axis)
    before = F.when(F.col(axis) % b == 0, F.lit(0)).otherwise(F.lag("v").over(w))
    return cells.select("x", "y", "z", (F.col("v") - before).alias("v"))


@query(f"""WITH {HALO}, {DUAL},
dx AS (SELECT x, y, z, q - CASE WHEN x % 4 = 0 THEN 0 ELSE lag(q) OVER (PARTITION BY y, z ORDER BY x) END AS q FROM dual),
dy AS (SELECT x, y, z, q - CASE WHEN y % 4 = 0 THEN 0 ELSE lag(q) OVER (PARTITION BY x, z ORDER BY y) END AS q FROM dx)
SELECT x, y, z, CAST(q - CASE WHEN z % 4 = 0 THEN 0 ELSE lag(q) OVER (PARTITION BY x, y ORDER BY z) END AS BIGINT) AS v FROM dy""")
def bpred_dual_lorenzo(s, d):
    cells = dual(s, d)[0].select("x", "y", "z", F.col("q").alias("v"))
    for axis in "xyz":
        cells = _axis_diff(cells, axis, 4)
    return cells


_SUMS = ", ".join(f"CAST(sum(v * (2 * ({c} % 4) - 3)) AS BIGINT) AS t{c}" for c in "xyz")


def _plane_sums(cells: DataFrame, g: int) -> DataFrame:
    """Sums that give the plane of each cube of 4: slope = t / 160, mean = s / 64."""
    return cells.groupBy(gr.block_key(4, g // 4, g // 4).alias("key")).agg(F.sum("v").alias("s"), *(F.sum(F.col("v") * (2 * (F.col(c) % 4) - 3)).alias(f"t{c}") for c in "xyz"))


_FIT = f"fit AS (SELECT CAST((x // 4) * (g // 4) * (g // 4) + (y // 4) * (g // 4) + z // 4 AS BIGINT) AS key, CAST(sum(v) AS BIGINT) AS s, {_SUMS} FROM halo, g GROUP BY ALL)"
core.add("bpred_regression_fit", lambda s, d: _plane_sums(*halo(s, d)), f"WITH {HALO}, {_FIT} SELECT key, s, tx, ty, tz FROM fit")


@query(f"""WITH {HALO}, {_FIT},
k AS (SELECT *, CAST((x // 4) * (g // 4) * (g // 4) + (y // 4) * (g // 4) + z // 4 AS BIGINT) AS key FROM halo, g),
dx AS (SELECT x, y, z, v - CASE WHEN x % 4 = 0 THEN 0 ELSE lag(v) OVER (PARTITION BY y, z ORDER BY x) END AS v FROM halo),
dy AS (SELECT x, y, z, v - CASE WHEN y % 4 = 0 THEN 0 ELSE lag(v) OVER (PARTITION BY x, z ORDER BY y) END AS v FROM dx),
dz AS (SELECT x, y, z, v - CASE WHEN z % 4 = 0 THEN 0 ELSE lag(v) OVER (PARTITION BY x, y ORDER BY z) END AS lor FROM dy)
SELECT key, CAST(sum(abs(320 * v - 5 * s - tx * (2 * (x % 4) - 3) - ty * (2 * (y % 4) - 3) - tz * (2 * (z % 4) - 3))) AS BIGINT) AS plane, CAST(sum(320 * abs(lor)) AS BIGINT) AS lorenzo,
sum(abs(320 * v - 5 * s - tx * (2 * (x % 4) - 3) - ty * (2 * (y % 4) - 3) - tz * (2 * (z % 4) - 3))) < sum(320 * abs(lor)) AS regression
FROM k JOIN fit USING (key) JOIN dz USING (x, y, z) GROUP BY key""")
def bpred_auto_choice(s, d):
    cells, g = halo(s, d)
    lor = cells
    for axis in "xyz":
        lor = _axis_diff(lor, axis, 4)
    keyed = cells.withColumn("key", gr.block_key(4, g // 4, g // 4)).join(_plane_sums(cells, g), "key").join(lor.withColumnRenamed("v", "lor"), ["x", "y", "z"])
    plane = 320 * F.col("v") - 5 * F.col("s") - sum((F.col(f"t{c}") * (2 * (F.col(c) % 4) - 3) for c in "xyz"), F.lit(0))
    return keyed.groupBy("key").agg(F.sum(F.abs(plane)).alias("plane"), F.sum(320 * F.abs("lor")).alias("lorenzo")).withColumn("regression", F.col("plane") < F.col("lorenzo"))


@query(f"WITH {HALO}, {DUAL}, c AS (SELECT q, count(*) AS n, sum(count(*)) OVER () AS t FROM dual GROUP BY q) SELECT count(*) AS kinds, CAST(floor(sum(-n * log2(n / t)) / any_value(t) * 1e4 + 0.5) AS BIGINT) AS bits_e4 FROM c")
def bpred_entropy(s, d):
    c = dual(s, d)[0].groupBy("q").agg(F.count("*").alias("n"))
    total = c.agg(F.sum("n").alias("t"))
    bits = F.sum(-F.col("n") * F.log2(F.col("n") / F.col("t"))) / F.first("t")
    return c.crossJoin(F.broadcast(total)).agg(F.count("*").alias("kinds"), F.floor(bits * 1e4 + 0.5).cast("long").alias("bits_e4"))


# repair

_START = f"{HALO}, {DUAL}, r0 AS (SELECT x, y, z, CAST(deco AS DOUBLE) AS v FROM dual)"


def _sweep_sql(name: str, source: str, axis: str, limit: str | None, b: int = 4) -> str:
    others = ", ".join(c for c in "xyz" if c != axis)
    m = "(l + 2 * v + r) / 4"
    m = m if limit is None else f"least(greatest({m}, v - {limit}), v + {limit})"
    return (
        f"{name} AS (SELECT x, y, z, CASE WHEN {axis} % {b} IN (0, {b - 1}) AND l IS NOT NULL AND r IS NOT NULL THEN {m} ELSE v END AS v FROM "
        f"(SELECT *, lag(v) OVER w AS l, lead(v) OVER w AS r FROM {source} WINDOW w AS (PARTITION BY {others} ORDER BY {axis})), lim)"
    )


def _repair_sql(limit: str | None) -> str:
    return f"WITH {_START}, {_sweep_sql('rx', 'r0', 'x', limit)}, {_sweep_sql('ry', 'rx', 'y', limit)}, {_sweep_sql('rz', 'ry', 'z', limit)} SELECT x, y, z, v FROM rz"


for _name, _a, _lim in (("repair_unclamped", None, None), ("repair_a1", 1.0, "eb"), ("repair_fixed_a", 0.25, "0.25 * eb")):
    core.add(_name, lambda s, d, a=_a: (lambda c, eb, g: rp.repair_cells(c, eb, None if a is None else (a,) * 3, 4))(*deco(s, d)), _repair_sql(_lim))
core.add(
    "repair_average",
    lambda s, d: (lambda c, eb, g: rp.repair_cells(c, eb, (0.25,) * 3, 4, "average").select("x", "y", "z", F.floor(F.col("v") * 1000 + 0.5).cast("long").alias("v_e3")))(*deco(s, d)),
    f"WITH {_START}, {_sweep_sql('a', 'r0', 'x', '0.25 * eb')}, {_sweep_sql('b', 'r0', 'y', '0.25 * eb')}, {_sweep_sql('c', 'r0', 'z', '0.25 * eb')} SELECT x, y, z, CAST(floor((a.v + b.v + c.v) / 3 * 1000 + 0.5) AS BIGINT) AS v_e3 FROM a JOIN b USING (x, y, z) JOIN c USING (x, y, z)",
)
core.add(
    "repair_midpoint",
    lambda s, d: (lambda c, eb, g: rp.with_neighbours(c, "x").where("l is not null and r is not null").select("x", "y", "z", rp.bezier(F.col("l"), F.col("v"), F.col("r"), 0.5).alias("mid")))(*deco(s, d)),
    f"WITH {_START} SELECT x, y, z, 0.25 * l + 0.5 * v + 0.25 * r AS mid FROM (SELECT *, lag(v) OVER w AS l, lead(v) OVER w AS r FROM r0 WINDOW w AS (PARTITION BY y, z ORDER BY x)) WHERE l IS NOT NULL AND r IS NOT NULL",
)
core.add(
    "repair_missing_neighbour",
    lambda s, d: (lambda c, eb, g: rp.sweep_cells(c.where("x % 5 <> 2"), "x", 4, 0.25 * eb))(*deco(s, d)),
    f"""WITH {HALO}, {DUAL}, r0 AS (SELECT x, y, z, CAST(deco AS DOUBLE) AS v FROM dual WHERE x % 5 <> 2),
n AS (SELECT *, CASE WHEN lag(x) OVER w = x - 1 THEN lag(v) OVER w END AS l, CASE WHEN lead(x) OVER w = x + 1 THEN lead(v) OVER w END AS r FROM r0 WINDOW w AS (PARTITION BY y, z ORDER BY x))
SELECT x, y, z, CASE WHEN x % 4 IN (0, 3) AND l IS NOT NULL AND r IS NOT NULL THEN least(greatest((l + 2 * v + r) / 4, v - 0.25 * eb), v + 0.25 * eb) ELSE v END AS v FROM n, lim""",
)


def cross_level(s, d):
    """Fine cells at the region's edge take a missing neighbour from the coarse cell beside them."""
    cells, r, g = ranges(s, d)
    lv = h.split_levels(cells, h.roi_top_scalable(r, 50), 8, g // 8, g // 8, "inject")
    fine, coarse = lv.where("level = 0").drop("level"), lv.where("level = 1").drop("level")
    near = rp.with_neighbours(fine, "x")
    for side, step in (("l", -1), ("r", 1)):
        at = F.floor((F.col("x") + step) / 2).cast("int")
        c = coarse.select(F.col("x").alias(f"{side}x"), F.col("y").alias(f"{side}y"), F.col("z").alias(f"{side}z"), F.col("v").alias(f"{side}v"))
        near = near.join(c, (at == F.col(f"{side}x")) & (F.floor(F.col("y") / 2) == F.col(f"{side}y")) & (F.floor(F.col("z") / 2) == F.col(f"{side}z")) & F.col(side).isNull(), "left")
    l, r_ = F.coalesce("l", "lv"), F.coalesce("r", "rv")
    mid = (l + 2 * F.col("v") + r_) / 4
    able = rp.is_face("x", 8) & l.isNotNull() & r_.isNotNull()
    return near.select("x", "y", "z", F.when(able, mid).otherwise(F.col("v").cast("double")).alias("v"))


core.add(
    "repair_cross_level",
    cross_level,
    f"""WITH {HALO}, {RANGES}, top AS (SELECT key FROM ranked WHERE place <= ceil(n_all * 50 / 100)), k AS (SELECT x, y, z, v, (x // 8) * (g // 8) * (g // 8) + (y // 8) * (g // 8) + z // 8 AS key FROM halo, g),
fine AS (SELECT x, y, z, v FROM k SEMI JOIN top USING (key)), co AS (SELECT x // 2 AS x, y // 2 AS y, z // 2 AS z, v FROM k ANTI JOIN top USING (key) WHERE x % 2 = 0 AND y % 2 = 0 AND z % 2 = 0),
n AS (SELECT f.x, f.y, f.z, f.v, coalesce(a.v, c.v) AS l, coalesce(b.v, e.v) AS r FROM fine f LEFT JOIN fine a ON a.x = f.x - 1 AND a.y = f.y AND a.z = f.z LEFT JOIN fine b ON b.x = f.x + 1 AND b.y = f.y AND b.z = f.z
LEFT JOIN co c ON c.x = floor((f.x - 1) / 2) AND c.y = f.y // 2 AND c.z = f.z // 2 LEFT JOIN co e ON e.x = (f.x + 1) // 2 AND e.y = f.y // 2 AND e.z = f.z // 2)
SELECT x, y, z, CASE WHEN x % 8 IN (0, 7) AND l IS NOT NULL AND r IS NOT NULL THEN (l + 2 * v + r) / 4 ELSE CAST(v AS DOUBLE) END AS v FROM n""",
)
core.add(
    "repair_situations",
    lambda s, d: rp.situations(dual(s, d)[0], "x", 4).select("kind", "n", (4 * F.col("gain")).cast("long").alias("gain4")),
    f"""WITH {HALO}, {DUAL}, n AS (SELECT orig, deco AS v, lag(deco) OVER w AS l, lead(deco) OVER w AS r, x FROM dual WINDOW w AS (PARTITION BY y, z ORDER BY x)),
m AS (SELECT l + r - 2 * v AS move4, 4 * (orig - v) AS want4 FROM n WHERE x % 4 IN (0, 3) AND l IS NOT NULL AND r IS NOT NULL)
SELECT CASE WHEN move4 = 0 OR want4 = 0 THEN 'still' WHEN sign(move4) <> sign(want4) THEN 'wrong way' WHEN abs(move4) > abs(want4) THEN 'overshoot' ELSE 'between' END AS kind, count(*) AS n,
CAST(sum(abs(want4) - abs(want4 - move4)) AS BIGINT) AS gain4 FROM m GROUP BY kind""",
)


@query(f"""WITH {HALO}, {DUAL}, n AS (SELECT orig, deco AS v, lag(deco) OVER w AS l, lead(deco) OVER w AS r, x, eb FROM dual WINDOW w AS (PARTITION BY y, z ORDER BY x)),
m AS (SELECT pct, 4 * orig AS o4, least(greatest(l + 2 * v + r, 4 * v - 4 * eb * pct // 100), 4 * v + 4 * eb * pct // 100) AS m4 FROM n, unnest([5, 10, 15, 20, 25, 30, 35, 40, 45, 50]) AS t(pct) WHERE x % 4 IN (0, 3) AND l IS NOT NULL AND r IS NOT NULL)
SELECT CAST(pct AS INTEGER) AS pct, CAST(sum(CAST((o4 - m4) AS HUGEINT) * (o4 - m4)) AS VARCHAR) AS sse16, count(*) AS n FROM m GROUP BY pct""")
def repair_fit_grid(s, d):
    """Squared error per candidate on x, in exact sixteenths."""
    p, eb, _ = dual(s, d)
    cells = rp.with_neighbours(p.select("x", "y", "z", F.col("deco").alias("v"), "orig"), "x").where(rp.is_face("x", 4) & F.col("l").isNotNull() & F.col("r").isNotNull())
    grid = F.broadcast(s.createDataFrame([(int(100 * a + 0.5),) for a in rp.CANDIDATES["blockpred"]], "pct int"))
    step = F.expr(f"{4 * eb}L * pct div 100")
    m4 = F.least(F.greatest(F.col("l") + 2 * F.col("v") + F.col("r"), 4 * F.col("v") - step), 4 * F.col("v") + step)
    e = (4 * F.col("orig") - m4).cast("decimal(18,0)")
    return cells.crossJoin(grid).groupBy("pct").agg(F.sum((e * e).cast("decimal(38,0)")).cast("string").alias("sse16"), F.count("*").alias("n"))


def _sample_cells(s, d):
    p, eb, g = dual(s, d)
    _, side, origins = rp.sample_plan((g, g, g), 4)
    hit = None
    for x, y, z in origins:
        box = gr.in_box((x, x + side - 1, y, y + side - 1, z, z + side - 1))
        hit = box if hit is None else hit | box
    return p.where(hit), eb, g


core.add(
    "repair_sample_plan",
    lambda s, d: (lambda p, eb, g: p.agg(F.count("*").alias("points"), (F.count("*") / g**3).alias("rate")))(*_sample_cells(s, d)),
    f"WITH {HALO}, {DUAL}, {SAMPLE} SELECT count(*) AS points, count(*) / (SELECT CAST(g * g * g AS DOUBLE) FROM g) AS rate FROM smp",
)


def _fitted(method: str):
    def run(s, d):
        import numpy as np

        p, eb, g = _sample_cells(s, d)
        _, side, origins = rp.sample_plan((g, g, g), 4)
        rows = p.select("x", "y", "z", "orig", "deco").toPandas()
        pairs = []
        for x, y, z in origins:
            t = rows[(rows.x.between(x, x + side - 1)) & (rows.y.between(y, y + side - 1)) & (rows.z.between(z, z + side - 1))].sort_values(["x", "y", "z"])
            pairs.append(tuple(t[c].to_numpy(np.float64).reshape(side, side, side) for c in ("orig", "deco")))
        a = rp.fit_intensity(pairs, eb, 4, rp.CANDIDATES["blockpred"], method)
        return s.createDataFrame(list(zip("xyz", map(float, a), strict=True)), "axis string, a double")

    return run


def _coordinate_sql() -> str:
    """The fit of one axis after the other, each on the sample as the axes before left it."""
    steps, src = [], "f0"
    for k, (axis, others) in enumerate((("x", "y, z"), ("y", "x, z"), ("z", "x, y"))):
        face = f"({axis} - o) % 4 IN (0, 3) AND l IS NOT NULL AND r IS NOT NULL"
        steps += [
            f"n{k} AS (SELECT *, lag(v) OVER w AS l, lead(v) OVER w AS r FROM {src} WINDOW w AS (PARTITION BY {others} ORDER BY {axis}))",
            f"s{k} AS (SELECT *, CASE WHEN {face} THEN least(greatest((l + 2 * v + r) / 4, v - a * eb), v + a * eb) ELSE v END AS m FROM n{k}, grid)",
            f"b{k} AS (SELECT arg_min(a, (sse, a)) AS a FROM (SELECT a, sum((orig - m) * (orig - m)) AS sse FROM s{k} GROUP BY a))",
            f"f{k + 1} AS (SELECT x, y, z, o, eb, orig, m AS v FROM s{k} SEMI JOIN b{k} USING (a))",
        ]
        src = f"f{k + 1}"
    return f"WITH {HALO}, {DUAL}, {SAMPLE}, grid AS (SELECT unnest([0.05, 0.10, 0.15, 0.20, 0.25, 0.30, 0.35, 0.40, 0.45, 0.50])::DOUBLE AS a), f0 AS (SELECT x, y, z, o, eb, orig::DOUBLE AS orig, deco::DOUBLE AS v FROM smp), " + ", ".join(steps) + " SELECT 'x' AS axis, a FROM b0 UNION ALL SELECT 'y', a FROM b1 UNION ALL SELECT 'z', a FROM b2"


for _m in ("coordinate", "joint", "sgd"):
    core.add(f"repair_fit_{_m}", _fitted(_m), _coordinate_sql() if _m == "coordinate" else None)


@query(f"""WITH {HALO}, {DUAL}, n AS (SELECT orig, deco AS v, lag(deco) OVER w AS l, lead(deco) OVER w AS r, x, eb FROM dual WINDOW w AS (PARTITION BY y, z ORDER BY x)),
m AS (SELECT a, orig - v AS want, least(greatest((l + 2 * v + r) / 4, v - a * eb), v + a * eb) - v AS move FROM n, unnest([0.05::DOUBLE, 0.25, 0.5, 1.0]) AS t(a) WHERE x % 4 IN (0, 3) AND l IS NOT NULL AND r IS NOT NULL)
SELECT a, CAST(floor(count(*) FILTER (sign(move) * sign(want) >= 0) / count(*) * 1e6 + 0.5) AS BIGINT) AS hit_e6, CAST(floor(avg(abs(want) - abs(want - move)) * 1e3 + 0.5) AS BIGINT) AS gain_e3 FROM m WHERE move <> 0 GROUP BY a""")
def repair_expected_gain(s, d):
    """Hit share and mean gain of the curve at several intensities, on face points along x."""
    p, eb, _ = dual(s, d)
    cells = rp.with_neighbours(p.select("x", "y", "z", F.col("deco").alias("v"), "orig"), "x").where(rp.is_face("x", 4) & F.col("l").isNotNull() & F.col("r").isNotNull())
    grid = F.broadcast(s.createDataFrame([(0.05,), (0.25,), (0.5,), (1.0,)], "a double"))
    m = (F.col("l") + 2 * F.col("v") + F.col("r")) / 4
    move = F.least(F.greatest(m, F.col("v") - F.col("a") * eb), F.col("v") + F.col("a") * eb) - F.col("v")
    want = F.col("orig") - F.col("v")
    hit, gain = F.count_if(F.signum(move) * F.signum(want) >= 0) / F.count("*"), F.avg(F.abs(want) - F.abs(want - move))
    return cells.crossJoin(grid).where(move != 0).groupBy("a").agg(F.floor(hit * 1e6 + 0.5).cast("long").alias("hit_e6"), F.floor(gain * 1e3 + 0.5).cast("long").alias("gain_e3"))


core.add(
    "filter_gauss",
    lambda s, d: fi.gauss_cells(deco(s, d)[0]),
    "WITH " + _START + "".join(
        f", g{a} AS (SELECT x, y, z, (coalesce(lag(v) OVER w, v) + 2 * v + coalesce(lead(v) OVER w, v)) / 4 AS v FROM {src} WINDOW w AS (PARTITION BY {o} ORDER BY {a}))"
        for a, o, src in (("x", "y, z", "r0"), ("y", "x, z", "gx"), ("z", "x, y", "gy"))
    ) + " SELECT x, y, z, v FROM gz",
)
core.add(
    "filter_median",
    lambda s, d: fi.median_cells(deco(s, d)[0]),
    f"""WITH {_START}, e AS (SELECT x + a AS x, y + b AS y, z + c AS z, v FROM r0, unnest([-1, 0, 1]) AS t(a), unnest([-1, 0, 1]) AS u(b), unnest([-1, 0, 1]) AS w(c))
SELECT CAST(x AS INTEGER) AS x, CAST(y AS INTEGER) AS y, CAST(z AS INTEGER) AS z, median(v) AS v FROM e, g WHERE x BETWEEN 0 AND g - 1 AND y BETWEEN 0 AND g - 1 AND z BETWEEN 0 AND g - 1 GROUP BY ALL""",
)

# uncertainty

_E = "orig - deco"


def _iso(s, d):
    p, eb, g = dual(s, d)
    hi = p.agg(F.max("orig")).first()[0]
    return p, eb, g, float(hi // 5) + 0.5


_ISO = "iso AS (SELECT CAST(max(orig) // 5 AS DOUBLE) + 0.5 AS iso FROM dual)"
_SQ = "CAST(sum(CAST((orig - deco) AS HUGEINT) * (orig - deco)) AS VARCHAR) AS see"


def _see() -> Column:
    e = (F.col("orig") - F.col("deco")).cast("decimal(18,0)")
    return F.sum((e * e).cast("decimal(38,0)")).cast("string").alias("see")


core.add("unc_error_model", lambda s, d: dual(s, d)[0].agg(F.count("*").alias("n"), F.sum(F.col("orig") - F.col("deco")).alias("se"), _see()), f"WITH {HALO}, {DUAL} SELECT count(*) AS n, CAST(sum({_E}) AS BIGINT) AS se, {_SQ} FROM dual")
core.add(
    "unc_error_model_near_iso",
    lambda s, d: (lambda p, eb, g, iso: p.where(F.abs(F.col("deco") - iso) <= 8 * eb).agg(F.count("*").alias("n"), F.coalesce(F.sum(F.col("orig") - F.col("deco")), F.lit(0)).alias("se")))(*_iso(s, d)),
    f"WITH {HALO}, {DUAL}, {_ISO} SELECT count(*) AS n, CAST(coalesce(sum({_E}), 0) AS BIGINT) AS se FROM dual, iso WHERE abs(deco - iso) <= 8 * eb",
)
core.add(
    "unc_error_shape",
    lambda s, d: (lambda p, eb, g: un.error_shape(p, eb))(*dual(s, d)),
    f"WITH {HALO}, {DUAL} SELECT CAST(least(19, greatest(0, floor((orig - deco + eb) / (2 * eb) * 20))) AS INTEGER) AS bucket, count(*) AS n FROM dual GROUP BY 1",
)


def _corner_sql(src: str, value: str) -> str:
    """Eight corners by three leads, as a list."""
    steps, last = [], src
    cols = [value]
    for axis, others in (("x", "y, z"), ("y", "x, z"), ("z", "x, y")):
        new = [f"k{len(cols) + i}" for i in range(len(cols))]
        steps.append(f"c{axis} AS (SELECT *, " + ", ".join(f"lead({c}) OVER w AS {n}" for c, n in zip(cols, new, strict=True)) + f" FROM {last} WINDOW w AS (PARTITION BY {others} ORDER BY {axis}))")
        cols, last = cols + new, f"c{axis}"
    return ", ".join(steps) + f", corner AS (SELECT x, y, z, [{', '.join(cols)}] AS c FROM {last} WHERE {cols[-1]} IS NOT NULL)"


core.add(
    "unc_det_cells",
    lambda s, d: (lambda p, eb, g, iso: un.det_cells(p.select("x", "y", "z", F.col("deco").alias("v")), iso))(*_iso(s, d)),
    f"WITH {HALO}, {DUAL}, {_ISO}, {_corner_sql('dual', 'deco')}, a AS (SELECT x, y, z, CAST(len([v FOR v IN c IF v > iso]) AS INTEGER) AS above FROM corner, iso) SELECT x, y, z, above, above > 0 AND above < 8 AS crossed FROM a",
)
#: Mean and spread of the error near the isovalue, from the sample alone: the neighbourhood doubles until it has 64 points.
_MODEL = f"""{SAMPLE}, taus AS (SELECT k, CASE WHEN k < 8 THEN 2 * eb * (1 << k) ELSE 'inf'::DOUBLE END AS tau FROM lim, unnest(range(9)) AS t(k)),
tried AS (SELECT k, count(*) FILTER (abs(deco - iso) <= tau) AS n, avg(orig - deco) FILTER (abs(deco - iso) <= tau) AS mu, stddev_samp(orig - deco) FILTER (abs(deco - iso) <= tau) AS sigma FROM smp, iso, taus GROUP BY k),
model AS (SELECT mu, coalesce(sigma, 0) AS sigma FROM tried WHERE n >= 64 OR k = 8 ORDER BY k LIMIT 1)"""


def _model(s, d):
    """(pairs, bound, edge, isovalue, mean and spread of the error near it by the sample)."""
    p, eb, g, iso = _iso(s, d)
    mu, sigma, _, _ = un.near_model(_sample_cells(s, d)[0], iso, eb)
    return p, eb, g, iso, float(mu), float(sigma)


core.add(
    "unc_sample_model",
    lambda s, d: (lambda p, eb, g, iso, mu, sigma: s.createDataFrame([(mu, sigma)], "mu double, sigma double").select(F.floor(F.col("mu") * 1e3 + 0.5).cast("long").alias("mu_e3"), F.floor(F.col("sigma") * 1e3 + 0.5).cast("long").alias("sigma_e3")))(*_model(s, d)),
    f"WITH {HALO}, {DUAL}, {_ISO}, {_MODEL} SELECT CAST(floor(mu * 1e3 + 0.5) AS BIGINT) AS mu_e3, CAST(floor(sigma * 1e3 + 0.5) AS BIGINT) AS sigma_e3 FROM model",
)
_T = "(1 / (1 + 0.3275911 * abs(zz)))"
_ERF = f"(1 - (((((1.061405429 * {_T} - 1.453152027) * {_T}) + 1.421413741) * {_T} - 0.284496736) * {_T} + 0.254829592) * {_T} * exp(-zz * zz))"
_PV = f"{_MODEL}, pv AS (SELECT x, y, z, 0.5 * (1 + CASE WHEN zz < 0 THEN -{_ERF} ELSE {_ERF} END) AS p FROM (SELECT x, y, z, (deco + mu - iso) / (sigma * sqrt(2)) AS zz FROM dual, iso, model))"


def _prob(s, d):
    p, eb, g, iso, mu, sigma = _model(s, d)
    return un.prob_cells(p.select("x", "y", "z", F.col("deco").alias("v")), mu, sigma, iso)


core.add(
    "unc_prob_cells",
    lambda s, d: _prob(s, d).select("x", "y", "z", F.floor(F.col("p") * 1e5 + 0.5).cast("long").alias("p_e5")),
    f"WITH {HALO}, {DUAL}, {_ISO}, {_PV}, {_corner_sql('pv', 'p')} SELECT x, y, z, CAST(floor(greatest(0, 1 - list_product(c) - list_product([1 - v FOR v IN c])) * 1e5 + 0.5) AS BIGINT) AS p_e5 FROM corner",
)


def _edges(s, d):
    p, eb, g, iso, mu, sigma = _model(s, d)
    return un.edges(p.select("x", "y", "z", F.col("deco").alias("v")), mu, sigma, iso).select("x", "y", "z", "axis", F.floor(F.col("p") * 1e5 + 0.5).cast("long").alias("p_e5"))


core.add(
    "unc_edges",
    _edges,
    f"WITH {HALO}, {DUAL}, {_ISO}, {_PV} "
    + " UNION ALL ".join(f"SELECT x, y, z, '{a}' AS axis, CAST(floor((p * (1 - q) + q * (1 - p)) * 1e5 + 0.5) AS BIGINT) AS p_e5 FROM (SELECT *, lead(p) OVER (PARTITION BY {o} ORDER BY {a}) AS q FROM pv) WHERE q IS NOT NULL" for a, o in (("x", "y, z"), ("y", "x, z"), ("z", "x, y"))),
)


@query(f"""WITH {HALO}, {DUAL}, {_ISO}, {_PV}, {_corner_sql('pv', 'p').replace('corner AS', 'cp AS')}, {_corner_sql('dual', 'deco').replace('cx AS', 'dx AS').replace('cy AS', 'dy AS').replace('cz AS', 'dz AS').replace('FROM cx', 'FROM dx').replace('FROM cy', 'FROM dy').replace('FROM cz', 'FROM dz').replace('corner AS', 'cd AS')},
{_corner_sql('dual', 'orig').replace('cx AS', 'ox AS').replace('cy AS', 'oy AS').replace('cz AS', 'oz AS').replace('FROM cx', 'FROM ox').replace('FROM cy', 'FROM oy').replace('FROM cz', 'FROM oz').replace('corner AS', 'co AS')},
j AS (SELECT len([v FOR v IN co.c IF v > iso]) BETWEEN 1 AND 7 AS t, len([v FOR v IN cd.c IF v > iso]) BETWEEN 1 AND 7 AS s, 1 - list_product(cp.c) - list_product([1 - v FOR v IN cp.c]) >= 0.05 AS h FROM co JOIN cd USING (x, y, z) JOIN cp USING (x, y, z), iso)
SELECT count(*) FILTER (t) AS crossed, count(*) FILTER (t AND NOT s) AS lost, count(*) FILTER (t AND NOT s AND h) AS recovered, count(*) FILTER (t AND s) AS kept, count(*) FILTER (NOT t AND h) AS false_hits, count(*) AS cells FROM j""")
def unc_recovery(s, d):
    p, eb, g, iso = _iso(s, d)
    o, q = (p.select("x", "y", "z", F.col(c).alias("v")) for c in ("orig", "deco"))
    return un.recovery(o, q, _prob(s, d), iso)


core.add(
    "unc_prune_blocks",
    lambda s, d: (lambda p, eb, g, iso: un.prune_blocks(p.groupBy(gr.block_key(8, g // 8, g // 8).alias("key")).agg(F.min("deco").alias("vmin"), F.max("deco").alias("vmax")), iso, 3 * eb))(*_iso(s, d)),
    f"WITH {HALO}, {DUAL}, {_ISO} SELECT * FROM (SELECT CAST((x // 8) * (g // 8) * (g // 8) + (y // 8) * (g // 8) + z // 8 AS BIGINT) AS key, min(deco) AS vmin, max(deco) AS vmax FROM dual, g GROUP BY ALL) SEMI JOIN iso ON vmin <= iso + 3 * (SELECT eb FROM lim) AND vmax >= iso - 3 * (SELECT eb FROM lim)",
)


def _mc(correlated: bool):
    def run(s, d):
        p, eb, g, iso, mu, sigma = _model(s, d)
        factor = un.corner_covariance(_sample_cells(s, d)[0]) if correlated else None
        return un.mc_cells(p.select("x", "y", "z", F.col("deco").alias("v")), mu, sigma, iso, 128, cholesky=factor)

    return run


core.add("unc_mc", _mc(False))
core.add("unc_mvn", _mc(True))


def _e5(c: str) -> Column:
    return F.floor(F.col(c) * 1e5 + 0.5).cast("long").alias(f"{c}_e5")


_CROSSED = "greatest(0, 1 - list_product(c) - list_product([1 - v FOR v IN c]))"
core.add(
    "unc_truncated",
    lambda s, d: (lambda p, eb, g, iso, mu, sigma: un.prob_cells(p.select("x", "y", "z", F.col("deco").alias("v")), mu, sigma, iso, float(eb)))(*_model(s, d)).select("x", "y", "z", _e5("p")),
    f"""WITH {HALO}, {DUAL}, {_ISO}, {_MODEL}, phi AS (SELECT x, y, z, deco, 0.5 * (1 + CASE WHEN zz < 0 THEN -{_ERF} ELSE {_ERF} END) AS f FROM (
  SELECT x, y, z, deco, (least(greatest(iso - deco, -eb), eb) - mu) / (sigma * sqrt(2)) AS zz FROM dual, iso, model UNION ALL SELECT -1, 0, 0, 0, (-eb - mu) / (sigma * sqrt(2)) FROM lim, model UNION ALL SELECT -2, 0, 0, 0, (eb - mu) / (sigma * sqrt(2)) FROM lim, model)),
pv AS (SELECT x, y, z, least(1, greatest(0, ((SELECT f FROM phi WHERE x = -2) - f) / ((SELECT f FROM phi WHERE x = -2) - (SELECT f FROM phi WHERE x = -1)))) AS p FROM phi WHERE x >= 0), {_corner_sql('pv', 'p')}
SELECT x, y, z, CAST(floor({_CROSSED} * 1e5 + 0.5) AS BIGINT) AS p_e5 FROM corner""",
)
core.add(
    "unc_case_entropy",
    lambda s, d: (lambda p, eb, g, iso, mu, sigma: un.case_entropy(p.select("x", "y", "z", F.col("deco").alias("v")), mu, sigma, iso))(*_model(s, d)).select("x", "y", "z", _e5("p"), _e5("entropy")),
    f"""WITH {HALO}, {DUAL}, {_ISO}, {_PV}, {_corner_sql('pv', 'p')} SELECT x, y, z, CAST(floor((1 - list_product(c) - list_product([1 - v FOR v IN c])) * 1e5 + 0.5) AS BIGINT) AS p_e5,
CAST(floor(list_sum([CASE WHEN v > 0 AND v < 1 THEN -(v * log2(v) + (1 - v) * log2(1 - v)) ELSE 0 END FOR v IN c]) * 1e5 + 0.5) AS BIGINT) AS entropy_e5 FROM corner""",
)


@query()
def unc_components(s, d):
    """Parts of the original surface: whole, cracked into several or vanished after decompression, and how much the probabilities find again."""
    p, eb, g, iso, mu, sigma = _model(s, d)
    o, q = (kept(un.det_cells(p.select("x", "y", "z", F.col(c).alias("v")), iso).where("crossed").select("x", "y", "z"), c) for c in ("orig", "deco"))
    likely = un.prob_cells(p.select("x", "y", "z", F.col("deco").alias("v")), mu, sigma, iso).where("p >= 0.05")
    return un.surface_parts(o, q, likely, g)


@query(f"WITH {HALO}, {DUAL}, {_ISO}, {_PV}, {_corner_sql('pv', 'p')} SELECT x, y, CAST(floor(greatest(0, 1 - list_product(c) - list_product([1 - v FOR v IN c])) * 1e5 + 0.5) AS BIGINT) AS p_e5 FROM corner WHERE z = 3")
def unc_slice(s, d):
    return _prob(s, d).where("z = 3").select("x", "y", F.floor(F.col("p") * 1e5 + 0.5).cast("long").alias("p_e5"))


# measures on the prequantised pairs

core.add(
    "metric_psnr",
    lambda s, d: (lambda p, eb, g: me.distortion(p.select(*"xyz", F.col("orig").cast("double").alias("orig"), F.col("deco").cast("double").alias("deco"))).select("n", F.floor(F.col("psnr") * 1e4 + 0.5).cast("long").alias("psnr_e4"), F.col("max_err").cast("long").alias("max_err")))(*dual(s, d)),
    f"WITH {HALO}, {DUAL} SELECT count(*) AS n, CAST(floor((20 * log10(max(orig) - min(orig)) - 10 * log10(sum(CAST(orig - deco AS DOUBLE) * (orig - deco)) / count(*))) * 1e4 + 0.5) AS BIGINT) AS psnr_e4, CAST(max(abs(orig - deco)) AS BIGINT) AS max_err FROM dual",
)
core.add("metric_l2", lambda s, d: dual(s, d)[0].agg(_see()), f"WITH {HALO}, {DUAL} SELECT {_SQ} FROM dual")
core.add("metric_maxerr", lambda s, d: (lambda p, eb, g: me.violations(p, eb))(*dual(s, d)), f"WITH {HALO}, {DUAL} SELECT count(*) FILTER (abs(orig - deco) > eb) AS violations, count(*) AS n FROM dual")
core.add(
    "metric_ssim_block",
    lambda s, d: me.ssim_blocks(dual(s, d)[0]).select(F.floor(F.col("ssim") * 1e5 + 0.5).cast("long").alias("ssim_e5"), "windows"),
    f"""WITH {HALO}, {DUAL}, r AS (SELECT pow(0.01 * (max(orig) - min(orig)), 2) AS c1, pow(0.03 * (max(orig) - min(orig)), 2) AS c2 FROM dual),
w AS (SELECT avg(orig) AS mo, avg(deco) AS md, var_pop(orig) AS vo, var_pop(deco) AS vd, covar_pop(CAST(orig AS DOUBLE), CAST(deco AS DOUBLE)) AS cv FROM dual GROUP BY x // 8, y // 8, z // 8 HAVING count(*) = 512)
SELECT CAST(floor(avg((2 * mo * md + c1) * (2 * cv + c2) / ((mo * mo + md * md + c1) * (vo + vd + c2))) * 1e5 + 0.5) AS BIGINT) AS ssim_e5, count(*) AS windows FROM w, r""",
)


def _sliding_sql() -> str:
    """Sums over 7 points along one axis after the other, then the index of every full window."""
    cols = ("o", "d", "oo", "dd", "od", "n")
    steps, src = ["t0 AS (SELECT x, y, z, o, d, o * o AS oo, d * d AS dd, o * d AS od, 1 AS n FROM (SELECT x, y, z, orig::DOUBLE AS o, deco::DOUBLE AS d FROM dual))"], "t0"
    for k, (axis, others) in enumerate((("x", "y, z"), ("y", "x, z"), ("z", "x, y"))):
        steps.append(f"t{k + 1} AS (SELECT x, y, z, {', '.join(f'sum({c}) OVER w AS {c}' for c in cols)} FROM {src} WINDOW w AS (PARTITION BY {others} ORDER BY {axis} ROWS BETWEEN CURRENT ROW AND 6 FOLLOWING))")
        src = f"t{k + 1}"
    return f"WITH {HALO}, {DUAL}, r AS (SELECT pow(0.01 * (max(orig) - min(orig)), 2) AS c1, pow(0.03 * (max(orig) - min(orig)), 2) AS c2 FROM dual), " + ", ".join(steps) + """,
m AS (SELECT o / 343 AS mo, d / 343 AS md, oo / 343 AS oo, dd / 343 AS dd, od / 343 AS od FROM t3 WHERE n = 343)
SELECT CAST(floor(avg((2 * mo * md + c1) * (2 * (od - mo * md) + c2) / ((mo * mo + md * md + c1) * (oo - mo * mo + dd - md * md + c2))) * 1e5 + 0.5) AS BIGINT) AS ssim_e5, count(*) AS windows FROM m, r"""


core.add("metric_ssim_sliding", lambda s, d: me.ssim_sliding(dual(s, d)[0]).select(F.floor(F.col("ssim") * 1e5 + 0.5).cast("long").alias("ssim_e5"), "windows"), _sliding_sql())
core.add(
    "metric_blockiness",
    lambda s, d: me.blockiness(deco(s, d)[0], 4),
    f"WITH {HALO}, {DUAL}, t AS (SELECT x % 4 = 3 AS face, abs(lead(deco) OVER (PARTITION BY y, z ORDER BY x) - deco) AS step FROM dual) SELECT CAST(sum(step) FILTER (face) AS BIGINT) AS across, count(*) FILTER (face) AS n_across, CAST(sum(step) FILTER (NOT face) AS BIGINT) AS inside, count(*) FILTER (NOT face) AS n_inside FROM t WHERE step IS NOT NULL",
)
core.add("metric_sample_rate", lambda s, d: (lambda p, eb, g: p.agg(F.count("*").alias("points"), F.lit(g**3).cast("long").alias("all_points")))(*_sample_cells(s, d)), f"WITH {HALO}, {DUAL}, {SAMPLE} SELECT count(*) AS points, (SELECT CAST(g * g * g AS BIGINT) FROM g) AS all_points FROM smp")


def _log_p() -> Column:
    return F.floor(F.log10("p") * 1e5 + 0.5).cast("long").alias("log_p_e5")


def _spectrum_sql() -> str:
    """Three contractions, one axis after the other, on the contrast to the mean."""
    steps, src = [], "c0"
    for k, (axis, rest) in enumerate((("x", ["y", "z"]), ("y", ["z"]), ("z", []))):
        keep = [*rest, *(f"k{a}" for a in "xyz"[:k])]
        angle = f"(6.283185307179586::DOUBLE / g * m.k * {axis})"
        cols = "".join(f"{c}, " for c in keep)
        steps.append(f"c{k + 1} AS (SELECT {cols}m.k AS k{axis}, sum(re * cos{angle} + im * sin{angle}) AS re, sum(im * cos{angle} - re * sin{angle}) AS im FROM {src}, g, (SELECT unnest(range(-9, 10)) AS k) m GROUP BY {cols}m.k)")
        src = f"c{k + 1}"
    return f"WITH {HALO}, c0 AS (SELECT x, y, z, v / (SELECT avg(v) FROM halo) - 1 AS re, 0.0::DOUBLE AS im FROM halo), " + ", ".join(steps) + """, p AS (SELECT CAST(floor(sqrt(kx * kx + ky * ky + kz * kz) + 0.5) AS INTEGER) AS k, avg(re * re + im * im) AS p FROM c3 GROUP BY 1)
SELECT k, CAST(floor(log10(p) * 1e5 + 0.5) AS BIGINT) AS log_p_e5 FROM p WHERE k BETWEEN 1 AND 9"""


core.add("metric_spectrum", lambda s, d: (lambda c, g: me.power_spectrum(c, g))(*halo(s, d)).select("k", _log_p()), _spectrum_sql())
core.add(
    "metric_spectrum_blocks",
    lambda s, d: (lambda c, g: me.power_spectrum_blocks(h.to_blocks(c, 8, g // 8, g // 8).select(F.lit(0).alias("level"), "key", "vals"), g, g // 8, g // 8))(*halo(s, d)).select("k", _log_p()),
    _spectrum_sql(),
)


@query()
def metric_spectrum_error(s, d):
    p, _, g = dual(s, d)
    a, b = (me.power_spectrum(p.select("x", "y", "z", F.col(c).alias("v")), g) for c in ("orig", "deco"))
    return me.spectrum_error(a, b)


_POINTS_SQL = """steps AS (SELECT k, greatest(1, (max(v) - min(v)) // (25 * (2 << k))) AS eb FROM halo, unnest(range(4)) AS t(k) GROUP BY k),
coded AS (SELECT k, x, y, z, v, eb, (v + eb) // (2 * eb) AS q FROM halo, steps),
both_ AS (SELECT k, 'plain' AS variant, q FROM coded UNION ALL SELECT k, 'differences', q - coalesce(lag(q) OVER (PARTITION BY k, x, y ORDER BY z), 0) FROM coded),
bits AS (SELECT variant, k, sum(-n * log2(n / t)) / any_value(t) AS bits FROM (SELECT variant, k, q, count(*) AS n, sum(count(*)) OVER (PARTITION BY variant, k) AS t FROM both_ GROUP BY variant, k, q) GROUP BY variant, k),
sq AS (SELECT k, sum((v - q * 2 * eb)::DOUBLE * (v - q * 2 * eb)) / count(*) AS mse FROM coded GROUP BY k), span AS (SELECT (max(v) - min(v))::DOUBLE AS span FROM halo),
pt AS (SELECT variant, k, 64 / bits AS cr, 20 * log10(span) - 10 * log10(mse) AS psnr FROM bits JOIN sq USING (k), span)"""


def _points(s, d):
    """Ratio (by entropy) and PSNR of quantised values and of their differences along z, at four bounds."""
    cells, g = halo(s, d)
    lo, hi = cells.agg(F.min("v"), F.max("v")).first()
    out = None
    for k in range(4):
        eb = max(1, (hi - lo) // (25 * (2 << k)))
        q = F.floor((F.col("v") + eb) / F.lit(2 * eb)).cast("long")
        coded = cells.select("x", "y", "z", "v", q.alias("q"))
        step = F.col("q") - F.coalesce(F.lag("q").over(Window.partitionBy("x", "y").orderBy("z")), F.lit(0))
        e = (F.col("v") - F.col("q") * (2 * eb)).cast("double")
        mse = coded.agg((F.sum(e * e) / F.count("*")).alias("mse"))
        for variant, codes in (("plain", coded.select("q")), ("differences", coded.select(step.alias("q")))):
            n = codes.groupBy("q").agg(F.count("*").alias("n"))
            bits = n.agg((F.sum(-F.col("n") * F.log2(F.col("n") / float(g**3))) / float(g**3)).alias("bits"))
            row = bits.crossJoin(F.broadcast(mse)).select(F.lit(variant).alias("variant"), F.lit(k).alias("k"), (64 / F.col("bits")).alias("cr"), (20 * F.log10(F.lit(float(hi - lo))) - 10 * F.log10("mse")).alias("psnr"))
            out = row if out is None else out.unionByName(row)
    return kept(out, "points")


def _gain(s, d):
    points = _points(s, d)
    at = F.broadcast(points.where("variant = 'plain' and k in (1, 2)").select((F.floor("psnr") + 1).cast("double").alias("at")))
    return me.gain_at_psnr(points, "differences", "plain", at).select("at", micro(F.col("gain")).alias("gain_e6"))


core.add(
    "metric_gain_at_psnr",
    _gain,
    f"""WITH {HALO}, {_POINTS_SQL}, s AS (SELECT variant, psnr AS p0, cr AS c0, lead(psnr) OVER w AS p1, lead(cr) OVER w AS c1 FROM pt WINDOW w AS (PARTITION BY variant ORDER BY psnr)),
ats AS (SELECT floor(psnr) + 1 AS q FROM pt WHERE variant = 'plain' AND k IN (1, 2)),
v AS (SELECT variant, q, max(exp(ln(c0) + (q - p0) / (p1 - p0) * (ln(c1) - ln(c0)))) AS cr FROM s, ats WHERE q BETWEEN p0 AND p1 GROUP BY ALL)
SELECT o.q AS at, CAST(floor(o.cr / b.cr * 1e6 + 0.5) AS BIGINT) AS gain_e6 FROM v o JOIN v b USING (q) WHERE o.variant = 'differences' AND b.variant = 'plain'""",
)


@query(f"""WITH {HALO}, {DUAL}, n AS (SELECT orig, deco AS v, lag(deco) OVER w AS l, lead(deco) OVER w AS r, x, eb FROM dual WINDOW w AS (PARTITION BY y, z ORDER BY x)),
m AS (SELECT 4 * abs(orig - v) AS before, abs(4 * orig - least(greatest(l + 2 * v + r, 4 * v - eb), 4 * v + eb)) AS after FROM n WHERE x % 4 IN (0, 3) AND l IS NOT NULL AND r IS NOT NULL)
SELECT CAST(sum(before) AS BIGINT) AS before, CAST(sum(after) AS BIGINT) AS after, CAST(floor(100 * (1 - sum(after) / sum(before)) * 1e4 + 0.5) AS BIGINT) AS pct_e4 FROM m""")
def metric_reduction_pct(s, d):
    """How much less the absolute error at faces along x is after a repair of a quarter of the bound, in exact quarters."""
    p, eb, _ = dual(s, d)
    cells = rp.with_neighbours(p.select("x", "y", "z", F.col("deco").alias("v"), "orig"), "x").where(rp.is_face("x", 4) & F.col("l").isNotNull() & F.col("r").isNotNull())
    m4 = F.least(F.greatest(F.col("l") + 2 * F.col("v") + F.col("r"), 4 * F.col("v") - eb), 4 * F.col("v") + eb)
    sums = cells.agg(F.sum(4 * F.abs(F.col("orig") - F.col("v"))).alias("before"), F.sum(F.abs(4 * F.col("orig") - m4)).alias("after"))
    return sums.withColumn("pct_e4", F.floor(me.reduction_pct(F.col("after"), F.col("before")) * 1e4 + 0.5).cast("long"))




def _size_plan(s, d):
    """Bytes of the four measures of lineitem: a point per line, a snapshot per month of shipping, a run per return flag."""
    n = table(s, d, "lineitem").agg(F.count("*").alias("points"), F.count_distinct(F.date_trunc("month", "l_shipdate")).alias("snapshots"), F.count_distinct("l_returnflag").alias("runs"))
    plan = me.size_plan(F.col("points"), 4, F.col("snapshots"), F.col("runs"))
    return n.select(*(size.alias(name) for name, size in plan.items()))


core.add(
    "metric_size_plan",
    _size_plan,
    "SELECT p * 8 AS field_bytes, p * 8 * 4 AS snapshot_bytes, p * 8 * 4 * m * r AS campaign_bytes FROM (SELECT count(*) AS p, count(DISTINCT date_trunc('month', l_shipdate)) AS m, count(DISTINCT l_returnflag) AS r FROM lineitem)",
)
