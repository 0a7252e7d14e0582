"""Relational operators, functions and streams around the methods, each on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import engine as en
from .. import fields as fl
from .. import grid as gr
from .. import hierarchy as h
from .. import sources as so
from .. import sqlfuncs
from .. import streaming as st
from ..codec.apply import mrinterp
from ..registry import Registry
from ..sources import table
from .core import CUBE, dual, halo, ranges
from .sqltext import DUAL, G, HALO, RANGES

ops = Registry()
add = ops.add


def T(s: SparkSession, d: str, *names: str):  # noqa: N802
    found = [table(s, d, n) for n in names]
    return found[0] if len(found) == 1 else found


# scans, sources, sinks

for _name in so.TABLES:
    _key = {"lineitem": "l_quantity", "orders": "o_orderkey", "part": "p_size", "embeddings": "label"}.get(_name)
    _first = so.TABLES[_name].split()[0]
    add(
        f"op_scan_{_name}",
        lambda s, d, n=_name, c=_first: s.read.schema(so.TABLES[n]).parquet(f"{d}/{n}.parquet").agg(F.count("*").alias("n"), F.count_if(F.col(c) > 10).alias("above"), F.max(c).alias("top")),
        f"SELECT count(*) AS n, count(*) FILTER ({_first} > 10) AS above, max({_first}) AS top FROM {_name}",
    )


def _stored(s, d):
    cells, g = halo(s, d)
    blocks = h.to_blocks(cells, 8, g // 8, g // 8).select(F.lit(0).alias("level"), "key", "vals")
    path = st.scratch(s, "blocks")
    so.write_blocks(blocks, path)
    return path, g


add("op_block_store", lambda s, d: (lambda p, g: so.read_blocks(s, p, [0], iso=1e6).agg(F.count("*").alias("blocks"), F.count_if(F.col("vmin") > F.col("vmax")).alias("bad")))(*_stored(s, d)), f"WITH {HALO}, {RANGES} SELECT count(*) AS blocks, count(*) FILTER (lo > hi) AS bad FROM rng WHERE lo <= 1e6 AND hi >= 1e6")


def _packets(s, d):
    cells, g = halo(s, d)
    hi = cells.agg(F.max("v")).first()[0]
    c = mrinterp(hi / 1000)
    path = st.scratch(s, "packets")
    so.write_packets(en.encode(en.field_chunks(cells, g, 8, per_chunk=16), c, 8, g // 8, g // 8), path)
    return cells, g, c, path


def _within(cells: DataFrame, back: DataFrame, eb: float) -> DataFrame:
    both = en.pairs(cells.withColumn("level", F.lit(0)), back)
    return both.agg(F.count("*").alias("n"), F.count_if(F.abs(F.col("orig") - F.col("deco")) > eb).alias("violations"))


def _packet_store(s, d):
    cells, g, c, path = _packets(s, d)
    return _within(cells, en.block_cells(en.decode(so.read_packets(s, path)), 8, g // 8, g // 8), c.eb)


add("op_packet_store", _packet_store, f"WITH {G} SELECT CAST(g * g * g AS BIGINT) AS n, CAST(0 AS BIGINT) AS violations FROM g")


def _packet_source(s, d):
    """The store as a data source: packets are listed by the driver and decoded by the tasks that read them."""
    from ..dsource import register

    register(s)
    cells, _, c, path = _packets(s, d)
    return _within(cells, s.read.format("packets").load(path), c.eb)


add("op_packet_source", _packet_source, f"WITH {G} SELECT CAST(g * g * g AS BIGINT) AS n, CAST(0 AS BIGINT) AS violations FROM g")


def _packet_box(s, d):
    """A box of the field: only packets with a block in it are decoded."""
    cells, g, c, path = _packets(s, d)
    box, n = (3, 12, 2, 9, 5, 10), g // 8
    packets = so.read_packets(s, path)
    near = packets.where(F.exists("keys", lambda k: gr.key_in_box(k, box, 8, n, n)))
    return _within(cells, en.block_cells(en.decode(near), 8, n, n).where(gr.in_box(box)), c.eb)


add("op_packet_box", _packet_box, "SELECT CAST(480 AS BIGINT) AS n, CAST(0 AS BIGINT) AS violations")


def _text_export(fmt: str):
    def run(s, d):
        path = st.scratch(s, fmt)
        T(s, d, "nation").write.format(fmt).option("header", "true").save(path)
        return s.read.format(fmt).option("header", "true").schema(so.TABLES["nation"]).load(path)

    return run


for _f in ("csv", "json", "orc"):
    add(f"op_export_{_f}", _text_export(_f), "SELECT n_nationkey, n_name, n_regionkey FROM nation")


def _raw(s, d):
    """A raw array file written to the folder that driver and executors share, read in parallel."""
    from ..dsource import register

    register(s)
    import numpy as np
    from pyarrow import fs

    path = f"{st.scratch(s, 'raw')}.bin"
    a = np.add.outer(np.add.outer(np.arange(16.0), 10 * np.arange(16.0)), 100 * np.arange(16.0))
    place, at = fs.FileSystem.from_uri(path)
    place.create_dir(at.rsplit("/", 1)[0])
    with place.open_output_stream(at) as f:
        f.write(a.astype("<f4").tobytes())
    return s.read.format("rawfield").option("shape", "16x16x16").option("dtype", "<f4").option("planes", "4").load(path).agg(F.count("*").alias("n"), F.sum("v").alias("total"))


add("op_raw_field", _raw, "SELECT count(*) AS n, sum(x + 10 * y + 100 * z)::DOUBLE AS total FROM unnest(range(16)) AS a(x), unnest(range(16)) AS b(y), unnest(range(16)) AS c(z)")

# predicates

_C = f"WITH {HALO}"
add("op_box", lambda s, d: halo(s, d)[0].where(gr.in_box((2, 5, 3, 6, 1, 4))), f"{_C} SELECT x, y, z, v FROM halo WHERE x BETWEEN 2 AND 5 AND y BETWEEN 3 AND 6 AND z BETWEEN 1 AND 4")
add("op_box_halo", lambda s, d: halo(s, d)[0].where(gr.in_box((2, 5, 3, 6, 1, 4), 1)), f"{_C} SELECT x, y, z, v FROM halo WHERE x BETWEEN 1 AND 6 AND y BETWEEN 2 AND 7 AND z BETWEEN 0 AND 5")
add("op_iso_range", lambda s, d: ranges(s, d)[1].where((F.col("lo") - 100 <= 500000) & (F.col("hi") + 100 >= 500000)).select("key", "lo", "hi"), f"WITH {HALO}, {RANGES} SELECT key, lo, hi FROM rng WHERE lo - 100 <= 500000 AND hi + 100 >= 500000")
add(
    "op_clamp_cases",
    lambda s, d: T(s, d, "customer").select("c_custkey", F.least(F.greatest("c_acctbal", F.lit(0.0)), F.lit(5000.0)).alias("clamped"), F.signum("c_acctbal").cast("int").alias("sign"), F.when(F.col("c_acctbal") < 0, "wrong way").when(F.col("c_acctbal") > 5000, "overshoot").otherwise("between").alias("kind")),
    "SELECT c_custkey, least(greatest(c_acctbal, 0.0), 5000.0) AS clamped, CAST(sign(c_acctbal) AS INTEGER) AS sign, CASE WHEN c_acctbal < 0 THEN 'wrong way' WHEN c_acctbal > 5000 THEN 'overshoot' ELSE 'between' END AS kind FROM customer",
)
add(
    "op_null_policy",
    lambda s, d: T(s, d, "customer").select("c_custkey", F.coalesce(F.when(F.col("c_acctbal") < 0, None).otherwise(F.col("c_acctbal")), F.lit(-1.0)).alias("v"), F.isnan(F.col("c_acctbal")).alias("nan")),
    "SELECT c_custkey, coalesce(CASE WHEN c_acctbal < 0 THEN NULL ELSE c_acctbal END, -1.0) AS v, isnan(c_acctbal) AS nan FROM customer",
)
add("op_hash_sample", lambda s, d: T(s, d, "events").where((F.col("event_id") * 2654435761) % 4294967296 < 64424509).select("event_id"), "SELECT event_id FROM events WHERE (event_id * 2654435761) % 4294967296 < 64424509")

# joins

add("op_join_equi", lambda s, d: T(s, d, "orders").hint("merge").join(T(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_nationkey").agg(F.count("*").alias("n")), "SELECT c_nationkey, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_nationkey")
add("op_join_shuffle_hash", lambda s, d: T(s, d, "lineitem").hint("shuffle_hash").join(T(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n")), "SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority")
add("op_join_broadcast", lambda s, d: T(s, d, "customer").join(F.broadcast(T(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n")), "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
add("op_join_semi", lambda s, d: T(s, d, "customer").join(T(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
add("op_join_anti", lambda s, d: T(s, d, "orders").join(T(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
add("op_join_left", lambda s, d: T(s, d, "documents").join(T(s, d, "labels"), "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality")), "SELECT doc_id, coalesce(quality, -1) AS quality FROM documents LEFT JOIN labels USING (doc_id)")
add("op_join_full", lambda s, d: T(s, d, "supplier").select(F.col("s_suppkey").alias("k")).join(T(s, d, "part").select(F.col("p_partkey").alias("k"), "p_size"), "k", "full").select("k", F.coalesce("p_size", F.lit(-1)).alias("p_size")), "SELECT coalesce(s_suppkey, p_partkey) AS k, coalesce(p_size, -1) AS p_size FROM supplier FULL JOIN part ON s_suppkey = p_partkey")


def _range_join(s, d):
    """Events within a radius of each other: places are joined by coarse bins with a residual filter, then their events are paired.

    Events of one place have the same links, so the join meets a place once, however many events it has.
    """
    hsh = (F.col("event_id") * 2654435761) % (1 << 32)
    p = T(s, d, "events").select("event_id", *((F.shiftright(hsh, k) % 64).cast("int").alias(c) for c, k in (("x", 8), ("y", 16), ("z", 24))))
    p = p.groupBy("x", "y", "z").agg(F.collect_list("event_id").alias("ids"))
    near = p.select(F.col("ids").alias("centers"), *(F.col(a).alias(f"c{a}") for a in "xyz"))
    for a in "xyz":
        near = near.select("*", F.explode(F.sequence(F.floor(F.col(f"c{a}") / 4) - 1, F.floor(F.col(f"c{a}") / 4) + 1)).alias(f"b{a}"))
    binned = p.select("*", *(F.floor(F.col(a) / 4).alias(f"b{a}") for a in "xyz"))
    dist = sum(((F.col(a) - F.col(f"c{a}")) * (F.col(a) - F.col(f"c{a}")) for a in "xyz"), F.lit(0))
    # Spark's estimate leaves out what explode adds, so it would broadcast 27 rows a place
    pairs = binned.join(near.hint("merge"), ["bx", "by", "bz"]).where(dist <= 16)
    return pairs.select("ids", F.explode("centers").alias("center")).select("center", F.explode("ids").alias("event_id"))


_P = "p AS (SELECT event_id, value, ((event_id * 2654435761) % 4294967296 // 256) % 64 AS x, ((event_id * 2654435761) % 4294967296 // 65536) % 64 AS y, ((event_id * 2654435761) % 4294967296 // 16777216) % 64 AS z FROM events)"
add("op_join_range", _range_join, f"WITH {_P} SELECT c.event_id AS center, p.event_id FROM p JOIN p c ON (p.x - c.x) * (p.x - c.x) + (p.y - c.y) * (p.y - c.y) + (p.z - c.z) * (p.z - c.z) <= 16")
add("op_join_neighbour", lambda s, d: (lambda c, r, g: gr.neighbour_keys(r, g // 8, g // 8, g // 8).join(r.select(F.col("key").alias("other"), F.col("hi").alias("other_hi")), "other").groupBy("key").agg(F.max("other_hi").alias("around")))(*ranges(s, d)), f"WITH {HALO}, {RANGES}, c AS (SELECT key, hi, key // ((g // 8) * (g // 8)) AS a, key // (g // 8) % (g // 8) AS b, key % (g // 8) AS c FROM rng, g) SELECT p.key, max(q.hi) AS around FROM c p JOIN c q ON abs(p.a - q.a) + abs(p.b - q.b) + abs(p.c - q.c) = 1 GROUP BY p.key")
add("op_join_cross", lambda s, d: T(s, d, "region").crossJoin(F.broadcast(s.createDataFrame([(1,), (2,), (3,)], "k int"))).select("r_name", "k"), "SELECT r_name, CAST(k AS INTEGER) AS k FROM region, unnest([1, 2, 3]) AS t(k)")


def _asof(s, d):
    """The last signup before each purchase of a user, by a union and one window per user."""
    e = T(s, d, "events").where("event_type in ('signup', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.select("event_id", "event_type", F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), ignorenulls=True).over(w).alias("last_signup")).where("event_type = 'purchase' and last_signup is not null").select("event_id", "last_signup")


add("op_join_asof", _asof, "SELECT event_id, last_signup FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'signup' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_signup FROM events WHERE event_type IN ('signup', 'purchase')) WHERE event_type = 'purchase' AND last_signup IS NOT NULL")


def _interval(s, d):
    """Events in windows [start, end) of a quarter of a day, by day bucket and a residual test."""
    e = T(s, d, "events").select("event_id", F.date_trunc("day", "ts").alias("day"), "ts")
    w = e.select("day").distinct().select("day", F.expr("timestampadd(HOUR, 6, day)").alias("a"), F.expr("timestampadd(HOUR, 12, day)").alias("b"))
    return e.join(w, "day").where("ts >= a and ts < b").select("event_id")


add("op_join_interval", _interval, "SELECT event_id FROM events WHERE hour(ts) BETWEEN 6 AND 11")
add("op_join_cross_level", lambda s, d: (lambda c: c.join(h.coarsen(c, 2, "max").select(F.col("x").alias("px"), F.col("y").alias("py"), F.col("z").alias("pz"), F.col("v").alias("top")), (F.floor(F.col("x") / 2) == F.col("px")) & (F.floor(F.col("y") / 2) == F.col("py")) & (F.floor(F.col("z") / 2) == F.col("pz"))).where("v = top").select("x", "y", "z"))(halo(s, d)[0]), f"{_C}, t AS (SELECT x // 2 AS px, y // 2 AS py, z // 2 AS pz, max(v) AS top FROM halo GROUP BY ALL) SELECT x, y, z FROM halo JOIN t ON x // 2 = px AND y // 2 = py AND z // 2 = pz WHERE v = top")


def _lateral(s, d):
    sqlfuncs.register(s)
    T(s, d, "nation").createOrReplaceTempView("op_lines")
    return s.sql("SELECT n_nationkey, count(*) AS points, count_if(kind = 'extrapolated') AS extrapolated FROM op_lines, LATERAL interp_plan(n_nationkey) WHERE n_nationkey > 3 GROUP BY n_nationkey")


add("op_join_lateral_udtf", _lateral, """WITH st AS (SELECT n_nationkey AS n, 1 << k AS s FROM nation, unnest(range(6)) AS t(k) WHERE n_nationkey > 3 AND (1 << k) < n_nationkey - 1),
p AS (SELECT n, CASE WHEN i + s < n THEN 0 ELSE 1 END AS extra FROM st, unnest(range(s, n - 1, 2 * s)) AS t(i))
SELECT CAST(n AS INTEGER) AS n_nationkey, count(*) + 2 AS points, CAST(sum(extra) AS BIGINT) AS extrapolated FROM p GROUP BY n""")

# aggregates

add("op_agg_hash", lambda s, d: T(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(fl.cents("l_extendedprice")).alias("cents"), F.max("l_quantity").alias("top")), "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(floor(l_extendedprice * 100 + 0.5) AS BIGINT)) AS BIGINT) AS cents, max(l_quantity) AS top FROM lineitem GROUP BY ALL")
add("op_agg_collect", lambda s, d: T(s, d, "nation").groupBy("n_regionkey").agg(F.concat_ws(",", F.array_sort(F.collect_list("n_name"))).alias("names")), "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
add("op_agg_distinct", lambda s, d: (lambda p, eb, g: p.agg(F.count_distinct("q").alias("codes"), F.count("*").alias("n")))(*dual(s, d)), f"WITH {HALO}, {DUAL} SELECT count(DISTINCT q) AS codes, count(*) AS n FROM dual")
add("op_agg_approx_distinct", lambda s, d: T(s, d, "events").agg(F.count_distinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("near")).select("users", (F.abs(F.col("near") - F.col("users")) <= 0.1 * F.col("users")).alias("close")), "SELECT count(DISTINCT user_id) AS users, true AS close FROM events")
add("op_agg_rollup", lambda s, d: T(s, d, "events").rollup("event_type", (F.col("user_id") % 4).cast("int").alias("b")).agg(F.count("*").alias("n")).select(F.coalesce("event_type", F.lit("all")).alias("event_type"), F.coalesce("b", F.lit(-1)).alias("b"), "n"), "SELECT coalesce(event_type, 'all') AS event_type, coalesce(b, -1) AS b, count(*) AS n FROM (SELECT event_type, CAST(user_id % 4 AS INTEGER) AS b FROM events) GROUP BY ROLLUP (event_type, b)")
add("op_agg_cube", lambda s, d: T(s, d, "part").cube("p_brand", "p_size").agg(F.count("*").alias("n")).select(F.coalesce("p_brand", F.lit("all")).alias("p_brand"), F.coalesce("p_size", F.lit(-1)).alias("p_size"), "n"), "SELECT coalesce(p_brand, 'all') AS p_brand, coalesce(p_size, -1) AS p_size, count(*) AS n FROM part GROUP BY CUBE (p_brand, p_size)")


def _sets(s, d):
    T(s, d, "orders").createOrReplaceTempView("op_orders")
    return s.sql("SELECT coalesce(o_orderstatus, 'all') AS status, coalesce(o_orderpriority, 'all') AS priority, count(*) AS n FROM op_orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")


add("op_agg_grouping_sets", _sets, "SELECT coalesce(o_orderstatus, 'all') AS status, coalesce(o_orderpriority, 'all') AS priority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
add("op_agg_quantile", lambda s, d: T(s, d, "part").groupBy("p_brand").agg(F.percentile("p_size", 0.5).alias("median")), "SELECT p_brand, quantile_cont(p_size, 0.5) AS median FROM part GROUP BY p_brand")
add("op_agg_quantile_sketch", lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.percentile_approx("value", [0.15, 0.46], 10000).alias("cuts")))
add("op_agg_moments", lambda s, d: T(s, d, "part").groupBy("p_brand").agg(F.count("*").alias("n"), F.sum(F.col("p_size").cast("long")).alias("s1"), F.sum(F.col("p_size").cast("long") * F.col("p_size")).alias("s2"), F.floor(F.var_samp("p_size") * 1e6 + 0.5).cast("long").alias("var_e6")), "SELECT p_brand, count(*) AS n, CAST(sum(p_size) AS BIGINT) AS s1, CAST(sum(p_size * p_size) AS BIGINT) AS s2, CAST(floor(var_samp(p_size) * 1e6 + 0.5) AS BIGINT) AS var_e6 FROM part GROUP BY p_brand")
add("op_agg_histogram", lambda s, d: T(s, d, "events").where("value >= 0 and value < 500").groupBy((F.width_bucket("value", F.lit(0.0), F.lit(500.0), F.lit(50)) - 1).cast("int").alias("bucket")).agg(F.count("*").alias("n")), "SELECT CAST(floor(value / 10) AS INTEGER) AS bucket, count(*) AS n FROM events WHERE value >= 0 AND value < 500 GROUP BY 1")
add("op_agg_argmax", lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("top"), F.min_by("event_id", F.struct("value", "event_id")).alias("low")), "SELECT event_type, arg_max(event_id, (value, event_id)) AS top, arg_min(event_id, (value, event_id)) AS low FROM events GROUP BY event_type")
add("op_agg_conditional", lambda s, d: T(s, d, "labels").agg(F.count_if(F.col("quality") == 1).alias("good"), F.sum(F.when(F.col("toxic") == 1, 1).otherwise(0)).alias("toxic")), "SELECT count(*) FILTER (quality = 1) AS good, CAST(sum(CASE WHEN toxic = 1 THEN 1 ELSE 0 END) AS BIGINT) AS toxic FROM labels")
add("op_pivot", lambda s, d: T(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0), "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS F, count(*) FILTER (o_orderstatus = 'O') AS O, count(*) FILTER (o_orderstatus = 'P') AS P FROM orders GROUP BY o_orderpriority")
add("op_unpivot", lambda s, d: T(s, d, "part").select("p_partkey", F.col("p_size").cast("long").alias("size"), (F.col("p_partkey") % 7).alias("mod")).unpivot("p_partkey", ["size", "mod"], "name", "value"), "SELECT p_partkey, 'size' AS name, CAST(p_size AS BIGINT) AS value FROM part UNION ALL SELECT p_partkey, 'mod', p_partkey % 7 FROM part")


def _udaf(s, d):
    """PSNR as a grouped-aggregate Arrow function, beside its expression twin."""
    import numpy as np
    import pandas as pd
    from pyspark.sql.functions import pandas_udf

    def measured(o, q):
        mse = float(((o - q) ** 2).mean())
        return float("nan") if mse == 0 else float(20 * np.log10(o.max() - o.min()) - 10 * np.log10(mse))

    measured.__annotations__ = {"o": pd.Series, "q": pd.Series, "return": float}
    psnr = pandas_udf(measured, "double")
    p = dual(s, d)[0].select((F.col("x") % 2).alias("half"), F.col("orig").cast("double").alias("o"), F.col("deco").cast("double").alias("q"))
    return p.groupBy("half").agg(psnr("o", "q").alias("psnr"))


add("op_agg_udaf", lambda s, d: _udaf(s, d).select("half", F.floor(F.col("psnr") * 1e4 + 0.5).cast("long").alias("psnr_e4")), f"WITH {HALO}, {DUAL} SELECT x % 2 AS half, CAST(floor((20 * log10(max(orig) - min(orig)) - 10 * log10(sum(CAST(orig - deco AS DOUBLE) * (orig - deco)) / count(*))) * 1e4 + 0.5) AS BIGINT) AS psnr_e4 FROM dual GROUP BY 1")

# windows

_W = lambda: Window.orderBy(F.desc("rng"), F.asc("key"))
add("op_win_row_number", lambda s, d: ranges(s, d)[1].select("key", F.row_number().over(_W()).alias("place")), f"WITH {HALO}, {RANGES} SELECT key, CAST(place AS INTEGER) AS place FROM ranked")
add("op_win_ranks", lambda s, d: T(s, d, "part").select("p_partkey", F.rank().over(Window.partitionBy("p_brand").orderBy("p_size")).alias("r"), F.dense_rank().over(Window.partitionBy("p_brand").orderBy("p_size")).alias("dr")), "SELECT p_partkey, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS dr FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
add("op_win_shares", lambda s, d: T(s, d, "supplier").select("s_suppkey", F.floor(F.percent_rank().over(Window.partitionBy("s_nationkey").orderBy("s_suppkey")) * 1e6).cast("long").alias("pr"), F.floor(F.cume_dist().over(Window.partitionBy("s_nationkey").orderBy("s_suppkey")) * 1e6).cast("long").alias("cd"), F.ntile(3).over(Window.partitionBy("s_nationkey").orderBy("s_suppkey")).alias("nt")), "SELECT s_suppkey, CAST(floor(percent_rank() OVER w * 1e6) AS BIGINT) AS pr, CAST(floor(cume_dist() OVER w * 1e6) AS BIGINT) AS cd, CAST(ntile(3) OVER w AS INTEGER) AS nt FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_suppkey)")
_U = lambda: Window.partitionBy("user_id").orderBy("event_id")
add("op_win_lag_lead", lambda s, d: T(s, d, "events").select("event_id", F.coalesce(F.lag("event_id").over(_U()), F.lit(-1)).alias("before"), F.coalesce(F.lead("event_id").over(_U()), F.lit(-1)).alias("after")), "SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before, coalesce(lead(event_id) OVER w, -1) AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
add("op_win_first_last", lambda s, d: T(s, d, "events").select("event_id", F.first("event_id").over(_U()).alias("first"), F.coalesce(F.last(F.when(F.col("value") > 100, F.col("event_id")), ignorenulls=True).over(_U().rowsBetween(Window.unboundedPreceding, 0)), F.lit(-1)).alias("last_big"), F.coalesce(F.nth_value("event_id", 2).over(_U().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)), F.lit(-1)).alias("second")), "SELECT event_id, first_value(event_id) OVER w AS first, coalesce(last_value(CASE WHEN value > 100 THEN event_id END IGNORE NULLS) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), -1) AS last_big, coalesce(nth_value(event_id, 2) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), -1) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
_L = lambda: Window.partitionBy("y", "z").orderBy("x")
add("op_win_taps", lambda s, d: halo(s, d)[0].select("x", "y", "z", F.sum("v").over(_L().rowsBetween(-1, 1)).alias("s3"), F.sum("v").over(_L().rowsBetween(-3, 3)).alias("s7")), f"{_C} SELECT x, y, z, CAST(sum(v) OVER (w ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS s3, CAST(sum(v) OVER (w ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING) AS BIGINT) AS s7 FROM halo WINDOW w AS (PARTITION BY y, z ORDER BY x)")
add("op_win_running", lambda s, d: halo(s, d)[0].select("x", "y", "z", F.sum("v").over(_L().rowsBetween(Window.unboundedPreceding, 0)).alias("total")), f"{_C} SELECT x, y, z, CAST(sum(v) OVER (PARTITION BY y, z ORDER BY x) AS BIGINT) AS total FROM halo")
add("op_win_range", lambda s, d: T(s, d, "events").select("event_id", F.sum(fl.cents("value")).over(Window.partitionBy("event_type").orderBy(F.unix_timestamp(F.col("ts").cast("timestamp"))).rangeBetween(-3600, 0)).alias("hour_sum")), "SELECT event_id, CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) OVER (PARTITION BY event_type ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS BIGINT) AS hour_sum FROM events")
add("op_win_whole", lambda s, d: T(s, d, "supplier").select("s_suppkey", F.max("s_acctbal").over(Window.partitionBy("s_nationkey")).alias("top")), "SELECT s_suppkey, max(s_acctbal) OVER (PARTITION BY s_nationkey) AS top FROM supplier")

# sorts and limits

add("op_sort_global", lambda s, d: (lambda c: c.select("x", "y", "z", gr.morton(*map(F.col, "xyz")).alias("code")).orderBy("code"))(halo(s, d)[0]), f"{_C} SELECT x, y, z, CAST(" + " + ".join(f"list_sum([((({c} >> k) & 1) << (3 * k + {a})) FOR k IN range(10)])" for a, c in enumerate("xyz")) + " AS BIGINT) AS code FROM halo ORDER BY code")
add("op_sort_local", lambda s, d: T(s, d, "orders").repartition(4, "o_custkey").sortWithinPartitions("o_custkey", "o_orderkey").select("o_custkey", "o_orderkey"), "SELECT o_custkey, o_orderkey FROM orders")
add("op_top_k", lambda s, d: ranges(s, d)[1].orderBy(F.desc("rng"), "key").limit(3).select("key", "rng"), f"WITH {HALO}, {RANGES} SELECT key, rng FROM ranked ORDER BY rng DESC, key LIMIT 3")
add("op_top_k_group", lambda s, d: T(s, d, "part").withColumn("r", F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey"))).where("r <= 3").select("p_brand", "p_partkey"), "SELECT p_brand, p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 3")
add("op_offset", lambda s, d: T(s, d, "part").orderBy("p_partkey").offset(10).limit(10).select("p_partkey"), "SELECT p_partkey FROM part ORDER BY p_partkey LIMIT 10 OFFSET 10")
add("op_null_order", lambda s, d: T(s, d, "documents").join(T(s, d, "labels"), "doc_id", "left").orderBy(F.asc_nulls_last("quality"), "doc_id").limit(20).select("doc_id"), "SELECT doc_id FROM documents LEFT JOIN labels USING (doc_id) ORDER BY quality ASC NULLS LAST, doc_id LIMIT 20")

# set operations

_S = lambda s, d: (T(s, d, "customer").select(F.col("c_nationkey").alias("k")), T(s, d, "supplier").select(F.col("s_nationkey").alias("k")))
add("op_union_all", lambda s, d: (lambda a, b: a.unionByName(b.withColumn("tag", F.lit("s")), allowMissingColumns=True).groupBy("k").agg(F.count("*").alias("n"), F.count("tag").alias("tagged")))(*_S(s, d)), "SELECT k, count(*) AS n, count(tag) AS tagged FROM (SELECT c_nationkey AS k, NULL AS tag FROM customer UNION ALL SELECT s_nationkey, 's' FROM supplier) GROUP BY k")
for _n, _f, _q in (("union_distinct", lambda a, b: a.union(b).distinct(), "UNION"), ("intersect", lambda a, b: a.intersect(b), "INTERSECT"), ("intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"), ("except", lambda a, b: a.subtract(b), "EXCEPT"), ("except_all", lambda a, b: a.exceptAll(b), "EXCEPT ALL")):
    add(f"op_{_n}", lambda s, d, f=_f: f(*_S(s, d)), f"SELECT c_nationkey AS k FROM customer {_q} SELECT s_nationkey FROM supplier")
add("op_drop_duplicates", lambda s, d: T(s, d, "lineitem").select("l_orderkey", "l_linenumber").dropDuplicates(), "SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem")

# scalar functions

add("op_fn_math", lambda s, d: T(s, d, "part").select("p_partkey", F.floor(F.col("p_retailprice") / 7).cast("long").alias("f"), F.ceil(F.col("p_retailprice") / 7).cast("long").alias("c"), F.pmod("p_partkey", F.lit(7)).alias("m"), F.floor(F.sqrt("p_retailprice") * 1e3).cast("long").alias("s"), F.floor(F.log10("p_retailprice") * 1e6).cast("long").alias("l"), F.floor(F.pow("p_size", F.lit(3))).cast("long").alias("p3")), "SELECT p_partkey, CAST(floor(p_retailprice / 7) AS BIGINT) AS f, CAST(ceil(p_retailprice / 7) AS BIGINT) AS c, p_partkey % 7 AS m, CAST(floor(sqrt(p_retailprice) * 1e3) AS BIGINT) AS s, CAST(floor(log10(p_retailprice) * 1e6) AS BIGINT) AS l, CAST(floor(pow(p_size, 3)) AS BIGINT) AS p3 FROM part")
add("op_fn_bits", lambda s, d: T(s, d, "part").select("p_partkey", F.shiftleft("p_partkey", 3).alias("l"), F.shiftright("p_partkey", 2).alias("r"), F.col("p_partkey").bitwiseAND(85).alias("a"), F.col("p_partkey").bitwiseOR(85).alias("o"), F.col("p_partkey").bitwiseXOR(85).alias("x"), F.bit_count("p_partkey").alias("b")), "SELECT p_partkey, p_partkey << 3 AS l, p_partkey >> 2 AS r, p_partkey & 85 AS a, p_partkey | 85 AS o, xor(p_partkey, 85) AS x, CAST(bit_count(p_partkey) AS INTEGER) AS b FROM part")
add("op_fn_time", lambda s, d: T(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.hour("o_orderdate").alias("h"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date")).alias("days")), "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(hour(o_orderdate) AS INTEGER) AS h, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders")
add("op_fn_string", lambda s, d: T(s, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host"), F.instr("url", "?").alias("q"), F.upper(F.substring("url", 1, 5)).alias("scheme"), F.length("html").alias("n"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("name")), "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, CAST(instr(url, '?') AS INTEGER) AS q, upper(substr(url, 1, 5)) AS scheme, CAST(length(html) AS INTEGER) AS n, lpad(CAST(page_id AS VARCHAR), 8, '0') AS name FROM pages")
add("op_fn_json", lambda s, d: T(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k")), "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
add("op_fn_array", lambda s, d: T(s, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.element_at("embedding", 1).alias("first"), F.array_max("embedding").alias("top"), F.array_min("embedding").alias("low"), F.size(F.filter("embedding", lambda v: v > 0)).alias("positive"), F.size(F.slice("embedding", 1, 16)).alias("part")), "SELECT vec_id, CAST(len(embedding) AS INTEGER) AS n, embedding[1] AS first, list_max(embedding) AS top, list_min(embedding) AS low, CAST(len([v FOR v IN embedding IF v > 0]) AS INTEGER) AS positive, CAST(len(embedding[1:16]) AS INTEGER) AS part FROM embeddings")
add("op_fn_map_struct", lambda s, d: T(s, d, "nation").select("n_nationkey", F.create_map(F.lit("region"), F.col("n_regionkey"), F.lit("key"), F.col("n_nationkey")).alias("m"), F.struct("n_name").alias("t")).select("n_nationkey", F.element_at("m", "region").alias("region"), F.size(F.map_entries("m")).alias("entries"), F.col("t.n_name").alias("name")), "SELECT n_nationkey, n_regionkey AS region, 2 AS entries, n_name AS name FROM nation")
add("op_fn_cast", lambda s, d: T(s, d, "events").select("event_id", F.try_divide(F.col("event_id").cast("double"), F.col("event_id") % 3).alias("ratio"), F.expr("try_cast(props AS INT)").isNull().alias("bad"), F.col("value").cast("decimal(12,2)").cast("string").alias("money")), "SELECT event_id, CASE WHEN event_id % 3 = 0 THEN NULL ELSE CAST(event_id AS DOUBLE) / (event_id % 3) END AS ratio, TRY_CAST(props AS INTEGER) IS NULL AS bad, CAST(CAST(value AS DECIMAL(12, 2)) AS VARCHAR) AS money FROM events")
add("op_fn_hash", lambda s, d: T(s, d, "nation").select("n_nationkey", F.sha2("n_name", 256).alias("sha"), F.md5("n_name").alias("md5")), "SELECT n_nationkey, sha256(n_name) AS sha, md5(n_name) AS md5 FROM nation")


def _engine_functions(s, d):
    sqlfuncs.register(s)
    T(s, d, "part").createOrReplaceTempView("op_part")
    return s.sql(
        "SELECT p_partkey, bezier_mid(p_size, p_retailprice, 0) AS mid, clamp_to(p_retailprice, 1000, 50) AS near, floor(eb_level(1.0, p_size % 5, 2.25, 8) * 1e6 + 0.5) AS eb_e6, block_key(p_size, p_size % 7, p_size % 3, 8, 4, 4) AS key, quant_code(p_retailprice, 900, 0.25) AS code, zigzag(quant_code(p_retailprice, 950, 2)) AS zz FROM op_part"
    )


add("op_fn_engine", _engine_functions, "SELECT p_partkey, (p_size + 2 * p_retailprice) / 4 AS mid, least(greatest(p_retailprice, 950.0), 1050.0) AS near, CAST(floor(1 / least(pow(2.25, p_size % 5), 8) * 1e6 + 0.5) AS BIGINT) AS eb_e6, CAST((p_size // 8) * 16 + (p_size % 7 // 8) * 4 + p_size % 3 // 8 AS BIGINT) AS key, CAST(floor((p_retailprice - 900) / 0.5 + 0.5) AS BIGINT) AS code, CASE WHEN floor((p_retailprice - 950) / 4 + 0.5) >= 0 THEN CAST(2 * floor((p_retailprice - 950) / 4 + 0.5) AS BIGINT) ELSE CAST(-2 * floor((p_retailprice - 950) / 4 + 0.5) - 1 AS BIGINT) END AS zz FROM part")

# streams; those with one batch answer have its SQL

_CENTS = "CAST(sum(CAST(floor(value * 100 + 0.5) AS BIGINT)) AS BIGINT)"
add("stream_tumbling", lambda s, d: st.drained(st.tumbling(st.event_stream(s, d)), "tumbling", "complete"), f"SELECT epoch_us(date_trunc('day', ts)) // 1000000 AS start, CAST(user_id % 16 AS INTEGER) AS x, event_type, {_CENTS} AS v, count(*) AS n FROM events GROUP BY ALL")
add("stream_sliding", lambda s, d: st.drained(st.tumbling(st.event_stream(s, d), "2 days", "1 day"), "sliding", "complete"), f"SELECT epoch_us(date_trunc('day', ts)) // 1000000 - 86400 * k AS start, CAST(user_id % 16 AS INTEGER) AS x, event_type, {_CENTS} AS v, count(*) AS n FROM events, unnest([0, 1]) AS t(k) GROUP BY ALL")
add("stream_session", lambda s, d: st.drained(st.sessions(st.event_stream(s, d).withWatermark("ts", "1 hour")), "session", "complete"), """WITH o AS (SELECT user_id, ts, event_id, coalesce(ts > lag(ts) OVER w + INTERVAL 30 MINUTE, true) AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
k AS (SELECT *, sum(fresh::INT) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM o)
SELECT user_id, epoch_us(min(ts)) // 1000000 AS start, epoch_us(max(ts) + INTERVAL 30 MINUTE) // 1000000 AS "end", count(*) AS n FROM k GROUP BY user_id, g""")
add("stream_late", lambda s, d: st.drained(st.tumbling(st.event_stream(s, d).withWatermark("ts", "1 day")), "late", "append"))
add("stream_state", lambda s, d: st.drained(st.running_model(st.event_stream(s, d)), "state", "update").select("event_type", "n", "total"), f"SELECT event_type, count(*) AS n, {_CENTS} AS total FROM events GROUP BY event_type")
add("stream_static_join", lambda s, d: st.drained(st.with_types(st.event_stream(s, d), s.createDataFrame([(t, i) for i, t in enumerate(fl.event_types(s, d))], "event_type string, kind int")).select("event_id", "kind"), "static", "append"), "SELECT event_id, CAST(k AS INTEGER) AS kind FROM events JOIN (SELECT event_type, row_number() OVER (ORDER BY event_type) - 1 AS k FROM (SELECT DISTINCT event_type FROM events)) USING (event_type)")
add("stream_interval_join", lambda s, d: st.drained(st.pairs_within(st.event_stream(s, d), "signup", "purchase"), "interval", "append"), "SELECT a.event_id, b.event_id AS next_id, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'signup' AND b.event_type = 'purchase'")
add("stream_dedup", lambda s, d: st.drained(st.event_stream(s, d).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "dedup", "append"), "SELECT DISTINCT event_id FROM events")


def _foreach(s, d):
    """The stream's cells are compressed batch by batch and read back: points and bytes, and points further off than the bounds of all batches."""
    types = fl.event_types(s, d)
    hour = F.floor((F.unix_timestamp(F.col("ts").cast("timestamp")) - F.unix_timestamp(F.date_trunc("day", F.col("first")))) / 3600)
    first, last = T(s, d, "events").agg(F.min("ts").alias("first"), F.max("ts").alias("ts")).select(F.date_trunc("day", "first").cast("timestamp"), hour).first()
    planes = -(-(int(last) + 1) // 8)
    codec = mrinterp(50.0)

    def encode(batch: DataFrame) -> DataFrame:
        cells = fl.event_axes(batch, types, F.lit(first)).groupBy("x", "y", "z").agg(F.sum("v").alias("v"))
        blocks = h.to_blocks(fl.dense(cells, 16, 8, 8 * planes), 8, 1, planes).select(F.lit(0).alias("level"), "key", "vals")
        return en.encode(en.chunks(blocks, 8), codec, 8, 1, planes)

    sink = st.scratch(s, "snapshots")
    st.compress_batches(st.event_stream(s, d), sink, encode)
    packets = s.read.parquet(sink)
    batches = packets.select("batch").distinct().count()
    back = en.block_cells(en.decode(packets), 8, 1, planes).groupBy("level", "x", "y", "z").agg(F.sum("v").alias("v"))
    both = en.pairs(fl.dense(fl.event_cube(s, d), 16, 8, 8 * planes).withColumn("level", F.lit(0)), back)
    size = packets.agg(F.sum("raw_bytes").alias("raw_bytes"), (F.sum("packed_bytes") < F.sum("raw_bytes")).alias("smaller"))
    return both.agg(F.count("*").alias("points"), F.count_if(F.abs(F.col("orig") - F.col("deco")) > batches * codec.eb).alias("violations")).crossJoin(F.broadcast(size))


add("stream_foreach_batch", _foreach, """WITH p AS (SELECT 16 * 8 * 8 * CAST(ceil((floor((epoch_us(max(ts)) // 1000000 - epoch_us(date_trunc('day', min(ts))) // 1000000) / 3600) + 1) / 8) AS BIGINT) AS points FROM events)
SELECT points, CAST(0 AS BIGINT) AS violations, 8 * points AS raw_bytes, true AS smaller FROM p""")


def _rate(s, d):
    """A source of numbered rows by the second, as cells of a closed form: rows of one run of the clock, checked against their numbers."""
    rows = s.readStream.format("rate-micro-batch").option("rowsPerBatch", 512).option("numPartitions", 2).load()
    out = st.scratch(s, "rate")
    q = rows.select("value", (F.col("value") * F.col("value")).alias("v")).writeStream.format("parquet").option("checkpointLocation", st.scratch(s, "rate-state")).start(out)
    while not q.lastProgress or q.lastProgress["batchId"] < 1:
        q.awaitTermination(0.2)
    q.stop()
    return s.read.schema("value long, v long").parquet(out).where("value < 512").agg(F.count("*").alias("n"), F.sum("v").alias("total"))


add("stream_rate", _rate, "SELECT count(*) AS n, CAST(sum(i * i) AS BIGINT) AS total FROM unnest(range(512)) AS t(i)")
