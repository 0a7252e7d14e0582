"""Numeric fields on 3-D grids, built from the tables.

Builders with exact integer values return (x, y, z, v LONG); wave and layer fields return doubles.  Every builder is one
declarative plan: sums combine before their shuffle, and no window spans more than one line of the grid.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .sources import table

#: Events that are point masses of the density field.
MASSES = 400


def grid_edge(spark: SparkSession, sf_dir: str) -> int:
    """16, 32 or 64 points an axis, by the number of events."""
    n = table(spark, sf_dir, "events").count()
    return 16 if n < 5_000 else 32 if n < 50_000 else 64


def cents(c: str) -> Column:
    return F.floor(F.col(c) * 100 + F.lit(0.5)).cast("long")


def _cells(spark: SparkSession, nx: int, ny: int, nz: int) -> DataFrame:
    i = F.col("id")
    return spark.range(nx * ny * nz).select((i % nx).cast("int").alias("x"), (F.floor(i / nx) % ny).cast("int").alias("y"), F.floor(i / (nx * ny)).cast("int").alias("z"))


def dense(sparse: DataFrame, nx: int, ny: int, nz: int) -> DataFrame:
    """The same cells with zeros wherever there are none."""
    zeros = _cells(sparse.sparkSession, nx, ny, nz).withColumn("v", F.lit(0).cast("long"))
    return sparse.select("x", "y", "z", "v").unionByName(zeros).groupBy("x", "y", "z").agg(F.sum("v").alias("v"))


def part_lattice(spark: SparkSession, sf_dir: str, u: int = 8) -> DataFrame:
    """Retail prices in key order on a u x u x m lattice, whole planes only: two short axes and a sharp jump."""
    part = table(spark, sf_dir, "part")
    planes = part.count() // (u * u)
    k = F.col("p_partkey")
    out = part.select((k % u).cast("int").alias("x"), (F.floor(k / u) % u).cast("int").alias("y"), F.floor(k / (u * u)).cast("int").alias("z"), cents("p_retailprice").alias("v"))
    return out.where(F.col("z") < planes)


def halo_density(spark: SparkSession, sf_dir: str, edge: int | None = None, masses: int = MASSES) -> DataFrame:
    """Point masses with a compact kernel on a torus: a heavy-tailed density with halos."""
    g = edge or grid_edge(spark, sf_dir)
    r = g // 6
    h = (F.col("event_id") * 2654435761) % (1 << 32)
    place = lambda shift: (F.shiftright(h, shift) % g).cast("int")
    heavy = table(spark, sf_dir, "events").select("event_id", cents("value").alias("m")).orderBy(F.desc("m"), "event_id").limit(masses)
    points = heavy.select(place(8).alias("cx"), place(16).alias("cy"), place(24).alias("cz"), "m")
    side = 2 * r + 1
    o = F.col("id")
    offsets = spark.range(side**3).select((o % side - r).cast("int").alias("dx"), (F.floor(o / side) % side - r).cast("int").alias("dy"), (F.floor(o / side**2) - r).cast("int").alias("dz"))
    w = F.lit(r * r) - F.col("dx") * F.col("dx") - F.col("dy") * F.col("dy") - F.col("dz") * F.col("dz")
    kernel = offsets.withColumn("w", (w * w).cast("long")).where(w > 0)
    wrap = lambda c, d: ((F.col(c) + F.col(d) + g) % g).cast("int")
    # the kernel's size depends on the grid alone
    deposits = points.crossJoin(F.broadcast(kernel)).select(wrap("cx", "dx").alias("x"), wrap("cy", "dy").alias("y"), wrap("cz", "dz").alias("z"), (F.col("m") * F.col("w")).alias("v"))
    return dense(deposits, g, g, g)


def ledger_integral(spark: SparkSession, sf_dir: str, edge: int | None = None) -> DataFrame:
    """Quantities by part, supplier and month of order, cumulated along every axis: a smooth field."""
    g = edge or grid_edge(spark, sf_dir)
    month = F.year("o_orderdate") * 12 + F.month("o_orderdate")
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), month.alias("month"))
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", F.floor(F.col("l_quantity") + 0.5).cast("long").alias("q"))
    summed = lines.join(orders, "l_orderkey").groupBy((F.col("l_partkey") % g).cast("int").alias("x"), (F.col("l_suppkey") % g).cast("int").alias("y"), (F.col("month") % g).cast("int").alias("z")).agg(F.sum("q").alias("v"))
    out = dense(summed, g, g, g)
    for axis, others in (("x", ("y", "z")), ("y", ("x", "z")), ("z", ("x", "y"))):
        w = Window.partitionBy(*others).orderBy(axis).rowsBetween(Window.unboundedPreceding, 0)
        out = out.select("x", "y", "z", F.sum("v").over(w).alias("v"))
    return out


def order_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order value by customer bucket, nation and month: noise on a 16 x 25 x 80 grid, count beside it."""
    customer = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey")
    month = (F.year("o_orderdate") * 12 + F.month("o_orderdate")) % 80
    orders = table(spark, sf_dir, "orders").select("o_custkey", cents("o_totalprice").alias("c"), month.cast("int").alias("z"))
    return orders.join(customer, "o_custkey").groupBy((F.col("o_custkey") % 16).cast("int").alias("x"), F.col("c_nationkey").cast("int").alias("y"), "z").agg(F.sum("c").alias("v"), F.count("*").alias("n"))


def event_axes(events: DataFrame, types: list[str], first: Column) -> DataFrame:
    """Events with their grid place: user bucket, index of the type, hour since ``first``."""
    kind = F.array_position(F.array(*map(F.lit, types)), F.col("event_type")) - 1
    hour = F.floor((F.unix_timestamp(F.col("ts").cast("timestamp")) - F.unix_timestamp(first)) / 3600)
    return events.select((F.col("user_id") % 16).cast("int").alias("x"), kind.cast("int").alias("y"), hour.cast("int").alias("z"), cents("value").alias("v"))


def event_types(spark: SparkSession, sf_dir: str) -> list[str]:
    """The types in order: a dictionary of a few values."""
    return sorted(r[0] for r in table(spark, sf_dir, "events").select("event_type").where("event_type is not null").distinct().collect())


def event_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event value by user bucket, type and hour: sparse."""
    events = table(spark, sf_dir, "events")
    first = events.agg(F.date_trunc("day", F.min("ts")).cast("timestamp").alias("t")).first()["t"]
    return event_axes(events, event_types(spark, sf_dir), F.lit(first)).groupBy("x", "y", "z").agg(F.sum("v").alias("v"))


def event_density(spark: SparkSession, sf_dir: str, edge: int | None = None, reach: int = 3) -> DataFrame:
    """All events as masses with a small kernel on a torus; masses of a place are summed first, so the kernel meets at most the grid's cells."""
    g = edge or grid_edge(spark, sf_dir)
    h = (F.col("event_id") * 2654435761) % (1 << 32)
    place = lambda shift: (F.shiftright(h, shift) % g).cast("int")
    masses = table(spark, sf_dir, "events").groupBy(place(8).alias("cx"), place(16).alias("cy"), place(24).alias("cz")).agg(F.sum(cents("value")).alias("m"))
    o, side = F.col("id"), 2 * reach + 1
    offsets = spark.range(side**3).select((o % side - reach).alias("dx"), (F.floor(o / side) % side - reach).alias("dy"), (F.floor(o / side**2) - reach).alias("dz"))
    w = F.lit(reach * reach) - F.col("dx") * F.col("dx") - F.col("dy") * F.col("dy") - F.col("dz") * F.col("dz")
    kernel = offsets.withColumn("w", (w * w).cast("long")).where(w > 0)
    spread = masses.crossJoin(F.broadcast(kernel)).select(*(((F.col(f"c{a}") + F.col(f"d{a}") + g) % g).cast("int").alias(a) for a in "xyz"), (F.col("m") * F.col("w")).alias("v"))
    return dense(spread, g, g, g)


def event_grid(spark: SparkSession, sf_dir: str, edge: int | None = None) -> DataFrame:
    """Event value on a full cube: user bucket, type and its sub-bucket, and time from the first event to the last; mostly zero."""
    g = edge or grid_edge(spark, sf_dir)
    events, types = table(spark, sf_dir, "events"), event_types(spark, sf_dir)
    seconds = F.unix_timestamp(F.col("ts").cast("timestamp"))
    first, last = events.agg(F.min(seconds), F.max(seconds)).first()
    kind = F.array_position(F.array(*map(F.lit, types)), F.col("event_type")) - 1
    per = max(1, g // max(1, len(types)))
    at = [
        (F.col("user_id") % g).cast("int").alias("x"), F.least(F.lit(g - 1), kind * per + F.floor(F.col("user_id") / g) % per).cast("int").alias("y"),
        F.least(F.lit(g - 1), F.floor((seconds - F.lit(first)) * g / max(1, last - first + 1))).cast("int").alias("z"),
    ]
    return dense(events.where("event_type is not null and user_id is not null and ts is not null").select(*at, cents("value").alias("v")), g, g, g)


def _modes(keys: DataFrame, spark: SparkSession, g: int) -> DataFrame:
    """Sum over a fixed number of modes (k, amplitude), by a small broadcast."""
    phase = 2 * 3.141592653589793 / g * (F.col("kx") * F.col("x") + F.col("ky") * F.col("y") + F.col("kz") * F.col("z")) + F.col("shift")
    return _cells(spark, g, g, g).crossJoin(F.broadcast(keys)).groupBy("x", "y", "z").agg(F.sum(F.col("amp") * F.sin(phase)).alias("v"))


def nation_modes(spark: SparkSession, sf_dir: str, edge: int | None = None) -> DataFrame:
    """One sinusoid per nation, mean account balance as amplitude: a wave field with a known spectrum."""
    g = edge or grid_edge(spark, sf_dir)
    amp = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("n_nationkey")).agg(F.avg("c_acctbal").alias("b"))
    nation = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).join(amp, "n_nationkey", "left")
    n = F.col("n_nationkey")
    keys = nation.select((n % 3 + 1).alias("kx"), (n % 4).alias("ky"), (n % 5).alias("kz"), (n * 0.7).alias("shift"), (F.coalesce("b", F.lit(1000.0)) / (1 + n % 7)).alias("amp"))
    return _modes(keys, spark, g)


def mixing_layer(spark: SparkSession, sf_dir: str, edge: int | None = None) -> DataFrame:
    """A smooth step across z whose interface height is a sum of supplier modes."""
    g = edge or grid_edge(spark, sf_dir)
    s = F.col("s_nationkey")
    mode = table(spark, sf_dir, "supplier").groupBy("s_nationkey").agg(F.avg("s_acctbal").alias("b"))
    keys = mode.select((s % 4 + 1).alias("kx"), (s % 3 + 1).alias("ky"), F.lit(0).alias("kz"), (s * 1.3).alias("shift"), (F.col("b") / 250000.0).alias("amp"))
    plane = _cells(spark, g, g, 1).crossJoin(F.broadcast(keys))
    phase = 2 * 3.141592653589793 / g * (F.col("kx") * F.col("x") + F.col("ky") * F.col("y")) + F.col("shift")
    height = plane.groupBy("x", "y").agg((F.sum(F.col("amp") * F.sin(phase)) + 0.5).alias("h"))
    return _cells(spark, g, g, g).join(height, ["x", "y"]).select("x", "y", "z", F.tanh((F.col("z") / g - F.col("h")) / 0.08).alias("v"))


def embedding_cubes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings as 4 x 4 x 4 cubes: (vec_id, label, off, v)."""
    return table(spark, sf_dir, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("off", "v"))


def text_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Text lengths by language, source and rank, with the label where there is one."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars")
    rank = F.row_number().over(Window.partitionBy("lang", "source").orderBy("doc_id")) - 1
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality")
    return docs.select("doc_id", "lang", "source", "n_chars", rank.cast("int").alias("rank")).join(labels, "doc_id", "left").select("lang", "source", "rank", F.col("n_chars").alias("v"), F.coalesce("quality", F.lit(-1)).alias("quality"))


def page_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Page sizes by host (the part after the scheme), and turn sizes by role and turn."""
    host = F.regexp_extract("url", "^[a-z]+://([^/]+)", 1)
    pages = table(spark, sf_dir, "pages").select(host.alias("axis"), F.length("html").cast("long").alias("size"))
    turns = table(spark, sf_dir, "conversations").select(F.concat_ws("/", "role", F.col("turn").cast("string")).alias("axis"), F.length("text").cast("long").alias("size"))
    return pages.unionByName(turns).groupBy("axis").agg(F.sum("size").alias("v"), F.count("*").alias("n"))


def analytic(spark: SparkSession, g: int, kind: str = "bumps") -> DataFrame:
    """Closed-form fields of any size, for scale tests."""
    x, y, z = (F.col(c) / g for c in "xyz")
    v = F.sin(12 * x) * F.cos(9 * y) + z if kind == "wave" else F.exp(-20 * ((x - 0.5) ** 2 + (y - 0.4) ** 2 + (z - 0.6) ** 2)) + 0.5 * F.exp(-60 * ((x - 0.2) ** 2 + (y - 0.7) ** 2 + (z - 0.3) ** 2))
    return _cells(spark, g, g, g).select("x", "y", "z", v.alias("v"))


#: Named fields on a cube, for workloads.
CUBES = {"halo": halo_density, "ledger": ledger_integral, "waves": nation_modes, "layer": mixing_layer}
