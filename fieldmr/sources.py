"""Tables, and the block and packet stores."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: Explicit schemas of the given tables: scans never infer, and prune and push down from the start.
TABLES = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, "
    "l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def write_blocks(blocks: DataFrame, path: str) -> None:
    """Block store: a folder per level, sorted by key, with min and max columns that scans can skip by."""
    from pyspark.sql import functions as F

    ranged = blocks.withColumn("vmin", F.array_min("vals")).withColumn("vmax", F.array_max("vals"))
    ranged.repartitionByRange("level", "key").sortWithinPartitions("level", "key").write.partitionBy("level").parquet(path)


def read_blocks(spark: SparkSession, path: str, levels: list[int] | None = None, iso: float | None = None, margin: float = 0.0) -> DataFrame:
    """Blocks of the wanted levels; with ``iso`` only those whose range comes within ``margin`` of it."""
    from pyspark.sql import functions as F

    out = spark.read.parquet(path)
    if levels is not None:
        out = out.where(F.col("level").isin(levels))
    if iso is not None:
        out = out.where((F.col("vmin") <= iso + margin) & (F.col("vmax") >= iso - margin))
    return out


def write_packets(packets: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Packet store: bodies are compressed already, so the files are not."""
    packets.write.mode(mode).option("compression", "none").partitionBy("level").parquet(path)


def read_packets(spark: SparkSession, path: str, levels: list[int] | None = None, iso: float | None = None, margin: float = 0.0) -> DataFrame:
    return read_blocks(spark, path, levels, iso, margin)
