"""Where intermediate tables go, and small helpers that several operators use."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``, or one in the warehouse where that is unset."""
    configured = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    return configured or f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/checkpoints"


#: Tables made since the innermost :func:`scratch` began.
_made: list[list[str]] = []


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Tables that :func:`materialise` writes inside are deleted at the end; what is wanted of them has to be written by then."""
    _made.append([])
    try:
        yield
    finally:
        for path in _made.pop():
            delete(spark, path)


def delete(spark: SparkSession, folder: str) -> None:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def materialise(df: DataFrame, label: str, **options: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back.

    It cuts the lineage with files that outlive any executor: a lost executor costs
    the tasks it was running and nothing before them.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/fieldmr-{label}-{uuid.uuid4().hex}"
    df.write.options(**options).parquet(path)
    if _made:
        _made[-1].append(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_table(df: DataFrame) -> None:
    """Delete the files of a table made by :func:`materialise` that no later plan reads."""
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/fieldmr-" in folder:
            delete(df.sparkSession, folder)


#: Rows of at most a few numbers that may be broadcast, some tens of MB.
BROADCAST_ROWS = 2_000_000


def broadcast_if_small(table: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """A materialised table with a broadcast hint if a count proves it small; else as it is, for a shuffled join."""
    return F.broadcast(table) if table.count() <= rows else table


def let(value: Column, body) -> Column:
    """``body(value)`` with ``value`` computed once per row.

    The optimiser inlines projections into lambda bodies, where they would be
    evaluated for every element; a one-element array binds the value instead.
    """
    return F.transform(F.array(value), body)[0]


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
