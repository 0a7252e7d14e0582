"""Intermediate tables that outlive any executor."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``, or one in the warehouse where that is unset."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    return folder or f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/checkpoints"


def kept(df: DataFrame, label: str = "kept") -> DataFrame:
    """``df`` written as Parquet to the shared folder and read back: its lineage ends there, and a lost executor costs only its running tasks."""
    path = f"{shared_dir(df.sparkSession)}/fieldmr-{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop(df: DataFrame) -> None:
    """Delete the files of a table made by :func:`kept` that no later plan reads."""
    spark = df.sparkSession
    path_of = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/fieldmr-" in folder:
            path = path_of(folder)
            path.getFileSystem(conf).delete(path, True)
