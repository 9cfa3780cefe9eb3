"""Intermediate results that outlive executors: written once to the folder that the whole cluster shares."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session, or a folder set here where it is unset (tests, single machines)."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        base = "/tmp/checkpoints"
        spark.conf.set("spark.checkpoint.dir", base)
    return base.rstrip("/") + "/" + spark.sparkContext.applicationId


def materialise(df: DataFrame, name: str = "state") -> DataFrame:
    """Writes df and reads it back: cuts the lineage, and what follows does not compute df again."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex[:12]}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def remove(df: DataFrame) -> None:
    """Deletes the files behind a materialised table that nothing reads any more."""
    spark = df.sparkSession
    for name in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = spark._jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
