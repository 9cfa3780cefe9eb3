"""Reading and writing tables and triples."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsegraph.plans.state import materialise


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def write_triples(a: DataFrame, path: str, *, partitions: int | None = None, by: str = "row") -> None:
    """Parquet sorted by one key within hash partitions of it, so that key ranges skip row groups."""
    out = a.repartition(partitions, by) if partitions else a.repartition(by)
    out.sortWithinPartitions(by).write.mode("overwrite").parquet(path)


def save_bucketed(a: DataFrame, name: str, buckets: int, by: str = "row") -> None:
    """A bucketed table: joins on `by` between tables of as many buckets need no exchange."""
    a.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(name)


def read_triples(spark: SparkSession, path: str, *, sep: str = "\t", has_val: bool = True, key: str = "bigint", val: str = "double") -> DataFrame:
    """Edge lists as text; without values every entry is 1. Lines that begin with # are left out."""
    schema = f"row {key}, col {key}" + (f", val {val}" if has_val else "")
    df = spark.read.csv(path, schema=schema, sep=sep, comment="#")
    return df if has_val else df.withColumn("val", F.lit(1).cast(val))


def write_triples_text(a: DataFrame, path: str, sep: str = "\t") -> None:
    a.select("row", "col", "val").write.mode("overwrite").csv(path, sep=sep)


def read_docs(spark: SparkSession, path: str, fmt: str = "json", schema: str = "doc_id bigint, text string") -> DataFrame:
    """JSON lines or ORC with a stated schema: nothing is inferred."""
    return spark.read.schema(schema).format(fmt).load(path)


def read_jdbc(spark: SparkSession, url: str, table: str, *, column: str, low: int, high: int, partitions: int, **options: str) -> DataFrame:
    """A partitioned read from a relational or key-value store that speaks JDBC; its driver must be on the class path."""
    return spark.read.format("jdbc").options(url=url, dbtable=table, partitionColumn=column, lowerBound=low, upperBound=high, numPartitions=partitions, **options).load()


def bucketed_copies(a: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The triples written twice: sorted by row and sorted by column, for methods that walk both ways."""
    by = lambda k: materialise(a.repartition(k).sortWithinPartitions(k), f"by-{k}")
    return by("row"), by("col")
