"""User functions for SQL: table functions and registered views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="edge_src: bigint, edge_dst: bigint")
class TriangleEdges:
    """The three edges of a triangle, ends in order."""

    def eval(self, a: int, b: int, c: int):
        a, b, c = sorted((a, b, c))
        yield a, b
        yield b, c
        yield a, c


@udtf(returnType="col: string, val: bigint")
class ExplodeRecord:
    """Column-value pairs of a JSON record with scalar fields."""

    def eval(self, record: str):
        import json

        for k, v in (json.loads(record) if record else {}).items():
            if v is not None:
                yield f"{k}|{v}", 1


def register(spark: SparkSession, **views: DataFrame) -> None:
    """Registers the table functions and the given DataFrames as views."""
    spark.udtf.register("triangle_edges", TriangleEdges)
    spark.udtf.register("explode_record", ExplodeRecord)
    for name, df in views.items():
        df.createOrReplaceTempView(name)
