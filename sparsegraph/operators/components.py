"""Connected components by star contraction, at any size: no part of the graph comes to the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsegraph.plans.state import materialise


def components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """(id, component) of every endpoint; component is the smallest id that can be reached.

    Each round makes every vertex point to the least of its neighbourhood, first from the larger ends, then among the
    smaller ends; the number of rounds grows with the logarithm of the diameter. Self loops name their vertex. Null ends
    are left out."""
    e = edges.where(F.col(src).isNotNull() & F.col(dst).isNotNull()).select(F.greatest(src, dst).alias("hi"), F.least(src, dst).alias("lo")).distinct()
    e = materialise(e, "components")
    loops = e.where("hi = lo").select(F.col("hi").alias("id"), F.col("hi").alias("component"))
    e = e.where("hi > lo")
    seen = None
    for _ in range(max_rounds):
        both = e.union(e.select(F.col("lo").alias("hi"), F.col("hi").alias("lo"))).toDF("u", "v")
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), "m").distinct()
        least = large.groupBy("u").agg(F.min("m").alias("least"))
        small = large.join(least, "u").where("m <> least").select(F.col("m").alias("hi"), F.col("least").alias("lo"))
        e = materialise(small.union(least.select("u", "least")).distinct(), "components")
        state = e.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    stars = e.select(F.col("hi").alias("id"), F.col("lo").alias("component"))
    return stars.union(e.select(F.col("lo").alias("id"), F.col("lo").alias("component"))).union(loops).groupBy("id").agg(F.min("component").alias("component"))
