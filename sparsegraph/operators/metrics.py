"""Cost and accuracy measures."""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .kernels import cosine, ewise_union, norm_fro  # noqa: F401
from .nmf import nmf_residual, purity  # noqa: F401
from .schema import both_ways
from .truss import edge_support, wasted_products  # noqa: F401


def fill(a: DataFrame, n_rows: int, n_cols: int) -> DataFrame:
    """Share of cells with an entry."""
    return a.agg((F.count("*") / F.lit(float(n_rows) * n_cols)).alias("fill"))


def step_norm(new: DataFrame, old: DataFrame) -> float:
    """Frobenius norm of the difference."""
    return norm_fro(ewise_union(new, old, lambda a, b: a - b, 0.0)).first()[0] or 0.0


def products(a: DataFrame, b: DataFrame) -> DataFrame:
    """(products, cells): multiplications of a sparse product and entries of its result."""
    x = a.groupBy(F.col("col").alias("l")).agg(F.count("*").alias("x"))
    y = b.groupBy(F.col("row").alias("l")).agg(F.count("*").alias("y"))
    n = x.join(y, "l").agg(F.coalesce(F.sum(F.col("x") * F.col("y")), F.lit(0)).alias("products"))
    cells = a.select("row", F.col("col").alias("l")).join(b.select(F.col("row").alias("l"), "col"), "l").select("row", "col").distinct().agg(F.count("*").alias("cells"))
    return n.crossJoin(cells)


def products_below_diagonal(edges: DataFrame) -> DataFrame:
    """(total, below): products of the full square of a symmetric matrix, and those that land on or below the diagonal and
    that the upper form never makes."""
    d = both_ways(edges).groupBy("row").agg(F.count("*").alias("d"))
    return d.agg(F.sum(F.col("d") * F.col("d")).alias("total"), F.sum(F.col("d") * F.col("d") - F.expr("d * (d - 1) div 2")).cast("bigint").alias("below"))


@dataclass
class KernelStats:
    """What the actions inside a `with` block cost, all jobs of the session together: seconds, stages, tasks, rows read, bytes
    shuffled and spilled, CPU seconds, from Spark's status store (which holds the last spark.ui.retainedStages stages).
    Rounds and products are the caller's, as a loop's report and `products` give them."""

    spark: SparkSession
    seconds: float = 0.0
    stages: int = 0
    tasks: int = 0
    input_rows: int = 0
    shuffle_written: int = 0
    shuffle_read: int = 0
    spilled: int = 0
    cpu_seconds: float = 0.0
    rounds: int | None = None
    products: int | None = None

    def _stages(self) -> list:
        sc = self.spark.sparkContext
        jvm = sc._jvm
        sc._jsc.sc().listenerBus().waitUntilEmpty()
        none = sc._gateway.new_array(jvm.double, 0)
        held = sc._jsc.sc().statusStore().stageList(None, False, False, none, jvm.java.util.ArrayList())
        return [held.apply(i) for i in range(held.size())]

    def __enter__(self) -> KernelStats:
        self._last = max((s.stageId() for s in self._stages()), default=-1)
        self._began = time.monotonic()
        return self

    def __exit__(self, *exc) -> None:
        self.seconds = time.monotonic() - self._began
        for s in self._stages():
            if s.stageId() > self._last and s.numCompleteTasks():
                self.stages += 1
                self.tasks += s.numCompleteTasks()
                self.input_rows += s.inputRecords()
                self.shuffle_written += s.shuffleWriteBytes()
                self.shuffle_read += s.shuffleReadBytes()
                self.spilled += s.diskBytesSpilled()
                self.cpu_seconds += s.executorCpuTime() / 1e9

    def row(self) -> dict:
        out = {"seconds": round(self.seconds, 3), "stages": self.stages, "tasks": self.tasks, "input_rows": self.input_rows, "shuffle_mb": round(self.shuffle_written / 1e6, 1), "spill_mb": round(self.spilled / 1e6, 1), "cpu_s": round(self.cpu_seconds, 1)}
        return out | {k: v for k, v in (("rounds", self.rounds), ("products", self.products)) if v is not None}
