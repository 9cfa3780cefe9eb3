"""Aggregates with a user's own monoid, written in Python: folded batch by batch before the shuffle."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Keys that a task holds before it passes its partial results on.
HELD = 1 << 16


def fold_by(df: DataFrame, key: str, val: str, op: Callable, *, held: int = HELD) -> DataFrame:
    """(key, val): the values of each key folded with op, which must be associative and commutative; its order is not fixed.
    Null values are skipped, a key with nulls alone gives null; null keys are one group. Each task folds its own rows and
    passes on one value for each key it saw, so a hot key reaches the last step as at most one value for each `held` keys
    of every task, never as its rows."""
    kinds = {f.name: f.dataType.simpleString() for f in df.select(key, val).schema.fields}

    def part(batches):
        import pyarrow as pa

        def out(acc):
            return pa.RecordBatch.from_arrays([pa.array(list(acc), kk), pa.array(list(acc.values()), vv)], names=["key", "val"])

        acc: dict = {}
        kk = vv = None
        for batch in batches:
            kk, vv = batch.schema.field(0).type, batch.schema.field(1).type
            for k, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                old = acc.get(k)
                acc[k] = v if old is None else old if v is None else op(old, v)
            if len(acc) >= held:
                yield out(acc)
                acc = {}
        if acc:
            yield out(acc)

    schema = f"key {kinds[key]}, val {kinds[val]}"
    partial = df.select(F.col(key).alias("key"), F.col(val).alias("val")).mapInArrow(part, schema)

    def last(table):
        import pyarrow as pa

        values = [v for v in table.column("val").to_pylist() if v is not None]
        total = values[0] if values else None
        for v in values[1:]:
            total = op(total, v)
        return pa.table([table.column("key").slice(0, 1), pa.array([total], table.schema.field("val").type)], names=["key", "val"])

    return partial.groupBy("key").applyInArrow(last, schema).select(F.col("key").alias(key), F.col("val").alias(val))


def cogrouped(a: DataFrame, b: DataFrame, key: str, fn: Callable, schema: str):
    """fn(table of a, table of b) for each key, in Arrow; for methods that need both sides of a small, bounded group."""
    return a.groupBy(key).cogroup(b.groupBy(key)).applyInArrow(fn, schema)
