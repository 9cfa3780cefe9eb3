"""What the operators of this subpackage share: table access, written intermediate results, Arrow batches of texts."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsegraph.plans.state import materialise, shared_dir  # noqa: F401

#: Most text bytes that one numpy step works on at once; a longer text is a step of its own.
STEP_BYTES = 1 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def ascii_lower(text: Column) -> Column:
    """Lower-cases A-Z only. Pure ASCII strings take the fast built-in."""
    ascii_only = F.octet_length(text) == F.char_length(text)
    return F.when(ascii_only, F.lower(text)).otherwise(F.translate(text, UPPER, UPPER.lower()))


def map_rows(df: DataFrame, fn: Callable[[pa.RecordBatch], Iterator[pa.RecordBatch] | pa.RecordBatch], schema: str) -> DataFrame:
    """mapInArrow over slices of about STEP_BYTES of the first string or binary column, so that memory stays bounded
    whatever batch Spark hands over."""

    def run(batches):
        for batch in batches:
            for part in slices(batch):
                out = fn(part)
                if isinstance(out, pa.RecordBatch):
                    yield out
                else:
                    yield from out

    return df.mapInArrow(run, schema)


def slices(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """Cuts a batch into runs of rows of about STEP_BYTES."""
    import numpy as np
    import pyarrow.compute as pc

    if not batch.num_rows:
        return
    wide = next((c for c in batch.columns if pa.types.is_string(c.type) or pa.types.is_binary(c.type) or pa.types.is_large_string(c.type) or pa.types.is_large_binary(c.type)), None)
    if wide is None:
        yield batch
        return
    ends = np.cumsum(pc.fill_null(pc.binary_length(wide), 0).to_numpy(zero_copy_only=False).astype(np.int64) + 1)
    at = 0
    while at < batch.num_rows:
        base = ends[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(ends, base + STEP_BYTES, side="right")))
        yield batch.slice(at, to - at)
        at = to



def texts_of(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of each text; null counts as empty."""
    return [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]


def schema_of(df: DataFrame, *more: str) -> str:
    """The schema of df as a string for mapInArrow, with more fields after it."""
    return ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields), *more])


def fold(doc_id: Column, folds: int) -> Column:
    """crc32 of the id as text, modulo folds; a null id falls into no fold (-1)."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % folds, F.lit(-1))


def sample_rows(docs: DataFrame, known: DataFrame | None, columns: list[str], most: int) -> DataFrame:
    """(doc_id, text, *columns) of at most `most` rows, the same for any order of the input: those whose ids hash lowest, and of
    the rows of one id those whose texts do. Rows equal in all of these columns count once. known (doc_id, ...) adds its
    columns to the documents that it names, and is itself cut to `most` rows in that way."""
    low = lambda rows, *by: rows.orderBy(F.xxhash64(F.lit(17), "doc_id"), *by).limit(most)
    rows = docs.withColumn("tk", F.xxhash64("text"))
    if known is not None:
        rows = rows.join(F.broadcast(low(known.distinct(), *known.columns)), "doc_id")
    # At most `most` short rows are broadcast; the texts themselves are only filtered.
    names = ["doc_id", "tk", *columns]
    picked = F.broadcast(low(rows.select(*names).distinct(), *names))
    return rows.select("doc_id", "text", "tk", *columns).join(picked, names, "left_semi").dropDuplicates(names).drop("tk")
