"""Sharding along a Hilbert curve, with DataFrame functions alone.

Several metadata dimensions are quantised, each row gets the index of its cell on the Hilbert curve through the grid, and
the order of the curve is cut into shards of equal row counts (at most one apart). Files written by shard then hold
narrow ranges of every dimension, so that filters on any of them skip files.

Numbers, booleans and times are quantised at equi-depth cut points, texts by the characters behind what all values begin with (order is kept).
Null is the lowest cell. Within a cell, rows go by a hash of the id, then by the id: a cell that holds a third of all rows
is split into hash ranges of equal expected size, so that no task ranks more than about 1/8192 of the rows. Only counts
by cell and range meet in one task (at most 4096 + 8192 rows at any input size). Rows that share an id count each, in
order of a hash of their columns. An empty table gives an empty result. Texts are read once, whole, for their size and checksum."""

from __future__ import annotations

import os.path

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

RANGES = 8192
CELL_BITS = 12
#: Steps of one dimension, as a power of two: at most.
DIM_BITS = 8
NUMERIC = ("tinyint", "smallint", "int", "bigint", "float", "double", "decimal", "boolean", "date", "timestamp")


def hilbert_index(point: list[int], bits: int) -> int:
    """Index of a grid point on the Hilbert curve, by exclusive-or transforms of its transposed coordinates (Skilling)."""
    x, n = list(point), len(point)
    for b in range(bits - 1, 0, -1):
        low = (1 << b) - 1
        for i in range(n):
            if x[i] >> b & 1:
                x[0] ^= low
            else:
                swap = (x[0] ^ x[i]) & low
                x[0] ^= swap
                x[i] ^= swap
    for i in range(1, n):
        x[i] ^= x[i - 1]
    flip = 0
    for b in range(bits - 1, 0, -1):
        if x[-1] >> b & 1:
            flip ^= (1 << b) - 1
    out = 0
    for b in range(bits - 1, -1, -1):
        for v in x:
            out = out << 1 | (v ^ flip) >> b & 1
    return out


def lookup(values: list[int], at: Column) -> Column:
    """values[at], as one constant that the optimiser folds."""
    return F.get(F.split(F.lit(",".join(map(str, values))), ",").cast("array<bigint>"), at.cast("int"))


def curve_cell(coords: list[Column], bits: int) -> Column:
    """The cell's index along the curve; coords are integers of `bits` bits each."""
    n = len(coords)
    mask = (1 << bits) - 1
    order = [hilbert_index([c >> bits * (n - 1 - i) & mask for i in range(n)], bits) for c in range(1 << bits * n)]
    cell = F.lit(0)
    for c in coords:
        cell = cell * (1 << bits) + c
    return lookup(order, cell)


def text_image(text: Column, skip: int) -> Column:
    """A long that sorts as the seven bytes of the text after the first `skip` do."""
    tail = F.hex(F.substring(text.cast("binary"), skip + 1, 7))
    return F.conv(F.rpad(tail, 14, "0"), 16, 10).cast("bigint")


def quantised(docs: DataFrame, dims: list[str], bits: int) -> list[Column]:
    """For each dimension its equi-depth step, 0 to 2**bits - 1; only a few numbers for each dimension are collected."""
    kinds = dict(docs.dtypes)
    texts = [d for d in dims if not kinds[d].startswith(NUMERIC)]
    bounds = docs.agg(F.count("*"), *[f(F.col(f"`{d}`").cast("string")).alias(f"{name}{i}") for i, d in enumerate(texts) for name, f in (("a", F.min), ("b", F.max))]).first()
    image = {d: number(F.col(f"`{d}`"), kinds[d]) for d in dims if d not in texts}
    for i, d in enumerate(texts):
        low, high = (bounds[f"{k}{i}"] or "" for k in "ab")
        image[d] = text_image(F.col(f"`{d}`").cast("string"), len(os.path.commonprefix([low.encode(), high.encode()])))
    at = [k / (1 << bits) for k in range(1, 1 << bits)]
    cuts = docs.agg(*[F.percentile_approx(image[d], at, 1000).alias(f"c{i}") for i, d in enumerate(dims)]).first()
    return [F.coalesce(step_of(image[d], sorted(set(cuts[f"c{i}"] or []))), F.lit(0)) for i, d in enumerate(dims)]


def number(x: Column, kind: str) -> Column:
    """A number that sorts as the values of a numeric or time column do."""
    if kind == "boolean":
        return x.cast("int").cast("double")
    if kind.startswith(("date", "timestamp")):
        return F.unix_micros(x.cast("timestamp")).cast("double")
    return x.cast("double")


def step_of(x: Column, cuts: list[float], low: int = 0) -> Column:
    """low and the number of cuts below x, by halving; null for null."""
    if not cuts:
        return F.when(x.isNotNull(), F.lit(low))
    mid = len(cuts) // 2
    return F.when(x > cuts[mid], step_of(x, cuts[mid + 1 :], low + mid + 1)).otherwise(step_of(x, cuts[:mid], low))


def hilbert_shards(docs: DataFrame, dims: list[str], *, shards: int = 8, id_col: str = "doc_id", keep: list[Column] | None = None) -> DataFrame:
    """The columns `keep` (all columns by default) plus curve (cell on the curve), shard (0 to shards - 1) and slot (place
    in the shard, from 0). Shards follow the curve; their row counts differ by one at most."""
    if not dims or len(dims) > CELL_BITS:
        raise ValueError(f"1 to {CELL_BITS} dimensions")
    bits = min(CELL_BITS // len(dims), DIM_BITS)
    coords = quantised(docs.select(*dims), dims, bits)
    keep = keep if keep is not None else [F.col(c) for c in docs.columns if c not in ("curve", "shard", "slot")]
    row = F.struct(*keep)
    # What map columns hold cannot be hashed: with them, rows that share an id keep an arbitrary order.
    tie = F.lit(0).cast("bigint") if "map<" in docs.select(*keep).schema.simpleString() else F.xxhash64(row)
    placed = docs.select(row.alias("row"), tie.alias("tie"), F.col(id_col).alias("id"), F.xxhash64(F.lit(3), F.col(id_col)).alias("h"), curve_cell(coords, bits).alias("curve"))
    cells = {r["curve"]: r["n"] for r in placed.groupBy("curve").agg(F.count("*").alias("n")).collect()}  # at most 2**CELL_BITS rows
    total = sum(cells.values())
    ranges = lookup([-(-cells.get(c, 0) * RANGES // max(total, 1)) or 1 for c in range(1 << bits * len(dims))], F.col("curve"))
    placed = placed.withColumn("range", F.pmod("h", ranges))
    sizes = placed.groupBy("curve", "range").agg(F.count("*").alias("n"))  # at most 2**CELL_BITS + RANGES rows
    offsets = sizes.select("curve", "range", (F.sum("n").over(W.orderBy("curve", "range")) - F.col("n")).alias("offset"))
    rank = F.col("offset") + F.row_number().over(W.partitionBy("curve", "range").orderBy("h", "id", "tie")) - 1
    ranked = placed.join(F.broadcast(offsets), ["curve", "range"]).select("row", "curve", rank.alias("rank"))
    cut = ranked.withColumn("shard", F.expr(f"cast(rank * {shards} div {max(total, 1)} as int)"))
    return cut.select("row.*", "curve", "shard", F.expr(f"rank - (cast(shard as bigint) * {total} + {shards - 1}) div {shards}").alias("slot"))


def write_shards(docs: DataFrame, path: str, dims: list[str], *, shards: int = 8, files_per_shard: int = 1, id_col: str = "doc_id") -> None:
    """Parquet files by shard, each a run of the curve, so that the files' minima and maxima prune on every dimension."""
    placed = hilbert_shards(docs, dims, shards=shards, id_col=id_col)
    placed.repartitionByRange(shards * files_per_shard, "shard", "slot").sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def pruning(placed: DataFrame, dims: list[str]) -> DataFrame:
    """By shard: rows, and the least and largest value of each dimension, which decide what a filter can skip."""
    return placed.groupBy("shard").agg(F.count("*").alias("rows"), *[f(d).alias(f"{name}_{d}") for d in dims for name, f in (("min", F.min), ("max", F.max))])
