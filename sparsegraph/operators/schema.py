"""Graph schemas: adjacency, incidence (plain, signed, hyper) and the exploded four-table schema."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .kernels import PLUS_TIMES, Prefix, gram, spgemm, spref, transpose


def simple_graph(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """(src, dst) with src < dst, each once, without loops and null ends."""
    return edges.where(f"{src} <> {dst}").select(F.least(src, dst).alias("src"), F.greatest(src, dst).alias("dst")).distinct()


def both_ways(edges: DataFrame) -> DataFrame:
    """(row, col, val=1) of a simple graph, each edge in both directions."""
    one = F.lit(1).cast("bigint").alias("val")
    return edges.select(F.col("src").alias("row"), F.col("dst").alias("col"), one).unionAll(edges.select(F.col("dst").alias("row"), F.col("src").alias("col"), one))


def adjacency(edges: DataFrame, *, directed: bool = True, weight: Column | None = None, loops: str = "count", src: str = "src", dst: str = "dst") -> DataFrame:
    """Triples of edge multiplicities, or of summed weights. loops: count (on the diagonal) or drop. An undirected graph
    has every edge in both directions and each loop once."""
    w = weight if weight is not None else F.lit(1).cast("bigint")
    e = edges.where(F.col(src).isNotNull() & F.col(dst).isNotNull()).select(F.col(src).alias("row"), F.col(dst).alias("col"), w.alias("val"))
    if loops == "drop":
        e = e.where("row <> col")
    if not directed:
        e = e.unionAll(transpose(e.where("row <> col")))
    return e.groupBy("row", "col").agg(F.sum("val").alias("val"))


def incidence(edges: DataFrame, *, oriented: bool = False, weight: Column | None = None, edge: str = "edge_id", src: str = "src", dst: str = "dst", loops: str = "reject") -> DataFrame:
    """(row=edge, col=vertex, val). Unoriented: 1 (or the weight) at both ends. Oriented: minus at the tail, plus at the
    head; a loop would need both in one cell, so loops are an error or, with loops="drop", left out."""
    w = weight if weight is not None else F.lit(1).cast("bigint")
    e = edges.select(F.col(edge).alias("row"), F.col(src).alias("_s"), F.col(dst).alias("_d"), w.alias("_w"))
    tail = F.col("_w")
    if oriented:
        if loops == "drop":
            e = e.where("_s <> _d")
        # As a value, not a filter: the optimiser moves filters ahead of those that rule loops out.
        tail = F.when(F.col("_s") != F.col("_d"), -F.col("_w")).otherwise(F.raise_error(F.lit("a loop has no signed incidence")).cast("double"))
        tail = tail.cast(dict(e.dtypes)["_w"])
    return e.select("row", F.explode(F.array(F.struct(F.col("_s").alias("col"), tail.alias("val")), F.struct(F.col("_d").alias("col"), F.col("_w").alias("val")))).alias("x")).select("row", "x.col", "x.val").distinct()


def hyper_incidence(df: DataFrame, edge: str, vertex: str) -> DataFrame:
    """A hyper-edge for each value of `edge`, with 1 at each of its vertices."""
    return df.select(F.col(edge).alias("row"), F.col(vertex).alias("col")).where("row is not null and col is not null").distinct().withColumn("val", F.lit(1).cast("bigint"))


def inc_to_adj(e: DataFrame, clamp: bool = False) -> DataFrame:
    """E^T E without its diagonal."""
    a = gram(e, diagonal=False)
    return a.withColumn("val", F.lit(1).cast("bigint")) if clamp else a


def laplacian(signed: DataFrame) -> DataFrame:
    """E^T E of a signed incidence."""
    return gram(signed)


def partition_block(e: DataFrame, part_a, part_b) -> DataFrame:
    """The block of E^T E between two sets of vertices."""
    return spgemm(transpose(spref(e, cols=part_a)), spref(e, cols=part_b))


@dataclass
class ExplodedTables:
    """edge: (row=record, col="name|value", val=1); edge_t: the same data keyed by column; deg: entries of each column;
    raw: the records."""

    edge: DataFrame
    edge_t: DataFrame
    deg: DataFrame
    raw: DataFrame


def explode_schema(df: DataFrame, id_col: str, cols: list[str | Column], names: list[str] | None = None, sep: str = "|") -> ExplodedTables:
    """Every column-value pair of a record becomes a column of a sparse row. Nulls give no entry; empty texts do."""
    columns = [F.col(c) if isinstance(c, str) else c for c in cols]
    names = names or [c for c in cols]
    pairs = F.array(*[F.when(c.isNotNull(), F.concat(F.lit(f"{n}{sep}"), c.cast("string"))) for n, c in zip(names, columns, strict=True)])
    edge = df.select(F.col(id_col).alias("row"), F.explode(pairs).alias("col")).where("col is not null").withColumn("val", F.lit(1).cast("bigint"))
    return ExplodedTables(edge, transpose(edge), degree_table(edge), df)


def degree_table(edge: DataFrame) -> DataFrame:
    return edge.groupBy("col").agg(F.count("*").alias("degree"))


def raw_join(keys: DataFrame, raw: DataFrame, id_col: str) -> DataFrame:
    """The records whose id is in keys (id)."""
    return raw.join(keys.select(F.col("id").alias(id_col)), id_col, "left_semi")


def facet(tables: ExplodedTables, column: str, prefix: str) -> DataFrame:
    """(col, count): how often each column with the prefix occurs in records that have the given column. The selective
    side, by the degree table's meaning, is the single column: it becomes the build side."""
    rows = spref(tables.edge, cols=[column]).select(F.col("row").alias("id"))
    return spref(tables.edge, rows=rows, cols=Prefix(prefix)).groupBy("col").agg(F.count("*").alias("count"))


def correlate(tables: ExplodedTables, prefix_a: str, prefix_b: str) -> DataFrame:
    """Products of two blocks of columns: co-occurrence counts."""
    return partition_block(tables.edge, Prefix(prefix_a), Prefix(prefix_b))


def encode_labels(a: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(triples with long keys, labels): keys are 64-bit hashes of the labels, which need no order or exchange; a pair of
    labels with one hash is an error (checked when the labels are read)."""
    code = lambda c: F.xxhash64(F.col(c).cast("string"))
    labels = a.select(F.col("row").cast("string").alias("label")).unionAll(a.select(F.col("col").cast("string"))).distinct().withColumn("id", F.xxhash64("label"))
    labels = labels.groupBy("id").agg(F.min("label").alias("label"), F.max("label").alias("_last")).withColumn("label", F.when(F.col("label") == F.col("_last"), F.col("label")).otherwise(F.raise_error(F.lit("two labels have one hash")))).drop("_last")
    return a.select(code("row").alias("row"), code("col").alias("col"), "val"), labels


class AssocArray:
    """An associative array: triples with any keys, and the operators of its algebra."""

    def __init__(self, df: DataFrame, sr=PLUS_TIMES):
        self.df, self.sr = df, sr

    @classmethod
    def build(cls, df: DataFrame, row: str, col: str, val: str | None = None, sr=PLUS_TIMES) -> AssocArray:
        v = F.col(val) if val else F.lit(1).cast("bigint")
        rows = df.where(F.col(row).isNotNull() & F.col(col).isNotNull()).select(F.col(row).alias("row"), F.col(col).alias("col"), v.alias("val"))
        from .kernels import prune

        return cls(prune(rows.groupBy("row", "col").agg(sr.add(F.col("val")).alias("val")), sr.zero), sr)

    @classmethod
    def empty(cls, spark, key: str = "string", val: str = "double") -> AssocArray:
        return cls(spark.createDataFrame([], f"row {key}, col {key}, val {val}"))

    def __add__(self, other: AssocArray) -> AssocArray:
        from .kernels import ewise_add

        return AssocArray(ewise_add(self.df, other.df, self.sr), self.sr)

    def __sub__(self, other: AssocArray) -> AssocArray:
        from .kernels import ewise_sub

        return AssocArray(ewise_sub(self.df, other.df), self.sr)

    def __matmul__(self, other: AssocArray) -> AssocArray:
        return AssocArray(spgemm(self.df, other.df, self.sr), self.sr)

    def __and__(self, other: AssocArray) -> AssocArray:
        from .kernels import ewise_mult

        return AssocArray(ewise_mult(self.df, other.df, self.sr.mult, self.sr.zero), self.sr)

    def __getitem__(self, keys) -> AssocArray:
        rows, cols = keys
        every = slice(None)
        return AssocArray(spref(self.df, None if rows == every else rows, None if cols == every else cols), self.sr)

    @property
    def T(self) -> AssocArray:
        return AssocArray(transpose(self.df), self.sr)

    def scale(self, s) -> AssocArray:
        from .kernels import scale

        return AssocArray(scale(self.df, s, self.sr), self.sr)

    def apply(self, fn) -> AssocArray:
        from .kernels import apply

        return AssocArray(apply(self.df, fn, self.sr.zero), self.sr)

    def reduce(self, axis: str = "row") -> DataFrame:
        """(id, val): the entries of each row, or of each column, added."""
        return self.df.groupBy(F.col(axis).alias("id")).agg(self.sr.add(F.col("val")).alias("val"))

    def gram(self, *, diagonal: bool = True) -> AssocArray:
        """A^T A, with the column labels on both sides."""
        return AssocArray(gram(self.df, self.sr, diagonal=diagonal), self.sr)

    def _edges(self) -> DataFrame:
        return simple_graph(self.df.select(F.col("row").alias("src"), F.col("col").alias("dst")))

    def truss(self, k: int, **kw) -> AssocArray:
        """The k-truss of the undirected graph of the entries, in both directions, with supports as values; labels stay."""
        from .truss import k_truss, with_ids

        kept, _ = k_truss(with_ids(self._edges()), k, **kw)
        up = kept.select(F.col("src").alias("row"), F.col("dst").alias("col"), F.col("support").alias("val"))
        return AssocArray(up.unionByName(transpose(up)), self.sr)

    def jaccard(self, **kw) -> AssocArray:
        """Jaccard index of the neighbourhoods in the undirected graph of the entries; row < col."""
        from .similarity import jaccard

        return AssocArray(jaccard(self._edges(), **kw).select(F.col("i").alias("row"), F.col("j").alias("col"), F.col("score").alias("val")), self.sr)

    def nmf(self, k: int, **kw):
        """Factors with this array's labels as ids (see nmf.nmf)."""
        from .nmf import nmf

        return nmf(self.df, k, **kw)


class AssocTensor:
    """An associative array over any number of key sets: the key columns and `val`, each key tuple at most once."""

    def __init__(self, df: DataFrame, keys: list[str], sr=PLUS_TIMES):
        self.df, self.keys, self.sr = df.select(*keys, "val"), list(keys), sr

    @classmethod
    def build(cls, df: DataFrame, keys: list[str], val: str | None = None, sr=PLUS_TIMES) -> AssocTensor:
        """Rows with a null key have no place; values of one tuple are added."""
        from .kernels import prune

        v = F.col(val) if val else F.lit(1).cast("bigint")
        rows = df.dropna(subset=keys).select(*keys, v.alias("val"))
        return cls(prune(rows.groupBy(*keys).agg(sr.add(F.col("val")).alias("val")), sr.zero), keys, sr)

    def _like(self, df: DataFrame, keys: list[str] | None = None) -> AssocTensor:
        from .kernels import prune

        return AssocTensor(prune(df, self.sr.zero), keys or self.keys, self.sr)

    def __add__(self, other: AssocTensor) -> AssocTensor:
        every = self.df.unionByName(other.df)
        return self._like(every.groupBy(*self.keys).agg(self.sr.add(F.col("val")).alias("val")))

    def __and__(self, other: AssocTensor) -> AssocTensor:
        both = self.df.withColumnRenamed("val", "_a").join(other.df.withColumnRenamed("val", "_b"), self.keys)
        return self._like(both.select(*self.keys, self.sr.mult(F.col("_a"), F.col("_b")).alias("val")))

    def at(self, **want) -> AssocTensor:
        """The part whose keys are in a list, a Range, a Prefix or the ids of a DataFrame."""
        from .kernels import key_filter

        df = self.df
        for key, keys in want.items():
            df = key_filter(df, key, keys)
        return AssocTensor(df, self.keys, self.sr)

    def reduce(self, *keep: str) -> AssocTensor:
        """The other keys added away; partial sums before the shuffle."""
        return self._like(self.df.groupBy(*keep).agg(self.sr.add(F.col("val")).alias("val")), list(keep))

    def contract(self, other: AssocTensor, *over: str) -> AssocTensor:
        """The product summed over the shared keys `over`; the rest of both, which must differ in name, remain."""
        left, right = [k for k in self.keys if k not in over], [k for k in other.keys if k not in over]
        if set(left) & set(right):
            raise ValueError("keys that stay must have different names")
        both = self.df.withColumnRenamed("val", "_a").join(other.df.withColumnRenamed("val", "_b"), list(over))
        cells = both.select(*left, *right, self.sr.mult(F.col("_a"), F.col("_b")).alias("val"))
        return self._like(cells.groupBy(*left, *right).agg(self.sr.add(F.col("val")).alias("val")), left + right)

    def unfold(self, rows: list[str], cols: list[str]) -> AssocArray:
        """A two-dimensional array whose keys are the given keys, as structs where there are several."""
        if sorted([*rows, *cols]) != sorted(self.keys):
            raise ValueError("each key goes to one side")
        side = lambda ks: F.col(ks[0]) if len(ks) == 1 else F.struct(*ks)
        return AssocArray(self.df.select(side(rows).alias("row"), side(cols).alias("col"), "val"), self.sr)
