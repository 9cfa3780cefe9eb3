"""Graphs and matrices made from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from sparsegraph.functions.semiring import PLUS_PAIR
from sparsegraph.operators.kernels import gram
from sparsegraph.operators.schema import ExplodedTables, explode_schema, hyper_incidence
from sparsegraph.plans.state import materialise

from .tables import read_table

#: The worked 5-vertex graph: (edge_id, src, dst).
TOY5 = [(1, 1, 2), (2, 2, 3), (3, 1, 4), (4, 3, 4), (5, 1, 3), (6, 2, 5)]


def toy5(spark: SparkSession) -> DataFrame:
    e = spark.createDataFrame(TOY5, "edge_id bigint, src bigint, dst bigint")
    return e


def order_part(spark: SparkSession, d: str) -> DataFrame:
    """Orders as hyper-edges over parts."""
    return hyper_incidence(read_table(spark, d, "lineitem"), "l_orderkey", "l_partkey")


def copurchase(spark: SparkSession, d: str, min_orders: int = 2) -> DataFrame:
    """(src, dst, w), src < dst: parts that share at least min_orders orders."""
    g = gram(order_part(spark, d), PLUS_PAIR, upper=True)
    return g.where(F.col("val") >= min_orders).select(F.col("row").alias("src"), F.col("col").alias("dst"), F.col("val").alias("w"))


def part_supplier(spark: SparkSession, d: str) -> DataFrame:
    """(row=part, col=supplier, val=quantity)."""
    return read_table(spark, d, "lineitem").groupBy(F.col("l_partkey").alias("row"), F.col("l_suppkey").alias("col")).agg(F.sum("l_quantity").alias("val"))


def customer_part(spark: SparkSession, d: str) -> DataFrame:
    li, o = read_table(spark, d, "lineitem"), read_table(spark, d, "orders")
    return li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.col("o_custkey").alias("row"), F.col("l_partkey").alias("col")).agg(F.sum("l_quantity").alias("val"))


def trade_lines(spark: SparkSession, d: str) -> DataFrame:
    """(src, dst, qty, price) of every line: customer's nation, supplier's nation. The nations are looked up first on the
    small tables."""
    li, o = read_table(spark, d, "lineitem"), read_table(spark, d, "orders")
    c, s = read_table(spark, d, "customer"), read_table(spark, d, "supplier")
    buyer = o.join(c, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", F.col("c_nationkey").alias("src"))
    seller = s.select("s_suppkey", F.col("s_nationkey").alias("dst"))
    return li.select("l_orderkey", "l_suppkey", "l_quantity", "l_extendedprice").join(seller, F.col("l_suppkey") == F.col("s_suppkey")).join(buyer, F.col("l_orderkey") == F.col("o_orderkey")).select("src", "dst", F.col("l_quantity").alias("qty"), F.col("l_extendedprice").alias("price"))


def nation_trade(spark: SparkSession, d: str) -> DataFrame:
    """(src, dst, w, qty): lines and quantity from customer nation to supplier nation."""
    return trade_lines(spark, d).groupBy("src", "dst").agg(F.count("*").alias("w"), F.sum("qty").alias("qty"))


def events(spark: SparkSession, d: str) -> DataFrame:
    """Events with ts as a timestamp in UTC and its microseconds."""
    return read_table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).withColumn("us", F.unix_micros("ts"))


def successions(ev: DataFrame) -> DataFrame:
    """(src, dst, gap_us) for each event and the next one of the whole stream. The order is total; days are ranked on their
    own and joined at their ends, so that no task orders more than a day."""
    day = F.to_date("ts")
    w = W.partitionBy("day").orderBy("ts", "event_id")
    e = ev.select("event_id", "ts", "us", "user_id", day.alias("day"))
    inner = e.select("day", "us", F.col("user_id").alias("src"), F.lead("user_id").over(w).alias("dst"), F.lead("us").over(w).alias("next"))
    firsts = e.groupBy("day").agg(F.min(F.struct("ts", "event_id", "us", "user_id")).alias("f"))
    # One row for each day.
    heads = firsts.select("day", F.lead("f").over(W.orderBy("day")).alias("n"))
    return inner.join(heads, "day").select("src", F.coalesce("dst", F.col("n.user_id")).alias("dst"), (F.coalesce("next", F.col("n.us")) - F.col("us")).alias("gap_us")).where("dst is not null")


def user_succession(spark: SparkSession, d: str) -> DataFrame:
    """(src, dst, w, gap_us): successions of users in the event stream, their number and least gap."""
    return successions(events(spark, d)).groupBy("src", "dst").agg(F.count("*").alias("w"), F.min("gap_us").alias("gap_us"))


def trade_graph(spark: SparkSession, d: str) -> DataFrame:
    """(edge_id, src, dst), src < dst: nations that trade at least as many lines, both ways together, as the mean pair does.
    Made from every line; as small as the number of nations, so that methods for small graphs can run on it."""
    t = nation_trade(spark, d).where("src <> dst")
    t = t.groupBy(F.least("src", "dst").cast("bigint").alias("src"), F.greatest("src", "dst").cast("bigint").alias("dst")).agg(F.sum("w").alias("w"))
    t = materialise(t, "trade")
    whole = t.agg(F.count("*").alias("n"), F.sum("w").alias("total"))
    return t.crossJoin(whole).where("w * n >= total").select((F.col("src") * 100 + F.col("dst")).alias("edge_id"), "src", "dst")


def page_link(spark: SparkSession, d: str) -> DataFrame:
    """(src=url, dst=href, w)."""
    p = read_table(spark, d, "pages")
    return p.select(F.col("url").alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("dst")).groupBy("src", "dst").agg(F.count("*").alias("w"))


def embed_sim(spark: SparkSession, d: str, t: float = 0.3, block: int = 512) -> DataFrame:
    """(src, dst, w), src < dst: vectors of cosine above t. Exact at any size: blocks of about `block` vectors meet each
    other, and a pair of blocks is one product of matrices. Vectors that are null or of length 0 have no cosine."""
    e = read_table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v")).where("v is not null")
    kind = e.schema["id"].dataType.simpleString()
    n = max(1, -(-e.count() // block))
    packed = materialise(e.groupBy(F.pmod(F.xxhash64("id"), F.lit(n)).alias("b")).agg(F.collect_list(F.struct("id", "v")).alias("x")).select("b", F.col("x.id").alias("ids"), F.flatten("x.v").alias("v")), "vectors")
    left = packed.repartition(min(n, 1000)).select(*[F.col(c).alias(f"{c}1") for c in packed.columns])
    return left.join(packed, F.expr("b1 <= b")).mapInArrow(_cosines(t), f"src {kind}, dst {kind}, w double")


def _cosines(t: float):
    """Pairs of vectors of two blocks with a cosine above t; a block with itself gives each pair once."""

    def run(batches):
        import numpy as np
        import pyarrow as pa

        def unit(ids, v):
            x = v.values.to_numpy(zero_copy_only=False).reshape(len(ids), -1)
            with np.errstate(invalid="ignore", divide="ignore"):
                return x / np.sqrt((x * x).sum(axis=1, keepdims=True))

        for batch in batches:
            for k in range(batch.num_rows):
                b1, ids1, v1, b2, ids2, v2 = (batch.column(c)[k] for c in ("b1", "ids1", "v1", "b", "ids", "v"))
                ids1, ids2 = ids1.values, ids2.values
                w = unit(ids1, v1) @ unit(ids2, v2).T
                i, j = np.nonzero(w > t)
                w = w[i, j]
                x, y = ids1.to_numpy(zero_copy_only=False)[i], ids2.to_numpy(zero_copy_only=False)[j]
                keep = x < y if b1.as_py() == b2.as_py() else x != y
                x, y, w = x[keep], y[keep], w[keep]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y), ids1.type), pa.array(np.maximum(x, y), ids1.type), pa.array(w)], names=["src", "dst", "w"])

    return run


def exploded_events(spark: SparkSession, d: str) -> ExplodedTables:
    e = read_table(spark, d, "events")
    k = F.get_json_object("props", "$.k")
    return explode_schema(e, "event_id", [F.col("event_type"), F.col("user_id"), k], ["event_type", "user_id", "k"])


def exploded_customer(spark: SparkSession, d: str) -> ExplodedTables:
    return explode_schema(read_table(spark, d, "customer"), "c_custkey", ["c_nationkey", "c_mktsegment"])


def conv_reply(spark: SparkSession, d: str) -> DataFrame:
    """(src, dst, roles): consecutive turns of a conversation; ends are structs of conversation and turn."""
    w = W.partitionBy("conv_id").orderBy("turn")
    c = read_table(spark, d, "conversations").select("conv_id", "turn", "role", F.lead("turn").over(w).alias("nt"), F.lead("role").over(w).alias("nr")).where("nt is not null")
    return c.select(F.struct("conv_id", "turn").alias("src"), F.struct(F.col("conv_id"), F.col("nt").alias("turn")).alias("dst"), F.concat("role", F.lit(">"), "nr").alias("roles"))


def geo_tree(spark: SparkSession, d: str) -> DataFrame:
    """(src, dst) text keys: region to nation to customer and supplier."""
    n, c, s = (read_table(spark, d, t) for t in ("nation", "customer", "supplier"))
    key = lambda p, x: F.concat(F.lit(p), F.col(x).cast("string"))
    return n.select(key("r", "n_regionkey").alias("src"), key("n", "n_nationkey").alias("dst")).unionAll(c.select(key("n", "c_nationkey"), key("c", "c_custkey"))).unionAll(s.select(key("n", "s_nationkey"), key("s", "s_suppkey")))
