"""Link prediction with a held-out test, and communities that emerge over time."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .components import components
from .similarity import link_scores
from .truss import k_truss, with_ids


def split_edges(edges: DataFrame, holdout: int = 10) -> tuple[DataFrame, DataFrame]:
    """(train, test): one edge in `holdout` by a hash of its ends is held out."""
    h = F.pmod(F.xxhash64(F.lit(5), "src", "dst"), F.lit(holdout))
    return edges.where(h != 0), edges.where(h == 0)


def link_prediction(edges: DataFrame, *, holdout: int = 10, kind: str = "adamic_adar", topk: int = 100) -> DataFrame:
    """(i, j, score, rank, hit): the topk best non-edges of the training part and whether they were held out."""
    train, test = split_edges(edges, holdout)
    s = link_scores(train, kind).join(train.select(F.col("src").alias("i"), F.col("dst").alias("j")), ["i", "j"], "left_anti")
    best = s.orderBy(F.col("score").desc(), "i", "j").limit(topk)
    hits = test.select(F.col("src").alias("i"), F.col("dst").alias("j"), F.lit(True).alias("_h"))
    return best.join(hits, ["i", "j"], "left").select("i", "j", "score", F.row_number().over(W.orderBy(F.col("score").desc(), "i", "j")).alias("rank"), F.coalesce("_h", F.lit(False)).alias("hit"))


def precision_at(predictions: DataFrame) -> DataFrame:
    return predictions.agg(F.avg(F.col("hit").cast("double")).alias("precision"))


def auc(edges: DataFrame, *, holdout: int = 10, kind: str = "adamic_adar") -> DataFrame:
    """Chance that a held-out edge scores above a scored non-edge, ties counting half: by score classes, without pairs."""
    train, test = split_edges(edges, holdout)
    s = link_scores(train, kind).join(train.select(F.col("src").alias("i"), F.col("dst").alias("j")), ["i", "j"], "left_anti")
    marked = test.select(F.col("src").alias("i"), F.col("dst").alias("j"), F.lit(1).alias("pos")).join(s, ["i", "j"], "full_outer").select(F.coalesce("pos", F.lit(0)).alias("pos"), F.round(F.coalesce("score", F.lit(0.0)), 9).alias("score"))
    classes = marked.groupBy("score").agg(F.sum("pos").alias("p"), F.sum(1 - F.col("pos")).alias("n"))
    ranked = classes.withColumn("below", F.sum("n").over(W.orderBy("score")) - F.col("n"))
    return ranked.agg((F.sum(F.col("p") * (F.col("below") + F.col("n") / 2)) / (F.sum("p") * F.sum("n"))).alias("auc"))


def emerging_communities(edges_t: DataFrame, *, k: int = 3, min_overlap: float = 0.1) -> DataFrame:
    """(window, community, size, previous, overlap) of edges (window, src, dst): communities are components of each
    window's k-truss; previous is the community of the window before with the largest Jaccard overlap, null for a new
    one. Windows are few; each is a graph of its own."""
    spark = edges_t.sparkSession
    out = None
    for r in edges_t.select("window").distinct().orderBy("window").toLocalIterator():
        e = edges_t.where(F.col("window") == r["window"]).select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).where("src < dst").distinct()
        t, _ = k_truss(with_ids(e), k)
        c = components(t).select(F.lit(r["window"]).alias("window"), "id", F.col("component").alias("community"))
        out = c if out is None else out.unionByName(c)
    if out is None:
        return spark.createDataFrame([], "window bigint, community bigint, size bigint, previous bigint, overlap double")
    order = out.select("window").distinct().withColumn("n", F.dense_rank().over(W.orderBy("window")))
    members = out.join(F.broadcast(order), "window")
    size = members.groupBy("n", "window", "community").agg(F.count("*").alias("size"))
    shared = members.select("n", "id", "community").join(members.select((F.col("n") + 1).alias("n"), "id", F.col("community").alias("previous")), ["n", "id"]).groupBy("n", "community", "previous").agg(F.count("*").alias("both"))
    old = size.select((F.col("n") + 1).alias("n"), F.col("community").alias("previous"), F.col("size").alias("old"))
    scored = shared.join(size, ["n", "community"]).join(old, ["n", "previous"]).withColumn("overlap", F.col("both") / (F.col("size") + F.col("old") - F.col("both"))).where(F.col("overlap") >= min_overlap)
    best = scored.groupBy("n", "community").agg(F.max(F.struct("overlap", (-F.col("previous")).alias("p"))).alias("b")).select("n", "community", (-F.col("b.p")).alias("previous"), "b.overlap")
    return size.join(best, ["n", "community"], "left").select("window", "community", "size", "previous", F.coalesce("overlap", F.lit(0.0)).alias("overlap"))
