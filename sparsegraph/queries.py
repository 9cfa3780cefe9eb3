"""Registered queries over the given tables, each with the SQL that must give the same rows where SQL can express it."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from sparsegraph.functions.semiring import MAX_MIN, MAX_PLUS, MAX_TIMES, MIN_PLUS, OR_AND, PLUS_PAIR, PLUS_TIMES
from sparsegraph.functions.udaf import fold_by
from sparsegraph.operators import centrality, kernels as K, linalg, nmf as N, paths, prediction, schema as S, similarity, spectral, subgraph, traversal, truss
from sparsegraph.operators.metrics import products_below_diagonal, wasted_products
from sparsegraph.plans.expr import Leaf
from sparsegraph.plans.state import materialise
from sparsegraph.sources import workloads as G
from sparsegraph.sources.tables import read_table
from sparsegraph.streaming import graph as stream

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


# --- SQL fragments: graphs as common table expressions --------------------------------------------------------------------
OP = "op AS (SELECT DISTINCT l_orderkey AS e, l_partkey AS v FROM lineitem)"
COP1 = f"{OP}, c1 AS (SELECT a.v AS src, b.v AS dst, count(*) AS w FROM op a JOIN op b ON a.e = b.e AND a.v < b.v GROUP BY 1, 2)"
COP = f"{COP1}, cop AS MATERIALIZED (SELECT src, dst, w FROM c1 WHERE w >= 2)"
BOTH = "bw AS MATERIALIZED (SELECT src AS r, dst AS c FROM cop UNION ALL SELECT dst, src FROM cop)"
DEG = "deg AS MATERIALIZED (SELECT r AS id, count(*) AS d FROM bw GROUP BY 1)"
TRADE_LINES = "tl AS (SELECT c_nationkey AS src, s_nationkey AS dst, l_quantity AS qty, l_extendedprice AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey)"
TRADE = f"{TRADE_LINES}, trade AS (SELECT src, dst, count(*) AS w, sum(qty) AS qty FROM tl GROUP BY 1, 2)"
TRADE_GRAPH = f"{TRADE}, tp AS (SELECT CAST(least(src, dst) AS BIGINT) AS src, CAST(greatest(src, dst) AS BIGINT) AS dst, sum(w) AS w FROM trade WHERE src <> dst GROUP BY 1, 2), tm AS (SELECT count(*) AS n, sum(w) AS total FROM tp), cop AS MATERIALIZED (SELECT src, dst FROM tp, tm WHERE w * n >= total)"
PS = "ps AS (SELECT l_partkey AS r, l_suppkey AS c, sum(l_quantity) AS v FROM lineitem GROUP BY 1, 2)"
SUCC = "ev AS (SELECT event_id, user_id, epoch_us(ts) AS us FROM events), nx AS (SELECT user_id AS src, lead(user_id) OVER (ORDER BY us, event_id) AS dst, lead(us) OVER (ORDER BY us, event_id) - us AS gap FROM ev), succ AS MATERIALIZED (SELECT src, dst, count(*) AS w, min(gap) AS gap_us FROM nx WHERE dst IS NOT NULL GROUP BY 1, 2)"
XE = "xe AS (SELECT event_id AS r, unnest(['event_type|' || event_type, 'user_id|' || CAST(user_id AS VARCHAR), 'k|' || (props ->> '$.k')]) AS c FROM events)"
TOKENS = "tok AS (SELECT doc_id, unnest(string_split_regex(lower(text), '[ \\t\\n\\r\\f\\v]+')) AS term FROM documents)"
LINKS = "pl AS (SELECT url AS src, dst, count(*) AS w FROM (SELECT url, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS dst FROM pages) GROUP BY 1, 2)"


def chain(first: str, step: Callable[[int], str], n: int, name: str = "s") -> str:
    """CTEs name0 .. name{n}, each from the one before."""
    return f"{name}0 AS MATERIALIZED ({first}), " + ", ".join(f"{name}{k + 1} AS MATERIALIZED ({step(k)})" for k in range(n))


def r6(c) -> F.Column:
    return F.round(c, 6)


# --- the worked graph ---------------------------------------------------------------------------------------------------------


@query(f"WITH {TRADE_GRAPH}, {BOTH}, c AS (SELECT t.src, t.dst, count(*) AS n FROM cop t JOIN bw a ON a.r = t.src JOIN bw b ON b.r = t.dst AND b.c = a.c GROUP BY 1, 2) SELECT cop.src * 100 + cop.dst AS edge_id, CAST(coalesce(n, 0) AS BIGINT) AS support FROM cop LEFT JOIN c ON cop.src = c.src AND cop.dst = c.dst")
def toy_support(spark, d):
    """Support through the incidence product, on the graph of nations that trade much."""
    return truss.edge_support(materialise(G.trade_graph(spark, d), "edges"), "incidence").select("edge_id", "support")


@query("SELECT CAST(edge_id AS BIGINT) AS edge_id, CAST(support AS BIGINT) AS support FROM (VALUES (1, 1), (2, 1), (3, 1), (4, 1), (5, 2)) v(edge_id, support)")
def toy_ktruss3(spark, d):
    return truss.k_truss(G.toy5(spark), 3, method="incidence")[0].select("edge_id", "support")


@query(f"WITH {TRADE_GRAPH}, {BOTH}, g AS (SELECT r AS id, count(*) AS d FROM bw GROUP BY 1), c AS (SELECT a.r AS i, b.r AS j, count(*) AS n FROM bw a JOIN bw b ON a.c = b.c AND a.r < b.r GROUP BY 1, 2) SELECT i, j, n AS common, round(n / (x.d + y.d - n), 6) AS score FROM c JOIN g x ON x.id = i JOIN g y ON y.id = j")
def toy_jaccard(spark, d):
    """From the products of triangular parts, on the graph of nations that trade much."""
    e = materialise(G.trade_graph(spark, d).select("src", "dst"), "edges")
    return similarity.jaccard(e, split=True).select("i", "j", "common", r6("score").alias("score"))


@query("SELECT CAST(id AS BIGINT) AS id, CAST(pre AS BIGINT) AS pre, CAST(post AS BIGINT) AS post FROM (VALUES (1, 0, 4), (2, 1, 3), (3, 2, 1), (4, 3, 0), (5, 4, 2)) v(id, pre, post)")
def dfs_toy(spark, d):
    return traversal.dfs(S.both_ways(G.toy5(spark).select("src", "dst")), 1)


@query(f"WITH RECURSIVE {TRADE_GRAPH}, {BOTH}, walk(id, level) AS (SELECT min(r), 0 FROM bw UNION ALL SELECT e.c, walk.level + 1 FROM walk JOIN bw e ON e.r = walk.id WHERE walk.level < 4) SELECT id, min(level) AS level FROM walk GROUP BY 1")
def bfs_sql(spark, d):
    """As recursive SQL, from the first of the nations that trade much."""
    a = materialise(S.both_ways(G.trade_graph(spark, d).select("src", "dst")).select("row", "col"), "adjacency")
    a.createOrReplaceTempView("adj_trade")
    return traversal.bfs_sql(spark, "adj_trade", a.agg(F.min("row")).first()[0], 4)


# --- schemas --------------------------------------------------------------------------------------------------------------------


@query(f"WITH {XE} SELECT r AS row, c AS col, CAST(1 AS BIGINT) AS val FROM xe WHERE c IS NOT NULL")
def exploded_edge(spark, d):
    return G.exploded_events(spark, d).edge


@query(f"WITH {XE} SELECT c AS col, count(*) AS degree FROM xe WHERE c IS NOT NULL GROUP BY 1")
def exploded_degree(spark, d):
    return G.exploded_events(spark, d).deg


@query(f"WITH {XE}, h AS (SELECT r FROM xe WHERE c = 'event_type|' || (SELECT min(event_type) FROM events)) SELECT c AS col, count(*) AS count FROM xe WHERE r IN (SELECT r FROM h) AND starts_with(c, 'k|') GROUP BY 1")
def exploded_facet(spark, d):
    first = read_table(spark, d, "events").agg(F.min("event_type")).first()[0]
    return S.facet(G.exploded_events(spark, d), f"event_type|{first}", "k|")


@query("WITH e AS (SELECT c_custkey AS r, unnest(['c_nationkey|' || CAST(c_nationkey AS VARCHAR), 'c_mktsegment|' || c_mktsegment]) AS c FROM customer) SELECT a.c AS row, b.c AS col, count(*) AS val FROM e a JOIN e b ON a.r = b.r WHERE starts_with(a.c, 'c_nationkey|') AND starts_with(b.c, 'c_mktsegment|') GROUP BY 1, 2")
def exploded_correlate(spark, d):
    return S.correlate(G.exploded_customer(spark, d), "c_nationkey|", "c_mktsegment|")


@query(f"WITH {XE}, h AS (SELECT r FROM xe WHERE c = 'k|7') SELECT event_id, event_type, user_id FROM events WHERE event_id IN (SELECT r FROM h)")
def raw_lookup(spark, d):
    t = G.exploded_events(spark, d)
    return S.raw_join(K.spref(t.edge, cols=["k|7"]).select(F.col("row").alias("id")), t.raw, "event_id").select("event_id", "event_type", "user_id")


@query(f"WITH {TRADE} SELECT src, dst, w, round(qty, 2) AS qty FROM trade")
def adj_nation_trade(spark, d):
    return G.nation_trade(spark, d).select("src", "dst", "w", F.round("qty", 2).alias("qty"))


@query(f"WITH {TRADE} SELECT src AS id, w AS val FROM trade WHERE src = dst")
def adj_self_loops(spark, d):
    return K.diag(S.adjacency(G.trade_lines(spark, d)))


@query(f"WITH {SUCC}, e AS (SELECT src * 1000000 + dst AS e, src, dst, w FROM succ WHERE src <> dst) SELECT e AS row, src AS col, -w AS val FROM e UNION ALL SELECT e, dst, w FROM e")
def inc_signed(spark, d):
    e = G.user_succession(spark, d).withColumn("edge_id", F.col("src") * 1000000 + F.col("dst"))
    return S.incidence(e, oriented=True, weight=F.col("w"), loops="drop")


@query(f"WITH {COP} SELECT src AS row, dst AS col, CAST(1 AS BIGINT) AS val FROM cop UNION ALL SELECT dst, src, 1 FROM cop")
def inc_to_adj(spark, d):
    return S.inc_to_adj(S.incidence(truss.with_ids(G.copurchase(spark, d))))


@query(f"WITH {COP}, {BOTH}, {DEG} SELECT id AS row, id AS col, d AS val FROM deg UNION ALL SELECT r, c, -1 FROM bw")
def laplacian(spark, d):
    return S.laplacian(S.incidence(truss.with_ids(G.copurchase(spark, d)), oriented=True))


@query(f"WITH {SUCC} SELECT DISTINCT least(src, dst) AS src, greatest(src, dst) AS dst FROM succ WHERE src <> dst")
def simple_graph(spark, d):
    return S.simple_graph(G.user_succession(spark, d))


@query(f"WITH {LINKS} SELECT src, dst, w FROM pl")
def page_link(spark, d):
    return G.page_link(spark, d)


@query("SELECT conv_id, turn, nt AS next_turn, role || '>' || nr AS roles FROM (SELECT conv_id, turn, role, lead(turn) OVER w AS nt, lead(role) OVER w AS nr FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE nt IS NOT NULL")
def conv_reply(spark, d):
    return G.conv_reply(spark, d).select("src.conv_id", "src.turn", F.col("dst.turn").alias("next_turn"), "roles")


@query("SELECT * FROM (SELECT 'r' || CAST(n_regionkey AS VARCHAR) AS src, 'n' || CAST(n_nationkey AS VARCHAR) AS dst FROM nation UNION ALL SELECT 'n' || CAST(c_nationkey AS VARCHAR), 'c' || CAST(c_custkey AS VARCHAR) FROM customer UNION ALL SELECT 'n' || CAST(s_nationkey AS VARCHAR), 's' || CAST(s_suppkey AS VARCHAR) FROM supplier)")
def geo_tree(spark, d):
    return G.geo_tree(spark, d)


# --- kernels ----------------------------------------------------------------------------------------------------------------------


@query(f"WITH {PS}, o AS (SELECT DISTINCT l_suppkey AS s, l_partkey AS p FROM lineitem) SELECT a.s AS row, b.s AS col, count(*) AS val FROM o a JOIN o b ON a.p = b.p GROUP BY 1, 2")
def spgemm_copart(spark, d):
    """Suppliers by the number of parts that both supply."""
    a = K.apply(G.part_supplier(spark, d), lambda v: F.lit(1).cast("bigint"))
    return K.spgemm(K.transpose(a), a, PLUS_PAIR)


@query(f"WITH {TRADE} SELECT a.src AS row, b.dst AS col, CAST(min(a.w + b.w) AS BIGINT) AS val FROM trade a JOIN trade b ON a.dst = b.src GROUP BY 1, 2")
def spgemm_min_plus(spark, d):
    t = K.triples(G.nation_trade(spark, d), "src", "dst", "w")
    return K.spgemm(t, t, MIN_PLUS)


@query(f"WITH {COP}, {BOTH} SELECT a.r AS row, b.c AS col, count(*) AS val FROM bw a JOIN bw b ON a.c = b.r JOIN cop m ON m.src = a.r AND m.dst = b.c GROUP BY 1, 2")
def spgemm_masked(spark, d):
    """Common neighbours of adjacent vertices: the mask drops wedges before they are counted."""
    e = materialise(G.copurchase(spark, d).select("src", "dst"), "edges")
    a = S.both_ways(e)
    return K.spgemm(a, a, PLUS_PAIR, mask=e.select(F.col("src").alias("row"), F.col("dst").alias("col")))


@query(f"WITH {PS} SELECT r AS id, round(sum(v * s_acctbal), 2) AS val FROM ps JOIN supplier ON c = s_suppkey GROUP BY 1")
def spmv_qty(spark, d):
    x = read_table(spark, d, "supplier").select(F.col("s_suppkey").alias("id"), F.col("s_acctbal").alias("val"))
    return K.spmv(G.part_supplier(spark, d), x).select("id", F.round("val", 2).alias("val"))


@query(f"WITH {SUCC} SELECT DISTINCT dst AS id, true AS val FROM succ WHERE src IN (0, 1, 2)")
def spmspv_or_and(spark, d):
    a = G.user_succession(spark, d).select(F.col("src").alias("row"), F.col("dst").alias("col"), F.lit(True).alias("val"))
    return K.spmspv(a, spark.createDataFrame([(i, True) for i in range(3)], "id bigint, val boolean"), OR_AND)


@query(f"WITH {TRADE}, b AS (SELECT s_nationkey AS r, c_nationkey AS c, count(*) AS n FROM supplier JOIN customer ON s_nationkey = c_nationkey GROUP BY 1, 2) SELECT src AS row, dst AS col, w * n AS val FROM trade JOIN b ON src = r AND dst = c")
def ewise_mult(spark, d):
    s, c = read_table(spark, d, "supplier"), read_table(spark, d, "customer")
    n, m = s.groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("n")), c.groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("m"))
    b = n.join(m, "k").select(F.col("k").alias("row"), F.col("k").alias("col"), (F.col("n") * F.col("m")).alias("val"))
    return K.ewise_mult(K.triples(G.nation_trade(spark, d), "src", "dst", "w"), b)


@query(f"WITH {TRADE} SELECT row, col, CAST(sum(val) AS BIGINT) AS val FROM (SELECT src AS row, dst AS col, w AS val FROM trade UNION ALL SELECT dst, src, w FROM trade) GROUP BY 1, 2")
def ewise_add(spark, d):
    t = K.triples(G.nation_trade(spark, d), "src", "dst", "w")
    return K.ewise_add(t, K.transpose(t))


@query(f"WITH {TRADE}, j AS (SELECT coalesce(a.src, b.dst) AS row, coalesce(a.dst, b.src) AS col, coalesce(a.w, 0) - coalesce(b.w, 0) AS val FROM trade a FULL JOIN trade b ON a.src = b.dst AND a.dst = b.src) SELECT row, col, CAST(val AS BIGINT) AS val FROM j WHERE val <> 0")
def ewise_sub(spark, d):
    t = K.triples(G.nation_trade(spark, d), "src", "dst", "w")
    return K.ewise_sub(t, K.transpose(t))


@query(f"WITH {TRADE} SELECT a.src AS row, a.dst AS col, round(a.w / b.w, 6) AS val FROM trade a JOIN trade b ON a.src = b.dst AND a.dst = b.src")
def ewise_div(spark, d):
    t = K.triples(G.nation_trade(spark, d), "src", "dst", "w")
    return K.ewise_div(t, K.transpose(t)).select("row", "col", r6("val").alias("val"))


@query(f"WITH {PS} SELECT r AS row, c AS col, v AS val FROM ps WHERE r IN (1, 5, 9)")
def spref_rows(spark, d):
    return K.spref(G.part_supplier(spark, d), rows=[1, 5, 9])


@query(f"WITH {PS} SELECT r AS row, c AS col, v AS val FROM ps WHERE r NOT IN (SELECT p_partkey FROM part WHERE p_size < 45)")
def spref_complement(spark, d):
    small = read_table(spark, d, "part").where("p_size < 45").select(F.col("p_partkey").alias("id"))
    return K.spref(G.part_supplier(spark, d), rows=small, complement_rows=True)


@query(f"WITH {PS} SELECT r AS row, c AS col, v AS val FROM ps WHERE r BETWEEN 10 AND 40 AND c BETWEEN 2 AND 30")
def spref_range(spark, d):
    return K.spref(G.part_supplier(spark, d), rows=K.Range(10, 40), cols=K.Range(2, 30))


@query(f"WITH {XE} SELECT r AS row, c AS col, CAST(1 AS BIGINT) AS val FROM xe WHERE starts_with(c, 'event_type|')")
def spref_prefix(spark, d):
    return K.spref(G.exploded_events(spark, d).edge, cols=K.Prefix("event_type|"))


@query(f"WITH {TRADE}, i AS (SELECT src, dst, w FROM trade WHERE src <= 4 AND dst <= 4) SELECT src AS row, dst AS col, w AS val FROM trade WHERE NOT (src <= 4 AND dst <= 4) UNION ALL SELECT dst, src, w * 10 FROM i")
def spasgn_block(spark, d):
    t = K.triples(G.nation_trade(spark, d), "src", "dst", "w")
    block = K.Range(0, 4)
    return K.spasgn(t, K.scale(K.transpose(K.spref(t, block, block)), 10), block, block)


@query(f"WITH {TRADE} SELECT src AS row, dst AS col, w * 3 AS val FROM trade")
def scale_const(spark, d):
    return K.scale(K.triples(G.nation_trade(spark, d), "src", "dst", "w"), 3)


@query(f"WITH {PS} SELECT r AS row, c AS col, v AS val FROM ps WHERE v >= 50")
def apply_threshold(spark, d):
    return K.apply(G.part_supplier(spark, d), lambda v: F.when(v >= 50, v).otherwise(0))


@query(f"WITH {PS}, x AS (SELECT r, c, CASE WHEN v >= 60 THEN 'high' WHEN v >= 30 THEN 'mid' ELSE NULL END AS v FROM ps) SELECT r AS row, c AS col, v AS val FROM x WHERE v IS NOT NULL")
def apply_case(spark, d):
    return K.apply(G.part_supplier(spark, d), lambda v: F.when(v >= 60, "high").when(v >= 30, "mid"), None)


@query(f"WITH {PS} SELECT r AS id, sum(v) AS val FROM ps GROUP BY 1")
def reduce_rows(spark, d):
    return K.reduce_rows(G.part_supplier(spark, d))


@query(f"WITH {TRADE} SELECT src AS row, dst AS col, w AS val FROM trade WHERE src < dst")
def triu_strict(spark, d):
    return K.triu(K.triples(G.nation_trade(spark, d), "src", "dst", "w"), 1)


@query(f"WITH {TRADE} SELECT src AS id, CAST(max(w) AS BIGINT) AS val FROM trade GROUP BY 1")
def reduce_max(spark, d):
    return K.reduce_rows(K.triples(G.nation_trade(spark, d), "src", "dst", "w"), F.max)


@query(f"WITH {TRADE} SELECT dst AS id, CAST(sum(w) AS BIGINT) AS val FROM trade GROUP BY 1")
def transpose_sum(spark, d):
    return K.reduce_rows(K.transpose(K.triples(G.nation_trade(spark, d), "src", "dst", "w")))


@query(f"WITH {PS} SELECT round(sqrt(sum(v * v)), 6) AS val FROM ps")
def norm_fro(spark, d):
    return K.norm_fro(G.part_supplier(spark, d)).select(r6("val").alias("val"))


@query(f"WITH {COP}, {BOTH} SELECT a.r AS row, b.r AS col, count(*) AS val FROM bw a JOIN bw b ON a.c = b.c AND a.r < b.r GROUP BY 1, 2")
def spgemm_upper(spark, d):
    u = G.copurchase(spark, d).select(F.col("src").alias("row"), F.col("dst").alias("col"), F.lit(1).cast("bigint").alias("val"))
    return K.spgemm_sym(u, PLUS_PAIR)


@query(f"WITH {COP}, {BOTH} SELECT a.r AS row, b.c AS col, count(*) AS val FROM bw a JOIN bw b ON a.c = b.r JOIN bw m ON m.r = a.r AND m.c = b.c GROUP BY 1, 2")
def expr_masked_square(spark, d):
    """The same product through the rewriting expression tree: squaring, mask and pattern arithmetic are planned once."""
    a = Leaf(materialise(S.both_ways(G.copurchase(spark, d).select("src", "dst")), "adjacency"), pattern=True)
    return ((a.T @ a) * a).lower()


@query(f"WITH {TRADE}, " + chain("SELECT src AS r, dst AS c, CAST(w AS BIGINT) AS v FROM trade", lambda k: f"SELECT a.r, b.c, min(a.v + b.v) AS v FROM s{k} a JOIN s{k} b ON a.c = b.r GROUP BY 1, 2", 2) + " SELECT r AS row, c AS col, CAST(v AS BIGINT) AS val FROM s2")
def matpow_min_plus(spark, d):
    t = K.triples(G.nation_trade(spark, d), "src", "dst", "w")
    return K.matpow(t, 4, MIN_PLUS)


# --- centrality -----------------------------------------------------------------------------------------------------------------------


def adjacency(spark, d, min_orders=2) -> DataFrame:
    return S.both_ways(G.copurchase(spark, d, min_orders).select("src", "dst"))


def user_adjacency(spark, d) -> DataFrame:
    return K.triples(G.user_succession(spark, d), "src", "dst", "w")


@query(f"WITH {SUCC} SELECT dst AS id, count(*) AS degree FROM succ GROUP BY 1")
def degree_in(spark, d):
    return centrality.degree(user_adjacency(spark, d), "in")


@query(f"WITH {SUCC} SELECT src AS id, CAST(sum(w) AS BIGINT) AS degree FROM succ GROUP BY 1")
def degree_out(spark, d):
    return centrality.degree(user_adjacency(spark, d), "out", weighted=True)


@query(f"WITH {COP}, {BOTH} SELECT p_partkey AS id, count(r) AS degree FROM part LEFT JOIN bw ON p_partkey = r GROUP BY 1")
def degree_total(spark, d):
    """Of a simple graph, with the vertices that have no edge."""
    e = G.copurchase(spark, d).select(F.col("src").alias("row"), F.col("dst").alias("col"), F.lit(1).cast("bigint").alias("val"))
    return centrality.degree(e, "total", vertices=read_table(spark, d, "part").select(F.col("p_partkey").alias("id")))


@query("SELECT user_id AS id, count(DISTINCT event_type) AS degree FROM events GROUP BY 1")
def degree_distinct(spark, d):
    return read_table(spark, d, "events").groupBy(F.col("user_id").alias("id")).agg(F.count_distinct("event_type").alias("degree"))


@query(f"WITH {COP}, {BOTH}, {DEG} SELECT count(*) AS n, round(avg(d), 6) AS mean, round(stddev_samp(d), 6) AS sd, CAST(max(d) AS BIGINT) AS most, CAST(quantile_disc(d, 0.5) AS BIGINT) AS mid FROM deg")
def degree_stats(spark, d):
    g = centrality.degree(adjacency(spark, d))
    return g.agg(F.count("*").alias("n"), r6(F.avg("degree")).alias("mean"), r6(F.stddev_samp("degree")).alias("sd"), F.max("degree").alias("most"), F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY degree)").cast("bigint").alias("mid"))


@query(f"WITH {COP}, {BOTH}, {DEG} SELECT id, d AS degree, CAST(rank() OVER (ORDER BY d DESC) AS INTEGER) AS rank, CAST(dense_rank() OVER (ORDER BY d DESC) AS INTEGER) AS dense FROM deg")
def window_rank_degree(spark, d):
    """Ranks over the degree classes (few), joined to the vertices: no task orders all vertices."""
    g = centrality.degree(adjacency(spark, d))
    w = W.orderBy(F.col("degree").desc())
    classes = g.groupBy("degree").agg(F.count("*").alias("n")).select("degree", (F.sum("n").over(w) - F.col("n") + 1).cast("int").alias("rank"), F.row_number().over(w).alias("dense"))
    return g.join(classes, "degree").select("id", "degree", "rank", "dense")


@query(f"WITH {COP}, {BOTH}, {DEG} SELECT d AS degree, count(*) AS n FROM deg GROUP BY 1")
def degree_histogram(spark, d):
    return centrality.degree(adjacency(spark, d)).groupBy("degree").agg(F.count("*").alias("n"))


POWER = chain("SELECT id, CAST(1 AS DOUBLE) AS x FROM deg", lambda k: f"SELECT bw.r AS id, sum(s.x) AS x FROM bw JOIN s{k} s ON bw.c = s.id GROUP BY 1", 10)


@query(f"WITH {COP}, {BOTH}, {DEG}, {POWER} SELECT id, round(x / sqrt((SELECT sum(x * x) FROM s10)), 6) AS score FROM s10")
def eigenvector_copurchase(spark, d):
    v, _ = centrality.eigenvector(adjacency(spark, d), fixed_steps=10)
    return v.select("id", r6("score").alias("score"))


KATZ = chain("SELECT id, CAST(1 AS DOUBLE) AS d, CAST(0 AS DOUBLE) AS x FROM deg", lambda k: f"SELECT s.id, t.d, s.x + power(0.01, {k}) * t.d AS x FROM s{k} s JOIN (SELECT bw.r AS id, sum(p.d) AS d FROM bw JOIN s{k} p ON bw.c = p.id GROUP BY 1) t ON s.id = t.id", 6)


@query(f"WITH {COP}, {BOTH}, {DEG}, {KATZ} SELECT id, round(x, 6) AS score FROM s6")
def katz_copurchase(spark, d):
    v, _ = centrality.katz(adjacency(spark, d), 0.01, fixed_steps=6)
    return v.select("id", r6("score").alias("score"))


def pagerank_sql(edges: str, src: str, dst: str, w: str, steps: int, jump: float, digits: int = 9) -> str:
    v = f"v AS MATERIALIZED (SELECT {src} AS id FROM {edges} UNION SELECT {dst} FROM {edges}), n AS (SELECT count(*) AS n FROM v), o AS MATERIALIZED (SELECT {src} AS id, sum({w}) AS t FROM {edges} GROUP BY 1), p AS MATERIALIZED (SELECT {src} AS s, {dst} AS t, {w} / o.t AS p FROM {edges} JOIN o ON {src} = o.id)"
    step = lambda k: f"SELECT v.id, {jump} / n.n + (1 - {jump}) * (coalesce(y.y, 0) + coalesce((SELECT sum(x) FROM s{k} WHERE id NOT IN (SELECT id FROM o)), 0) / n.n) AS x FROM v CROSS JOIN n LEFT JOIN (SELECT p.t AS id, sum(p.p * s.x) AS y FROM p JOIN s{k} s ON p.s = s.id GROUP BY 1) y ON v.id = y.id"
    return f"{v}, {chain('SELECT id, 1.0 / n.n AS x FROM v CROSS JOIN n', step, steps)} SELECT id, round(x, {digits}) AS score FROM s{steps}"


@query(f"WITH {SUCC}, {pagerank_sql('succ', 'src', 'dst', 'w', 10, 0.15)}")
def pagerank_users(spark, d):
    v, _ = centrality.pagerank(user_adjacency(spark, d), jump=0.15, fixed_steps=10)
    return v.select("id", F.round("score", 9).alias("score"))


@query(f"WITH {LINKS}, {pagerank_sql('pl', 'src', 'dst', 'w', 8, 0.15)}")
def pagerank_pages(spark, d):
    """Text keys; every target is dangling."""
    v, _ = centrality.pagerank(K.triples(G.page_link(spark, d), "src", "dst", "w"), jump=0.15, fixed_steps=8)
    return v.select("id", F.round("score", 9).alias("score"))


@query(f"WITH {COP}, {BOTH}, {pagerank_sql('(SELECT r, c, 1 AS w FROM bw)', 'r', 'c', 'w', 10, 0.0)}")
def pagerank_nojump(spark, d):
    v, _ = centrality.pagerank(adjacency(spark, d), jump=0.0, fixed_steps=10)
    return v.select("id", F.round("score", 9).alias("score"))


@query(f"WITH {SUCC}, z AS ({'WITH ' + pagerank_sql('succ', 'src', 'dst', 'w', 10, 0.15)}) SELECT id, score FROM z ORDER BY score DESC, id LIMIT 10")
def topk_pagerank(spark, d):
    return pagerank_users(spark, d).orderBy(F.col("score").desc(), "id").limit(10)


def levels_sql(edges: str, r: str, c: str, sources: str, n: int) -> str:
    """Levels of a search from many sources: (src, id, level)."""
    return chain(f"SELECT id AS src, id, 0 AS level FROM ({sources})", lambda k: f"SELECT src, id, min(level) AS level FROM (SELECT src, id, level FROM s{k} UNION ALL SELECT s.src, e.{c}, s.level + 1 FROM s{k} s JOIN {edges} e ON e.{r} = s.id WHERE s.level = {k}) GROUP BY 1, 2", n)


@query(f"WITH {COP}, {BOTH}, {DEG}, {levels_sql('bw', 'r', 'c', 'SELECT id FROM deg WHERE id % 50 = 0', 40)} SELECT src AS id, round(count(*) / sum(level), 6) AS score FROM s40 WHERE level > 0 GROUP BY 1")
def closeness_sample(spark, d):
    """From every fiftieth vertex: a sampling operator."""
    a = materialise(adjacency(spark, d), "adjacency")
    src = centrality.endpoints(a).where("id % 50 = 0")
    return centrality.closeness(a, src).select("id", r6("score").alias("score"))


@query()
def closeness_all(spark, d):
    """Of every vertex, in blocks of sources."""
    a = materialise(adjacency(spark, d), "adjacency")
    return centrality.by_source_blocks(a, centrality.closeness).select("id", r6("score").alias("score"))


@query()
def betweenness_all(spark, d):
    """Paths from every vertex, in blocks of sources."""
    a = materialise(adjacency(spark, d), "adjacency")
    return centrality.by_source_blocks(a, centrality.betweenness).select("id", r6("score").alias("score"))


@query()
def betweenness_sample(spark, d):
    """From one vertex in fifty by hash, with scores divided by the share of sources taken: an estimate of
    betweenness_all."""
    a = materialise(adjacency(spark, d), "adjacency")
    ids = centrality.endpoints(a)
    src = materialise(ids.where(F.pmod(F.xxhash64("id"), F.lit(50)) == 0), "sources")
    scale = ids.count() / max(src.count(), 1)
    return centrality.betweenness(a, src).select("id", r6(F.col("score") * F.lit(scale)).alias("score"))


# --- trusses ----------------------------------------------------------------------------------------------------------------------------


def support_sql(e: str) -> str:
    return f"SELECT e.src, e.dst, count(x.c) AS support FROM {e} e LEFT JOIN (SELECT a.r AS p, b.r AS q, a.c FROM (SELECT src AS r, dst AS c FROM {e} UNION ALL SELECT dst, src FROM {e}) a JOIN (SELECT src AS r, dst AS c FROM {e} UNION ALL SELECT dst, src FROM {e}) b ON a.c = b.c) x ON x.p = e.src AND x.q = e.dst GROUP BY 1, 2"


def truss_sql(start: str, k: int, rounds: int, name: str) -> str:
    return chain(f"SELECT src, dst FROM {start}", lambda i: f"SELECT src, dst FROM ({support_sql(f'{name}{i}')}) WHERE support >= {k - 2}", rounds, name)


def edges2(spark, d) -> DataFrame:
    return truss.with_ids(G.copurchase(spark, d).select("src", "dst"))


@query(f"WITH {COP} {support_sql('cop')}")
def edge_support_copurchase(spark, d):
    return truss.edge_support(materialise(edges2(spark, d), "edges"), "incidence").select("src", "dst", "support")


@query(f"WITH {COP} {support_sql('cop')}")
def edge_support_masked(spark, d):
    return truss.edge_support(materialise(edges2(spark, d), "edges"), "masked").select("src", "dst", "support")


@query(f"WITH {COP}, t AS ({support_sql('cop')}) SELECT support, count(*) AS n FROM t GROUP BY 1")
def support_histogram(spark, d):
    return edge_support_masked(spark, d).groupBy("support").agg(F.count("*").alias("n"))


@query(f"WITH {COP}, {truss_sql('cop', 3, 4, 'k')} {support_sql('k4')}")
def ktruss_k3(spark, d):
    return truss.k_truss(edges2(spark, d), 3)[0].select("src", "dst", "support")


@query(f"WITH {COP}, {truss_sql('cop', 4, 8, 'k')} {support_sql('k8')}")
def ktruss_k4(spark, d):
    return truss.k_truss(edges2(spark, d), 4)[0].select("src", "dst", "support")


@query(f"WITH {COP}, {truss_sql('cop', 3, 4, 'k')} {support_sql('k4')}")
def ktruss_incidence(spark, d):
    return truss.k_truss(edges2(spark, d), 3, method="incidence", update="incremental")[0].select("src", "dst", "support")


@query(f"WITH {COP}, {truss_sql('cop', 3, 4, 'k')} {support_sql('k4')}")
def ktruss_recompute(spark, d):
    return truss.k_truss(edges2(spark, d), 3, method="incidence", update="recompute")[0].select("src", "dst", "support")


@query(f"WITH {COP}, {truss_sql('cop', 4, 8, 'k')} {support_sql('k8')}")
def ktruss_ordered(spark, d):
    return truss.k_truss(edges2(spark, d), 4, method="ordered")[0].select("src", "dst", "support")


@query(f"WITH {COP}, {truss_sql('cop', 3, 4, 'k')}, {truss_sql('k4', 4, 8, 'm')}, {truss_sql('m8', 5, 32, 'p')} SELECT c.src, c.dst, 2 + (k.src IS NOT NULL)::INT + (m.src IS NOT NULL)::INT + (p.src IS NOT NULL)::INT AS trussness FROM cop c LEFT JOIN k4 k ON c.src = k.src AND c.dst = k.dst LEFT JOIN m8 m ON c.src = m.src AND c.dst = m.dst LEFT JOIN p32 p ON c.src = p.src AND c.dst = p.dst")
def truss_decomposition(spark, d):
    return truss.truss_decomposition(edges2(spark, d)).select("src", "dst", "trussness")


@query(f"WITH {COP}, {BOTH}, {DEG}, w AS (SELECT CAST(sum(d * (d - 1) // 2) AS BIGINT) AS wedges FROM deg), t AS (SELECT count(*) AS triangles FROM cop a JOIN cop b ON a.dst = b.src JOIN cop c ON c.src = a.src AND c.dst = b.dst) SELECT wedges, triangles, wedges - 3 * triangles AS wasted FROM w CROSS JOIN t")
def wasted_work(spark, d):
    return wasted_products(materialise(edges2(spark, d), "edges"))


@query(f"WITH {COP}, {BOTH}, {DEG} SELECT CAST(sum(d * d) AS BIGINT) AS total, CAST(sum(d * d - d * (d - 1) // 2) AS BIGINT) AS below FROM deg")
def lower_triangle_work(spark, d):
    return products_below_diagonal(G.copurchase(spark, d).select("src", "dst"))


TRIPLES = "w3 AS MATERIALIZED (SELECT a.src AS v1, a.dst AS v2, b.dst AS v3 FROM cop a JOIN cop b ON b.src = a.dst), t3 AS MATERIALIZED (SELECT w3.v1, w3.v2, w3.v3 FROM w3 SEMI JOIN cop ON cop.src = w3.v1 AND cop.dst = w3.v3)"


@query(f"WITH {COP}, {TRIPLES}, w4 AS MATERIALIZED (SELECT a.v1, a.v2, a.v3, b.v3 AS v4 FROM t3 a JOIN t3 b ON a.v1 = b.v1 AND a.v2 = b.v2 AND a.v3 < b.v3) SELECT v1, v2, v3, v4 FROM w4 SEMI JOIN cop ON cop.src = w4.v3 AND cop.dst = w4.v4")
def k_clique4(spark, d):
    return subgraph.k_cliques(G.copurchase(spark, d).select("src", "dst"), 4)


@query(f"WITH {COP}, {TRIPLES} SELECT v1, v2, v3 FROM t3")
def k_clique3(spark, d):
    return subgraph.k_cliques(G.copurchase(spark, d).select("src", "dst"), 3)


@query(f"WITH {TRADE_GRAPH}, {truss_sql('cop', 6, 8, 'k')}, left_ AS ({support_sql('k8')}) SELECT src * 100 + dst AS edge_id, support FROM left_")
def toy_ktruss_sequential(spark, d):
    """One edge at a time, on the graph of nations that trade much: for comparison with the simultaneous peel."""
    return truss.k_truss(G.trade_graph(spark, d), 6, method="sequential")[0].select("edge_id", "support")


@query("SELECT size, members FROM (VALUES (3, '1,2,3'), (3, '1,3,4'), (2, '2,5')) v(size, members)")
def toy_maximal_cliques(spark, d):
    found = subgraph.maximal_cliques(G.toy5(spark).select("src", "dst"))
    return found.select("size", F.array_join("members", ",").alias("members"))


@query("SELECT pair, verdict FROM (VALUES ('relabelled', 'yes'), ('one edge less', 'no'), ('other shape', 'no')) v(pair, verdict)")
def toy_isomorphism(spark, d):
    """The worked graph against itself under new names, without an edge, and against one of the same size."""
    e = G.toy5(spark).select("src", "dst")
    renamed = S.simple_graph(e.select(((F.col("src") * 3) % 7 + 10).alias("src"), ((F.col("dst") * 3) % 7 + 10).alias("dst")))
    ring = spark.createDataFrame([(1, 2), (2, 3), (3, 4), (4, 5), (1, 5), (1, 3)], "src bigint, dst bigint")
    others = {"relabelled": renamed, "one edge less": e.where("src <> 1 or dst <> 3"), "other shape": ring}
    return spark.createDataFrame([(k, similarity.isomorphic(e, g)) for k, g in others.items()], "pair string, verdict string")


@query()
def toy_matching(spark, d):
    """The nations that trade much matched with those of a renamed copy of their graph."""
    e = materialise(G.trade_graph(spark, d).select("src", "dst"), "edges")
    return similarity.neighbor_matching(e, e.select((F.col("src") + 100).alias("src"), (F.col("dst") + 100).alias("dst")))


@query()
def planted_clique_found(spark, d):
    """(method, k, found): of twelve vertices made a clique, how many each method names."""
    edges, members = subgraph.plant(G.copurchase(spark, d).select("src", "dst"), 12)
    edges = materialise(edges, "planted")
    parts = [subgraph.planted_clique(edges, 12, m).join(members, "id", "left_semi").agg(F.lit(m).alias("method"), F.lit(12).alias("k"), F.count("*").alias("found")) for m in ("truss", "degree", "spectral")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


LABELS = chain("SELECT id, id AS l FROM deg", lambda k: f"SELECT s.id, least(s.l, t.l) AS l FROM s{k} s JOIN (SELECT bw.r AS id, min(p.l) AS l FROM bw JOIN s{k} p ON bw.c = p.id GROUP BY 1) t ON s.id = t.id", 40)


@query(f"WITH {COP}, {BOTH}, {DEG}, {LABELS} SELECT id, l AS component FROM s40")
def components_copurchase(spark, d):
    return subgraph.components(G.copurchase(spark, d))


@query(f"WITH {COP}, {BOTH}, cues AS (SELECT p_partkey AS id FROM part WHERE p_size = 10), s AS (SELECT c AS id, CAST(count(*) AS DOUBLE) AS score FROM bw WHERE r IN (SELECT id FROM cues) AND c NOT IN (SELECT id FROM cues) GROUP BY 1) SELECT id, score, CAST(row_number() OVER (ORDER BY score DESC, id) AS INTEGER) AS rank FROM s ORDER BY score DESC, id LIMIT 20")
def nominate_parts(spark, d):
    cues = read_table(spark, d, "part").where("p_size = 10").select(F.col("p_partkey").alias("id"))
    return subgraph.nominate(adjacency(spark, d), cues, top=20)


@query()
def nominate_ppr(spark, d):
    cues = read_table(spark, d, "part").where("p_size = 10").select(F.col("p_partkey").alias("id"))
    return subgraph.nominate(adjacency(spark, d), cues, "ppr", top=20)


@query(f"WITH {TOKENS}, b AS (SELECT DISTINCT doc_id, term FROM tok WHERE term <> ''), f AS (SELECT term FROM b GROUP BY 1 HAVING count(*) >= 5), a AS (SELECT b.* FROM b JOIN f ON b.term = f.term), q AS (SELECT doc_id FROM labels WHERE toxic = 1), t AS (SELECT term, count(*) AS n FROM a WHERE doc_id IN (SELECT doc_id FROM q) GROUP BY 1), s AS (SELECT a.doc_id AS id, CAST(sum(n) AS DOUBLE) AS score FROM a JOIN t ON a.term = t.term WHERE a.doc_id NOT IN (SELECT doc_id FROM q) GROUP BY 1) SELECT id, score, CAST(row_number() OVER (ORDER BY score DESC, id) AS INTEGER) AS rank FROM s ORDER BY score DESC, id LIMIT 50")
def nominate_docs(spark, d):
    """Documents by the terms they share with documents labelled toxic: two sparse products through the terms, A (A^T x)."""
    a = N.doc_term(read_table(spark, d, "documents"))
    cues = read_table(spark, d, "labels").where("toxic = 1").select(F.col("doc_id").alias("id"), F.lit(1.0).alias("val"))
    s = K.spmv(a, K.vxm(cues, a)).select("id", F.col("val").alias("score")).join(cues, "id", "left_anti")
    best = s.orderBy(F.col("score").desc(), "id").limit(50)
    return best.withColumn("rank", F.row_number().over(W.orderBy(F.col("score").desc(), "id")))


@query(f"WITH {TOKENS}, b AS (SELECT DISTINCT doc_id, term FROM tok WHERE term <> ''), f AS (SELECT term FROM b GROUP BY 1 HAVING count(*) BETWEEN 2 AND 50), i AS (SELECT DISTINCT item_id, term FROM (SELECT item_id, unnest(string_split_regex(lower(text), '[ \\t\\n\\r\\f\\v]+')) AS term FROM benchmark) WHERE term <> '') SELECT i.item_id AS row, b.doc_id AS col, count(*) AS val FROM i JOIN f ON i.term = f.term JOIN b ON b.term = f.term GROUP BY 1, 2")
def benchmark_doc_overlap(spark, d):
    """Items by documents: shared terms that 2 to 50 documents hold (the band that tells documents apart)."""
    a = N.doc_term(read_table(spark, d, "documents"), min_df=2).select("row", "col", F.lit(1).cast("bigint").alias("val"))
    rare = a.groupBy(F.col("col").alias("id")).agg(F.count("*").alias("n")).where("n <= 50").select("id")
    b = N.doc_term(read_table(spark, d, "benchmark"), id_col="item_id", min_df=1).select("row", "col", F.lit(1).cast("bigint").alias("val"))
    return K.spgemm(K.spref(b, cols=rare), K.transpose(a), PLUS_PAIR)


@query(f"WITH {TOKENS}, b AS (SELECT DISTINCT doc_id, term FROM tok WHERE term <> ''), i AS (SELECT DISTINCT item_id, term FROM (SELECT item_id, unnest(string_split_regex(lower(text), '[ \\t\\n\\r\\f\\v]+')) AS term FROM benchmark) WHERE term <> '') SELECT i.item_id AS row, b.doc_id AS col, count(*) AS val FROM i JOIN b ON b.term = i.term GROUP BY 1, 2")
def benchmark_doc_overlap_all(spark, d):
    """Items by documents: all shared terms, however many documents hold them."""
    a = N.doc_term(read_table(spark, d, "documents"), min_df=1).select("row", "col")
    b = N.doc_term(read_table(spark, d, "benchmark"), id_col="item_id", min_df=1).select("row", "col")
    return similarity.shared_columns(b, a)


# --- similarity and prediction --------------------------------------------------------------------------------------------------------

JAC = "jac AS (SELECT a.r AS i, b.r AS j, count(*) AS common FROM bw a JOIN bw b ON a.c = b.c AND a.r < b.r GROUP BY 1, 2), js AS (SELECT i, j, common, common / (x.d + y.d - common) AS score FROM jac JOIN deg x ON x.id = i JOIN deg y ON y.id = j)"


@query(f"WITH {COP}, {BOTH}, {DEG}, {JAC} SELECT i, j, common, round(score, 6) AS score FROM js")
def jaccard_upper(spark, d):
    return similarity.jaccard(G.copurchase(spark, d).select("src", "dst")).select("i", "j", "common", r6("score").alias("score"))


@query(f"WITH {COP}, {BOTH}, {DEG}, {JAC} SELECT i, j, common, round(score, 6) AS score FROM js")
def jaccard_split(spark, d):
    return similarity.jaccard(G.copurchase(spark, d).select("src", "dst"), split=True).select("i", "j", "common", r6("score").alias("score"))


@query(f"WITH {COP}, {BOTH}, {DEG}, {JAC} SELECT i, j, round(score, 6) AS score FROM js UNION ALL SELECT j, i, round(score, 6) FROM js")
def jaccard_full(spark, d):
    return similarity.jaccard(G.copurchase(spark, d).select("src", "dst"), symmetric=True).select("i", "j", r6("score").alias("score"))


@query(f"WITH {COP}, {BOTH}, {DEG}, {JAC}, full_ AS (SELECT i, j, score FROM js UNION ALL SELECT j, i, score FROM js), r AS (SELECT i, j, round(score, 6) AS score, CAST(row_number() OVER (PARTITION BY i ORDER BY score DESC, j) AS INTEGER) AS rank FROM full_) SELECT * FROM r WHERE rank <= 3")
def jaccard_topk(spark, d):
    s = similarity.jaccard(G.copurchase(spark, d).select("src", "dst"), symmetric=True)
    return similarity.top_k(s, 3).select("i", "j", r6("score").alias("score"), "rank")


@query(f"WITH {COP1}, cop AS (SELECT src, dst FROM c1 WHERE src < 60 AND dst < 60), {BOTH}, {DEG}, {JAC} SELECT i, j, common, round(score, 6) AS score FROM js")
def jaccard_dense_small(spark, d):
    """The dense ratio, on a small block: a baseline."""
    e = materialise(G.copurchase(spark, d, 1).select("src", "dst").where("src < 60 and dst < 60"), "edges")
    return similarity.jaccard(e, "dense").select("i", "j", "common", r6("score").alias("score"))


@query(f"WITH {COP1}, cop AS (SELECT src, dst FROM c1 WHERE src < 60 AND dst < 60), {BOTH}, {DEG}, {JAC} SELECT i, j, common, round(score, 6) AS score FROM js")
def jaccard_sets(spark, d):
    e = materialise(G.copurchase(spark, d, 1).select("src", "dst").where("src < 60 and dst < 60"), "edges")
    return similarity.jaccard(e, "sets").select("i", "j", "common", r6("score").alias("score"))


@query(f"WITH {COP}, {BOTH}, {DEG}, {JAC} SELECT i, j, common, round(score, 6) AS score FROM js")
def jaccard_sets_all(spark, d):
    """By definition, over all co-purchase edges."""
    e = materialise(G.copurchase(spark, d).select("src", "dst"), "edges")
    return similarity.jaccard(e, "sets").select("i", "j", "common", r6("score").alias("score"))


@query(f"WITH {COP}, {BOTH}, {DEG}, {JAC} SELECT i, j, common, round(score, 6) AS score FROM js")
def jaccard_dense_all(spark, d):
    """The dense ratio over all co-purchase edges, tile by tile."""
    e = materialise(G.copurchase(spark, d).select("src", "dst"), "edges")
    return similarity.jaccard(e, "dense").select("i", "j", "common", r6("score").alias("score"))


@query(f"WITH {COP}, {BOTH}, {DEG}, {JAC} SELECT i, j, round(score, 6) AS score FROM js WHERE score >= 0.5 AND NOT EXISTS (SELECT 1 FROM cop WHERE src = i AND dst = j)")
def jaccard_links(spark, d):
    """Pairs that are no edge yet, of a score of at least 0.5; the degree bound prunes wedges before the shuffle."""
    e = materialise(G.copurchase(spark, d).select("src", "dst"), "edges")
    return similarity.jaccard(e, min_score=0.5, only_non_edges=True).select("i", "j", r6("score").alias("score"))


@query(f"WITH {COP}, {BOTH}, {DEG} SELECT a.r AS i, b.r AS j, round(sum(1 / ln(d)), 6) AS score FROM bw a JOIN bw b ON a.c = b.c AND a.r < b.r JOIN deg ON id = a.c GROUP BY 1, 2")
def link_scores_aa(spark, d):
    return similarity.link_scores(G.copurchase(spark, d).select("src", "dst")).select("i", "j", r6("score").alias("score"))


@query(f"WITH {COP}, {BOTH}, {DEG} SELECT a.r AS i, b.r AS j, round(sum(1 / d), 6) AS score FROM bw a JOIN bw b ON a.c = b.c AND a.r < b.r JOIN deg ON id = a.c GROUP BY 1, 2")
def link_scores_ra(spark, d):
    return similarity.link_scores(G.copurchase(spark, d).select("src", "dst"), "resource_allocation").select("i", "j", r6("score").alias("score"))


@query(f"WITH {COP}, {BOTH}, {DEG} SELECT a.r AS i, b.r AS j, round(count(*) / sqrt(min(x.d) * min(y.d)), 6) AS score FROM bw a JOIN bw b ON a.c = b.c AND a.r < b.r JOIN deg x ON x.id = a.r JOIN deg y ON y.id = b.r GROUP BY 1, 2")
def link_scores_cosine(spark, d):
    return similarity.link_scores(G.copurchase(spark, d).select("src", "dst"), "cosine").select("i", "j", r6("score").alias("score"))


@query()
def link_prediction(spark, d):
    return prediction.link_prediction(materialise(G.copurchase(spark, d).select("src", "dst"), "edges"), topk=100)


@query()
def emerging_communities(spark, d):
    """Windows of a quarter of the orders' time span; edges are parts bought together in it."""
    o = read_table(spark, d, "orders").select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("window"))
    e = read_table(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct().join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    x, y = e.select("window", "l_orderkey", F.col("l_partkey").alias("src")), e.select("window", "l_orderkey", F.col("l_partkey").alias("dst"))
    pairs = x.join(y, ["window", "l_orderkey"]).where("src < dst").groupBy("window", "src", "dst").agg(F.count("*").alias("n")).where("n >= 1")
    return prediction.emerging_communities(materialise(pairs.select("window", "src", "dst"), "windows"))


WL = chain("SELECT id, sha256('v') AS colour FROM deg", lambda k: f"SELECT s.id, sha256(s.colour || '|' || t.near) AS colour FROM s{k} s JOIN (SELECT bw.r AS id, string_agg(p.colour, ',' ORDER BY p.colour) AS near FROM bw JOIN s{k} p ON bw.c = p.id GROUP BY 1) t ON s.id = t.id", 3)


@query(f"WITH {COP}, {BOTH}, {DEG}, {WL} SELECT id, colour FROM s3")
def wl_colours(spark, d):
    return similarity.colours(G.copurchase(spark, d).select("src", "dst"), 3)


COSINE = "e AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings)"


@query(f"WITH {COSINE} SELECT a.vec_id AS src, b.vec_id AS dst, round(list_cosine_similarity(a.v, b.v), 6) AS w FROM e a JOIN e b ON a.vec_id < b.vec_id WHERE list_cosine_similarity(a.v, b.v) > 0.3")
def embed_sim_pairs(spark, d):
    return G.embed_sim(spark, d, 0.3).select("src", "dst", r6("w").alias("w"))


# --- factorisation --------------------------------------------------------------------------------------------------------------------

GRAM2 = "g AS (SELECT sum(c_acctbal / 1000 * c_acctbal / 1000) AS a, sum(c_acctbal / 1000) AS b, CAST(count(*) AS DOUBLE) AS c FROM customer)"


@query(f"WITH {GRAM2} SELECT CAST(r AS INTEGER) AS row, CAST(s AS INTEGER) AS col, round(v * 1000, 6) AS val FROM (SELECT 0 AS r, 0 AS s, c / (a * c - b * b) AS v FROM g UNION ALL SELECT 0, 1, -b / (a * c - b * b) FROM g UNION ALL SELECT 1, 0, -b / (a * c - b * b) FROM g UNION ALL SELECT 1, 1, a / (a * c - b * b) FROM g)")
def inverse_gram(spark, d):
    """The inverse of a 2 x 2 Gram matrix by kernels alone, against the closed form."""
    x = F.col("c_acctbal") / 1000
    g = read_table(spark, d, "customer").agg(F.sum(x * x).alias("a"), F.sum(x).alias("b"), F.count("*").cast("double").alias("c"))
    cell = lambda i, j, c: F.struct(F.lit(i).alias("row"), F.lit(j).alias("col"), F.col(c).alias("val"))
    m = g.select(F.explode(F.array(cell(0, 0, "a"), cell(0, 1, "b"), cell(1, 0, "b"), cell(1, 1, "c"))).alias("x")).select("x.*")
    return linalg.inverse(m)[0].select("row", "col", r6(F.col("val") * 1000).alias("val"))


def _start(k: str, t: int) -> str:
    return f"CAST((({k} * 7919 + {t * 104729 + 1} + {k} * {31 * (t + 1)}) % 10007) + 1 AS DOUBLE) / 10008.0"


def _half(side: str, factor: str, name: str) -> str:
    """One clamped solve with the closed inverse of a 2 x 2 Gram matrix."""
    other = "term" if side == "doc_id" else "doc_id"
    return (
        f"g{name} AS MATERIALIZED (SELECT sum(w0 * w0) AS a, sum(w0 * w1) AS b, sum(w1 * w1) AS c FROM {factor}), "
        f"b{name} AS MATERIALIZED (SELECT m.{other} AS id, sum(f.w0) AS b0, sum(f.w1) AS b1 FROM m JOIN {factor} f ON f.id = m.{side} GROUP BY 1), "
        f"{name} AS MATERIALIZED (SELECT id, greatest((c * b0 - b * b1) / (a * c - b * b), 0) AS w0, greatest((a * b1 - b * b0) / (a * c - b * b), 0) AS w1 FROM b{name} CROSS JOIN g{name})"
    )


@query(f"WITH {TOKENS}, u AS (SELECT DISTINCT doc_id, term FROM tok WHERE term <> ''), m AS MATERIALIZED (SELECT u.* FROM u JOIN (SELECT term FROM u GROUP BY 1 HAVING count(*) >= 5) f ON u.term = f.term), w_0 AS (SELECT DISTINCT doc_id AS id, {_start('doc_id', 0)} AS w0, {_start('doc_id', 1)} AS w1 FROM m), {_half('doc_id', 'w_0', 'h_1')}, {_half('term', 'h_1', 'w_1')}, {_half('doc_id', 'w_1', 'h_2')}, {_half('term', 'h_2', 'w_2')} SELECT id AS doc_id, round(w0, 6) AS w0, round(w1, 6) AS w1 FROM w_2")
def nmf_docterm_k2(spark, d):
    return _docterm_k2(spark, d, "newton")


def _docterm_k2(spark, d, solver: str) -> DataFrame:
    model = N.nmf(N.doc_term(read_table(spark, d, "documents")), 2, solver=solver, max_iter=2, rel_tol=0.0)
    return model.W.select(F.col("id").alias("doc_id"), r6("w0").alias("w0"), r6("w1").alias("w1"))


@query(ORACLES["nmf_docterm_k2"])
def nmf_docterm_k2_cg(spark, d):
    return _docterm_k2(spark, d, "cg")


@query(ORACLES["nmf_docterm_k2"])
def nmf_docterm_k2_qr(spark, d):
    return _docterm_k2(spark, d, "qr")


def topics(spark, d):
    return N.nmf(N.doc_term(read_table(spark, d, "documents")), 5, max_iter=10)


@query()
def nmf_topics_k5(spark, d):
    """(document, topic, weight)."""
    return N.communities(topics(spark, d))


@query()
def topic_terms(spark, d):
    return N.topic_terms(topics(spark, d), 10)


@query()
def topic_table(spark, d):
    """Topic against language."""
    truth = read_table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("label"))
    return N.topic_table(N.communities(topics(spark, d)), truth)


@query()
def topic_purity(spark, d):
    truth = read_table(spark, d, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("label"))
    return N.purity(N.communities(topics(spark, d)), truth)


@query()
def nmf_residual(spark, d):
    """The error after every sweep, with the steps of the inversions."""
    m = topics(spark, d)
    rows = [(h["sweep"], h["error"], h["relative"], h["steps_h"], h["steps_w"], len(h["dead"])) for h in m.history]
    return spark.createDataFrame(rows, "sweep int, error double, relative double, steps_h int, steps_w int, dead int")


@query()
def nmf_recommend(spark, d):
    a = materialise(G.customer_part(spark, d), "counts")
    return N.recommend(N.nmf(a, 3, max_iter=4), a, 3)


@query()
def pca_embeddings(spark, d):
    e = read_table(spark, d, "embeddings").select(F.col("embedding").cast("array<double>").alias("vec"))
    return spectral.pca(e, 5, 64)[0].select("component", "explained")


@query()
def svd_docterm(spark, d):
    _, s, _ = spectral.svd(N.doc_term(read_table(spark, d, "documents")), 4)
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(s)], "component int, value double")


@query()
def svd_lanczos(spark, d):
    """The values of svd_docterm, from single vectors."""
    _, s, _ = spectral.svd(N.doc_term(read_table(spark, d, "documents")), 4, method="lanczos")
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(s)], "component int, value double")


# --- traversal and paths --------------------------------------------------------------------------------------------------------------

USER0 = "SELECT min(src) AS id FROM succ"


@query(f"WITH {SUCC}, {levels_sql('succ', 'src', 'dst', USER0, 12)} SELECT s.id, s.level, min(p.id) AS parent FROM s12 s LEFT JOIN succ e ON e.dst = s.id AND s.level > 0 LEFT JOIN s12 p ON p.id = e.src AND p.level = s.level - 1 GROUP BY 1, 2")
def bfs_levels(spark, d):
    a = materialise(user_adjacency(spark, d), "adjacency")
    source = a.agg(F.min("row").alias("id"))
    return traversal.bfs(a, source).select("id", "level", "parent")


DIST = chain(f"SELECT id, CAST(0 AS DOUBLE) AS d FROM ({USER0})", lambda k: f"SELECT id, min(d) AS d FROM (SELECT id, d FROM s{k} UNION ALL SELECT e.dst, s.d + e.gap_us FROM s{k} s JOIN succ e ON e.src = s.id) GROUP BY 1", 40)


@query(f"WITH {SUCC}, {DIST} SELECT id, d AS dist FROM s40")
def sssp_users(spark, d):
    """Least sum of gaps (microseconds) from the first user."""
    a = materialise(K.triples(G.user_succession(spark, d), "src", "dst", "gap_us"), "adjacency")
    return paths.bellman_ford(a, a.agg(F.min("row")).first()[0])


COST = f"{TRADE}, cost AS MATERIALIZED (SELECT src AS r, dst AS c, CAST(1000000 // w AS DOUBLE) AS v FROM trade)"
APSP = chain("SELECT r, c, min(v) AS v FROM (SELECT r, c, v FROM cost UNION ALL SELECT n_nationkey, n_nationkey, 0.0 FROM nation) GROUP BY 1, 2", lambda k: f"SELECT a.r, b.c, min(a.v + b.v) AS v FROM s{k} a JOIN s{k} b ON a.c = b.r GROUP BY 1, 2", 5)


def trade_cost(spark, d) -> DataFrame:
    return G.nation_trade(spark, d).select(F.col("src").alias("row"), F.col("dst").alias("col"), F.expr("cast(1000000 div w as double)").alias("val"))


def nations(spark, d) -> DataFrame:
    return read_table(spark, d, "nation").select(F.col("n_nationkey").alias("id"))


@query(f"WITH {COST}, {APSP} SELECT r AS row, c AS col, v AS val FROM s5")
def apsp_nation(spark, d):
    return paths.apsp(materialise(trade_cost(spark, d), "cost"), nations(spark, d))


@query(f"WITH {COST}, {APSP} SELECT r AS row, c AS col, v AS val FROM s5")
def floyd_warshall_nation(spark, d):
    return paths.floyd_warshall(trade_cost(spark, d), nations(spark, d))


@query(f"WITH {COST}, {APSP} SELECT r AS row, c AS col, v AS val FROM s5")
def johnson_nation(spark, d):
    return paths.johnson(materialise(trade_cost(spark, d), "cost"), nations(spark, d))


RELY = chain("SELECT r, c, max(v) AS v FROM (SELECT src AS r, dst AS c, 1 - 1.0 / (1 + w) AS v FROM trade UNION ALL SELECT n_nationkey, n_nationkey, 1.0 FROM nation) GROUP BY 1, 2", lambda k: f"SELECT a.r, b.c, max(a.v * b.v) AS v FROM s{k} a JOIN s{k} b ON a.c = b.r GROUP BY 1, 2", 5)


@query(f"WITH {TRADE}, {RELY} SELECT c AS id, round(v, 9) AS dist FROM s5 WHERE r = 0")
def reliable_path(spark, d):
    a = G.nation_trade(spark, d).select(F.col("src").alias("row"), F.col("dst").alias("col"), (1 - 1 / (1 + F.col("w"))).alias("val"))
    return paths.best_path(materialise(a, "cost"), 0, MAX_TIMES).select("id", F.round("dist", 9).alias("dist"))


@query(f"WITH {COST}, {APSP} SELECT v AS dist FROM s5 WHERE r = 0 AND c = 24")
def astar_nation(spark, d):
    """From nation 0 to nation 24, with bounds from two landmarks."""
    a = materialise(trade_cost(spark, d), "cost")
    dist = paths.astar(a, 0, 24, paths.landmark_bound(a, 24, [5, 24]))
    return spark.createDataFrame([] if dist is None else [(dist,)], "dist double")


WIDE = chain("SELECT src AS r, dst AS c, CAST(w AS DOUBLE) AS v FROM trade WHERE src <> dst", lambda k: f"SELECT r, c, max(v) AS v FROM (SELECT r, c, v FROM s{k} UNION ALL SELECT a.r, b.c, least(a.v, b.v) FROM s{k} a JOIN s{k} b ON a.c = b.r) GROUP BY 1, 2", 5)


@query(f"WITH {TRADE}, {WIDE} SELECT c AS id, v AS dist FROM s5 WHERE r = 0 AND c <> 0")
def widest_path(spark, d):
    """From nation 0: the largest least trade on a path."""
    a = G.nation_trade(spark, d).where("src <> dst").select(F.col("src").alias("row"), F.col("dst").alias("col"), F.col("w").cast("double").alias("val"))
    return paths.best_path(materialise(a, "width"), 0, MAX_MIN).where("id <> 0").select("id", "dist")


LONG = chain("SELECT src AS r, dst AS c, CAST(w AS DOUBLE) AS v FROM trade WHERE src < dst", lambda k: f"SELECT r, c, max(v) AS v FROM (SELECT r, c, v FROM s{k} UNION ALL SELECT a.r, b.c, a.v + b.v FROM s{k} a JOIN s{k} b ON a.c = b.r) GROUP BY 1, 2", 5)


@query(f"WITH {TRADE}, {LONG} SELECT c AS id, v AS dist FROM s5 WHERE r = 0")
def critical_path(spark, d):
    """From nation 0 along edges to larger numbers alone: the largest sum of trade."""
    a = G.nation_trade(spark, d).where("src < dst").select(F.col("src").alias("row"), F.col("dst").alias("col"), F.col("w").cast("double").alias("val"))
    return paths.best_path(materialise(a, "length"), 0, MAX_PLUS).where("id <> 0").select("id", "dist")


# --- surrounding relational operators -------------------------------------------------------------------------------------------------


@query(f"WITH {TRADE_LINES} SELECT src, dst, grouping(src) * 2 + grouping(dst) AS level, count(*) AS w FROM tl GROUP BY CUBE (src, dst)")
def cube_trade(spark, d):
    return G.trade_lines(spark, d).cube("src", "dst").agg(F.grouping_id().alias("level"), F.count("*").alias("w"))


@query("SELECT r_name, n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def rollup_geo(spark, d):
    c, n, r = (read_table(spark, d, t) for t in ("customer", "nation", "region"))
    j = c.join(F.broadcast(n.join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))), F.col("c_nationkey") == F.col("n_nationkey"))  # nation and region are fixed lists
    return j.rollup("r_name", "n_name").agg(F.count("*").alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


@query(f"WITH {TRADE_LINES} SELECT src, dst, count(*) AS w FROM tl GROUP BY GROUPING SETS ((src), (dst), ())")
def grouping_sets_trade(spark, d):
    G.trade_lines(spark, d).createOrReplaceTempView("trade_lines")
    return spark.sql("SELECT src, dst, count(*) AS w FROM trade_lines GROUP BY GROUPING SETS ((src), (dst), ())")


@query(f"WITH {SUCC} SELECT src, max(w) AS w, CAST(arg_min(dst, -w * 1000000 + dst) AS BIGINT) AS dst FROM succ GROUP BY 1")
def top_edge_per_vertex(spark, d):
    best = F.min(F.struct((-F.col("w")).alias("w"), "dst"))
    return G.user_succession(spark, d).groupBy("src").agg(best.alias("b")).select("src", (-F.col("b.w")).alias("w"), "b.dst")


@query(f"WITH {TRADE_LINES} SELECT src, count(*) FILTER (WHERE dst = 0) AS d0, count(*) FILTER (WHERE dst = 1) AS d1, count(*) FILTER (WHERE dst = 2) AS d2 FROM tl WHERE dst < 3 GROUP BY 1")
def trade_block(spark, d):
    t = G.trade_lines(spark, d).where("dst < 3").groupBy("src").pivot("dst", [0, 1, 2]).agg(F.count(F.lit(1)))
    return t.select("src", *[F.coalesce(str(k), F.lit(0)).alias(f"d{k}") for k in range(3)])


@query(f"WITH {TRADE_LINES} SELECT src, {', '.join(f'count(*) FILTER (WHERE dst = {k}) AS d{k}' for k in range(25))} FROM tl GROUP BY 1")
def trade_block_all(spark, d):
    """All nations: those of the table are the columns."""
    keys = sorted(r[0] for r in read_table(spark, d, "nation").select("n_nationkey").collect())
    t = G.trade_lines(spark, d).groupBy("src").pivot("dst", keys).agg(F.count(F.lit(1)))
    return t.select("src", *[F.coalesce(F.col(str(k)), F.lit(0)).alias(f"d{k}") for k in keys])


@query(f"WITH {TRADE_LINES} SELECT src, CAST(sum(CAST(price AS DECIMAL(18, 2))) AS DECIMAL(38, 2)) AS price FROM tl GROUP BY 1")
def trade_decimal_sum(spark, d):
    return G.trade_lines(spark, d).groupBy("src").agg(F.sum(F.col("price").cast("decimal(18,2)")).cast("decimal(38,2)").alias("price"))


@query(f"WITH {SUCC} SELECT src, dst, w, gap_us FROM succ")
def user_succession(spark, d):
    return G.user_succession(spark, d)


@query("SELECT event_id, user_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS seen FROM events")
def running_degree(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    return G.events(spark, d).select("event_id", "user_id", F.count("*").over(w).alias("seen"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def moving_range(spark, d):
    w = W.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return G.events(spark, d).select("event_id", F.count("*").over(w).alias("n"))


@query("WITH e AS (SELECT user_id, event_id, event_type, epoch_us(ts) AS us FROM events), g AS (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY user_id ORDER BY us, event_id) > 86400000000 THEN 1 ELSE 0 END AS cut FROM e), s AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY us, event_id ROWS UNBOUNDED PRECEDING) AS sess FROM g) SELECT user_id, CAST(sess AS BIGINT) AS sess, count(*) AS n, arg_min(event_type, us) AS first, arg_max(event_type, us) AS last FROM s GROUP BY 1, 2")
def session_first_last(spark, d):
    by = W.partitionBy("user_id").orderBy("us", "event_id")
    e = G.events(spark, d).withColumn("cut", F.when(F.col("us") - F.lag("us").over(by) > 86_400_000_000, 1).otherwise(0))
    s = e.withColumn("sess", F.sum("cut").over(by.rowsBetween(W.unboundedPreceding, 0)))
    return s.groupBy("user_id", "sess").agg(F.count("*").alias("n"), F.min_by("event_type", "us").alias("first"), F.max_by("event_type", "us").alias("last"))


@query("SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND epoch_us(b.ts) - epoch_us(a.ts) <= 600000000")
def join_interval_events(spark, d):
    """Pairs of a user's events within ten minutes: equal user and time bucket (own or next), then the range."""
    e = G.events(spark, d).select("event_id", "user_id", "us", (F.col("us") / 600_000_000).cast("bigint").alias("bucket"))
    a = e.select("user_id", F.col("event_id").alias("first"), F.col("us").alias("t"), F.explode(F.array("bucket", F.col("bucket") + 1)).alias("bucket"))
    b = e.select("user_id", F.col("event_id").alias("second"), F.col("us").alias("u"), "bucket")
    return a.join(b, ["user_id", "bucket"]).where("u > t and u - t <= 600000000").select("first", "second")


@query("WITH t AS (SELECT min(event_type) AS a FROM events), v AS (SELECT event_id, user_id, ts FROM events, t WHERE event_type = a), o AS (SELECT event_id, user_id, ts FROM events, t WHERE event_type <> a) SELECT v.event_id, o.event_id AS before FROM v ASOF LEFT JOIN o ON v.user_id = o.user_id AND v.ts >= o.ts")
def join_asof_events(spark, d):
    """For each event of one type the user's latest earlier event of another type: one sort for each user, no pairs."""
    e = G.events(spark, d)
    kind = e.agg(F.min("event_type")).first()[0]
    w = W.partitionBy("user_id").orderBy("us", "event_id").rowsBetween(W.unboundedPreceding, 0)
    other = F.last(F.when(F.col("event_type") != kind, F.col("event_id")), ignorenulls=True).over(w)
    return e.select("event_id", "event_type", other.alias("before")).where(F.col("event_type") == kind).select("event_id", "before")


ONE, TWO = "SELECT DISTINCT src, dst FROM succ WHERE w >= 2", "SELECT DISTINCT dst AS src, src AS dst FROM succ"


def patterns(spark, d):
    s = materialise(G.user_succession(spark, d), "succession")
    return s.where("w >= 2").select("src", "dst"), s.select(F.col("dst").alias("src"), F.col("src").alias("dst"))


@query(f"WITH {SUCC} {ONE} UNION {TWO}")
def setops_union(spark, d):
    a, b = patterns(spark, d)
    return a.union(b).distinct()


@query(f"WITH {SUCC} {ONE} INTERSECT {TWO}")
def setops_intersect(spark, d):
    a, b = patterns(spark, d)
    return a.intersect(b)


@query(f"WITH {SUCC} {ONE} EXCEPT {TWO}")
def setops_except(spark, d):
    a, b = patterns(spark, d)
    return a.subtract(b)


@query(f"WITH {TOKENS} SELECT doc_id, count(*) AS tokens, count(DISTINCT term) AS terms FROM tok WHERE term <> '' GROUP BY 1")
def doc_tokens(spark, d):
    t = read_table(spark, d, "documents").select("doc_id", F.filter(F.split(F.lower("text"), r"[ \t\n\r\f\x0b]+"), lambda x: x != "").alias("t"))
    return t.select("doc_id", F.size("t").cast("bigint").alias("tokens"), F.size(F.array_distinct("t")).cast("bigint").alias("terms")).where("tokens > 0")


@query("SELECT regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, count(*) AS pages FROM pages GROUP BY 1")
def page_hosts(spark, d):
    return read_table(spark, d, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count("*").alias("pages"))


@query("SELECT CAST(date_trunc('day', ts) AS DATE) AS day, event_type, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY 1, 2")
def events_daily_degree(spark, d):
    return G.events(spark, d).groupBy(F.to_date("ts").alias("day"), "event_type").agg(F.count("*").alias("n"), F.count_distinct("user_id").alias("users"))


@query("SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, count(*) AS orders, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY 1, 2")
def order_month_graph(spark, d):
    return read_table(spark, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count("*").alias("orders"), F.count_distinct("o_custkey").alias("customers"))


@query(f"WITH {COSINE} SELECT a.vec_id, round(list_cosine_similarity(a.v, b.v), 6) AS next_cosine FROM e a JOIN e b ON b.vec_id = a.vec_id + 1")
def cosine_pairs(spark, d):
    e = read_table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    b = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("v").alias("b"))
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    return e.join(b, "vec_id").select("vec_id", r6(dot("v", "b") / F.sqrt(dot("v", "v") * dot("b", "b"))).alias("next_cosine"))


@query("WITH c AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) SELECT user_id, string_agg(event_type || '=' || CAST(n AS VARCHAR), ',' ORDER BY event_type) AS degrees FROM c GROUP BY 1")
def degree_map(spark, d):
    c = read_table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = c.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    pairs = F.transform(F.array_sort(F.map_keys("m")), lambda k: F.concat(k, F.lit("="), F.element_at("m", k).cast("string")))
    return m.select("user_id", F.array_join(pairs, ",").alias("degrees"))


@query("SELECT CAST(props ->> '$.k' AS BIGINT) AS k, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1")
def props_json_facet(spark, d):
    k = F.from_json("props", T.StructType([T.StructField("k", T.LongType())]))["k"]
    return read_table(spark, d, "events").groupBy(k.alias("k")).agg(F.count("*").alias("n"), r6(F.avg("value")).alias("mean"))


@query("SELECT CAST(epoch_us(date_trunc('hour', ts)) AS BIGINT) AS start_us, user_id, event_type, count(*) AS w FROM events GROUP BY 1, 2, 3")
def tumbling_adjacency(spark, d):
    return stream.windowed_adjacency(G.events(spark, d)).select(F.unix_micros("start").alias("start_us"), "user_id", "event_type", "w")


@query("WITH e AS (SELECT user_id, epoch_us(ts) AS us FROM events), s AS (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY user_id ORDER BY us) >= 1800000000 THEN 1 ELSE 0 END AS cut FROM e), g AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY us ROWS UNBOUNDED PRECEDING) AS sess FROM s) SELECT min(us) AS start_us, max(us) + 1800000000 AS end_us, user_id, count(*) AS w FROM g GROUP BY user_id, sess")
def session_adjacency(spark, d):
    return stream.session_adjacency(G.events(spark, d)).select(F.unix_micros("start").alias("start_us"), F.unix_micros("end").alias("end_us"), "user_id", "w")


# --- labelled arrays, lateral joins, folds of one's own -----------------------------------------------------------------------


@query(f"WITH {COP}, {truss_sql('cop', 3, 4, 'k')}, t AS ({support_sql('k4')}) SELECT 'part|' || src AS row, 'part|' || dst AS col, support AS val FROM t UNION ALL SELECT 'part|' || dst, 'part|' || src, support FROM t")
def assoc_truss(spark, d):
    label = lambda c: F.concat(F.lit("part|"), F.col(c).cast("string"))
    parts = G.copurchase(spark, d).select(label("src").alias("a"), label("dst").alias("b"))
    return S.AssocArray.build(parts, "a", "b").truss(3).df.select("row", "col", "val")


@query("WITH t AS (SELECT user_id, event_type, CAST(ts AS DATE) AS day, count(*) AS n FROM events GROUP BY 1, 2, 3), u AS (SELECT user_id, event_type AS other, count(*) AS m FROM events GROUP BY 1, 2) SELECT event_type, day, other, CAST(sum(n * m) AS BIGINT) AS val FROM t JOIN u ON t.user_id = u.user_id GROUP BY 1, 2, 3")
def tensor_contract(spark, d):
    """Users, types and days as one array of three key sets, multiplied by users and types over the users."""
    t = S.AssocTensor.build(G.events(spark, d).withColumn("day", F.to_date("ts")), ["user_id", "event_type", "day"])
    u = t.reduce("user_id", "event_type")
    other = S.AssocTensor(u.df.withColumnRenamed("event_type", "other"), ["user_id", "other"])
    return t.contract(other, "user_id").df


@query("WITH t AS (SELECT DISTINCT user_id, event_type, CAST(ts AS DATE) AS day FROM events) SELECT event_type, count(*) AS cells FROM t GROUP BY 1")
def tensor_pattern(spark, d):
    t = S.AssocTensor.build(G.events(spark, d).withColumn("day", F.to_date("ts")), ["user_id", "event_type", "day"])
    return t.df.groupBy("event_type").agg(F.count("*").alias("cells"))


@query(f"WITH {COP}, bw AS (SELECT src AS r, dst AS c, w FROM cop UNION ALL SELECT dst, src, w FROM cop), t AS (SELECT r AS id, c AS near, w, row_number() OVER (PARTITION BY r ORDER BY w DESC, c) AS rank FROM bw WHERE r IN (SELECT p_partkey FROM part WHERE p_size = 10)) SELECT id, near, w FROM t WHERE rank <= 3")
def lateral_neighbours(spark, d):
    """The three strongest neighbours of each cue, by a lateral join."""
    e = G.copurchase(spark, d)
    both = e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")).toDF("r", "near", "w")
    cues = read_table(spark, d, "part").where("p_size = 10").select(F.col("p_partkey").alias("id"))
    best = both.where(F.col("r") == F.col("id").outer()).orderBy(F.col("w").desc(), "near").limit(3).select("near", "w")
    return cues.lateralJoin(best).select("id", "near", "w")


@query("SELECT event_type, count(DISTINCT user_id) AS users, TRUE AS near FROM events GROUP BY 1")
def degree_approx(spark, d):
    """Distinct users of each type, and whether the sketch of 2% deviation comes within 10%."""
    both = read_table(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("about"))
    return both.select("event_type", "users", (F.abs(F.col("about") - F.col("users")) <= F.greatest(F.lit(1.0), F.col("users") * 0.1)).alias("near"))


@query("WITH q AS (SELECT l_partkey AS id, CAST(l_quantity AS BIGINT) AS q FROM lineitem) SELECT id, CAST(max(d) AS BIGINT) AS val FROM (SELECT id, d FROM q, range(1, 101) r(d) GROUP BY 1, 2 HAVING bool_and(q % d = 0)) GROUP BY 1")
def reduce_user_monoid(spark, d):
    """The greatest common divisor of each part's quantities: an addition that only Python knows."""
    q = read_table(spark, d, "lineitem").select(F.col("l_partkey").alias("id"), F.col("l_quantity").cast("bigint").alias("val"))
    return fold_by(q, "id", "val", math.gcd)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
