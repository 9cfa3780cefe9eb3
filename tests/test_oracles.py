"""Registered queries against their SQL in DuckDB, on the smallest tables. The driver compares all of them at sf0.01; here
a part of each kind keeps the suite short."""

import datetime
import decimal
import os

import duckdb
import pytest

import __spark_entry__ as entry
from sparsegraph import queries as Q

D = "/root/testdata/sf0.001"
SOME = [
    "toy_support", "exploded_correlate", "raw_lookup", "inc_to_adj", "spgemm_min_plus", "spgemm_masked", "ewise_sub", "spref_prefix", "spasgn_block", "expr_masked_square",
    "degree_stats", "window_rank_degree", "katz_copurchase", "pagerank_pages", "edge_support_masked", "wasted_work", "jaccard_topk", "link_scores_aa", "wl_colours",
    "inverse_gram", "nmf_docterm_k2", "apsp_nation", "cube_trade", "rollup_geo", "grouping_sets_trade", "top_edge_per_vertex", "trade_block", "trade_decimal_sum", "user_succession",
    "moving_range", "session_first_last", "join_interval_events", "join_asof_events", "setops_except", "page_hosts", "events_daily_degree", "degree_map", "props_json_facet", "session_adjacency",
    "k_clique3", "k_clique4", "toy_ktruss_sequential", "toy_maximal_cliques", "toy_isomorphism", "astar_nation", "widest_path", "critical_path",
    "nmf_docterm_k2_cg", "nmf_docterm_k2_qr", "assoc_truss", "tensor_contract", "tensor_pattern", "lateral_neighbours", "degree_approx", "reduce_user_monoid",
]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for name in os.listdir(D):
        con.execute(f"CREATE VIEW {name.removesuffix('.parquet')} AS SELECT * FROM read_parquet('{D}/{name}')")
    return con


def norm(v):
    if isinstance(v, float):
        return round(v, 9) + 0.0
    if isinstance(v, (datetime.datetime, datetime.date, decimal.Decimal)):
        return str(v)
    return v


@pytest.mark.parametrize("name", SOME)
def test_query_equals_sql(spark, duck, name):
    df = Q.QUERIES[name](spark, D)
    cols = sorted(df.columns)
    r = duck.execute(Q.ORACLES[name])
    names = [x[0] for x in r.description]
    assert sorted(names) == cols
    got = sorted((tuple(norm(x[c]) for c in cols) for x in df.collect()), key=repr)
    want = sorted((tuple(norm(x[names.index(c)]) for c in cols) for x in r.fetchall()), key=repr)
    assert got == want


def test_entry_and_registry(spark):
    df = entry.entry(spark)
    assert df.columns == ["src", "dst", "support", "score"] and df.count() == 2244
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["jaccard_sets_all", "jaccard_dense_all", "trade_block_all", "benchmark_doc_overlap_all"])
def test_whole_tables_equal_sql(spark, duck, name):
    test_query_equals_sql(spark, duck, name)


def test_whole_tables_are_no_block(spark):
    assert Q.QUERIES["jaccard_sets_all"](spark, "/root/testdata/sf0.01").agg({"j": "max"}).first()[0] >= 60
    assert len(Q.QUERIES["trade_block_all"](spark, D).columns) == 26


@pytest.mark.parametrize("name", ["bfs_sql", "toy_jaccard", "toy_ktruss_sequential", "toy_matching", "toy_support"])
def test_worked_queries_read_every_line(spark, duck, name):
    from sparsegraph.operators.metrics import KernelStats

    with KernelStats(spark) as stats:
        if name in Q.ORACLES:
            test_query_equals_sql(spark, duck, name)
        else:
            nations = duck.execute(f"WITH {Q.TRADE_GRAPH} SELECT src FROM cop UNION SELECT dst FROM cop").fetchall()
            got = Q.QUERIES[name](spark, D).collect()
            assert {(r["u"],) for r in got} == set(nations) and {(r["v"] - 100,) for r in got} == set(nations) and len(got) == len(nations)
    assert stats.input_rows >= duck.execute("SELECT count(*) FROM lineitem").fetchone()[0]
