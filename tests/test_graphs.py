import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from sparsegraph import queries as Q
from sparsegraph.functions.semiring import MAX_MIN, MAX_PLUS
from sparsegraph.operators import centrality as C
from sparsegraph.operators import kernels as K
from sparsegraph.operators import metrics, paths, prediction, similarity, subgraph, traversal, truss
from sparsegraph.operators import schema as S
from sparsegraph.operators.components import components
from sparsegraph.sources.workloads import copurchase, toy5

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def toy(spark):
    return toy5(spark).cache()


@pytest.fixture(scope="module")
def adj(toy):
    return S.both_ways(toy).cache()


@pytest.fixture(scope="module")
def random_edges(spark):
    rng = np.random.default_rng(8)
    e = sorted({tuple(sorted(map(int, rng.choice(22, 2, replace=False)))) for _ in range(80)})
    return truss.with_ids(spark.createDataFrame(e, "src bigint, dst bigint")).cache()


def pairs(df):
    return {(r["src"], r["dst"]) for r in df.collect()}


def values(df, v, *keys):
    return {tuple(r[k] for k in keys) if len(keys) > 1 else r[keys[0]]: r[v] for r in df.collect()}


def dense(edges, n):
    a = np.zeros((n, n))
    for x, y in pairs(edges):
        a[x, y] = a[y, x] = 1
    return a


# --- worked examples -----------------------------------------------------------------------------------------------------


def test_worked_support_and_truss(toy):
    inc = S.incidence(toy)
    truss.check_unit(inc)
    r = truss.overlap_cells(inc, S.inc_to_adj(inc))
    assert values(r.where("val = 2").groupBy("row").count(), "count", "row") == {1: 1, 2: 1, 3: 1, 4: 1, 5: 2}
    assert values(C.degree(S.inc_to_adj(inc)), "degree", "id") == {1: 3, 2: 3, 3: 3, 4: 2, 5: 1}
    for method in ("incidence", "masked"):
        assert values(truss.edge_support(toy, method), "support", "edge_id") == {1: 1, 2: 1, 3: 1, 4: 1, 5: 2, 6: 0}
    left, report = truss.k_truss(toy, 3, method="incidence")
    assert {x["edge_id"] for x in left.collect()} == {1, 2, 3, 4, 5} and report.rounds == 1 and report.converged
    assert truss.k_truss(toy, 4)[0].count() == 0 and truss.k_truss(toy, 2)[0].count() == 6
    assert values(truss.truss_decomposition(toy), "trussness", "edge_id") == {1: 3, 2: 3, 3: 3, 4: 3, 5: 3, 6: 2}
    assert truss.wasted_products(toy).first()[:] == (10, 2, 4)


JACCARD = {(1, 2): 1 / 5, (1, 3): 1 / 2, (1, 4): 1 / 4, (1, 5): 1 / 3, (2, 3): 1 / 5, (2, 4): 2 / 3, (3, 4): 1 / 4, (3, 5): 1 / 3}


@pytest.mark.parametrize("kw", [{}, {"split": True}, {"method": "sets"}, {"method": "dense"}], ids=str)
def test_worked_jaccard(toy, kw):
    got = values(similarity.jaccard(toy.select("src", "dst"), **kw), "score", "i", "j")
    assert got == pytest.approx(JACCARD)


def test_worked_centralities(adj):
    close = lambda df, want: [values(df, "score", "id")[i] for i in range(1, 6)] == pytest.approx(want, abs=2e-6)
    v, report = C.eigenvector(adj, tol=1e-14)
    assert close(v, [0.537077, 0.474750, 0.537077, 0.406694, 0.179749]) and report.converged
    assert close(C.katz(adj, 0.1, tol=1e-12)[0], [4.085996, 3.956767, 4.085996, 2.817199, 1.395677])
    assert close(C.katz(adj, 0.1, x0=1.0, tol=1e-12)[0], [5.085996, 4.956767, 5.085996, 3.817199, 2.395677])
    assert close(C.katz(adj, 0.2, tol=1e-12)[0], [6.387435, 5.994764, 6.387435, 4.554974, 2.198953])
    assert close(C.pagerank(adj, jump=0.0, tol=1e-15)[0], [0.25, 0.25, 0.25, 0.166667, 0.083333])
    for ones in (False, True):
        assert close(C.pagerank(adj, jump=0.15, tol=1e-15, explicit_ones=ones, max_iter=40)[0], [0.240079, 0.252309, 0.240079, 0.166045, 0.101488])
    assert close(C.betweenness(adj), [1, 3, 1, 0, 0])
    assert values(C.closeness(adj), "score", "id")[2] == pytest.approx(4 / 5)


def test_awkward_graphs(spark, toy):
    doubled = S.simple_graph(toy.unionAll(toy.where("edge_id = 6")))
    looped = S.simple_graph(toy.select("src", "dst").unionAll(spark.createDataFrame([(3, 3)], "src bigint, dst bigint")))
    assert pairs(doubled) == pairs(looped) == pairs(toy)
    with pytest.raises(ValueError):
        truss.check_unit(S.incidence(toy, weight=F.lit(2)))
    path = S.both_ways(spark.createDataFrame([(1, 2), (2, 3), (3, 4)], "src bigint, dst bigint"))
    start = spark.createDataFrame([(1, 1.0), (2, 0.2)], "id bigint, val double")
    assert not C.eigenvector(path, x0=start, max_iter=25)[1].converged
    v, r = C.eigenvector(path, x0=start, shift=1.0, max_iter=80)
    assert r.converged and values(v, "score", "id")[2] == pytest.approx(0.601501, abs=1e-3)
    chain = spark.createDataFrame([(1, 2, 1), (2, 3, 1), (3, 4, 1)], "row bigint, col bigint, val bigint")
    assert C.eigenvector(chain, max_iter=10)[1].status == "vanished"
    for how in ("uniform", "self", "drop"):
        assert sum(values(C.pagerank(chain, dangling=how)[0], "score", "id").values()) == pytest.approx(1)
    with pytest.raises(ValueError):
        C.katz(S.both_ways(toy), 0.9)
    none = spark.createDataFrame([], "edge_id bigint, src bigint, dst bigint")
    assert truss.k_truss(none, 3)[0].count() == 0 and similarity.jaccard(none).count() == 0 and components(none).count() == 0
    assert truss.truss_decomposition(none).count() == 0
    iso = spark.range(7).select("id")
    assert values(C.degree(S.both_ways(toy), vertices=iso), "degree", "id")[6] == 0
    with pytest.raises(Exception, match="loop"):
        S.incidence(spark.createDataFrame([(1, 2, 2)], "edge_id bigint, src bigint, dst bigint"), oriented=True).collect()


# --- agreement of variants --------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("k", [3, 4, 5])
def test_truss_variants_agree(random_edges, k):
    want = values(truss.k_truss(random_edges, k)[0], "support", "src", "dst")
    for kw in ({"method": "incidence"}, {"method": "incidence", "update": "recompute"}, {"update": "recompute"}, {"method": "ordered"}, *([{"method": "sequential"}] if k == 3 else [])):
        assert values(truss.k_truss(random_edges, k, **kw)[0], "support", "src", "dst") == want, kw
    assert all(v >= k - 2 for v in want.values())
    below = pairs(truss.k_truss(random_edges, k - 1)[0])
    assert set(want) <= below
    left = set(pairs(random_edges))
    while True:
        sup = {e: sum(tuple(sorted((e[0], v))) in left and tuple(sorted((e[1], v))) in left for v in range(22)) for e in left}
        weak = {e for e, s in sup.items() if s < k - 2}
        if not weak:
            break
        left -= weak
    assert set(want) == left


def test_truss_sizes_of_the_given_table(spark):
    e = truss.with_ids(copurchase(spark, D).select("src", "dst")).cache()
    t = truss.truss_decomposition(e)
    size = lambda k: t.where(f"trussness >= {k}").count()
    assert [e.count(), size(3), size(4), size(5), size(6)] == [2324, 2244, 1966, 532, 0]


def test_jaccard_options(random_edges):
    e = random_edges.select("src", "dst")
    full = values(similarity.jaccard(e), "score", "i", "j")
    a = dense(e, 22)
    both, d = a @ a, a.sum(0)
    assert full == pytest.approx({(i, j): both[i, j] / (d[i] + d[j] - both[i, j]) for i in range(22) for j in range(i + 1, 22) if both[i, j]})
    assert values(similarity.jaccard(e, min_score=0.4), "score", "i", "j") == pytest.approx({k: v for k, v in full.items() if v >= 0.4})
    assert set(values(similarity.jaccard(e, only_non_edges=True), "score", "i", "j")) == set(full) - pairs(e)
    some = e.select(F.col("src").alias("i"), F.col("dst").alias("j"))
    assert set(values(similarity.jaccard(e, pairs=some), "score", "i", "j")) == set(full) & pairs(e)
    assert similarity.jaccard(e, symmetric=True).count() == 2 * len(full)
    near = values(similarity.jaccard(e, "minhash"), "score", "i", "j")
    assert all(full.get(k, v) == pytest.approx(v) for k, v in near.items())
    assert values(metrics.products_below_diagonal(e), "total", "below") == {int((d * d - d * (d - 1) / 2).sum()): int((d * d).sum())}


def test_link_scores(random_edges):
    e = random_edges.select("src", "dst")
    a = dense(e, 22)
    d = a.sum(0)
    with np.errstate(divide="ignore"):
        w = {"adamic_adar": np.where(d > 1, 1 / np.log(np.maximum(d, 2)), 0), "resource_allocation": np.where(d > 0, 1 / np.maximum(d, 1), 0), "common": np.ones(22)}
    for kind, weight in w.items():
        s = a @ np.diag(weight) @ a
        assert values(similarity.link_scores(e, kind), "score", "i", "j") == pytest.approx({(i, j): s[i, j] for i in range(22) for j in range(i + 1, 22) if (a @ a)[i, j]})
    p = prediction.link_prediction(e, topk=10)
    assert p.count() == 10 and [r["rank"] for r in p.orderBy("rank").collect()] == list(range(1, 11))
    assert 0 <= prediction.precision_at(p).first()[0] <= 1 and 0 <= prediction.auc(e, holdout=4).first()[0] <= 1


def test_betweenness_and_closeness_against_brute_force(random_edges):
    a = dense(random_edges, 22)
    ids = [i for i in range(22) if a[i].any()]
    near = {i: np.flatnonzero(a[i]).tolist() for i in ids}
    between = dict.fromkeys(ids, 0.0)
    for s in ids:
        dist, count, order = {s: 0}, {s: 1.0}, [s]
        for v in order:
            for w in near[v]:
                if w not in dist:
                    dist[w], count[w] = dist[v] + 1, 0.0
                    order.append(w)
                if dist[w] == dist[v] + 1:
                    count[w] += count[v]
        dep = dict.fromkeys(order, 0.0)
        for w in reversed(order):
            for v in near[w]:
                if dist[v] == dist[w] - 1:
                    dep[v] += count[v] / count[w] * (1 + dep[w])
            if w != s:
                between[w] += dep[w] / 2
    adj = S.both_ways(random_edges)
    assert values(C.betweenness(adj), "score", "id") == pytest.approx(between)


# --- subgraphs ----------------------------------------------------------------------------------------------------------------


def test_cliques(random_edges):
    e = pairs(random_edges)
    for k in (3, 4):
        want = {c for c in itertools.combinations(range(22), k) if all(p in e for p in itertools.combinations(c, 2))}
        assert {tuple(r) for r in subgraph.k_cliques(random_edges.select("src", "dst"), k).collect()} == want
    maximal = {tuple(r["members"]) for r in subgraph.maximal_cliques(random_edges.select("src", "dst"), 6).collect()}
    every = [c for k in range(2, 7) for c in itertools.combinations(range(22), k) if all(p in e for p in itertools.combinations(c, 2))]
    assert maximal == {c for c in every if not any(set(c) < set(o) for o in every)}


def test_planted(spark):
    rng = np.random.default_rng(11)
    e = sorted({tuple(sorted(map(int, rng.choice(80, 2, replace=False)))) for _ in range(200)})
    g, members = subgraph.plant(spark.createDataFrame(e, "src bigint, dst bigint"), 9)
    want = {r["id"] for r in members.collect()}
    for method in ("truss", "degree", "spectral"):
        found = {r["id"] for r in subgraph.planted_clique(g, 9, method).collect()}
        assert len(found & want) >= 8, method
    assert len({r["id"] for r in subgraph.planted_cluster(g, 9).collect()} & want) >= 7


def test_nomination(adj):
    cues = adj.select(F.col("row").alias("id")).where("id in (1, 4)").distinct()
    assert subgraph.nominate(adj, cues, top=1).first()["id"] == 3
    assert subgraph.nominate(adj, cues, "ppr", top=1).first()["id"] == 3
    assert subgraph.nominate(adj, cues, "jaccard", top=1).first()[:2] == (2, pytest.approx(2 / 3))


def test_components(spark):
    e = [(i, i + 1) for i in range(60)] + [(100, 101), (101, 102), (200, 200), (None, 5)]
    got = values(components(spark.createDataFrame(e, "src bigint, dst bigint")), "component", "id")
    assert got == {**{i: 0 for i in range(61)}, 100: 100, 101: 100, 102: 100, 200: 200}


def test_isomorphism_and_matching(spark, random_edges):
    e = random_edges.select("src", "dst")
    perm = np.random.default_rng(3).permutation(22)
    other = spark.createDataFrame([(int(perm[a]), int(perm[b])) for a, b in pairs(e)], "src bigint, dst bigint").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"))
    assert similarity.isomorphic(e, other) == "yes"
    assert similarity.isomorphic(e, e.limit(e.count() - 1)) == "no"
    ring = lambda n, at: [(at + i, at + (i + 1) % n) for i in range(n)]
    six = spark.createDataFrame([tuple(sorted(p)) for p in ring(6, 0)], "src bigint, dst bigint")
    threes = spark.createDataFrame([tuple(sorted(p)) for p in ring(3, 0) + ring(3, 3)], "src bigint, dst bigint")
    assert similarity.isomorphic(six, threes) == "no"  # refinement alone cannot tell
    assert similarity.isomorphic(six, threes, exact_limit=3) == "maybe"
    star = spark.createDataFrame([(0, i) for i in range(1, 5)], "src bigint, dst bigint")
    moved = spark.createDataFrame([(7, 9), (8, 9), (9, 10), (9, 11)], "src bigint, dst bigint")
    assert similarity.neighbor_matching(star, moved).orderBy("rank").first()[:2] == (0, 9)


def test_emerging(spark):
    k4 = lambda w, ids: [(w, a, b) for a, b in itertools.combinations(ids, 2)]
    e = spark.createDataFrame(k4(1, [1, 2, 3, 4]) + k4(2, [2, 3, 4, 5]) + k4(2, [10, 11, 12]), "window bigint, src bigint, dst bigint")
    got = {(r["window"], r["community"]): (r["size"], r["previous"], r["overlap"]) for r in prediction.emerging_communities(e).collect()}
    assert got == {(1, 1): (4, None, 0.0), (2, 2): (4, 1, 0.6), (2, 10): (3, None, 0.0)}


# --- traversal and paths -----------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def weighted(spark):
    rng = np.random.default_rng(12)
    rows = {(int(a), int(b)): int(rng.integers(1, 20)) for a, b in rng.integers(0, 14, (45, 2)) if a != b}
    return spark.createDataFrame([(a, b, float(w)) for (a, b), w in rows.items()], "row bigint, col bigint, val double").cache()


def floyd(df, n=14):
    d = np.full((n, n), np.inf)
    np.fill_diagonal(d, 0)
    for r in df.collect():
        d[r["row"], r["col"]] = min(d[r["row"], r["col"]], r["val"])
    for k in range(n):
        d = np.minimum(d, d[:, k : k + 1] + d[k])
    return d


def test_paths(spark, weighted):
    d = floyd(weighted)
    ids = spark.range(14).select("id")
    one = values(paths.bellman_ford(weighted, 0), "dist", "id")
    assert one == {j: d[0, j] for j in range(14) if np.isfinite(d[0, j])}
    every = {(i, j): d[i, j] for i in range(14) for j in range(14) if np.isfinite(d[i, j])}
    for method in (paths.apsp, paths.floyd_warshall, paths.johnson):
        assert values(method(weighted, ids), "val", "row", "col") == pytest.approx(every)
    h = paths.landmark_bound(weighted, 9, [0, 3])
    bound = values(h, "h", "id")
    assert all(b <= d[i, 9] + 1e-9 for i, b in bound.items())
    for target in (5, 9, 13):
        want = d[0, target] if np.isfinite(d[0, target]) else None
        assert paths.astar(weighted, 0, target, h if target == 9 else None) == want


def test_negative_weights(spark):
    e = spark.createDataFrame([(0, 1, 4.0), (0, 2, 5.0), (2, 1, -3.0), (1, 3, 1.0)], "row bigint, col bigint, val double")
    assert values(paths.bellman_ford(e, 0), "dist", "id") == {0: 0, 1: 2, 2: 5, 3: 3}
    assert values(paths.johnson(e, spark.range(4).select("id")), "val", "row", "col")[0, 3] == 3
    loop = e.unionAll(spark.createDataFrame([(1, 2, 2.0)], e.schema))
    with pytest.raises(ValueError):
        paths.bellman_ford(loop, 0)
    with pytest.raises(ValueError):
        paths.floyd_warshall(loop, spark.range(4).select("id"))


def test_other_path_semirings(spark):
    dag = spark.createDataFrame([(0, 1, 3.0), (1, 2, 4.0), (0, 2, 5.0), (2, 3, 2.0)], "row bigint, col bigint, val double")
    assert values(paths.best_path(dag, 0, MAX_PLUS), "dist", "id")[3] == 9
    assert values(paths.best_path(dag, 0, MAX_MIN), "dist", "id")[2] == 5


def test_traversal(spark, toy, adj):
    src = spark.createDataFrame([(1,), (5,)], "id bigint")
    got = {(r["source"], r["id"]): (r["level"], r["parent"]) for r in traversal.bfs(adj, src).collect()}
    assert got[1, 5] == (2, 2) and got[5, 4] == (3, 1) and got[1, 1] == (0, None)
    assert {r["id"]: (r["pre"], r["post"]) for r in traversal.dfs(adj, 1).collect()} == {1: (0, 4), 2: (1, 3), 3: (2, 1), 4: (3, 0), 5: (4, 2)}
    with pytest.raises(ValueError):
        traversal.dfs(adj, 1, limit=3)
    adj.select("row", "col").createOrReplaceTempView("adj_t")
    assert values(traversal.bfs_sql(spark, "adj_t", 1, 4), "level", "id") == {1: 0, 2: 1, 3: 1, 4: 1, 5: 2}


def test_dense_ratio_has_no_limit_of_vertices(spark):
    """A path of 6,000 vertices: each pair two steps apart shares one neighbour."""
    path = spark.range(5_999).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    got = similarity.jaccard(path, "dense").collect()
    assert {(r["i"], r["j"]) for r in got} == {(v, v + 2) for v in range(5_998)} and {r["common"] for r in got} == {1}
    assert {r["i"]: r["score"] for r in got} == {v: 1 / 2 if v in (0, 5_997) else 1 / 3 for v in range(5_998)}


def test_hub(spark):
    star = truss.with_ids(spark.range(1, 10_001).select(F.lit(0).cast("bigint").alias("src"), F.col("id").alias("dst")))
    assert truss.triangles(star).count() == 0
    assert truss.edge_support(star).agg(F.sum("support")).first()[0] == 0


def test_schemas(spark, toy):
    signed = S.incidence(toy, oriented=True)
    lap = values(S.laplacian(signed), "val", "row", "col")
    assert lap[1, 1] == 3 and lap[1, 2] == -1 and (2, 4) not in lap
    recs = spark.createDataFrame([(1, "a|b", 5), (2, "", None), (3, None, 5)], "id bigint, x string, y bigint")
    t = S.explode_schema(recs, "id", ["x", "y"])
    assert {(r["row"], r["col"]) for r in t.edge.collect()} == {(1, "x|a|b"), (1, "y|5"), (2, "x|"), (3, "y|5")}
    assert values(t.deg, "degree", "col")["y|5"] == 2 and t.edge_t.count() == 4
    assert values(S.facet(t, "y|5", "x|"), "count", "col") == {"x|a|b": 1}
    und = S.adjacency(spark.createDataFrame([(1, 2), (1, 2), (3, 3)], "src bigint, dst bigint"), directed=False)
    assert values(und, "val", "row", "col") == {(1, 2): 2, (2, 1): 2, (3, 3): 1}
    hyper = S.hyper_incidence(spark.createDataFrame([("o", 1), ("o", 2), ("p", 2)], "e string, v bigint"), "e", "v")
    assert values(S.partition_block(hyper, [1], [2]), "val", "row", "col") == {(1, 2): 1}
    assert metrics.fill(K.transpose(hyper), 2, 2).first()[0] == 0.75
    assert metrics.products(K.transpose(hyper), hyper).first()[:] == (5, 4)


def test_jaccard_sets_joins_on_shared_neighbours(random_edges):
    plan = similarity.jaccard(random_edges, "sets")._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


@pytest.mark.parametrize("per", [3, 10_000])
def test_shared_columns_keep_hot_ones(spark, per):
    """Column 0 is in all 60 rows, the others in some."""
    rows = {r: {0} | {c for c in range(1, 9) if (r * c) % 7 < 2} for r in range(60)}
    few = {i: {0, i, i + 1} for i in range(4)}
    frame = lambda x: spark.createDataFrame([(r, c) for r, cs in x.items() for c in cs], "row bigint, col bigint")
    got = {(r["row"], r["col"]): r["val"] for r in similarity.shared_columns(frame(few), frame(rows), per=per).collect()}
    assert got == {(i, r): len(few[i] & rows[r]) for i in few for r in rows if few[i] & rows[r]}


@pytest.mark.parametrize("measure", [C.betweenness, C.closeness])
def test_blocks_of_sources_are_all_sources(random_edges, measure):
    a = S.both_ways(random_edges).select("row", "col")
    n = C.endpoints(a).count()
    assert values(C.by_source_blocks(a, measure, cells=n * n // 3), "score", "id") == pytest.approx(values(measure(a), "score", "id"))


def test_betweenness_of_the_whole_table(spark):
    """A vertex of the co-purchase graph that has two neighbours which are no neighbours of each other lies between them."""
    d = "/root/testdata/sf0.001"
    got = values(Q.QUERIES["betweenness_all"](spark, d), "score", "id")
    near = {}
    for r in copurchase(spark, d).collect():
        near.setdefault(r["src"], set()).add(r["dst"])
        near.setdefault(r["dst"], set()).add(r["src"])
    assert set(got) == set(near)
    assert all((got[v] > 0) == any(y not in near[x] for x, y in itertools.combinations(near[v], 2)) for v in near)


def test_isomorphism_search_is_deeper_than_the_stack():
    n = 3000
    ring = {(i, (i + 1) % n) for i in range(n)}
    moved = {((7 * u + 5) % n, (7 * v + 5) % n) for u, v in ring}
    same = dict.fromkeys(range(n), "c")
    # A colour for each place keeps the search straight; it is as deep as the graph.
    assert similarity._map_vertices({i: str(i) for i in range(n)}, ring, {(7 * i + 5) % n: str(i) for i in range(n)}, moved)
    assert not similarity._map_vertices({i: same[i] for i in range(6)}, {(i, (i + 1) % 6) for i in range(6)}, {i: "c" for i in range(6)}, {(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5)})


def test_truss_of_doubled_edges_and_loops(spark):
    e = spark.createDataFrame([(1, 1, 2), (2, 2, 3), (3, 1, 4), (4, 3, 4), (5, 3, 1), (6, 2, 5), (7, 2, 5), (8, 3, 3), (9, 2, 1)], "edge_id bigint, src bigint, dst bigint")
    for method in ("incidence", "masked"):
        assert sorted((r["edge_id"], r["support"]) for r in truss.edge_support(e, method).collect()) == [(1, 1), (2, 1), (3, 1), (4, 1), (5, 2), (6, 0)]
    assert sorted(r["edge_id"] for r in truss.k_truss(e, 3)[0].collect()) == [1, 2, 3, 4, 5]
    with pytest.raises(RuntimeError):
        truss.k_truss(e, 3, max_rounds=0)


def test_searches_have_no_hidden_depth(spark):
    a = spark.createDataFrame([(i, i + 1, 1) for i in range(12)], "row bigint, col bigint, val int")
    start = spark.createDataFrame([(0,)], "id bigint")
    assert traversal.bfs(a, start).agg({"level": "max"}).first()[0] == 12
    assert traversal.bfs(a, start, max_depth=3).agg({"level": "max"}).first()[0] == 3
    assert traversal.dfs(a, 0).count() == 13
