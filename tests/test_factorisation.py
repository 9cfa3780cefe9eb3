import numpy as np
import pytest
from pyspark.sql import functions as F

from sparsegraph.operators import linalg, nmf, spectral
from sparsegraph.sources.tables import read_table

D = "/root/testdata/sf0.001"


def triples(spark, m):
    return spark.createDataFrame([(i, j, float(m[i, j])) for i in range(m.shape[0]) for j in range(m.shape[1]) if m[i, j]], "row bigint, col bigint, val double")


def dense(df, n, m):
    out = np.zeros((n, m))
    for r in df.collect():
        out[r["row"], r["col"]] = r["val"]
    return out


def test_inverse_variants(spark):
    rng = np.random.default_rng(1)
    w = rng.random((9, 3))
    g = w.T @ w
    for method in ("kernels", "local"):
        x, report = linalg.inverse(triples(spark, g), method=method)
        assert report.converged and np.allclose(dense(x, 3, 3), np.linalg.inv(g), atol=1e-6)
    x, report = linalg.inverse_local(g * 1e8, eps=1e-6, stop="absolute")
    assert report.rounds < 3 and np.abs(g * 1e8 @ x - np.eye(3)).max() > 0.1  # the absolute stop ends too early
    x, report = linalg.inverse_local(g * 1e8)
    assert report.converged and np.allclose(g * 1e8 @ x, np.eye(3), atol=1e-6)
    for bad in (np.diag([2.0, 0, 1]), np.array([[1.0, 1, 0], [1, 1, 0], [0, 0, 2]])):  # a dead topic, twin topics
        x, report = linalg.inverse_local(bad)
        assert np.allclose(x, np.linalg.pinv(bad), atol=1e-6) and report.status == "rank deficient"
    with pytest.raises(ValueError):
        linalg.inverse_local(np.ones((2, 3)))


def test_conjugate_gradient_and_tsqr(spark):
    rng = np.random.default_rng(2)
    w = rng.random((40, 4))
    g = w.T @ w
    b = rng.random((7, 4))
    b[3] = 0
    assert np.allclose(nmf.conjugate_gradients(g, b), np.linalg.solve(g, b.T).T)
    flat = np.outer(np.ones(3), np.ones(3))
    assert np.allclose(nmf.conjugate_gradients(flat, flat[:1]) @ flat, flat[:1])  # singular, but with a solution
    r = linalg.tsqr(spark.createDataFrame([(x.tolist(),) for x in w], "vec array<double>"), 4)
    assert np.allclose(r.T @ r, g)


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(3)
    a = (rng.random((25, 3)) @ rng.random((3, 18))) * (rng.random((25, 18)) < 0.7)
    return a, triples(spark, a).cache()


def numpy_nmf(a, k, sweeps, seed=1):
    key = np.arange(a.shape[0])
    w = np.stack([((key * 7919 + t * 104729 + seed + key * 31 * (t + 1)) % 10007 + 1) / 10008 for t in range(k)], 1)
    for _ in range(sweeps):
        h = np.maximum(np.linalg.pinv(w.T @ w) @ w.T @ a, 0)
        w = np.maximum(a @ h.T @ np.linalg.pinv(h @ h.T), 0)
    return w, h


@pytest.mark.parametrize("solver", ["newton", "direct", "svd", "qr", "cg"])
def test_solvers_agree_with_numpy(small, solver):
    a, t = small
    model = nmf.nmf(t, 3, solver=solver, max_iter=3, rel_tol=0.0)
    w, h = numpy_nmf(a, 3, 3)
    got = {r["id"]: [r["w0"], r["w1"], r["w2"]] for r in model.W.collect()}
    assert np.allclose([got[i] for i in range(25)], w, atol=1e-6)
    want = np.linalg.norm(a - w @ h)
    assert model.history[-1]["error"] == pytest.approx(want, abs=1e-6)
    if solver == "newton":
        assert nmf.nmf_residual(t, model) == pytest.approx(want, abs=1e-6) and nmf.nmf_residual(t, model, method="dense") == pytest.approx(want, abs=1e-6)
        assert all(x >= 0 for r in got.values() for x in r) and model.history[-1]["steps_h"] > 3


def test_multiplicative_updates_and_best(small):
    a, t = small
    mu = nmf.nmf(t, 3, solver="mu", max_iter=6, rel_tol=0.0)
    e = [h["error"] for h in mu.history]
    assert e == sorted(e, reverse=True)  # these updates never make it worse
    best = nmf.nmf(t, 3, max_iter=4, rel_tol=0.0, keep_best=True)
    assert nmf.nmf_residual(t, best) == pytest.approx(min(h["error"] for h in best.history), abs=1e-6)
    stopped = nmf.nmf(t, 3, eps=1e9, max_iter=9)
    assert stopped.status == "converged" and len(stopped.history) == 1
    assert nmf.nmf(t, 3, max_iter=2, reseed_dead=True, rel_tol=0.0).history[-1]["dead"] == []
    picks = nmf.recommend(best, t, 2)
    assert picks.join(t, ["row", "col"], "left_semi").count() == 0 and picks.agg(F.max("rank")).first()[0] <= 2


@pytest.mark.parametrize("weighting,least", [("binary", 0.8), ("l2tf", 0.7)])
def test_topics_find_the_languages(spark, weighting, least):
    docs = read_table(spark, D, "documents")
    terms, assigned, model = nmf.topic_model(docs, 5, weighting=weighting, max_iter=6)
    truth = docs.select(F.col("doc_id").alias("id"), F.col("lang").alias("label"))
    r = nmf.purity(assigned, truth).first()
    assert r["purity"] >= least and r["n"] >= 0.9 * docs.count() and 0 < r["nmi"] <= 1
    assert terms.groupBy("topic").count().where("count = 10").count() == 5
    overlap = nmf.communities(model, "threshold", 0.2)
    assert overlap.select("id").distinct().count() > 0.9 * docs.count()


@pytest.mark.parametrize("weighting", ["tf", "tfidf"])
def test_weightings(spark, weighting):
    docs = spark.createDataFrame([(1, "a a b"), (2, "a c\tb"), (3, None), (4, "")], "doc_id bigint, text string")
    got = {(r["row"], r["col"]): r["val"] for r in nmf.doc_term(docs, min_df=1, weighting=weighting).collect()}
    assert got[1, "a"] == (2.0 if weighting == "tf" else pytest.approx(2 * np.log(2)))
    assert (3, "a") not in got and len(got) == 5


def test_spectral(spark, small):
    a, t = small
    u, s, v = spectral.svd(t, 3, iters=10)
    assert np.allclose(s, np.linalg.svd(a)[1][:3], rtol=1e-5)
    read = lambda d, n: np.array([[r[f"w{k}"] for k in range(3)] for r in d.orderBy("id").collect()]).reshape(n, 3)
    assert np.allclose(abs(read(u, 25).T @ a @ read(v, 18)), np.diag(s), atol=1e-4)
    sym = a.T @ a - 3 * np.eye(18)
    values, _ = spectral.top_eigs(triples(spark, sym), 2, iters=25)
    want = np.linalg.eigvalsh(sym)
    assert values[0] == pytest.approx(want[np.abs(want).argmax()], rel=1e-4)
    x = np.random.default_rng(4).random((60, 5)) @ np.diag([5, 3, 1, 0.5, 0.1])
    comp, var, basis = spectral.pca(spark.createDataFrame([(r.tolist(),) for r in x], "vec array<double>"), 3, 5)
    want = np.sort(np.linalg.eigvalsh(np.cov(x.T, bias=True)))[::-1]
    assert np.allclose(var, want[:3]) and np.allclose(basis.T @ basis, np.eye(3)) and comp.count() == 3


@pytest.mark.parametrize("block", [7, 1 << 14])
def test_recommendations_are_the_exact_best(spark, block):
    rng, k, n, m, top = np.random.default_rng(3), 3, 40, 300, 3
    w, h = rng.exponential(size=(n, k)), rng.exponential(size=(m, k))
    h[10] = h[11]  # a tie
    factor = lambda x: spark.createDataFrame([(i, *map(float, r)) for i, r in enumerate(x)], "id bigint, " + ", ".join(f"{c} double" for c in nmf.names(k)))
    s = w @ h.T
    # Row 0 holds its 280 best columns, row 1 all, row 2 none; the others some.
    held = {0: list(np.argsort(-s[0])[:280]), 1: list(range(m)), 2: []} | {i: list(np.argsort(-s[i])[: 4 * i]) for i in range(3, n)}
    a = spark.createDataFrame([(i, int(c)) for i, cs in held.items() for c in cs], "row bigint, col bigint")
    model = nmf.NmfModel(factor(w), factor(h), k)
    got = {}
    for r in nmf.recommend(model, a, top, block=block).orderBy("row", "rank").collect():
        got.setdefault(r["row"], []).append(r["col"])
        assert r["score"] == pytest.approx(s[r["row"], r["col"]]) and r["rank"] == len(got[r["row"]])
    want = {i: [int(c) for c in sorted(set(range(m)) - set(held[i]), key=lambda c: (-s[i, c], c))[:top]] for i in range(n)}
    assert got == {i: c for i, c in want.items() if c}


@pytest.mark.parametrize("kind", ["bigint", "string"])
def test_recommendations_score_few_columns(kind, monkeypatch):
    """Rows without weight, with negative weights, with ties and with held columns: exact, from a small part of all scores."""
    import pyarrow as pa

    rng, k, n, m, top = np.random.default_rng(5), 3, 300, 20_000, 4
    w, h = rng.exponential(size=(n, k)), rng.exponential(size=(m, k))
    w[0], w[1], h[::7], h[5] = 0, (-1, 0, 0), h[0], h[6]
    keys = sorted(f"{c}" for c in range(m)) if kind == "string" else list(range(m))
    s = nmf._scores(w, h)
    held = [sorted(rng.choice(m, i % 40, replace=False).tolist() + np.argsort(-s[i])[: i % 5].tolist()) for i in range(n)]
    seen, scores = [], nmf._scores
    monkeypatch.setattr(nmf, "_scores", lambda a, b: seen.append(len(a) * len(b)) or scores(a, b))
    shared = type("Shared", (), {"value": nmf._leaves(pa.table({"col": keys, **{c: h[:, t] for t, c in enumerate(nmf.names(k))}}), nmf.names(k), 64)})
    rows = pa.RecordBatch.from_pydict({"row": list(range(n)), **{c: w[:, t] for t, c in enumerate(nmf.names(k))}, "held": [[keys[c] for c in x] + ([-1] if kind == "bigint" else ["none"]) for x in held]})
    got = {}
    for b in nmf._best_columns(shared, nmf.names(k), top)([rows]):
        for r, c in zip(b.column("row").to_pylist(), b.column("col").to_pylist()):
            got.setdefault(r, []).append(c)
    for i in range(n):
        left = np.setdiff1d(np.arange(m), held[i])
        assert got[i] == [keys[c] for c in left[np.argsort(-s[i, left], kind="stable")][:top]]
    assert sum(seen) < 0.05 * n * m


def test_topic_table(spark):
    assigned = spark.createDataFrame([(1, 0), (2, 0), (3, 0), (4, 1)], "id bigint, topic int")
    truth = spark.createDataFrame([(1, "en"), (2, "en"), (3, "de"), (4, "de"), (9, "fr")], "id bigint, label string")
    got = {(r["topic"], r["label"]): (r["n"], round(r["share"], 6)) for r in nmf.topic_table(assigned, truth).collect()}
    assert got == {(0, "en"): (2, 0.666667), (0, "de"): (1, 0.333333), (1, "de"): (1, 1.0)}


def test_lanczos_agrees_with_numpy(spark, small):
    a, t = small
    u, s, v = spectral.svd(t, 3, method="lanczos")
    assert np.allclose(s, np.linalg.svd(a, compute_uv=False)[:3], rtol=1e-8)
    left = {r["id"]: [r["w0"], r["w1"], r["w2"]] for r in u.collect()}
    right = {r["id"]: [r["w0"], r["w1"], r["w2"]] for r in v.collect()}
    x, y = np.array([left[i] for i in range(25)]), np.array([right[i] for i in range(18)])
    assert np.allclose(x.T @ x, np.eye(3), atol=1e-7) and np.allclose(y.T @ y, np.eye(3), atol=1e-7)
    assert np.allclose(a @ y, x * s, atol=1e-7)
    one = triples(spark, np.outer(np.arange(1.0, 5), np.arange(1.0, 4)))
    assert len(spectral.svd(one, 3, method="lanczos")[1]) <= 2  # ends when nothing new is left
    with pytest.raises(ValueError):
        spectral.svd(t, 2, method="other")


def test_lanczos_leaves_the_matrix_in_place(spark, monkeypatch):
    """Text keys, vectors broadcast or not: the same values, and only a matrix that no vector fits beside is shuffled."""
    from sparsegraph.operators import metrics

    rng = np.random.default_rng(6)
    a = rng.random((400, 60)) * (rng.random((400, 60)) < 0.5)
    t = spark.createDataFrame([(int(i), f"c{j}", float(a[i, j])) for i, j in zip(*np.nonzero(a))], "row bigint, col string, val double")
    moved = {}
    threshold = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    for limit in (1 << 20, 0):
        monkeypatch.setattr(nmf, "BROADCAST_BYTES", limit)
        with metrics.KernelStats(spark) as stats:
            _, s, v = spectral.svd(t, 1, method="lanczos", extra=1, iters=3)
        assert s[0] == pytest.approx(np.linalg.norm(a, 2), rel=1e-6)
        moved[limit] = stats.shuffle_written
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", threshold)
    assert {r["id"] for r in v.select("id").collect()} == {f"c{j}" for j in range(60)}
    assert moved[1 << 20] < 0.7 * moved[0]


def test_kernel_stats(spark, small):
    from sparsegraph.operators import metrics
    from sparsegraph.operators.kernels import gram

    with metrics.KernelStats(spark) as stats:
        gram(small[1]).write.format("noop").mode("overwrite").save()
    assert stats.stages >= 2 and stats.shuffle_written > 0 and stats.shuffle_read == stats.shuffle_written and stats.seconds > 0
    stats.rounds = 3
    assert stats.row()["rounds"] == 3 and "products" not in stats.row()
    with metrics.KernelStats(spark) as idle:
        pass
    assert idle.stages == 0
