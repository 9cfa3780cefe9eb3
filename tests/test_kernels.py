import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from sparsegraph.functions import semiring as sr
from sparsegraph.operators import kernels as K
from sparsegraph.operators import schema as S
from sparsegraph.plans.expr import Leaf, Product, Times

N = 6


def triples(spark, m):
    rows = [(i, j, float(m[i, j])) for i in range(m.shape[0]) for j in range(m.shape[1]) if m[i, j] and np.isfinite(m[i, j])]
    return spark.createDataFrame(rows, "row bigint, col bigint, val double")


def dense(df, zero=0.0, n=N):
    out = np.full((n, n), zero)
    for r in df.collect():
        assert out[r["row"], r["col"]] == zero, "two entries in a cell"
        out[r["row"], r["col"]] = r["val"]
    return out


def random_matrix(seed):
    rng = np.random.default_rng(seed)
    return rng.integers(1, 9, (N, N)) * (rng.random((N, N)) < 0.4)


@pytest.mark.parametrize("s", [sr.PLUS_TIMES, sr.MIN_PLUS, sr.MAX_PLUS, sr.MAX_MIN, sr.OR_AND], ids=lambda s: s.name)
@settings(max_examples=10, deadline=None)
@given(data=st.data())
def test_semiring_laws(s, data):
    values = st.booleans() if s is sr.OR_AND else st.integers(-20, 20)
    assert s.check_laws([*data.draw(st.lists(values, min_size=2, max_size=4)), s.zero, s.one]) == []


def test_laws_find_a_fake():
    fake = sr.Semiring("fake", F.sum, lambda a, b: a * b, 0, 1, lambda a, b: a - b, lambda a, b: a * b)
    assert "commutative addition" in fake.check_laws([1, 2, 3])


@pytest.mark.parametrize("seed", [1, 2])
def test_products_against_dense(spark, seed):
    a, b = random_matrix(seed), random_matrix(seed + 50)
    ta, tb = triples(spark, a), triples(spark, b)
    assert (dense(K.spgemm(ta, tb)) == a @ b).all()
    inf = lambda m: np.where(m > 0, m, np.inf)
    want = (inf(a)[:, :, None] + inf(b)[None]).min(1)
    assert (dense(K.spgemm(ta, tb, sr.MIN_PLUS), np.inf) == want).all()
    assert (dense(K.spgemm(ta, tb, sr.PLUS_PAIR)) == (a > 0).astype(int) @ (b > 0)).all()
    mask = triples(spark, b)
    assert (dense(K.spgemm(ta, tb, mask=mask)) == (a @ b) * (b > 0)).all()
    assert (dense(K.spgemm(ta, tb, mask=mask, complement=True)) == (a @ b) * (b == 0)).all()
    assert (dense(K.spgemm(ta, tb, accum=ta)) == a @ b + a).all()
    assert (dense(K.gram(ta)) == a.T @ a).all() and (dense(K.cogram(ta)) == a @ a.T).all()
    assert (dense(K.gram(ta, upper=True)) == np.triu(a.T @ a, 1)).all()
    assert (dense(K.transpose(K.spgemm(ta, tb))) == dense(K.spgemm(K.transpose(tb), K.transpose(ta)))).all()
    assert (dense(K.matpow(ta, 3)) == a @ a @ a).all()


def test_vectors(spark):
    a, x = random_matrix(3), np.arange(N) % 3
    tx = spark.createDataFrame([(i, float(v)) for i, v in enumerate(x) if v], "id bigint, val double")
    read = lambda d: np.array([dict((r["id"], r["val"]) for r in d.collect()).get(i, 0) for i in range(N)])
    t = triples(spark, a)
    assert (read(K.spmv(t, tx)) == a @ x).all() and (read(K.vxm(tx, t)) == x @ a).all()
    mask = spark.createDataFrame([(0,), (2,)], "id bigint")
    assert (read(K.spmspv(t, tx, mask=mask)) == (x @ a) * np.isin(np.arange(N), [0, 2])).all()
    assert (read(K.reduce_rows(t)) == a.sum(1)).all() and (read(K.reduce_cols(t)) == a.sum(0)).all()
    assert K.reduce_all(t).first()["val"] == a.sum() and K.nnz(t) == (a > 0).sum()
    assert K.norm_fro(t).first()["val"] == pytest.approx(np.linalg.norm(a)) and K.norm1(t).first()["val"] == a.sum(0).max()
    assert K.dot(tx, tx).first()["val"] == x @ x and K.cosine(tx, tx) == pytest.approx(1)
    assert (dense(K.scale_rows(t, tx)) == np.diag(x) @ a).all() and (dense(K.scale_cols(t, tx)) == a @ np.diag(x)).all()
    assert sorted(r["id"] for r in K.find(tx, lambda v: v == 2).collect()) == [2, 5]


def test_element_wise_and_parts(spark):
    a, b = random_matrix(4), random_matrix(5)
    ta, tb = triples(spark, a), triples(spark, b)
    assert (dense(K.ewise_mult(ta, tb)) == a * b).all() and (dense(K.ewise_add(ta, tb)) == a + b).all()
    sub = K.ewise_sub(ta, ta.unionByName(triples(spark, np.eye(N) * (a == 0) * 2)))
    assert (dense(sub) == -np.eye(N) * (a == 0) * 2).all()
    assert K.ewise_sub(ta, ta).count() == 0  # no stored zeros
    both = (a > 0) & (b > 0)
    assert np.allclose(dense(K.ewise_div(ta, tb)), np.divide(a, b, out=np.zeros_like(a, dtype=float), where=both))
    for part in ([0, 3], K.Range(1, 3)):
        inside, outside = K.spref(ta, rows=part), K.spref(ta, rows=part, complement_rows=True)
        assert (dense(inside) + dense(outside) == a).all()
    block = K.Range(0, 2)
    out = dense(K.spasgn(ta, tb, block, block))
    want = a.copy()
    want[:3, :3] = b[:3, :3]
    assert (out == want).all() and (dense(K.spref(K.spasgn(ta, tb, block, block), block, block)) == dense(K.spref(tb, block, block))).all()
    want = a.copy()
    want[:3, :3] += b[:3, :3]
    assert (dense(K.spasgn(ta, tb, block, block, accum=sr.PLUS_TIMES)) == want).all()
    for k in (0, 1, 2):
        assert (dense(K.triu(ta, k)) == np.triu(a, k)).all() and (dense(K.tril(ta, -k)) == np.tril(a, -k)).all()
    assert (dense(K.offdiag(ta)) == a - np.diag(np.diag(a))).all()
    assert (dense(K.apply(ta, lambda v: F.when(v > 4, v).otherwise(0))) == a * (a > 4)).all()
    assert (dense(K.apply_indexed(ta, lambda i, j, v: F.when(i <= j, v).otherwise(0))) == np.triu(a)).all()
    assert (dense(K.scale(ta, 2)) == 2 * a).all()
    nan = spark.createDataFrame([(0, 0, float("nan")), (0, 1, None), (1, 1, 0.0), (1, 0, 3.0)], "row bigint, col bigint, val double")
    assert K.prune(nan).count() == 1


def test_set_values_and_non_semiring(spark):
    a = spark.createDataFrame([("x", "p", ["u", "v"]), ("x", "q", ["w"])], "row string, col string, val array<string>")
    b = spark.createDataFrame([("p", "y", ["v", "z"]), ("q", "y", ["w"])], "row string, col string, val array<string>")
    assert K.spgemm(a, b, sr.UNION).first()["val"] == ["v", "w"]
    twos = sr.NonSemiring("twos", lambda c: F.size(F.filter(c, lambda x: x == 2)), lambda p, q: p + q)
    m = spark.createDataFrame([(0, 0, 1), (0, 1, 1)], "row bigint, col bigint, val bigint")
    assert not twos.allow_partial and K.spgemm(m, K.transpose(m), twos).first()["val"] == 2


def test_associative_arrays(spark):
    build = lambda rows: S.AssocArray.build(spark.createDataFrame(rows, "a string, b string, v double"), "a", "b", "v")
    x, y = build([("r|1", "été", 1.0), ("", "c", 2.0), ("z", "z", 0.0), (None, "c", 4.0)]), build([("new", "k", 5.0)])
    assert x.df.count() == 2  # zeros and null keys are no entries
    assert (x + y).df.count() == 3  # disjoint keys: a union
    assert (x - x).df.count() == 0 and (x & x).df.agg(F.sum("val")).first()[0] == 5.0
    assert (x @ x.T).df.count() == 2
    assert x[["r|1"], :].df.first()["col"] == "été" and x[K.Prefix("r|"), slice(None)].df.count() == 1
    codes, labels = S.encode_labels(x.df)
    back = codes.join(labels.withColumnRenamed("id", "row"), "row").select("label").collect()
    assert sorted(r["label"] for r in back) == ["", "r|1"]
    e = S.AssocArray.empty(spark)
    assert (e + e).df.count() == 0 and (e @ e).df.count() == 0


def test_algorithms_on_labels(spark):
    edges = [("a", "b"), ("b", "c"), ("a", "c"), ("c", "d"), ("d", "d")]
    x = S.AssocArray.build(spark.createDataFrame(edges, "s string, t string"), "s", "t")
    kept = {(r["row"], r["col"]): r["val"] for r in x.truss(3).df.collect()}
    assert kept == {(p, q): 1 for p in "abc" for q in "abc" if p != q}
    near = {(r["row"], r["col"]): r["val"] for r in x.jaccard().df.collect()}
    assert near["a", "b"] == pytest.approx(1 / 3) and near["a", "d"] == pytest.approx(1 / 2)
    assert x.scale(3).df.agg(F.sum("val")).first()[0] == 15 and x.apply(lambda v: v - 1).df.count() == 0
    assert {r["id"]: r["val"] for r in x.reduce("row").collect()} == {"a": 2, "b": 1, "c": 1, "d": 1}
    assert {(r["row"], r["col"]) for r in x.gram(diagonal=False).df.collect()} == {("b", "c"), ("c", "b")}
    model = x.nmf(2, max_iter=2)
    assert {r["id"] for r in model.W.select("id").collect()} == set("abcd")


def test_tensors_against_dense(spark):
    rng = np.random.default_rng(7)
    a, b = (rng.integers(1, 5, (3, 4, 5)) * (rng.random((3, 4, 5)) < 0.5) for _ in range(2))

    def tensor(m, keys):
        rows = [(*map(int, at), float(m[tuple(at)])) for at in np.argwhere(m)]
        return S.AssocTensor.build(spark.createDataFrame(rows, ", ".join(f"{k} bigint" for k in keys) + ", v double"), keys, "v")

    def array(t, shape):
        out = np.zeros(shape)
        for r in t.df.collect():
            out[tuple(r[k] for k in t.keys)] += r["val"]
        return out

    x, y = tensor(a, ["i", "j", "k"]), tensor(b, ["i", "j", "k"])
    assert np.array_equal(array(x + y, a.shape), a + b) and np.array_equal(array(x & y, a.shape), a * b)
    assert np.array_equal(array(x.reduce("k", "i"), (5, 3)), np.einsum("ijk->ki", a))
    z = tensor(b.transpose(2, 1, 0), ["k", "j", "l"])
    assert np.array_equal(array(x.contract(z, "j", "k"), (3, 3)), np.einsum("ijk,ljk->il", a, b))
    assert np.array_equal(array(x.at(i=[0], k=K.Range(1, 2)), a.shape)[0, :, 1:3], a[0, :, 1:3])
    flat = x.unfold(["i"], ["j", "k"])
    got = (flat @ flat.T).df
    assert np.array_equal(dense(got, n=3), np.einsum("ijk,ljk->il", a, a))
    with pytest.raises(ValueError):
        x.contract(y, "j")
    none = S.AssocTensor.build(spark.createDataFrame([(None, "x", 1)], "i string, j string, v bigint"), ["i", "j"], "v")
    assert none.df.count() == 0 and (none + none).df.count() == 0


@pytest.mark.parametrize("held", [1, 1 << 16])
def test_folds_of_ones_own(spark, held):
    from math import gcd

    from sparsegraph.functions import udaf

    rows = [("a", 12), ("a", 18), ("a", None), ("b", 7), (None, 4), (None, 6), ("c", None)] + [("hot", 30)] * 500
    df = spark.createDataFrame(rows, "k string, v bigint").repartition(5)
    got = {r["k"]: r["v"] for r in udaf.fold_by(df, "k", "v", gcd, held=held).collect()}
    assert got == {"a": 6, "b": 7, None: 2, "c": None, "hot": 30}
    assert udaf.fold_by(df.limit(0), "k", "v", gcd).count() == 0


def test_cogroups(spark):
    import pyarrow as pa

    from sparsegraph.functions import udaf

    a, b = (spark.createDataFrame(r, "k bigint, v bigint") for r in ([(1, 2), (1, 3), (2, 5)], [(1, 7)]))
    both = lambda x, y: pa.table({"n": [x.num_rows], "m": [y.num_rows]})
    assert sorted(map(tuple, udaf.cogrouped(a, b, "k", both, "n bigint, m bigint").collect())) == [(1, 0), (2, 1)]


def test_expression_rewrites(spark):
    a = random_matrix(6)
    p = (a > 0).astype(float)
    ta = triples(spark, a)
    leaf, pat = Leaf(ta), Leaf(triples(spark, p), pattern=True)
    assert (dense((leaf.T @ leaf).lower()) == a.T @ a).all()
    assert (dense((leaf.T @ leaf).triu(1).lower()) == np.triu(a.T @ a, 1)).all()
    assert (dense((leaf @ pat).T.lower()) == (a @ p).T).all() and leaf.T.T.rewrite() is leaf
    masked = ((pat @ pat) * pat).rewrite()
    assert isinstance(masked, Product) and masked.mask is pat and masked.sr is sr.PLUS_PAIR
    assert (dense(masked.plan()) == (p @ p) * p).all()
    assert isinstance(((leaf @ leaf) * leaf).rewrite(), Times)  # not a pattern: no mask
    rows = {r["id"]: r["val"] for r in (leaf @ leaf).row_sums().lower().collect()}
    assert all(rows.get(i, 0) == v for i, v in enumerate((a @ a).sum(1)))
    twos = (pat @ pat).apply(lambda v: F.when(v == 2, 1).otherwise(0)).row_sums().lower()  # no reordering across a function
    assert {r["id"]: r["val"] for r in twos.collect()} == {i: v for i, v in enumerate(((p @ p) == 2).sum(1)) if v}


def test_plans(spark, tmp_path):
    a = triples(spark, random_matrix(7))
    a.write.parquet(str(tmp_path / "a"))
    stored = spark.read.parquet(str(tmp_path / "a"))
    text = lambda df: df._jdf.queryExecution().toString()
    plan = text(K.spref(stored, rows=K.Range(1, 2)).select("row"))
    assert "PushedFilters: [IsNotNull(row), GreaterThanOrEqual(row,1), LessThanOrEqual(row,2)]" in plan and "ReadSchema: struct<row:bigint>" in plan
    masked = text(K.spgemm(stored, stored, mask=stored))
    optimized = masked[masked.index("== Optimized") : masked.index("== Physical")]
    assert optimized.index("Aggregate") < optimized.index("LeftSemi")  # the mask lies below the sum
    assert "CartesianProduct" not in masked and "NestedLoop" not in masked
