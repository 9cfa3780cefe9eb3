"""Vertex similarity: Jaccard in all its forms, neighbour scores, graph isomorphism, neighbour matching."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from sparsegraph.plans.state import materialise

from .kernels import PLUS_TIMES, gram, spgemm, symmetrize, transpose, triu
from .schema import both_ways

#: Vertices to a side of a dense tile.
TILE = 256


def degrees(edges: DataFrame) -> DataFrame:
    return both_ways(edges).groupBy(F.col("row").alias("id")).agg(F.count("*").alias("d"))


def common_neighbours(edges: DataFrame, *, split: bool = False) -> DataFrame:
    """(row, col, val), row < col: numbers of common neighbours. One self-join gives one product for each unordered wedge;
    split forms the three products of triangular parts (centre between, above and below the ends) and adds them."""
    if not split:
        return gram(both_ways(edges), upper=True)
    u = edges.select(F.col("src").alias("row"), F.col("dst").alias("col"), F.lit(1).cast("bigint").alias("val"))
    parts = spgemm(u, u).unionByName(triu(spgemm(u, transpose(u)), 1)).unionByName(triu(spgemm(transpose(u), u), 1))
    return parts.groupBy("row", "col").agg(F.sum("val").alias("val"))


def jaccard(edges: DataFrame, method: str = "triangular", *, symmetric: bool = False, split: bool = False, min_score: float | None = None, only_non_edges: bool = False, pairs: DataFrame | None = None) -> DataFrame:
    """(i, j, common, score) with i < j (or both ways), for pairs that have a common neighbour, of a simple graph.

    triangular: wedges, then degrees by inclusion and exclusion. sets: by definition, on neighbour sets, for pairs that share one.
    dense: the ratio of the AND and the OR product on dense tiles of pairs, at any size (see _dense_ratio). minhash: candidate pairs from
    least-hash bands of the neighbour sets, verified exactly; may miss pairs below the usual similarity of 0.8."""
    if method == "sets":
        sets = both_ways(edges).groupBy("row").agg(F.collect_set("col").alias("s"))
        near = both_ways(edges).select("col", F.col("row").alias("v"))
        shared = near.withColumnRenamed("v", "i").join(near.withColumnRenamed("v", "j"), "col").where("i < j").select("i", "j").distinct()
        out = shared.join(sets.select(F.col("row").alias("i"), F.col("s").alias("a")), "i").join(sets.select(F.col("row").alias("j"), F.col("s").alias("b")), "j")
        out = out.select("i", "j", F.size(F.array_intersect("a", "b")).cast("bigint").alias("common"), (F.size(F.array_intersect("a", "b")) / F.size(F.array_union("a", "b"))).alias("score"))
    elif method == "dense":
        out = _dense_ratio(edges)
    elif method == "minhash":
        out = _scored(edges, _minhash_pairs(edges))
    elif method == "triangular":
        if split:
            both = common_neighbours(edges, split=True).select(F.col("row").alias("i"), F.col("col").alias("j"), F.col("val").alias("common"))
            out = _with_degrees(edges, both)
        else:
            # Degrees ride along on the wedge join: no exchange after the count.
            n = both_ways(edges).select(F.col("row").alias("v"), F.col("col").alias("c"))
            d = degrees(edges)
            n = n.join(d.select(F.col("id").alias("v"), "d"), "v")
            x, y = n.select("c", F.col("v").alias("i"), F.col("d").alias("di")), n.select("c", F.col("v").alias("j"), F.col("d").alias("dj"))
            wedges = x.join(y, "c").where("i < j")
            if min_score is not None:
                # common <= min degree, so score <= min / max: what cannot reach min_score is never shuffled.
                wedges = wedges.where(F.least("di", "dj") >= F.lit(min_score) * F.greatest("di", "dj"))
            if pairs is not None:
                wedges = wedges.join(pairs.select("i", "j"), ["i", "j"], "left_semi")
            both = wedges.groupBy("i", "j").agg(F.count("*").alias("common"), F.first("di").alias("di"), F.first("dj").alias("dj"))
            out = both.select("i", "j", "common", (F.col("common") / (F.col("di") + F.col("dj") - F.col("common"))).alias("score"))
    else:
        raise ValueError(method)
    if min_score is not None:
        out = out.where(F.col("score") >= min_score)
    if pairs is not None and (method != "triangular" or split):
        out = out.join(pairs.select("i", "j"), ["i", "j"], "left_semi")
    if only_non_edges:
        out = out.join(edges.select(F.col("src").alias("i"), F.col("dst").alias("j")), ["i", "j"], "left_anti")
    return out.unionByName(out.select(F.col("j").alias("i"), F.col("i").alias("j"), "common", "score")) if symmetric else out


def _dense_ratio(edges: DataFrame, tile: int = TILE) -> DataFrame:
    """(i, j, common, score) from dense arrays of vertices by vertices. Vertices are dealt over tiles of about `tile`; the AND
    and the OR product of two tiles are one array each, and so is their ratio. A pair of tiles without a common neighbour
    has a ratio of 0 everywhere, so only the others are formed: no array grows with the graph."""
    d = materialise(degrees(edges), "degrees")
    tiles = max(1, -(-d.count() // tile))
    at = lambda c: F.pmod(F.xxhash64(c), F.lit(tiles))
    packed = d.groupBy(at("id").alias("t")).agg(F.sort_array(F.collect_list(F.struct("id", "d"))).alias("x")).select("t", F.col("x.id").alias("ids"), F.col("x.d").alias("ds"))
    both = common_neighbours(edges)
    held = both.groupBy(at("row").alias("t"), at("col").alias("u")).agg(F.collect_list("row").alias("rows"), F.collect_list("col").alias("cols"), F.collect_list("val").alias("vals"))
    held = held.join(packed.select("t", F.col("ids").alias("ids1"), F.col("ds").alias("ds1")), "t").join(packed.select(F.col("t").alias("u"), F.col("ids").alias("ids2"), F.col("ds").alias("ds2")), "u")
    kind = d.schema["id"].dataType.simpleString()
    return held.mapInArrow(_tile_ratio, f"i {kind}, j {kind}, common bigint, score double")


def _tile_ratio(batches):
    """For each pair of tiles: the ratio of the two products where the AND product is not 0."""
    import numpy as np
    import pyarrow as pa
    import pyarrow.compute as pc

    for batch in batches:
        for k in range(batch.num_rows):
            rows, cols, vals, ids1, ds1, ids2, ds2 = (batch.column(c)[k].values for c in ("rows", "cols", "vals", "ids1", "ds1", "ids2", "ds2"))
            both = np.zeros((len(ids1), len(ids2)), np.int64)
            both[pc.index_in(rows, ids1).to_numpy(), pc.index_in(cols, ids2).to_numpy()] = vals.to_numpy()
            either = ds1.to_numpy()[:, None] + ds2.to_numpy()[None, :] - both
            ratio = both / either
            i, j = np.nonzero(ratio)
            yield pa.RecordBatch.from_arrays([ids1.take(pa.array(i)), ids2.take(pa.array(j)), pa.array(both[i, j]), pa.array(ratio[i, j])], names=["i", "j", "common", "score"])


def _with_degrees(edges: DataFrame, both: DataFrame) -> DataFrame:
    d = degrees(edges)
    out = both.join(d.select(F.col("id").alias("i"), F.col("d").alias("di")), "i").join(d.select(F.col("id").alias("j"), F.col("d").alias("dj")), "j")
    return out.select("i", "j", "common", (F.col("common") / (F.col("di") + F.col("dj") - F.col("common"))).alias("score"))


def _scored(edges: DataFrame, pairs: DataFrame) -> DataFrame:
    n = both_ways(edges).select(F.col("row").alias("v"), F.col("col").alias("c"))
    both = pairs.join(n.select(F.col("v").alias("i"), "c"), "i").join(n.select(F.col("v").alias("j"), "c"), ["j", "c"]).groupBy("i", "j").agg(F.count("*").alias("common"))
    return _with_degrees(edges, both)


def _minhash_pairs(edges: DataFrame, bands: int = 12, rows: int = 3) -> DataFrame:
    n = both_ways(edges)
    sig = n.groupBy("row").agg(*[F.min(F.xxhash64(F.lit(k), "col")).alias(f"m{k}") for k in range(bands * rows)])
    keys = F.array(*[F.struct(F.lit(b).alias("b"), F.xxhash64(*[f"m{b * rows + r}" for r in range(rows)]).alias("h")) for b in range(bands)])
    k = sig.select(F.col("row").alias("v"), F.explode(keys).alias("k")).select("v", "k.b", "k.h")
    return k.select(F.col("v").alias("i"), "b", "h").join(k.select(F.col("v").alias("j"), "b", "h"), ["b", "h"]).where("i < j").select("i", "j").distinct()


def shared_columns(a: DataFrame, b: DataFrame, *, per: int = 10_000) -> DataFrame:
    """(row of a, col = row of b, val): numbers of columns that two patterns (row, col) have in common. A column that more
    than `per` rows of b hold is dealt over as many join keys as it takes; no column is left out."""
    wide = b.groupBy("col").agg(F.ceil(F.count("*") / per).alias("keys"))
    y = b.join(wide, "col").select("col", F.col("row").alias("other"), F.pmod(F.xxhash64("row"), F.col("keys")).alias("key"))
    x = a.join(wide, "col").select("row", "col", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("keys") - 1)).alias("key"))
    return x.join(y, ["col", "key"]).groupBy("row", F.col("other").alias("col")).agg(F.count("*").alias("val"))


def top_k(scores: DataFrame, k: int) -> DataFrame:
    """The k best partners of each i; ties go to the smaller j."""
    w = W.partitionBy("i").orderBy(F.col("score").desc(), "j")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def link_scores(edges: DataFrame, kind: str = "adamic_adar") -> DataFrame:
    """(i, j, score), i < j: common, cosine, overlap, adamic_adar, resource_allocation, jaccard, preferential (over pairs
    with a common neighbour)."""
    n = both_ways(edges).select(F.col("row").alias("v"), F.col("col").alias("c"))
    d = degrees(edges)
    if kind == "jaccard":
        return jaccard(edges).select("i", "j", "score")
    n = n.join(d.select(F.col("id").alias("v"), "d"), "v").join(d.select(F.col("id").alias("c"), F.col("d").alias("dc")), "c")
    w = n.select("c", "dc", F.col("v").alias("i"), F.col("d").alias("di")).join(n.select("c", F.col("v").alias("j"), F.col("d").alias("dj")), "c").where("i < j")
    one = {"adamic_adar": F.sum(1 / F.log(F.col("dc").cast("double"))), "resource_allocation": F.sum(1 / F.col("dc"))}.get(kind, F.count("*"))
    s = w.groupBy("i", "j").agg(one.alias("s"), F.first("di").alias("di"), F.first("dj").alias("dj"))
    score = {"cosine": F.col("s") / F.sqrt(F.col("di") * F.col("dj")), "overlap": F.col("s") / F.least("di", "dj"), "preferential": (F.col("di") * F.col("dj")).cast("double")}.get(kind, F.col("s").cast("double"))
    return s.select("i", "j", score.alias("score"))


def colours(edges: DataFrame, rounds: int, vertices: DataFrame | None = None) -> DataFrame:
    """(id, colour) after the given rounds of colour refinement: a colour is a digest of the own colour and the sorted
    colours of the neighbours, the same in any graph."""
    n = both_ways(edges).select("row", "col")
    ids = vertices.select("id") if vertices is not None else n.select(F.col("row").alias("id")).distinct()
    c = ids.withColumn("colour", F.sha2(F.lit("v"), 256))
    for _ in range(rounds):
        around = n.join(c.select(F.col("id").alias("col"), F.col("colour").alias("x")), "col").groupBy(F.col("row").alias("id")).agg(F.array_join(F.sort_array(F.collect_list("x")), ",").alias("near"))
        # Written each round: the next one reads it twice.
        c = materialise(c.join(around, "id", "left").select("id", F.sha2(F.concat_ws("|", "colour", F.coalesce("near", F.lit(""))), 256).alias("colour")), "colours")
    return c


def isomorphic(a: DataFrame, b: DataFrame, *, rounds: int = 8, exact_limit: int = 1_000) -> str:
    """"no" if refinement tells the graphs apart; else "yes" or "no" by an exact search up to exact_limit vertices; else
    "maybe"."""
    ca, cb = (materialise(colours(g, rounds), "colours") for g in (a, b))
    count = lambda c, name: c.groupBy("colour").agg(F.count("*").alias(name))
    odd = count(ca, "x").join(count(cb, "y"), "colour", "full_outer").where("x is null or y is null or x <> y")
    if not odd.isEmpty() or a.count() != b.count():
        return "no"
    if ca.count() > exact_limit:
        return "maybe"
    read = lambda g, c: ({r["id"]: r["colour"] for r in c.collect()}, {(r["src"], r["dst"]) for r in g.select("src", "dst").collect()})
    return "yes" if _map_vertices(*read(a, ca), *read(b, cb)) else "no"


def _map_vertices(ca: dict, ea: set, cb: dict, eb: set) -> bool:
    """Backtracking over vertices by the size of their colour class, within size-guarded graphs."""

    def near(edges: set) -> dict:
        out: dict = {}
        for u, v in edges:
            out.setdefault(u, set()).add(v)
            out.setdefault(v, set()).add(u)
        return out

    na, nb = near(ea), near(eb)
    by_colour: dict = {}
    for v, c in cb.items():
        by_colour.setdefault(c, []).append(v)
    order = sorted(ca, key=lambda v: (len(by_colour[ca[v]]), v))
    chosen: dict = {}
    back: dict = {}
    tries = [iter(by_colour[ca[order[0]]])] if order else []
    # An explicit stack: the search is as deep as the graph has vertices.
    while tries:
        v = order[len(tries) - 1]
        if v in chosen:
            del back[chosen.pop(v)]
        # Neighbours that are mapped must be neighbours of the image, and as many of them.
        done = {chosen[x] for x in na.get(v, ()) if x in chosen}
        fit = next((w for w in tries[-1] if w not in back and done == {y for y in nb.get(w, ()) if y in back}), None)
        if fit is None:
            tries.pop()
            continue
        chosen[v], back[fit] = fit, v
        if len(tries) == len(order):
            return True
        tries.append(iter(by_colour[ca[order[len(tries)]]]))
    return not order


def neighbor_matching(a: DataFrame, b: DataFrame, *, iters: int = 6, limit: int = 1_000) -> DataFrame:
    """(u, v, score, rank): vertices of two small graphs matched greedily by a similarity that averages that of their
    neighbours; the Kronecker product is never formed: two sparse products for each round."""
    na, nb = both_ways(a), both_ways(b)
    va, vb = na.select(F.col("row").alias("u")).distinct(), nb.select(F.col("row").alias("v")).distinct()
    if va.count() > limit or vb.count() > limit:
        raise ValueError(f"matching is for at most {limit} vertices a graph")
    da, db = (n.groupBy("row").agg(F.count("*").alias("d")) for n in (na, nb))
    s = materialise(va.crossJoin(vb).select(F.col("u").alias("row"), F.col("v").alias("col"), F.lit(1.0).alias("val")), "match")
    for _ in range(iters):
        t = spgemm(spgemm(na, s, PLUS_TIMES), nb, PLUS_TIMES)
        t = t.join(da.select("row", F.col("d").alias("x")), "row").join(db.select(F.col("row").alias("col"), F.col("d").alias("y")), "col")
        s = materialise(t.select("row", "col", (F.col("val") / F.greatest("x", "y") / F.greatest("x", "y") * F.least("x", "y") / F.greatest("x", "y")).alias("val")), "match")
        top = s.agg(F.max("val")).first()[0] or 1.0
        s = s.withColumn("val", F.col("val") / F.lit(top))
    out, used_u, used_v = [], set(), set()
    for r in s.orderBy(F.col("val").desc(), "row", "col").toLocalIterator():  # at most limit**2 rows, one at a time
        if r["row"] not in used_u and r["col"] not in used_v:
            used_u.add(r["row"])
            used_v.add(r["col"])
            out.append((r["row"], r["col"], float(r["val"]), len(out) + 1))
    return a.sparkSession.createDataFrame(out, "u bigint, v bigint, score double, rank int")


def symmetrised(scores: DataFrame) -> DataFrame:
    return symmetrize(scores.select(F.col("i").alias("row"), F.col("j").alias("col"), F.col("score").alias("val")))
