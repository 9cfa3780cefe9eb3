"""Groups of near duplicates against all pairs, by hand."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from sparsegraph.llm import neardup

from .fixtures import DOCS, awkward, empty

SCHEMA = "doc_id bigint, text string"


def brute_groups(rows, similarity=0.8):
    """Components of all pairs of texts whose five-word shingle sets have that Jaccard index."""
    shingles = {}
    for i, t in rows:
        w = t.lower().split()
        shingles[i] = {" ".join(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if w else set()
    parent = {i: i for i, _ in rows}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a, b in itertools.combinations(shingles, 2):
        x, y = shingles[a], shingles[b]
        if len(x & y) >= similarity * len(x | y):
            p, q = find(a), find(b)
            parent[max(p, q)] = min(p, q)
    return {i: find(i) for i in parent}


def groups(df):
    return {r["doc_id"]: r["component_id"] for r in neardup.similar_groups(df).collect()}


def test_groups_against_all_pairs(spark):
    rng = np.random.default_rng(4)
    vocabulary = [f"w{i}" for i in range(500)]
    rows = []
    for g in range(12):
        base = list(rng.choice(vocabulary, 120))
        for k in range(8):
            t = list(base)
            for p in rng.choice(120, int(rng.integers(0, 4)), replace=False):
                t[p] = str(rng.choice(vocabulary))
            rows.append((100 * g + k, " ".join(t)))
    rows += [(5000, ""), (5001, " "), (5002, "one"), (5003, "ONE")]
    want = brute_groups(rows)
    df = spark.createDataFrame(rows, SCHEMA)
    assert groups(df) == want
    kept = neardup.keep_one(awkward(df))
    assert kept.columns == awkward(df).columns
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(set(want.values()))


@pytest.mark.parametrize("bucket", [1, 4])
def test_large_buckets_lose_no_link(spark, monkeypatch, bucket):
    """Chains of copies whose ends are far from the least one, and strangers that share a long passage with them."""
    monkeypatch.setattr(neardup, "BUCKET", bucket)
    rng = np.random.default_rng(9)
    vocabulary = [f"w{i}" for i in range(900)]
    rows = []
    for g in range(4):
        text = list(rng.choice(vocabulary, 150))
        for k in range(30):  # each a small step from the one before
            p = int(rng.integers(0, 145))
            text[p : p + 4] = rng.choice(vocabulary, 4)
            rows.append((int(rng.integers(0, 1000)) * 1000 + 100 * g + k, " ".join(text)))
    passage = list(rng.choice(vocabulary, 100))
    for k in range(40):  # alike, yet no near copies; every third has one
        own = list(rng.choice(vocabulary, 22))
        rows.append((2_000_000 + k, " ".join(passage + own)))
        if k % 3 == 0:
            rows.append((3_000_000 - k, " ".join([*passage, *own[:-1], "other"])))
    made = []
    plain = neardup.prefix_pairs
    monkeypatch.setattr(neardup, "prefix_pairs", lambda *a: made.append(plain(*a)) or made[-1])
    assert groups(spark.createDataFrame(rows, SCHEMA)) == brute_groups(rows)
    assert made


def near_copies(n, length, edits, seed=11):
    rng = np.random.default_rng(seed)
    vocabulary = [f"w{i}" for i in range(400)]
    base, rows = list(rng.choice(vocabulary, length)), []
    for k in range(n):
        t = list(base)
        for p in rng.choice(length, k % edits, replace=False):
            t[p] = str(rng.choice(vocabulary))
        rows.append((k, " ".join(t[: length - k % 7])))
    return rows


def test_prefix_pairs_hold_every_similar_pair(spark):
    rows = near_copies(30, 90, 5)
    sets = {i: {tuple(w[j : j + 5]) for j in range(len(w) - 4)} for i, w in ((i, t.split()) for i, t in rows)}
    want = {(a, b) for a, b in itertools.combinations(sets, 2) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])}
    texts = neardup.distinct_texts(neardup.marks(spark.createDataFrame(rows, SCHEMA)))
    fetched = neardup.shingle_sets(spark.createDataFrame(rows, SCHEMA), texts)
    alone = texts.select("node", "sketch", F.col("node").alias("component"))
    name = {r["node"]: r["id"] for r in texts.collect()}
    got = {tuple(sorted((name[r["src"]], name[r["dst"]]))) for r in neardup.prefix_pairs(fetched, alone, 0.8).collect()}
    first = {w: min(i for i, t in rows if t == w) for _, w in rows}
    want = {tuple(sorted((first[rows[a][1]], first[rows[b][1]]))) for a, b in want if rows[a][1] != rows[b][1]}
    assert len(want) > 30 and want <= got


def test_sketches_never_hide_a_similar_pair():
    rng = np.random.default_rng(2)
    for n in (3, 40, 300, 3000):
        a = rng.integers(0, 1 << 63, n).astype(np.uint64)
        b = a.copy()
        gone = rng.choice(n, n // 9, replace=False)
        b[gone] = rng.integers(0, 1 << 63, len(gone)).astype(np.uint64)
        sets, at = neardup.distinct_shingles(np.concatenate((a, b)), np.array([0, n, 2 * n]))
        x, y = neardup.sketches(sets, at)
        apart = sum(int(v).bit_count() for v in x ^ y)
        assert apart <= len(np.setxor1d(a, b)) and (apart > 0) == (len(gone) > 0)


def test_bands_find_planted_copies(spark):
    """Copies at 0.8 and more, each in a group of its own: the share found is the recall that the README states."""
    rng = np.random.default_rng(6)
    vocabulary = [f"w{i}" for i in range(3000)]
    rows, want = [], 0
    for g in range(300):
        t = list(rng.choice(vocabulary, 104))
        rows.append((2 * g, " ".join(t)))
        for p in (20, 70)[: 1 + g % 2]:  # one or two words: 95 or 90 of 105 or 110 shingles are shared
            t[p] = f"x{g}"
        rows.append((2 * g + 1, " ".join(t)))
        want += 1
    got = groups(spark.createDataFrame(rows, SCHEMA))
    assert got == brute_groups(rows)
    assert sum(got[2 * g + 1] == 2 * g for g in range(300)) == want


def test_texts_under_one_id_are_not_merged(spark):
    a, b = "a text of some words that is here alone", "another text of other words that is elsewhere"
    df = spark.createDataFrame([(7, a), (7, b), (8, b)], SCHEMA)
    assert sorted((r["doc_id"], r["text"]) for r in neardup.keep_one(df).collect()) == [(7, a), (7, b)]
    got = sorted((r["doc_id"], r["component_id"]) for r in neardup.similar_groups(df).collect())
    assert got == [(7, 7), (7, 7), (8, 7)]


def test_null_ids_and_repeated_rows(spark):
    rows = [(None, "only me here", "x"), (None, "only me here", "a"), (4, "the same words", None), (None, "THE same  words", "z"), (4, "the same words", "b"), (4, "the same words", "b"), (9, None, "q"), (3, "", "q"), (5, " \n", "q")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, id string")
    kept = sorted(((r["doc_id"] or -1), r["text"] or "") for r in neardup.keep_one(df).collect())
    assert kept == [(-1, "only me here"), (3, ""), (4, "the same words")]
    again = [neardup.keep_one(df.orderBy(F.rand(k))).where("doc_id = 4").first()["id"] for k in range(2)]
    assert again[0] == again[1]
    assert (None, None) in {(r["doc_id"], r["component_id"]) for r in neardup.similar_groups(df).collect()}
    none = neardup.keep_one(empty(spark))
    assert none.count() == 0 and none.columns == spark.createDataFrame([], DOCS).columns


def test_many_wanted_texts_are_joined_without_a_broadcast(spark, monkeypatch):
    monkeypatch.setattr(neardup, "BROADCAST_TEXTS", 2)
    rows = near_copies(12, 60, 3)
    assert groups(spark.createDataFrame(rows, SCHEMA)) == brute_groups(rows)
