"""Near duplicates by similarity: groups of texts whose sets of five-word shingles have a Jaccard index of at least 0.8.

Texts that share 0.8 of their shingles differ in 8 to 14 of 64 fingerprint bits, where pigeonhole blocks would be 4 bits
wide and hold everything. So candidates come from SimHash blocks (at most 2 bits apart) and from bands of least shingle
hashes, and links from the exact Jaccard index of the shingle sets alone. Nothing expands a group into its pairs:

1. Equal word sequences are one text. A text is compared with one leader, the least text that shares a band or a block
   with it and could be similar; links of these comparisons make the first components.
2. Band buckets that the components leave in several parts are compared again, across components only: pair by pair up
   to BUCKET texts; the texts of larger ones by an exact prefix join (`prefix_pairs`), so that no link between texts that
   share a band is lost, however large the bucket.

What could be similar: two sets at similarity s differ in at most (1 - s) / (1 + s) of their summed sizes. Every text
carries a parity sketch of SKETCH_BITS (the shingle hashes, each of which flips one bit); the bits in which two sketches differ
never outnumber the shingles in which the sets differ, so the filter drops no similar pair.

A pair at similarity s shares no band with probability (1 - s**ROWS)**BANDS: 2.6e-5 at 0.8, 2e-7 at 0.85.

Null and empty texts, and texts without words, are one text. A null id counts as larger than all others. Rows that share an
id are texts of their own unless their words are equal. Of a group stays the row with the smallest id; of rows with that id
the text of the smallest hash, and of equal rows one. Other columns are not read, whatever their names. Empty tables give
empty results."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from sparsegraph.operators.components import components

from .common import map_rows, materialise, texts_of
from .simhash import block_masks, fold_bits, shingle_hashes

BANDS, ROWS = 20, 4
BUCKET = 32
SIMILARITY = 0.8
SHINGLE = 5
SKETCH_BITS = 1024
#: The sketch folded to so many bits travels with the rows of the prefix join.
FOLD_LONGS = 4
#: So many shingles before each row of the prefix join travel with it, to tell pairs that an earlier row has made.
BEFORE = 16
#: Texts whose shingle sets are fetched by a broadcast of their names; more go through a shuffle.
BROADCAST_TEXTS = 500_000
LAST = (1 << 63) - 1


def multipliers() -> np.ndarray:
    """Odd 64-bit factors of a fixed sequence, one for each least hash."""
    x, out = 0x243F6A8885A308D3, []
    for _ in range(BANDS * ROWS):
        x = (x * 6364136223846793005 + 1442695040888963407) % (1 << 64)
        out.append(x | 1)
    return np.array(out, np.uint64)


def band_keys(hashes: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """(texts, BANDS): a key for each band of ROWS least hashes; texts without shingles have the key zero."""
    full = np.flatnonzero(np.diff(begin) > 0)
    keys = np.zeros((len(begin) - 1, BANDS), np.uint64)
    if not len(full):
        return keys
    with np.errstate(over="ignore"):
        x, high = np.empty_like(hashes), np.empty_like(hashes)
        for i, m in enumerate(multipliers()):
            np.multiply(hashes, m, out=x)
            np.right_shift(x, np.uint64(32), out=high)
            x ^= high
            x *= np.uint64(0x9E3779B97F4A7C15)
            low = np.minimum.reduceat(x, begin[full])
            keys[full, i // ROWS] = (keys[full, i // ROWS] ^ low) * np.uint64(0xBF58476D1CE4E5B9) + np.uint64(i)
    return keys


def distinct_shingles(hashes: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The sorted distinct hashes of each text, and where each text's begin."""
    text = np.repeat(np.arange(len(begin) - 1), np.diff(begin))
    order = np.lexsort((hashes, text))
    h, t = hashes[order], text[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (t[1:] != t[:-1])
    return h[new], np.searchsorted(t[new], np.arange(len(begin)))


def sketches(sets: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """(texts, SKETCH_BITS / 64): bit b is the parity of the number of shingles whose hash begins with b."""
    out = np.zeros((len(begin) - 1, SKETCH_BITS // 64), np.uint64)
    bit = (sets >> np.uint64(54)).astype(np.int64)
    for a in range(0, len(out), 2000):
        b = min(a + 2000, len(out))
        n = np.diff(begin[a : b + 1])
        at = np.repeat(np.arange(b - a) * SKETCH_BITS, n) + bit[begin[a] : begin[b]]
        odd = (np.bincount(at, minlength=(b - a) * SKETCH_BITS) & 1).astype(np.uint8)
        out[a:b] = np.packbits(odd, bitorder="little").view(np.uint64).reshape(b - a, -1)
    return out


def named(docs: DataFrame) -> DataFrame:
    """(doc, id, tk, tie): each row of docs as a struct, its id (nulls last), and hashes of its text and of the other columns."""
    rest = [F.col(f"`{c}`") for c, kind in docs.dtypes if c not in ("doc_id", "text") and "map<" not in kind and kind != "variant"]
    tie = F.xxhash64(*rest) if rest else F.lit(0).cast("bigint")
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("doc"), F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("tk"), tie.alias("tie"))


def marks(docs: DataFrame) -> DataFrame:
    """(id, tk, tie, whole, fp, n, sketch, keys): names of a row, a hash of all its words, the fingerprint, the number of
    distinct shingles, their sketch, band keys."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = texts_of(batch.column("text"))
        hashes, begin = shingle_hashes(texts, SHINGLE)
        whole, _ = shingle_hashes(texts, 1 << 40)
        some = np.zeros(len(texts), np.uint64)
        some[np.diff(begin) > 0] = whole
        sets, at = distinct_shingles(hashes, begin)
        listed = lambda x: pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), pa.array(np.ascontiguousarray(x).reshape(-1).view(np.int64)))
        arrays = [pa.array(some.view(np.int64)), pa.array(fold_bits(hashes, begin).view(np.int64)), pa.array(np.diff(at), pa.int64()), listed(sketches(sets, at)), listed(band_keys(hashes, begin))]
        return pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("id", "tk", "tie")), *arrays], names=["id", "tk", "tie", "whole", "fp", "n", "sketch", "keys"])

    return map_rows(named(docs).select("doc.text", "id", "tk", "tie"), run, "id long, tk long, tie long, whole long, fp long, n long, sketch array<long>, keys array<long>")


def distinct_texts(marked: DataFrame) -> DataFrame:
    """(node, id, tk, whole, fp, n, sketch, keys), one row for each word sequence: its first row's names and a number."""
    first = marked.groupBy("whole", "fp").agg(F.min(F.struct("id", "tk")).alias("f"), *[F.first(c).alias(c) for c in ("n", "sketch", "keys")])
    return materialise(first.select(F.monotonically_increasing_id().alias("node"), "f.id", "f.tk", "whole", "fp", "n", "sketch", "keys"), "texts")


def could_be_similar(n1: Column, s1: Column, n2: Column, s2: Column, similarity: float) -> Column:
    """False only for sets (n shingles, sketch s) whose similarity is lower."""
    apart = F.aggregate(F.zip_with(s1, s2, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda a, x: a + x)
    return apart <= (n1 + n2) * ((1 - similarity) / (1 + similarity)) + 1e-9


def filtered(pairs: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """The pairs (src, dst) that could be similar."""
    a = texts.select(F.col("node").alias("src"), F.col("n").alias("na"), F.col("sketch").alias("sa"))
    b = texts.select(F.col("node").alias("dst"), F.col("n").alias("nb"), F.col("sketch").alias("sb"))
    return pairs.join(a, "src").join(b, "dst").where(could_be_similar(F.col("na"), F.col("sa"), F.col("nb"), F.col("sb"), similarity)).select("src", "dst")


def shingle_sets(docs: DataFrame, nodes: DataFrame) -> DataFrame:
    """(node, n, shingles): the sorted distinct shingle hashes, as bytes, of the texts `nodes` (node, id, tk)."""
    # Two longs and a key for each text, at most BROADCAST_TEXTS of them; else Spark plans the join.
    nodes = materialise(nodes.select("node", "id", "tk"), "wanted")
    wanted = F.broadcast(nodes) if nodes.count() <= BROADCAST_TEXTS else nodes
    rows = named(docs.select("doc_id", "text")).join(wanted, ["id", "tk"]).select("doc.text", "node")

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets, at = distinct_shingles(*shingle_hashes(texts_of(batch.column("text")), SHINGLE))
        data = [sets[a:b].tobytes() for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
        return pa.RecordBatch.from_arrays([batch.column("node"), pa.array(np.diff(at), pa.int64()), pa.array(data, pa.binary())], names=["node", "n", "shingles"])

    # Repeated rows give the same set more than once.
    return materialise(map_rows(rows, run, "node long, n long, shingles binary"), "sets")


def similar(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs whose shingle sets have a Jaccard index of at least `similarity`."""
    both = pairs.join(sets.select(F.col("node").alias("src"), F.col("shingles").alias("a")), "src").join(sets.select(F.col("node").alias("dst"), F.col("shingles").alias("b")), "dst")

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        keep = []
        for k, (x, y) in enumerate(zip(batch.column("a"), batch.column("b"), strict=True)):
            x, y = (np.frombuffer(v.as_buffer(), np.uint64) for v in (x, y))
            shared = len(np.intersect1d(x, y, assume_unique=True))
            if shared >= similarity * (len(x) + len(y) - shared):
                keep.append(k)
        return batch.select(["src", "dst"]).take(pa.array(keep, pa.int64()))

    return map_rows(both.select("src", "dst", "a", "b"), run, "src long, dst long")


def band_rows(texts: DataFrame) -> DataFrame:
    """(t, key, node, texts, least) of the buckets with more than one text: one for each band, and one for each choice of
    pigeonhole blocks of the fingerprint, so that texts at most 2 bits apart share one too."""
    blocks = [F.col("fp").bitwiseAND(F.lit(m)) for m in block_masks(2)]
    rows = texts.select("node", F.posexplode(F.concat("keys", F.array(*blocks))).alias("t", "key"))
    sizes = rows.groupBy("t", "key").agg(F.count("*").alias("texts"), F.min("node").alias("least")).where("texts > 1")
    return materialise(rows.join(sizes, ["t", "key"]), "bands")


def roots(up: DataFrame) -> DataFrame:
    """(node, component) of a forest (src, dst) in which every dst has one src, by doubling: each round every text takes the
    place of its leader's leader, so the rounds are the logarithm of the longest chain."""
    at = materialise(up.select(F.col("dst").alias("node"), F.col("src").alias("component")), "roots")
    while True:
        above = at.select(F.col("node").alias("component"), F.col("component").alias("top"))
        at = materialise(at.join(above, "component", "left").select("node", F.coalesce("top", "component").alias("component"), F.col("top").isNotNull().alias("moved")), "roots")
        if at.where("moved").isEmpty():
            return at.select("node", "component")
        at = at.select("node", "component")


def open_rows(bands: DataFrame, found: DataFrame) -> DataFrame:
    """(t, key, node, texts, component) of the buckets that the components leave in more than one part."""
    rows = bands.join(found, "node", "left").withColumn("component", F.coalesce("component", "node"))
    parts = rows.groupBy("t", "key").agg(F.min("component").alias("a"), F.max("component").alias("b")).where("a <> b").select("t", "key")
    return materialise(rows.join(parts, ["t", "key"], "left_semi").select("t", "key", "node", "texts", "component"), "open")


def across(rows: DataFrame) -> DataFrame:
    """(src, dst) of all texts of different components that share one of the buckets."""
    a = rows.select("t", "key", F.col("node").alias("src"), F.col("component").alias("ca"))
    b = rows.select("t", "key", F.col("node").alias("dst"), F.col("component").alias("cb"))
    return a.join(b, ["t", "key"]).where("src < dst and ca <> cb").select("src", "dst").distinct()


def folded_sketch(k: int) -> Column:
    """Every FOLD_LONGS-th long of the sketch from the k-th on, by exclusive or: still a parity sketch, of fewer bits."""
    longs = [F.get("sketch", F.lit(i)) for i in range(k, SKETCH_BITS // 64, FOLD_LONGS)]
    out = longs[0]
    for x in longs[1:]:
        out = out.bitwiseXOR(x)
    return out.alias(f"s{k}")


def prefix_pairs(sets: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """(src, dst): candidates that hold every pair of `texts` (node, component, sketch) of different components whose Jaccard
    index is at least `similarity`; sets (node, n, shingles) are theirs.

    With shingles in order of rarity, two sets of that similarity share one among the first n - ceil(similarity * n) + 1
    of each. Of the texts that share such a shingle, those of its most frequent component are not paired with each other,
    as they are linked already; so a group of copies costs its size times the number of strangers in it, not its square.
    A pair leaves the join only if sizes, places of the shingle, shingles that nobody else holds and folded sketches
    allow the similarity."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        each = [np.frombuffer(x.as_buffer(), np.int64) for x in batch.column("shingles")]
        n = np.array([len(x) for x in each], np.int64)
        flat = np.concatenate(each) if each else np.zeros(0, np.int64)
        return pa.RecordBatch.from_arrays([batch.column("node").take(pa.array(np.repeat(np.arange(len(n)), n))), pa.array(np.repeat(n, n)), pa.array(flat)], names=["node", "n", "shingle"])

    sets = sets.join(texts.select("node").distinct(), "node", "left_semi").dropDuplicates(["node"]).select("shingles", "node")
    rows = materialise(map_rows(sets, run, "node long, n long, shingle long"), "shingles")
    # A shingle that one text alone holds comes first in the order, matches nothing, and is only counted.
    held = materialise(rows.groupBy("shingle").agg(F.count("*").alias("texts"), F.min("node").alias("node")), "rarity")
    own = held.where("texts = 1").groupBy("node").agg(F.count("*").alias("own"))
    place = rows.groupBy("node").agg(F.first("n").alias("n")).join(own, "node", "left").select("node", "n", F.coalesce("own", F.lit(0)).alias("own"), (F.col("n") - F.ceil(F.col("n") * similarity - 1e-9) + 1).alias("prefix"))
    rare = held.where((F.col("texts") > 1) & (F.col("texts") <= BUCKET)).select("shingle", "texts")
    low = materialise(rows.select("node", "shingle").join(rare, "shingle"), "rare")
    place = materialise(place.join(low.groupBy("node").agg(F.count("*").alias("low")), "node", "left").withColumn("low", F.coalesce("low", F.lit(0))), "places")
    # Frequent shingles matter only to texts whose own and rare ones do not fill the prefix.
    short = place.where("own + low < prefix").select("node")
    common = map_rows(sets.join(short, "node", "left_semi"), run, "node long, n long, shingle long").select("node", "shingle").join(held.where(F.col("texts") > BUCKET).select("shingle", "texts"), "shingle")
    mine = W.partitionBy("node").orderBy("texts", "shingle")
    ranked = low.unionByName(common).join(place, "node").withColumns({"rank": F.col("own") + F.row_number().over(mine), "before": F.collect_list("shingle").over(mine.rowsBetween(-BEFORE, -1))})
    folded = [folded_sketch(k) for k in range(FOLD_LONGS)]
    first = ranked.where(F.col("rank") <= F.col("prefix")).select("node", "n", "shingle", "rank", "own", "before")
    first = materialise(first.join(texts.select("node", "component", *folded), "node"), "prefixes")
    sizes = first.groupBy("shingle", "component").agg(F.count("*").alias("k"))
    main = sizes.groupBy("shingle").agg(F.max_by("component", F.struct("k", "component")).alias("main"), F.count("*").alias("parts")).where("parts > 1").select("shingle", "main")
    split = materialise(first.join(main, "shingle"), "split")
    x = split.where("component <> main").select("shingle", *[F.col(c).alias(f"x_{c}") for c in ("node", "n", "rank", "own", "before", "component", *(f"s{k}" for k in range(FOLD_LONGS)))])
    apart = (F.col("x_n") + F.col("n")) * ((1 - similarity) / (1 + similarity)) + 1e-9
    # A pair shares at most the shingles from its first common one on; that row passes if the pair is similar.
    at_most = F.least(F.col("x_n") - F.col("x_rank"), F.col("n") - F.col("rank")) + 1
    bits = sum((F.bit_count(F.col(f"x_s{k}").bitwiseXOR(F.col(f"s{k}"))) for k in range(FOLD_LONGS)), F.lit(0))
    fits = (F.col("x_n") + F.col("n") - 2 * at_most <= apart) & (F.col("x_own") + F.col("own") <= apart) & (bits <= apart)
    # Where both are strangers, the pair would come twice.
    once = (F.col("component") == F.col("main")) | (F.col("x_node") < F.col("node"))
    # A pair that shares one of the shingles just before leaves the join there.
    fresh = ~F.arrays_overlap("x_before", "before")
    both = x.join(split, "shingle").where((F.col("x_component") != F.col("component")) & once & fits & fresh)
    return both.select(F.least("x_node", "node").alias("src"), F.greatest("x_node", "node").alias("dst")).distinct()


def text_groups(docs: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """(node, component) of the texts that a link ties to another one."""
    bands = band_rows(texts)
    names = texts.select("node", "id", "tk")
    wanted = lambda pairs: names.join(pairs.select(F.col("src").alias("node")).union(pairs.select("dst")).distinct(), "node", "left_semi")
    leaders = bands.where("node > least").select(F.col("least").alias("src"), F.col("node").alias("dst")).distinct()
    first = materialise(filtered(leaders, texts, similarity).groupBy("dst").agg(F.min("src").alias("src")).select("src", "dst"), "leaders")
    found = roots(similar(first, shingle_sets(docs, wanted(first)), similarity).distinct())
    left = open_rows(bands, found)
    if left.isEmpty():
        return found
    small, large = left.where(F.col("texts") <= BUCKET), left.where(F.col("texts") > BUCKET)
    pairs = materialise(filtered(across(small).join(first, ["src", "dst"], "left_anti"), texts, similarity), "across")
    rest = materialise(large.select("node", "component").distinct().join(texts.select("node", "sketch"), "node"), "undecided")
    sets = shingle_sets(docs, wanted(pairs.unionByName(rest.select(F.col("node").alias("src"), F.col("node").alias("dst")))))
    if not rest.isEmpty():
        pairs = materialise(pairs.unionByName(filtered(prefix_pairs(sets, rest, similarity), texts, similarity)).distinct(), "pairs")
    # Links between components make components of components.
    part = left.select("node", "component").distinct()
    between = similar(pairs, sets, similarity).join(part.toDF("src", "a"), "src").join(part.toDF("dst", "b"), "dst")
    merged = components(between.select("a", "b").distinct(), "a", "b").select(F.col("id").alias("component"), F.col("component").alias("merged"))
    every = found.unionByName(part).distinct()
    return every.join(merged, "component", "left").select("node", F.coalesce("merged", "component").alias("component"))


def grouped(docs: DataFrame, similarity: float) -> tuple[DataFrame, DataFrame]:
    """The marks of all rows, and (node, whole, fp, id, tk, component) of all texts."""
    marked = materialise(marks(docs), "marks")
    texts = distinct_texts(marked)
    found = text_groups(docs, texts, similarity)
    texts = texts.select("node", "whole", "fp", "id", "tk").join(found, "node", "left")
    return marked, materialise(texts.withColumn("component", F.coalesce("component", "node")), "grouped")


def similar_groups(docs: DataFrame, *, similarity: float = SIMILARITY) -> DataFrame:
    """(doc_id, component_id) for each row: the smallest id of its group, null if no row of it has one."""
    marked, texts = grouped(docs, similarity)
    least = texts.groupBy("component").agg(F.min("id").alias("least"))
    of = texts.join(least, "component").select("whole", "fp", "least")
    given = lambda c: F.when(F.col(c) != LAST, F.col(c))
    return marked.select("id", "whole", "fp").join(of, ["whole", "fp"]).select(given("id").alias("doc_id"), given("least").alias("component_id"))


def keep_one(docs: DataFrame, *, similarity: float = SIMILARITY) -> DataFrame:
    """docs with one row of each group of near duplicates: see the module's text for which."""
    marked, texts = grouped(docs, similarity)
    first = texts.groupBy("component").agg(F.min(F.struct("id", "tk")).alias("f")).select("f.id", "f.tk")
    rows = marked.select("id", "tk", "tie").join(first, ["id", "tk"])
    stay = materialise(rows.groupBy("id", "tk").agg(F.min("tie").alias("tie"), F.count("*").alias("rows")), "stay")
    out = named(docs).join(stay.select("id", "tk", "tie"), ["id", "tk", "tie"], "left_semi")
    if not stay.where("rows > 1").isEmpty():
        out = out.dropDuplicates(["id", "tk", "tie"])
    return out.select("doc.*")
