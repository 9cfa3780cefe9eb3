"""SimHash near-duplicates: 64-bit fingerprints, joined on pigeonhole blocks and verified by Hamming distance.

Texts are lower-cased (A-Z), cut into words at white space and into shingles of consecutive words, repeats included;
fewer words make one shingle. A fingerprint bit is 1 if it is set in over half of the shingles' XXH64 (seed 42).
Fingerprints of at most `distance` differing bits link.

Pigeonhole: 64 bits in BLOCKS blocks; two fingerprints at most 2 bits apart agree on at least BLOCKS - 2 blocks, so each
choice of that many blocks is a join key. Only distinct fingerprints are joined. A bucket of more than BUCKET of them is
not compared pair by pair: two fingerprints at most 2 bits apart have a fingerprint within 1 bit of both, so each is
grouped under itself and its 64 one-bit neighbours, and every group is tied to its least member. That is exact too.

Null and empty texts, and texts without words, have fingerprint zero and link like any other. Repeated rows share a
component. A null doc_id takes part through its fingerprint; its component is null only if no document with that
fingerprint has an id. Empty tables give empty results."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparsegraph.operators.components import components

from . import bytewords as bw
from .common import map_rows, materialise, texts_of

BLOCKS = 5
BUCKET = 32
SEED = 42


def shingle_hashes(texts: list[bytes], size: int) -> tuple[np.ndarray, np.ndarray]:
    """XXH64 of all shingles of all texts; where each text's shingles begin (one more than texts)."""
    words = bw.Words(texts, bw.nonspace_class(), hashed=False)
    start, end, doc = words.start, words.end, words.doc
    # All words of the batch, each followed by one space.
    keep = np.zeros(len(words.buf) + 1, np.int8)
    np.add.at(keep, start, 1)
    np.add.at(keep, np.minimum(end + 1, len(words.buf)), -1)
    keep = np.cumsum(keep[:-1]) > 0
    raw = words.buf[keep]
    length = end - start
    at = np.concatenate(([0], np.cumsum(length + 1)))[: len(start)]
    raw[at + length] = 0x20
    raw = raw.tobytes()
    count = words.count()
    shingles = np.where(count == 0, 0, np.maximum(count - size + 1, 1))
    begin = np.concatenate(([0], np.cumsum(shingles)))
    first = np.repeat(doc[:-1] - begin[:-1], shingles) + np.arange(begin[-1])
    last = np.minimum(first + size, np.repeat(doc[1:], shingles)) - 1
    digest, s, e = xxhash.xxh64_intdigest, at[first].tolist(), (at[last] + length[last]).tolist()
    return np.array([digest(raw[a:b], SEED) for a, b in zip(s, e, strict=True)], np.uint64), begin


def fold_bits(hashes: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """For each text the majority of its shingles' bits; zero without shingles."""
    out = np.zeros(len(begin) - 1, np.uint64)
    for k, (a, b) in enumerate(zip(begin[:-1].tolist(), begin[1:].tolist(), strict=True)):
        if b > a:
            ones = np.zeros(64, np.int64)
            for c in range(a, b, 1 << 14):
                ones += np.unpackbits(hashes[c : min(b, c + (1 << 14)), None].view(np.uint8), axis=1, bitorder="little").sum(0, dtype=np.int32)
            out[k] = np.packbits(2 * ones > b - a, bitorder="little").view(np.uint64)[0]
    return out


def fingerprints(docs: DataFrame, *, shingle: int = 3, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """(id, fp): the fingerprint as a signed long."""

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        fp = fold_bits(*shingle_hashes(texts_of(batch.column(1)), shingle))
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp.view(np.int64), pa.int64())], names=["id", "fp"])

    return map_rows(docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")), run, "id long, fp long")


def block_masks(distance: int) -> list[int]:
    """Masks of all choices of BLOCKS - distance blocks, as signed longs."""
    edge = [64 * k // BLOCKS for k in range(BLOCKS + 1)]
    block = [((1 << (b - a)) - 1) << a for a, b in zip(edge, edge[1:], strict=False)]
    masks = [sum(c) for c in combinations(block, BLOCKS - distance)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def links(prints: DataFrame, distance: int = 2) -> DataFrame:
    """(src, dst) that connect what fingerprints at most `distance` (0 to 2) bits apart connect; prints is (fp, rep) with
    distinct fp."""
    if not 0 <= distance <= 2:
        raise ValueError("links by blocks are exact for a distance of 0 to 2 bits")
    masks = block_masks(distance)
    blocks = prints.select("fp", "rep", F.explode(F.array(*[F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for t, m in enumerate(masks)])).alias("b")).select("b.t", "b.key", "fp", "rep")
    sizes = blocks.groupBy("t", "key").agg(F.count("*").alias("n")).where("n > 1")
    shared = materialise(blocks.join(sizes, ["t", "key"]), "blocks")
    small, hot = shared.where(F.col("n") <= BUCKET), shared.where(F.col("n") > BUCKET)
    a, b = small.select("t", "key", F.col("fp").alias("x"), F.col("rep").alias("src")), small.select("t", "key", F.col("fp").alias("y"), F.col("rep").alias("dst"))
    near = a.join(b, ["t", "key"]).where((F.col("x") < F.col("y")) & (F.bit_count(F.col("x").bitwiseXOR(F.col("y"))) <= distance)).select("src", "dst")
    return near.union(tied(hot.select("fp", "rep").distinct(), distance)).distinct()


def tied(hot: DataFrame, distance: int) -> DataFrame:
    """Links among many fingerprints without pairs; see the module's text."""
    flips: list[Column] = [F.col("fp")]
    if distance == 2:
        flips += [F.col("fp").bitwiseXOR(F.lit((1 << j) - (1 << 64) * (j == 63))) for j in range(64)]
    if distance < 2:
        # At distance 1 two fingerprints are each other's neighbour: look the neighbours up.
        near = hot.select(F.explode(F.array(*[F.col("fp").bitwiseXOR(F.lit((1 << j) - (1 << 64) * (j == 63))) for j in range(64)])).alias("fp"), F.col("rep").alias("src"))
        return near.join(hot, "fp").where(F.lit(distance == 1)).select("src", F.col("rep").alias("dst"))
    around = hot.select(F.explode(F.array(*flips)).alias("mid"), "rep")
    least = around.groupBy("mid").agg(F.min("rep").alias("least"), F.count("*").alias("n")).where("n > 1").drop("n")
    return around.join(least, "mid").where("rep <> least").select(F.col("rep").alias("src"), F.col("least").alias("dst"))


def near_duplicates(docs: DataFrame, *, shingle: int = 3, distance: int = 2, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """(doc_id, fp, component_id), one row for each row of docs."""
    marked = materialise(fingerprints(docs, shingle=shingle, text_col=text_col, id_col=id_col), "fingerprints")
    prints = materialise(marked.groupBy("fp").agg(F.min("id").alias("rep")), "prints")
    found = components(links(prints.where("rep is not null"), distance))
    named = prints.join(found.withColumnRenamed("id", "rep"), "rep", "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    return marked.join(named, "fp", "left").select(F.col("id").alias("doc_id"), "fp", "component_id")


def hex_print(fp: Column) -> Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")
