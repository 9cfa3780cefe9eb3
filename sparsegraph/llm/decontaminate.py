"""Benchmark decontamination: a broadcast hash set of the test items' word windows, scanned over whole documents.

Words are maximal runs of ASCII digits, a-z (A-Z is lower-cased) and all non-ASCII characters. A test item gives one
window for each WINDOW consecutive words; an item of fewer words, but not none, is one window. A scan looks windows up
by 64-bit hash, behind a bit table that most windows fail, and compares each hit's words with the item's words.

Items are broadcast in blocks of at most BLOCK_BYTES of text, whose windows each worker sorts once. Usually all items are
one block; more blocks meet the documents one after the other, each in a pass of its own, so that never more than one is
held in memory.

Nulls and texts without words: no words, no hits. Items without words: no windows. An item without an id counts as the item
"". Repeated rows are scanned each for itself; items with equal ids count once. Empty tables give empty results or
documents without hits. Other columns of the documents stay as they are."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bytewords as bw
from .common import map_rows, materialise, schema_of, texts_of

WINDOW = 10
#: A block of items has at most this many bytes of text; an item that is larger is a block of its own.
BLOCK_BYTES = 32 << 20
FILTER_BITS = 22


def item_blocks(items: DataFrame, id_col: str, text_col: str, block_bytes: int) -> Iterator[list[tuple[str, bytes]]]:
    """Items in blocks of a proven size: they come one partition at a time and are cut at block_bytes."""
    block, size = [], 0
    rows = items.where(F.col(text_col).isNotNull()).select(F.coalesce(F.col(id_col).cast("string"), F.lit("")), F.encode(F.col(text_col), "UTF-8"))
    for key, text in rows.toLocalIterator():
        if block and size + len(text) > block_bytes:
            yield block
            block, size = [], 0
        block.append((key, bytes(text)))
        size += len(text)
    if block:
        yield block


class Scanner:
    """Finds a block's windows in texts: for each window length the sorted hashes of the windows, and where they stand."""

    def __init__(self, items: list[tuple[str, bytes]], window: int):
        self.keys = [k for k, _ in items]
        self.words = words = bw.Words([t for _, t in items], bw.alnum_class())
        count = words.count()
        self.levels = {}
        for n in sorted({min(window, c) for c in count.tolist()} - {0}):
            own = np.flatnonzero(np.minimum(count, window) == n)
            starts = [np.arange(words.doc[k], words.doc[k + 1] - n + 1) for k in own]
            at = np.concatenate(starts)
            item = np.repeat(own, [len(s) for s in starts])
            hashes = words.window_hashes(n)[at]
            order = np.argsort(hashes, kind="stable")
            bits = np.zeros(1 << FILTER_BITS, bool)
            bits[hashes >> np.uint64(64 - FILTER_BITS)] = True
            self.levels[n] = (bits, hashes[order], at[order], item[order])
        self.known: dict[tuple[int, int], dict[bytes, list[str]]] = {}

    def owners(self, n: int, low: int, high: int) -> dict[bytes, list[str]]:
        """The words of the windows from place low to high of equal hash, and the items that hold them."""
        if (n, low) not in self.known:
            _, _, at, item = self.levels[n]
            out: dict[bytes, dict[str, None]] = {}
            for a, k in zip(at[low:high].tolist(), item[low:high].tolist(), strict=True):
                out.setdefault(self.words.span(a, n), {})[self.keys[k]] = None
            self.known[n, low] = {w: list(keys) for w, keys in out.items()}
        return self.known[n, low]

    def hits(self, words: bw.Words) -> Iterator[tuple[int, int, list[str]]]:
        """(first word, words, items) of every occurrence."""
        for n, (bits, keys, _, _) in self.levels.items():
            hashes = words.window_hashes(n)
            at = np.flatnonzero(bits[hashes >> np.uint64(64 - FILTER_BITS)])
            at = at[words.inside(at, n)]
            low, high = np.searchsorted(keys, hashes[at], "left"), np.searchsorted(keys, hashes[at], "right")
            for i, a, b in zip(at.tolist(), low.tolist(), high.tolist(), strict=True):
                if a < b and (found := self.owners(n, a, b).get(words.span(i, n))):
                    yield i, n, found


#: The block that a worker has sorted last.
_HELD: dict[str, Scanner] = {}


def scanner(block, name: str, window: int) -> Scanner:
    if name not in _HELD:
        _HELD.clear()
        _HELD[name] = Scanner(block.value, window)
    return _HELD[name]


SCAN = "struct<n_words:bigint,hits:array<struct<first:int,words:int>>,bytes:array<struct<start:int,end:int>>,items:array<string>>"
KIND = pa.struct([("n_words", pa.int64()), ("hits", pa.list_(pa.struct([("first", pa.int32()), ("words", pa.int32())]))), ("bytes", pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))), ("items", pa.list_(pa.string()))])


def find(texts: list[bytes], block: Scanner | None, before: list[dict] | None = None) -> list[dict]:
    """For each text: n_words, hits, bytes and items of a scan, with those of the scans `before`."""
    words = bw.Words(texts, bw.alnum_class())
    owners: dict[int, set[str]] = {}
    mark = np.zeros(len(words.start) + 1, np.int64)
    for k, b in enumerate(before or ()):
        if b["hits"]:
            owners[k] = set(b["items"])
            for h in b["hits"]:
                mark[words.doc[k] + h["first"]] += 1
                mark[words.doc[k] + h["first"] + h["words"]] -= 1
    for i, k, keys in block.hits(words) if block else ():
        mark[i] += 1
        mark[i + k] -= 1
        owners.setdefault(int(np.searchsorted(words.doc, i, side="right")) - 1, set()).update(keys)
    hit = np.cumsum(mark[:-1]) > 0
    out = [{"n_words": c, "hits": [], "bytes": [], "items": []} for c in words.count().tolist()]
    for k, keys in owners.items():
        low, high = int(words.doc[k]), int(words.doc[k + 1])
        step = np.diff(np.concatenate(([0], hit[low:high].astype(np.int8), [0])))
        for s, e in zip(np.flatnonzero(step == 1).tolist(), np.flatnonzero(step == -1).tolist(), strict=True):
            out[k]["hits"].append({"first": s, "words": e - s})
            out[k]["bytes"].append({"start": int(words.start[low + s] - words.offsets[k]), "end": int(words.end[low + e - 1] - words.offsets[k])})
        out[k]["items"] = sorted(keys)
    return out


def scanned(docs: DataFrame, items: DataFrame, text_col: str, item_id: str, item_text: str, window: int, block_bytes: int, finish: Callable[[pa.RecordBatch, list[bytes], list[dict]], pa.RecordBatch], schema: str) -> DataFrame:
    """finish(batch, texts, scans) over all documents, after a pass for each block of items."""
    column = f"scan-{uuid.uuid4().hex[:8]}"
    context = docs.sparkSession.sparkContext

    def step(rows: DataFrame, block: list | None, last: bool) -> DataFrame:
        shared, name = (context.broadcast(block), uuid.uuid4().hex) if block else (None, "")
        carried = column in rows.columns

        def run(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = texts_of(batch.column(text_col))
            before = batch.column(column).to_pylist() if carried else None
            found = find(texts, scanner(shared, name, window) if shared else None, before)
            names = [c for c in batch.schema.names if c != column]
            batch = batch.select(names)
            return finish(batch, texts, found) if last else pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, KIND)], names=[*names, column])

        return map_rows(rows, run, schema if last else schema_of(rows.drop(column), f"`{column}` {SCAN}"))

    blocks = item_blocks(items, item_id, item_text, block_bytes)
    block = next(blocks, None)
    while (after := next(blocks, None)) is not None:
        docs = materialise(step(docs, block, False), "scanned")
        block = after
    return step(docs, block, True)


def scan(docs: DataFrame, items: DataFrame, *, text_col: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = WINDOW, block_bytes: int = BLOCK_BYTES, keep: list[str] | None = None) -> DataFrame:
    """docs (or its columns `keep`) plus, in a struct column `scan`: n_words; hits, the maximal runs of hit words; bytes,
    the same runs as byte offsets of the UTF-8 text; items, the sorted ids of the items that occur."""
    docs = docs.drop("scan")
    kept = keep or docs.columns

    def finish(batch: pa.RecordBatch, _: list[bytes], found: list[dict]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(found, KIND)], names=[*kept, "scan"])

    return scanned(docs, items, text_col, item_id, item_text, window, block_bytes, finish, schema_of(docs.select(*kept), f"scan {SCAN}"))


def contamination(docs: DataFrame, items: DataFrame, *, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row for each document: doc_id, n_words, n_hit, n_items, items, contaminated."""
    s = scan(docs.select("doc_id", "text"), items.select("item_id", "text"), window=window, block_bytes=block_bytes, keep=["doc_id"])
    return s.select(
        "doc_id",
        F.col("scan.n_words").alias("n_words"),
        F.aggregate("scan.hits", F.lit(0).cast("long"), lambda a, x: a + x["words"]).alias("n_hit"),
        F.size("scan.items").cast("long").alias("n_items"),
        F.col("scan.items").alias("items"),
        (F.size("scan.hits") > 0).alias("contaminated"),
    )


def remove_spans(docs: DataFrame, items: DataFrame, *, window: int = WINDOW, max_share: float = 0.5, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Documents without their contaminated parts: hit runs go from the text; a document of which more than max_share of
    the words is hit goes altogether. Columns stay; n_chars follows the text (null: 0)."""

    def finish(batch: pa.RecordBatch, texts: list[bytes], scans: list[dict]) -> pa.RecordBatch:
        null = batch.column("text").is_null().to_pylist()
        stay, out = [], []
        for k, found in enumerate(scans):
            if sum(h["words"] for h in found["hits"]) > max_share * found["n_words"]:
                continue
            stay.append(k)
            text = None if null[k] else texts[k]
            if found["bytes"]:
                edge = [0, *(x for r in found["bytes"] for x in (r["start"], r["end"])), len(text)]
                text = b"".join(text[a:b] for a, b in zip(edge[::2], edge[1::2], strict=True))
            out.append(text)
        part = batch.take(pa.array(stay, pa.int64()))
        columns = [pa.array(out, pa.binary()).cast(pa.string()) if c == "text" else part.column(c) for c in part.schema.names]
        return pa.RecordBatch.from_arrays(columns, names=part.schema.names)

    out = scanned(docs, items, "text", "item_id", "text", window, block_bytes, finish, schema_of(docs))
    if "n_chars" in out.columns:
        out = out.withColumn("n_chars", F.coalesce(F.char_length("text"), F.lit(0)).cast(dict(docs.dtypes)["n_chars"]))
    return out
