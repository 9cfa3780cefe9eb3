"""Toxic passages as maximum-scoring segments over token log-odds.

Fit: words of labelled documents and their stems, counted once for each document, get log-odds between the two classes with an
informative Dirichlet prior (the pooled counts); tokens whose z-score is large either way carry their log-odds. A word scores
as the scan finds it, by itself or by its longest such stem; all other words carry the small negative score that makes both
sides sum to one. Scan: every maximal scoring segment of a document in
linear time. Calibration: a segment of score S in n words has expectation K n exp(-lambda S) by chance (extreme-value
law; lambda solves E exp(lambda s) = 1 over the scores that the scan gives the words of clean documents, K is fitted on
clean documents). The bits of all segments beyond
chance add up; a logistic curve on the fitted rows turns them into the chance of label 1.

Nulls and empty texts: no words, no segments, the base score. Labels other than 0 and 1, and null labels, are not
learned from. Ties and repeated rows: each row is scored for itself, and learned from once. Without labels of both classes, the model knows no words and
gives the base rate (0.5 without labels). Very long texts: whole, in bounded memory."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import bytewords as bw
from .common import map_rows, materialise, sample_rows, schema_of, texts_of

#: Bound of the labelled rows that a fit reads.
FIT_ROWS = 20_000
Z_MIN = 3.0
#: The prior weighs this share of the pooled counts.
PRIOR_SHARE = 0.1
#: Lengths in bytes of the stems that count as tokens beside the whole words.
STEMS = (4, 5, 6, 7, 8)


@dataclass
class ToxicityModel:
    words: dict[bytes, float] = field(default_factory=dict)
    drift: float = -1e-3
    lam: float = 1.0
    k: float = 1.0
    slope: float = 0.0
    bias: float = 0.0

    def bits(self, best: float, n_words: int) -> float:
        """Natural-log units by which a segment score exceeds what n_words clean words give by chance."""
        return self.lam * best - math.log(self.k * max(n_words, 1) + 1.0)

    def probability(self, evidence: float) -> float:
        x = self.slope * evidence + self.bias
        return 1 / (1 + math.exp(-x)) if x > -500 else 0.0


def segments(scores: list[float], at: list[int], drift: float) -> list[tuple[int, int, float]]:
    """All maximal scoring segments of a sequence that scores drift (< 0) everywhere but at the positions `at`.

    Ruzzo and Tompa's stack, over the positive positions alone: what lies between them is one negative step.
    Returns (first, last, score), from left to right."""
    stack: list[list[float]] = []  # first, last, sum before, sum after
    total, prev = 0.0, -1
    for s, i in zip(scores, at, strict=True):
        total += drift * (i - prev - 1)
        prev = i
        before, total = total, total + s
        if s <= 0:
            continue
        item = [i, i, before, total]
        while True:
            j = len(stack) - 1
            while j >= 0 and stack[j][2] >= item[2]:
                j -= 1
            if j < 0 or stack[j][3] >= item[3]:
                stack.append(item)
                break
            item = [stack[j][0], item[1], stack[j][2], item[3]]
            del stack[j:]
    return [(int(a), int(b), after - before) for a, b, before, after in stack]


def token_hashes(words: bw.Words, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(words, hashes): the whole words (length 0), or the first `length` bytes of the words that are longer."""
    if not length:
        return np.arange(len(words.start)), words.hashes
    at = np.flatnonzero(words.end - words.start > length)
    h = bw.word_hashes(words.buf, words.start[at], words.start[at] + length)
    return at, h ^ np.uint64(length * 0x9E3779B97F4A7C1)


def token(words: bw.Words, at: int, length: int) -> bytes:
    """A word, or a stem followed by a star."""
    return words.word(at) if not length else words.raw[words.start[at] : words.start[at] + length] + b"*"


class Lookup:
    """Scores of a model's tokens by hash; equal hashes of other tokens are told apart by their bytes. A word has the score
    of itself, else of its longest known stem."""

    def __init__(self, model: ToxicityModel):
        self.levels = []
        for length in (0, *sorted(STEMS, reverse=True)):
            texts = [t for t in model.words if (t.endswith(b"*") and len(t) == length + 1) == bool(length) and t.endswith(b"*") == bool(length)]
            if not texts:
                continue
            # A stem's hash is that of a longer word that begins with it.
            _, hashes = token_hashes(bw.Words([t[:-1] + b"zz" if length else t for t in texts], bw.alnum_class()), length)
            order = np.argsort(hashes)
            flags = np.zeros(1 << 16, bool)
            flags[hashes >> np.uint64(48)] = True
            self.levels.append((length, hashes[order], [texts[i] for i in order], np.array([model.words[texts[i]] for i in order]), flags))

    def find(self, words: bw.Words) -> tuple[np.ndarray, np.ndarray]:
        """Positions of words with a score, and the scores."""
        score = np.full(len(words.start), np.nan)
        for length, keys, texts, scores, flags in self.levels:
            at, hashes = token_hashes(words, length)
            some = np.flatnonzero(flags[hashes >> np.uint64(48)])
            some = some[np.isnan(score[at[some]])]
            k = np.minimum(np.searchsorted(keys, hashes[some]), len(keys) - 1)
            same = keys[k] == hashes[some]
            for i, j in zip(at[some[same]].tolist(), k[same].tolist(), strict=True):
                if token(words, i, length) == texts[j]:
                    score[i] = scores[j]
        at = np.flatnonzero(~np.isnan(score))
        return at, score[at]


def lookup_of(shared) -> Lookup:
    """The lookup of a broadcast model, made once in each worker."""
    model = shared.value
    if not hasattr(model, "_lookup"):
        model._lookup = Lookup(model)
    return model._lookup


def document_segments(words: bw.Words, lookup: Lookup, drift: float) -> list[list[tuple[int, int, float]]]:
    """For each text, its maximal scoring segments as (first word, last word, score)."""
    at, score = lookup.find(words)
    cut = np.searchsorted(at, words.doc)
    out = []
    for k in range(len(words.doc) - 1):
        a, b = int(cut[k]), int(cut[k + 1])
        out.append(segments(score[a:b].tolist(), (at[a:b] - words.doc[k]).tolist(), drift) if b > a else [])
    return out


def word_counts(labelled: DataFrame) -> DataFrame:
    """(word, toxic, clean): documents of each class that hold the token; counted within each batch before the shuffle."""

    def count(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        words = bw.Words(texts_of(batch.column("text")), bw.alnum_class())
        label = np.array(batch.column("toxic").to_pylist(), np.int64)
        doc_of = np.repeat(np.arange(batch.num_rows), words.count())
        for length in (0, *STEMS):
            at, h = token_hashes(words, length)
            doc = doc_of[at]
            order = np.lexsort((doc, h))
            h, doc, at = h[order], doc[order], at[order]
            new = np.ones(len(h), bool)
            new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
            h, doc, at = h[new], doc[new], at[new]
            if not len(h):
                continue
            first = np.flatnonzero(np.concatenate(([True], h[1:] != h[:-1])))
            toxic = np.add.reduceat(label[doc], first)
            size = np.diff(np.append(first, len(h)))
            yield pa.RecordBatch.from_pydict({"word": pa.array([token(words, i, length) for i in at[first].tolist()], pa.binary()), "toxic": pa.array(toxic, pa.int64()), "clean": pa.array(size - toxic, pa.int64())})

    return map_rows(labelled.select("text", "toxic"), count, "word binary, toxic long, clean long").groupBy("word").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))


def fit(docs: DataFrame, labels: DataFrame, *, fit_rows: int = FIT_ROWS, z_min: float = Z_MIN) -> ToxicityModel:
    """Learns from the documents whose doc_id has a label; at most fit_rows of them, those whose ids hash lowest (see
    sample_rows). The words that a model keeps are bounded by those rows alone."""
    known = labels.where("doc_id is not null and toxic in (0, 1)").select("doc_id", F.col("toxic").cast("int").alias("toxic"))
    rows = materialise(sample_rows(docs.select("doc_id", "text"), known, ["toxic"], fit_rows).select("text", "toxic"), "labelled")
    counted = word_counts(rows).persist()
    try:
        whole = counted.where(~F.col("word").endswith(F.lit(b"*")))
        total = whole.agg(F.sum("toxic").alias("t"), F.sum("clean").alias("c")).first()
        nt, nc = total["t"] or 0, total["c"] or 0
        if not nt or not nc:
            return ToxicityModel()
        prior, weight = F.lit(PRIOR_SHARE) * (F.col("toxic") + F.col("clean")), PRIOR_SHARE * (nt + nc)
        odds = lambda y, n: F.log((y + prior) / (n + weight - y - prior))
        delta = odds(F.col("toxic"), nt) - odds(F.col("clean"), nc)
        z = delta / F.sqrt(1 / (F.col("toxic") + prior) + 1 / (F.col("clean") + prior))
        best = counted.select("word", delta.alias("delta"), z.alias("z")).where(F.abs("z") >= z_min).select("word", "delta").collect()
    finally:
        counted.unpersist()
    model = ToxicityModel({bytes(r["word"]): float(r["delta"]) for r in sorted(best, key=lambda r: bytes(r["word"]))})
    # One row for each class and known token.
    seen = found_scores(rows, model).groupBy("toxic", "score").agg(F.sum("n").alias("n")).collect()
    size = {k: max(sum(r["n"] for r in seen if r["toxic"] == k), 1) for k in (0, 1)}
    known_share = {k: min(sum(r["n"] for r in seen if r["toxic"] == k and r["score"] is not None) / size[k], 0.99) for k in (0, 1)}
    model.drift = min(math.log((1 - known_share[1]) / (1 - known_share[0])), -1e-4)
    background = [(r["n"] / size[0], r["score"]) for r in seen if r["toxic"] == 0 and r["score"] is not None]
    model.lam = karlin_lambda([*background, (1 - known_share[0], model.drift)])
    lookup_rows = evidence_rows(rows, model).collect()  # a few numbers for each of at most fit_rows rows
    clean = [(r["n_words"], r["best"]) for r in lookup_rows if r["toxic"] == 0]
    model.k = len(clean) / max(sum(max(n, 1) * math.exp(-model.lam * s) for n, s in clean), 1e-9)
    x = np.array([evidence(model, r["n_words"], r["scores"]) for r in lookup_rows])
    y = np.array([r["toxic"] for r in lookup_rows])
    model.slope, model.bias = logistic(x, y)
    return model


def found_scores(rows: DataFrame, model: ToxicityModel) -> DataFrame:
    """(toxic, score, n): how many words the scan gives each score (null: none), for each class and batch."""
    shared = rows.sparkSession.sparkContext.broadcast(model)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        words = bw.Words(texts_of(batch.column("text")), bw.alnum_class())
        label = np.repeat(np.array(batch.column("toxic").to_pylist(), np.int64), words.count())
        at, score = lookup_of(shared).find(words)
        out: dict[tuple[int, float | None], int] = {}
        for k in (0, 1):
            out[k, None] = int((label == k).sum() - (label[at] == k).sum())
            for v, n in zip(*np.unique(score[label[at] == k], return_counts=True), strict=True):
                out[k, float(v)] = int(n)
        return pa.RecordBatch.from_pydict({"toxic": pa.array([k for k, _ in out], pa.int32()), "score": pa.array([v for _, v in out], pa.float64()), "n": pa.array(list(out.values()), pa.int64())})

    return map_rows(rows, run, "toxic int, score double, n long")


def karlin_lambda(scores: list[tuple[float, float]]) -> float:
    """The positive root of sum p exp(lambda s) = 1."""
    f = lambda lam: sum(p * math.exp(min(lam * s, 600)) for p, s in scores) - 1
    if not any(s > 0 for _, s in scores) or sum(p * s for p, s in scores) >= 0:
        return 1.0
    low, high = 1e-6, 1.0
    while f(high) < 0 and high < 64:
        high *= 2
    for _ in range(80):
        mid = (low + high) / 2
        low, high = (mid, high) if f(mid) < 0 else (low, mid)
    return (low + high) / 2


def logistic(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope (not below 0) and bias of a logistic curve, by Newton steps with a small ridge."""
    if not len(x):
        return 0.0, 0.0
    scale = max(float(np.std(x)), 1e-9)
    a = np.stack([x / scale, np.ones(len(x))])
    w = np.array([0.0, math.log((y.sum() + 1) / (len(y) - y.sum() + 1))])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(w @ a, -30, 30)))
        step = np.linalg.solve((a * (p * (1 - p))) @ a.T + 1e-3 * np.eye(2), a @ (p - y) + 1e-3 * w)
        w -= np.clip(step, -2, 2)
    return max(float(w[0]) / scale, 0.0), float(w[1])


def evidence(model: ToxicityModel, n_words: int, scores: list[float]) -> float:
    """Sum of the bits of all segments beyond chance (its logarithm beyond 1, so that long texts do not outweigh all others
    in the fit); else those, not positive, of the best segment."""
    bits = [model.bits(s, n_words) for s in scores]
    beyond = sum(b for b in bits if b > 0)
    return (1 + math.log(beyond) if beyond > 1 else beyond) if beyond > 0 else model.bits(max(scores, default=0.0), n_words)


def evidence_rows(rows: DataFrame, model: ToxicityModel) -> DataFrame:
    shared = rows.sparkSession.sparkContext.broadcast(model)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        model = shared.value
        words = bw.Words(texts_of(batch.column("text")), bw.alnum_class())
        found = document_segments(words, lookup_of(shared), model.drift)
        scores = [sorted((s for _, _, s in f), reverse=True) for f in found]
        return pa.RecordBatch.from_pydict({"toxic": batch.column("toxic").cast(pa.int32()), "n_words": pa.array(words.count(), pa.int64()), "best": pa.array([s[0] if s else 0.0 for s in scores], pa.float64()), "scores": pa.array(scores, pa.list_(pa.float64()))})

    return map_rows(rows, run, "toxic int, n_words long, best double, scores array<double>")


SEGMENTS = "array<struct<first:int,last:int,start:int,end:int,bits:double>>"


def score(docs: DataFrame, model: ToxicityModel, *, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """docs (or its columns `keep`) plus toxicity, the chance of label 1, and toxic_segments, the passages beyond chance
    (word and UTF-8 byte offsets, bits). Columns of these names in docs give way."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    docs = docs.drop("toxicity", "toxic_segments")
    kept = keep or docs.columns

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        model = shared.value
        words = bw.Words(texts_of(batch.column(text_col)), bw.alnum_class())
        counts = words.count().tolist()
        probability, passages = [], []
        for k, found in enumerate(document_segments(words, lookup_of(shared), model.drift)):
            probability.append(model.probability(evidence(model, counts[k], [s for _, _, s in found])))
            rows, low, origin = [], int(words.doc[k]), int(words.offsets[k])
            for a, b, s in found:
                if (bits := model.bits(s, counts[k])) > 0:
                    rows.append({"first": a, "last": b, "start": int(words.start[low + a]) - origin, "end": int(words.end[low + b]) - origin, "bits": bits})
            passages.append(rows)
        kind = pa.list_(pa.struct([("first", pa.int32()), ("last", pa.int32()), ("start", pa.int32()), ("end", pa.int32()), ("bits", pa.float64())]))
        return pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(probability, pa.float64()), pa.array(passages, kind)], names=[*kept, "toxicity", "toxic_segments"])

    return map_rows(docs, run, schema_of(docs.select(*kept), "toxicity double", f"toxic_segments {SEGMENTS}"))
