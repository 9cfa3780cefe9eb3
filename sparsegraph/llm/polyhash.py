"""Document fingerprints from prefix polynomial hashes.

The prefix array of a text holds, for each prefix, sum c[j] b**j modulo the prime 2**31 - 1, for two bases b; a span's
hash is the difference of two prefixes times a power of 1/b, so any two spans are compared in constant time and the
longest common extension of two positions is found by binary search.

A fingerprint keeps: the length; the prefix hashes at the multiples of the least power of two that gives at most 32
steps, with the hash of the whole; and the SKETCH least mixed hashes of all spans of SPAN code points (a text shorter
than SPAN is one span). Likeness of two fingerprints, 0 to 1: the larger of the share of code points in the longest
common prefix that binary search finds in the prefix hashes, and the Dice share of common spans that the sketches
estimate. Equal texts have equal fingerprints and likeness 1.

Null counts as the empty text; two empty texts are alike (1), an empty and another text are not (0). Rows are ordered by
id, then a hash of the text, then text; rows that share an id follow each other. A null id comes first. Very long texts are hashed whole, in pieces
of bounded memory."""

from __future__ import annotations

import hashlib
from collections import Counter
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import slices

M = (1 << 31) - 1
BASES = (911_382_323, 1_972_663_201)
SPAN = 16
SKETCH = 64
STEPS = 32
PIECE = 1 << 17
LOWEST = -(1 << 63)
#: UTF-8 bytes of text that one range of ids should hold.
RANGE_BYTES = 2 << 20
_TABLES: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def fold(x: np.ndarray) -> np.ndarray:
    """x modulo 2**31 - 1 for x below 2**62."""
    x = (x & M) + (x >> 31)
    x = (x & M) + (x >> 31)
    return np.where(x >= M, x - M, x)


def powers(base: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, for one piece."""
    if base not in _TABLES:
        out = []
        for b in (base, pow(base, -1, M)):
            p = np.ones(1, np.int64)
            while len(p) <= PIECE + SPAN:
                p = np.concatenate((p, fold(p * pow(b, len(p), M))))
            out.append(p[: PIECE + SPAN + 1])
        _TABLES[base] = tuple(out)
    return _TABLES[base]


class PrefixHashes:
    """The prefix arrays of one text, of whatever length."""

    def __init__(self, text: str):
        self.codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64) + 1
        self.n = len(self.codes)
        self.prefix = [self._prefix(b) for b in BASES]

    def _prefix(self, base: int) -> np.ndarray:
        p, _ = powers(base)
        out = np.zeros(self.n + 1, np.int64)
        for a in range(0, self.n, PIECE):
            c = self.codes[a : a + PIECE]
            piece = fold(np.cumsum(fold(c * p[: len(c)])))
            out[a + 1 : a + 1 + len(c)] = fold(out[a] + fold(piece * pow(base, a, M)))
        return out

    def spans(self, low: int, high: int, width: int) -> np.ndarray:
        """62-bit hashes of the spans of `width` code points that begin at low, ..., high - 1; the same for equal spans
        wherever they stand."""
        out = np.zeros(max(high - low, 0), np.int64)
        for base, pre in zip(BASES, self.prefix, strict=True):
            _, q = powers(base)
            for a in range(low, high, PIECE):
                b = min(a + PIECE, high)
                d = fold(pre[a + width : b + width] - pre[a:b] + M)
                h = fold(fold(d * q[: b - a]) * pow(base, -a, M))
                out[a - low : b - low] = (out[a - low : b - low] << 31) | h
        return out

    def span(self, at: int, width: int) -> int:
        out = 0
        for base, pre in zip(BASES, self.prefix, strict=True):
            out = out << 31 | (int(pre[at + width]) - int(pre[at])) * pow(base, -at, M) % M
        return out

    def lce(self, at: int, other: PrefixHashes, there: int) -> int:
        """Length of the longest common extension of position `at` here and `there` in the other text."""
        low, high = 0, min(self.n - at, other.n - there)
        while low < high:
            mid = (low + high + 1) // 2
            low, high = (mid, high) if self.span(at, mid) == other.span(there, mid) else (low, mid - 1)
        return low


def mixed(h: np.ndarray) -> np.ndarray:
    """A fixed permutation of 64-bit values, so that the least values are a fair sample."""
    x = h.astype(np.uint64)
    with np.errstate(over="ignore"):
        x ^= x >> np.uint64(30)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(27)
        x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def least(values: np.ndarray) -> np.ndarray:
    """The SKETCH least distinct values."""
    k = 2 * SKETCH
    while k < len(values):
        out = np.unique(np.partition(values, k)[:k])
        if len(out) >= SKETCH:
            return out[:SKETCH]
        k *= 4
    return np.unique(values)[:SKETCH]


def stride(n: int) -> int:
    s = 1
    while n // s > STEPS:
        s *= 2
    return s


class Fingerprint:
    def __init__(self, n: int, steps: list[int], whole: int, sketch: np.ndarray):
        self.n, self.steps, self.whole, self.sketch = n, steps, whole, sketch

    def __str__(self) -> str:
        return f"{self.n:x}:{self.whole:016x}:{''.join(f'{s:016x}' for s in self.steps)}:{self.sketch.astype('>u8').tobytes().hex()}"

    @classmethod
    def parse(cls, text: str) -> Fingerprint:
        n, whole, steps, sketch = text.split(":")
        return cls(int(n, 16), [int(steps[i : i + 16], 16) for i in range(0, len(steps), 16)], int(whole, 16), np.frombuffer(bytes.fromhex(sketch), ">u8").astype(np.uint64))

    def common_prefix(self, other: Fingerprint) -> int:
        """A length up to which both begin alike, by binary search; short of the true one by less than a step."""
        if self.n == other.n and self.whole == other.whole:
            return self.n
        a, b = stride(self.n), stride(other.n)
        s = max(a, b)
        low, high = 0, min(self.n, other.n) // s
        while low < high:
            mid = (low + high + 1) // 2
            low, high = (mid, high) if self.steps[mid * s // a - 1] == other.steps[mid * s // b - 1] else (low, mid - 1)
        return low * s

    def likeness(self, other: Fingerprint) -> float:
        if self.n == other.n and self.whole == other.whole:
            return 1.0
        if not self.n or not other.n:
            return 0.0
        prefix = 2 * self.common_prefix(other) / (self.n + other.n)
        both = np.union1d(self.sketch, other.sketch)[:SKETCH]
        shared = np.isin(both, self.sketch, assume_unique=True) & np.isin(both, other.sketch, assume_unique=True)
        j = shared.sum() / len(both)
        return float(min(max(prefix, 2 * j / (1 + j)), 1.0))


class Hashed:
    """A text with its prefix hashes and the mixed hashes of its spans."""

    def __init__(self, text: str):
        self.text = text
        self.made: Fingerprint | None = None
        self.hashes = PrefixHashes(text)
        self.n = self.hashes.n
        self.spans = mixed(self.hashes.spans(0, self.n - SPAN + 1, SPAN)) if self.n >= SPAN else mixed(np.array([self.hashes.span(0, self.n)] if self.n else [], np.int64))

    def fingerprint(self) -> Fingerprint:
        if self.made is None:
            s = stride(self.n)
            self.made = Fingerprint(self.n, [self.hashes.span(0, k) for k in range(s, self.n + 1, s)], self.hashes.span(0, self.n), least(self.spans))
        return self.made

    def edited(self, other: Hashed) -> tuple[str, Fingerprint]:
        """This text with its last half replaced by the beginning of the other, and its fingerprint, composed from the two
        prefix arrays; only the spans across the seam are hashed anew."""
        cut = self.n - self.n // 2
        take = min(self.n // 2, other.n)
        text = self.text[:cut] + other.text[:take]
        n = cut + take
        if n < 2 * SPAN:
            return text, Hashed(text).fingerprint()

        def prefix(k: int) -> int:
            if k <= cut:
                return self.hashes.span(0, k)
            out = 0
            for base, a, b in zip(BASES, self.hashes.prefix, other.hashes.prefix, strict=True):
                out = out << 31 | (int(a[cut]) + int(b[k - cut]) * pow(base, cut, M)) % M
            return out

        low, high = max(cut - SPAN + 1, 0), min(cut + SPAN - 1, n)
        seam = Hashed(text[low:high]).spans if high - low >= SPAN else np.zeros(0, np.uint64)
        own = self.spans[: max(cut - SPAN + 1, 0)] if self.n >= SPAN else seam[:0]
        new = other.spans[: max(take - SPAN + 1, 0)] if other.n >= SPAN else seam[:0]
        s = stride(n)
        return text, Fingerprint(n, [prefix(k) for k in range(s, n + 1, s)], prefix(n), least(np.concatenate((own, seam, new))))


COARSE = 128


def range_number(docs: DataFrame, key, mark, range_bytes: int):
    """A number that never falls as (key, mark) grows and puts about range_bytes of text under each value: the place among
    COARSE quantiles of the key, then even steps between two of them. A key that several quantiles meet has as many times
    the steps to itself, by its 64-bit marks, so that the rows of one id (or of none) are split too. 2**21 ranges at most."""
    got = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("bytes"), F.percentile_approx(key, [k / COARSE for k in range(COARSE + 1)], 20 * COARSE).alias("cuts")).first()
    met = Counter(got["cuts"] or [0])
    cuts = sorted(met)
    fine = min(max(1, got["bytes"] // range_bytes // COARSE), (1 << 20) // COARSE)
    own = [fine * met[c] if met[c] > 1 else 1 for c in cuts]
    # Each cut has its own ranges, then those up to the next cut.
    start = [0, *accumulate(n + fine for n in own)]
    numbers = lambda values: F.array(*[F.lit(v) for v in values])
    at = numbers(cuts)
    i = F.greatest(F.size(F.filter(at, lambda c: c <= key)), F.lit(1)) - 1
    low, high = F.get(at, i), F.coalesce(F.get(at, i + 1), F.get(at, i) + 1)
    first, mine = F.get(numbers(start), i), F.get(numbers(own), i)
    share = lambda x, n: F.least((F.least(F.greatest(x, F.lit(0.0)), F.lit(1.0)) * n).cast("int"), n - 1)
    within = share(mark.cast("double") / 2.0**64 + 0.5, mine)
    between = mine + share((key.cast("double") - low) / (high.cast("double") - low), F.lit(fine))
    return (first + F.when(key < low, 0).when(key == low, within).otherwise(between)).cast("int")


RESULT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def chained_fingerprints(docs: DataFrame, *, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """One row for each row of docs: its fingerprint, that of its edited text (see Hashed.edited; the other text is the
    next in ascending id, after the last the first) and how alike they are to the text's own.

    Texts move once: to ranges of ids, in which they are read in order. The first text of a range also goes to the range
    before it (that of the first range to the last), as what follows its last. The firsts are broadcast: 32 bytes for each
    of at most 2**21 ranges. Only rows equal in id and text are never split."""
    key = F.coalesce(F.col("doc_id").cast("long"), F.lit(LOWEST))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), key.alias("k"), F.coalesce("text", F.lit("")).alias("text"))
    docs = docs.withColumn("m", F.xxhash64("text"))
    docs = docs.withColumn("r", range_number(docs, F.col("k"), F.col("m"), range_bytes))
    heads = docs.groupBy("r").agg(F.min(F.struct("k", "m")).alias("head"))
    heads = heads.select("head", F.coalesce(F.lag("r").over(W.orderBy("r")), F.max("r").over(W.partitionBy())).alias("back"))
    both = docs.join(F.broadcast(heads), (docs["k"] == heads["head.k"]) & (docs["m"] == heads["head.m"]), "left")
    own, copy = F.struct(F.lit(0).alias("follows"), F.col("r").alias("r")), F.struct(F.lit(1).alias("follows"), F.col("back").alias("r"))
    placed = both.select("doc_id", "k", "m", "text", F.explode(F.when(F.col("back").isNull(), F.array(own)).otherwise(F.array(own, copy))).alias("to"))
    ordered = placed.select("text", "doc_id", "k", "m", "to.follows", "to.r").repartition("r").sortWithinPartitions("r", "follows", "k", "m", "text")

    def run(batches):
        last_range, held, held_id = None, None, None
        for batch in batches:
            for part in slices(batch):
                out = []
                for text, doc_id, follows, r in zip(part.column("text").to_pylist(), part.column("doc_id").to_pylist(), part.column("follows").to_pylist(), part.column("r").to_pylist(), strict=True):
                    if r != last_range:
                        last_range, held = r, None
                    elif held is None:
                        continue  # further copies of what follows
                    now = Hashed(text)
                    if held is not None:
                        edited, print_edited = held.edited(now)
                        own, after = held.fingerprint(), now.fingerprint()
                        out.append((held_id, held.n, hashlib.sha256(edited.encode("utf-8", "surrogatepass")).hexdigest(), str(own), str(print_edited), own.likeness(print_edited), own.likeness(after)))
                    held, held_id = (None, None) if follows else (now, doc_id)
                if out:
                    columns = list(zip(*out, strict=True))
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()), strict=True)], names=[f.split()[0] for f in RESULT.split(", ")])

    return ordered.mapInArrow(run, RESULT)
