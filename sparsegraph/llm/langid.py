"""Language identification in two steps: the language family first, then the languages within it, each step by
one-versus-one linear support vector machines on hashed byte trigrams.

Null texts and texts without a letter are `und` with score 0. Rows whose language is null are not learned from. With one
family, or one language in a family, that step has no choice to make. Without rows to learn from, every text is `und`.
Ties in votes go to the larger sum of margins, then to the first name. Repeated rows are predicted each for itself, and learned
from once."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows, sample_rows, schema_of, texts_of

#: Bound of the labelled rows that a fit reads.
FIT_ROWS = 4_000
BITS = 12
EPOCHS = 25

# Language families of ISO 639-1 codes. A code that is not listed is a family of its own kind, "other".
FAMILIES = {
    "germanic": ["af", "da", "de", "en", "fo", "is", "lb", "nb", "nl", "nn", "no", "sv"],
    "romance": ["ca", "es", "fr", "gl", "it", "oc", "pt", "ro"],
    "slavic": ["be", "bg", "bs", "cs", "hr", "mk", "pl", "ru", "sk", "sl", "sr", "uk"],
    "turkic": ["az", "kk", "ky", "tr", "tt", "uz"],
    "uralic": ["et", "fi", "hu"],
    "indo-aryan": ["bn", "gu", "hi", "mr", "ne", "pa", "ur"],
}


def family_of(lang: str) -> str:
    code = lang.lower().split("-")[0]
    return next((name for name, codes in FAMILIES.items() if code in codes), "other")


def fold_table() -> bytes:
    """For bytes.translate: A-Z to a-z; all other ASCII but letters becomes a space."""
    return bytes(b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def trigrams(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hashed trigram of each byte position of all texts, each between spaces; where each text's trigrams begin."""
    raw = b"".join(b" " + t + b" \0" for t in texts)
    buf = np.frombuffer(raw.translate(fold_table()), np.uint8).astype(np.uint32)
    begin = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) + 3 for t in texts], out=begin[1:])
    code = np.zeros(len(buf), np.uint32)
    code[:-2] = (buf[:-2] << 16) | (buf[1:-1] << 8) | buf[2:]
    with np.errstate(over="ignore"):
        return (code * np.uint32(2654435761)) >> np.uint32(32 - BITS), begin


@dataclass
class Machine:
    """Positive margins speak for `yes`."""

    yes: str
    no: str
    weights: np.ndarray
    bias: float


@dataclass
class LanguageModel:
    families: dict[str, list[str]] = field(default_factory=dict)
    between: list[Machine] = field(default_factory=list)
    within: dict[str, list[Machine]] = field(default_factory=dict)


def train_machine(x: np.ndarray, y: np.ndarray, epochs: int = EPOCHS, cost: float = 10.0, seed: int = 7) -> tuple[np.ndarray, float]:
    """L2-regularised squared-hinge machine by dual coordinate descent; classes weigh the same."""
    n, d = x.shape
    order = np.random.default_rng(seed)
    share = np.where(y > 0, (y > 0).mean(), (y < 0).mean())
    c = cost * 0.5 / np.maximum(share, 1e-9)
    w, b, alpha = np.zeros(d), 0.0, np.zeros(n)
    q = np.einsum("ij,ij->i", x, x) + 1 + 1 / (2 * c)
    for _ in range(epochs):
        for i in order.permutation(n):
            g = y[i] * (w @ x[i] + b) - 1 + alpha[i] / (2 * c[i])
            a = max(alpha[i] - g / q[i], 0.0)
            if a != alpha[i]:
                w += (a - alpha[i]) * y[i] * x[i]
                b += (a - alpha[i]) * y[i]
                alpha[i] = a
    return w, float(b)


SCALE = 30.0


def features(texts: list[bytes]) -> np.ndarray:
    """Shares of the hashed trigrams, times SCALE."""
    codes, begin = trigrams(texts)
    out = np.zeros((len(texts), 1 << BITS), np.float32)
    for k in range(len(texts)):
        c = np.bincount(codes[begin[k] : begin[k + 1] - 2], minlength=1 << BITS)
        out[k] = c * (SCALE / max(c.sum(), 1))
    return out


def fit(docs: DataFrame, *, fit_rows: int = FIT_ROWS) -> LanguageModel:
    """Learns from (text, lang) of at most fit_rows documents, those whose ids hash lowest (see sample_rows)."""

    def vectors(batch: pa.RecordBatch) -> pa.RecordBatch:
        x = features(texts_of(batch.column("text")))
        at = [np.flatnonzero(r) for r in x]
        return pa.RecordBatch.from_pydict({"lang": batch.column("lang"), "at": pa.array([a.astype(np.int16) for a in at], pa.list_(pa.int16())), "share": pa.array([r[a] for r, a in zip(x, at, strict=True)], pa.list_(pa.float32()))})

    rows = sample_rows(docs.where("doc_id is not null and lang is not null and text <> ''").select("doc_id", "text", "lang"), None, ["lang"], fit_rows)
    got = map_rows(rows.select("text", "lang"), vectors, "lang string, at array<smallint>, share array<float>").toArrow()  # at most fit_rows sparse rows
    langs = np.array(got.column("lang").to_pylist(), object)
    x = np.zeros((len(langs), 1 << BITS), np.float32)
    for k, (at, share) in enumerate(zip(got.column("at"), got.column("share"), strict=True)):
        x[k, np.asarray(at.values)] = np.asarray(share.values)
    model = LanguageModel()
    for lang in sorted(set(langs)):
        model.families.setdefault(family_of(lang), []).append(lang)
    family = np.array([family_of(v) for v in langs], object)
    machines = lambda names, label: [Machine(a, b, *train_machine(x[pick := (label == a) | (label == b)], np.where(label[pick] == a, 1.0, -1.0))) for a, b in combinations(names, 2)]
    model.between = machines(sorted(model.families), family)
    model.within = {f: machines(names, langs) for f, names in model.families.items()}
    return model


def decide(names: list[str], machines: list[Machine], margins: list[float]) -> tuple[str, float]:
    """The name with most votes, and how sure its closest contest was (0 to 1)."""
    votes = dict.fromkeys(names, 0)
    sums = dict.fromkeys(names, 0.0)
    for m, v in zip(machines, margins, strict=True):
        votes[m.yes if v > 0 else m.no] += 1
        sums[m.yes] += v
        sums[m.no] -= v
    best = max(sorted(names), key=lambda n: (votes[n], sums[n]))
    least = min((v if m.yes == best else -v for m, v in zip(machines, margins, strict=True) if best in (m.yes, m.no)), default=math.inf)
    return best, 1 / (1 + math.exp(-max(min(2 * least, 50), -50)))


def predict(docs: DataFrame, model: LanguageModel, *, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """docs (or its columns `keep`) plus lang_pred and lang_score. Columns of these names in docs give way."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    docs = docs.drop("lang_pred", "lang_score")
    kept = keep or docs.columns

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        model = shared.value
        texts = texts_of(batch.column(text_col))
        codes, begin = trigrams(texts)
        count = np.maximum(np.diff(begin) - 2, 1)
        every = [*model.between, *(m for f in model.within.values() for m in f)]
        margin = {}
        for m in every:
            at = m.weights[codes]
            at[begin[1:] - 1] = 0
            at[begin[1:] - 2] = 0
            margin[id(m)] = np.add.reduceat(at, begin[:-1]) * (SCALE / count) + m.bias
        names, scores = [], []
        for k, t in enumerate(texts):
            if not model.families or not any(c.isalpha() for c in t.decode("utf-8", "replace")):
                names.append("und")
                scores.append(0.0)
                continue
            family, sure = decide(sorted(model.families), model.between, [float(margin[id(m)][k]) for m in model.between])
            lang, more = decide(model.families[family], model.within[family], [float(margin[id(m)][k]) for m in model.within[family]])
            names.append(lang)
            scores.append(sure * more)
        return pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=[*kept, "lang_pred", "lang_score"])

    return map_rows(docs, run, schema_of(docs.select(*kept), "lang_pred string", "lang_score double"))
