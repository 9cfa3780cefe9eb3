import hashlib
import itertools
import random
import re
import textwrap
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from sparsegraph.llm import bytewords, decontaminate, langid, licenses, linededup, pieces, polyhash, queries, sharding, simhash, toxicity, warc

from .fixtures import DOCS, awkward, documents, empty

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
MODEL = queries.tokenizer("piece_bpe_32k.model")


@pytest.fixture(scope="module")
def docs(spark):
    return documents(spark).cache()


@pytest.fixture(scope="module")
def folder(spark, docs, tmp_path_factory):
    """The small tables as a folder that the registered queries read."""
    d = tmp_path_factory.mktemp("small")
    docs.write.parquet(f"{d}/documents.parquet")
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    spark.createDataFrame([(0, " ".join(text[7].split()[-15:-1])), (1, "ab"), (2, None), (3, ""), (11, text[3])], "item_id bigint, text string").write.parquet(f"{d}/benchmark.parquet")
    spark.createDataFrame([(i, i % 2, int(i % 5 == 0)) for i in range(60)], "doc_id bigint, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
    pages = [(i, f"http://h/{i}", f"<p>{i}</p>" * (10 * i)) for i in range(40)] + [(100, None, None), (101, "u", "<b>" * 500), (102, "u", "<b>" * 500), (103, "v", "<b>" * 500), (104, "w", "short"), (105, "w", "short")]
    spark.createDataFrame(pages, "page_id bigint, url string, html string").write.parquet(f"{d}/pages.parquet")
    return str(d)


def collected(df, key="doc_id"):
    return {r[key]: r for r in df.collect()}


# --- op1 ---------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("dims,bits", [(2, 3), (3, 3), (4, 2)])
def test_hilbert_curve_is_a_walk(dims, bits):
    points = {sharding.hilbert_index(list(p), bits): p for p in itertools.product(range(1 << bits), repeat=dims)}
    assert sorted(points) == list(range(1 << bits * dims))
    path = [points[i] for i in range(len(points))]
    assert all(sum(abs(x - y) for x, y in zip(a, b, strict=True)) == 1 for a, b in itertools.pairwise(path))


def test_shards(spark, folder):
    rows = queries.op1_hilbert_shards(spark, folder).collect()
    text = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{folder}/documents.parquet").collect()}
    assert sorted(r["doc_id"] for r in rows) == sorted(text)
    count = Counter(r["shard"] for r in rows)
    assert set(count) == set(range(8)) and max(count.values()) - min(count.values()) <= 1
    for s in count:
        mine = sorted((r["slot"], r["curve"]) for r in rows if r["shard"] == s)
        assert [m[0] for m in mine] == list(range(len(mine))) and [m[1] for m in mine] == sorted(m[1] for m in mine)
    for r in rows:
        data = (text[r["doc_id"]] or "").encode()
        assert (r["size"], r["text_crc32"], r["grown_shard"]) == (len(data) + 1, zlib.crc32(data), None)


def test_shards_of_awkward_tables(spark, docs, tmp_path):
    odd = awkward(docs)
    placed = sharding.hilbert_shards(odd, ["lang", "n_chars"], shards=5)
    count = Counter(r["shard"] for r in placed.collect())
    assert sum(count.values()) == odd.count() and max(count.values()) - min(count.values()) <= 1
    assert sharding.hilbert_shards(empty(spark), ["lang", "source", "n_chars"]).count() == 0
    sharding.write_shards(docs, str(tmp_path / "out"), ["lang", "n_chars"], shards=3)
    assert spark.read.parquet(str(tmp_path / "out")).count() == docs.count()
    assert sharding.pruning(placed, ["lang"]).count() == 5


@pytest.mark.parametrize("kind", ["decimal(12,2)", "boolean", "double", "timestamp", "string"])
def test_one_dimension_follows_its_values(spark, kind):
    rows = spark.range(2000).select(F.col("id").alias("doc_id"), (F.col("id") % 2 if kind == "boolean" else F.lpad("id", 5, "0") if kind == "string" else F.col("id")).cast(kind).alias("v"))
    placed = sharding.hilbert_shards(rows, ["v"], shards=4)
    ends = [(r["min_v"], r["max_v"]) for r in sharding.pruning(placed, ["v"]).orderBy("shard").collect()]
    assert ends == sorted(ends) and [r["rows"] for r in sharding.pruning(placed, ["v"]).collect()] == [500] * 4
    if kind != "boolean":  # a cell holds 1/256 of the rows
        width = {int(r["doc_id"] / 500) - r["shard"] for r in placed.select("doc_id", "shard").collect()}
        assert width <= {-1, 0, 1}


def test_rows_of_one_id_keep_their_place(spark):
    rows = spark.createDataFrame([(1, f"t{k}", None) for k in range(50)], "doc_id bigint, text string, v int")
    place = lambda df: sorted((r["text"], r["shard"], r["slot"]) for r in sharding.hilbert_shards(df, ["v"], shards=3).collect())
    assert place(rows) == place(rows.orderBy(F.rand(3)).repartition(3))


def test_pruning_beats_arrival_order(spark):
    df = spark.range(4000).select(F.col("id").alias("doc_id"), F.pmod(F.xxhash64("id"), F.lit(97)).alias("a"), F.pmod(F.xxhash64(F.lit(1), "id"), F.lit(89)).alias("b"))
    stats = sharding.pruning(sharding.hilbert_shards(df, ["a", "b"], shards=16), ["a", "b"]).collect()
    read = sum(r["min_a"] <= 5 and r["max_a"] >= 0 for r in stats) + sum(r["min_b"] <= 5 and r["max_b"] >= 0 for r in stats)
    assert read <= 12  # of 32 shard reads that arrival order needs


# --- op2 ---------------------------------------------------------------------------------------------------------------


def test_span_hashes_and_extensions():
    a, b = polyhash.PrefixHashes("xxabcabcabcyé"), polyhash.PrefixHashes("abcabcz")
    assert a.span(2, 3) == a.span(5, 3) == b.span(0, 3) != a.span(3, 3)
    assert a.lce(2, b, 0) == 6 and a.lce(12, b, 6) == 0
    assert a.spans(2, 6, 3).tolist() == [a.span(i, 3) for i in range(2, 6)]
    long = "0123456789" * 40_000  # longer than a piece
    h = polyhash.PrefixHashes(long)
    assert h.span(0, 100_000) == h.span(200_000, 100_000) != h.span(200_001, 100_000)
    assert h.lce(0, h, 10) == len(long) - 10


def test_fingerprints(spark, folder):
    text = sorted((r["doc_id"], r["text"] or "") for r in spark.read.parquet(f"{folder}/documents.parquet").collect())
    got = collected(queries.op2_prefix_fingerprints(spark, folder))
    assert len(got) == len(text)
    for (i, t), (_, nxt) in zip(text, text[1:] + text[:1], strict=True):
        half = len(t) // 2
        edited = t[: len(t) - half] + nxt[:half]
        r = got[i]
        assert r["n_chars"] == len(t) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        own, new = polyhash.Hashed(t).fingerprint(), polyhash.Hashed(edited).fingerprint()
        assert r["fingerprint"] == str(own) and r["edited_fingerprint"] == str(new)
        assert r["near_edited"] == polyhash.Fingerprint.parse(str(own)).likeness(polyhash.Fingerprint.parse(str(new)))
        assert 0 <= r["near_next"] <= 1
    assert got[5]["fingerprint"] == got[104]["fingerprint"] == got[105]["fingerprint"]
    assert np.mean([r["near_edited"] for i, r in got.items() if r["n_chars"] > 100]) > 0.4
    assert np.mean([r["near_next"] for i, r in got.items() if r["n_chars"] > 100 and i < 100]) < 0.2


def plain_fingerprint(text):
    """The fingerprint by its definition, in whole numbers, one power and one span at a time."""
    m, wide = 2**31 - 1, 2**64

    def span(at, width):
        out = 0
        for b in polyhash.BASES:
            h = 0
            for c in reversed(text[at : at + width]):
                h = (h * b + ord(c) + 1) % m
            out = out << 31 | h
        return out

    def mix(x):
        x ^= x >> 30
        x = x * 0xBF58476D1CE4E5B9 % wide
        x ^= x >> 27
        x = x * 0x94D049BB133111EB % wide
        return x ^ x >> 31

    n, step = len(text), 1
    while n // step > 32:
        step *= 2
    width = min(n, 16)
    sketch = sorted({mix(span(i, width)) for i in range(n - width + 1)} if n else ())[:64]
    whole = span(0, n)
    return n, step, sketch, f"{n:x}:{whole:016x}:{''.join(f'{span(0, k):016x}' for k in range(step, n + 1, step))}:{''.join(f'{x:016x}' for x in sketch)}"


def plain_likeness(s, t):
    if s == t:
        return 1.0
    if not s or not t:
        return 0.0
    (n, a, x, _), (k, b, y, _) = plain_fingerprint(s), plain_fingerprint(t)
    step = max(a, b)
    same = max(j for j in range(0, min(n, k) + 1, step) if s[:j] == t[:j])
    both = sorted({*x, *y})[:64]
    j = sum(v in x and v in y for v in both) / len(both)
    return max(2 * same / (n + k), 2 * j / (1 + j))


def test_fingerprints_against_their_definition(spark):
    base = "the quick brown fox jumps over the lazy dog, twice: été 𝄞 "
    text = ["", "a", "ab", base[:15], base[:16], base[:17], base * 3, base * 3 + "tail", base[::-1] * 2, "z" * 400, base * 9]
    docs = spark.createDataFrame(list(enumerate(text)), "doc_id bigint, text string")
    got = {r["doc_id"]: r for r in polyhash.chained_fingerprints(docs, range_bytes=100).collect()}
    for i, t in enumerate(text):
        nxt = text[(i + 1) % len(text)]
        edited = t[: len(t) - len(t) // 2] + nxt[: len(t) // 2]
        r = got[i]
        assert r["fingerprint"] == plain_fingerprint(t)[3] and r["edited_fingerprint"] == plain_fingerprint(edited)[3]
        assert r["near_edited"] == pytest.approx(plain_likeness(t, edited)) and r["near_next"] == pytest.approx(plain_likeness(t, nxt))


@pytest.mark.parametrize("hot", [7, None])
def test_rows_of_one_id_are_split(spark, hot):
    rows = [(hot if i % 2 else i, f"text number {i} " * 5) for i in range(3000)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    got, whole = (sorted(map(str, polyhash.chained_fingerprints(docs, range_bytes=b).collect())) for b in (400, 1 << 30))
    assert got == whole and len(got) == 3000
    key, mark = F.coalesce("doc_id", F.lit(polyhash.LOWEST)), F.xxhash64("text")
    placed = docs.select(key.alias("k"), mark.alias("m"), polyhash.range_number(docs, key, mark, 400).alias("r")).orderBy("k", "m").collect()
    assert [p["r"] for p in placed] == sorted(p["r"] for p in placed)  # never falls
    lot = Counter(p["r"] for p in placed if p["k"] == (polyhash.LOWEST if hot is None else hot))
    assert len(lot) > 50 and max(lot.values()) < 150


def test_fingerprints_of_few_rows(spark):
    one = spark.createDataFrame([(7, "abcd", None, None, 4)], DOCS)
    assert polyhash.chained_fingerprints(one).first()["edited_sha256"] == hashlib.sha256(b"abab").hexdigest()
    assert polyhash.chained_fingerprints(empty(spark)).count() == 0
    odd = spark.createDataFrame([(1, "a"), (1, "a"), (None, "b"), (None, None)], "doc_id bigint, text string")
    assert polyhash.chained_fingerprints(awkward(odd), range_bytes=1).count() == 8
    many = spark.range(3000).select(F.col("id").alias("doc_id"), F.repeat(F.col("id").cast("string"), 20).alias("text"))
    a = collected(polyhash.chained_fingerprints(many, range_bytes=300))
    b = collected(polyhash.chained_fingerprints(many, range_bytes=1 << 30))
    assert a == b and len(a) == 3000


# --- op3 ---------------------------------------------------------------------------------------------------------------


def brute_segments(scores):
    """Maximal scoring segments by definition: repeatedly the best segment, then both sides of it."""
    out = []

    def go(a, b):
        best = max(((sum(scores[i:j]), -(j - i), -i) for i in range(a, b) for j in range(i + 1, b + 1)), default=(0,))
        if best[0] <= 1e-12:
            return
        i, n = -best[2], -best[1]
        go(a, i)
        out.append((i, i + n - 1, round(best[0], 9)))
        go(i + n, b)

    go(0, len(scores))
    return out


def test_segments_against_definition():
    rng = np.random.default_rng(5)
    for _ in range(60):
        n = int(rng.integers(1, 25))
        at = sorted(rng.choice(n, int(rng.integers(0, n + 1)), replace=False).tolist())
        vals = [float(x) for x in rng.integers(-4, 7, len(at)) + rng.random(len(at))]
        drift = -0.35
        full = [drift] * n
        for i, v in zip(at, vals, strict=True):
            full[i] = v
        got = [(a, b, round(s, 9)) for a, b, s in toxicity.segments(vals, at, drift)]
        assert got == brute_segments(full)


def test_toxicity_learns_and_holds_out(spark):
    rng = np.random.default_rng(1)
    plain = [f"w{i}" for i in range(200)]
    rows, labels = [], []
    for i in range(400):
        t = list(rng.choice(plain, 60))
        if i % 5 == 0:
            for p in rng.choice(60, 4, replace=False):
                t[p] = ["Vile", "nasty", "vileness"][int(rng.integers(3))]
        rows.append((i, " ".join(t)))
        labels.append((i, int(i % 5 == 0)))
    docs = spark.createDataFrame([*rows, (900, None), (901, "")], "doc_id bigint, text string")
    lab = spark.createDataFrame([*labels, (902, None)], "doc_id bigint, toxic int")
    model = toxicity.fit(docs, lab.where("doc_id % 3 <> 1"))
    assert model.words[b"vile"] > 0 and model.drift < 0
    got = {r["doc_id"]: r for r in toxicity.score(awkward(docs), model).collect()}
    held = [i for i in range(400) if i % 3 == 1]
    assert np.mean([(got[i]["toxicity"] >= 0.7) == (i % 5 == 0) for i in held]) > 0.97
    assert got[900]["toxicity"] == got[901]["toxicity"] < 0.5
    seg = got[0]["toxic_segments"][0]
    assert re.search("vile|nasty", dict(rows)[0][seg["start"] : seg["end"]].lower())


def test_toxicity_without_labels(spark, docs):
    none = spark.createDataFrame([], "doc_id bigint, toxic int")
    model = toxicity.fit(docs, none)
    assert {r["toxicity"] for r in toxicity.score(docs, model).collect()} == {0.5}
    assert toxicity.score(empty(spark), model).count() == 0


def test_toxicity_query(spark, folder):
    rows = queries.op3_toxic_segments(spark, folder).collect()
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.7) for r in rows)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in rows)


# --- op4 ---------------------------------------------------------------------------------------------------------------


def test_warc(spark, folder):
    html = {r["page_id"]: r["html"] or "" for r in spark.read.parquet(f"{folder}/pages.parquet").collect()}
    last = {}
    for i, h in html.items():
        last[h] = max(i, last.get(h, i))
    got = collected(queries.op4_warc(spark, folder), "page_id")
    assert set(got) == set(html)
    for i, h in html.items():
        again = len(h.encode()) >= 1000 and last[h] != i
        assert (got[i]["payload_bytes"], got[i]["payload_digest"]) == (len(h.encode()), hashlib.sha1(h.encode()).hexdigest())
        assert (got[i]["record_type"], got[i]["refers_to"]) == (("revisit", last[h]) if again else ("response", None))


@pytest.mark.parametrize("split", [700, 4096, 1 << 20])
def test_warc_splits_own_every_record_once(spark, tmp_path, split):
    rows = [(i, f"u{i}", "x" * (i * 37 % 5000) + chr(0x1F) + "é") for i in range(200)] + [(None, None, None)]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string").repartition(3)
    out, files = warc.archive(pages, str(tmp_path / "warc"))
    assert files.count() >= 1
    got = sorted((r["page_id"] if r["page_id"] is not None else -1, bytes(r["payload"])) for r in warc.read(spark, out, split_bytes=split).collect() if r["record_type"] == "response")
    assert got == sorted((-1 if i is None else i, (h or "").encode()) for i, _, h in rows)


def test_warc_ignores_false_magic(spark, tmp_path):
    """Gzip magic inside stored payload bytes is no record: candidates must decode to a WARC header."""
    fake = bytes([0x1F, 0x8B, 8, 0]) * 50
    inner = warc.member(warc.record(1, "u", b"a", None))
    data = fake + inner + b"\x1f\x8b\x08junk" + warc.member(b"no header here") + warc.member(warc.record(2, "u", b"b", None))
    (tmp_path / "x.warc.gz").write_bytes(data)
    for split in (50, 1000):
        assert sorted(r["page_id"] for r in warc.read(spark, str(tmp_path), split_bytes=split).collect()) == [1, 2]


def test_warc_empty(spark, tmp_path):
    out, _ = warc.archive(spark.createDataFrame([], "page_id bigint, url string, html string"), str(tmp_path / "none"))
    assert warc.read(spark, out).count() == 0


# --- op5 ---------------------------------------------------------------------------------------------------------------


def test_pieces_equal_the_library(spark, folder):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=MODEL)
    got = collected(queries.op5_pieces(spark, folder))
    for r in spark.read.parquet(f"{folder}/documents.parquet").collect():
        ids = sp.encode(r["text"] or "", add_bos=True, add_eos=True)
        want = (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(sp.decode(ids).encode()).hexdigest())
        assert (got[r["doc_id"]]["n_tokens"], got[r["doc_id"]]["ids_sha256"], got[r["doc_id"]]["decoded_sha256"]) == want


def test_piece_spans_tile_the_text(spark, docs):
    for r in pieces.encode(awkward(docs), MODEL).collect():
        raw = (r["text"] or "").encode()
        start, end = r["piece_start"], r["piece_end"]
        assert len(r["ids"]) == len(start) == len(end) and start[0] == end[0] == 0
        assert all(a <= b for a, b in zip(start, end, strict=True)) and sorted(start) == start
        covered = b"".join(raw[a:b] for a, b in zip(start, end, strict=True))
        assert covered == raw
    assert pieces.encode(empty(spark), MODEL).count() == 0


def test_spans_match_the_library_offsets():
    model = pieces.PieceModel(pieces.load(MODEL))
    for text in ["Hello  world", " a é日本 𝄞x", "tab\tnew\nline", "ß" * 5, "x"]:
        proto = model.library.encode(text, return_type="proto")
        (ids,), (aligned,) = model.encode([text])
        assert ids[1:-1] == [p.id for p in proto.pieces]
        start, end = model.spans(len(text.encode()), ids, aligned)
        for p, a, b in zip(proto.pieces, start[1:-1], end[1:-1], strict=True):
            if b > a and not p.piece.startswith("<0x"):
                assert (a, b) == (p.begin, p.end)


def test_character_map_longest_prefix():
    """A hand-made double array with the keys "a" -> "b" and "ab" -> "cc"."""
    units = [0] * 1024
    leaf = lambda v: v | 0x80000000
    off = lambda o: o << 10
    units[0] = off(256)
    units[256 ^ 97] = 97 | off((256 ^ 97) ^ 512) | 1 << 8  # node "a" with a value
    units[512] = leaf(0)
    units[512 ^ 98] = 98 | off((512 ^ 98) ^ 768) | 1 << 8  # node "ab"
    units[768] = leaf(2)
    blob = (len(units) * 4).to_bytes(4, "little") + b"".join(u.to_bytes(4, "little") for u in units) + b"b\0cc\0"
    m = pieces.CharacterMap(blob)
    assert m.longest(b"abx", 0) == (2, b"cc") and m.longest(b"ax", 0) == (1, b"b") and m.longest(b"x", 0) is None

    class Spec:
        precompiled_charsmap, add_dummy_prefix, remove_extra_whitespaces, escape_whitespaces = blob, True, True, True

    out, start, end = pieces.Normaliser(Spec).align(b"  ab  a ")
    assert out.decode() == "▁cc▁b" and start.tolist() == [2, 2, 2, 2, 2, 4, 4, 4, 6] and end.tolist() == [2, 2, 2, 4, 4, 5, 5, 5, 7]


# --- op6 ---------------------------------------------------------------------------------------------------------------


def test_language(spark):
    rng = np.random.default_rng(2)
    bits = {"en": ["th", "ing", "the", "ow"], "de": ["sch", "ein", "ung", "ü"], "fr": ["eau", "oi", "é", "qu"], "es": ["ción", "ñ", "os", "ll"]}
    rows = [(i, " ".join("".join(rng.choice(b, 3)) for _ in range(12)), lang) for i, lang, b in ((4 * k + j, lang, b) for k in range(60) for j, (lang, b) in enumerate(bits.items()))]
    docs = spark.createDataFrame([*rows, (900, None, "en"), (901, "12 !? ²", None), (902, "", "de")], "doc_id bigint, text string, lang string")
    model = langid.fit(docs.where("doc_id % 5 <> 2"))
    assert {f: sorted(v) for f, v in model.families.items()} == {"germanic": ["de", "en"], "romance": ["es", "fr"]}
    got = {r["doc_id"]: r for r in langid.predict(awkward(docs), model).collect()}
    assert np.mean([got[i]["lang_pred"] == lang for i, _, lang in rows if i % 5 == 2]) > 0.97
    assert [got[i]["lang_pred"] for i in (900, 901, 902)] == ["und"] * 3
    assert all(0 <= r["lang_score"] <= 1 for r in got.values())


def test_language_query_holds_out(spark):
    d = "/root/testdata/sf0.01"
    truth = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "lang").collect()}
    got = queries.op6_language(spark, d).collect()
    assert {r["doc_id"] for r in got} == set(truth)
    held = [r for r in got if r["held_out"]]
    assert all((zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) == r["held_out"] for r in got)
    right = [truth[r["doc_id"]] == r["lang_pred"] for r in held if r["lang_pred"] != "und" and truth[r["doc_id"]]]
    assert len(right) > 200 and sum(right) >= 0.98 * len(right)
    assert all(0 <= r["score"] <= 1 for r in got)


def test_fits_read_no_more_rows_than_their_bound(spark):
    from sparsegraph.llm.common import sample_rows

    many = spark.createDataFrame([(7, f"text number {k}", "en") for k in range(400)] + [(k, "same", "fr") for k in (1, 1, 1, 2)], "doc_id bigint, text string, lang string")
    assert sample_rows(many, None, ["lang"], 50).count() == 50
    assert sample_rows(many.where("doc_id <> 7"), None, ["lang"], 50).count() == 2
    known = spark.createDataFrame([(7, 1), (1, 0), (7, 1)], "doc_id bigint, toxic int")
    assert sample_rows(many.drop("lang"), known, ["toxic"], 50).count() == 50
    first = [sorted(map(tuple, sample_rows(many.orderBy(F.rand(k)), None, ["lang"], 50).collect())) for k in (1, 2)]
    assert first[0] == first[1]


def test_language_without_choice(spark, docs):
    assert {r["lang_pred"] for r in langid.predict(docs, langid.LanguageModel()).collect()} == {"und"}
    one = langid.fit(docs.where("lang = 'en'"))
    assert {r["lang_pred"] for r in langid.predict(docs, one).collect()} == {"en", "und"}
    assert langid.predict(empty(spark), one).count() == 0


# --- op7 ---------------------------------------------------------------------------------------------------------------


def brute_print(text, size):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    s = [" ".join(w[i : i + size]) for i in range(max(1, len(w) - size + 1))] if w else []
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def brute_components(prints, distance):
    parent = {i: i for i in prints}

    def find(i):
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    for a, b in itertools.combinations(prints, 2):
        if (prints[a] ^ prints[b]).bit_count() <= distance:
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    return {i: find(i) for i in prints}


def test_simhash_query(spark, folder):
    text = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{folder}/documents.parquet").collect()}
    prints = {i: brute_print(t, 3) for i, t in text.items()}
    comp = brute_components(prints, 2)
    got = collected(queries.op7_simhash(spark, folder))
    assert {i: (r["fingerprint"], r["component_id"]) for i, r in got.items()} == {i: (f"{prints[i]:016x}", comp[i]) for i in text}


@pytest.mark.parametrize("distance,bucket", [(2, 4), (2, 32), (1, 4), (0, 4)])
def test_links_by_blocks_and_by_middles(spark, monkeypatch, distance, bucket):
    monkeypatch.setattr(simhash, "BUCKET", bucket)
    rng = np.random.default_rng(distance)
    base = [int(x) for x in rng.integers(0, 1 << 63, 6)]
    prints = set(base)
    for b in base:  # dense neighbourhoods, and chains
        for _ in range(40):
            x = b
            for j in rng.choice(64, int(rng.integers(1, 5)), replace=False):
                x ^= 1 << int(j)
            prints.add(x)
    prints = dict(enumerate(sorted(prints)))
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    df = spark.createDataFrame([(signed(p), i) for i, p in prints.items()], "fp bigint, rep bigint")
    from sparsegraph.operators.components import components

    got = {r["id"]: r["component"] for r in components(simhash.links(df, distance)).collect()}
    assert {i: got.get(i, i) for i in prints} == brute_components(prints, distance)


def test_simhash_odd_rows(spark, docs):
    odd = spark.createDataFrame([(None, "a b c d"), (3, "a b c d"), (3, "a b c d"), (None, "only me here now"), (5, None), (4, "")], "doc_id bigint, text string")
    got = [(r["doc_id"], r["component_id"]) for r in simhash.near_duplicates(awkward(odd)).collect()]
    assert Counter(got) == Counter({(None, 3): 2, (3, 3): 4, (None, None): 2, (5, 4): 2, (4, 4): 2})
    assert simhash.near_duplicates(empty(spark)).count() == 0


# --- op8 ---------------------------------------------------------------------------------------------------------------


def brute_lines(rows, min_chars=20, min_docs=3):
    """rows: (doc_id, text); documents are rows."""
    key = lambda x: x.strip(" \t\n\x0b\x0c\r").translate(LOWER)
    held = {}
    for n, (i, t) in enumerate(rows):
        for x in (t or "").split("\n"):
            if len(key(x)) >= min_chars:
                held.setdefault(key(x), set()).add((i, n))
    out = []
    for i, t in rows:
        lines = (t or "").split("\n")
        gone = [len(held.get(key(x), ())) >= min_docs and max(held[key(x)])[0] != i for x in lines]
        out.append((i, len(lines), sum(gone), hashlib.sha256("\n".join(x for x, g in zip(lines, gone, strict=True) if not g).encode()).hexdigest()))
    return sorted(out)


def test_lines(spark, folder):
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{folder}/documents.parquet").collect()]
    got = sorted((r["doc_id"], r["n_lines"], r["n_dropped"], r["kept_sha256"]) for r in queries.op8_line_dedup(spark, folder).collect())
    assert got == brute_lines(rows) and sum(r[2] for r in got) > 5


def test_lines_odd_rows_and_bitmaps(spark):
    a, b = "A line of twenty chars or more É", "another one of those long lines é"
    rows = [(1, f"{a}\n{b}\n{a.upper()}"), (1, f"{a}\n{b}\n{a.upper()}"), (2, f" {a.lower()}\t\nx"), (3, f"{b}\n{b}\n\n{a}"), (4, None), (5, "")]
    rows[2] = (2, f" {a.lower().replace('é', 'É')}\t\nx")
    df = spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("n_chars", F.lit(1).cast("bigint"))
    kept = linededup.dedup_lines(awkward(df.select("doc_id", "text", "n_chars")))
    assert kept.count() == 12
    maps = {r["doc_id"]: r for r in linededup.keep_bitmaps(df).collect()}
    assert maps[3]["bitmap"] == "" and maps[4]["n_lines"] == 1
    assert maps[2]["n_dropped"] == 1 and maps[2]["bitmap"] == "0,1"
    assert linededup.dedup_lines(empty(spark)).count() == 0


def test_kept_text_of_all_run_patterns(spark):
    """Runs at the beginning, the end, everywhere and nowhere, against the brute force."""
    line = [f"repeated line number {i} of every text" for i in range(3)]
    rows = [(9, "\n".join(line)), (8, "\n".join(line))]
    rows += [(i, "\n".join(line[j] if i >> j & 1 else f"own {i} {j}" for j in range(3)) + ("\n" if i % 2 else "")) for i in range(8)]
    got = {(r["doc_id"], r["text"]) for r in linededup.dedup_lines(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    key = lambda t: hashlib.sha256(t.encode()).hexdigest()
    assert sorted((i, key(t)) for i, t in got) == sorted((r[0], r[3]) for r in brute_lines(rows))
    assert (8, "") in got


def test_lines_plan_is_native(spark, docs):
    plan = linededup.dedup_lines(docs)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


# --- op9 ---------------------------------------------------------------------------------------------------------------


def test_licenses(spark):
    rows = [
        (1, "Some text.\nReleased under the MIT License.\nmore"),
        (2, "licensed under the apache license, version 2.0."),
        (3, "This work is licensed under the GNU General Public Licence, version 3."),
        (4, "She had a driving license for years and years, and no other permission."),
        (5, None),
        (6, ""),
        (7, "Licensed under CC BY-NC 4.0."),
        (8, "Licensed under CC BY 4.0."),
        (9, "x\n" + licenses.TEMPLATES["MIT"][1].replace("free of charge", "for a fee")),
        (10, "Licensed under the Apache License, Version 2.0.\n\nReleased under the MIT License."),
    ]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = {r["doc_id"]: [x["license"] for x in r["licenses"]] for r in licenses.scan(awkward(df)).collect()}
    assert got == {1: ["MIT"], 2: ["Apache-2.0"], 3: ["GPL-3.0"], 4: [], 5: [], 6: [], 7: ["CC-BY-NC-4.0"], 8: ["CC-BY-4.0"], 9: ["MIT"], 10: ["Apache-2.0", "MIT"]}
    three = licenses.scan(df.where("doc_id = 3")).first()["licenses"][0]
    assert three["missing"] == 1 and three["added"] == 1 and set(three["differences"]) == {"-license", "+licence"}
    assert (rows[0][1].encode()[licenses.scan(df).first()["licenses"][0]["start"] :]).startswith(b"Released")
    assert licenses.by_document(empty(spark)).count() == 0


def test_licenses_do_not_depend_on_the_text_around(spark):
    short, long = "Released under the MIT License.", licenses.TEMPLATES["MIT"][1]
    prose = "The quick river of plain words runs on beneath a low grey sky and never says a thing. " * 800
    wrap = lambda s, mark="": "\n".join(mark + line for line in textwrap.wrap(s, 76))
    rows = [
        (1, f"{prose[:500]} {short} {prose[:500]}"),
        (2, wrap(f"{prose[:1500]} {long} {prose[:1500]}")),
        (3, wrap(long, " * ")),
        (4, f"{prose[:65520]} {short} {prose[:2000]}"),
        (5, f"{prose[:65000]} {long} {prose[:2000]}"),
        (6, f"{prose[:500]} {long.upper()}"),
        (7, wrap(f"{prose[:560]} {licenses.TEMPLATES['Unlicense'][0]}", "# ")),
    ]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    for r in licenses.scan(df).collect():
        assert [x["license"] for x in r["licenses"]] == ["Unlicense" if r["doc_id"] == 7 else "MIT"]
        x, text = r["licenses"][0], r["text"].encode()
        assert x["missing"] == x["added"] == 0 and x["differences"] == []
        want = {1: short, 4: short, 7: licenses.TEMPLATES["Unlicense"][0]}.get(r["doc_id"], long)
        assert licenses.words(text[x["start"] : x["end"]]) == licenses.words(want.encode())


def test_licenses_of_one_block_are_all_found(spark):
    mit, apache = "Released under the MIT License.", "Licensed under the Apache License, Version 2.0."
    long = licenses.TEMPLATES["Apache-2.0"][1]
    rows = [
        (1, f"{mit} {apache}", ["MIT", "Apache-2.0"]),
        (2, f"{mit} Some words. {mit} {apache} {mit}", ["MIT", "MIT", "Apache-2.0", "MIT"]),
        (3, f"{long} or {licenses.TEMPLATES['MIT'][1]}", ["Apache-2.0", "MIT"]),
        (4, licenses.TEMPLATES["CC-BY-SA-4.0"][1], ["CC-BY-SA-4.0"]),
        (5, long.replace("a copy", "some copy"), ["Apache-2.0"]),
        (6, long.replace("you may", f"{mit} you may"), ["Apache-2.0", "MIT"]),
        (7, " ".join([mit] * 200), ["MIT"] * 200),
    ]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, want array<string>")
    for r in licenses.scan(df).collect():
        assert [x["license"] for x in r["licenses"]] == r["want"]
    one = {r["doc_id"]: r for r in licenses.by_document(df).collect()}[2]
    assert (one["n_licenses"], one["licenses"], one["n_differences"]) == (4, "Apache-2.0,MIT", 0)
    spans = [r["text"].encode()[x["start"] : x["end"]].decode() for r in licenses.scan(df.where("doc_id = 1")).collect() for x in r["licenses"]]
    assert spans == ["Released under the MIT License", "Licensed under the Apache License, Version 2.0"]


def test_licenses_with_most_edits_are_candidates():
    """Saving does not drop what the wording would confirm: random edits, up to the allowed number, in random words."""
    scanner, rng = licenses.Scanner(licenses.TEMPLATES), random.Random(5)
    filler = lambda n: [bytes(rng.choices(b"abcdefghijklmnop", k=rng.randint(2, 9))) for _ in range(n)]
    for k, (name, want, *_) in enumerate(scanner.templates):
        for _ in range(40):
            own = list(want)
            for i in rng.sample(range(len(own)), int(0.15 * len(own))):
                own[i] = filler(1)[0]
            found = scanner.matches(k, filler(len(own) * 2) + own + filler(len(own) * 2), 0.25, 0.15)
            assert [f["license"] for f in found] == [name]


def test_licenses_need_no_hint_words():
    """Every notice with up to the allowed edits, wherever they fall, opens a window: in any text, also across the places
    where long texts are cut, and for templates without a word of license language."""
    rng = random.Random(9)
    filler = lambda n: [bytes(rng.choices(b"abcdefghijklmnop", k=rng.randint(2, 9))) for _ in range(n)]
    plain = {"plain": [b" ".join(filler(n)).decode() for n in (1, 2, 7, 13, 20, 41)]}
    scanner = licenses.Scanner(licenses.TEMPLATES | plain)
    for k, (name, want, *_) in enumerate(scanner.templates):
        for _ in range(25):
            own = list(want)
            for _ in range(scanner.most(k)):
                i = rng.randrange(len(own))
                match rng.randrange(3):
                    case 0:
                        own[i] = filler(1)[0]
                    case 1 if len(own) > 1:
                        del own[i]
                    case _:
                        own.insert(i, filler(1)[0])
            text = b"\n# ".join([*filler(60), *own, *filler(60)])
            hits = scanner.anchors(text)[k]
            reach = len(want) + scanner.most(k)
            assert any(h - reach <= 60 and 60 + len(own) <= h + reach + 1 for h in hits), (name, own)


def test_license_anchors_in_blocks(monkeypatch):
    scanner = licenses.Scanner(licenses.TEMPLATES)
    text = ("some words, e.g. v1.2-x .-. " * 40 + " ".join(t for ts in licenses.TEMPLATES.values() for t in ts) + " and more") * 3
    low = text.lower().encode()
    whole = scanner.anchors(low)
    assert len(whole) == len(scanner.templates)
    assert all(licenses.words(low)[h : h + 1] for hits in whole.values() for h in hits)
    for block in (1, 37, 500):
        monkeypatch.setattr(licenses, "BLOCK", block)
        assert scanner.anchors(low) == whole
    assert scanner.anchors(b"") == scanner.anchors(b" -. \xc3\xa9") == {}
    assert licenses.Scanner({}).anchors(low) == {}


def test_licenses_query_finds_every_notice(spark):
    d = "/root/testdata/sf0.001"
    want = {r["doc_id"] for r in spark.read.parquet(f"{d}/documents.parquet").where("text rlike 'Released under the MIT|Licensed under the Apache|licensed under the GNU General|under CC BY-NC'").collect()}
    assert {r["doc_id"] for r in queries.op9_licenses(spark, d).where("n_licenses > 0").collect()} == want


# --- op10 --------------------------------------------------------------------------------------------------------------

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def brute_leaks(docs, items, n=10):
    split = lambda t: WORD.findall((t or "").translate(LOWER))
    windows = [(str(i), tuple(w[k : k + n])) for i, t in items for w in [split(t)] for k in range(max(1, len(w) - n + 1)) if w]
    out = {}
    for i, t in docs:
        w = split(t)
        hit, own = set(), set()
        for item, win in windows:
            for k in range(len(w) - len(win) + 1):
                if tuple(w[k : k + len(win)]) == win:
                    hit.update(range(k, k + len(win)))
                    own.add(item)
        out[i] = (len(w), len(hit), len(own), hashlib.sha256(",".join(sorted(own)).encode()).hexdigest(), bool(hit))
    return out


def test_decontamination(spark, folder):
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{folder}/documents.parquet").where("doc_id <> 106").collect()]
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{folder}/benchmark.parquet").collect()]
    want = brute_leaks(rows, items)
    got = {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in queries.op10_decontamination(spark, folder).where("doc_id <> 106").collect()}
    assert got == want and sum(x[1] > 0 for x in want.values()) > 3


def test_decontamination_in_blocks_and_removal(spark, folder, docs):
    items = spark.read.parquet(f"{folder}/benchmark.parquet")
    whole = sorted(r.asDict(True).__repr__() for r in decontaminate.scan(docs, items, keep=["doc_id"]).collect())
    parts = sorted(r.asDict(True).__repr__() for r in decontaminate.scan(docs, items, keep=["doc_id"], block_bytes=1).collect())
    assert whole == parts
    clean = decontaminate.remove_spans(awkward(docs), items)
    assert decontaminate.contamination(clean, items).where("n_hit > 0").count() == 0
    left = {r["doc_id"]: r for r in clean.collect()}
    assert 3 not in left and left[1]["text"] == docs.where("doc_id = 1").first()["text"] and left[100]["text"] is None
    none = spark.createDataFrame([], "item_id bigint, text string")
    assert decontaminate.contamination(docs, none).where("contaminated").count() == 0
    assert decontaminate.contamination(empty(spark), items).count() == 0


def test_decontamination_with_items_without_id(spark, docs):
    text = docs.where("doc_id = 1").first()["text"]
    items = spark.createDataFrame([(None, text), (4, text), (4, text), (None, None)], "item_id bigint, text string")
    for size in (1, decontaminate.BLOCK_BYTES):
        got = collected(decontaminate.contamination(docs, items, block_bytes=size))[1]
        assert (got["items"], got["n_items"], got["contaminated"]) == (["", "4"], 2, True)


def test_words_against_regex():
    texts = ["Ab1-c é_ß ÀX", "", "x" * 300_000 + " yy " + "z" * 10, "a b", "日本 語"]
    w = bytewords.Words([t.encode() for t in texts], bytewords.alnum_class())
    got = [[w.word(i).decode() for i in range(w.doc[k], w.doc[k + 1])] for k in range(len(texts))]
    assert got == [WORD.findall(t.translate(LOWER)) for t in texts]
    again = bytewords.Words([t.encode() for t in reversed(texts)], bytewords.alnum_class())
    pairs = lambda v: {(v.word(i), int(v.hashes[i])) for i in range(len(v.start))}
    assert pairs(w) == pairs(again)
