import pytest

from pyspark.sql import functions as F

import corpus_pipeline

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def stages(spark):
    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    out = [("input", docs)]
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.materialise(stage(spark, docs, d), name)
        out.append((name, docs))
    return out


def test_order_and_columns(stages):
    assert [n for n, _ in stages[1:]] == ["toxicity", "line_dedup", "simhash_near_dedup", "decontamination", "pieces"]
    assert all(df.columns == COLUMNS for _, df in stages[:-1])
    assert {"doc_id", "ids", "piece_start", "piece_end"} <= set(stages[-1][1].columns)


def test_each_stage_keeps_a_part_of_its_input(stages):
    sizes = [df.count() for _, df in stages]
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] > 0.6 * sizes[0]
    ids = [{r["doc_id"] for r in df.select("doc_id").collect()} for _, df in stages]
    assert all(b <= a for a, b in zip(ids, ids[1:], strict=False))


def test_toxic_go_and_clean_stay(spark):
    """On a table with enough labels to learn from."""
    d = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    kept = {r["doc_id"] for r in dict(corpus_pipeline.STAGES)["toxicity"](spark, docs, d).select("doc_id").collect()}
    bad = docs.select("doc_id", F.size(F.regexp_extract_all(F.lower("text"), F.lit(r"\b(idiot|moron|scum|loser|worthless|pathetic)\b"), 0)).alias("n"))
    rows = bad.collect()
    assert sum(r["doc_id"] in kept for r in rows if r["n"] >= 3) <= 0.1 * sum(r["n"] >= 3 for r in rows)
    assert sum(r["doc_id"] not in kept for r in rows if r["n"] == 0) <= 0.08 * len(rows)


def test_run_gives_the_last_stage(spark, stages):
    got = sorted((r["doc_id"], len(r["ids"])) for r in corpus_pipeline.run(spark, "/root/testdata/sf0.001").collect())
    assert got == sorted((r["doc_id"], len(r["ids"])) for r in stages[-1][1].collect())
