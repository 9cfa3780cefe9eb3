"""The registered queries of this subpackage: each applies one operator, with production parameters, to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, langid, licenses, linededup, pieces, polyhash, sharding, simhash, toxicity, warc
from .common import fold, table
from .oracles import ORACLES



def tokenizer(name: str) -> str:
    """Where a vocabulary file of the public tokenizers lies."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_hilbert_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    data = F.encode("text", "UTF-8")
    keep = [F.col("doc_id"), (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"), F.crc32(F.coalesce(data, F.lit(b""))).alias("text_crc32"), F.lit("rows").alias("law")]
    return sharding.hilbert_shards(docs, ["lang", "source", "n_chars"], shards=8, keep=keep).select("doc_id", "size", "text_crc32", "law", "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve")


def op2_prefix_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return polyhash.chained_fingerprints(table(spark, sf_dir, "documents"))


def op3_toxic_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity.fit(docs, labels.where(fold(F.col("doc_id"), 3) != 1))
    scored = toxicity.score(docs.select("doc_id", "text"), model, keep=["doc_id"])
    return scored.select("doc_id", (fold(F.col("doc_id"), 3) == 1).alias("held_out"), F.col("toxicity").alias("score"), (F.col("toxicity") >= 0.7).cast("int").alias("predicted"), F.size("toxic_segments").alias("n_segments"))


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder, _ = warc.archive(table(spark, sf_dir, "pages"))
    return warc.read(spark, folder, columns=["page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])


def op5_pieces(spark: SparkSession, sf_dir: str, model: str | None = None) -> DataFrame:
    return pieces.round_trip(table(spark, sf_dir, "documents"), model or tokenizer("piece_bpe_32k.model"))


def op6_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = langid.fit(docs.where(fold(F.col("doc_id"), 4) != 2))
    said = langid.predict(docs.select("doc_id", "text"), model, keep=["doc_id"])
    return said.select("doc_id", (fold(F.col("doc_id"), 4) == 2).alias("held_out"), "lang_pred", F.col("lang_score").alias("score"))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(table(spark, sf_dir, "documents"), shingle=3, distance=2)
    return found.select("doc_id", simhash.hex_print(F.col("fp")).alias("fingerprint"), "component_id")


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = linededup.joined(docs, linededup.drop_runs(docs, min_chars=20, min_docs=3))
    return found.select("doc.doc_id", F.size(linededup.split_lines(F.col("doc.text"))).cast("long").alias("n_lines"), linededup.n_dropped(), F.sha2(linededup.kept_text(), 256).alias("kept_sha256"))


def op9_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.by_document(table(spark, sf_dir, "documents"))


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontaminate.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_hilbert_shards, op2_prefix_fingerprints, op3_toxic_segments, op4_warc, op5_pieces, op6_language, op7_simhash, op8_line_dedup, op9_licenses, op10_decontamination)
}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
