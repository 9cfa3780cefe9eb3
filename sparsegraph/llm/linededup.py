"""Line deduplication over all documents, with DataFrame functions alone; the result is a compressed keep bitmap for
each document, not text.

A line's key is the line without white space (0x20, 0x09-0x0D) at both ends and with A-Z lower-cased. Keys of at least
min_chars code points that are found in at least min_docs documents lose all their lines, except in the document with
the largest id that holds them. Keys are compared by two independent 64-bit hashes.

Counts are combined before the shuffle, so a line that a third of all documents hold is one row for each task. The rows
of frequent lines alone are then sorted by hash, document and position. Documents are rows: rows that share an id count
each, and all rows with the largest id keep their lines. A null id is below all others. A null or empty text is one
empty line. Very long texts are taken whole. Other columns are not read. Empty tables give empty results."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import ascii_lower, materialise

SPACE = " \t\n\x0b\x0c\r"
LOWEST = -(1 << 63)


def split_lines(text):
    """Java's split drops nothing with a limit of -1; an empty text is one empty line."""
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def line_keys(text, min_chars: int):
    """The key of each line, null where the line is too short to have one (in bytes; code points are counted later)."""
    return F.transform(split_lines(text), lambda x: F.when(F.octet_length(x) >= min_chars, ascii_lower(F.btrim(x, F.lit(SPACE)))))


def hashed(rows: DataFrame, min_chars: int) -> DataFrame:
    """Two hashes in place of the key, for keys that are long enough."""
    return rows.where(F.char_length("key") >= min_chars).withColumns({"h1": F.xxhash64("key"), "h2": F.xxhash64(F.lit(7), "key")}).drop("key")


def frequent_keys(docs: DataFrame, *, min_chars: int, min_docs: int) -> DataFrame:
    """(h1, h2, last): keys of at least min_docs documents and the largest id that holds them."""
    keys = docs.select(doc_key(), F.explode(F.array_distinct(line_keys(F.col("text"), min_chars))).alias("key"))
    return hashed(keys, min_chars).groupBy("h1", "h2").agg(F.count("*").alias("n"), F.max("id").alias("last")).where(F.col("n") >= min_docs).drop("n")


def doc_key():
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(LOWEST)).alias("id")


def drop_runs(docs: DataFrame, *, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """(id, row, runs, n_dropped): for each document that loses lines, the runs of dropped lines as (start, length), in
    order: a run-length code of its keep bitmap. id and row (a hash of the text) name the document."""
    lines = hashed(docs.select(doc_key(), F.xxhash64("text").alias("row"), F.posexplode(line_keys(F.col("text"), min_chars)).alias("pos", "key")), min_chars)
    # Written first: a table of its own on this side lets the join be a broadcast where it is small, and split where a line
    # is hot.
    frequent = materialise(frequent_keys(docs, min_chars=min_chars, min_docs=min_docs), "frequent")
    dropped = lines.join(frequent, ["h1", "h2"]).where("id <> last").select("id", "row", "pos").distinct()
    run = dropped.withColumn("grp", F.col("pos") - F.row_number().over(W.partitionBy("id", "row").orderBy("pos")))
    runs = run.groupBy("id", "row", "grp").agg(F.min("pos").alias("start"), F.count("*").cast("int").alias("length"))
    return runs.groupBy("id", "row").agg(F.sort_array(F.collect_list(F.struct("start", "length"))).alias("runs"), F.sum("length").alias("n_dropped"))


def keep_bitmaps(docs: DataFrame, *, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """(doc_id, n_lines, n_dropped, bitmap) for each row of docs; the bitmap is a text of run lengths, kept and dropped by
    turns, that ends with the last dropped run ("" keeps all)."""
    with_runs = joined(docs.select("doc_id", "text"), drop_runs(docs, min_chars=min_chars, min_docs=min_docs))
    return with_runs.select("doc.doc_id", F.size(split_lines(F.col("doc.text"))).cast("long").alias("n_lines"), n_dropped(), bitmap().alias("bitmap"))


def joined(docs: DataFrame, runs: DataFrame) -> DataFrame:
    """(doc, dropped): each row of docs as a struct, so that no name clashes, with a struct of its runs and n_dropped, null
    where all lines stay."""
    runs = runs.select("id", "row", F.struct("runs", "n_dropped").alias("dropped"))
    rows = docs.select(doc_key(), F.xxhash64("text").alias("row"), F.struct(*docs.columns).alias("doc"))
    return rows.join(runs, ["id", "row"], "left").select("doc", "dropped")


def n_dropped():
    return F.coalesce(F.col("dropped.n_dropped"), F.lit(0)).cast("long").alias("n_dropped")


def bitmap():
    runs = F.col("dropped.runs")
    gaps = F.transform(runs, lambda r, i: F.concat_ws(",", r["start"] - F.when(i > 0, F.get(runs, i - 1)["start"] + F.get(runs, i - 1)["length"]).otherwise(0), r["length"]))
    return F.coalesce(F.array_join(gaps, ","), F.lit(""))


def kept_text():
    """The lines that stay, joined by line feeds; the text itself where none goes (null: empty)."""
    text, runs = F.col("doc.text"), F.col("dropped.runs")
    end = lambda r: r["start"] + r["length"]

    def joined_gaps(lines):
        """The stretches before each run and after the last one: each line is copied once, however many runs there are."""
        before = F.transform(runs, lambda r, i: F.struct(F.when(i > 0, end(F.get(runs, i - 1))).otherwise(0).alias("from"), r["start"].alias("to")))
        after = F.struct(end(F.element_at(runs, -1)).alias("from"), F.size(lines).alias("to"))
        return F.array_join(F.flatten(F.transform(F.concat(before, F.array(after)), lambda g: F.slice(lines, g["from"] + 1, g["to"] - g["from"]))), "\n")

    # The one-element array has the text split once, not once for each run.
    kept = F.get(F.transform(F.array(split_lines(text)), joined_gaps), 0)
    return F.when(F.col("dropped").isNull(), F.coalesce(text, F.lit(""))).otherwise(kept)


def dedup_lines(docs: DataFrame, *, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """docs with the kept lines as text (null stays null); n_chars follows the text."""
    out = joined(docs, drop_runs(docs, min_chars=min_chars, min_docs=min_docs)).select("doc", F.when(F.col("doc.text").isNotNull(), kept_text()).alias("kept"))
    new = {"text": F.col("kept"), "n_chars": F.coalesce(F.char_length("kept"), F.lit(0)).cast(dict(docs.dtypes).get("n_chars", "long"))}
    return out.select(*[new.get(c, F.col(f"doc.`{c}`")).alias(c) for c in docs.columns])
