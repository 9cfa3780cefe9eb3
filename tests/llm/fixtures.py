"""Small tables with every awkward case: nulls, empty and long texts, ties, repeated rows, clashing column names."""

import random

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def words(rng: random.Random, n: int) -> list[str]:
    return ["".join(rng.choice("abcdeéß") for _ in range(rng.randint(2, 6))) for _ in range(n)]


def documents(spark, n: int = 60, seed: int = 3):
    rng = random.Random(seed)
    passage = " ".join(words(rng, 14))
    line = "This very common line is in many documents."
    rows = []
    for i in range(n):
        text = " ".join(words(rng, rng.randint(1, 80)))
        if i % 4 == 0:
            text += "\n" + ("  " if i % 8 else "") + (line.upper() if i % 3 else line) + "\t\nEnd"
        if i % 7 == 0:
            text += " " + passage + " tail"
        rows.append((i, text, "en" if i % 2 else "fr", f"src{i % 3}", len(text)))
    rows += [
        (100, None, None, None, None),
        (101, "", "en", "src0", 0),
        (102, "   \n\t", "en", "src0", 5),
        (103, "é" * 3 + "!?", "fr", "src1", 5),
        (104, rows[5][1], "fr", "src1", 1),
        (105, rows[5][1], "fr", "src1", 1),
        (106, " ".join(words(rng, 6000)), "en", "src2", 1),
        (107, "\n" * 50, "en", "src2", 50),
    ]
    return spark.createDataFrame(rows, DOCS)


def awkward(df):
    """df twice over (repeated rows), with columns whose names clash with those the operators use."""
    from pyspark.sql import functions as F

    more = {c: F.lit("x") for c in ("row", "id", "k", "r", "line", "key", "scan", "ids", "curve", "shard", "slot", "dropped", "toxicity", "licenses", "rank", "fp", "_id", "_row", "lang_pred")}
    return df.unionAll(df.limit(7)).withColumns(more)


def empty(spark):
    return spark.createDataFrame([], DOCS)
