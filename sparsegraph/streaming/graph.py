"""Structured Streaming over events: exploded ingest, degree tables, windowed adjacency, successions, maintained graphs."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def stream_events(spark: SparkSession, path: str, *, schema: str = EVENTS, max_files: int = 1) -> DataFrame:
    """A file stream of Parquet parts with timestamps."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def exploded(stream: DataFrame) -> DataFrame:
    """(row, col, val) as exploded_events, without state."""
    pairs = F.array(*[F.concat(F.lit(f"{n}|"), c.cast("string")) for n, c in (("event_type", F.col("event_type")), ("user_id", F.col("user_id")), ("k", F.get_json_object("props", "$.k")))])
    return stream.select(F.col("event_id").alias("row"), F.explode(pairs).alias("col")).where("col is not null").withColumn("val", F.lit(1).cast("bigint"))


def degrees(stream: DataFrame) -> DataFrame:
    """The degree table, kept up to date (complete or update mode)."""
    return exploded(stream).groupBy("col").agg(F.count("*").alias("degree"))


def windowed_adjacency(df: DataFrame, *, length: str = "1 hour", slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """(start, user_id, event_type, w): entries of user x type for each tumbling or sliding window; batch or stream."""
    if watermark:
        df = df.withWatermark("ts", watermark)
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return df.groupBy(w.alias("w0"), "user_id", "event_type").agg(F.count("*").alias("w")).select(F.col("w0.start").alias("start"), "user_id", "event_type", "w")


def session_adjacency(df: DataFrame, *, gap: str = "30 minutes", watermark: str | None = None) -> DataFrame:
    """(start, end, user_id, w): a user's events in sessions that end after a gap; batch or stream."""
    if watermark:
        df = df.withWatermark("ts", watermark)
    return df.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("w")).select(F.col("s.start").alias("start"), F.col("s.end").alias("end"), "user_id", "w")


def deduplicated(stream: DataFrame, watermark: str = "1 day") -> DataFrame:
    """Each event id once, as far back as the watermark."""
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def late_rows(query) -> int:
    """Rows that a streaming query's stateful operators dropped behind the watermark, over the progress it still holds."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


SUCCESSION = "user_id bigint, src string, dst string, gap_us bigint"


def type_successions(stream: DataFrame, *, idle_ms: int | None = None, watermark: str = "1 day") -> DataFrame:
    """(user_id, src, dst, gap_us): for each user, the type of every event and of the next one. State holds the last event
    of a user. With idle_ms a user is forgotten once the watermark is that far past the user's last event; events behind
    the watermark are then dropped. An event that comes after its successor starts anew from the last seen."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key: tuple, parts: Iterator, state) -> Iterator:
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame([], columns=["user_id", "src", "dst", "gap_us"])
            return
        pdf = pd.concat(list(parts)).sort_values(["us", "event_id"])
        last = state.get if state.exists else None
        out = []
        for us, kind in zip(pdf["us"].tolist(), pdf["event_type"].tolist(), strict=True):
            if last is not None and us >= last[0]:
                out.append((key[0], last[1], kind, us - last[0]))
            last = (us, kind)
        state.update(last)
        if idle_ms is not None:
            state.setTimeoutTimestamp(max(last[0] // 1000, state.getCurrentWatermarkMs()) + idle_ms)
        yield pd.DataFrame(out, columns=["user_id", "src", "dst", "gap_us"])

    timeout = GroupStateTimeout.NoTimeout
    if idle_ms is not None:
        stream, timeout = stream.withWatermark("ts", watermark), GroupStateTimeout.EventTimeTimeout
    rows = stream.select("user_id", "event_id", "event_type", "ts", F.unix_micros("ts").alias("us"))
    return rows.groupBy("user_id").applyInPandasWithState(step, SUCCESSION, "us bigint, kind string", "append", timeout)


def with_static(stream: DataFrame, cues: DataFrame) -> DataFrame:
    """Live events of users in a cue table (user_id)."""
    return stream.join(F.broadcast(cues.select("user_id").distinct()), "user_id", "left_semi")


def interval_pairs(left: DataFrame, right: DataFrame, *, within: str = "10 minutes", watermark: str = "1 hour") -> DataFrame:
    """(user_id, left_id, right_id): events of one user in two streams, the right one at most `within` after the left."""
    a = left.withWatermark("ts", watermark).select(F.col("user_id").alias("u"), F.col("ts").alias("t0"), F.col("event_id").alias("left_id"))
    b = right.withWatermark("ts", watermark).select("user_id", F.col("ts").alias("t1"), F.col("event_id").alias("right_id"))
    return a.join(b, F.expr(f"u = user_id and t1 >= t0 and t1 <= t0 + interval {within}")).select("user_id", "left_id", "right_id")


class MaintainedGraph:
    """An undirected simple graph with edge supports, kept in Parquet by micro-batches (foreachBatch).

    A batch adds edges; only triangles through new edges are formed. Every state is a folder named by its batch, written under
    another name and then renamed. A batch starts from the state of the one before it, whoever wrote it, so a batch that
    runs twice changes nothing and a new instance goes on where the last one ended."""

    SCHEMA = "src bigint, dst bigint, support bigint"

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def _folder(self, name: str):
        path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}" if name else self.path)
        return path.getFileSystem(self.spark._jsc.hadoopConfiguration()), path

    def batches(self) -> list[int]:
        """Numbers of the batches that are written, in order."""
        fs, root = self._folder("")
        names = [f.getPath().getName() for f in fs.listStatus(root)] if fs.exists(root) else []
        return sorted(int(n.removeprefix("batch-")) for n in names if n.startswith("batch-"))

    def state(self, before: int | None = None) -> DataFrame:
        """(src, dst, support) after the last batch, or after the last one below `before`."""
        held = [b for b in self.batches() if before is None or b < before]
        return self.spark.read.schema(self.SCHEMA).parquet(f"{self.path}/batch-{held[-1]:08d}") if held else self.spark.createDataFrame([], self.SCHEMA)

    def apply(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id in self.batches():
            return
        old = self.state(batch_id)
        new = batch.where("src <> dst").select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct().join(old.select("src", "dst"), ["src", "dst"], "left_anti")
        every = old.select("src", "dst", F.lit(0).alias("n")).unionByName(new.withColumn("n", F.lit(1)))
        both = every.select(F.col("src").alias("a"), F.col("dst").alias("b"), "n").unionByName(every.select(F.col("dst").alias("a"), F.col("src").alias("b"), "n"))
        # Wedges at a whose first leg is new; closed by any edge; each triangle once by its sorted vertices.
        wedge = both.where("n = 1").select("a", F.col("b").alias("u")).join(both.select("a", F.col("b").alias("v")), "a").where("u <> v")
        closed = wedge.select("a", F.least("u", "v").alias("src"), F.greatest("u", "v").alias("dst")).join(every.select("src", "dst"), ["src", "dst"], "left_semi")
        tri = closed.select(F.array_sort(F.array("a", "src", "dst")).alias("t")).distinct().select(F.col("t")[0].alias("x"), F.col("t")[1].alias("y"), F.col("t")[2].alias("z"))
        gain = tri.select(F.explode(F.array(F.struct(F.col("x").alias("src"), F.col("y").alias("dst")), F.struct(F.col("y").alias("src"), F.col("z").alias("dst")), F.struct(F.col("x").alias("src"), F.col("z").alias("dst")))).alias("e")).groupBy("e.src", "e.dst").agg(F.count("*").alias("gain"))
        out = old.unionByName(new.withColumn("support", F.lit(0).cast("bigint"))).join(gain, ["src", "dst"], "left").select("src", "dst", (F.col("support") + F.coalesce("gain", F.lit(0))).alias("support"))
        out.write.mode("overwrite").parquet(f"{self.path}/_next-{batch_id:08d}")
        fs, written = self._folder(f"_next-{batch_id:08d}")
        if not fs.rename(written, self._folder(f"batch-{batch_id:08d}")[1]):
            raise OSError(f"batch {batch_id} could not be renamed")
