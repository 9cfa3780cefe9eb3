import os

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from sparsegraph.functions import udtf
from sparsegraph.operators import schema as S
from sparsegraph.operators import truss
from sparsegraph.sources import coordinate, tables
from sparsegraph.sources import workloads as G
from sparsegraph.sources.tables import read_table
from sparsegraph.streaming import graph as stream

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def batches(spark, tmp_path_factory):
    """The events as shuffled Parquet parts."""
    path = str(tmp_path_factory.mktemp("events"))
    G.events(spark, D).drop("us").repartition(4, F.xxhash64("event_id")).write.mode("overwrite").parquet(path)
    return path


def drained(df, name, mode, tmp_path):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
    assert q.awaitTermination(120)
    return df.sparkSession.table(name)


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_triples_and_documents_round_trip(spark, tmp_path):
    a = spark.createDataFrame([(1, 2, 0.5), (3, 4, -1.0)], "row bigint, col bigint, val double")
    tables.write_triples(a, str(tmp_path / "p"))
    assert rows(spark.read.parquet(str(tmp_path / "p"))) == rows(a)
    tables.write_triples_text(a, str(tmp_path / "t"))
    assert rows(tables.read_triples(spark, str(tmp_path / "t"))) == rows(a)
    (tmp_path / "e.txt").write_text("# edges\n1\t2\n3\t4\n")
    assert rows(tables.read_triples(spark, str(tmp_path / "e.txt"), has_val=False)) == [(1, 2, 1.0), (3, 4, 1.0)]
    docs = spark.createDataFrame([(1, "x"), (2, None)], "doc_id bigint, text string")
    for fmt in ("json", "orc"):
        docs.write.format(fmt).save(str(tmp_path / fmt))
        assert tables.read_docs(spark, str(tmp_path / fmt), fmt).count() == 2
    tables.save_bucketed(a, "bucketed_a", 2)
    plan = spark.table("bucketed_a").join(spark.table("bucketed_a").toDF("row", "c", "v").hint("merge"), "row")._jdf.queryExecution().toString()
    assert "Exchange hashpartitioning" not in plan
    spark.sql("DROP TABLE bucketed_a")
    assert all(rows(c) == rows(a) for c in tables.bucketed_copies(a))


@pytest.mark.parametrize("split", [7, 16, 1 << 20])
def test_coordinate_source(spark, tmp_path, split):
    path = tmp_path / "m.mtx"
    path.write_text("%%MatrixMarket matrix coordinate real symmetric\n% c\n3 3 4\n1 1 2.5\n2 1 -1\n3 2 4\n3 3 1e2\n")
    assert rows(coordinate.read_coordinate(spark, str(path))) == [(0, 0, 2.5), (0, 1, -1.0), (1, 0, -1.0), (1, 2, 4.0), (2, 1, 4.0), (2, 2, 100.0)]
    df = spark.read.format("coordinate").option("path", str(path)).option("split", str(split)).load()
    assert df.count() == 6
    path.write_text("%%MatrixMarket matrix coordinate pattern general\n2 2 1\n1 2\n")
    assert rows(coordinate.read_coordinate(spark, str(path))) == [(0, 1, 1.0)]


def test_derived_graphs(spark):
    assert G.copurchase(spark, D, 1).count() == 8899 and G.copurchase(spark, D).count() == 2324
    assert G.user_succession(spark, D).count() == 221 and G.page_link(spark, D).count() == 279
    assert G.nation_trade(spark, D).count() == 250 and G.embed_sim(spark, D).count() == 920


def test_degree_stream(spark, batches, tmp_path):
    got = drained(stream.degrees(stream.stream_events(spark, batches)), "degrees", "complete", tmp_path)
    assert rows(got) == rows(G.exploded_events(spark, D).deg)
    edges = drained(stream.exploded(stream.stream_events(spark, batches)), "exploded", "append", tmp_path)
    assert rows(edges) == rows(G.exploded_events(spark, D).edge)


def test_windows_and_sessions(spark, batches, tmp_path):
    ev = G.events(spark, D)
    for name, slide in (("tumbling", None), ("sliding", "30 minutes")):
        live = drained(stream.windowed_adjacency(stream.stream_events(spark, batches), slide=slide), name, "complete", tmp_path)
        assert rows(live) == rows(stream.windowed_adjacency(ev, slide=slide))
    live = drained(stream.session_adjacency(stream.stream_events(spark, batches)), "sessions", "complete", tmp_path)
    assert rows(live) == rows(stream.session_adjacency(ev))


def test_deduplication(spark, batches, tmp_path):
    twice = str(tmp_path / "twice")
    spark.read.parquet(batches).write.parquet(twice)
    spark.read.parquet(batches).write.mode("append").parquet(twice)
    got = drained(stream.deduplicated(stream.stream_events(spark, twice), "3650 days"), "dedup", "append", tmp_path)
    assert got.count() == G.events(spark, D).count()


@pytest.mark.parametrize("kw", [{}, {"idle_ms": 10**12, "watermark": "3650 days"}], ids=["for ever", "idle"])
def test_successions_by_user(spark, tmp_path, kw):
    ordered = str(tmp_path / "ordered")
    G.events(spark, D).drop("us").coalesce(1).sortWithinPartitions("ts").write.parquet(ordered)
    got = drained(stream.type_successions(stream.stream_events(spark, ordered), **kw), f"successions{len(kw)}", "append", tmp_path)
    G.events(spark, D).createOrReplaceTempView("ev")
    want = spark.sql("SELECT user_id, src, dst, gap_us FROM (SELECT user_id, event_type AS src, lead(event_type) OVER w AS dst, (lead(us) OVER w) - us AS gap_us FROM ev WINDOW w AS (PARTITION BY user_id ORDER BY us, event_id)) WHERE dst IS NOT NULL")
    assert rows(got) == rows(want)


def test_late_rows_are_counted(spark, tmp_path):
    """Two batches: the second holds one row far behind the watermark of the first."""
    path, kind = str(tmp_path / "late"), "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"
    rows_at = lambda *days: spark.createDataFrame([(d, f"2024-01-{d:02d} 00:00:00", 1, "a", 1.0, None) for d in days], kind.replace("timestamp", "string")).withColumn("ts", F.to_timestamp("ts"))
    os.makedirs(path)
    live = stream.windowed_adjacency(stream.stream_events(spark, path), watermark="1 day")
    q = None
    for part in ((10, 11), (12, 1)):
        rows_at(*part).coalesce(1).write.mode("append").parquet(path)
        q = live.writeStream.outputMode("append").format("parquet").option("path", str(tmp_path / "late-out")).option("checkpointLocation", str(tmp_path / "late-state")).trigger(availableNow=True).start()
        assert q.awaitTermination(120)
    assert stream.late_rows(q) == 1


def test_stream_joins(spark, batches, tmp_path):
    cues = spark.createDataFrame([(1,), (1,), (3,)], "user_id bigint")
    got = drained(stream.with_static(stream.stream_events(spark, batches), cues), "cued", "append", tmp_path)
    assert got.count() == G.events(spark, D).where("user_id in (1, 3)").count()
    s = lambda: stream.stream_events(spark, batches, max_files=10)
    pairs = drained(stream.interval_pairs(s(), s(), within="2 hours", watermark="3650 days"), "pairs", "append", tmp_path)
    e = G.events(spark, D)
    want = e.alias("a").join(e.alias("b"), F.expr("a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 2 hours"))
    assert pairs.count() == want.count()


def test_maintained_graph(spark, tmp_path):
    edges = G.copurchase(spark, D).select("src", "dst").where("src < 60 and dst < 60")
    parts = [edges.where(F.pmod(F.xxhash64("src", "dst"), F.lit(3)) == k) for k in range(3)]
    g = stream.MaintainedGraph(spark, str(tmp_path / "graph"))
    for k, p in enumerate(parts):
        g.apply(p, k)
        if k:  # a batch that runs again, and an instance that starts anew
            g.apply(p, k)
            g = stream.MaintainedGraph(spark, str(tmp_path / "graph"))
    want = truss.edge_support(truss.with_ids(S.simple_graph(edges)))
    assert g.batches() == [0, 1, 2]
    assert rows(g.state().select("src", "dst", "support")) == rows(want.select("src", "dst", "support"))


def test_table_functions(spark):
    udtf.register(spark, tri=spark.createDataFrame([(3, 1, 2)], "a bigint, b bigint, c bigint"))
    assert rows(spark.sql("SELECT edge_src, edge_dst FROM tri, LATERAL triangle_edges(a, b, c)")) == [(1, 2), (1, 3), (2, 3)]
    assert rows(spark.sql("""SELECT * FROM explode_record('{"k": 3, "z": null, "t": "é"}')""")) == [("k|3", 1), ("t|é", 1)]


def test_no_names_leak():
    """The library stands without the llm folders: nothing in it imports them."""
    root = os.path.join(os.path.dirname(os.path.dirname(os.path.abspath(__file__))), "sparsegraph")
    for folder, _, names in os.walk(root):
        if "/llm" in folder or "__pycache__" in folder:
            continue
        for n in names:
            if n.endswith(".py"):
                assert "sparsegraph.llm" not in open(os.path.join(folder, n)).read()


def test_embed_sim_has_no_size_limit(spark, tmp_path):
    """20,100 vectors in clusters of 3 that are orthogonal or nearly so to most others, and one of length 0."""
    rng, n, width = np.random.default_rng(1), 20_100, 64
    base = np.repeat(rng.normal(size=(n // 3, width)), 3, axis=0) + 0.01 * rng.normal(size=(n, width))
    base[5] = 0
    pq.write_table(pa.table({"vec_id": np.arange(n), "embedding": pa.array(list(base), pa.list_(pa.float64()))}), tmp_path / "embeddings.parquet")
    got = {(r["src"], r["dst"]) for r in G.embed_sim(spark, str(tmp_path), 0.9).collect()}
    assert got == {(a, b) for c in range(0, n, 3) for a, b in ((c, c + 1), (c, c + 2), (c + 1, c + 2)) if 5 not in (a, b)}


def test_embed_sim_blocks_agree_with_brute_force(spark):
    e = read_table(spark, D, "embeddings").orderBy("vec_id").collect()
    x = np.array([r["embedding"] for r in e], dtype=float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    want = {(e[i]["vec_id"], e[j]["vec_id"]): (x @ x.T)[i, j] for i, j in zip(*np.nonzero(np.triu(x @ x.T > 0.3, 1)))}
    got = {(r["src"], r["dst"]): r["w"] for r in G.embed_sim(spark, D, 0.3, block=37).collect()}
    assert got == pytest.approx(want)
