"""Sources, sinks, SQL access and the live path."""

import tempfile

import pytest
from pyspark.sql import functions as F

from streamcut.operators import greedy, metrics, ordering, transforms
from streamcut.plans import api, sqlapi
from streamcut.sources import files, graphs, zipf
from streamcut.streaming import live, snapshot


def test_edge_files(spark):
    root = tempfile.mkdtemp()
    for name, text in (("m", "%%head\n% c\n3 3 2\n1 2\n2 3 0.5\n"), ("t", "# c\n1 2\n\n2 3\n"), ("a", "1 2 3\n4 5\n"), ("c", "#c\n1\t2\n2\t3\n")):
        with open(f"{root}/{name}.txt", "w") as f:
            f.write(text)
    pairs = lambda df: sorted((r.src, r.dst) for r in df.collect())
    assert pairs(files.read_coordinate(spark, f"{root}/m.txt")) == [(1, 2), (2, 3)]
    assert pairs(files.read_edges(spark, f"{root}/t.txt", "text")) == [(1, 2), (2, 3)]
    assert pairs(files.read_edges(spark, f"{root}/c.txt")) == [(1, 2), (2, 3)]
    assert pairs(files.read_adjacency(spark, f"{root}/a.txt")) == [(1, 2), (1, 3), (4, 5)]


def test_sink_round_trip(spark):
    root = tempfile.mkdtemp()
    placed = spark.createDataFrame([(1, 2, 0), (2, 3, 1)], "src long, dst long, part int")
    files.write_parts(placed, f"{root}/p")
    back = spark.read.parquet(f"{root}/p")
    assert {(r.src, r.dst, r.part) for r in back.collect()} == {(1, 2, 0), (2, 3, 1)}


def test_zipf_source_equals_the_plan(spark):
    spark.dataSource.register(zipf.ZipfSource)
    a = spark.read.format("zipf_edges").options(n="200", alpha="2.0", beta="1.9", seed="3").load().distinct()
    b = zipf.zipf_graph(spark, 200, 2.0, 1.9, seed=3)
    assert {tuple(r) for r in a.collect()} == {tuple(r) for r in b.collect()}
    assert zipf.zipf_graph(spark, 500, 1.9, 1.9).count() > zipf.zipf_graph(spark, 500, 2.2, 2.2).count()


def test_vertex_dictionary(spark):
    keyed = spark.createDataFrame([("a", "b"), ("b", "c")], "src_key string, dst_key string")
    e, words = transforms.encode_vertices(keyed)
    assert transforms.id_collisions(words).count() == 0
    assert {(r.src_key, r.dst_key) for r in transforms.decode_vertices(e, words).collect()} == {("a", "b"), ("b", "c")}


def test_distributed_numbers(spark, monkeypatch):
    monkeypatch.setattr(transforms, "ONE_WINDOW", 10)
    df = spark.range(500).select((F.col("id") * 7 % 500).alias("k"))
    assert all(r.k == r.n for r in transforms.number_rows(df, [F.col("k")], "n").collect())
    df = spark.createDataFrame([(k // 2, k % 3 - 1) for k in range(200)], "at long, d long")
    got = transforms.running_sum(df, "at", "d", "s", block=7).collect()
    assert len(got) == 200 and all(r.s == sum(k % 3 - 1 for k in range(200) if k // 2 <= r["at"]) for r in got)


def test_other_formats_and_sinks(spark):
    root = tempfile.mkdtemp()
    e = spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long")
    for fmt in ("json", "orc", "parquet"):
        e.write.format(fmt).save(f"{root}/{fmt}")
        assert {tuple(r) for r in files.read_edges(spark, f"{root}/{fmt}", fmt).collect()} == {(1, 2), (2, 3)}
    q = files.stream_rate(spark, 50, 100).writeStream.format("memory").queryName("rate_edges").start()
    q.processAllAvailable()
    q.stop()
    assert spark.table("rate_edges").columns == ["src", "dst", "ts", "event_id"]
    files.write_replicas(metrics.replica_sets(e.withColumn("part", F.lit(0))), "replica_table", 4)
    assert spark.table("replica_table").count() == 3
    spark.sql("DROP TABLE replica_table")
    graphs.register_views(spark, "/root/testdata/sf0.001", ("nation", "region"))
    assert spark.sql("SELECT count(*) AS n FROM nation JOIN region ON n_regionkey = r_regionkey").first().n == 25


def test_repeated_edges_of_a_stream_come_once(spark):
    root = tempfile.mkdtemp()
    rows = [(k % 9, k % 4, k) for k in range(60)]
    made = spark.createDataFrame(rows, "src long, dst long, event_id long").withColumn("ts", F.timestamp_seconds(F.col("event_id") + 1_000_000))
    for _ in range(2):  # one file twice
        made.coalesce(1).write.mode("append").parquet(f"{root}/in")
    s = files.stream_edges(spark, f"{root}/in")
    q = live.exactly_once(s).writeStream.option("checkpointLocation", f"{root}/c").trigger(availableNow=True).format("parquet").start(f"{root}/out")
    q.awaitTermination()
    out = [(r.src, r.dst) for r in spark.read.parquet(f"{root}/out").collect()]
    assert sorted(out) == sorted({(a, b) for a, b, _ in rows})


def test_sql_access(spark):
    sqlapi.register(spark)
    assert spark.sql("SELECT occupancy(2, 4L) AS x").first().x == 1 - 0.5**4
    stream = ordering.stream(zipf.zipf_graph(spark, 100, 2.0, 2.0, 30)).withColumn("run", F.lit(1))
    stream.select("run", "src", "dst", "seq").createOrReplaceTempView("stream_t")
    for method in ("greedy_affinity", "greedy_indegree", "greedy_total_degree"):
        got = spark.sql(f"SELECT * FROM partition_edges(TABLE(stream_t) PARTITION BY (run) ORDER BY (seq), '{method}', 4)").collect()
        want = getattr(greedy, method)(stream, 4).collect()
        assert {(r.src, r.dst, r.part) for r in got} == {(r.src, r.dst, r.part) for r in want}


def test_live_equals_batch_restarts_and_flushes(spark):
    """A stopped and restarted query loses no edge, and every held edge is placed in the end."""
    never = spark.createDataFrame([(k % 9, 1000 + k) for k in range(60)], "src long, dst long")  # targets that never come
    stream = ordering.stream(zipf.zipf_graph(spark, 150, 2.0, 2.0, 60, seed=2).unionByName(never)).cache()
    rows = stream.orderBy("seq").select("src", "dst", "seq").collect()
    root = tempfile.mkdtemp()
    cut = next(k for k in range(len(rows) // 2, len(rows)) if rows[k].src != rows[k - 1].src)
    for method, rules in (("greedy_indegree", {}), ("greedy_total_degree", {}), ("greedy_total_degree", {"max_buffer": 7})):
        at = f"{root}/{method}{len(rules)}"
        for part in (rows[:cut], rows[cut:]):  # a new query from the checkpoint
            spark.createDataFrame(part, "src long, dst long, seq long").coalesce(1).write.mode("append").parquet(f"{at}/in")
            live.PlacementStream(4, method, at, **rules).start(spark.readStream.schema("src long, dst long, seq long").parquet(f"{at}/in")).awaitTermination()
        out = live.PlacementStream(4, method, at, **rules)
        early = out.placed(spark).count()
        got = {(r.src, r.dst): r.part for r in out.flush(spark).collect()}
        assert out.flush(spark).count() == len(got) == len(rows)  # a second flush changes nothing
        if method == "greedy_indegree":
            assert early == len(rows)
            want = greedy.greedy_indegree(stream, 4)
        elif rules:
            assert len(rows) - 7 <= early < len(rows)
            want = greedy.bounded_total_degree(stream, 4, 7)
        else:
            assert early < len(rows)
            want = greedy.greedy_total_degree(stream, 4)
        assert got == {(r.src, r.dst): r.part for r in want.collect()}
    assert live.live_state(spark, f"{root}/greedy_total_degree0/checkpoint", "vertices").count() > 100  # a row a vertex, not one value


def test_unknown_methods_and_options_are_errors(spark):
    e = spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long")
    for method, opts in (("greedy_indegree", {"hub_threshold": 3}), ("greedy_indegree", {"engine": "snapshot", "tie": "hash"}), ("greedy_total_degree", {"engine": "snapshot"}), ("greedy_affinity", {"shards": 3}), ("greedy_affinity", {"engine": "sharded", "tie": "up"}), ("no_such_method", {})):
        with pytest.raises(ValueError):
            api.partition(e, method, 4, **opts)
    with pytest.raises(ValueError):
        live.place_live(e, 4, "no_such_method")
    sqlapi.register(spark)
    e.withColumns({"run": F.lit(1), "seq": F.col("src")}).createOrReplaceTempView("two_edges")
    with pytest.raises(Exception, match="unknown live method"):
        spark.sql("SELECT * FROM partition_edges(TABLE(two_edges) PARTITION BY (run) ORDER BY (seq), 'no_such_method', 4)").collect()


def test_snapshot_sink_replays_and_restarts(spark):
    path = tempfile.mkdtemp()
    made = lambda lo, hi: spark.createDataFrame([(k % 5, k % 7 + k // 40, k) for k in range(lo, hi)], "src long, dst long, event_id long").withColumn("ts", F.timestamp_seconds("event_id"))
    sink = snapshot.SnapshotSink(spark, path, 4)
    sink(made(0, 40), 0)
    first = sink.state()
    sink(made(0, 40), 0)
    assert sink.state().loads == first.loads and sum(first.loads) == 40
    whole = {r.v: (r.mask, r.d_in) for r in first.vertices(spark).collect()}
    again = snapshot.SnapshotSink(spark, path, 4)  # after a restart
    assert again.state().loads == first.loads and {r.v: (r.mask, r.d_in) for r in again.state().vertices(spark).collect()} == whole
    for k in range(1, 11):
        again(made(40 * k, 40 * k + 40), k)
    state = again.state()
    assert sum(state.loads) == 440 and len(state.layers) <= snapshot.LAYERS and len(again.committed()) == 2
    assert sum(r.d_in for r in state.vertices(spark).collect()) == 440
    placed = spark.read.parquet(*[f"{path}/batch={k}" for k in range(11)])
    want = {r.v: r.copies for r in metrics.replica_sets(placed).collect()}
    assert {r.v: r.mask.bit_count() for r in state.vertices(spark).collect()} == want


def test_windows_and_duplicates(spark):
    e = graphs.load(spark, "/root/testdata/sf0.001", "events")
    assert live.windowed_load(e).agg(F.sum("edges")).first()[0] == e.count() == live.session_load(e).agg(F.sum("edges")).first()[0]
