import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from streamcut.functions.hashing import hash32, shuffle_key
from streamcut.operators import native, whole
from streamcut.operators.greedy import Run
from streamcut.sources import zipf


def test_keys_are_those_of_hashing(spark):
    native.register(spark)
    e = spark.createDataFrame([(0, 0), (-1, 5), (2**63 - 1, -(2**63)), (-(2**63), -(2**63))], "src long, dst long").unionByName(spark.range(50).selectExpr("xxhash64(id) as src", "id as dst"))
    key, grid = whole.keys(7)
    want = F.unhex(F.substring(shuffle_key("src", "dst", seed=7), 1, 16)), hash32("src", "dst", seed=8)
    assert e.select(key, grid).collect() == e.select(want[0].alias("key"), want[1].alias("grid")).collect()


def test_streams_in_the_jvm_measure_as_python_does(spark):
    """Every order, method and option, with up to 128 parts, on a graph with loops and targets that come late or never."""
    native.register(spark)
    e = zipf.zipf_graph(spark, 300, 1.9, 2.1, 90, seed=5).unionByName(spark.createDataFrame([(5, 5), (9, 9), (7, 9000)], "src long, dst long")).distinct()
    rows = e.select("src", "dst", *whole.keys(1)).toArrow().to_batches()
    g = whole.Whole(iter(rows), sum(b.num_rows for b in rows), 1)
    assert (g.out == 0).any() and (g.src == g.dst).any()
    todo = []
    for kind in ("random", "bfs", "dfs"):
        for p, guard, tie in ((1, 1.1, "lowest"), (5, None, "hash"), (64, 1.02, "lowest"), (65, 1.1, "hash"), (128, 1.1, "lowest")):
            run = Run(p, guard, tie, 3)
            todo += [(kind, whole.Job(0, m, run)) for m in ("greedy_affinity", "greedy_indegree", "greedy_total_degree", "final_degrees")]
            todo.append((kind, whole.Job(0, "greedy_indegree", run, count_before=False)))
            todo += [(kind, whole.Job(0, "greedy_total_degree", run, h, s, r)) for h, s, r in ((0, "all", "last"), (3, "none", "first"), (2, "direct", "last"), (1 << 60, "all", "first"))]
    jobs = [(kind, whole.Job(k, j.method, j.run, j.hub_threshold, j.guard_scope, j.release, j.count_before)) for k, (kind, j) in enumerate(todo)]
    table = spark.createDataFrame(pa.Table.from_batches([whole._row(g, None, np.concatenate([whole._numbers(*x) for x in jobs]))]))
    found = table.select(F.call_function(native.STREAMS, "dst", "at", "jobs")).first()[0]
    want = [r for kind in ("random", "bfs", "dfs") for r in g.run(kind, [j for k, j in jobs if k == kind])]
    assert [tuple(map(int, x.split())) for x in found.split(";")] == want


def test_runs_of_a_graph_shared_out_over_tasks(spark, monkeypatch):
    """Numbers of parts up to 128, in three orders: a task for all runs of a graph, or one for each, gives the same rows."""
    from streamcut.plans import api

    g = {"g": zipf.zipf_graph(spark, 120, 2.0, 2.0, 40, seed=6)}
    run = lambda: sorted(tuple(r) for r in api.compare(g, methods=api.FIVE[2:], ps=(4, 96, 128)).collect())
    together = run()
    monkeypatch.setattr(whole, "SHARE_NATIVE", 1)
    assert run() == together and len(together) == 27


def test_shares_of_runs_read_one_kept_graph(spark, monkeypatch):
    """The edges are sorted once for all shares; hashes come with them."""
    from streamcut.plans import api

    g = {"g": zipf.zipf_graph(spark, 120, 2.0, 2.0, 40, seed=6), "none": spark.createDataFrame([], "src long, dst long")}
    run = lambda: sorted(tuple(r) for r in api.compare(g, ps=(4, 48, 96)).collect())
    together, made, graph = run(), [], whole._graph
    monkeypatch.setattr(whole, "SHARE_KEPT", 1)
    monkeypatch.setattr(whole, "_graph", lambda *a: made.append(a) or graph(*a))
    assert run() == together and len(together) == 45
    assert len(made) == 2  # a graph each, for 33 runs
