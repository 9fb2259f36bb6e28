import pytest
from pyspark.sql import functions as F

from streamcut.operators import ordering, whole
from streamcut.plans import api
from streamcut.plans.scratch import keep
from streamcut.sources import zipf
from streamcut.streaming import snapshot


@pytest.fixture(scope="module")
def some(spark):
    loops = spark.createDataFrame([(5, 5), (9, 9), (77, 500), (500, 78), (78, 500)], "src long, dst long")
    return {"a": zipf.zipf_graph(spark, 250, 1.9, 2.1, 80, seed=3).unionByName(loops).distinct().cache(), "b": zipf.zipf_graph(spark, 100, 2.0, 2.0, 40, seed=4).select("src", (-1 - F.col("dst")).alias("dst")).cache(), "none": loops.limit(0)}


def test_graphs_in_a_task_measure_as_plans_do(spark, some, monkeypatch):
    """Each order, method, hash and option of a whole graph gives what orders, schedules and runs as plans give."""
    key = lambda t: sorted(tuple(r) for r in t.collect())
    for more in ({"ps": (7, 70)}, {"methods": ("greedy_affinity", "greedy_total_degree"), "ps": (4,), "hub_threshold": 2, "release": "last", "guard_scope": "all"}, {"methods": ("greedy_total_degree",), "ps": (5,), "guard": None, "hub_threshold": 0, "guard_scope": "none"}):
        inside = key(api.compare(some, seed=1, **more))
        monkeypatch.setattr(whole, "EDGES", -1)
        assert inside == key(api.compare(some, seed=1, **more)) and inside
        monkeypatch.undo()


def test_halves_of_md5_that_are_equal(spark, some, monkeypatch):
    """Edges whose sort keys are equal are told apart by the whole md5."""
    want = sorted(tuple(r) for r in api.compare(some, orders=("random",), methods=api.FIVE[2:]).collect())
    monkeypatch.setattr(whole, "keys", lambda seed: [F.unhex(F.lit("00" * 8)).alias("key"), F.lit(0).alias("grid")])
    assert sorted(tuple(r) for r in api.compare(some, orders=("random",), methods=api.FIVE[2:]).collect()) == want


def test_batches_in_a_task_place_as_steps_do(spark, some, monkeypatch):
    stream = keep(ordering.stream(some["b"], "random"), "stream")
    for batch, more in ((150, {}), (200, {"degree_aware": False, "guard": 1.01})):
        one = {tuple(r) for r in snapshot.run_batches(stream, 6, batch, seed=2, **more).select("src", "dst", "seq", "part").collect()}
        monkeypatch.setattr(snapshot, "WHOLE", -1)
        assert one == {tuple(r) for r in snapshot.run_batches(stream, 6, batch, seed=2, **more).select("src", "dst", "seq", "part").collect()}
        monkeypatch.undo()
    assert not snapshot.run_batches(stream.limit(0), 6, 40).count()


def test_snapshot_of_small_batches_starts_no_job_for_each(spark, some):
    tracker = spark.sparkContext.statusTracker()
    stream = keep(ordering.stream(some["a"], "random"), "stream")
    jobs = []
    for batch in (1000, 5):
        spark.sparkContext.setJobGroup(f"snapshot-{batch}", "")
        snapshot.run_batches(stream, 6, batch).count()
        jobs.append(len(tracker.getJobIdsForGroup(f"snapshot-{batch}")))
    spark.sparkContext._jsc.clearJobGroup()
    assert jobs[0] == jobs[1]


def test_ablations_in_tasks_as_plans(spark, monkeypatch):
    from streamcut.plans import experiments

    monkeypatch.setattr(experiments, "VARIANTS", {k: experiments.VARIANTS[k] for k in ("default", "ties by hash", "held edges last", "hold all unknown targets")})
    run = lambda: sorted(tuple(r) for r in experiments.ablations(spark, "/root/testdata/sf0.001", "nation_flow", 4, ("random",)).collect())
    inside = run()
    monkeypatch.setattr(whole, "EDGES", -1)
    assert inside == run() and len(inside) == 15


def test_a_stream_of_few_vertices_stays_in_one_task(spark, some, monkeypatch):
    """Whether one task runs the batches goes by the vertices, of which it holds a row each, whatever the edges."""
    stream = keep(ordering.stream(some["a"], "random"), "stream")
    n, n_vertices = stream.count(), stream.select(F.explode(F.array("src", "dst")).alias("v")).distinct().count()
    want = {tuple(r) for r in snapshot.run_batches(stream, 6, 90, seed=2).collect()}
    monkeypatch.setattr(snapshot, "WHOLE", n_vertices)
    monkeypatch.setattr(snapshot, "step", lambda *a, **k: pytest.fail("a batch has jobs of its own"))
    assert n > n_vertices and {tuple(r) for r in snapshot.run_batches(stream, 6, 90, seed=2).collect()} == want


def test_snapshot_engine_runs_once_for_all_measures(spark, some):
    placement = api.partition(some["a"], "greedy_indegree", 6, engine="snapshot", batch=90)
    assert "MapInArrow" not in placement.placed._jdf.queryExecution().toString()


def test_an_engine_and_its_reference_share_one_stream(spark, monkeypatch):
    """The query's words are read and its edges put in order once, for the engine and for what it is measured against."""
    from streamcut import registry

    made, stream = [], ordering.stream
    monkeypatch.setattr(ordering, "stream", lambda *a, **k: made.append(a) or stream(*a, **k))
    row = registry.QUERIES["greedy_snapshot_word_next_conv"](spark, "/root/testdata/sf0.001").first()
    assert len(made) == 1 and row.engine == "snapshot" and row.engine_gap > -1


def test_ablations_of_more_edges_than_vertices_start_no_jobs_a_batch(spark, monkeypatch):
    """The snapshot engines go by vertices here too; every variant and engine has its row."""
    from streamcut.plans import experiments

    monkeypatch.setattr(experiments, "VARIANTS", {"default": experiments.VARIANTS["default"]})
    monkeypatch.setattr(snapshot, "WHOLE", 25)  # as many as nations
    monkeypatch.setattr(snapshot, "step", lambda *a, **k: pytest.fail("a batch has jobs of its own"))
    rows = experiments.ablations(spark, "/root/testdata/sf0.001", "nation_flow", 4, ("random",)).collect()
    assert sorted(r.variant for r in rows) == sorted(["default"] * 3 + ["in-degree without the edge itself", "final degrees", "sharded 2", "sharded 8", "sharded 32", "snapshot 5000", "snapshot 50000"])
    assert all(r.replication_factor >= 1 and r.imbalance >= 1 for r in rows)
