"""The experiment workloads: reports over graphs, arrival orders, methods, numbers of parts and exponents.

All take a folder of the given tables.  The number of parts is 48 unless it is what is varied.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from functools import partial

from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from ..operators import greedy, metrics, ordering, schedule, whole
from ..sources import graphs, zipf
from ..streaming import snapshot
from . import api
from .scratch import drop, keep

#: Graphs of the replication and imbalance reports: skewed on both sides, to the source, to the target, and not at all.
REAL = ("word_next_doc", "word_next_conv", "word_doc", "doc_word", "conv_word", "user_next", "order_part")
PARTS = (4, 8, 16, 32, 48, 64, 96, 128)
GREEDY = ("greedy_affinity", "greedy_indegree", "greedy_total_degree")


def _named(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> dict[str, DataFrame]:
    return {n: graphs.edges(spark, sf_dir, n) for n in names}


def vertices_for(spark: SparkSession, sf_dir: str) -> int:
    """A million vertices at scale factor one, as the customers tell the scale."""
    return max(500, graphs.load(spark, sf_dir, "customer").count() * 20 // 3)


def synthetic(spark: SparkSession, sf_dir: str, pairs: tuple[tuple[float, float], ...] = zipf.PAIRS) -> dict[str, DataFrame]:
    n = vertices_for(spark, sf_dir)
    return {f"zipf_{a}_{b}": zipf.zipf_graph(spark, n, a, b) for a, b in pairs}


def replication(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Replication factor, improvement and imbalance of five methods on the named graphs in three orders."""
    return api.compare(_named(spark, sf_dir, REAL))


def imbalance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The imbalance tables: a row per graph and order, a column per method."""
    return api.report(api.compare(_named(spark, sf_dir, REAL)), "imbalance")


def exponents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pairs of exponents in three orders, five methods, with the exponents as columns."""
    x = F.split("graph", "_")
    return api.compare(synthetic(spark, sf_dir)).withColumns({"alpha": x[1].cast("double"), "beta": x[2].cast("double")})


def exponent_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(alpha, beta, part_of_collection, edges, improvement of either method): how the gain moves with the exponents."""
    x = F.split("graph", "_")
    t = api.compare(synthetic(spark, sf_dir), orders=("random",), methods=GREEDY).withColumns({"alpha": x[1].cast("double"), "beta": x[2].cast("double")})
    side = F.when(F.col("alpha") >= F.col("beta"), "in-degree at least as skewed").otherwise("out-degree more skewed")
    return t.groupBy("alpha", "beta", side.alias("collection"), "n_edges").pivot("method", list(GREEDY)).agg(F.first("replication_factor").alias("rf"), F.first("improvement").alias("gain"))


def parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The largest graph in three orders, over numbers of parts."""
    return api.compare(_named(spark, sf_dir, ("word_next_doc",)), methods=GREEDY, ps=PARTS)


def out_skew(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Graphs whose out-degree is more skewed than their in-degree, where in-degrees alone mislead."""
    return api.compare(_named(spark, sf_dir, ("word_doc",)) | synthetic(spark, sf_dir, tuple(x for x in zipf.PAIRS if x[0] < x[1])))


def theorem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The low-degree hash over many seeds against its expectations, in three forms."""
    from ..operators import theory

    e = keep(graphs.edges(spark, sf_dir, "nation_flow").unionByName(graphs.edges(spark, sf_dir, "host_link")).distinct(), "edges")
    forms = [theory.expected_rf_low_degree(e, 8, f, alpha=2.0).select(F.lit(f).alias("form"), "expected_rf") for f in ("paper", "law", "exact")]
    out = forms[0].unionByName(forms[1]).unionByName(forms[2])
    return out.crossJoin(F.broadcast(api.theorem_check(e, 8, 50)))  # one row


#: Variants of the exact engine: name -> (methods, options).
VARIANTS = {
    "default": (GREEDY, {}),
    "no guard": (GREEDY, {"guard": None}),
    "guard 1.02": (GREEDY, {"guard": 1.02}),
    "guard 1.5": (GREEDY, {"guard": 1.5}),
    "ties by hash": (GREEDY, {"tie": "hash"}),
    "guard on held edges too": (GREEDY[2:], {"guard_scope": "all"}),
    "guard on no edge": (GREEDY[2:], {"guard_scope": "none"}),
    "held edges last": (GREEDY[2:], {"release": "last"}),
    "hold all unknown targets": (GREEDY[2:], {"hub_threshold": 0}),
    "hold nothing": (GREEDY[2:], {"hub_threshold": 1 << 60}),
}


#: Engines of the ablations that run at the same time, besides the variants of the exact one.
ENGINES_AT_ONCE = 2


def ablations(spark: SparkSession, sf_dir: str, graph: str = "word_next_conv", p: int = 16, orders: tuple[str, ...] = ("random", "bfs")) -> DataFrame:
    """(variant, arrival_order, method, replication_factor, imbalance): guard, scope, ties, threshold, release, estimate, engine."""
    edges = keep(api.disjoint({graph: graphs.edges(spark, sf_dir, graph)}), "edges")
    n = edges.count()
    names = "variant string, arrival_order string, method string"
    variants = partial(_variants_in_tasks, spark, edges, n) if n <= whole.EDGES else partial(_variants_as_plans, edges)

    def measured(placed: DataFrame) -> Row:
        table = keep(placed, "placed")
        row = metrics.summary(table, p).select("replication_factor", "imbalance").first()
        drop(table)
        return row

    # The variants are few long tasks, and so are most engines: side by side, they fill each other's gaps.
    with ThreadPoolExecutor(1 + ENGINES_AT_ONCE) as pool:
        runs = pool.submit(variants, p, orders, names)
        stream = keep(ordering.stream(edges, "random"), "stream")
        plain = keep(schedule.indegree_schedule(stream), "schedule")
        engines = {f"sharded {k}": partial(greedy.sharded, plain, p, k) for k in (2, 8, 32)} | {f"snapshot {k}": partial(snapshot.run_batches, stream, p, k) for k in (5_000, 50_000)}
        rows = pool.map(lambda place: measured(place()), engines.values())
        others = [(tag, "random", "greedy_indegree", *row) for tag, row in zip(engines, rows)]
        out = runs.result().select("variant", "arrival_order", "method", "replication_factor", "imbalance")
    return out.unionByName(spark.createDataFrame(others, "variant string, arrival_order string, method string, replication_factor double, imbalance double"))


def _variants_in_tasks(spark: SparkSession, edges: DataFrame, n: int, p: int, orders: tuple[str, ...], names: str) -> DataFrame:
    runs, jobs = api.WholeRuns(spark, names), []
    table = keep(edges, "edges")  # dropped with its runs
    for o in orders:
        for name, (methods, opts) in VARIANTS.items():
            run = greedy.Run(p, **{k: v for k, v in opts.items() if k in ("guard", "tie")})
            jobs += [(o, (name, o, m), whole.Job(0, m, run, **{k: v for k, v in opts.items() if k not in ("guard", "tie")})) for m in methods]
        jobs.append((o, ("in-degree without the edge itself", o, "greedy_indegree"), whole.Job(0, "greedy_indegree", greedy.Run(p), count_before=False)))
        jobs.append((o, ("final degrees", o, "greedy_indegree"), whole.Job(0, "final_degrees", greedy.Run(p))))
    runs.add(table, n, jobs)
    return runs.measures()


def _variants_as_plans(edges: DataFrame, p: int, orders: tuple[str, ...], names: str) -> DataFrame:
    runs = api.Runs()
    for o in orders:
        stream = keep(ordering.stream(edges, o), "stream")
        bases = {r: keep(schedule.total_degree_base(stream, r), "base") for r in ("first", "last")}
        for name, (methods, opts) in VARIANTS.items():
            run = greedy.Run(p, **{k: v for k, v in opts.items() if k in ("guard", "tie")})
            for m in methods:
                runs.method(bases[opts.get("release", "first")], m, [(name, o, m)], run, **{k: v for k, v in opts.items() if k not in ("guard", "tie")})
        runs.plain(schedule.indegree_schedule(stream, False), [("in-degree without the edge itself", o, "greedy_indegree")], greedy.Run(p))
        runs.plain(schedule.degree_schedule(stream), [("final degrees", o, "greedy_indegree")], greedy.Run(p))
    return runs.measures(names)


def buffer_bounds(spark: SparkSession, sf_dir: str, p: int = 16) -> DataFrame:
    """(max_buffer, n_vertices, copies, replication_factor, imbalance): the total-degree method with a bounded buffer."""
    stream = keep(ordering.stream(graphs.edges(spark, sf_dir, "word_next_conv")), "stream")
    out = None
    for bound in (0, 100, 1000, 10_000, 1 << 40):
        m = metrics.summary(keep(greedy.bounded_total_degree(stream, p, bound), "placed"), p).withColumn("max_buffer", F.lit(bound).cast("long"))
        out = m if out is None else out.unionByName(m)
    return out
