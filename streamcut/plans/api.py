"""The public surface: one call per placement, metric tables, and reports."""

from __future__ import annotations

from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import edgecut, greedy, metrics, ordering, schedule, stateless, whole
from ..streaming import snapshot
from .scratch import drop, keep

#: Method -> (needs the stream's order, needs all degrees in advance, kind).
METHODS = {
    "edge_hash": (False, False, "baseline"),
    "grid_hash": (False, False, "baseline"),
    "greedy_affinity": (True, False, "baseline"),
    "low_degree_hash": (False, True, "proposed, offline"),
    "greedy_indegree": (True, False, "proposed"),
    "greedy_total_degree": (True, False, "proposed"),
    "hybrid_threshold": (False, True, "relative"),
}
ENGINES = ("exact", "sharded", "snapshot")


@dataclass
class Placement:
    placed: DataFrame
    p: int
    method: str
    order: str
    schedule: DataFrame | None = None
    params: dict = field(default_factory=dict)
    #: 'stateless' for plain projections; shards: streams that don't see each other, 0 if there are none.
    engine: str = "stateless"
    shards: int = 0

    def replicas(self) -> DataFrame:
        return metrics.replica_sets(self.placed)

    def loads(self) -> DataFrame:
        return metrics.part_loads(self.placed, self.p)

    def masters(self, rule: str = "most_edges") -> DataFrame:
        return metrics.masters(self.placed, rule)

    def metrics(self, graph: str = "") -> DataFrame:
        out = metrics.summary(self.placed, self.p)
        held = self.schedule is not None and self.method == "greedy_total_degree"
        if held:
            late = self.schedule.agg(F.sum((F.col("class") == "postponed").cast("long")).alias("postponed"), F.sum((F.col("place_arrival") == schedule.END).cast("long")).alias("flushed"))
            peak = schedule.buffer_occupancy(self.schedule).agg(F.coalesce(F.max("buffered"), F.lit(0)).alias("peak_buffered"))
            out = out.crossJoin(late).crossJoin(peak)  # single rows
        else:
            out = out.withColumns({c: F.lit(0).cast("long") for c in ("postponed", "flushed", "peak_buffered")})
        return out.select(F.lit(graph).alias("graph"), F.lit(self.order).alias("arrival_order"), F.lit(self.method).alias("method"), F.lit(self.p).alias("p"), F.lit(self.engine).alias("engine"), F.lit(self.shards).alias("shards"), *out.columns)


def make_schedule(stream: DataFrame, method: str, p: int, rows: int | None = None, **opts) -> DataFrame:
    if method == "greedy_affinity":
        return schedule.plain_schedule(stream)
    if method == "greedy_indegree":
        return schedule.indegree_schedule(stream, opts.get("count_before", True)) if opts.get("degree", "in") == "in" and "degrees" not in opts else schedule.degree_schedule(stream, opts.get("degrees"), opts.get("degree", "total"))
    return schedule.total_degree_schedule(stream, p, opts.get("hub_threshold"), opts.get("guard_scope", "direct"), opts.get("release", "first"), opts.get("flush", "end"), rows)


#: Options of the greedy methods, by what they act on.
_COMMON = {"guard", "tie"}
_OWN = {"greedy_affinity": set(), "greedy_indegree": {"degree", "degrees", "count_before"}, "greedy_total_degree": {"hub_threshold", "guard_scope", "release", "flush"}}
_ENGINE = {"exact": set(), "sharded": {"shards"}, "snapshot": {"batch"}}


def partition(edges: DataFrame, method: str, p: int, order: str = "random", engine: str = "exact", seed: int = 0, stream: DataFrame | None = None, **opts) -> Placement:
    """Places ``edges`` (src, dst).  engine: 'exact', 'sharded' (opts: shards) or 'snapshot' (opts: batch), whatever the size.

    ``stream``: the kept ``ordering.stream`` of the edges by ``order``, ``seed`` and its options, where the caller has it.

    An option that the method or the engine doesn't know is an error; so is the total-degree method on snapshots, which
    can't hold edges back.
    """
    if method not in METHODS:
        raise ValueError(f"unknown method {method}; known: {sorted(METHODS)}")
    if engine not in ENGINES:
        raise ValueError(f"unknown engine {engine}; known: {ENGINES}")
    if not METHODS[method][0]:
        call = edgecut.hybrid_threshold if method == "hybrid_threshold" else getattr(stateless, method)
        return Placement(call(edges, p, seed=seed, **opts), p, method, order, None, opts)
    stream_opts = {k: opts.pop(k) for k in ("start", "follow", "key") if k in opts}
    known = ({"guard"} if engine == "snapshot" else _COMMON | _OWN[method]) | _ENGINE[engine]
    if odd := sorted(set(opts) - known):
        raise ValueError(f"{method} on the {engine} engine takes no {odd}; it takes {sorted(known)}")
    if engine == "snapshot" and (method == "greedy_total_degree" or opts.get("guard", 1.1) is None):
        raise ValueError("the snapshot engine places greedy_affinity and greedy_indegree, with a guard")
    stream = keep(ordering.stream(edges, order, seed, **stream_opts), "stream") if stream is None else stream
    if engine == "snapshot":
        out = snapshot.run_batches(stream, p, opts.get("batch", 100_000), seed=seed, guard=opts.get("guard", 1.1), degree_aware=method != "greedy_affinity")
        return Placement(keep(out, "placed"), p, method, order, None, opts, engine)
    s = keep(make_schedule(stream, method, p, stream.count(), **opts), "schedule")
    guard, shards = opts.get("guard", 1.1), 0
    if engine == "sharded":
        shards = opts.get("shards") or int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        placed = greedy.sharded(s, p, shards, guard, opts.get("tie", "rotate"), seed)
    else:
        placed = greedy.exact(s, p, guard, opts.get("tie", "lowest"), seed)
    # One evaluation: the sequential pass would run again for each measure.
    return Placement(keep(placed, "placed"), p, method, order, s, opts, engine, shards)


FIVE = ("edge_hash", "grid_hash", "greedy_affinity", "greedy_indegree", "greedy_total_degree")


def disjoint(graphs: dict[str, DataFrame]) -> DataFrame:
    """(src, dst): the graphs side by side as one graph; the last six bits of a vertex are its graph's number."""
    if len(graphs) > 64:
        raise ValueError("at most 64 graphs at once")
    out = None
    for k, edges in enumerate(graphs.values()):
        e = _own(edges, k)
        out = e if out is None else out.unionByName(e)
    return out


def _own(edges: DataFrame, k: int) -> DataFrame:
    own = lambda c: F.shiftleft(F.xxhash64(F.lit(k), F.col(c)), 6).bitwiseOR(F.lit(k)).alias(c)
    return edges.select(own("src"), own("dst"))


ORDER = ("place_arrival", "phase", "seq")


class Runs:
    """Runs of the greedy methods for ``greedy.grid_of_runs``, collected as projections of shared prepasses."""

    def __init__(self):
        self.runs: list[greedy.Run] = []
        self.labels: list[tuple] = []
        self.rows: DataFrame | None = None

    def _add(self, rows: DataFrame, labels: list[tuple], run: greedy.Run) -> None:
        """Rows of one run for each graph of a disjoint union; ``labels`` by the graph's number."""
        first = len(self.runs)
        self.runs += [run] * len(labels)
        self.labels += labels
        own = rows.select((F.col("src").bitwiseAND(63) + first).cast("int").alias("run"), "src", "dst", "seq", "cmp", "guarded", "place_arrival", "phase")
        self.rows = own if self.rows is None else self.rows.unionByName(own)

    def plain(self, schedule: DataFrame, labels: list[tuple], run: greedy.Run) -> None:
        """A method without buffers: a schedule with ``cmp``."""
        self._add(schedule.withColumns({"guarded": F.lit(True), "place_arrival": F.col("arrival"), "phase": F.lit(1)}), labels, run)

    def method(self, base: DataFrame, method: str, labels: list[tuple], run: greedy.Run, hub_threshold: int | None = None, guard_scope: str = "direct", release: str = "first") -> None:
        """``base``: ``schedule.total_degree_base`` with the same ``release``; it serves all methods and numbers of parts."""
        if method == "greedy_total_degree":
            self._add(schedule.total_degree_rows(base, run.p, hub_threshold, guard_scope, release), labels, run)
        else:
            self.plain(base.withColumn("cmp", F.col("cmp_in") if method == "greedy_indegree" else F.lit(0)), labels, run)

    def measures(self, names: str) -> DataFrame:
        """``names``: the labels' columns; with n_vertices, n_edges, copies, p, replication_factor and imbalance."""
        spark = self.rows.sparkSession
        done = keep(greedy.grid_of_runs(self.rows, self.runs, ORDER), "runs")
        labels = spark.createDataFrame([(k, r.p, *x) for k, (r, x) in enumerate(zip(self.runs, self.labels))], f"run int, p int, {names}")
        out = done.join(F.broadcast(labels), "run").drop("run")  # a row a run
        return out.withColumn("replication_factor", F.col("copies") / F.col("n_vertices")).withColumn("imbalance", F.col("max_edges") * F.col("p") / F.col("n_edges")).drop("max_edges")


#: Edges of small graphs whose runs are started together, and waves of larger ones that may be under way.
WAVE, LARGE = 12_000_000, 3


class WholeRuns:
    """Runs on graphs that fit a task (``operators.whole``): rows of measures with the labels given."""

    def __init__(self, spark: SparkSession, names: str, seed: int = 0):
        self.spark, self.names, self.seed = spark, names, seed
        self.labels: list[tuple] = []
        self.rows: list[tuple] = []
        self.wave: list[tuple[DataFrame, int, dict[str, list[whole.Job]]]] = []
        self.pool = ThreadPoolExecutor(16)
        self.running: list[tuple[list[Future], list[DataFrame], bool]] = []
        self.profile = whole.alone(spark)

    def add(self, edges: DataFrame, n: int, jobs: list[tuple[str, tuple, whole.Job]]) -> None:
        """``edges``: a kept table, dropped once its runs are done; ``jobs``: (order, labels, job without its number)."""
        todo: dict[str, list[whole.Job]] = {}
        for o, label, job in jobs:
            todo.setdefault(o, []).append(replace(job, number=len(self.labels)))
            self.labels.append((job.run.p, *label))
        self.wave.append((edges, n, todo))
        if sum(n for _, n, _ in self.wave) >= WAVE:
            self.start()

    def start(self) -> None:
        """Runs the graphs at hand while the caller writes the next ones; a wave begins when the one before is done.

        A graph of ``WAVE`` edges or more doesn't wait if its tasks can have executors for themselves: they take turns.
        """
        large = self.profile is not None and all(n >= WAVE for _, n, _ in self.wave)
        while len(self.running) >= LARGE or not large and any(not x for *_, x in self.running):
            self.wait()
        tables = [e for e, _, _ in self.wave]

        def kept(graph: DataFrame) -> DataFrame:
            tables.append(keep(graph, "graph"))
            return tables[-1]

        calls = [c for e, n, todo in self.wave for c in whole.measures(e, n, todo, self.seed, self.profile if large else None, kept)]
        self.running.append(([self.pool.submit(c) for c in calls], tables, large))
        self.wave = []

    def wait(self) -> None:
        done, tables, _ = self.running.pop(0)
        self.rows += [tuple(r) for rows in done for r in rows.result()]  # a row a run
        drop(*tables)

    def measures(self) -> DataFrame:
        self.start()
        while self.running:
            self.wait()
        self.pool.shutdown()
        rows = [(*self.labels[r[0]], *r[1:4], r[3] / r[1], r[4] * self.labels[r[0]][0] / r[2]) for r in self.rows]
        return self.spark.createDataFrame(rows, f"p int, {self.names}, n_vertices long, n_edges long, copies long, replication_factor double, imbalance double")


_COLUMNS = ["graph", "arrival_order", "method", "p", "n_vertices", "n_edges", "copies", "replication_factor", "imbalance"]


def compare(graphs: dict[str, DataFrame], orders: tuple[str, ...] = ("random", "bfs", "dfs"), methods: tuple[str, ...] = FIVE, ps: tuple[int, ...] = (48,), seed: int = 0, guard: float | None = 1.1, tie: str = "lowest", **opts) -> DataFrame:
    """A row of measures for each (graph, order, method, p), with the improvement over greedy affinity.

    A graph that fits a task is written once and read by the tasks that run its streams.  Larger ones are put side by side as one
    graph, so that each order and the prepass are computed once for all of them; their greedy runs go through one plan, a task
    per run, and return their measures rather than their edges.  Both ways give the same measures.
    """
    if len(graphs) > 64:
        raise ValueError("at most 64 graphs at once")
    spark = next(iter(graphs.values())).sparkSession
    inside = all(m in METHODS and (METHODS[m][0] or m in whole.HASHES) for m in methods) and (tie == "lowest" or len(graphs) == 1)
    runs, large = WholeRuns(spark, "graph string, arrival_order string, method string", seed), {}
    for k, (name, edges) in enumerate(graphs.items()):
        e = keep(_own(edges, k), "edges")
        n = e.count()
        if not inside or n > whole.EDGES:
            large[k] = e
            continue
        jobs = [(o, (name, o, m), whole.Job(0, m, greedy.Run(p, guard, tie, seed), **opts)) for o in orders for m in methods if METHODS[m][0] for p in ps]
        # Stateless: the same in all orders.
        runs.add(e, n, jobs + [(orders[0], (name, None, m), whole.Job(0, m, greedy.Run(p, guard, tie, seed))) for m in methods if not METHODS[m][0] for p in ps])
    found = runs.measures()
    every = F.when(F.col("arrival_order").isNull(), F.array(*[F.lit(o) for o in orders])).otherwise(F.array("arrival_order"))
    tables = [found.withColumn("arrival_order", F.explode(every)).select(_COLUMNS)]
    if large:
        tables += _side_by_side(list(graphs), large, orders, methods, ps, seed, guard, tie, **opts)
    table = tables[0]
    for t in tables[1:]:
        table = table.unionByName(t.select(_COLUMNS))
    return metrics.improvement(keep(table, "metrics")) if "greedy_affinity" in methods else table


def _side_by_side(names: list[str], large: dict[int, DataFrame], orders: tuple[str, ...], methods: tuple[str, ...], ps: tuple[int, ...], seed: int, guard: float | None, tie: str, **opts) -> list[DataFrame]:
    edges, tables = None, []
    for e in large.values():
        edges = e if edges is None else edges.unionByName(e)
    greedy_methods, runs = [m for m in methods if METHODS[m][0]], Runs()
    if greedy_methods:
        # The orders are independent jobs: run side by side, they fill the gaps of each other's small steps.
        def prepass(o: str) -> DataFrame:
            return keep(schedule.total_degree_base(keep(ordering.stream(edges, o, seed), "stream"), opts.get("release", "first")), "base")

        with ThreadPoolExecutor(len(orders)) as pool:
            bases = list(pool.map(prepass, orders))
        for o, base in zip(orders, bases):
            for m in greedy_methods:
                for p in ps:
                    runs.method(base, m, [(g, o, m) for g in names], greedy.Run(p, guard, tie, seed), **opts)
        tables.append(runs.measures("graph string, arrival_order string, method string"))
    for m in (m for m in methods if not METHODS[m][0]):
        for p in ps:
            # Stateless: the same in all orders.
            placed = getattr(stateless, m)(edges, p, seed=seed).select("src", "dst", "part", F.col("src").bitwiseAND(63).alias("g"))
            name = F.element_at(F.array(*[F.lit(n) for n in names]), F.col("g").cast("int") + 1)
            one = metrics.summary(placed, p, ["g"]).withColumns({"graph": name, "method": F.lit(m), "p": F.lit(p), "arrival_order": F.explode(F.array(*[F.lit(o) for o in orders]))})
            tables.append(one.drop("g"))
    return tables


def report(table: DataFrame, value: str = "imbalance") -> DataFrame:
    """A row per graph, order and p, a column per method."""
    return table.groupBy("graph", "arrival_order", "p").pivot("method").agg(F.round(F.first(value), 5))


def theorem_check(edges: DataFrame, p: int, seeds: int) -> DataFrame:
    """One row (mean, stddev, runs): replication factors of the low-degree hash over many seeds."""
    from ..functions.hashing import text_of

    e = stateless.with_degrees(edges).withColumn("lo", stateless.low_endpoint(F.col("du"), F.col("dv"))).select("src", "dst", "lo", F.explode(F.sequence(F.lit(0), F.lit(seeds - 1))).alias("seed"))
    part = F.conv(F.substring(F.md5(text_of("seed", "lo").cast("binary")), 1, 8), 16, 10).cast("long") % p
    placed = e.withColumn("part", part)
    rf = metrics._copies(placed, ["seed"]).groupBy("seed").agg((F.count("*") / F.countDistinct("v")).alias("rf"))
    return rf.agg(F.avg("rf").alias("mean"), F.stddev_samp("rf").alias("stddev"), F.count("*").alias("runs"))
