"""Cost and balance measures of placements.  ``placed`` has src, dst and part."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .transforms import degrees


def _copies(placed: DataFrame, by: list[str]) -> DataFrame:
    """(by..., v, part) once each; a partial distinct runs before the shuffle."""
    ends = placed.where("part is not null").select(*by, "part", F.explode(F.array_distinct(F.array("src", "dst"))).alias("v"))
    return ends.distinct()


def replica_sets(placed: DataFrame) -> DataFrame:
    """(v, parts, copies, mirrors)."""
    sets = _copies(placed, []).groupBy("v").agg(F.sort_array(F.collect_list("part")).alias("parts"))
    return sets.select("v", "parts", F.size("parts").cast("long").alias("copies"), (F.size("parts") - 1).cast("long").alias("mirrors"))


def replica_masks(placed: DataFrame) -> DataFrame:
    """(v, mask, copies) as 64-bit masks, for up to 63 parts; a higher part is an error (use ``replica_sets``)."""
    bit = F.when((F.col("part") >= 0) & (F.col("part") < 63), F.expr("shiftleft(1L, part)")).otherwise(F.raise_error(F.concat(F.lit("masks hold parts 0 to 62, not "), F.col("part").cast("string"))).cast("long"))
    bits = placed.where("part is not null").select(F.explode(F.array_distinct(F.array("src", "dst"))).alias("v"), bit.alias("b"))
    return bits.groupBy("v").agg(F.bit_or("b").alias("mask")).withColumn("copies", F.bit_count("mask").cast("long"))


def replication_factor(placed: DataFrame, vertices: DataFrame | None = None) -> DataFrame:
    """One row (n_vertices, copies, replication_factor); isolated vertices of ``vertices`` count with no copy."""
    one = _copies(placed, []).groupBy("v").agg(F.count("*").alias("c"))
    if vertices is not None:
        one = vertices.select("v").distinct().join(one, "v", "left").fillna(0, ["c"])
    return one.agg(F.count("*").alias("n_vertices"), F.coalesce(F.sum("c"), F.lit(0)).alias("copies")).withColumn("replication_factor", F.col("copies") / F.col("n_vertices"))


def part_loads(placed: DataFrame, p: int) -> DataFrame:
    """(part, edges) of all p parts, empty ones included."""
    n = placed.where("part is not null").groupBy("part").agg(F.count("*").alias("edges"))
    parts = placed.sparkSession.range(p).select(F.col("id").cast("int").alias("part"))
    return parts.join(n, "part", "left").fillna(0, ["edges"])


def imbalance(placed: DataFrame, p: int) -> DataFrame:
    """One row (n_edges, max_edges, imbalance): largest load times p over all edges."""
    return part_loads(placed, p).agg(F.sum("edges").alias("n_edges"), F.max("edges").alias("max_edges")).withColumn("imbalance", F.col("max_edges") * F.lit(p) / F.col("n_edges"))


def vertex_cut_feasible(placed: DataFrame, p: int, numerator: int, denominator: int = 1) -> DataFrame:
    """Whether the largest load is strictly below numerator/denominator times the mean, in whole numbers."""
    return imbalance(placed, p).withColumn("feasible", F.col("max_edges") * F.lit(p * denominator) < F.col("n_edges") * F.lit(numerator))


def summary(placed: DataFrame, p: int, by: list[str] | None = None) -> DataFrame:
    """(by..., n_vertices, n_edges, copies, replication_factor, imbalance)."""
    by = by or []
    c = _copies(placed, by).groupBy(*by, "v").agg(F.count("*").alias("c")).groupBy(*by).agg(F.count("*").alias("n_vertices"), F.sum("c").alias("copies"))
    e = placed.where("part is not null").groupBy(*by, "part").agg(F.count("*").alias("e")).groupBy(*by).agg(F.sum("e").alias("n_edges"), F.max("e").alias("max_edges"))
    both = c.join(e, by) if by else c.crossJoin(e)  # two single rows
    return both.select(*by, "n_vertices", "n_edges", "copies", (F.col("copies") / F.col("n_vertices")).alias("replication_factor"), (F.col("max_edges") * F.lit(p) / F.col("n_edges")).alias("imbalance"))


def improvement(metrics: DataFrame, baseline: str = "greedy_affinity", keys: tuple[str, ...] = ("graph", "arrival_order", "p")) -> DataFrame:
    """``metrics`` with the percentage by which each replication factor is below the baseline's."""
    base = metrics.where(F.col("method") == baseline).select(*keys, F.col("replication_factor").alias("_base"))
    return metrics.join(base, list(keys), "left").withColumn("improvement", 100 * (F.col("_base") - F.col("replication_factor")) / F.col("_base")).drop("_base")


def engine_gap(exact: DataFrame, other: DataFrame) -> DataFrame:
    a, b = replication_factor(exact).select(F.col("replication_factor").alias("a")), replication_factor(other).select(F.col("replication_factor").alias("b"))
    return a.crossJoin(b).select((F.col("b") / F.col("a") - 1).alias("gap"))  # two single rows


def load_trace(placed: DataFrame, p: int, every: int) -> DataFrame:
    """(step, max_edges, placed, ratio) after each ``every`` placements: the running ratio that the guard looks at."""
    step = F.floor(F.col("place_seq") / every).cast("long")
    n = placed.groupBy(step.alias("step"), "part").agg(F.count("*").alias("n"))
    steps = placed.select(step.alias("step")).distinct()
    grid = steps.crossJoin(F.broadcast(placed.sparkSession.range(p).select(F.col("id").cast("int").alias("part"))))  # steps x p rows
    run = F.sum("n").over(Window.partitionBy("part").orderBy("step"))
    return grid.join(n, ["step", "part"], "left").fillna(0, ["n"]).withColumn("e", run).groupBy("step").agg(F.max("e").alias("max_edges"), F.sum("e").alias("placed")).withColumn("ratio", F.col("max_edges") * p / F.col("placed"))


def masters(placed: DataFrame, rule: str = "most_edges") -> DataFrame:
    """(v, part): one master copy of each vertex, where most of its edges are ('most_edges') or by hash ('hash')."""
    ends = placed.select("part", F.explode(F.array_distinct(F.array("src", "dst"))).alias("v")).groupBy("v", "part").agg(F.count("*").alias("n"))
    key = F.struct(-F.col("n"), F.col("part")) if rule == "most_edges" else F.struct(F.xxhash64("v", "part"), F.col("part"))
    return ends.groupBy("v").agg(F.min_by("part", key).alias("part"))


def message_count(placed: DataFrame) -> DataFrame:
    """Messages between parts in one step of a vertex program: the number of mirrors."""
    return replica_sets(placed).agg(F.sum("mirrors").alias("messages"))


def degree_distribution(edges: DataFrame) -> DataFrame:
    """(degree, n_vertices, share)."""
    d = degrees(edges).groupBy(F.col("d").alias("degree")).agg(F.count("*").alias("n_vertices"))
    total = d.agg(F.sum("n_vertices").alias("t"))
    return d.crossJoin(F.broadcast(total)).select("degree", "n_vertices", (F.col("n_vertices") / F.col("t")).alias("share"))  # one row


def power_law_alpha(edges: DataFrame, dmin: int = 1, method: str = "mle", degree: str = "d") -> DataFrame:
    """One row (n, alpha): discrete maximum likelihood, or a regression on the log-log histogram."""
    d = degrees(edges).where(F.col(degree) >= dmin)
    if method == "mle":
        return d.agg(F.count("*").alias("n"), F.round(1 + F.count("*") / F.sum(F.log(F.col(degree) / F.lit(dmin - 0.5))), 6).alias("alpha"))
    h = d.groupBy(degree).agg(F.count("*").alias("n"))
    return h.agg(F.sum("n").alias("n"), F.round(-F.regr_slope(F.log("n"), F.log(degree)), 6).alias("alpha"))


def skew_profile(edges: DataFrame) -> DataFrame:
    """One row: coefficient of variation and largest-to-mean ratio of in- and out-degrees over vertices that have any."""
    d = degrees(edges)

    def one(c: str) -> list[Column]:
        x = F.when(F.col(c) > 0, F.col(c))
        return [F.round(F.stddev_pop(x) / F.avg(x), 6).alias(f"cv_{c[2:]}"), F.round(F.max(x) / F.avg(x), 6).alias(f"peak_{c[2:]}")]

    return d.agg(*one("d_in"), *one("d_out"))


def advise(edges: DataFrame) -> DataFrame:
    """One row with a method: little skew: affinity; in-degree clearly more skewed: in-degree; else total degree."""
    s = skew_profile(edges)
    rule = F.when(F.greatest("cv_in", "cv_out") < 0.6, "greedy_affinity").when(F.col("cv_in") > 1.5 * F.col("cv_out"), "greedy_indegree").otherwise("greedy_total_degree")
    return s.withColumn("method", rule)


def approximate_profile(edges: DataFrame, top: int = 10) -> DataFrame:
    """One row from sketches: distinct vertices and median and tail of the out-degree, for graphs too large to count."""
    v = edges.select(F.explode(F.array("src", "dst")).alias("v")).agg(F.approx_count_distinct("v").alias("approx_vertices"))
    q = edges.groupBy("src").count().agg(F.percentile_approx("count", F.array(F.lit(0.5), F.lit(0.99))).alias("out_degree_quantiles"))
    return v.crossJoin(q)  # two single rows
