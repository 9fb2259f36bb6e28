"""Relational operators around a graph: joins by time, reports over several levels, ranks, sketches, set operations."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, value: str, tie: str | None = None) -> DataFrame:
    """``left`` with the ``value`` of the last row of ``right`` of the same key at or before its time, null if there is none.

    One window over the union of both sides; rows of ``right`` at the same time count, the last of them by ``tie``.
    """
    order = [ts, "_side", *([tie] if tie else [])]
    a = left.select(key, ts, F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias("_value"), *([F.lit(None).cast(right.schema[tie].dataType).alias(tie)] if tie else []), F.struct("*").alias("_row"))
    b = right.select(key, ts, F.lit(0).alias("_side"), F.col(value).alias("_value"), *([tie] if tie else []), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"))
    # A struct around the value tells a null value from no row.
    last = F.last(F.when(F.col("_side") == 0, F.struct("_value")), ignorenulls=True).over(Window.partitionBy(key).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    return a.unionByName(b).withColumn("_last", last).where("_side = 1").select("_row.*", F.col("_last._value").alias(f"asof_{value}"))


def mutual(edges: DataFrame) -> DataFrame:
    """(src, dst): edges of which the other direction exists too, by a self join."""
    a, b = edges.alias("a"), edges.alias("b")
    return a.join(b, F.expr("a.src = b.dst AND a.dst = b.src")).select("a.src", "a.dst")


def first_neighbour(edges: DataFrame) -> DataFrame:
    """(v, dst): each source's least target, by a lateral join."""
    spark = edges.sparkSession
    edges.createOrReplaceTempView("_lateral_edges")
    return spark.sql("SELECT s.v, t.dst FROM (SELECT DISTINCT src AS v FROM _lateral_edges) s, LATERAL (SELECT min(e.dst) AS dst FROM _lateral_edges e WHERE e.src = s.v) t")


def cube_report(df: DataFrame, keys: list[str], name: str = "n") -> DataFrame:
    """Counts by all subsets of the keys; ``level`` tells which keys are summed over."""
    return df.cube(*keys).agg(F.grouping_id().cast("int").alias("level"), F.count("*").alias(name))


def rollup_report(df: DataFrame, keys: list[str], name: str = "n") -> DataFrame:
    """Counts by all leading runs of the keys."""
    return df.rollup(*keys).agg(F.grouping_id().cast("int").alias("level"), F.count("*").alias(name))


def degree_ranks(degrees: DataFrame, by: str = "d") -> DataFrame:
    """(v, d, rank, dense, percent, share): positions of the vertices in falling order of degree.

    Ranks follow from the histogram of degrees, whose rows are few; no window holds the vertices.
    """
    h = degrees.groupBy(by).agg(F.count("*").alias("n"))
    w = Window.orderBy(F.desc(by))  # a row per degree
    total = F.sum("n").over(Window.partitionBy())
    upto = F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0))
    ranked = h.select(by, (upto - F.col("n") + 1).alias("rank"), F.row_number().over(w).cast("long").alias("dense"), F.when(total > 1, (upto - F.col("n")) / (total - 1)).otherwise(F.lit(0.0)).alias("percent"), (upto / total).alias("share"))
    return degrees.select("v", by).join(ranked, by).select("v", by, "rank", "dense", "percent", "share")


def edges_in_both(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("src", "dst").intersect(b.select("src", "dst"))


def edges_only_in(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("src", "dst").exceptAll(b.select("src", "dst"))


def sketches(edges: DataFrame, heavy: int | None = None) -> DataFrame:
    """One row of sketches: distinct sources, quantiles of the out-degree, and the frequency sketch of the targets.

    (approx_sources, out_median, out_p99, target_sketch): sizes are fixed whatever the graph's.
    """
    distinct = edges.agg(F.hll_sketch_estimate(F.hll_sketch_agg("src", F.lit(14))).alias("approx_sources"), F.count_min_sketch("dst", F.lit(0.0005), F.lit(0.99), F.lit(7)).alias("target_sketch"))
    sizes = edges.groupBy("src").agg(F.count("*").alias("n")).agg(F.expr("kll_sketch_get_quantile_bigint(kll_sketch_agg_bigint(n), array(0.5D, 0.99D))").alias("q"))
    return distinct.crossJoin(sizes).select("approx_sources", F.col("q")[0].alias("out_median"), F.col("q")[1].alias("out_p99"), "target_sketch")  # two single rows


def start_ranks(edges: DataFrame) -> DataFrame:
    """(v, rank): equal ranks."""
    v = edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    return v.crossJoin(F.broadcast(v.agg(F.count("*").alias("n")))).select("v", (1 / F.col("n")).alias("rank"))  # one row


def pagerank_step(placed: DataFrame, ranks: DataFrame, damping: float = 0.85) -> tuple[DataFrame, DataFrame]:
    """(v, rank) after a step of a vertex program on placed edges, and one row of what it sent between parts.

    Each part adds up what its edges give a vertex; a copy sends its sum to the vertex's master and gets the new rank
    back.  Messages are therefore the mirrors of vertices in use: the number that the replication factor stands for.
    """
    out = placed.groupBy("src").agg(F.count("*").alias("d"))
    each = placed.join(ranks.withColumnRenamed("v", "src"), "src").join(out, "src").select("part", F.col("dst").alias("v"), (F.col("rank") / F.col("d")).alias("gift"))
    local = each.groupBy("part", "v").agg(F.sum("gift").alias("gift"))
    n = ranks.agg(F.count("*").alias("n"))
    total = local.groupBy("v").agg(F.sum("gift").alias("gift"))
    new = ranks.select("v").join(total, "v", "left").crossJoin(F.broadcast(n))  # one row
    copies = placed.select("part", F.explode(F.array("src", "dst")).alias("v")).distinct().groupBy("v").agg(F.count("*").alias("c"))
    sent = copies.agg(F.sum(F.col("c") - 1).alias("gathered"), F.sum(F.col("c") - 1).alias("scattered"))
    return new.select("v", ((1 - damping) / F.col("n") + damping * F.coalesce("gift", F.lit(0.0))).alias("rank")), sent
