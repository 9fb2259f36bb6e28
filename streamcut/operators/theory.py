"""Expected replication factors and imbalance, in closed form."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .stateless import low_endpoint, with_degrees
from .transforms import degrees


def occupancy(p: int, n: Column) -> Column:
    """Chance that a given part gets at least one of n hashed edges."""
    return 1 - F.pow(F.lit(1 - 1 / p), n)


def ratio(edges: DataFrame) -> DataFrame:
    """(v, d, ratio): the share of a vertex's neighbours of at least its own degree."""
    e = with_degrees(edges)
    ends = e.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.col("du").alias("d"), F.col("dv").alias("o")), F.struct(F.col("dst").alias("v"), F.col("dv").alias("d"), F.col("du").alias("o")))).alias("x"))
    return ends.groupBy(F.col("x.v").alias("v")).agg(F.max("x.d").alias("d"), F.sum(F.when(F.col("x.d") <= F.col("x.o"), 1).otherwise(0)).alias("up"), F.count("*").alias("n")).select("v", "d", (F.col("up") / F.col("n")).alias("ratio"), (F.col("n") - F.col("up")).alias("below"))


def _mean(copies: DataFrame) -> DataFrame:
    return copies.agg(F.count("*").alias("n_vertices"), F.round(F.avg("c"), 6).alias("expected_rf"))


def expected_rf_low_degree(edges: DataFrame, p: int, form: str = "paper", alpha: float | None = None, law: str = "vertex") -> DataFrame:
    """One row (n_vertices, expected_rf) of the low-degree hash.

    'paper': one own part plus the others hit by the edges to lower neighbours.  'law': the share of lower neighbours
    from a power law with exponent ``alpha`` over the degrees that occur, by vertices or (``law`` 'edge') by edge ends.
    'exact': the number r of distinct hashed neighbours and the presence of an own home under the min-id tie rule.
    """
    if form == "paper":
        r = ratio(edges)
        return _mean(r.select((1 + (p - 1) * occupancy(p, F.col("below"))).alias("c")))
    if form == "law":
        a = alpha if alpha is not None else 2.0
        d = degrees(edges).groupBy("d").agg(F.count("*").alias("n"))
        weight = F.pow(F.col("d").cast("double"), F.lit(-a if law == "vertex" else 1 - a))
        upto = d.withColumn("w", weight).withColumn("s", F.sum("w").over(Window.orderBy("d")))  # a row per degree
        total = d.select(F.sum(weight).alias("t"))
        rows = upto.crossJoin(F.broadcast(total)).select("n", (1 + (p - 1) * occupancy(p, F.col("d") * F.col("s") / F.col("t"))).alias("c"))
        return rows.agg(F.sum("n").alias("n_vertices"), F.round(F.sum(F.col("n") * F.col("c")) / F.sum("n"), 6).alias("expected_rf"))
    e = with_degrees(edges).withColumn("lo", low_endpoint(F.col("du"), F.col("dv")))
    hit = e.select(F.explode(F.array_distinct(F.array("src", "dst"))).alias("v"), "lo").distinct()
    q = occupancy(p, F.col("r"))
    per = hit.groupBy("v").agg(F.max(F.when(F.col("lo") == F.col("v"), 1).otherwise(0)).alias("home"), F.sum(F.when(F.col("lo") != F.col("v"), 1).otherwise(0)).alias("r"))
    return _mean(per.select(F.when(F.col("home") == 1, 1 + (p - 1) * q).otherwise(p * q).alias("c")))


def expected_rf_edge_hash(edges: DataFrame, p: int) -> DataFrame:
    d = edges.select(F.explode(F.array_distinct(F.array("src", "dst"))).alias("v")).groupBy("v").agg(F.count("*").alias("d"))
    return _mean(d.select((p * occupancy(p, F.col("d"))).alias("c")))


def expected_imbalance_hash(p: int, n_edges: int) -> float:
    """About one plus 2.24 standard deviations of a part's load (p near 48)."""
    return 1 + 2.24 * math.sqrt((p - 1) / n_edges)
