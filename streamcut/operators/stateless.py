"""Hash placements: pure projections, and the low-degree hash with its degree join."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import bucket, hash32
from .transforms import degrees as degree_table


def edge_hash(edges: DataFrame, p: int, seed: int = 0, mode: str = "directed", algo: str = "md5") -> DataFrame:
    """Part by hash of the edge.  mode: 'directed', 'canonical' (both directions together), 'src' or 'dst' alone."""
    ends = {"directed": ("src", "dst"), "canonical": (F.least("src", "dst"), F.greatest("src", "dst")), "src": ("src",), "dst": ("dst",)}[mode]
    return edges.withColumn("part", bucket(*ends, p=p, seed=seed, algo=algo))


def grid_shape(p: int) -> tuple[int, int]:
    """Rows and columns: the nearest-square factors of p, or a square folded modulo p if those are too lopsided."""
    r = max(k for k in range(1, math.isqrt(p) + 1) if p % k == 0)
    if p // r <= 2 * r:
        return r, p // r
    side = math.isqrt(p - 1) + 1
    return side, -(-p // side)


def constraint_set(cell: int, p: int, shape: tuple[int, int]) -> list[int]:
    """Parts in the cell's row or column, folded modulo p."""
    r, c = shape
    row, col = divmod(cell, c)
    return sorted({(row * c + k) % p for k in range(c)} | {(k * c + col) % p for k in range(r)})


def grid_hash(edges: DataFrame, p: int, shape: tuple[int, int] | None = None, seed: int = 0, pick: str = "intersection") -> DataFrame:
    """Part by hash within the common constraint set of both ends; 'corners' takes one of the two crossing cells."""
    r, c = shape or grid_shape(p)
    cells = r * c
    cell = lambda v: (hash32(v, seed=seed) % cells).cast("int")
    h = hash32("src", "dst", seed=seed + 1)
    if pick == "corners":
        row, col = (lambda v: F.floor(cell(v) / c)), (lambda v: cell(v) % c)
        first, second = row("src") * c + col("dst"), row("dst") * c + col("src")
        return edges.withColumn("part", (F.when(h % 2 == 0, first).otherwise(second) % p).cast("int"))
    sets = F.array(*[F.array(*[F.lit(x) for x in constraint_set(k, p, (r, c))]) for k in range(cells)])
    common = edges.withColumn("_c", F.array_intersect(F.element_at(sets, cell("src") + 1), F.element_at(sets, cell("dst") + 1)))
    return common.withColumn("part", F.element_at("_c", (h % F.size("_c") + 1).cast("int")).cast("int")).drop("_c")


def low_endpoint(du: Column, dv: Column, ties: str = "min_id", seed: int = 0) -> Column:
    """The endpoint of lower degree; ties by smaller id ('min_id'), to the source ('src') or by hash ('hash')."""
    tie = {"min_id": F.least("src", "dst"), "src": F.col("src"), "hash": F.when(hash32("src", "dst", seed=seed + 7) % 2 == 0, F.col("src")).otherwise(F.col("dst"))}[ties]
    return F.when(du < dv, F.col("src")).when(dv < du, F.col("dst")).otherwise(tie)


_OF = {"in": "d_in", "out": "d_out", "total": "d"}


def with_degrees(edges: DataFrame, degree: str = "total", degrees: DataFrame | None = None) -> DataFrame:
    """The edges with du and dv, the degrees of their ends."""
    d = (degree_table(edges) if degrees is None else degrees).select("v", F.col(_OF[degree]).cast("long").alias("n"))
    # Few vertices: the optimiser broadcasts; many: two shuffled joins, in which it splits the partitions of hubs.
    return edges.join(d.select(F.col("v").alias("src"), F.col("n").alias("du")), "src", "left").join(d.select(F.col("v").alias("dst"), F.col("n").alias("dv")), "dst", "left").fillna(0, ["du", "dv"])


def low_degree_hash(edges: DataFrame, p: int, degree: str = "total", ties: str = "min_id", seed: int = 0, degrees: DataFrame | None = None) -> DataFrame:
    """Part by hash of the lower-degree endpoint, with the degrees of the whole graph."""
    placed = with_degrees(edges, degree, degrees).withColumn("_lo", low_endpoint(F.col("du"), F.col("dv"), ties, seed))
    return placed.withColumn("part", bucket("_lo", p=p, seed=seed)).select(*edges.columns, "part")


#: Positions of one block in the running counts: a hub's events are counted block by block, never in one window.
BLOCK = 100_000


def running_count(events: DataFrame, probes: DataFrame, block: int = BLOCK) -> DataFrame:
    """For each probe (v, pos, ...) the number of events (v, pos) at or before its position, as column n.

    Counts are summed by (vertex, block of positions) first; a prefix sum over blocks and a window inside a block give
    the result, so that a hub vertex with a large share of all events is spread over its blocks.
    """
    own = [c for c in probes.columns if c not in ("v", "pos")]
    b = F.floor(F.col("pos") / block).cast("long")
    rows = events.select("v", "pos", F.lit(0).alias("probe"), F.lit(None).cast(probes.select(F.struct("*")).schema[0].dataType).alias("x"))
    rows = rows.unionByName(probes.select("v", "pos", F.lit(1).alias("probe"), F.struct(*probes.columns).alias("x"))).withColumn("b", b)
    inside = F.sum(1 - F.col("probe")).over(Window.partitionBy("v", "b").orderBy("pos", "probe").rowsBetween(Window.unboundedPreceding, 0))
    sums = rows.groupBy("v", "b").agg(F.sum(1 - F.col("probe")).alias("s"))
    before = sums.withColumn("before", F.coalesce(F.sum("s").over(Window.partitionBy("v").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    out = rows.withColumn("inside", inside).where("probe = 1").join(before.select("v", "b", "before"), ["v", "b"])
    return out.select(F.col("x.v").alias("v"), F.col("x.pos").alias("pos"), *[F.col(f"x.{c}").alias(c) for c in own], (F.col("before") + F.col("inside")).cast("long").alias("n"))


def low_degree_hash_online(stream: DataFrame, p: int, degree: str = "total", ties: str = "min_id", seed: int = 0) -> DataFrame:
    """As ``low_degree_hash``, with the degrees seen so far (the current edge included) in stream order ``seq``."""
    ends = {"in": ["dst"], "out": ["src"], "total": ["src", "dst"]}[degree]
    events = None
    for c in ends:
        e = stream.select(F.col(c).alias("v"), F.col("seq").alias("pos"))
        events = e if events is None else events.unionByName(e)
    probes = stream.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.lit(0).alias("side")), F.struct(F.col("dst").alias("v"), F.lit(1).alias("side")))).alias("e"), F.col("seq").alias("pos")).select("e.v", "pos", "e.side")
    n = running_count(events, probes).groupBy(F.col("pos").alias("seq")).agg(F.max(F.when(F.col("side") == 0, F.col("n"))).alias("du"), F.max(F.when(F.col("side") == 1, F.col("n"))).alias("dv"))
    placed = stream.join(n, "seq").withColumn("_lo", low_endpoint(F.col("du"), F.col("dv"), ties, seed))
    return placed.withColumn("part", bucket("_lo", p=p, seed=seed)).select(*stream.columns, "part")
