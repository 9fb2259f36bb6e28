"""Edge-cut measures and the edge-cut and hybrid relatives of the vertex-cut methods."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import bucket
from .transforms import degrees, undirect


def hash_vertices(edges: DataFrame, p: int, seed: int = 0) -> DataFrame:
    """(v, part) by hash of the vertex."""
    v = edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    return v.withColumn("part", bucket("v", p=p, seed=seed))


def edge_cut(edges: DataFrame, vparts: DataFrame) -> DataFrame:
    """One row (n_edges, cut_edges)."""
    a, b = vparts.select(F.col("v").alias("src"), F.col("part").alias("pu")), vparts.select(F.col("v").alias("dst"), F.col("part").alias("pv"))
    return edges.join(a, "src").join(b, "dst").agg(F.count("*").alias("n_edges"), F.sum((F.col("pu") != F.col("pv")).cast("long")).alias("cut_edges"))


def vertex_balance(vparts: DataFrame, p: int, xi_num: int = 1, xi_den: int = 10) -> DataFrame:
    """One row (n_vertices, max_vertices, balance, feasible): largest part at most (1 + xi) of the mean, in whole numbers."""
    n = vparts.groupBy("part").agg(F.count("*").alias("n")).agg(F.sum("n").alias("n_vertices"), F.max("n").alias("max_vertices"))
    return n.withColumn("balance", F.col("max_vertices") * p / F.col("n_vertices")).withColumn("feasible", F.col("max_vertices") * F.lit(p * xi_den) <= F.col("n_vertices") * F.lit(xi_den + xi_num))


def _vertex_stream(edges: DataFrame, order: DataFrame) -> DataFrame:
    """(v, arrival, near): vertices with their neighbours; those without a block come last, by id."""
    near = undirect(edges).groupBy(F.col("src").alias("v")).agg(F.collect_list("dst").alias("near"))
    return near.join(order.withColumnRenamed("src", "v"), "v", "left").withColumn("late", F.col("arrival").isNull())


def _edge_cut_greedy(edges: DataFrame, order: DataFrame, p: int, rule: str, gamma: float = 1.5) -> DataFrame:
    n, m = edges.select(F.explode(F.array("src", "dst")).alias("v")).distinct().count(), edges.count()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, size = {}, [0] * p
        room = n / p * 1.1 + 1
        scale = m * p ** (gamma - 1) / max(1, n) ** gamma
        for b in batches:
            out = []
            for v, near in zip(b.column("v").to_pylist(), b.column("near").to_pylist()):
                held = [0] * p
                for w in near:
                    if w in part:
                        held[part[w]] += 1
                if rule == "linear":
                    score = [held[k] * (1 - size[k] / room) for k in range(p)]
                else:
                    score = [held[k] - scale * gamma * size[k] ** (gamma - 1) if size[k] < room else float("-inf") for k in range(p)]
                k = min(range(p), key=lambda k: (-score[k], size[k], k))
                part[v] = k
                size[k] += 1
                out.append(k)
            yield pa.RecordBatch.from_arrays([b.column("v"), pa.array(out, pa.int32())], names=["v", "part"])

    rows = _vertex_stream(edges, order)
    return rows.repartition(1).sortWithinPartitions("late", "arrival", "v").select("v", "near").mapInArrow(run, "v long, part int")


def edge_cut_linear_greedy(edges: DataFrame, order: DataFrame, p: int) -> DataFrame:
    """Linear deterministic greedy: neighbours present, weighted by the part's free room."""
    return _edge_cut_greedy(edges, order, p, "linear")


def edge_cut_interpolated(edges: DataFrame, order: DataFrame, p: int, gamma: float = 1.5) -> DataFrame:
    """Neighbours present less the marginal cost of the part's size to the power gamma."""
    return _edge_cut_greedy(edges, order, p, "interpolated", gamma)


def hybrid_threshold(edges: DataFrame, p: int, threshold: int = 100, seed: int = 0) -> DataFrame:
    """Edges into targets of low in-degree go by the target, those into hubs by the source."""
    d = degrees(edges).select(F.col("v").alias("dst"), "d_in")
    placed = edges.join(d, "dst")
    return placed.withColumn("part", F.when(F.col("d_in") <= threshold, bucket("dst", p=p, seed=seed)).otherwise(bucket("src", p=p, seed=seed))).select("src", "dst", "part")
