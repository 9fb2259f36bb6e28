"""Arrival orders.  A stream is the edges with ``arrival`` (position of the source's block) and ``seq`` (of the edge)."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import shuffle_key
from ..plans.scratch import drop, keep
from .transforms import number_rows


def order_random(edges: DataFrame, seed: int = 0) -> DataFrame:
    """(src, arrival): sources in a seeded random order."""
    return number_rows(edges.select("src").distinct(), [shuffle_key("src", seed=seed), F.col("src")], "arrival")


def order_by_time(df: DataFrame, key: str, ts: str, tie: str) -> DataFrame:
    """(src, arrival): sources by their first appearance."""
    first = df.groupBy(F.col(key).cast("long").alias("src")).agg(F.min(F.struct(ts, tie)).alias("_t"))
    return number_rows(first, [F.col(f"_t.{ts}"), F.col(f"_t.{tie}"), F.col("src")], "arrival").drop("_t")


def _neighbours(edges: DataFrame, follow: str) -> DataFrame:
    a = edges.select(F.col("src").alias("u"), F.col("dst").alias("w")).distinct()
    return a if follow == "out" else a.unionByName(a.select(F.col("w").alias("u"), F.col("u").alias("w"))).distinct()


def _sort_key(seed: int, key: str) -> Column:
    return shuffle_key("v", seed=seed) if key == "hash" else F.lit("")


def _roots(near: DataFrame, places: DataFrame) -> DataFrame:
    """(v, place, root): the least place of all vertices from which v can be reached, its own included.

    A search that restarts at the first vertex not yet seen reaches v from just that vertex: an earlier one that reached
    any vertex on the way would have reached v too.  So all trees can grow at once.
    """
    labels = keep(places.select("v", "place", F.col("place").alias("root")), "roots")
    moved = labels
    while True:
        better = moved.join(near, moved["v"] == near["u"]).groupBy(F.col("w").alias("v")).agg(F.min("root").alias("new"))
        step = labels.join(better, "v", "left").select("v", "place", F.least("root", F.coalesce("new", "root")).alias("root"), (F.col("new") < F.col("root")).alias("fell"))
        step = keep(step, "roots")
        moved = step.where("fell").select("v", "root")
        drop(labels)
        labels = step
        if moved.isEmpty():
            return labels.select("v", "place", "root")


def bfs_levels(edges: DataFrame, start: int | None = None, follow: str = "out", seed: int = 0, key: str = "hash") -> DataFrame:
    """(v, tree, depth, rank): breadth-first positions of all vertices; rank orders a level of all trees.

    A tree starts at the first vertex that no earlier tree has reached: ``start`` first, then vertices with out-edges
    before others, in seeded order (``key`` 'hash') or by id ('id').  The trees are found first (``_roots``) and then
    grow together: a level is one join of the frontier with the edges inside a tree and one anti join with the vertices
    already placed, appended to the levels in the shared folder.
    """
    near = keep(_neighbours(edges, follow), "near")
    vertices = near.select(F.explode(F.array("u", "w")).alias("v")).distinct()
    sources = near.select(F.col("u").alias("v")).distinct().withColumn("s", F.lit(0))
    first = F.lit(1) if start is None else F.when(F.col("v") == F.lit(start), 0).otherwise(1)
    ranked = vertices.join(sources, "v", "left").select("v", first.alias("f"), F.coalesce("s", F.lit(1)).alias("s"), _sort_key(seed, key).alias("k"))
    places = keep(number_rows(ranked, [F.col("f"), F.col("s"), F.col("k"), F.col("v")], "place").select("v", "place", "k"), "places")
    roots = keep(_roots(near, places), "trees")
    # Edges inside a tree; most vertices of a sparse graph are in a few trees, those of a bipartite one in many small ones.
    inside = near.join(roots.select(F.col("v").alias("u"), F.col("root").alias("tree")), "u").join(roots.select(F.col("v").alias("w"), F.col("root").alias("tree_w")), "w")
    inside = keep(inside.where("tree = tree_w and u <> w").select("u", "w"), "inside")
    tree = roots.select("v", F.col("root").alias("tree")).join(places.select("v", "k"), "v")
    frontier = keep(roots.where("place = root").select("v", F.col("root").alias("tree"), F.lit(0).alias("depth"), F.col("root").alias("rank")), "level")
    levels, depth = frontier, 0
    while True:
        depth += 1
        found = frontier.join(inside, frontier["v"] == inside["u"]).groupBy(F.col("w").alias("v")).agg(F.min("rank").alias("parent"))
        found = keep(found.join(levels.select("v"), "v", "left_anti").join(tree, "v"), "found")
        n = found.count()
        if not n:
            return levels
        nxt = number_rows(found, [F.col("tree"), F.col("parent"), F.col("k"), F.col("v")], "rank", n)
        frontier = keep(nxt.select("v", "tree", F.lit(depth).alias("depth"), "rank"), "level")
        drop(found)
        levels = levels.unionByName(frontier)


def order_bfs(edges: DataFrame, start: int | None = None, follow: str = "out", seed: int = 0, key: str = "hash") -> DataFrame:
    """(src, arrival) by breadth-first search with restarts; see ``bfs_levels``."""
    levels = bfs_levels(edges, start, follow, seed, key).join(edges.select(F.col("src").alias("v")).distinct(), "v", "left_semi")
    return number_rows(levels, [F.col("tree"), F.col("depth"), F.col("rank")], "arrival").select(F.col("v").alias("src"), "arrival")


def dfs_preorder(src: np.ndarray, dst: np.ndarray, start: int | None, follow: str, key) -> list[int]:
    """Vertices in depth-first preorder, without recursion; neighbours and restarts by ``key``."""
    near: dict[int, list[int]] = {}
    for u, w in zip(src.tolist(), dst.tolist()):
        near.setdefault(u, []).append(w)
        if follow == "both":
            near.setdefault(w, []).append(u)
    rank = {v: k for k, v in enumerate(sorted({*near, *dst.tolist()}, key=key))}
    for u in near:
        near[u] = sorted(set(near[u]), key=rank.__getitem__, reverse=True)
    roots = sorted(near, key=rank.__getitem__) + sorted(set(dst.tolist()) - set(near), key=rank.__getitem__)
    if start is not None:
        roots.insert(0, start)
    seen: set[int] = set()
    out = []
    for r in roots:
        stack = [r]
        while stack:
            v = stack.pop()
            if v in seen:
                continue
            seen.add(v)
            out.append(v)
            stack += [w for w in near.get(v, ()) if w not in seen]
    return out


def order_dfs(edges: DataFrame, start: int | None = None, follow: str = "out", seed: int = 0, key: str = "hash") -> DataFrame:
    """(src, arrival) by depth-first search: inherently sequential, so one task holds the graph (use on graphs that fit)."""
    by = (lambda v: (hashlib.md5(f"{seed}:{v}".encode()).hexdigest(), v)) if key == "hash" else (lambda v: v)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        t = pa.Table.from_batches(held)
        src = t.column("src").to_numpy()
        out = np.array(dfs_preorder(src, t.column("dst").to_numpy(), start, follow, by), dtype=np.int64)
        out = out[np.isin(out, src)]
        yield pa.RecordBatch.from_arrays([pa.array(out), pa.array(np.arange(len(out)))], names=["src", "arrival"])

    return edges.select("src", "dst").repartition(1).mapInArrow(run, "src long, arrival long")


def as_stream(edges: DataFrame, order: DataFrame, seed: int = 0) -> DataFrame:
    """(src, dst, arrival, seq): blocks by arrival, out-edges of a block in seeded random order."""
    placed = edges.select("src", "dst").join(order, "src")
    return number_rows(placed, [F.col("arrival"), shuffle_key("src", "dst", seed=seed), F.col("dst")], "seq")


def stream(edges: DataFrame, order: str = "random", seed: int = 0, **opts) -> DataFrame:
    made = {"random": order_random, "bfs": order_bfs, "dfs": order_dfs}[order](edges, seed=seed, **opts)
    return as_stream(edges, made, seed)
