"""Greedy methods on Spark: the exact engine, many runs at once, and independent shards.

A schedule (``operators.schedule``) fixes the order and the degree comparisons; the kernel keeps only replica masks and
loads.  The exact engine is one logical stream and so one task: it is the reference that the others are measured
against.  ``sharded`` runs one stream per shard; its loss in replication is what ``metrics.engine_gap`` reports.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import schedule as S
from .kernel import Buffered, Placer

_FIELDS = ["src", "dst", "arrival", "seq", "place_seq", "class", "part"]
PLACED = "src long, dst long, arrival long, seq long, place_seq long, class string, part int"


def _ratio(guard: float | str | None) -> tuple[int, int] | None:
    if guard is None:
        return None
    f = Fraction(str(guard))
    return f.numerator, f.denominator


def _place(placer: Placer, batch: pa.RecordBatch | pa.Table) -> pa.Array:
    columns = [batch.column(n).to_pylist() for n in ("src", "dst", "cmp", "guarded", "seq")]
    skips = batch.column("dropped").to_pylist() if "dropped" in batch.schema.names else None
    return pa.array(placer.run(*columns, skips), pa.int32())


def exact(schedule: DataFrame, p: int, guard: float | None = 1.1, tie: str = "lowest", seed: int = 0, affinity_only: bool = False) -> DataFrame:
    """All edges as one stream, in one task, in placement order."""
    ratio = _ratio(guard)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        placer = Placer(p, ratio, tie, seed)
        for b in batches:
            yield pa.RecordBatch.from_arrays([*(b.column(n) for n in _FIELDS[:-1]), _place(placer, b)], names=_FIELDS)

    rows = schedule.withColumn("cmp", F.lit(0)) if affinity_only else schedule
    return rows.repartition(1).sortWithinPartitions("place_seq").mapInArrow(run, PLACED)


def _streams(batches: Iterator[pa.RecordBatch], key: str, start) -> Iterator[tuple[pa.RecordBatch, Placer, pa.Array]]:
    """(rows, placer, parts) of streams that follow each other, each with a placer made by ``start`` from its first rows."""
    placer, current = None, None
    for b in batches:
        if not b.num_rows:
            continue
        which = b.column(key).dictionary_encode().indices.to_numpy()
        cuts = [0, *(np.flatnonzero(np.diff(which)) + 1).tolist(), len(which)]
        for lo, hi in zip(cuts, cuts[1:]):
            part = b.slice(lo, hi - lo)
            if (mark := part.column(key)[0].as_py()) != current:
                placer, current = start(part), mark
            yield part, placer, _place(placer, part)


def sharded(schedule: DataFrame, p: int, shards: int, guard: float | None = 1.1, tie: str = "rotate", seed: int = 0) -> DataFrame:
    """One independent stream per shard of sources, each with its own replica sets and loads.

    The sum of the shards' largest loads is at most guard * mean + shards, so balance holds globally as well.  ``tie``:
    'rotate' breaks ties by a hash that differs by shard, so that the shards don't all fill part 0 first; 'hash' by one
    that is the same for all; 'lowest' by the lowest part.
    """
    if tie not in ("rotate", "hash", "lowest"):
        raise ValueError(f"unknown tie rule {tie}")
    ratio = _ratio(guard)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def start(row: pa.RecordBatch) -> Placer:
            return Placer(p, ratio, "lowest" if tie == "lowest" else "hash", seed + (row.column("shard")[0].as_py() if tie == "rotate" else 0))

        for part, _, parts in _streams(batches, "shard", start):
            yield pa.RecordBatch.from_arrays([*(part.column(n) for n in _FIELDS[:-1]), parts], names=_FIELDS)

    rows = schedule.withColumn("shard", F.pmod(F.xxhash64("src", F.lit(seed)), F.lit(shards)).cast("int"))
    # By number: hashes of few shards meet in a task, of two shards in one.
    return rows.repartitionById(shards, F.col("shard")).sortWithinPartitions("shard", "place_seq").mapInArrow(run, PLACED)


@dataclass(frozen=True)
class Run:
    """One stream of ``grid_of_runs``."""

    p: int
    guard: float | None = 1.1
    tie: str = "lowest"
    seed: int = 0


MEASURES = "run int, n_vertices long, n_edges long, copies long, max_edges long"


def grid_of_runs(schedules: DataFrame, runs: list[Run], order: tuple[str, ...] = ("place_seq",)) -> DataFrame:
    """Measures of many exact streams, a row per run that has edges.

    ``schedules``: rows (run, src, dst, seq, cmp, guarded) and the columns of ``order``; ``run`` is a place in ``runs``.  A
    run streams through its task in order; the task holds its replica masks, loads and one batch.
    """
    hashed = any(r.tie == "hash" for r in runs)

    def start(part: pa.RecordBatch) -> Placer:
        r = runs[part.column("run")[0].as_py()]
        return Placer(r.p, _ratio(r.guard), r.tie, r.seed)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def row(number: int, placer: Placer) -> pa.RecordBatch:
            values = (number, len(placer.at), placer.placed, sum(m.bit_count() for m in placer.at.values()), placer.top)
            return pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(values, (pa.int32(), *[pa.int64()] * 4))], names=["run", "n_vertices", "n_edges", "copies", "max_edges"])

        number, placer = None, None
        for part, now, _ in _streams(batches, "run", start):
            if now is not placer:
                if placer is not None:
                    yield row(number, placer)
                number, placer = part.column("run")[0].as_py(), now
        if placer is not None:
            yield row(number, placer)

    rows = schedules.select("run", *order, "src", "dst", "seq", F.col("cmp").cast("byte").alias("cmp"), "guarded")
    rows = rows.repartition(len(runs), "run").sortWithinPartitions("run", *order)
    # What only the order needs stays in Spark.
    return rows.select("run", "src", "dst", F.col("seq") if hashed else F.lit(0).cast("byte").alias("seq"), "cmp", "guarded").mapInArrow(run, MEASURES)


def bounded_total_degree(stream: DataFrame, p: int, max_buffer: int, hub_threshold: int | None = None, guard: float | None = 1.1, guard_scope: str = "direct", release: str = "first", tie: str = "lowest", seed: int = 0) -> DataFrame:
    """(src, dst, seq, part, place_seq): the total-degree method with at most ``max_buffer`` held edges, as one stream."""
    ratio = _ratio(guard)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        engine = Buffered(p, hub_threshold, ratio, guard_scope, release, tie, seed, max_buffer)
        held: tuple[int, list[int], int] | None = None
        done = 0

        def rows(found) -> pa.RecordBatch:
            nonlocal done
            found = list(found)
            done += len(found)
            u, v, s, k = zip(*found) if found else ((), (), (), ())
            return pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64()), pa.array(s, pa.int64()), pa.array(k, pa.int32()), pa.array(range(done - len(found), done), pa.int64())], names=["src", "dst", "seq", "part", "place_seq"])

        for b in batches:
            out = []
            for u, v, s in zip(*(b.column(n).to_pylist() for n in ("src", "dst", "seq"))):
                if held is not None and held[0] == u:
                    held[1].append(v)
                    continue
                if held is not None:
                    out += engine.block(*held)
                held = (u, [v], s)
            yield rows(out)
        if held is not None:
            yield rows([*engine.block(*held), *engine.flush()])

    return stream.select("src", "dst", "seq").repartition(1).sortWithinPartitions("seq").mapInArrow(run, "src long, dst long, seq long, part int, place_seq long")


def _run(s: DataFrame, p: int, guard: float | None, tie: str | None, seed: int, shards: int | None) -> DataFrame:
    """The exact engine, or shards; ``tie`` None is the engine's own default."""
    return exact(s, p, guard, tie or "lowest", seed) if shards is None else sharded(s, p, shards, guard, tie or "rotate", seed)


def greedy_affinity(stream: DataFrame, p: int, guard: float | None = 1.1, tie: str | None = None, seed: int = 0, shards: int | None = None) -> DataFrame:
    return _run(S.plain_schedule(stream), p, guard, tie, seed, shards)


def greedy_indegree(
    stream: DataFrame, p: int, guard: float | None = 1.1, tie: str | None = None, seed: int = 0, degree: str = "in", count_before: bool = True, degrees: DataFrame | None = None, shards: int | None = None
) -> DataFrame:
    """``degree`` 'in' counts arrivals; 'out' or 'total', or given ``degrees``, use the whole graph's."""
    s = S.indegree_schedule(stream, count_before) if degree == "in" and degrees is None else S.degree_schedule(stream, degrees, degree)
    return _run(s, p, guard, tie, seed, shards)


def greedy_total_degree(
    stream: DataFrame, p: int, hub_threshold: int | None = None, guard: float | None = 1.1, guard_scope: str = "direct", release: str = "first", tie: str | None = None, flush: str = "end", seed: int = 0, shards: int | None = None
) -> DataFrame:
    s = S.total_degree_schedule(stream, p, hub_threshold, guard_scope, release, flush)
    return _run(s, p, guard, tie, seed, shards)
