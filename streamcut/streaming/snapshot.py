"""Micro-batches scored against the last committed state, as DataFrame plans (up to 63 parts).

The state is a table of vertices (v, mask, d_in), kept as layers of which a newer one replaces an older one's rows, and the
loads of the parts.  A batch reads the rows of its own vertices and writes a layer of them; now and then the layers become
one.  In a batch every edge takes the least loaded part of its candidate set as of the snapshot; edges of two new vertices
meet at the hash of their lower-degree end.  A part takes no more than its room under the guard; what is over is poured
into the parts with room left.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import bucket
from ..operators.transforms import number_rows
from ..plans.scratch import keep

VERTEX = "v long, mask long, d_in long"
#: Layers that are read side by side before they are merged.
LAYERS = 8


@dataclass
class State:
    loads: list[int]
    layers: list[str] = field(default_factory=list)  # paths, oldest first

    def vertices(self, spark: SparkSession, of: DataFrame | None = None) -> DataFrame:
        """The newest row of each vertex, or of those in ``of`` (v)."""
        rows = None
        for age, path in enumerate(self.layers):
            layer = spark.read.schema(VERTEX).parquet(path).withColumn("age", F.lit(age))
            layer = layer if of is None else layer.join(of, "v", "left_semi")
            rows = layer if rows is None else rows.unionByName(layer)
        if rows is None:
            return spark.createDataFrame([], VERTEX)
        return rows.groupBy("v").agg(F.max_by(F.struct("mask", "d_in"), "age").alias("x")).select("v", "x.mask", "x.d_in")


def start(spark: SparkSession, p: int) -> State:
    if p > 63:
        raise ValueError("a snapshot's masks hold at most 63 parts")
    return State([0] * p)


def step(state: State, batch: DataFrame, p: int, guard: float = 1.1, seed: int = 0, degree_aware: bool = True, layer: str | None = None) -> tuple[DataFrame, State]:
    """(placed batch, next state) for a batch with src, dst, seq; ``layer``: where the batch's layer is written."""
    spark = batch.sparkSession
    batch = keep(batch.select("src", "dst", "seq"), "batch")
    touched = batch.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    arrived = batch.groupBy(F.col("dst").alias("v")).agg(F.count("*").alias("new"))
    known = touched.join(state.vertices(spark, touched), "v", "left").join(arrived, "v", "left")
    known = keep(known.select("v", F.coalesce("mask", F.lit(0)).cast("long").alias("mask"), (F.coalesce("d_in", F.lit(0)) + F.coalesce("new", F.lit(0))).cast("long").alias("d_in")), "known")
    a, b = known.select(F.col("v").alias("src"), F.col("mask").alias("mu"), F.col("d_in").alias("du")), known.select(F.col("v").alias("dst"), F.col("mask").alias("mv"), F.col("d_in").alias("dv"))
    e = batch.join(a, "src", "left").join(b, "dst", "left").fillna(0, ["mu", "mv", "du", "dv"])
    low, high = (F.when(F.col("du") < F.col("dv"), F.col(x)).otherwise(F.col(y)) for x, y in (("mu", "mv"), ("mv", "mu")))
    both, any_ = F.col("mu").bitwiseAND(F.col("mv")), F.col("mu").bitwiseOR(F.col("mv"))
    tiers = F.when(both != 0, both).when(F.lit(not degree_aware) | (F.col("du") == F.col("dv")), any_).when(low != 0, low).otherwise(high)
    by_load = sorted(range(p), key=lambda k: (state.loads[k], k))
    order = F.array(*[F.lit(k) for k in by_load])
    home = bucket(F.when(F.col("du") <= F.col("dv"), F.col("src")).otherwise(F.col("dst")), p=p, seed=seed)
    e = e.withColumn("cand", tiers).withColumn("_order", order)
    e = e.withColumn("want", F.when(F.col("cand") == 0, home).otherwise(F.expr("filter(_order, k -> shiftright(cand, k) & 1 = 1)[0]"))).select("src", "dst", "seq", "want")
    ranked = keep(e.withColumn("nth", F.row_number().over(Window.partitionBy("want").orderBy("seq"))), "ranked")
    n = {r.want: r.n for r in ranked.groupBy("want").agg(F.count("*").alias("n")).collect()}  # p rows
    total = sum(state.loads) + sum(n.values())
    room = [max(0, int(guard * total / p) - x) for x in state.loads]
    took = [min(n.get(k, 0), room[k]) for k in range(p)]
    rooms = F.array(*[F.lit(x).cast("long") for x in room])
    ranked = ranked.withColumn("ok", F.col("nth") <= F.element_at(rooms, F.col("want") + 1))
    over = number_rows(ranked.where("not ok"), [F.col("seq")], "r")
    bounds, at = [], 0
    for k in sorted(range(p), key=lambda k: (state.loads[k] + took[k], k)):
        bounds.append((k, at, at + room[k] - took[k]))
        at = bounds[-1][2]
    table = batch.sparkSession.createDataFrame(bounds, "part int, lo long, hi long")
    poured = over.join(F.broadcast(table), (F.col("r") >= F.col("lo")) & (F.col("r") < F.col("hi")), "left")  # p rows
    poured = poured.select("src", "dst", "seq", F.coalesce("part", F.pmod("r", F.lit(p)).cast("int")).alias("part"))
    placed = keep(ranked.where("ok").select("src", "dst", "seq", F.col("want").alias("part")).unionByName(poured), "placed")
    bits = placed.select(F.explode(F.array_distinct(F.array("src", "dst"))).alias("v"), F.expr("shiftleft(1L, part)").alias("m")).groupBy("v").agg(F.bit_or("m").alias("m"))
    vertices = known.join(bits, "v").select("v", F.col("mask").bitwiseOR(F.col("m")).alias("mask"), "d_in")
    loads = list(state.loads)
    for r in placed.groupBy("part").agg(F.count("*").alias("n")).collect():  # p rows
        loads[r.part] += r.n
    if layer is None:
        layers = [*state.layers, keep(vertices, "layer")._scratch_path]
    else:
        vertices.write.mode("overwrite").parquet(layer)
        layers = [*state.layers, layer]
    after = State(loads, layers)
    if len(layers) > LAYERS:
        merged = after.vertices(spark)
        if layer is None:
            after.layers = [keep(merged, "layer")._scratch_path]
        else:
            merged.write.mode("overwrite").parquet(f"{layer}-merged")
            after.layers = [f"{layer}-merged"]
    return placed, after


#: Vertices of a stream up to which one task runs all batches, with about 60 bytes a vertex and one batch; the results are those of ``step``.
WHOLE = 10_000_000


def run_batches(stream: DataFrame, p: int, batch: int, **opts) -> DataFrame:
    """A whole stream in batches of ``batch`` edges."""
    state, out = start(stream.sparkSession, p), None
    vertices = keep(stream.select(F.explode(F.array("src", "dst")).alias("v")).distinct(), "vertices")
    if vertices.count() <= WHOLE:
        return _in_one_task(stream, vertices, p, batch, **opts)
    for lo in range(0, max(stream.count(), 1), batch):
        placed, state = step(state, stream.where((F.col("seq") >= lo) & (F.col("seq") < lo + batch)), p, **opts)
        out = placed if out is None else out.unionByName(placed)
    return out


def _by_batch(rows: Iterator[pa.RecordBatch], batch: int) -> Iterator[tuple[int, pa.Table]]:
    """(number, rows) of each batch that has rows; they come in order of seq."""
    held, number = [], None
    for b in rows:
        which = b.column("seq").to_numpy() // batch
        cuts = [0, *(np.flatnonzero(np.diff(which)) + 1).tolist(), len(which)]
        for lo, hi in zip(cuts, cuts[1:] if len(which) else []):
            if held and which[lo] != number:
                yield number, pa.Table.from_batches(held)
                held = []
            number = int(which[lo])
            held.append(b.slice(lo, hi - lo))
    if held:
        yield number, pa.Table.from_batches(held)


def _in_one_task(stream: DataFrame, vertices: DataFrame, p: int, batch: int, guard: float = 1.1, seed: int = 0, degree_aware: bool = True) -> DataFrame:
    """The batches one after the other over arrays of masks and in-degrees, so that a small batch costs no job of its own.

    The vertices come first, by number; of the edges, a batch is held at a time.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, loads = np.empty(0, np.int64), [0] * p
        mask = d_in = ids
        for number, rows in _by_batch(batches, batch):
            if number < 0:
                ids = rows.column("src").to_numpy()
                mask, d_in = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64)
                continue
            src, dst, hu, hv = (rows.column(c).to_numpy() for c in ("src", "dst", "hu", "hv"))
            u, v = np.searchsorted(ids, src), np.searchsorted(ids, dst)
            np.add.at(d_in, v, 1)
            part = _placed(mask[u], mask[v], d_in[u], d_in[v], hu, hv, loads, p, guard, degree_aware)
            bit = np.left_shift(np.int64(1), part.astype(np.int64))
            np.bitwise_or.at(mask, u, bit)
            np.bitwise_or.at(mask, v, bit)
            loads = (np.array(loads) + np.bincount(part, minlength=p)).tolist()
            yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst), pa.array(rows.column("seq").to_numpy()), pa.array(part, pa.int32())], names=["src", "dst", "seq", "part"])

    rows = stream.select("src", "dst", "seq", bucket("src", p=p, seed=seed).alias("hu"), bucket("dst", p=p, seed=seed).alias("hv"))
    first = vertices.select(F.col("v").alias("src"), F.col("v").alias("dst"), F.lit(-1).cast("long").alias("seq"), F.lit(0).alias("hu"), F.lit(0).alias("hv"))
    first = first.select(*(F.col(c).cast(rows.schema[c].dataType) for c in rows.columns))
    return first.unionByName(rows).repartition(1).sortWithinPartitions("seq", "src").mapInArrow(run, "src long, dst long, seq long, part int")


def _placed(mu, mv, du, dv, hu, hv, loads: list[int], p: int, guard: float, degree_aware: bool) -> np.ndarray:
    """The parts of a batch's edges in order of seq, by the rules of ``step``."""
    low, high = np.where(du < dv, mu, mv), np.where(du < dv, mv, mu)
    alike = np.ones(len(du), bool) if not degree_aware else du == dv
    cand = np.where(mu & mv != 0, mu & mv, np.where(alike, mu | mv, np.where(low != 0, low, high)))
    want = np.where(du <= dv, hu, hv).astype(np.int64)
    free = cand != 0
    for k in sorted(range(p), key=lambda k: (loads[k], k)):
        hit = free & (cand >> k & 1 == 1)
        want[hit] = k
        free &= ~hit
    n = np.bincount(want, minlength=p)
    by = np.argsort(want, kind="stable")
    nth = np.empty(len(want), np.int64)
    nth[by] = np.arange(len(want)) - (np.cumsum(n) - n)[want[by]]
    total = sum(loads) + len(want)
    room = [max(0, int(guard * total / p) - x) for x in loads]
    took = [min(int(n[k]), room[k]) for k in range(p)]
    over = np.flatnonzero(nth >= np.array(room)[want])
    ranked = sorted(range(p), key=lambda k: (loads[k] + took[k], k))
    ends = np.cumsum([room[k] - took[k] for k in ranked])
    r = np.arange(len(over))
    slot = np.searchsorted(ends, r, side="right")
    want[over] = np.where(slot < p, np.array(ranked)[np.minimum(slot, p - 1)], r % p)
    return want


class SnapshotSink:
    """``foreachBatch`` function whose state is in ``path``, so that a new sink goes on where the last one stopped.

    A batch that is replayed replaces its own output, from the state before it.
    """

    def __init__(self, spark: SparkSession, path: str, p: int, **opts):
        self.spark, self.path, self.p, self.opts = spark, path.rstrip("/"), p, opts
        start(spark, p)  # refuses too many parts

    def _fs(self, path: str):
        at = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return at.getFileSystem(self.spark._jsc.hadoopConfiguration()), at

    def committed(self) -> list[int]:
        """Batches whose state is complete, in order."""
        fs, at = self._fs(f"{self.path}/_states")
        names = [x.getPath() for x in fs.listStatus(at)] if fs.exists(at) else []
        done = [int(x.getName()) for x in names if x.getName().isdigit() and fs.exists(self.spark._jvm.org.apache.hadoop.fs.Path(x, "_SUCCESS"))]
        return sorted(done)

    def state(self, before: int | None = None) -> State:
        """The state after the last batch, or after the last one before ``before``."""
        done = [k for k in self.committed() if before is None or k < before]
        return State(**json.loads(self.spark.read.text(f"{self.path}/_states/{done[-1]}").first()[0])) if done else start(self.spark, self.p)

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        numbered = number_rows(batch, [F.col("ts"), F.col("event_id")], "seq")
        # A layer has a name of its own: a replay must not overwrite what a later state still reads.
        layer = f"{self.path}/_layers/{batch_id}-{uuid.uuid4().hex[:8]}"
        placed, after = step(self.state(batch_id), numbered, self.p, layer=layer, **self.opts)
        placed.write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")
        text = json.dumps({"loads": after.loads, "layers": after.layers})
        self.spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.path}/_states/{batch_id}")
        # States before the last two can't be asked for again.
        for old in self.committed()[:-2]:
            fs, at = self._fs(f"{self.path}/_states/{old}")
            fs.delete(at, True)
