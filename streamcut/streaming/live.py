"""Live placement with keyed state, and windowed measures.

Edges are keyed by a shard of their source.  A shard's state is a map of its vertices (replica mask, degrees), its loads, and
its held edges by target; a batch reads and writes the vertices that it touches and no others.  Spark checkpoints the
state, so a restarted query goes on where it stopped.  With one shard the placement equals the exact engine's.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.streaming.query import StreamingQuery

from ..operators.greedy import _ratio
from ..operators.kernel import Buffered, check_live

PLACED = "shard int, src long, dst long, seq long, part int"
#: Keyed maps in the state need this store; it is a setting of the session that can change at any time.
STORE = ("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
_COLUMNS = ["shard", "src", "dst", "seq", "part"]


def exactly_once(edges: DataFrame, delay: str = "1 day") -> DataFrame:
    """Drops repeated edges within the watermark."""
    return edges.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["src", "dst"])


@dataclass(frozen=True)
class Rules:
    """What a live placement does; the same for all shards."""

    p: int
    method: str = "greedy_indegree"
    guard: float | None = 1.1
    hub_threshold: int | None = None
    guard_scope: str = "direct"
    release: str = "first"
    tie: str = "lowest"
    seed: int = 0
    max_buffer: int | None = None

    def engine(self) -> Buffered:
        return Buffered(self.p, self.hub_threshold, _ratio(self.guard), self.guard_scope, self.release, self.tie, self.seed, self.max_buffer)


def _put(engine: Buffered, v: int, mask: bytes, d_in: int, d_out: int) -> None:
    if mask:
        engine.placer.at[v] = int.from_bytes(mask, "little")
    if d_in:
        engine.d_in[v] = d_in
    if d_out:
        engine.d_out[v] = d_out


def _frame(shard: int, rows: list[tuple]) -> pd.DataFrame:
    return pd.DataFrame([(shard, *r) for r in rows], columns=_COLUMNS).astype({"shard": "int32", "src": "int64", "dst": "int64", "seq": "int64", "part": "int32"})


class _Shard(StatefulProcessor):
    def __init__(self, rules: Rules):
        self.rules = rules

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.vertices = handle.getMapState("vertices", "v long", "mask binary, d_in long, d_out long")
        self.loads = handle.getValueState("loads", "loads array<long>, buffered long")
        self.held = handle.getMapState("held", "v long", "sources array<long>, seqs array<long>")
        # All held edges by age; kept only if their number is bounded.
        self.ages = handle.getValueState("ages", "seqs array<long>, targets array<long>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        frame = pd.concat(list(rows)).sort_values("seq")
        u, v, s = (frame[c].tolist() for c in ("src", "dst", "seq"))
        engine, seen = self.rules.engine(), set()
        if self.loads.exists():
            loads, engine.buffered = self.loads.get()
            engine.placer.loads = [int(x) for x in loads]
            engine.placer.placed, engine.placer.top = sum(engine.placer.loads), max(engine.placer.loads)

        def vertex(w: int) -> None:
            if w not in seen:
                seen.add(w)
                if self.vertices.containsKey((w,)):
                    mask, d_in, d_out = self.vertices.getValue((w,))
                    _put(engine, w, bytes(mask), int(d_in), int(d_out))

        def waiting(target: int) -> None:
            if target not in engine.waiting and self.held.containsKey((target,)):
                sources, seqs = self.held.getValue((target,))
                engine.waiting[target] = {int(n): int(x) for n, x in zip(seqs, sources)}
                for w in (target, *engine.waiting[target].values()):
                    vertex(w)

        for w in {*u, *v}:
            vertex(w)
        if self.rules.method == "greedy_total_degree":
            for target in dict.fromkeys((*u, *v)):
                waiting(target)
            before = set(engine.waiting)
            if self.rules.max_buffer is not None and self.ages.exists():
                seqs, targets = self.ages.get()
                engine.oldest = {int(n): int(t) for n, t in zip(seqs, targets)}
                # This batch can push out no more than it has edges, after those that it releases.
                released = sum(map(len, engine.waiting.values()))
                for t in list(engine.oldest.values())[: len(u) + released]:
                    waiting(t)
                before = set(engine.waiting)
            else:
                engine.oldest = dict(sorted((n, t) for t, held in engine.waiting.items() for n in held))
            out, at = [], 0
            while at < len(u):
                end = at
                while end < len(u) and u[end] == u[at]:
                    end += 1
                out += engine.block(u[at], v[at:end], s[at])
                at = end
            for target in before | set(engine.waiting):
                held = engine.waiting.get(target)
                if held:
                    self.held.updateValue((target,), (list(held.values()), list(held)))
                else:
                    self.held.removeKey((target,))
            if self.rules.max_buffer is not None:
                self.ages.update((list(engine.oldest), list(engine.oldest.values())))
        else:
            out = [(a, b, n, engine.edge(a, b, n, self.rules.method)) for a, b, n in zip(u, v, s)]
        for w in seen:
            mask = engine.placer.at.get(w, 0)
            self.vertices.updateValue((w,), (mask.to_bytes(-(-self.rules.p // 8), "little"), engine.d_in.get(w, 0), engine.d_out.get(w, 0)))
        self.loads.update((engine.placer.loads, engine.buffered))
        yield _frame(key[0], out)

    def close(self) -> None:
        pass


def place_live(edges: DataFrame, p: int, method: str = "greedy_indegree", shards: int = 1, **rules) -> DataFrame:
    """Placements of a streaming edge table (src, dst, seq); ``rules``: other fields of ``Rules``.

    For the total-degree method a source's block must not straddle batches.  Its held edges come out when their target
    arrives, or when ``max_buffer`` is reached; ``flush_live`` places what is left at the end.
    """
    own = Rules(p, check_live(method), **rules)
    edges.sparkSession.conf.set(*STORE)
    keyed = edges.withColumn("shard", F.pmod(F.xxhash64("src", F.lit(own.seed)), F.lit(shards)).cast("int")).select("shard", "src", "dst", "seq")
    return keyed.groupBy("shard").transformWithStateInPandas(_Shard(own), PLACED, "append", "none")


def live_state(spark: SparkSession, checkpoint: str, name: str) -> DataFrame:
    """One variable of the state at the last committed batch: 'vertices', 'loads', 'held' or 'ages'."""
    spark.conf.set(*STORE)
    return spark.read.format("statestore").option("path", checkpoint).option("stateVarName", name).load()


def flush_live(spark: SparkSession, checkpoint: str, p: int, **rules) -> DataFrame:
    """The edges that a stopped total-degree query still holds, placed as at the end of the stream, in their order."""
    own = Rules(p, "greedy_total_degree", **rules)
    held = live_state(spark, checkpoint, "held").select(F.col("key.shard").alias("shard"), F.col("user_map_key.v").alias("dst"), F.explode(F.arrays_zip("user_map_value.sources", "user_map_value.seqs")).alias("x"))
    held = held.select("shard", F.col("x.sources").alias("src"), "dst", F.col("x.seqs").alias("seq"))
    ends = held.select("shard", F.explode(F.array("src", "dst")).alias("v")).distinct()
    vertices = live_state(spark, checkpoint, "vertices").select(F.col("key.shard").alias("shard"), F.col("user_map_key.v").alias("v"), "user_map_value.*").join(ends, ["shard", "v"], "left_semi")
    loads = live_state(spark, checkpoint, "loads").select(F.col("key.shard").alias("shard"), F.col("value.loads").alias("loads"))
    none = lambda t, *names: [F.lit(None).cast(t).alias(n) for n in names]
    rows = (
        held.select("shard", "src", "dst", "seq", *none("long", "v"), *none("binary", "mask"), *none("long", "d_in", "d_out"), *none("array<long>", "loads"))
        .unionByName(vertices.select("shard", *none("long", "src", "dst", "seq"), "v", "mask", "d_in", "d_out", *none("array<long>", "loads")))
        .unionByName(loads.select("shard", *none("long", "src", "dst", "seq", "v"), *none("binary", "mask"), *none("long", "d_in", "d_out"), "loads"))
    )

    def run(key: tuple, t: pd.DataFrame) -> pd.DataFrame:
        engine = own.engine()
        for r in t[t["v"].notna()].itertuples():
            _put(engine, int(r.v), bytes(r.mask), int(r.d_in), int(r.d_out))
        for r in t[t["loads"].notna()].itertuples():
            engine.placer.loads = [int(x) for x in r.loads]
            engine.placer.placed, engine.placer.top = sum(engine.placer.loads), max(engine.placer.loads)
        for r in t[t["seq"].notna()].sort_values("seq").itertuples():
            engine.waiting.setdefault(int(r.dst), {})[int(r.seq)] = int(r.src)
            engine.oldest[int(r.seq)] = int(r.dst)
            engine.buffered += 1
        return _frame(int(key[0]), list(engine.flush()))

    return rows.groupBy("shard").applyInPandas(run, PLACED)


class PlacementStream:
    """Live placement of a stream into a folder of Parquet files: start, stop, start again, and flush at the end."""

    def __init__(self, p: int, method: str, path: str, shards: int = 1, **rules):
        self.p, self.method, self.path, self.shards, self.rules = p, check_live(method), path.rstrip("/"), shards, rules

    def start(self, edges: DataFrame, **trigger) -> StreamingQuery:
        """``trigger``: as of ``DataStreamWriter.trigger``; all that is there by default."""
        placed = place_live(edges, self.p, self.method, self.shards, **self.rules)
        return placed.writeStream.option("checkpointLocation", f"{self.path}/checkpoint").trigger(**(trigger or {"availableNow": True})).format("parquet").start(f"{self.path}/placed")

    def flush(self, spark: SparkSession) -> DataFrame:
        """Held edges, written beside the placed ones; a second flush gives the same rows."""
        if self.method == "greedy_total_degree":
            flush_live(spark, f"{self.path}/checkpoint", self.p, **self.rules).write.mode("overwrite").parquet(f"{self.path}/flushed")
        return self.placed(spark)

    def placed(self, spark: SparkSession) -> DataFrame:
        done = spark.read.parquet(f"{self.path}/placed")
        try:
            return done.unionByName(spark.read.schema(done.schema).parquet(f"{self.path}/flushed"))
        except AnalysisException as e:
            if e.getCondition() != "PATH_NOT_FOUND":
                raise
            return done


def windowed_load(events: DataFrame, size: str = "1 day", slide: str | None = None, delay: str | None = None) -> DataFrame:
    """(start, sources, edges) per tumbling or sliding window of ``ts``; works on batch and streaming tables."""
    e = events if delay is None else events.withWatermark("ts", delay)
    w = F.window("ts", size) if slide is None else F.window("ts", size, slide)
    return e.groupBy(w.alias("w")).agg(F.approx_count_distinct("user_id").alias("sources"), F.count("*").alias("edges")).select(F.col("w.start").alias("start"), "sources", "edges")


def session_load(events: DataFrame, gap: str = "30 minutes", delay: str | None = None) -> DataFrame:
    e = events if delay is None else events.withWatermark("ts", delay)
    return e.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("edges")).select("user_id", F.col("w.start").alias("start"), "edges")


def matched_reverse(edges: DataFrame, within: str = "1 day", delay: str = "1 day") -> DataFrame:
    """(src, dst, ts, back): edges met by an edge in the other direction within an interval; for streams and batches.

    A join of two streams on the pair of ends and a bounded time, so that its state can be dropped by the watermarks.
    """
    e = edges.withWatermark("ts", delay) if edges.isStreaming else edges
    a, b = e.select("src", "dst", "ts"), e.select(F.col("dst").alias("src2"), F.col("src").alias("dst2"), F.col("ts").alias("back"))
    return a.join(b, F.expr(f"src = src2 AND dst = dst2 AND src <> dst AND back > ts AND back <= ts + INTERVAL {within}")).select("src", "dst", "ts", "back")
