"""Graphs that fit a task: order, degree comparisons and many greedy runs in one pass over the edges, without a shuffle.

The results are those of ``ordering``, ``schedule`` and ``greedy``, which stay the way for larger graphs.  Vertices are numbered
by (md5 of 'seed:vertex', vertex): the order of restarts and of neighbours.  Searches and streams of up to 128 parts
run in the JVM (``native``); ``Stream`` and the loops of ``Whole.order`` are the same in Python, for any number of parts.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.resource import ResourceProfile, ResourceProfileBuilder, TaskResourceRequests
from pyspark.sql import Column, DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from . import native
from .greedy import MEASURES, Run, _ratio
from .kernel import Tally
from .stateless import constraint_set, grid_shape

#: Edges of a graph up to which ``measures`` may be asked: about 32 bytes an edge in a task's Python, and 20 in its JVM.
EDGES = 20_000_000
#: Placements that one task should have, so that the runs of a graph are shared out: in Python, in the JVM, and there over a kept graph.
SHARE, SHARE_NATIVE, SHARE_KEPT = 12_000_000, 200_000_000, 140_000_000
CHUNK, BLOCK = 1 << 17, 1 << 21


@dataclass(frozen=True)
class Job:
    """A run of one method on one order.  ``count_before``: a target's in-degree has the edge itself."""

    number: int
    method: str
    run: Run
    hub_threshold: int | None = None
    guard_scope: str = "direct"
    release: str = "first"
    count_before: bool = True


HASHES = ("edge_hash", "grid_hash")


def _digest(*parts: int) -> tuple[int, int]:
    d = hashlib.md5(":".join(map(str, parts)).encode()).digest()
    return int.from_bytes(d[:8], "big"), int.from_bytes(d[8:], "big")


class Whole:
    """The edges by source, and in a source's block by (md5 of 'seed:src:dst', dst), as the streams have them.

    The hashes of ``hashes`` are measured while the edges are read: no order needs their keys.
    """

    def __init__(self, batches: Iterator[pa.RecordBatch], n: int, seed: int, hashes: list[Job] = ()):
        self.seed, self.n = seed, n
        src, dst, key, grid = np.empty(n, np.int64), np.empty(n, np.int64), np.empty(n, np.uint64), np.empty(n if hashes else 0, np.uint32)
        lo = 0
        for b in batches:
            hi = lo + b.num_rows
            src[lo:hi], dst[lo:hi] = b.column("src").to_numpy(), b.column("dst").to_numpy()
            key[lo:hi] = np.frombuffer(b.column("key").cast(pa.binary(8)).buffers()[1], ">u8")[b.column("key").offset :][: b.num_rows]
            if hashes:
                grid[lo:hi] = b.column("grid").to_numpy()
            lo = hi
        if lo != n:
            raise ValueError(f"{lo} edges were read of {n}")
        found = [pc.unique(pa.array(x[k : k + BLOCK])) for x in (src, dst) for k in range(0, n, BLOCK)]
        ids = pc.unique(pa.chunked_array(found, pa.int64())).to_numpy()
        self.nv = len(ids)
        named = np.frombuffer(b"".join(hashlib.md5(f"{seed}:{v}".encode()).digest() for v in ids.tolist()), ">u8").astype(np.uint64).reshape(-1, 2)
        by = np.lexsort((ids, named[:, 1], named[:, 0]))
        rank = np.empty(self.nv, np.int32)
        rank[by] = np.arange(self.nv, dtype=np.int32)
        self.ids, h32 = ids[by], (named[by, 0] >> np.uint64(32)).astype(np.int64)
        s = _numbered(src, ids, rank)
        del src  # one side at a time
        d = _numbered(dst, ids, rank)
        del dst, named, rank
        self.hashed = {j.number: self._hash(j, s, d, key, grid, h32) for j in hashes}
        del grid, h32
        self.out = np.bincount(s, minlength=self.nv)
        # By source and as many first bits of the key as there is place for.
        room = np.uint64(64 - max(1, self.nv).bit_length())
        key >>= np.uint64(64) - room
        for k in range(0, n, BLOCK):
            key[k : k + BLOCK] |= s[k : k + BLOCK].astype(np.uint64) << room
        by = np.argsort(key)
        same = np.concatenate([k + np.flatnonzero(key[by[k + 1 : k + 1 + BLOCK]] == key[by[k : k + BLOCK][: n - 1 - k]]) for k in range(0, max(1, n - 1), BLOCK)])
        del key
        if len(same):  # keys that are equal in a block: whole md5 decide
            for lo, hi in zip(*_spans(same)):
                at = by[lo:hi].tolist()
                by[lo:hi] = sorted(at, key=lambda k, u=int(self.ids[s[at[0]]]): (_digest(seed, u, int(self.ids[d[k]])), int(self.ids[d[k]])))
        self.dst = d[by]
        self.at = np.concatenate([[0], np.cumsum(self.out)])
        self.sources = np.flatnonzero(self.out)

    @cached_property
    def src(self) -> np.ndarray:
        return np.repeat(np.arange(self.nv, dtype=np.int32), self.out)

    @cached_property
    def into(self) -> np.ndarray:
        return np.bincount(self.dst, minlength=self.nv)

    @cached_property
    def near(self) -> tuple[np.ndarray, np.ndarray]:
        """Offsets and targets that are sources themselves, by number: others never lead a search anywhere."""
        on = self.out[self.dst] > 0
        pair = np.repeat(np.arange(self.nv) * self.nv, self.out)[on]
        pair += self.dst[on]
        pair.sort()
        count = np.bincount(pair // max(1, self.nv), minlength=self.nv)
        pair %= max(1, self.nv)
        return np.concatenate([[0], np.cumsum(count)]), pair.astype(np.int32)

    def order(self, kind: str) -> np.ndarray:
        """The sources by arrival."""
        if kind == "random":
            return self.sources
        at, near = self.near
        seen, out = np.zeros(self.nv, bool), []
        starts = at.tolist()
        for r in self.sources.tolist():
            if seen[r]:
                continue
            if kind == "bfs":
                seen[r], queue = True, [r]
                for u in queue:
                    if starts[u] < starts[u + 1]:
                        found = near[starts[u] : starts[u + 1]]
                        found = found[~seen[found]]
                        seen[found] = True
                        queue += found.tolist()
                out += queue
                continue
            stack = [r]
            while stack:
                u = stack.pop()
                if seen[u]:
                    continue
                seen[u] = True
                out.append(u)
                found = near[starts[u] : starts[u + 1]]
                stack += found[~seen[found]][::-1].tolist()
        return np.array(out, dtype=np.int64)

    def run(self, kind: str, jobs: list[Job]) -> Iterator[tuple]:
        """(number, copies, max_edges) of each job."""
        stream = None
        for j in jobs:
            if j.number in self.hashed:
                yield j.number, *self.hashed[j.number]
                continue
            if stream is None:
                stream = Stream(self, self.order(kind))
            yield j.number, *stream.run(j)

    def _hash(self, job: Job, src: np.ndarray, dst: np.ndarray, key: np.ndarray, grid: np.ndarray, h32: np.ndarray) -> tuple[int, int]:
        p = job.run.p
        if job.method == "grid_hash":
            r, c = grid_shape(p)
            sets = [constraint_set(k, p, (r, c)) for k in range(r * c)]
            common = [[x for x in a if x in b] for a in map(list, sets) for b in map(set, sets)]
            size = np.array([len(x) for x in common])
            first, item = np.concatenate([[0], np.cumsum(size)]), np.array([x for y in common for x in y])
            cell = h32 % (r * c)
        held, loads = np.zeros((self.nv, p), bool), np.zeros(p, np.int64)
        for lo in range(0, len(src), CHUNK):
            s, d = src[lo : lo + CHUNK], dst[lo : lo + CHUNK]
            if job.method == "edge_hash":
                part = ((key[lo : lo + CHUNK] >> np.uint64(32)) % np.uint64(p)).astype(np.int64)
            else:
                pair = cell[s] * (r * c) + cell[d]
                part = item[first[pair] + grid[lo : lo + CHUNK] % size[pair]]
            held[s, part] = True
            held[d, part] = True
            loads += np.bincount(part, minlength=p)
        return int(held.sum()), int(loads.max())


def _numbered(ends: np.ndarray, ids: np.ndarray, rank: np.ndarray) -> np.ndarray:
    out, known = np.empty(len(ends), np.int32), pa.array(ids)
    for k in range(0, len(ends), BLOCK):
        out[k : k + BLOCK] = rank[pc.index_in(pa.array(ends[k : k + BLOCK]), value_set=known).to_numpy()]
    return out


def _spans(same: np.ndarray) -> tuple[list[int], list[int]]:
    """Bounds of the rows that are equal to a neighbour, from the first of each equal pair."""
    cut = np.flatnonzero(np.diff(same) > 1)
    return same[np.concatenate([[0], cut + 1])].tolist(), (same[np.concatenate([cut, [len(same) - 1]])] + 2).tolist()


class Stream:
    """One arrival order of a graph with what the methods compare, as ``schedule.total_degree_base`` has it."""

    def __init__(self, g: Whole, order: np.ndarray):
        self.g, size = g, g.out[order]
        begin = np.cumsum(size) - size
        index = np.repeat(g.at[order] - begin, size) + np.arange(g.n)
        self.s, self.d = g.src[index], g.dst[index]
        del index
        self.arrival = np.repeat(np.arange(len(order), dtype=np.int32), size)
        self.came = np.full(g.nv, -1, np.int32)
        self.came[order] = np.arange(len(order), dtype=np.int32)
        self.begin = np.zeros(g.nv, np.int64)
        self.begin[order] = begin
        #: Positions of the edges by target and, in it, by position.
        self.by = np.argsort(self.d, kind="stable")
        self.into = g.into
        self.first = np.concatenate([[0], np.cumsum(self.into)])
        self.event = self.d[self.by].astype(np.int64) * max(1, g.n) + self.by
        self.before = self._seen(np.arange(g.nv), self.begin)  # of the sources
        at = np.empty(g.n, np.int32)
        at[self.by] = np.arange(g.n) - self.first[self.d[self.by]] + 1
        self.in_v = at
        loop = np.flatnonzero(self.s == self.d)  # the only edges that raise a source's in-degree in its block
        own = np.full(g.nv, g.n + 1, np.int64)
        own[self.s[loop]] = loop
        self.own = own
        self.in_u = (self.before[self.s] + (np.arange(g.n) >= own[self.s])).astype(np.int32)

    def _seen(self, v: np.ndarray, pos: np.ndarray) -> np.ndarray:
        """Edges into v before the position."""
        return np.searchsorted(self.event, v.astype(np.int64) * max(1, self.g.n) + pos) - self.first[v]

    def run(self, job: Job) -> tuple[int, int]:
        g, n = self.g, self.g.n
        order = guarded = None
        if job.method == "greedy_affinity":
            cmp = np.zeros(n, np.int8)
        elif job.method == "final_degrees":
            total = g.out + self.into
            cmp = np.sign(total[self.s] - total[self.d]).astype(np.int8)
        elif job.method == "greedy_indegree":
            loops = self.s == self.d
            less = (0, 0) if job.count_before else (loops, 1)
            cmp = np.sign((self.in_u - less[0]) - (self.in_v - less[1])).astype(np.int8)
        else:
            cmp, order, guarded = self._total(job)
        t = Tally(job.run.p, _ratio(job.run.guard), job.run.tie, job.run.seed, g.nv)
        for lo in range(0, n, CHUNK):
            at = slice(lo, lo + CHUNK) if order is None else order[lo : lo + CHUNK]
            seqs = range(lo, lo + CHUNK) if order is None else at.tolist()
            t.run(self.s[at].tolist(), self.d[at].tolist(), cmp[at].tolist(), None if guarded is None else guarded[at].tolist(), seqs)
        return t.copies(), t.top

    def _total(self, job: Job) -> tuple[np.ndarray, np.ndarray | None, np.ndarray | None]:
        """Comparisons by position, positions by placement, and what the guard looks at, as ``schedule.total_degree_rows``."""
        g, s, d = self.g, self.s, self.d
        come = self.came[d]
        known = (come >= 0) & (come <= self.arrival)
        small = g.out[s] < (job.run.p if job.hub_threshold is None else job.hub_threshold)
        cmp = np.where(known, np.sign(self.in_u + g.out[s] - self.in_v - g.out[d]), np.sign(self.in_u - self.in_v)).astype(np.int8)
        late = ~known & ~small
        k = np.flatnonzero(late)
        u, v, c = s[k], d[k], come[k]
        never = c < 0
        du, dv = self.into[u], self.into[v]
        w = np.flatnonzero(~never)
        pos = self.begin[v[w]] + (0 if job.release == "first" else g.out[v[w]])
        du[w] = self._seen(u[w], pos)
        dv[w] = self.before[v[w]] + (0 if job.release == "first" else self.own[v[w]] <= g.n)
        cmp[k] = np.sign(du + g.out[u] - dv - g.out[v])
        order = None
        if len(k):
            place = self.arrival.astype(np.int64) * 3 + 1
            place[k] = np.where(never, 1 << 60, c.astype(np.int64) * 3) + (0 if job.release == "first" else 2)
            order = np.argsort(place, kind="stable")
        guarded = {"all": None, "none": np.zeros(g.n, bool), "direct": ~late if len(k) else None}[job.guard_scope]
        return cmp, order, guarded


def keys(seed: int) -> list[Column]:
    """What ``Whole`` reads besides src and dst: ``shuffle_key``, of which it needs 64 bits, and ``hash32``."""
    return [F.call_function(native.KEY, F.lit(seed), "src", "dst").alias("key"), F.call_function(native.GRID, F.lit(seed + 1), "src", "dst").alias("grid")]


def alone(spark: SparkSession) -> ResourceProfile | None:
    """Tasks that have an executor for themselves, where the session names the cores of one."""
    master = spark.sparkContext.master
    local = re.fullmatch(r"local-cluster\[\s*\d+\s*,\s*(\d+)\s*,.*\]", master)
    cores = local[1] if local else spark.sparkContext.getConf().get("spark.executor.cores") if re.match(r"spark:|yarn|k8s:", master) else None
    return ResourceProfileBuilder().require(TaskResourceRequests().cpus(int(cores))).build if cores else None


def measures(edges: DataFrame, n: int, jobs: dict[str, list[Job]], seed: int = 0, profile: ResourceProfile | None = None, kept: Callable[[DataFrame], DataFrame] | None = None) -> list[Callable[[], list[Row]]]:
    """``greedy.MEASURES`` of the jobs of each order on a graph of ``n`` distinct edges: calls for rows of one task each over a kept table.

    They are for jobs side by side; a union of single partitions would be one task again.  ``profile``: of the tasks.  ``kept``
    writes a table of one row: runs in the JVM that are shared out read the graph from it, rather than each share its edges.
    """
    if n > EDGES:
        raise ValueError(f"a graph of {n} edges is no graph for one task; the bound is {EDGES}")
    # Every other run of an order, so that shares have few and many parts.
    many = [(kind, j) for kind, todo in jobs.items() for j in todo[::2] + todo[1::2]]
    native.register(edges.sparkSession)
    python = any(j.run.p > native.PARTS and j.method not in HASHES for _, j in many)
    if kept is not None and profile is None and not python and len(shares := _shares(many, n, SHARE_KEPT)) > 1:
        return [lambda: _kept_runs(kept(_graph(edges, n, many, seed, None)), shares)]
    out = []
    for mine in _shares(many, n, SHARE if python else SHARE_NATIVE):
        found = F.concat_ws(";", "found", F.call_function(native.STREAMS, "dst", "at", "jobs"))
        out.append(_measured(_graph(edges, n, mine, seed, profile), found).collect)
    return out


def _shares(many: list[tuple[str, Job]], n: int, share: int) -> list[list[tuple[str, Job]]]:
    shares = min(len(many), max(1, -(-n * len(many) // share)))
    return [many[k * len(many) // shares : (k + 1) * len(many) // shares] for k in range(shares)]


def _graph(edges: DataFrame, n: int, mine: list[tuple[str, Job]], seed: int, profile: ResourceProfile | None) -> DataFrame:
    """(n_vertices, n_edges, found, dst, at, jobs): what is measured in Python, and the graph for the other runs; no row without edges."""
    key, grid = keys(seed)

    def run(batches: Iterator[pa.RecordBatch], mine=tuple(mine)) -> Iterator[pa.RecordBatch]:
        here: dict[str, list[Job]] = {}
        for kind, j in mine:
            if not _native(j):
                here.setdefault(kind, []).append(j)
        g = Whole(batches, n, seed, [j for todo in here.values() for j in todo if j.method in HASHES])
        if g.n:
            found = ";".join(f"{number} {copies} {top}" for kind, todo in here.items() for number, copies, top in g.run(kind, todo))
            yield _row(g, found or None, _blob(mine))

    gridded = any(j.method == "grid_hash" for _, j in mine)
    return edges.coalesce(1).select("src", "dst", key, grid if gridded else F.lit(0).alias("grid")).mapInArrow(run, "n_vertices long, n_edges long, found string, dst binary, at binary, jobs binary", profile=profile)


def _measured(graph: DataFrame, found: Column) -> DataFrame:
    x = F.split("found", " ")
    rows = graph.select("n_vertices", "n_edges", F.explode(F.split(found, ";")).alias("found"))
    return rows.select(x[0].cast("int").alias("run"), "n_vertices", "n_edges", x[1].cast("long").alias("copies"), x[2].cast("long").alias("max_edges"))


def _kept_runs(graph: DataFrame, shares: list[list[tuple[str, Job]]]) -> list[Row]:
    blobs = [_blob(mine) for mine in shares]
    tables = [_measured(graph, F.call_function(native.STREAMS, "dst", "at", F.lit(x.tobytes()))) for x in blobs if x is not None]
    tables.append(_measured(graph.where("found is not null"), F.col("found")))
    with ThreadPoolExecutor(len(tables)) as pool:
        return [r for rows in pool.map(lambda t: t.collect(), tables) for r in rows]  # a row a run


def _native(job: Job) -> bool:
    return job.method not in HASHES and job.run.p <= native.PARTS


def _blob(mine: list[tuple[str, Job]]) -> np.ndarray | None:
    found = [_numbers(kind, j) for kind, j in mine if _native(j)]
    return np.concatenate(found) if found else None


def _numbers(kind: str, job: Job) -> np.ndarray:
    """A job as ``Streams.java`` reads it."""
    num, den = _ratio(job.run.guard) or (0, 0)
    method = ("greedy_affinity", "greedy_indegree", "greedy_total_degree", "final_degrees").index(job.method)
    scope = ("all", "direct", "none").index(job.guard_scope) if job.method == "greedy_total_degree" else 0
    hub = job.run.p if job.hub_threshold is None else job.hub_threshold
    return np.array([job.number, ("random", "bfs", "dfs").index(kind), method, job.run.p, num, den, job.run.tie == "hash", job.run.seed, hub, scope, job.release == "last", job.count_before], np.int64)


def _row(g: Whole, found: str | None, jobs: np.ndarray | None) -> pa.RecordBatch:
    blob = lambda x: pa.array([None], pa.binary()) if jobs is None else pa.Array.from_buffers(pa.binary(), 1, [None, pa.py_buffer(np.array([0, x.nbytes], np.int32)), pa.py_buffer(x)])
    columns = [pa.array([g.nv], pa.int64()), pa.array([g.n], pa.int64()), pa.array([found], pa.string()), blob(g.dst), blob(g.at.astype(np.int32)), blob(jobs)]
    return pa.RecordBatch.from_arrays(columns, names=["n_vertices", "n_edges", "found", "dst", "at", "jobs"])
