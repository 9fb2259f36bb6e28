"""Spark plumbing shared by the operators: scratch tables in the cluster's shared folder, and Arrow streams."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text bytes that a vectorised kernel handles at once (one longer document is handled alone).
SLICE_BYTES = 3 << 20


class Scratch:
    """Tables written once under ``spark.checkpoint.dir``: they cut lineage and outlive any executor.

    If the session names no such folder, one is made and set where driver and tasks are one machine (``local``), as in
    tests; on a cluster that is an error, since a machine's own folder would lose the tables.
    """

    def __init__(self, spark: SparkSession, tag: str):
        root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
        if not root:
            if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
                raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
            root = tempfile.mkdtemp(prefix="streamcut-")
            spark.sparkContext.setCheckpointDir(root)
        self.spark, self.root, self.n = spark, f"{root.rstrip('/')}/{tag}-{uuid.uuid4().hex[:12]}", 0

    def keep(self, df: DataFrame, name: str = "t", codec: str = "snappy") -> DataFrame:
        self.n += 1
        path = f"{self.root}/{self.n:03d}-{name}"
        df.write.option("compression", codec).parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, *frames: DataFrame | None) -> None:
        """Removes tables that no later plan reads."""
        for df in frames:
            if df is not None:
                path = self.spark._jvm.org.apache.hadoop.fs.Path(df._scratch_path)
                path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def pieces(batch: pa.RecordBatch, column: str = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Zero-copy row slices of about ``limit`` text bytes."""
    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0), dtype=np.int64)
    part = np.cumsum(sizes) // limit
    cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), len(sizes)]
    for a, b in zip(cuts, cuts[1:]):
        if b > a:
            yield batch.slice(a, b - a)


def raw(batch: pa.RecordBatch, column: str = "text") -> list[bytes]:
    """The texts as UTF-8 bytes; null as empty."""
    return [x or b"" for x in batch.column(column).cast(pa.binary()).to_pylist()]


def free(df: DataFrame, name: str) -> str:
    """``name``, or the first longer one that no column of ``df`` has (names are compared without case)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def groups(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[pa.Table]:
    """Tables of equal ``key`` (a long column) from a stream sorted by it; only one group is held beside a batch."""
    held: list[pa.RecordBatch] = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = batch.column(key).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
        for a, b in zip(cuts, cuts[1:]):
            if held and keys[a] != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = keys[a]
    if held:
        yield pa.Table.from_batches(held)


def components(scratch: Scratch, links: DataFrame) -> DataFrame:
    """Connected components of ``links`` (a, b): rows (node, root), root the smallest node reached.

    Each round gives every node its smallest neighbour, jumps pointers, and contracts the edges; the rounds needed grow
    with the logarithm of the longest chain.  Nothing but a row count reaches the driver.
    """
    edges = scratch.keep(links.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    roots = None
    while not edges.isEmpty():
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        up = both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("root"))
        for _ in range(2):
            up = _follow(up, up)
        up = scratch.keep(up, "up")
        merged = up if roots is None else scratch.keep(_follow(roots, up), "roots")
        ends = _root_of(_root_of(edges, up, "a", "ra"), up, "b", "rb")
        rest = scratch.keep(ends.where("ra <> rb").select(F.least("ra", "rb").alias("a"), F.greatest("ra", "rb").alias("b")).distinct(), "edges")
        scratch.drop(edges, roots, None if merged is up else up)
        edges, roots = rest, merged
    if roots is None:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return roots


#: Parts over which the rows of one key are dealt where a root or a hub may have a large share of all rows.
SALTS = 4


def salted_join(left: DataFrame, right: DataFrame, key: str) -> DataFrame:
    """Left join by ``key``, which is unique in ``right``: a key's rows of ``left`` are dealt over the salts.

    Larger shares than a salt's are split at run time, as Spark does for sorted joins of skewed keys.
    """
    salt = F.pmod(F.xxhash64(*left.columns), F.lit(SALTS)).cast("int")
    return left.withColumn("_salt", salt).join(right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))), [key, "_salt"], "left").drop("_salt")


def _root_of(left: DataFrame, up: DataFrame, key: str, out: str) -> DataFrame:
    # A hub's rows are one key of ``left``; Spark splits its partition when it is skewed, and salting would send ``up``
    # several times through the shuffles of each round.
    return left.join(up.select(F.col("node").alias(key), F.col("root").alias(out)), key, "left")


def _follow(roots: DataFrame, up: DataFrame) -> DataFrame:
    """Rows (node, root) with each root replaced by its own root in ``up``, if it has one."""
    return _root_of(roots, up, "root", "top").select("node", F.coalesce("top", "root").alias("root"))
