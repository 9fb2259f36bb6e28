"""Shaping of edge tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import hash32, vertex_id


def to_edges(df: DataFrame, src: Column | str, dst: Column | str) -> DataFrame:
    col = lambda c: F.col(c) if isinstance(c, str) else c
    return df.select(col(src).cast("long").alias("src"), col(dst).cast("long").alias("dst"))


def check(df: DataFrame) -> DataFrame:
    """The edges, or an error if the columns aren't bigint src and dst."""
    kinds = dict(df.dtypes)
    if kinds.get("src") != "bigint" or kinds.get("dst") != "bigint":
        raise TypeError(f"edges need bigint src and dst, not {kinds}")
    return df


def reverse(e: DataFrame) -> DataFrame:
    return e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))


def undirect(e: DataFrame) -> DataFrame:
    return e.select("src", "dst").unionByName(reverse(e)).distinct()


def canonical(e: DataFrame) -> DataFrame:
    return e.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()


def drop_loops(e: DataFrame) -> DataFrame:
    return e.where("src <> dst")


def drop_null_ends(e: DataFrame) -> DataFrame:
    return e.where("src is not null and dst is not null")


def dedup_edges(e: DataFrame) -> DataFrame:
    return drop_null_ends(e).select("src", "dst").distinct()


def endpoints(e: DataFrame) -> DataFrame:
    """Rows (v, dst side) with a row for each end of each edge; a loop has one row."""
    return e.select("*", F.explode(F.array_distinct(F.array("src", "dst"))).alias("v"))


def degrees(e: DataFrame) -> DataFrame:
    """(v, d_in, d_out, d)."""
    ends = e.select(F.explode(F.array(F.struct(F.col("src").alias("v"), F.lit(0).alias("i"), F.lit(1).alias("o")), F.struct(F.col("dst").alias("v"), F.lit(1).alias("i"), F.lit(0).alias("o")))).alias("x"))
    return ends.groupBy(F.col("x.v").alias("v")).agg(F.sum("x.i").alias("d_in"), F.sum("x.o").alias("d_out"), F.count("*").alias("d"))


def filter_min_degree(e: DataFrame, k: int) -> DataFrame:
    rich = degrees(e).where(F.col("d") >= k).select("v")
    return e.join(rich.withColumnRenamed("v", "src"), "src", "left_semi").join(rich.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "dst")


def induced(e: DataFrame, vertices: DataFrame) -> DataFrame:
    v = vertices.select("v").distinct()
    return e.join(v.withColumnRenamed("v", "src"), "src", "left_semi").join(v.withColumnRenamed("v", "dst"), "dst", "left_semi").select("src", "dst")


def sample_edges(e: DataFrame, percent: int, seed: int = 0) -> DataFrame:
    return e.where(hash32("src", "dst", seed=seed) % 100 < percent)


def hub_filter(e: DataFrame, threshold: int) -> DataFrame:
    """Edges out of sources with at least ``threshold`` out-edges."""
    hubs = e.groupBy("src").count().where(F.col("count") >= threshold).select("src")
    return e.join(hubs, "src", "left_semi").select("src", "dst")


def encode_vertices(keyed: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(edges, dictionary (v, key)) of text-keyed edges (src_key, dst_key)."""
    e = keyed.select(vertex_id(F.col("src_key")).alias("src"), vertex_id(F.col("dst_key")).alias("dst"))
    keys = keyed.select(F.explode(F.array("src_key", "dst_key")).alias("key")).distinct()
    return e, keys.select(vertex_id(F.col("key")).alias("v"), "key")


def decode_vertices(e: DataFrame, dictionary: DataFrame) -> DataFrame:
    d = dictionary
    return e.join(d.select(F.col("v").alias("src"), F.col("key").alias("src_key")), "src").join(d.select(F.col("v").alias("dst"), F.col("key").alias("dst_key")), "dst")


def id_collisions(dictionary: DataFrame) -> DataFrame:
    return dictionary.groupBy("v").agg(F.countDistinct("key").alias("n")).where("n > 1")


#: Rows up to which positions come from one sorted window; more are numbered per range partition with offsets.
ONE_WINDOW = 2_000_000


def number_rows(df: DataFrame, order: list[Column | str], name: str, rows: int | None = None) -> DataFrame:
    """Consecutive numbers from 0 in the given total order.

    ``rows``: their number, if the caller knows it; else the input is written once and counted there, not computed twice.
    """
    from ..plans.scratch import keep

    if rows is None:
        df = keep(df, "numbered")
        rows = df.count()
    if rows <= ONE_WINDOW:
        return df.withColumn(name, (F.row_number().over(Window.orderBy(*order)) - 1).cast("long"))
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = df.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_m", F.monotonically_increasing_id())
    placed = keep(placed.withColumn("_p", F.shiftright("_m", 33)).withColumn("_i", F.col("_m").bitwiseAND((1 << 33) - 1)), "ranged")
    sizes = placed.groupBy("_p").agg(F.count("*").alias("_n"))
    before = sizes.withColumn("_b", F.coalesce(F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))  # a row per range
    return placed.join(F.broadcast(before.select("_p", "_b")), "_p").withColumn(name, F.col("_b") + F.col("_i")).drop("_m", "_p", "_i", "_b")


def running_sum(df: DataFrame, position: str, value: str, name: str, block: int = 100_000) -> DataFrame:
    """``df`` with the sum of ``value`` up to each row's position (rows of one position count together).

    Sums per block of positions are added up first, so that no window holds more than one block or a row per block.
    """
    b = F.floor(F.col(position) / block).cast("long")
    rows = df.withColumn("_b", b)
    sums = rows.groupBy("_b").agg(F.sum(value).alias("_s"))
    before = sums.select("_b", F.coalesce(F.sum("_s").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_before"))
    inside = F.sum(value).over(Window.partitionBy("_b").orderBy(position).rangeBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("_inside", inside).join(before, "_b").withColumn(name, F.col("_before") + F.col("_inside")).drop("_b", "_inside", "_before")
