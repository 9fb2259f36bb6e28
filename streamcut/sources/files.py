"""Edge files in and out."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "src long, dst long"


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", sep: str = "\t", comment: str = "#") -> DataFrame:
    """Edges from csv, json, orc, parquet, or text lines with two numbers; nothing is inferred."""
    if fmt == "csv":
        return spark.read.schema(SCHEMA).option("sep", sep).option("comment", comment).csv(path)
    if fmt == "text":
        lines = spark.read.text(path).where(~F.col("value").startswith(comment) & (F.trim("value") != ""))
        x = F.split(F.trim("value"), r"\s+")
        return lines.select(x[0].cast("long").alias("src"), x[1].cast("long").alias("dst"))
    return spark.read.schema(SCHEMA).format(fmt).load(path)


def read_coordinate(spark: SparkSession, path: str) -> DataFrame:
    """Edges of a sparse matrix in coordinate text: '%' lines and the size line are skipped."""
    lines = spark.read.text(path).where(~F.col("value").startswith("%")).select(F.split(F.trim("value"), r"\s+").alias("x"), F.monotonically_increasing_id().alias("i"))
    size = lines.agg(F.min("i").alias("m"))
    rows = lines.join(F.broadcast(size), F.col("i") > F.col("m"))  # one row
    return rows.where(F.size("x") >= 2).select(F.col("x")[0].cast("long").alias("src"), F.col("x")[1].cast("long").alias("dst"))


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """(src, pos, dst) from lines of a vertex followed by its targets."""
    x = spark.read.text(path).select(F.split(F.trim("value"), r"\s+").alias("x"))
    return x.select(F.col("x")[0].cast("long").alias("src"), F.posexplode(F.slice("x", 2, 1 << 30)).alias("pos", "t")).select("src", "pos", F.col("t").cast("long").alias("dst"))


def stream_edges(spark: SparkSession, path: str, schema: str = "src long, dst long, ts timestamp, event_id long", max_files: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(path)


def stream_rate(spark: SparkSession, vertices: int = 1000, rows_per_second: int = 100) -> DataFrame:
    r = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return r.select((F.col("value") % vertices).alias("src"), F.pmod(F.xxhash64("value"), F.lit(vertices)).alias("dst"), F.col("timestamp").alias("ts"), F.col("value").alias("event_id"))


def write_parts(placed: DataFrame, path: str) -> None:
    """One folder per part; rows of a part are spread over a few files by source."""
    placed.repartition("part", F.pmod(F.xxhash64("src"), F.lit(4))).write.partitionBy("part").mode("overwrite").parquet(path)


def write_replicas(replicas: DataFrame, table: str, buckets: int = 16) -> None:
    """A bucketed table by vertex, so that later joins on v need no shuffle."""
    replicas.write.bucketBy(buckets, "v").sortBy("v").mode("overwrite").saveAsTable(table)
