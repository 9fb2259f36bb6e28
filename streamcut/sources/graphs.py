"""Named graphs on the given tables, each with the DuckDB SQL that extracts the same edges.

Edges are distinct pairs (src, dst) of bigint.  Text keys get 60-bit md5 ids.  Where the two ends of an edge play roles
with overlapping keys (an order and a part), the target is stored as -1 - key.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import vertex_id
from ..operators import native


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names: tuple[str, ...]) -> None:
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def other_side(key: Column) -> Column:
    return (F.lit(-1) - key).cast("long")


def _edges(df: DataFrame, src: Column, dst: Column) -> DataFrame:
    return df.select(src.cast("long").alias("src"), dst.cast("long").alias("dst")).where("src is not null and dst is not null").distinct()


def _next_words(df: DataFrame) -> DataFrame:
    native.register(df.sparkSession)
    pairs = df.select(F.inline(F.call_function(native.PAIRS, F.lower(F.col("text")))))
    return _edges(pairs, F.col("a"), F.col("b"))


def _hrefs(pages: DataFrame) -> DataFrame:
    host = F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1)
    return pages.select("page_id", host.alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))


def _knn(emb: DataFrame, k: int, block: int = 1024) -> DataFrame:
    """The ``k`` nearest by cosine, exactly: every vector is a query, asked in blocks against blocks of all vectors.

    The work is that of all pairs; a task holds two blocks and passes on ``k`` rows a query.
    """
    n = max(1, -(-emb.count() // block))
    e = emb.select("vec_id", F.col("embedding").cast("array<double>").alias("embedding"), F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int").alias("own"))
    other = F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    asked = e.select(F.col("own").alias("q"), other.alias("d"), F.lit(1).alias("ask"), "vec_id", "embedding")
    there = e.select(other.alias("q"), F.col("own").alias("d"), F.lit(0).alias("ask"), "vec_id", "embedding")

    def nearest(t: pa.Table) -> pa.Table:
        t = t.sort_by("vec_id")
        ask, ids = t.column("ask").to_numpy() == 1, t.column("vec_id").to_numpy()
        x = np.stack(t.column("embedding").to_pylist()) if len(ids) else np.zeros((0, 1))
        norm = np.sqrt((x * x).sum(axis=1))
        c = np.round(x[ask] @ x[~ask].T / norm[ask][:, None] / norm[~ask], 9) if ask.any() and not ask.all() else np.zeros((int(ask.sum()), 0))
        c[ids[ask][:, None] == ids[~ask]] = -np.inf
        top = np.argsort(-c, axis=1, kind="stable")[:, :k]
        src = np.repeat(ids[ask], top.shape[1])
        out = pa.table([src, ids[~ask][top].ravel(), np.take_along_axis(c, top, axis=1).ravel()], names=["src", "dst", "c"])
        return out.filter(pa.array(out.column("src").to_numpy() != out.column("dst").to_numpy()))

    pairs = asked.unionByName(there).groupBy("q", "d").applyInArrow(nearest, "src long, dst long, c double")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("c"), "dst"))
    return pairs.withColumn("r", rank).where(F.col("r") <= k).select("src", "dst")


_ID = "CAST(('0x' || substr(md5({}), 1, 15)) AS BIGINT)"


def _word_sql(table: str) -> str:
    return f"""SELECT DISTINCT {_ID.format("w[i]")} AS src, {_ID.format("w[i + 1]")} AS dst FROM (
      SELECT w, unnest(range(1, len(w))) AS i FROM (SELECT list_filter(regexp_split_to_array(lower(text), '[^\\p{{L}}]+'), lambda x: x <> '') AS w FROM {table}))"""


def _doc_word_sql(key: str, table: str, flip: bool = False) -> str:
    a, b = f"{key}", f"-1 - {_ID.format('x')}"
    a, b = (b, a) if flip else (a, b)
    return f"SELECT DISTINCT {a} AS src, {b} AS dst FROM (SELECT {key}, unnest(list_filter(regexp_split_to_array(lower(text), '[^\\p{{L}}]+'), lambda x: x <> '')) AS x FROM {table})"


@dataclass(frozen=True)
class Graph:
    build: Callable[[SparkSession, str], DataFrame]
    sql: str
    note: str


def _t(name: str, f: Callable[[DataFrame], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: f(load(spark, d, name))


def _bag(key: str):
    def edges(df: DataFrame) -> DataFrame:
        native.register(df.sparkSession)
        return _edges(df.select(key, F.explode(F.call_function(native.WORDS, F.lower(F.col("text")))).alias("w")), F.col(key), other_side(F.col("w")))

    return edges


def _flip(f):
    return lambda df: f(df).select(F.col("dst").alias("src"), F.col("src").alias("dst"))


def _user_next(df: DataFrame) -> DataFrame:
    # The whole table is one time line; days are chained by carrying the first user of the next day that has one.
    day = F.to_date("ts")
    w = Window.partitionBy("day").orderBy("ts", "event_id")
    e = df.select("user_id", "ts", "event_id", day.alias("day")).withColumn("nxt", F.lead("user_id").over(w))
    first = e.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("f"))
    nextday = first.withColumn("g", F.lead("f").over(Window.orderBy("day"))).select("day", "g")  # a row per day
    return _edges(e.join(F.broadcast(nextday), "day"), F.col("user_id"), F.coalesce("nxt", "g"))


def _part_next(df: DataFrame) -> DataFrame:
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey")
    return _edges(df.select("l_partkey", F.lead("l_partkey").over(w).alias("n")), F.col("l_partkey"), F.col("n"))


def _trade(flow: bool):
    def build(spark: SparkSession, d: str) -> DataFrame:
        o = load(spark, d, "orders").select(F.col("o_orderkey").alias("k"), F.col("o_custkey").alias("c_custkey")).join(load(spark, d, "customer").select("c_custkey", "c_nationkey"), "c_custkey")
        li = load(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), F.col("l_suppkey").alias("s_suppkey")).join(load(spark, d, "supplier").select("s_suppkey", "s_nationkey"), "s_suppkey")
        e = o.select("k", "c_nationkey").join(li.select("k", "s_nationkey"), "k")
        return _edges(e, F.col("c_nationkey"), F.col("s_nationkey") if flow else other_side(F.col("s_nationkey")))

    return build


def _cust_supp(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "orders").select(F.col("o_orderkey").alias("k"), "o_custkey").join(load(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), "l_suppkey"), "k")
    return _edges(e, F.col("o_custkey"), other_side(F.col("l_suppkey")))


_TRADE = "SELECT DISTINCT CAST(c_nationkey AS BIGINT) AS src, CAST({} AS BIGINT) AS dst FROM orders JOIN customer ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey"
_HREF = "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages"

GRAPHS: dict[str, Graph] = {
    "word_next_doc": Graph(_t("documents", _next_words), _word_sql("documents"), "skewed on both sides, largest"),
    "word_next_conv": Graph(_t("conversations", _next_words), _word_sql("conversations"), "skewed on both sides"),
    "doc_word": Graph(_t("documents", _bag("doc_id")), _doc_word_sql("doc_id", "documents"), "in-degree skew"),
    "word_doc": Graph(_t("documents", _flip(_bag("doc_id"))), _doc_word_sql("doc_id", "documents", True), "out-degree skew"),
    "conv_word": Graph(_t("conversations", _bag("conv_id")), _doc_word_sql("conv_id", "conversations"), "in-degree skew, small"),
    "host_link": Graph(_t("pages", lambda p: _edges(_hrefs(p), vertex_id(F.col("host")), vertex_id(F.col("href")))), f"SELECT DISTINCT {_ID.format('host')} AS src, {_ID.format('href')} AS dst FROM ({_HREF})", "crawl"),
    "page_link": Graph(_t("pages", lambda p: _edges(_hrefs(p), F.col("page_id"), other_side(vertex_id(F.col("href"))))), f"SELECT DISTINCT page_id AS src, -1 - {_ID.format('href')} AS dst FROM ({_HREF})", "crawl with leaf targets"),
    "user_next": Graph(_t("events", _user_next), "SELECT DISTINCT user_id AS src, n AS dst FROM (SELECT user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS n FROM events) WHERE n IS NOT NULL", "dense time-stamped stream"),
    "user_key": Graph(_t("events", lambda e: _edges(e, F.col("user_id"), other_side(F.get_json_object("props", "$.k").cast("long")))), "SELECT DISTINCT user_id AS src, -1 - CAST(json_extract(props, '$.k') AS BIGINT) AS dst FROM events WHERE json_extract(props, '$.k') IS NOT NULL", "JSON target"),
    "order_part": Graph(_t("lineitem", lambda x: _edges(x, F.col("l_orderkey"), other_side(F.col("l_partkey")))), "SELECT DISTINCT l_orderkey AS src, -1 - l_partkey AS dst FROM lineitem", "little skew"),
    "supp_part": Graph(_t("lineitem", lambda x: _edges(x, F.col("l_suppkey"), other_side(F.col("l_partkey")))), "SELECT DISTINCT l_suppkey AS src, -1 - l_partkey AS dst FROM lineitem", "hubs against a small side"),
    "cust_supp": Graph(_cust_supp, "SELECT DISTINCT o_custkey AS src, -1 - l_suppkey AS dst FROM orders JOIN lineitem ON l_orderkey = o_orderkey", "dense bipartite"),
    "part_next": Graph(_t("lineitem", _part_next), "SELECT DISTINCT l_partkey AS src, n AS dst FROM (SELECT l_partkey, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey) AS n FROM lineitem) WHERE n IS NOT NULL", "one kind of vertex"),
    "nation_trade": Graph(_trade(False), _TRADE.format("-1 - s_nationkey"), "smallest"),
    "nation_flow": Graph(_trade(True), _TRADE.format("s_nationkey"), "smallest whose targets arrive"),
    "vec_knn": Graph(_t("embeddings", lambda e: _knn(e, 8)), """SELECT src, dst FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(
      list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: CAST(z[1] AS DOUBLE) * CAST(z[2] AS DOUBLE))) / sqrt(list_sum(list_transform(a.embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))))
      / sqrt(list_sum(list_transform(b.embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 9) DESC, b.vec_id) AS r FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 8""", "constant out-degree, in-degree hubs"),
}


def edges(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return GRAPHS[name].build(spark, sf_dir)
