"""Line dedup by site-relative frequency, in DataFrame functions only.

Documents are grouped by host (the ``source`` column).  For each line the share of its host's documents that contain it
is computed; a line is boilerplate if that share is at least ``ratio``, and every copy of it on that host goes.  Other
lines stay in order.  A line that only one document of its host holds repeats nowhere, so it stays whatever the share
(``least`` = 2): a host with a single page would lose all its text otherwise.

Counting is spread: a document's distinct lines are partially counted before the shuffle by host and line, so that neither
a host with a third of all rows nor a line that is everywhere meets in one task.  Only lines that repeat are joined with
their hosts' totals.  A host has at most (mean lines a document) / ratio boilerplate lines.  Their table is broadcast if
its bytes (looked up first) are few; else the documents' lines are joined with it by host and line.  Both ways give the
same rows.

Odd input: a null text stays null; a null source is a host of its own; lines of white space only never count as
boilerplate; a text that loses all lines becomes empty; rows that repeat count each; a null or repeated id changes
nothing; an empty table gives no rows; other columns pass unchanged, whatever their names, but for ``n_lines`` and
``n_dropped``, which the result has with ``counts`` (the default) and which replace columns of these names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import frames

RATIO, LEAST = 0.10, 2
#: Bytes of boilerplate lines up to which their table is broadcast.
BROADCAST_BYTES = 16 << 20


def boilerplate(docs: DataFrame, ratio: float = RATIO, least: int = LEAST) -> DataFrame:
    """Rows (host, line, n_docs, n_host) of the lines that are dropped."""
    docs = docs.select(F.coalesce(F.col("source").cast("string"), F.lit("\u0000")).alias("host"), F.col("text").cast("string").alias("text"))
    hosts = docs.groupBy("host").agg(F.count("*").alias("n_host"))
    lines = docs.where("text is not null").select("host", F.explode(F.array_distinct(F.split("text", "\n", -1))).alias("line"))
    lines = lines.where(F.col("line").rlike("[^\\x20\\x09-\\x0D]"))
    counted = lines.groupBy("host", "line").agg(F.count("*").alias("n_docs")).where(F.col("n_docs") >= least)
    return counted.join(hosts, "host").where(F.col("n_docs") >= ratio * F.col("n_host")).select("host", "line", "n_docs", "n_host")


def drop_boilerplate(docs: DataFrame, ratio: float = RATIO, least: int = LEAST, counts: bool = True) -> DataFrame:
    """``docs`` with new ``text`` and, with ``counts``, the columns ``n_lines`` and ``n_dropped``."""
    scratch = frames.Scratch(docs.sparkSession, "lines")
    table = scratch.keep(boilerplate(docs, ratio, least).select("host", "line"), "boilerplate")
    # The rows travel as one value, so that no name of theirs can meet one of ours.
    rest = [c for c in docs.columns if c != "text"]
    rows = docs.select(F.struct(*rest).alias("row"), F.coalesce(F.col("source").cast("string"), F.lit("\u0000")).alias("host"), F.col("text").cast("string").alias("text"))
    rows = rows.withColumn("lines", F.split("text", "\n", -1))
    if (table.agg(F.sum(F.length("line") + F.length("host") + 16)).first()[0] or 0) <= BROADCAST_BYTES:
        sets = table.groupBy("host").agg(F.collect_list("line").alias("bad"))
        out = rows.join(F.broadcast(sets), "host", "left")
    else:
        keyed = scratch.keep(rows.withColumn("nth", F.monotonically_increasing_id()), "rows")
        each = keyed.select("nth", "host", F.explode(F.array_distinct("lines")).alias("line")).join(table, ["host", "line"], "left_semi")
        out = keyed.join(each.groupBy("nth").agg(F.collect_list("line").alias("bad")), "nth", "left")
    out = out.withColumn("kept", F.when(F.col("bad").isNotNull() & F.arrays_overlap("lines", "bad"), F.filter("lines", lambda x: ~F.array_contains("bad", x))).otherwise(F.col("lines")))
    size = lambda c: F.when(F.col("text").isNotNull(), F.size(c)).otherwise(0).cast("long")
    text = F.when(F.size("kept") < F.size("lines"), F.array_join("kept", "\n")).otherwise(F.col("text"))
    made = {"text": text, **({"n_lines": size("lines"), "n_dropped": size("lines") - size("kept")} if counts else {})}
    own = [made.pop(c).alias(c) if c in made else F.col("row").getField(c).alias(c) for c in docs.columns]
    return out.select(*own, *[v.alias(c) for c, v in made.items()])


ORACLE = f"""
WITH d AS (SELECT doc_id, coalesce(source, chr(0)) AS host, text, string_split(text, chr(10)) AS ls FROM documents),
hosts AS (SELECT host, count(*) AS n_host FROM d GROUP BY host),
u AS (SELECT host, unnest(list_distinct(ls)) AS line FROM d),
bad AS (SELECT u.host, u.line FROM u JOIN hosts USING (host) WHERE regexp_matches(u.line, '[^\\x20\\x09-\\x0D]')
  GROUP BY u.host, u.line, n_host HAVING count(*) >= {LEAST} AND count(*) >= {RATIO} * n_host),
sets AS (SELECT host, list(line) AS bad FROM bad GROUP BY host),
k AS (SELECT d.*, CASE WHEN bad IS NULL THEN ls ELSE list_filter(ls, lambda x: NOT list_contains(bad, x)) END AS kept FROM d LEFT JOIN sets USING (host))
SELECT doc_id, CASE WHEN text IS NULL THEN NULL ELSE array_to_string(kept, chr(10)) END AS text,
  CAST(coalesce(len(ls), 0) AS BIGINT) AS n_lines, CAST(coalesce(len(ls) - len(kept), 0) AS BIGINT) AS n_dropped FROM k
"""
