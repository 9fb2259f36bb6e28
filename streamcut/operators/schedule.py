"""The relational prepass of the greedy methods: degree comparisons, classes and placement positions.

Neither observed degrees nor the postponement of edges depend on where edges are placed, only on the stream's order.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .stateless import running_count, with_degrees
from .transforms import number_rows, running_sum

END = 1 << 62


def _cmp(a, b):
    return F.signum(a - b).cast("int")


def _in_degree_at(stream: DataFrame, probes: DataFrame) -> DataFrame:
    return running_count(stream.select(F.col("dst").alias("v"), F.col("seq").alias("pos")), probes)


def indegree_schedule(stream: DataFrame, count_before: bool = True) -> DataFrame:
    """(src, dst, arrival, seq, place_seq, cmp, class, guarded): cmp is the sign of D_in(u) - D_in(v) at the edge's arrival."""
    at = F.col("seq") if count_before else F.col("seq") - 1
    probes = stream.select("seq", at.alias("pos"), F.explode(F.array(F.struct(F.col("src").alias("v"), F.lit(0).alias("side")), F.struct(F.col("dst").alias("v"), F.lit(1).alias("side")))).alias("e")).select("e.v", "pos", "seq", "e.side")
    n = _in_degree_at(stream, probes).groupBy("seq").agg(F.max(F.when(F.col("side") == 0, F.col("n"))).alias("du"), F.max(F.when(F.col("side") == 1, F.col("n"))).alias("dv"))
    return stream.join(n, "seq").select("src", "dst", "arrival", "seq", F.col("seq").alias("place_seq"), _cmp(F.col("du"), F.col("dv")).alias("cmp"), F.lit("small").alias("class"), F.lit(True).alias("guarded"))


def degree_schedule(stream: DataFrame, degrees: DataFrame | None = None, degree: str = "total") -> DataFrame:
    """As ``indegree_schedule`` with the final degrees of the graph (or given ones)."""
    known = with_degrees(stream, degree, degrees)
    return known.select("src", "dst", "arrival", "seq", F.col("seq").alias("place_seq"), _cmp(F.col("du"), F.col("dv")).alias("cmp"), F.lit("known").alias("class"), F.lit(True).alias("guarded"))


def plain_schedule(stream: DataFrame) -> DataFrame:
    return stream.select("src", "dst", "arrival", "seq", F.col("seq").alias("place_seq"), F.lit(0).alias("cmp"), F.lit("small").alias("class"), F.lit(True).alias("guarded"))


def total_degree_base(stream: DataFrame, release: str = "first") -> DataFrame:
    """What the total-degree method needs of each edge, whatever the parts and the hub threshold.

    Rows (src, dst, arrival, seq, out_u, known, cmp_in, cmp_all, cmp_late, late_arrival): whether the target's block has
    come; the signs of the difference of in-degrees and of total degrees at the edge's arrival, and of total degrees when
    the target's block comes (or at the end of the stream, with no out-edges of the target); and when that is.
    """
    blocks = stream.groupBy("src").agg(F.count("*").alias("d_out"), F.min("arrival").alias("came"), F.min("seq").alias("first_seq"), F.max("seq").alias("last_seq"))
    e = stream.select("src", "dst", "arrival", "seq").join(blocks.select("src", F.col("d_out").alias("out_u")), "src")
    e = e.join(blocks.select(F.col("src").alias("dst"), F.col("d_out").alias("out_v"), F.col("came").alias("came_v"), "first_seq", "last_seq"), "dst", "left")
    e = e.withColumn("known", F.col("came_v").isNotNull() & (F.col("came_v") <= F.col("arrival")))
    last = stream.agg(F.max("seq").alias("m"))
    e = e.crossJoin(F.broadcast(last))  # one row
    # In-degree events up to this position are seen when a held edge is placed.
    late = F.when(F.col("came_v").isNull(), F.col("m")).otherwise(F.col("first_seq") - 1 if release == "first" else F.col("last_seq"))
    ends = [F.struct(F.col(c).alias("v"), F.lit(k).alias("side")) for k, c in enumerate(("src", "dst"))]
    now = e.select("seq", F.col("seq").alias("pos"), F.explode(F.array(*ends)).alias("x"))
    # Only an edge whose target hasn't come can be held.
    then = e.where("not known").select("seq", late.alias("pos"), F.explode(F.array(*[x.withField("side", x["side"] + 2) for x in ends])).alias("x"))
    n = _in_degree_at(stream, now.unionByName(then).select("x.v", "pos", "seq", "x.side")).groupBy("seq").agg(*[F.max(F.when(F.col("side") == k, F.col("n"))).alias(c) for k, c in enumerate(("in_u", "in_v", "late_u", "late_v"))])
    e, out_v = e.join(n, "seq"), F.coalesce("out_v", F.lit(0))
    return e.select(
        "src", "dst", "arrival", "seq", "out_u", "known", _cmp(F.col("in_u"), F.col("in_v")).alias("cmp_in"), _cmp(F.col("in_u") + F.col("out_u"), F.col("in_v") + out_v).alias("cmp_all"),
        _cmp(F.col("late_u") + F.col("out_u"), F.col("late_v") + out_v).alias("cmp_late"), F.coalesce("came_v", F.lit(END)).alias("late_arrival"),
    )


def total_degree_rows(base: DataFrame, p: int, hub_threshold: int | None = None, guard_scope: str = "direct", release: str = "first") -> DataFrame:
    """The decision table over ``total_degree_base``, ordered by (place_arrival, phase, seq): a projection.

    Target known: total degrees at the edge's arrival.  Unknown and the source has fewer than ``hub_threshold`` (p)
    out-edges: in-degrees.  Else postponed to the target's block or the end of the stream: total degrees then.
    """
    limit = p if hub_threshold is None else hub_threshold
    e = base.withColumn("class", F.when(F.col("known"), "known").when(F.col("out_u") < F.lit(limit), "small").otherwise("postponed"))
    late = F.col("class") == "postponed"
    cmp = F.when(late, F.col("cmp_late")).when(F.col("known"), F.col("cmp_all")).otherwise(F.col("cmp_in"))
    guarded = {"all": F.lit(True), "none": F.lit(False), "direct": ~late}[guard_scope]
    return e.select(
        "src", "dst", "arrival", "seq", cmp.alias("cmp"), "class", guarded.alias("guarded"), F.when(late, F.col("late_arrival")).otherwise(F.col("arrival")).alias("place_arrival"),
        F.when(late, 0 if release == "first" else 2).otherwise(1).alias("phase"),
    )


def total_degree_schedule(
    stream: DataFrame, p: int, hub_threshold: int | None = None, guard_scope: str = "direct", release: str = "first", flush: str = "end", rows: int | None = None
) -> DataFrame:
    """``total_degree_rows`` with positions.  ``flush`` 'drop' marks edges whose target never comes as dropped.

    ``rows``: the stream's edges, if their number is known.
    """
    placed = total_degree_rows(total_degree_base(stream, release), p, hub_threshold, guard_scope, release)
    if flush == "drop":
        placed = placed.withColumn("dropped", F.col("place_arrival") == END)
    return number_rows(placed, [F.col("place_arrival"), F.col("phase"), F.col("seq")], "place_seq", rows)


def buffer_occupancy(schedule: DataFrame) -> DataFrame:
    """(arrival, buffered): edges held after each arrival of a block; the last row (arrival = END) is after the flush."""
    moves = schedule.where("class = 'postponed'").select(F.explode(F.array(F.struct(F.col("arrival").alias("a"), F.lit(1).alias("d")), F.struct(F.col("place_arrival").alias("a"), F.lit(-1).alias("d")))).alias("m"))
    steps = moves.groupBy(F.col("m.a").alias("arrival")).agg(F.sum("m.d").alias("d"))
    return running_sum(steps, "arrival", "d", "buffered").select("arrival", "buffered")
