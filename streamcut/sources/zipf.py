"""Synthetic graphs: Zipf out-degrees with uniform targets, united with Zipf in-degrees with uniform sources."""

from __future__ import annotations

import math
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.hashing import hash32
from ..operators.transforms import number_rows
from ..plans.scratch import keep

#: The fifteen exponent pairs (out, in): fixed values, first those with the in-degree at least as skewed, then the others.
PAIRS = (
    (2.2, 2.2), (2.2, 2.1), (2.2, 2.0), (2.2, 1.9), (2.1, 2.1), (2.1, 2.0), (2.1, 1.9), (2.0, 2.0), (2.0, 1.9),
    (2.1, 2.2), (2.0, 2.2), (2.0, 2.1), (1.9, 2.2), (1.9, 2.1), (1.9, 2.0),
)


#: Degrees with a step of their own; above, a step is a SPREAD-th of its first degree wide, and even inside.
SINGLE, SPREAD = 4096, 64


def _tail(dmax: int) -> list[int]:
    """First degrees of the steps above SINGLE, with dmax + 1 at the end."""
    out = [SINGLE + 1]
    while out[-1] <= dmax:
        out.append(min(dmax + 1, out[-1] + out[-1] // SPREAD))
    return out


def cdf(exponent: float, dmax: int) -> list[int]:
    """Upper bounds, in 2**32, of the steps of the degrees 1..dmax."""
    w = [k**-exponent for k in range(1, min(dmax, SINGLE) + 1)]
    if dmax > SINGLE:
        # The sum over a step as an integral between half degrees: its error is about a 10**-8th up here.
        over = (lambda x: math.log(x)) if exponent == 1 else (lambda x: x ** (1 - exponent) / (1 - exponent))
        cuts = _tail(dmax)
        w += [over(b - 0.5) - over(a - 0.5) for a, b in zip(cuts, cuts[1:])]
    total, run, out = sum(w), 0.0, []
    for x in w:
        run += x
        out.append(int(run / total * 2**32))
    out[-1] = 2**32
    return out


def steps(exponent: float, dmax: int) -> list[tuple[int, int, int, int]]:
    """(first degree, degrees, lo, hi): a hash h of lo..hi-1 has the degree first + (h - lo) * degrees // (hi - lo)."""
    cuts = [*range(1, min(dmax, SINGLE) + 1), *(_tail(dmax) if dmax > SINGLE else [dmax + 1])]
    bounds = cdf(exponent, dmax)
    return [(a, b - a, lo, hi) for a, b, lo, hi in zip(cuts, cuts[1:], [0, *bounds], bounds)]


def _side(vertices: DataFrame, n: int, exponent: float, dmax: int, seed: int) -> DataFrame:
    """(v, w): each of ``vertices`` (v) with as many numbers below ``n`` as its degree."""
    v = vertices.select("v", hash32("v", seed=seed).alias("h"))
    table = vertices.sparkSession.createDataFrame(steps(exponent, dmax), "a long, width long, lo long, hi long")
    # A range join with a table of a few thousand rows.
    d = v.join(F.broadcast(table), (F.col("h") >= F.col("lo")) & (F.col("h") < F.col("hi"))).select("v", F.expr("a + (h - lo) * width div (hi - lo)").alias("d"))
    return d.select("v", F.explode(F.sequence(F.lit(1), F.col("d").cast("int"))).alias("j")).select("v", (hash32("v", "j", seed=seed + 1) % n).alias("w"))


def zipf_graph(spark: SparkSession, n: int, alpha: float, beta: float, dmax: int | None = None, seed: int = 0) -> DataFrame:
    """Distinct edges over vertices 0..n-1; a pure function of the arguments."""
    top = (n - 1) if dmax is None else dmax
    v = spark.range(n).select(F.col("id").alias("v"))
    out = _side(v, n, alpha, top, seed).select(F.col("v").alias("src"), F.col("w").alias("dst"))
    inn = _side(v, n, beta, top, seed + 100).select(F.col("w").alias("src"), F.col("v").alias("dst"))
    return out.unionByName(inn).distinct()


def zipf_on(keys: DataFrame, alpha: float, beta: float, dmax: int, seed: int = 0) -> DataFrame:
    """As ``zipf_graph`` over the keys of a table (one column of whole numbers; null is no key) in place of 0..n-1."""
    v = keys.select(F.col(keys.columns[0]).cast("long").alias("v")).where("v is not null").distinct()
    numbered = keep(number_rows(v, [F.col("v")], "w"), "keys")
    n = numbered.count()
    other = numbered.select("w", F.col("v").alias("x"))
    # Without keys there are no rows to take a remainder for.
    out, inn = (_side(numbered, max(n, 1), e, dmax, s).join(other, "w") for e, s in ((alpha, seed), (beta, seed + 100)))
    return out.select(F.col("v").alias("src"), F.col("x").alias("dst")).unionByName(inn.select(F.col("x").alias("src"), F.col("v").alias("dst"))).distinct()


def zipf_on_sql(keys: str, alpha: float, beta: float, dmax: int, seed: int = 0) -> str:
    """DuckDB SQL for ``zipf_on``; ``keys`` selects the column v.  For ``dmax`` up to SINGLE."""
    h = "CAST(('0x' || substr(md5({}), 1, 8)) AS BIGINT)"

    def side(exponent: float, s: int) -> str:
        values = ", ".join(f"({a}, {lo}, {hi})" for a, _, lo, hi in steps(exponent, dmax))
        key, pair = h.format(f"'{s}:' || v"), h.format(f"'{s + 1}:' || v || ':' || j")
        return f"""SELECT o.v, k.v AS x FROM (SELECT v, {pair} % (SELECT count(*) FROM k) AS w FROM (SELECT v, unnest(range(1, d + 1)) AS j FROM (
          SELECT v, d FROM (SELECT v, {key} AS h FROM k) JOIN (VALUES {values}) s(d, lo, hi) ON h >= lo AND h < hi))) o JOIN k ON k.w = o.w"""

    return f"""WITH k AS (SELECT v, row_number() OVER (ORDER BY v) - 1 AS w FROM (SELECT DISTINCT CAST(v AS BIGINT) AS v FROM ({keys}) WHERE v IS NOT NULL))
    SELECT DISTINCT src, dst FROM (SELECT v AS src, x AS dst FROM ({side(alpha, seed)}) UNION ALL SELECT x, v FROM ({side(beta, seed + 100)}))"""


def zipf_sql(n: int, alpha: float, beta: float, dmax: int | None = None, seed: int = 0) -> str:
    """DuckDB SQL for the same graph."""
    top = (n - 1) if dmax is None else dmax
    h = "CAST(('0x' || substr(md5({}), 1, 8)) AS BIGINT)"

    def side(exponent: float, s: int, cols: str) -> str:
        wide = top > SINGLE
        values = ", ".join(f"({a}, {width}, {lo}, {hi})" if wide else f"({a}, {lo}, {hi})" for a, width, lo, hi in steps(exponent, top))
        degree, names = ("a + (h - lo) * width // (hi - lo) AS d", "a, width, lo, hi") if wide else ("d", "d, lo, hi")
        key, pair = h.format(f"'{s}:' || v"), h.format(f"'{s + 1}:' || v || ':' || j")
        return f"""SELECT {cols} FROM (SELECT v, {pair} % {n} AS w FROM (SELECT v, unnest(range(1, d + 1)) AS j FROM (
          SELECT v, {degree} FROM (SELECT v, {key} AS h FROM range({n}) t(v)) JOIN (VALUES {values}) s({names}) ON h >= lo AND h < hi)))"""

    return f"SELECT DISTINCT src, dst FROM ({side(alpha, seed, 'v AS src, w AS dst')} UNION ALL {side(beta, seed + 100, 'w AS src, v AS dst')})"


class _Part(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.n, self.parts = int(options.get("n", 1000)), int(options.get("parts", 4))
        self.alpha, self.beta, self.seed = float(options.get("alpha", 2.0)), float(options.get("beta", 2.0)), int(options.get("seed", 0))

    def partitions(self):
        step = -(-self.n // self.parts)
        return [_Part(k, min(self.n, k + step)) for k in range(0, self.n, step)]

    def read(self, partition) -> Iterator[tuple]:
        import bisect
        import hashlib

        h = lambda *x: int(hashlib.md5(":".join(map(str, x)).encode()).hexdigest()[:8], 16)
        for exponent, seed, flip in ((self.alpha, self.seed, False), (self.beta, self.seed + 100, True)):
            bounds, table = cdf(exponent, self.n - 1), steps(exponent, self.n - 1)
            for v in range(partition.lo, partition.hi):
                a, width, lo, hi = table[bisect.bisect_right(bounds, x := h(seed, v))]
                for j in range(1, a + (x - lo) * width // (hi - lo) + 1):
                    w = h(seed + 1, v, j) % self.n
                    yield (w, v) if flip else (v, w)


class ZipfSource(DataSource):
    """``spark.read.format("zipf_edges")`` with options n, alpha, beta, seed, parts; edges may repeat (use distinct)."""

    @classmethod
    def name(cls) -> str:
        return "zipf_edges"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)
