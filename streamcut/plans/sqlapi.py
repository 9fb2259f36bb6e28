"""SQL access: temporary functions that Catalyst inlines, and a table function for the greedy methods."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..operators.kernel import Buffered, check_live
from ..operators.stateless import constraint_set, grid_shape


@udtf(returnType="src long, dst long, seq long, part int")
class PartitionEdges:
    """partition_edges(TABLE(stream) PARTITION BY (run) ORDER BY (seq), method, p): columns src, dst, seq of the table.

    Each partition is a stream of its own, with the default guard.  The total-degree method takes an unbroken run of rows
    of one source as its block; what it still holds comes out at the end.  An unknown method is an error.
    """

    def __init__(self):
        self.engine: Buffered | None = None
        self.block: tuple[int, list[int], int] | None = None

    def eval(self, row, method: str, p: int) -> Iterator[tuple]:
        if self.engine is None:
            self.method, self.engine = check_live(method), Buffered(p)
        u, v, s = row["src"], row["dst"], row["seq"]
        if self.method != "greedy_total_degree":
            yield u, v, s, self.engine.edge(u, v, s, self.method)
        elif self.block is not None and self.block[0] == u:
            self.block[1].append(v)
        else:
            if self.block is not None:
                yield from self.engine.block(*self.block)
            self.block = (u, [v], s)

    def terminate(self) -> Iterator[tuple]:
        if self.block is not None:
            yield from self.engine.block(*self.block)
            yield from self.engine.flush()


def register(spark: SparkSession, grid: tuple[int, ...] = (4, 8, 16, 32, 48, 64)) -> None:
    """edge_part(src, dst, p, seed), grid_part_<p>(src, dst, seed) for each p of ``grid``, occupancy(p, n), partition_edges."""
    h = "cast(conv(substr(md5(cast(concat_ws(':', {}) as binary)), 1, 8), 16, 10) as bigint)"
    of = lambda seed, *cols: h.format(", ".join(f"cast({c} as string)" for c in (seed, *cols)))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION edge_part(src BIGINT, dst BIGINT, p INT, seed INT) RETURNS INT RETURN cast({of('seed', 'src', 'dst')} % p as int)")
    for p in grid:
        shape = grid_shape(p)
        cells = shape[0] * shape[1]
        sets = "array(" + ", ".join(f"array({', '.join(map(str, constraint_set(k, p, shape)))})" for k in range(cells)) + ")"
        common = f"array_intersect(element_at({sets}, cast({of('seed', 'src')} % {cells} as int) + 1), element_at({sets}, cast({of('seed', 'dst')} % {cells} as int) + 1))"
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION grid_part_{p}(src BIGINT, dst BIGINT, seed INT) RETURNS INT RETURN element_at({common}, cast({of('seed + 1', 'src', 'dst')} % size({common}) as int) + 1)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION occupancy(p INT, n BIGINT) RETURNS DOUBLE RETURN 1 - pow(1 - 1D / p, n)")
    spark.udtf.register("partition_edges", PartitionEdges)
