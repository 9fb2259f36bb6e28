"""Seeded hashes that give the same value in Spark and in ANSI SQL engines with md5."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def text_of(*cols: Column | str) -> Column:
    return F.concat_ws(":", *[(F.col(c) if isinstance(c, str) else c).cast("string") for c in cols])


def hash32(*cols: Column | str, seed: int = 0) -> Column:
    """The first 32 bits of md5 over the seed and the columns, as a non-negative bigint."""
    return F.conv(F.substring(F.md5(text_of(F.lit(seed), *cols).cast("binary")), 1, 8), 16, 10).cast("long")


def bucket(*cols: Column | str, p: int, seed: int = 0, algo: str = "md5") -> Column:
    """Part 0..p-1 by hash; ``algo`` 'md5' (portable) or 'xx' (fast)."""
    if algo == "xx":
        return F.pmod(F.xxhash64(F.lit(seed), *cols), F.lit(p)).cast("int")
    return (hash32(*cols, seed=seed) % p).cast("int")


def vertex_id(key: Column) -> Column:
    """A 60-bit id of a natural key; ``operators.transforms.id_collisions`` tells if two keys share one."""
    return F.conv(F.substring(F.md5(key.cast("string").cast("binary")), 1, 15), 16, 10).cast("long")


def shuffle_key(*cols: Column | str, seed: int = 0) -> Column:
    """A seeded random-looking sort key."""
    return F.md5(text_of(F.lit(seed), *cols).cast("binary"))
