"""Vectors as arrays, as rows of blocks, and as rows of coordinates; conversions and array expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

GRID = 1 << 20
"""Grid units in 1: sums of whole grid units do not depend on their order."""


def snap(value: Column) -> Column:
    """A double as the nearest whole number (halves up)."""
    return F.floor(value + F.lit(0.5)).cast("long")


def to_grid(value: Column, unit: int = GRID) -> Column:
    return snap(value.cast("double") * F.lit(float(unit)))


def coordinates(df: DataFrame, keys: list[str], vector: str, name: str = "v") -> DataFrame:
    """One row for each element: keys, coord, value."""
    return df.select(*keys, F.posexplode(F.col(vector)).alias("coord", name)).withColumn("coord", F.col("coord").cast("long"))


def blocks(df: DataFrame, keys: list[str], vector: str, size: int) -> DataFrame:
    """One row for each block of at most ``size`` elements: keys, block_id, vals."""
    n = F.size(vector)
    cut = F.transform(F.sequence(F.lit(0), F.floor((n - 1) / size).cast("int")), lambda b: F.slice(F.col(vector), b * size + 1, F.lit(size)))
    return df.where(n > 0).select(*keys, F.posexplode(cut).alias("block_id", "vals"))


def uneven_blocks(df: DataFrame, keys: list[str], vector: str, sizes: list[int]) -> DataFrame:
    """One row for each block of the given lengths."""
    starts = [1 + sum(sizes[:k]) for k in range(len(sizes))]
    cut = F.array(*[F.slice(F.col(vector), s, n) for s, n in zip(starts, sizes, strict=True)])
    return df.select(*keys, F.posexplode(cut).alias("block_id", "vals"))


def from_blocks(df: DataFrame, keys: list[str], vals: str = "vals", vector: str = "vector") -> DataFrame:
    ordered = F.sort_array(F.collect_list(F.struct("block_id", vals)))
    return df.groupBy(*keys).agg(F.flatten(F.transform(ordered, lambda b: b[vals])).alias(vector))


def from_coordinates(df: DataFrame, keys: list[str], value: str = "v", vector: str = "vector") -> DataFrame:
    ordered = F.sort_array(F.collect_list(F.struct("coord", value)))
    return df.groupBy(*keys).agg(F.transform(ordered, lambda e: e[value]).alias(vector))


def let(value: Column, body) -> Column:
    """``body`` of a value that is worked out once, where a lambda would work it out for every element."""
    return F.transform(F.array(value), body)[0]


def by_blocks(vals: Column, block: int | None, body) -> Column:
    """``body`` of every block of an array and the place of its first element, put together again; without blocks, of the array."""
    if block is None:
        return body(vals, F.lit(0))
    starts = F.sequence(F.lit(0), F.greatest(F.size(vals) - 1, F.lit(0)), F.lit(block))
    return F.flatten(F.transform(starts, lambda s: body(F.slice(vals, s + 1, F.lit(block)), s)))


def total(vals: Column, of=lambda v: v) -> Column:
    return F.aggregate(vals, F.lit(0.0), lambda acc, v: acc + of(v))


def norm(vals: Column, p: float) -> Column:
    """The p-norm of an array; infinity is the largest magnitude."""
    if p == float("inf"):
        return F.coalesce(F.array_max(F.transform(vals, F.abs)), F.lit(0.0))
    if p == 1:
        return total(vals, F.abs)
    if p == 2:
        return F.sqrt(total(vals, lambda v: v * v))
    return F.pow(total(vals, lambda v: F.pow(F.abs(v), F.lit(p))), F.lit(1 / p))


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: x * y))


def distance2(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)))


def vector_sum(df: DataFrame, keys: list[str], vector: str, salts: int = 0) -> DataFrame:
    """Element-wise sums of arrays per key, in coordinates: partial sums before the shuffle.

    With ``salts`` the sum goes in two levels, so a hot key's rows are added by many tasks first.
    """
    parts = coordinates(df, keys, vector)
    if salts:
        parts = parts.withColumn("_salt", F.spark_partition_id() % salts).groupBy(*keys, "coord", "_salt").agg(F.sum("v").alias("v"))
    return parts.groupBy(*keys, "coord").agg(F.sum("v").alias("v"))
