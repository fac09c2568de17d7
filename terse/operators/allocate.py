"""Which worker holds which row: even runs in order, by hash, by range of a key, or sorted by label so that workers differ."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from terse.sources.tables import shared_folder, written


def numbered(df: DataFrame, *order: str, name: str = "_n") -> DataFrame:
    """Rows numbered from 0 in a global order, without bringing them to one task: a range exchange, then counts of the partitions before.

    The ranges are written down before they are counted: their bounds come from a sample, and a second run of the exchange could draw others.
    """
    ranged = written(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()), shared_folder(df.sparkSession), "ranges")
    counts = ranged.groupBy("_part").agg(F.count("*").alias("_size"))
    starts = counts.select("_part", (F.sum("_size").over(Window.orderBy("_part")) - F.col("_size")).alias("_start"))
    inside = Window.partitionBy("_part").orderBy(*order)
    placed = ranged.withColumn("_place", F.row_number().over(inside) - 1).join(F.broadcast(starts), "_part")
    return placed.withColumn(name, F.col("_start") + F.col("_place")).drop("_part", "_place", "_start")


def assign(df: DataFrame, n: int, how: str = "hash", key: str = "row_id", name: str = "worker") -> DataFrame:
    """Adds the worker (0 to n - 1) of every row."""
    if how == "hash":
        return df.withColumn(name, F.pmod(F.xxhash64(key), F.lit(n)))
    if how not in ("even", "label_skew", "range"):
        raise ValueError(f"unknown allocation {how}")
    order = ("label", key) if how == "label_skew" else (key,)
    total = df.count()
    return numbered(df, *order).withColumn(name, F.expr(f"_n * {n} div {max(total, 1)}")).drop("_n")
