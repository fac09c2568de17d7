"""Shared pieces of the training-data operators: tables in the shared folder, checked broadcasts, components."""

from __future__ import annotations

import ctypes
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

BLANK_CLASS = r"[\x20\x09-\x0D]+"
"""Java and RE2 pattern for runs of the ASCII blanks that part words."""

BLANK_CHARS = " \t\n\x0b\x0c\r"

BROADCAST_ROWS = 1_000_000
"""Rows of narrow tables (a few numbers a row) that may be broadcast; beyond it joins shuffle."""


def shared_folder(spark: SparkSession) -> str:
    """A new folder that driver and executors share: under spark.checkpoint.dir.

    The setting is read from the session.  Where it is unset, only a local master may go on (tests): there one
    machine is everything, and /tmp/checkpoints serves.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        root = "file:///tmp/checkpoints"
    return f"{root.rstrip('/')}/terse-{uuid.uuid4().hex}"


def written(df: DataFrame, folder: str, name: str) -> DataFrame:
    """Writes the rows as Parquet in the shared folder and reads them back: cuts lineage, survives lost executors."""
    path = f"{folder}/{name}"
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> bool:
    """Whether a written table has at most so many rows (looks at no more than that)."""
    return df.limit(rows + 1).count() <= rows


def bounded(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """Marks a written table for broadcast if it is proven small; otherwise leaves the join to a shuffle."""
    return F.broadcast(df) if small(df, rows) else df


def without(docs: DataFrame, gone: DataFrame, *keys: Column) -> DataFrame:
    """The rows of docs whose keys are not among the (narrow, distinct) rows of gone, nulls being equal; columns as in docs.

    Keys are compared under names that no column of docs has.
    """
    gone = written(gone.toDF(*(f"__gone_{i}" for i in range(len(keys)))), shared_folder(docs.sparkSession), "gone")
    keyed = docs.withColumns({f"__key_{i}": key for i, key in enumerate(keys)})
    same = None
    for i in range(len(keys)):
        equal = F.col(f"__key_{i}").eqNullSafe(F.col(f"__gone_{i}"))
        same = equal if same is None else same & equal
    return keyed.join(bounded(gone), same, "left_anti").select(*docs.columns)


def small_batches(spark: SparkSession, size: int = 4 << 20) -> None:
    """Bounds the bytes of a batch that travels to Python; 10,000 long texts would take many times that in the JVM, and again in the worker.

    A setting of the session that may change while it runs; results do not depend on it, and a smaller bound stays.
    """
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.conf.get(name, None)
    if not (now and now.isdigit() and int(now) <= size):
        spark.conf.set(name, str(size))


def give_back() -> None:
    """Returns memory that a worker has freed to the system, so that workers that wait do not hold what a task needed for a while."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def words(text: Column) -> Column:
    """Words of a text as an array; null has none."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), BLANK_CLASS), lambda w: w != "")


def held_out(doc_id: Column, modulus: int, remainder: int) -> Column:
    """Whether crc32 of the id as text has this remainder; a null id counts as empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % modulus == remainder


def components(edges: DataFrame, folder: str, name: str, max_rounds: int = 60) -> DataFrame:
    """Connected components of undirected edges (a, b long): rows (node, root), root the smallest node.

    Alternates large-star and small-star steps until the edges no longer change.  Each step is one shuffle by
    node and keeps at most one edge per node and neighbour; every round is written to the shared folder.
    Hot nodes cost no more than their edges: minima are aggregates with partial sums, joined back by node.
    """
    seen = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    seen = written(seen, folder, f"{name}-0")
    mark = None
    for k in range(max_rounds):
        both = seen.unionByName(seen.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low2 = large.groupBy("u").agg(F.min("v").alias("m"))
        small_star = (
            large.join(low2, "u")
            .select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e"))
            .select("e.u", "e.v")
            .where("u <> v")
            .distinct()
        )
        seen = written(small_star, folder, f"{name}-{k + 1}")
        now = seen.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError("components did not settle")
    return seen.select(F.col("u").alias("node"), F.col("v").alias("root"))
