"""What a method sends: nominal and exact bits, savings, message counts, and time over a link."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from terse.sources.tables import read

FLOAT_BITS, TRIT_BITS = 32.0, 1.5
BLOCKS = (16, 64, 128, 256, 320, 512)
COMPUTE_S, CODING_RATE = 0.2, 5e7
"""Stand-ins where nothing is measured: seconds of a gradient, and elements coded (or decoded) in a second."""


def bits_raw(d: Column) -> Column:
    return d.cast("double") * FLOAT_BITS


def bits_ternary(d: Column, b: Column, exact: bool = False) -> Column:
    n_blocks = F.ceil(d.cast("double") / b) if exact else d.cast("double") / b
    return n_blocks * FLOAT_BITS + d * TRIT_BITS


#: legs of each method: (coded up, coded down)
LEGS = {
    "plain": (False, False),
    "quantized_gradient": (True, False),
    "ternary_gradient": (True, False),
    "compensated_gradient": (True, False),
    "gradient_difference": (True, False),
    "two_sided_compensated": (True, True),
    "two_way_residual": (True, True),
}


def sizes(spark: SparkSession, dims: tuple[int, ...] = (64, 500, 11_000_000), block_sizes: tuple[int, ...] = BLOCKS) -> DataFrame:
    return blocked(spark.createDataFrame([(x,) for x in dims], "d bigint"), block_sizes)


def messages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, d): every embedding that is there as a message of so many numbers."""
    return read(spark, sf_dir, "embeddings", "vec_id", F.size("embedding").cast("long").alias("d")).where("d > 0")


def blocked(sizes: DataFrame, block_sizes: tuple[int, ...] = BLOCKS) -> DataFrame:
    return sizes.crossJoin(F.broadcast(sizes.sparkSession.createDataFrame([(x,) for x in block_sizes], "block bigint")))


def bits_per_iteration(spark: SparkSession, sizes_: DataFrame | None = None) -> DataFrame:
    """Bits a worker sends and receives, and what that saves against raw vectors both ways; of given sizes (d, block, and columns that stay), or of ``sizes``."""
    of = sizes(spark) if sizes_ is None else sizes_
    legs = spark.createDataFrame([(m, *v) for m, v in LEGS.items()], "method string, up boolean, down boolean")
    coded, raw = bits_ternary(F.col("d"), F.col("block")), bits_raw(F.col("d"))
    bits = F.when(F.col("up"), coded).otherwise(raw) + F.when(F.col("down"), coded).otherwise(raw)
    return of.crossJoin(F.broadcast(legs)).select("method", *of.columns, bits.alias("bits"), (1 - bits / (2 * raw)).alias("saving"))


def links(spark: SparkSession) -> DataFrame:
    """Star and all-to-all networks at six bandwidths."""
    rows = [(t, float(b), 0.1) for t in ("star", "all_to_all") for b in (1000, 500, 200, 100, 50, 10)]
    return spark.createDataFrame(rows, "topology string, bandwidth_mbps double, latency_ms double")


def iteration_time(compute_s: Column, bits_up: Column, bits_down: Column, n: int, link: Column, topology: Column) -> Column:
    """Seconds: computing plus what passes the busiest link (the server's in a star; a worker's own among peers), link in Mbit/s."""
    star = n * (bits_up + bits_down)
    peers = (n - 1) * 2 * bits_up
    return compute_s + F.when(topology == "star", star).otherwise(peers) / (link * 1e6)


def time_vs_bandwidth(spark: SparkSession, d: int = 11_000_000, block: int = 256, n: int = 10, compute_s: float = COMPUTE_S, coding_rate: float = CODING_RATE) -> DataFrame:
    """Seconds of an iteration by method and bandwidth: gradient, coding of each coded leg, and what passes the server's link."""
    per = bits_per_iteration(spark).where((F.col("d") == d) & (F.col("block") == block))
    raw = bits_raw(F.col("d"))
    coded = bits_ternary(F.col("d"), F.col("block"))
    up = F.when(F.col("method") == "plain", raw).otherwise(coded)
    down = F.col("bits") - up
    star = links(spark).where("topology = 'star'")
    legs = F.element_at(F.create_map(*[F.lit(v) for m, (u, w) in LEGS.items() for v in (m, int(u) + int(w))]), F.col("method"))
    busy = F.lit(compute_s) + legs * F.col("d") / F.lit(coding_rate)
    return star.crossJoin(F.broadcast(per)).select("method", "bandwidth_mbps", iteration_time(busy, up, down, n, F.col("bandwidth_mbps"), F.col("topology")).alias("seconds"))


def message_edges(spark: SparkSession, sf_dir: str, workers: tuple[int, ...] = (2, 5, 10, 20)) -> DataFrame:
    """Messages of an iteration by topology: to and from a server, or from each worker to every other; workers are those that hold an embedding when these are dealt by id."""
    n = F.explode(F.array(*[F.lit(w).cast("long") for w in workers]))
    held = messages(spark, sf_dir).select("vec_id", n.alias("workers")).select("workers", F.pmod("vec_id", F.col("workers")).alias("sender")).where("sender is not null").distinct()
    peers = held.join(held.withColumnRenamed("sender", "receiver"), "workers").where("sender <> receiver").select("workers", F.lit("all_to_all").alias("topology"))
    star = held.select("workers", F.explode(F.array(F.lit("star"), F.lit("star"))).alias("topology"))
    return peers.unionByName(star).groupBy("topology", "workers").agg(F.count("*").alias("messages"))
