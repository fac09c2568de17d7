"""Tables in, samples and messages out: scans with given schemas, sinks, shared folders, and a data source of wire messages."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

#: fixed values: the columns of the given tables
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, "
    "l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


def read(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    """A table with its fixed schema; named columns only are read."""
    df = spark.read.schema(SCHEMAS[table]).parquet(f"{sf_dir}/{table}.parquet")
    return df.select(*columns) if columns else df


def require(df: DataFrame, schema: str) -> DataFrame:
    """The frame, if it has these columns with these types."""
    have = {f.name: f.dataType.simpleString() for f in df.schema}
    want = {f.name: f.dataType.simpleString() for f in StructType.fromDDL(schema)}
    wrong = {k: (v, have.get(k)) for k, v in want.items() if have.get(k) != v}
    if wrong:
        raise TypeError(f"columns that do not fit: {wrong}")
    return df


def shared_folder(spark: SparkSession) -> str:
    """A new folder that all executors share, under spark.checkpoint.dir (a local master may do without the setting)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        root = "file:///tmp/checkpoints"
    return f"{root.rstrip('/')}/terse-{uuid.uuid4().hex}"


def written(df: DataFrame, folder: str, name: str) -> DataFrame:
    """Rows written as Parquet and read again: short plans, and nothing lost with an executor."""
    df.write.mode("overwrite").parquet(f"{folder}/{name}")
    return df.sparkSession.read.schema(df.schema).parquet(f"{folder}/{name}")


def write_samples(samples: DataFrame, path: str, parts: int = 8) -> None:
    """Samples by worker; inside a worker by a draw, so that a run of files is a batch and pruning replaces a random filter."""
    salted = samples.withColumn("part", F.pmod(F.xxhash64("row_id"), F.lit(parts)))
    salted.repartition(parts, "worker_id", "part").sortWithinPartitions("worker_id", "part", "row_id").write.mode("overwrite").partitionBy("worker_id", "part").parquet(path)


def bucketed(samples: DataFrame, table: str, n: int = 8, path: str | None = None) -> None:
    """Samples in a table bucketed and sorted by worker: joins by worker need no exchange.  With a path its files are there."""
    writer = samples.write.mode("overwrite").bucketBy(n, "worker_id").sortBy("worker_id")
    (writer.option("path", path) if path else writer).saveAsTable(table)


def append(df: DataFrame, path: str, by: str = "run_id") -> None:
    """Traces and messages: appended Parquet, by run."""
    df.write.mode("append").partitionBy(by).parquet(path)


FORMATS = ("parquet", "orc", "json", "csv")


def round_trip(df: DataFrame, folder: str, kind: str) -> DataFrame:
    """A frame written and read in another format."""
    writer, reader = df.write.mode("overwrite"), df.sparkSession.read.schema(df.schema)
    if kind == "csv":
        writer, reader = writer.option("header", True), reader.option("header", True)
    writer.format(kind).save(f"{folder}/{kind}")
    return reader.format(kind).load(f"{folder}/{kind}")


def text_lines(spark: SparkSession, path: str) -> DataFrame:
    """Lines of text files, with the file of each."""
    return spark.read.text(path).select(F.col("_metadata.file_path").alias("path"), "value")


def whole_files(spark: SparkSession, path: str, pattern: str = "*") -> DataFrame:
    """Files as bytes: path, length, content."""
    return spark.read.format("binaryFile").option("pathGlobFilter", pattern).load(path).select("path", "length", "content")


class MessageSource(DataSource):
    """Coded vectors of simulated workers: options workers, dim, block, seed; a partition for each worker."""

    @classmethod
    def name(cls) -> str:
        return "terse_messages"

    def schema(self) -> str:
        return "sender bigint, n_elems int, n_nonzero int, payload binary"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _MessageReader(self.options)


class _MessageReader(DataSourceReader):
    def __init__(self, options):
        self.options = dict(options)

    def partitions(self):
        return [InputPartition(i) for i in range(int(self.options.get("workers", "4")))]

    def read(self, partition) -> Iterator[tuple]:
        import numpy as np

        from terse.functions.draws import generator
        from terse.operators.codecs import NormTernary
        from terse.operators.wire import pack_ternary

        d, block = int(self.options.get("dim", "64")), int(self.options.get("block", "16"))
        rng = generator(int(self.options.get("seed", "1")), partition.value)
        q = NormTernary(np.inf, block).apply(rng.normal(size=d), rng)
        yield int(partition.value), d, int((q != 0).sum()), pack_ternary(q, block)
