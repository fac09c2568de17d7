"""A training corpus from documents: toxicity, line dedup, near duplicates, benchmark decontamination, mixing.

Each stage works on all rows that its predecessor kept and returns the columns of documents; the last returns the mix per document.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from terse.llm import decontaminate, line_dedup, nearest_toxic, shingle_join, source_mix
from terse.llm.common import held_out, shared_folder, written


def drop_toxic_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = nearest_toxic.fit(docs, labels, ~held_out(F.col("doc_id"), 5, 0))
    return nearest_toxic.drop_toxic(docs, model)


def drop_boilerplate_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return line_dedup.dedup_lines(docs).withColumn("n_chars", F.char_length("text").cast("long")).select(*docs.columns)


def keep_one_of_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return shingle_join.keep_first(docs, shingle_join.JoinRule(width=5, percent=80))


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.drop_leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return source_mix.mix_digest(docs)


STAGES = [
    ("toxicity", drop_toxic_documents),
    ("line_dedup", drop_boilerplate_lines),
    ("near_duplicates", keep_one_of_near_duplicates),
    ("decontamination", drop_benchmark_leaks),
    ("mix", mix_sources),
]

ORACLE_SQL = None
"""The toxicity scores are learnt, which SQL cannot express; tests compare the run with a brute-force version."""


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written as Parquet and read again by the next."""
    folder = shared_folder(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = written(stage(spark, docs, sf_dir), folder, f"stage-{k}-{name}")
    return docs
