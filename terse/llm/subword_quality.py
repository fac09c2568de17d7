"""Quality classifier by supervised subword embeddings.

Every word, every pair of words in a row and every run of 3 to 5 bytes inside a word (with a blank as its boundary) is hashed to a row of an embedding table.
A document is the average of its rows, words, pairs and runs having equal parts in it (runs would drown the others); a softmax over two classes reads it.  Table and softmax are learnt together by stochastic gradient descent in numpy, on a
sample of labelled documents whose size is a parameter.  Tasks turn the sampled texts into bags of rows, and one task learns from them.

As the softmax of two classes is linear in the average, each row adds one number to the log-odds; workers get these numbers (a table of
fixed size) and score whole texts in a few vector operations per batch.

Defined cases: null and empty texts have no rows and score the learnt bias; labels that are null are left out; ids labelled more than once
count once; without labels of both classes the score is the share of good labels, or one half; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from terse.llm.common import held_out, shared_folder, written
from terse.llm.text_kernel import BLANKS, doc_chunks, mix64, utf8_buffer, word_hashes, word_spans

_U4 = np.uint32
_ODD = np.uint64(0x9E3779B97F4A7C15)


@dataclass(frozen=True)
class SubwordPlan:
    """sample: labelled documents learnt from at most; rows: of the embedding table; dim: its width; pairs: whether pairs of words have rows;
    shortest, longest: byte runs; epochs, rate, seed: of the descent."""

    sample: int = 5000
    rows: int = 1 << 19
    dim: int = 8
    pairs: bool = True
    shortest: int = 3
    longest: int = 5
    epochs: int = 6
    rate: float = 3.0
    seed: int = 5


def subword_rows(raw: np.ndarray, offsets: np.ndarray, plan: SubwordPlan) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(kind, documents, rows): words, pairs of words in a row, then byte runs of each length."""
    n_docs = len(offsets) - 1
    starts, _, firsts = word_spans(raw, offsets)
    of_word = np.repeat(np.arange(n_docs), np.diff(firsts))
    words = word_hashes(raw, starts, False)
    yield 0, of_word, (words % np.uint64(plan.rows)).astype(np.int32)
    if plan.pairs:
        both = np.flatnonzero(of_word[1:] == of_word[:-1])
        yield 1, of_word[both], (mix64(words[both] * _ODD + words[both + 1]) % np.uint64(plan.rows)).astype(np.int32)
    # one blank before, between and behind documents, so that no run crosses from one to the next
    owner = np.repeat(np.arange(n_docs, dtype=np.int32), np.diff(offsets))
    padded = np.full(len(raw) + n_docs + 1, 0x20, np.uint8)
    at = np.arange(len(raw)) + owner + 1
    padded[at] = np.where(BLANKS[raw], np.uint8(0x20), raw)
    whose = np.zeros(len(padded), np.int32)
    whose[at] = owner
    blank = padded == 0x20
    wide = padded.astype(_U4)
    h = wide.copy()
    inner = np.ones(len(padded), bool)  # no blank strictly inside the run
    for k in range(2, plan.longest + 1):
        h = h[:-1] * _U4(0x01000193) ^ wide[k - 1 :]
        if k > 2:
            inner = inner[:-1] & ~blank[k - 2 : -1]
        else:
            inner = inner[:-1]
        if k >= plan.shortest:
            keep = np.flatnonzero(inner)
            mixed = h[keep] * _U4(0x9E3779B1)
            yield 2, whose[keep + 1], ((mixed ^ (mixed >> _U4(15))) * _U4(0x85EBCA77 + 2 * k) >> _U4(8)).astype(np.int32) % plan.rows


def bags_of(column: pa.Array, plan: SubwordPlan) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Per document: its distinct rows and their shares."""
    raw, offsets = utf8_buffer(column)
    for d in range(len(column)):
        kinds: list[list[np.ndarray]] = [[], [], []]
        for kind, _, rows in subword_rows(raw[offsets[d] : offsets[d + 1]], np.array([0, offsets[d + 1] - offsets[d]]), plan):
            kinds[kind].append(rows)
        held = [x for x in (np.concatenate([*k, np.zeros(0, np.int32)]) for k in kinds) if len(x)]
        rows, at = np.unique(np.concatenate([*held, np.zeros(0, np.int32)]), return_inverse=True)
        parts = np.concatenate([*(np.full(len(x), 1 / len(x) / len(held)) for x in held), np.zeros(0)])
        yield rows.astype(np.int32), np.bincount(at, parts, len(rows)).astype(np.float32)


def learn(bags: list[tuple[np.ndarray, np.ndarray]], good: np.ndarray, plan: SubwordPlan) -> tuple[np.ndarray, float]:
    """Log-odds that each embedding row adds (before averaging) and the bias."""
    n = len(good)
    share = float(good.mean()) if n else 0.5
    if not n or share in (0.0, 1.0):
        share = min(max(share, 1e-3), 1 - 1e-3)
        return np.zeros(plan.rows, np.float32), float(np.log(share / (1 - share)))
    rng = np.random.default_rng(plan.seed)
    table = rng.uniform(-1 / plan.dim, 1 / plan.dim, (plan.rows, plan.dim)).astype(np.float32)
    soft = np.zeros((plan.dim, 2), np.float32)
    bias = np.log(np.array([1 - share, share], np.float32))
    steps, done = plan.epochs * n, 0
    for _ in range(plan.epochs):
        for d in rng.permutation(n):
            rows, weight = bags[d]
            own = table[rows]
            mean = weight @ own
            z = mean @ soft + bias
            p = np.exp(z - z.max())
            p /= p.sum()
            p[int(good[d])] -= 1
            rate = plan.rate * (1 - done / steps)
            back = soft @ p
            soft -= 0.1 * rate * np.outer(mean, p)
            bias -= 0.01 * rate * p
            table[rows] = own - (rate * 50 * weight)[:, None] * back
            done += 1
    return table @ (soft[:, 1] - soft[:, 0]), float(bias[1] - bias[0])


def fit(docs: DataFrame, labels: DataFrame, usable: Column, plan: SubwordPlan = SubwordPlan()) -> tuple[np.ndarray, float]:
    """Learns from at most ``plan.sample`` labelled documents (chosen by hash of their id) among those that ``usable`` admits."""
    chosen = (
        labels.where(F.col("quality").isNotNull() & usable).groupBy("doc_id").agg(F.max("quality").cast("int").alias("good"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(plan.sample)
    )
    texts = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id").select(F.col("doc_id").cast("long").alias("doc_id"), "good", "text")

    def bags(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                part = batch.slice(a, 256)
                found = list(bags_of(part.column("text"), plan))
                columns = [pa.array([x[i].tobytes() for x in found], pa.binary()) for i in (0, 1)]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("good"), *columns], names=["doc_id", "good", "rows", "shares"])

    def learnt(table: pa.Table) -> pa.Table:
        order = pc.sort_indices(table, [("doc_id", "ascending"), ("rows", "ascending"), ("shares", "ascending")])
        rows, shares = table.column("rows").combine_chunks(), table.column("shares").combine_chunks()
        found = [(np.frombuffer(rows[i].as_buffer(), np.int32), np.frombuffer(shares[i].as_buffer(), np.float32)) for i in order.to_pylist()]
        adds, bias = learn(found, table.column("good").take(order).to_numpy().astype(int), plan)
        return pa.table({"adds": pa.array([adds.astype(np.float32).tobytes()], pa.binary()), "bias": [bias]})

    rows = written(texts.mapInArrow(bags, "doc_id bigint, good int, rows binary, shares binary"), shared_folder(docs.sparkSession), "bags")
    model = rows.withColumn("all", F.lit(0)).groupBy("all").applyInArrow(learnt, "adds binary, bias double").first()
    return (np.frombuffer(model["adds"], np.float32), model["bias"]) if model else learn([], np.zeros(0), plan)


def score(docs: DataFrame, model: tuple[np.ndarray, float], plan: SubwordPlan = SubwordPlan()) -> DataFrame:
    """doc_id and score, the probability of good, of whole texts."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        adds, bias = shared.value
        for batch in batches:
            raw, offsets = utf8_buffer(batch.column("text"))
            ids = batch.column("doc_id")
            for a, b in doc_chunks(offsets):
                part, own = raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
                total, count = np.zeros((3, b - a)), np.zeros((3, b - a))
                for kind, who, rows in subword_rows(part, own, plan):
                    total[kind] += np.bincount(who, adds[rows], b - a)
                    count[kind] += np.bincount(who, minlength=b - a)
                odds = (total / np.maximum(count, 1)).sum(0) / np.maximum((count > 0).sum(0), 1) + bias
                yield pa.RecordBatch.from_arrays([ids.slice(a, b - a), pa.array(1 / (1 + np.exp(-np.clip(odds, -50, 50))))], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id bigint, score double")


def op5_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    out = held_out(F.col("doc_id"), 4, 2)
    return score(docs, fit(docs, labels, ~out)).select("doc_id", out.alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
