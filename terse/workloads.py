"""The experiments, re-expressed on the given tables: each returns a trace or a small table of outcomes."""

from __future__ import annotations

import timeit
from math import inf

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from terse.functions.draws import draw
from terse.functions.vectors import dot
from terse.operators.allocate import assign
from terse.operators.codecs import NormTernary
from terse.operators.objectives import L1, ConvNet, Logistic, Perceptron, ResidualNet, Ridge, Softmax
from terse.plans import methods as M
from terse.plans.costs import time_vs_bandwidth
from terse.plans.engine import Fit, QuadraticSource, Sampler, SparkSource, fit, quadratic, regularised_optimum, ridge_problem, source_of, trace_frame
from terse.sources.tables import read, shared_folder, written

M_RIDGE = Ridge(0.1)
OUTCOME = "workload string, setting string, method string, value double"


def embedding_ridge(spark: SparkSession, sf_dir: str, workers: int = 10, target: str = "planted", how: str = "id") -> DataFrame:
    """Embeddings times 8 as features; target planted with noise, or the centred label; dealt by id or by label."""
    w = np.random.default_rng(7).normal(0, 1, 64)
    x = F.transform("embedding", lambda e: e.cast("double") * 8)
    noise = (F.pmod(F.xxhash64("row_id"), F.lit(2001)) - 1000) / 1000 * 0.17
    planted = F.aggregate(F.zip_with("x", F.array(*[F.lit(float(v)) for v in w]), lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b) + noise
    who = F.col("label") if how == "label" else F.pmod("vec_id", F.lit(workers))
    rows = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), who.cast("long").alias("worker_id"), x.alias("x"), "label")
    return rows.select("row_id", "worker_id", "x", (planted if target == "planted" else F.col("label") - 4.5).cast("double").alias("y"))


def _curves(source: QuadraticSource, block: int, steps=(0.05, 0.025), iterations: int = 600, every: int = 20, prefix: str = ""):
    best = source.optimum()
    out = []
    for step in steps:
        for m in M.seven_curves(block):
            f = fit(source, m, M.Schedule(step), iterations, optimum=best, every=every, measure_loss=True)
            for r in f.trace:
                r["method"] = f"{prefix}{m.name}@{step}"
            out.append(f)
    return out


def regression(spark, sf_dir) -> DataFrame:
    """Seven methods at two steps on embeddings with a planted model, and on the synthetic matrix at its default scale."""
    table = QuadraticSource.from_samples(embedding_ridge(spark, sf_dir), 0.1)
    synthetic = quadratic(ridge_problem())
    return trace_frame(spark, _curves(table, 16) + _curves(synthetic, 256, iterations=300, every=50, prefix="synthetic/"))


def _levels(df: DataFrame, column: str, most: int = 100) -> list[str]:
    """Values of a column of few values, all but the last (which the others tell); more than ``most`` are refused."""
    found = sorted(r[0] for r in df.select(column).where(F.col(column).isNotNull()).distinct().limit(most + 1).collect())
    if len(found) > most:
        raise ValueError(f"{column} has more than {most} values")
    return found[:-1]


def lineitem_features(spark: SparkSession, sf_dir: str, workers: int = 10) -> DataFrame:
    """Order lines with their order, customer and part as samples: eight standardised numbers, one-hot columns, and a planted target with noise."""
    orders = read(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderpriority")
    customer = read(spark, sf_dir, "customer", "c_custkey", "c_acctbal", "c_mktsegment")
    part = read(spark, sf_dir, "part", "p_partkey", "p_brand", "p_size", "p_retailprice")
    lines = read(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus")
    numbers = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "o_totalprice", "c_acctbal", "p_size", "p_retailprice"]
    hot = [(lines, "l_returnflag"), (lines, "l_linestatus"), (orders, "o_orderstatus"), (orders, "o_orderpriority"), (customer, "c_mktsegment"), (part, "p_brand")]
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey")).join(part, F.col("l_partkey") == F.col("p_partkey"))
    of = joined.agg(*[f(c).alias(f"{kind}_{c}") for c in numbers for kind, f in (("m", F.avg), ("s", F.stddev_pop))])
    scaled = [F.coalesce((F.col(c) - F.col(f"m_{c}")) / F.nullif(F.col(f"s_{c}"), F.lit(0.0)), F.lit(0.0)) for c in numbers]
    bits = [F.coalesce((F.col(c) == v).cast("double"), F.lit(0.0)) for df, c in hot for v in _levels(df, c)]
    planted = np.random.default_rng(11).normal(0, 1, len(scaled) + len(bits))
    rows = joined.crossJoin(F.broadcast(of)).select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("row_id"), F.pmod(F.xxhash64("l_orderkey"), F.lit(workers)).alias("worker_id"), F.array(*scaled, *bits).alias("x"))
    noise = (F.pmod(F.xxhash64("row_id"), F.lit(2001)) - 1000) / 1000 * 0.17
    return rows.withColumn("y", dot(F.col("x"), F.array(*[F.lit(float(v)) for v in planted])) + noise)


def lineitem_regression(spark, sf_dir) -> DataFrame:
    """Seven methods on order lines: one pass over the join, whatever the number of iterations.

    Rare one-hot columns curve little, so the ridge weight is 1 here: at 0.1 no method, plain descent included, is near the optimum after 1,000 iterations.
    """
    return trace_frame(spark, _curves(QuadraticSource.from_samples(lineitem_features(spark, sf_dir), 1.0), 16, iterations=500, every=20))


def proximal(spark, sf_dir) -> DataFrame:
    """The general form with a sparsity penalty against the exact optimum."""
    source = QuadraticSource.from_samples(embedding_ridge(spark, sf_dir), 0.1)
    prox = L1(0.05)
    best = regularised_optimum(source, prox)
    return trace_frame(spark, [fit(source, m, M.Schedule(0.05), 800, optimum=best, every=25) for m in (M.plain(prox), M.gradient_difference(16, prox=prox), M.two_way_residual(16, prox=prox))])


def scales(spark, sf_dir) -> DataFrame:
    """The synthetic regression at its three matrix scales and two seeds, step 0.05: distance after 300 iterations over that at the start."""
    rows = []
    for scale in ("half", "one", "uniform"):
        for seed in (3, 4):
            source = quadratic(ridge_problem(seed, scale=scale))
            best = source.optimum()
            for m in M.seven_curves(256):
                f = fit(source, m, M.Schedule(0.05), 300, optimum=best, every=300)
                rows.append(("scales", f"{scale},seed={seed}", m.name, float(min(f.trace[-1]["dist"] / np.linalg.norm(best), 1e12))))
    return spark.createDataFrame(rows, OUTCOME)


def sensitivity(spark, sf_dir) -> DataFrame:
    """Distance after 300 iterations over block size, anchor rate, apply rate and carry weight; blocks of 64 to 512, one setting at a time, on the synthetic matrix of 500 columns."""
    source = QuadraticSource.from_samples(embedding_ridge(spark, sf_dir), 0.1)
    best, rows = source.optimum(), []
    for block in (8, 16, 32, 64):
        for a in (0.05, 0.1, 0.2):
            for b in (0.5, 1.0):
                for e in (0.0, 0.5, 1.0):
                    f = fit(source, M.two_way_residual(block, a, b, e), M.Schedule(0.05), 300, optimum=best, every=300)
                    rows.append(("sensitivity", f"block={block},anchor={a},apply={b},carry={e}", "two_way_residual", float(min(f.trace[-1]["dist"], 1e12))))
    wide = quadratic(ridge_problem())
    best = wide.optimum()
    for block in (64, 128, 256, 512):
        for a, b, e in ((0.1, 1.0, 1.0), (0.05, 1.0, 1.0), (0.2, 1.0, 1.0), (0.1, 0.5, 1.0), (0.1, 1.0, 0.0), (0.1, 1.0, 0.5)):
            f = fit(wide, M.two_way_residual(block, a, b, e), M.Schedule(0.05), 200, optimum=best, every=200)
            rows.append(("sensitivity", f"wide,block={block},anchor={a},apply={b},carry={e}", "two_way_residual", float(min(f.trace[-1]["dist"], 1e12))))
    return spark.createDataFrame(rows, OUTCOME)


def diminishing(spark, sf_dir) -> DataFrame:
    """Methods with an error floor under a falling step."""
    source = QuadraticSource.from_samples(embedding_ridge(spark, sf_dir), 0.1)
    return trace_frame(spark, [fit(source, m, M.Schedule(0.05, slow=50), 1000, optimum=source.optimum(), every=50) for m in M.seven_curves(16) if m.name in ("quantized_gradient", "compensated_gradient", "two_sided_compensated", "two_sided_largest_k")])


def heterogeneous(spark, sf_dir) -> DataFrame:
    """Rows dealt by label, so that workers' optima differ."""
    source = QuadraticSource.from_samples(embedding_ridge(spark, sf_dir, target="label", how="label"), 0.1)
    return trace_frame(spark, _curves(source, 16, steps=(0.05,), iterations=800, every=50))


def speedup(spark, sf_dir) -> DataFrame:
    """Squared distance at which runs with global mini-batches settle, for growing numbers of workers."""
    best, rows = QuadraticSource.from_samples(embedding_ridge(spark, sf_dir, workers=1), 0.1).optimum(), []
    for n in (1, 2, 5, 10, 20):
        source = source_of(embedding_ridge(spark, sf_dir, workers=n), M_RIDGE)
        f = fit(source, M.two_way_residual(16), M.Schedule(0.05), 300, optimum=best, sampler=Sampler(8, "global"))
        rows.append(("speedup", f"n={n}", "two_way_residual", float(np.mean(f.column("dist")[-100:] ** 2))))
    return spark.createDataFrame(rows, OUTCOME)


def noise(spark, sf_dir) -> DataFrame:
    """Squared distance at which mini-batch runs settle, by batch size and step."""
    best, rows = QuadraticSource.from_samples(embedding_ridge(spark, sf_dir), 0.1).optimum(), []
    source = source_of(embedding_ridge(spark, sf_dir), M_RIDGE)
    for batch in (2, 8, 32):
        for step in (0.05, 0.025):
            f = fit(source, M.two_way_residual(16), M.Schedule(step), 500, optimum=best, sampler=Sampler(batch))
            rows.append(("noise", f"batch={batch},step={step}", "two_way_residual", float(np.mean(f.column("dist")[-150:] ** 2))))
    return spark.createDataFrame(rows, OUTCOME)


def pictures(spark: SparkSession, rows: int, seed: int = 5, spread: float = 1.6) -> DataFrame:
    """(row_id, x, y): vectors of 64 around one of ten fixed patterns, with noise that depends on the row alone: labels that can be learnt."""
    patterns = np.random.default_rng(13).normal(0, 1, (10, 64))
    y = F.floor(draw(seed, F.lit("label"), F.col("id")) * 10).cast("int")
    noise = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda j: (draw(seed, F.col("id"), j) + draw(seed + 1, F.col("id"), j) + draw(seed + 2, F.col("id"), j) - 1.5) * (2 * spread))
    every = F.array(*[F.array(*[F.lit(float(v)) for v in p]) for p in patterns])
    return spark.range(rows).withColumn("y", y).select(F.col("id").alias("row_id"), F.zip_with(F.get(every, F.col("y")), noise, lambda a, b: a + b).alias("x"), F.col("y").cast("long").alias("y"))


NET_ROWS, NET_BATCH = 320, 64
"""Rows of a worker and of its batches: five iterations are an epoch."""


def _nets(spark, objective, schedule, epochs) -> DataFrame:
    """Seven methods on planted pictures, ten workers, a fifth of the rows held out; a row of the trace for every epoch (five iterations)."""
    rows = pictures(spark, NET_ROWS * 10 * 5 // 4).withColumn("held", F.col("row_id") % 5 == 0)
    train = source_of(assign(rows.where("not held").drop("held"), 10, "even", name="worker_id"), objective)
    test = source_of(rows.where("held").drop("held").withColumn("worker_id", F.lit(0)), objective)
    start, per = objective.start(64, 1), NET_ROWS // NET_BATCH
    methods = [M.plain(), M.quantized_gradient(codec=NormTernary(inf, 256)), M.compensated_gradient(256), M.gradient_difference(256), M.two_sided_compensated(256), M.two_sided_largest_k(), M.two_way_residual(256)]
    fits = []
    for m in methods:
        parts, state = [], None
        for _ in range(epochs):  # one epoch at a time, so that its last iteration is what the trace tells
            f = fit(train, m, schedule, per, x0=start, sampler=Sampler(NET_BATCH), every=10**9, measure_loss=True, test=test.loss, state=state)
            parts.append(f.trace[-1])
            state = f.state
        fits.append(Fit(f.model, parts, f.state))
    return trace_frame(spark, fits)


def softmax(spark, sf_dir) -> DataFrame:
    return _nets(spark, Softmax(), M.Schedule(0.1), 12)


def conv_net(spark, sf_dir) -> DataFrame:
    """Convolutional net on 8 by 8 pictures, ten workers; the step falls to a tenth after 25 epochs."""
    return _nets(spark, ConvNet(), M.Schedule(0.1, 0.1, 25 * NET_ROWS // NET_BATCH), 28)


def residual_net(spark, sf_dir) -> DataFrame:
    """The step falls to a tenth after 100 epochs, beyond the run."""
    return _nets(spark, ResidualNet(), M.Schedule(0.01, 0.1, 100 * NET_ROWS // NET_BATCH), 16)


def perceptron(spark, sf_dir) -> DataFrame:
    return _nets(spark, Perceptron(), M.Schedule(0.1, 0.1, 25 * NET_ROWS // NET_BATCH), 28)


def bandwidth(spark, sf_dir) -> DataFrame:
    """Seconds of an iteration by method and bandwidth with measured gradient and coding times: a convolutional net's gradient on a batch of 256, coding of 11 million elements."""
    net, rng = ConvNet(), np.random.default_rng(1)
    x, y, w = rng.normal(size=(256, 64)), rng.integers(0, 10, 256).astype(float), net.start(64, 1)
    least = lambda f: min(timeit.repeat(f, number=1, repeat=3))
    compute, v = least(lambda: net.value_grad(w, x, y)), rng.normal(size=1_100_000)
    coding = 1_100_000 / least(lambda: NormTernary(inf, 256).apply(v, rng))
    out = time_vs_bandwidth(spark, compute_s=compute, coding_rate=coding)
    return out.select(F.lit("bandwidth").alias("workload"), F.concat(F.lit("mbps="), F.col("bandwidth_mbps").cast("int").cast("string")).alias("setting"), "method", F.col("seconds").alias("value"))


def hashed_words(spark: SparkSession, sf_dir: str, buckets: int) -> DataFrame:
    """Labelled documents (doc_id, lang, source, quality, toxic) with their words' counts by hash, of norm 4, as places and numbers."""
    docs = read(spark, sf_dir, "documents", "doc_id", "text", "lang", "source").where(F.col("text").isNotNull()).join(read(spark, sf_dir, "labels"), "doc_id")
    words = F.transform(F.split(F.lower("text"), " "), lambda w: F.pmod(F.xxhash64(w), F.lit(buckets)).cast("int"))
    keys = ["doc_id", "lang", "source", "quality", "toxic"]

    def counted(batches):
        for b in batches:
            if not b.num_rows:
                continue
            found = b.column("b")
            row = np.repeat(np.arange(b.num_rows), found.value_lengths().to_numpy(zero_copy_only=False))
            each, c = np.unique(row * buckets + found.flatten().to_numpy(zero_copy_only=False), return_counts=True)
            row, c = each // buckets, c.astype(float)
            v = c / np.sqrt(np.bincount(row, c * c, b.num_rows))[row] * 4
            ends = np.cumsum([0, *np.bincount(row, minlength=b.num_rows)]).astype(np.int32)
            x = pa.StructArray.from_arrays([pa.ListArray.from_arrays(ends, (each % buckets).astype(np.int32)), pa.ListArray.from_arrays(ends, v)], names=["at", "v"])
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), x], names=[*keys, "x"])

    bags = docs.select(*keys, words.alias("b")).groupBy(*keys).agg(F.flatten(F.collect_list("b")).alias("b"))
    return bags.mapInArrow(counted, "doc_id bigint, lang string, source string, quality int, toxic int, x struct<at: array<int>, v: array<double>>")


def text(spark, sf_dir, buckets: int = 4096, iterations: int = 12) -> DataFrame:
    """Logistic regression of the quality and toxic labels on hashed words, positives and negatives weighing alike, workers by language or by source: a Spark job per
    iteration, all methods in each pass.  Rows stay sparse, as counted once for all labels."""
    held = written(hashed_words(spark, sf_dir, buckets), shared_folder(spark), "words")
    rows = []
    for label, by in (("quality", "lang"), ("quality", "source"), ("toxic", "lang")):
        known = held.where(F.col(label).isNotNull())
        rare = known.agg(F.count_if(F.col(label) == 1).alias("ones"), F.count("*").alias("all")).first()
        few = 1 if rare["ones"] * 2 < rare["all"] else 0
        times = max(1, round(max(rare["ones"], rare["all"] - rare["ones"]) / max(1, min(rare["ones"], rare["all"] - rare["ones"]))))
        copies = F.explode(F.sequence(F.lit(1), F.when(F.col(label) == few, times).otherwise(1)))
        samples = known.withColumn("copy", copies).select((F.col("doc_id") * 64 + F.col("copy")).alias("row_id"), F.pmod(F.xxhash64(by), F.lit(4)).alias("worker_id"), "x", F.col(label).cast("double").alias("y"))
        source = SparkSource(samples, Logistic(), buckets)
        chosen = [M.plain(), M.quantized_gradient(64), M.gradient_difference(64), M.two_way_residual(64)]
        states = [M.State.start(np.zeros(source.d), source.n) for _ in chosen]
        for k in range(iterations):
            g, loss = source.gradients_of([s.shared for s in states], Sampler(), 1, k)
            for m, s, gm, lm in zip(chosen, states, g, loss, strict=True):
                M.iterate(m, s, gm, 0.5, 1, k)
                rows.append((f"text {label} by {by}", f"iter={k}", m.name, float(lm.mean())))
        source.close()
    return spark.createDataFrame(rows, OUTCOME)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The two-way method, the difference method and plain descent on embeddings: gradients by a Spark pass, then a trace."""
    source = QuadraticSource.from_samples(embedding_ridge(spark, sf_dir), 0.1)
    best = source.optimum()
    return trace_frame(spark, [fit(source, m, M.Schedule(0.05), 200, optimum=best, every=10, measure_loss=True) for m in (M.plain(), M.gradient_difference(16), M.two_way_residual(16))])

QUERIES = {
    "run_w1_all": regression, "run_w2_lineitem": lineitem_regression, "run_w3_softmax": softmax, "run_w4_text": text, "run_w5_conv": conv_net, "run_w5_perceptron": perceptron, "run_w6_residual": residual_net, "run_w9_lasso": proximal,
    "run_w1_scales": scales, "run_w7_bandwidth": bandwidth, "run_w10_grid": sensitivity, "run_w12_diminishing": diminishing, "run_w13_speedup": speedup, "run_w14_label_skew": heterogeneous, "run_w15_noise": noise, "run_flagship": flagship,
}
