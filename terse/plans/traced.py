"""Measures of runs: every query reads the tables of iterations that methods have really made, and its SQL makes the same iterations itself.

The problem has a known optimum and workers that pull apart at it: every embedding is a row of two workers, with a planted target plus an offset for the one and less the
same offset for the other, and no ridge weight.  The offsets cancel in the mean, so the planted model is the exact optimum, while each worker's gradient there
is not 0.  A fifth of the embeddings is held out.  Arithmetic is in whole grid units, so both engines give the same rows.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from terse.functions.draws import draw, draw_sql
from terse.functions.vectors import GRID
from terse.plans.sharded import FEATURES_SQL, TWO_WAY, UNIT, Plan, run, sql_iterations, sql_samples, worker_gradients
from terse.sources.tables import shared_folder, written

COMMON = {"l2": 0.0, "step": 0.3, "iterations": 6, "seed": 17}
TRACED = {
    p.name: p
    for p in (
        Plan("plain", **COMMON),
        Plan("quantized_gradient", "ternary2", **COMMON),
        Plan("gradient_difference", "ternary", anchor_rate=0.1, **COMMON),
        Plan("two_sided_compensated", "ternary", "gradient", "ternary", memory=1.0, carry=1.0, **COMMON),
        replace(TWO_WAY, name="two_way_residual", **COMMON),
    )
}
K = COMMON["iterations"]
D, BLOCK = 64, 16
RAW_BITS, CODED_BITS = 32 * D, 32 * D // BLOCK + D * 3 // 2
BITS = {p.name: (RAW_BITS if p.up == "identity" else CODED_BITS) + (RAW_BITS if p.down == "raw" else CODED_BITS) for p in TRACED.values()}
BATCHES, REDRAWS = 4, 16

QUERIES: dict = {}
SQL: dict[str, str] = {}


# ---- the runs as tables -------------------------------------------------------------------------------------------------


def _sum(x: Column) -> Column:
    return F.sum(x).cast("long")


def planted() -> Column:
    return ((F.col("coord") % 5 - 2) * GRID).cast("long")


def mirrored_samples(emb: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(samples, targets) of ten workers and (row_id, coord, v) of the embeddings held out."""
    v = F.floor(F.col("e").cast("double") * 8.0 * UNIT + 0.5).cast("long")
    long = emb.select(F.col("vec_id").cast("long").alias("vec_id"), F.posexplode("embedding").alias("coord", "e")).select("vec_id", F.col("coord").cast("long").alias("coord"), v.alias("v"))
    held = draw(21, F.col("vec_id"), mode="portable") >= 0.8
    sides = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(1).cast("long")))
    both = long.where(~held).withColumn("side", sides).withColumn("row_id", F.col("vec_id") * 2 + F.col("side")).withColumn("worker", F.col("vec_id") % 5 + 5 * F.col("side"))
    offset = (F.pmod(F.col("vec_id") * 7919, F.lit(2001)) - 1000) * (GRID // 2048)
    target = _sum(F.col("v") * (F.col("coord") % 5 - 2)) * (GRID // UNIT)
    targets = both.groupBy("row_id", "worker", "vec_id", "side").agg(target.alias("y0")).select("row_id", "worker", (F.col("y0") + F.when(F.col("side") == 0, offset).otherwise(-offset)).alias("y"))
    return both.select("row_id", "worker", "coord", "v"), targets, long.where(held).withColumnRenamed("vec_id", "row_id")


_MADE: dict[tuple[str, str], dict[str, DataFrame]] = {}


def traces(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """The tables of all runs, made once for a session and folder: samples, targets, held, rows, models (method, iter, coord, x, r) and workers (method, iter, worker, coord, a, v, q)."""
    key = spark.sparkContext.applicationId, sf_dir
    if key not in _MADE:
        folder = shared_folder(spark)
        samples, targets, held = (written(t, folder, n) for t, n in zip(mirrored_samples(spark.read.parquet(f"{sf_dir}/embeddings.parquet")), ("samples", "targets", "held"), strict=True))
        out = {"samples": samples, "targets": targets, "held": held}
        models = workers = None
        for p in TRACED.values():
            made = run(samples, targets, p)
            for k, (m, w) in enumerate(zip(made.models, made.workers, strict=True)):
                m = m.select(F.lit(p.name).alias("method"), F.lit(k).alias("iter"), "coord", "x", "r")
                w = w.select(F.lit(p.name).alias("method"), F.lit(k).alias("iter"), "worker", "coord", "a", "v", "q")
                models, workers = (m, w) if models is None else (models.unionByName(m), workers.unionByName(w))
            out["rows"] = made.rows
        out["models"], out["workers"] = written(models.coalesce(4), folder, "models"), written(workers.coalesce(4), folder, "workers")
        _MADE[key] = out
    return _MADE[key]


def gradients(t: dict[str, DataFrame]) -> DataFrame:
    """(method, iter, worker, coord, g) at every model of the runs."""
    return worker_gradients(t["samples"], t["targets"], t["rows"], t["models"].select("method", "iter", "coord", "x"), TRACED["plain"], ("method", "iter"))


def errors(t: dict[str, DataFrame], held: bool = False) -> DataFrame:
    """(method, iter, row_id, e, p, y): prediction less target; of rows held out the target has no offset."""
    rows = t["held"] if held else t["samples"]
    said = rows.join(t["models"], "coord").groupBy("method", "iter", "row_id").agg(F.floor(_sum(F.col("v") * F.col("x")) / float(UNIT) + 0.5).cast("long").alias("p"))
    y = rows.groupBy("row_id").agg((_sum(F.col("v") * (F.col("coord") % 5 - 2)) * (GRID // UNIT)).alias("y")) if held else t["targets"].select("row_id", "y")
    return said.join(y, "row_id").withColumn("e", F.col("p") - F.col("y"))


def distances(t: dict[str, DataFrame]) -> DataFrame:
    return t["models"].groupBy("method", "iter").agg(_sum((F.col("x") - planted()) * (F.col("x") - planted())).alias("d2"))


# ---- the same in SQL -------------------------------------------------------------------------------------------------------


def _union(what: str, columns: str, methods=TRACED, first: int = 0) -> str:
    return " UNION ALL ".join(f"SELECT '{m}' AS method, {k} AS iter, {columns} FROM t{list(TRACED).index(m)}_{what}{k}" for m in methods for k in range(first, K + 1))


def _base_sql() -> list[str]:
    offset = f"((vec_id * 7919) % 2001 - 1000) * {GRID // 2048}"
    kept = f"SELECT vec_id, {FEATURES_SQL} AS f FROM embeddings WHERE NOT ({draw_sql(21, 'vec_id')} >= 0.8)"
    base = f"SELECT vec_id * 2 + side AS row_id, vec_id % 5 + 5 * side AS worker, f, CASE side WHEN 0 THEN {offset} ELSE -({offset}) END AS off FROM ({kept}), (VALUES (0), (1)) s(side)"
    y = f"CAST(list_sum(list_transform(f, lambda v, i: v * ((i - 1) % 5 - 2))) * {GRID // UNIT} + off AS BIGINT)"
    held = f"SELECT vec_id AS row_id, unnest({FEATURES_SQL}) AS v, unnest(range(0, len(embedding))) AS coord FROM embeddings WHERE {draw_sql(21, 'vec_id')} >= 0.8"
    return [*sql_samples(base, y), f"held AS MATERIALIZED ({held})"]


def _sql(query: str, methods=TRACED, gradient: bool = False) -> str:
    """A query over models, workers and, if wanted, grads (method, iter, worker, coord, g) and their mean."""
    parts = _base_sql()
    for m in methods:
        parts += sql_iterations(TRACED[m], f"t{list(TRACED).index(m)}_")
    parts += [f"models AS MATERIALIZED ({_union('model', 'coord, x, r', methods)})", f"workers AS MATERIALIZED ({_union('workers', 'worker, coord, a, v, q', methods)})"]
    parts += [
        f"said AS MATERIALIZED (SELECT method, iter, row_id, CAST(floor(CAST(sum(v * x) AS BIGINT) / {UNIT}.0::DOUBLE + 0.5) AS BIGINT) AS p FROM samples JOIN models USING (coord) GROUP BY method, iter, row_id)",
        "errs AS MATERIALIZED (SELECT *, p - y AS e FROM said JOIN targets USING (row_id))",
    ]
    if gradient:
        parts.append(
            f"grads AS MATERIALIZED (SELECT method, iter, worker, coord, CAST(floor(CAST(sum(v * e) AS DOUBLE) / {UNIT}.0::DOUBLE / n_rows + 0.5) AS BIGINT) AS g "
            "FROM (SELECT method, iter, errs.worker, coord, v, e FROM samples JOIN errs USING (row_id)) JOIN sized USING (worker) GROUP BY method, iter, worker, coord, n_rows)"
        )
    return "WITH " + ",\n".join(parts) + "\n" + query


def _add(name: str, sql: str, build, **more) -> None:
    QUERIES[name] = lambda spark, sf_dir: build(traces(spark, sf_dir))
    SQL[name] = _sql(sql, **more)


# ---- losses, distances, residuals ------------------------------------------------------------------------------------------

_add(
    "measure_loss", "SELECT method, iter, CAST(sum(u * u) AS DOUBLE) / count(*) AS loss FROM (SELECT *, CAST(floor(e / 1024.0::DOUBLE) AS BIGINT) AS u FROM errs) GROUP BY method, iter",
    lambda t: errors(t).withColumn("u", F.floor(F.col("e") / 1024.0).cast("long")).groupBy("method", "iter").agg((_sum(F.col("u") * F.col("u")).cast("double") / F.count("*")).alias("loss")),
)
_HELD = f"SELECT method, iter, row_id, CAST(floor(CAST(sum(v * x) AS BIGINT) / {UNIT}.0::DOUBLE + 0.5) AS BIGINT) AS p, CAST(sum(v * (coord % 5 - 2)) * {GRID // UNIT} AS BIGINT) AS y FROM held JOIN models USING (coord) GROUP BY method, iter, row_id"
_add(
    "measure_test_loss", f"SELECT method, iter, CAST(sum(u * u) AS DOUBLE) / count(*) AS loss FROM (SELECT *, CAST(floor((p - y) / 1024.0::DOUBLE) AS BIGINT) AS u FROM ({_HELD})) GROUP BY method, iter",
    lambda t: errors(t, held=True).withColumn("u", F.floor(F.col("e") / 1024.0).cast("long")).groupBy("method", "iter").agg((_sum(F.col("u") * F.col("u")).cast("double") / F.count("*")).alias("loss")),
)
_add(  # the sign of the target, told by the sign of the prediction
    "measure_accuracy", f"SELECT method, iter, count(*) FILTER ((p > 0) = (y > 0)) AS hits, count(*) AS n FROM ({_HELD}) GROUP BY method, iter",
    lambda t: errors(t, held=True).groupBy("method", "iter").agg(F.count_if((F.col("p") > 0) == (F.col("y") > 0)).alias("hits"), F.count("*").alias("n")),
)
_GAP = f"(x - (coord % 5 - 2) * {GRID})"
_D2 = f"SELECT method, iter, CAST(sum({_GAP} * {_GAP}) AS BIGINT) AS d2 FROM models GROUP BY method, iter"
_add("measure_distance", _D2, distances)
_add(
    "measure_residual_norms",
    "SELECT method, iter, CAST(sum(up2) AS BIGINT) AS up2_all, CAST(max(up2) AS BIGINT) AS up2_max, any_value(down2) AS down2 FROM (SELECT method, iter, worker, sum(v * v) AS up2 FROM workers WHERE iter > 0 GROUP BY ALL) JOIN (SELECT method, iter, CAST(sum(r * r) AS BIGINT) AS down2 FROM models GROUP BY ALL) USING (method, iter) GROUP BY method, iter",
    lambda t: t["workers"].where("iter > 0").groupBy("method", "iter", "worker").agg(_sum(F.col("v") * F.col("v")).alias("up2")).groupBy("method", "iter").agg(F.sum("up2").alias("up2_all"), F.max("up2").alias("up2_max"))
    .join(t["models"].groupBy("method", "iter").agg(_sum(F.col("r") * F.col("r")).alias("down2")), ["method", "iter"]),
)

# ---- along the run ---------------------------------------------------------------------------------------------------------

_w = lambda: Window.partitionBy("method").orderBy("iter").rowsBetween(Window.unboundedPreceding, 0)
_MEAN = "SELECT method, iter, coord, CAST(floor(CAST(sum(g) AS DOUBLE) / 10 + 0.5) AS BIGINT) AS g FROM grads GROUP BY method, iter, coord"


def _mean_gradient(t: dict[str, DataFrame]) -> DataFrame:
    return gradients(t).groupBy("method", "iter", "coord").agg(F.floor(F.sum("g").cast("double") / 10 + 0.5).cast("long").alias("g"))


_add(
    "measure_grad_norm_avg", f"SELECT method, iter, CAST(sum(n2) OVER (PARTITION BY method ORDER BY iter) AS DOUBLE) / (iter + 1) AS mean FROM (SELECT method, iter, CAST(sum(g * g) AS BIGINT) AS n2 FROM ({_MEAN}) GROUP BY method, iter)",
    lambda t: _mean_gradient(t).groupBy("method", "iter").agg(_sum(F.col("g") * F.col("g")).alias("n2")).select("method", "iter", (F.sum("n2").over(_w()).cast("double") / (F.col("iter") + 1)).alias("mean")),
    gradient=True,
)
_add(
    "measure_linear_rate", f"SELECT method, floor(regr_slope(ln(CAST(d2 AS DOUBLE)) / 2, iter) * 1e6 + 0.5) AS slope, floor(exp(ln(max(CAST(d2 AS DOUBLE)) FILTER (iter = {K}) / max(CAST(d2 AS DOUBLE)) FILTER (iter = 0)) / {2 * K}) * 1e6 + 0.5) AS ratio FROM ({_D2}) GROUP BY method",
    lambda t: distances(t).withColumn("d2", F.col("d2").cast("double")).groupBy("method").agg(
        F.floor(F.regr_slope(F.log("d2") / 2, F.col("iter").cast("double")) * 1e6 + 0.5).cast("double").alias("slope"),
        F.floor(F.exp(F.log(F.max(F.when(F.col("iter") == K, F.col("d2"))) / F.max(F.when(F.col("iter") == 0, F.col("d2")))) / (2 * K)) * 1e6 + 0.5).cast("double").alias("ratio"),
    ),
)
_add("measure_floor", f"SELECT method, median(CAST(d2 AS DOUBLE)) AS floor FROM ({_D2}) WHERE iter > {K - 3} GROUP BY method", lambda t: distances(t).where(f"iter > {K - 3}").groupBy("method").agg(F.median(F.col("d2").cast("double")).alias("floor")))
_CASE = "CASE method " + " ".join(f"WHEN '{m}' THEN {b}" for m, b in BITS.items()) + " END"
_add(
    "measure_cumulative_bits", f"SELECT method, iter, d2, CAST(sum(CASE WHEN iter = 0 THEN 0 ELSE {_CASE} END) OVER (PARTITION BY method ORDER BY iter) AS BIGINT) AS so_far FROM ({_D2})",
    lambda t: distances(t).select("method", "iter", "d2", F.sum(F.expr(f"CASE WHEN iter = 0 THEN 0L ELSE CAST({_CASE} AS BIGINT) END")).over(_w()).alias("so_far")),
)
_add(  # until the squared distance is a quarter of the first
    "measure_to_target", f"SELECT method, min(iter) AS iter, CAST(min(iter) * any_value({_CASE}) AS BIGINT) AS bits FROM (SELECT *, first_value(d2) OVER (PARTITION BY method ORDER BY iter) AS d0 FROM ({_D2})) WHERE 4 * d2 < d0 GROUP BY method",
    lambda t: distances(t).withColumn("d0", F.first("d2").over(Window.partitionBy("method").orderBy("iter"))).where("4 * d2 < d0").groupBy("method").agg(F.min("iter").alias("iter")).select("method", "iter", F.expr(f"CAST(iter * {_CASE} AS BIGINT)").alias("bits")),
)

# ---- workers: heterogeneity, noise, anchors, potentials -------------------------------------------------------------------------

_AT = f"SELECT worker, coord, CAST(floor(CAST(sum(v * off) AS DOUBLE) / {UNIT}.0::DOUBLE / n_rows + 0.5) AS BIGINT) AS g FROM (SELECT s.worker, s.coord, s.v, -b.off AS off FROM samples s JOIN base b USING (row_id)) JOIN sized USING (worker) GROUP BY worker, coord, n_rows"


def _at_optimum(t: dict[str, DataFrame]) -> DataFrame:
    """(worker, coord, g): gradients of the workers at the planted model."""
    best = t["samples"].select("coord").distinct().select("coord", planted().alias("x"))
    return worker_gradients(t["samples"], t["targets"], t["rows"], best, TRACED["plain"])


_add("measure_heterogeneity", f"SELECT worker, CAST(sum(g * g) AS BIGINT) AS norm2 FROM ({_AT}) GROUP BY worker", lambda t: _at_optimum(t).groupBy("worker").agg(_sum(F.col("g") * F.col("g")).alias("norm2")), methods=["plain"])


def _noise(t: dict[str, DataFrame]) -> DataFrame:
    """By worker and iteration of plain descent: mean squared distance of the gradients of disjoint random batches from the worker's own, and the batches."""
    batch = F.floor(draw(22, F.col("row_id"), mode="portable") * BATCHES).cast("long")
    samples, targets = t["samples"].withColumn("batch", batch), t["targets"].withColumn("batch", batch)
    models = t["models"].where("method = 'plain'").select("iter", "coord", "x")
    rows = targets.groupBy("worker", "batch").agg(F.count("*").alias("rows"))
    part = worker_gradients(samples, targets.drop("batch"), rows, models, TRACED["plain"], ("iter",), ("batch",)).withColumnRenamed("g", "gb")
    whole = worker_gradients(t["samples"], t["targets"], t["rows"], models, TRACED["plain"], ("iter",))
    gap = F.col("gb") - F.col("g")
    return part.join(whole, ["iter", "worker", "coord"]).groupBy("iter", "worker", "batch").agg(_sum(gap * gap).alias("n2")).groupBy("iter", "worker").agg(
        (F.sum("n2").cast("double") / F.count("*")).alias("sigma2"), F.count("*").alias("batches")
    )


_BATCH = f"CAST(floor({draw_sql(22, 'row_id')} * {BATCHES}) AS BIGINT)"
_add(
    "measure_gradient_noise",
    f"""SELECT iter, worker, CAST(sum(n2) AS DOUBLE) / count(*) AS sigma2, count(*) AS batches FROM (
  SELECT iter, worker, batch, CAST(sum((gb - g) * (gb - g)) AS BIGINT) AS n2 FROM (
    SELECT iter, e.worker, batch, coord, CAST(floor(CAST(sum(v * e) AS DOUBLE) / {UNIT}.0::DOUBLE / any_value(z) + 0.5) AS BIGINT) AS gb
    FROM (SELECT row_id, coord, v FROM samples) JOIN (SELECT *, {_BATCH} AS batch FROM errs) e USING (row_id) JOIN (SELECT worker, {_BATCH} AS batch, count(*) AS z FROM targets GROUP BY ALL) USING (worker, batch)
    GROUP BY iter, e.worker, batch, coord
  ) JOIN (SELECT iter, worker, coord, g FROM grads) USING (iter, worker, coord) GROUP BY iter, worker, batch
) GROUP BY iter, worker""",
    _noise, methods=["plain"], gradient=True,
)


def _tracking(t: dict[str, DataFrame]) -> DataFrame:
    """Sum over redraws of the next anchor, and what the average of old anchor and gradient says it should be, at the last iteration of the two-way method."""
    now = t["workers"].where(f"method = 'two_way_residual' and iter = {K}").select("worker", "coord", "v", "q", "a")
    before = t["workers"].where(f"method = 'two_way_residual' and iter = {K - 1}").select("worker", "coord", F.col("a").alias("a0"))
    scale = F.max(F.abs("v")).over(Window.partitionBy("worker", F.floor(F.col("coord") / BLOCK)))
    rep = now.join(before, ["worker", "coord"]).withColumn("scale", scale).withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(REDRAWS - 1))))
    q = F.when(draw(33, F.col("worker"), F.col("coord"), F.col("rep"), mode="portable") * F.col("scale") < F.abs("v"), (F.signum("v") * F.col("scale")).cast("long")).otherwise(F.lit(0).cast("long"))
    after = F.col("a0") + F.floor(F.lit(0.1) * q + 0.5).cast("long")
    return rep.groupBy("worker", "coord").agg(F.sum(after).alias("total"), F.first(F.col("a0") * REDRAWS + F.floor(F.lit(0.1 * REDRAWS) * F.col("v") + 0.5).cast("long")).alias("expected"))


_QR = f"CASE WHEN {draw_sql(33, 'worker', 'coord', 'rep')} * scale < abs(v) THEN CAST(sign(v) * scale AS BIGINT) ELSE 0 END"
_add(
    "measure_anchor_tracking",
    f"SELECT worker, coord, CAST(sum(a0 + CAST(floor(0.1::DOUBLE * ({_QR}) + 0.5) AS BIGINT)) AS BIGINT) AS total, any_value(a0 * {REDRAWS} + CAST(floor({0.1 * REDRAWS!r}::DOUBLE * v + 0.5) AS BIGINT)) AS expected "
    f"FROM (SELECT *, max(abs(v)) OVER (PARTITION BY worker, coord // {BLOCK}) AS scale FROM workers JOIN (SELECT worker, coord, a AS a0 FROM workers WHERE iter = {K - 1}) USING (worker, coord) WHERE iter = {K}), (SELECT unnest(range(0, {REDRAWS})) AS rep) GROUP BY worker, coord",
    _tracking, methods=["two_way_residual"],
)

#: settings that the potentials weigh with: apply rate, constant of the way back, carry weight, free constant, step, smoothness
APPLY, C_DOWN, CARRY, EXTRA, STEP, SMOOTH = 0.25, 1.5, 0.1, 1.5, 0.3, 4.0
_CONVEX = (APPLY * (1 - (C_DOWN + 1) * APPLY), (1 + CARRY) * EXTRA * APPLY * STEP**2)
_NONCONVEX = ((C_DOWN + 1) * SMOOTH * APPLY**2, 3 * EXTRA * (C_DOWN + 1) * SMOOTH * APPLY**2 * STEP**2)


def _potentials(t: dict[str, DataFrame]) -> DataFrame:
    """(method, iter, d2, r2, gap2, a2, excess): what the two potentials add up; gap and anchors over all workers."""
    g = _at_optimum(t).withColumnRenamed("g", "best")
    gap = t["workers"].join(g, ["worker", "coord"]).groupBy("method", "iter").agg(_sum((F.col("a") - F.col("best")) * (F.col("a") - F.col("best"))).alias("gap2"), _sum(F.col("a") * F.col("a")).alias("a2"))
    r = t["models"].groupBy("method", "iter").agg(_sum(F.col("r") * F.col("r")).alias("r2"))
    u = F.floor(F.col("e") / 1024.0).cast("long")
    loss = errors(t).groupBy("method", "iter").agg(_sum(u * u).alias("e2"), F.count("*").alias("n"))
    return distances(t).join(r, ["method", "iter"]).join(gap, ["method", "iter"]).join(loss, ["method", "iter"])


_OF = f"""SELECT * FROM ({_D2}) JOIN (SELECT method, iter, CAST(sum(r * r) AS BIGINT) AS r2 FROM models GROUP BY ALL) USING (method, iter)
JOIN (SELECT method, iter, CAST(sum((a - best) * (a - best)) AS BIGINT) AS gap2, CAST(sum(a * a) AS BIGINT) AS a2 FROM workers JOIN (SELECT worker, coord, g AS best FROM ({_AT})) USING (worker, coord) GROUP BY method, iter) USING (method, iter)
JOIN (SELECT method, iter, CAST(sum(CAST(floor(e / 1024.0::DOUBLE) AS BIGINT) * CAST(floor(e / 1024.0::DOUBLE) AS BIGINT)) AS BIGINT) AS e2, count(*) AS n FROM errs GROUP BY method, iter) USING (method, iter)"""
_add(
    "measure_convex_potential", f"SELECT method, iter, {_CONVEX[0]!r}::DOUBLE * r2 + d2 + {_CONVEX[1]!r}::DOUBLE * (CAST(gap2 AS DOUBLE) / 10) AS potential FROM ({_OF})",
    lambda t: _potentials(t).select("method", "iter", (F.lit(_CONVEX[0]) * F.col("r2") + F.col("d2") + F.lit(_CONVEX[1]) * (F.col("gap2").cast("double") / 10)).alias("potential")),
)
_add(  # the loss less nothing: its least value is a constant that the differences of the bound lose
    "measure_nonconvex_potential", f"SELECT method, iter, {_NONCONVEX[0]!r}::DOUBLE * r2 + CAST(e2 AS DOUBLE) / n * {1024.0 * 1024.0 / 2!r}::DOUBLE + {_NONCONVEX[1]!r}::DOUBLE * (CAST(a2 AS DOUBLE) / 10) AS potential FROM ({_OF})",
    lambda t: _potentials(t).select("method", "iter", (F.lit(_NONCONVEX[0]) * F.col("r2") + F.col("e2").cast("double") / F.col("n") * (1024.0 * 1024.0 / 2) + F.lit(_NONCONVEX[1]) * (F.col("a2").cast("double") / 10)).alias("potential")),
)
