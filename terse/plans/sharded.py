"""Iterations on tables of coordinates: state never on the driver, and the same iterations as SQL text for another engine.

Samples are rows (row_id, worker, coord, value); the model (coord, x, carry, anchor mean) and the workers' state (worker, coord, anchor, error) are
tables hashed by coordinate.  In ``grid`` arithmetic all state is in whole units of 2**-20 and every sum is of whole numbers, so the result does
not depend on order or engine; in float arithmetic the same plan runs on doubles with fast draws.

One iteration: predictions (one shuffle by row), gradients (one by worker and coordinate), messages (windows over a block of a worker), their mean (one
by coordinate), then narrow steps on the model.  State is written to the shared folder after each iteration.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from terse.functions.draws import draw, draw_sql
from terse.functions.vectors import GRID
from terse.plans.theory import horizon_step
from terse.sources.tables import shared_folder, written

UNIT = 1024
"""Grid units in 1 for features."""

RANGE = 65_536
"""Coordinates whose best are found by one task before the best of all are."""


@dataclass(frozen=True)
class Plan:
    """Settings as in ``terse.plans.methods``; codecs by name: identity, ternary (largest magnitude), ternary2 (2-norm), sign, sparsify, largest_k.

    memory, decay: weight of a worker's error in its message, and in the next error (none: the rest of the message); blocks: lengths of unequal blocks;
    steps: one for each iteration; start: 'zero' or 'seed'; precise: the master goes on from its own model; peers: workers send to each other.
    """

    name: str
    up: str = "identity"
    down: str = "raw"
    down_codec: str = "identity"
    anchor_rate: float = 0.0
    memory: float = 0.0
    decay: float | None = None
    carry: float = 0.0
    apply: float = 1.0
    step: float = 0.05
    steps: tuple[float, ...] = ()
    l2: float = 0.1
    l1: float = 0.0
    block: int = 16
    blocks: tuple[int, ...] = ()
    k: int = 7
    iterations: int = 3
    seed: int = 11
    start: str = "zero"
    precise: bool = False
    peers: bool = False
    grid: bool = True

    def step_at(self, k: int) -> float:
        return self.steps[k] if self.steps else self.step

    def edges(self) -> list[tuple[int, int]]:
        """(number of a block, first coordinate behind it) of unequal blocks but the last."""
        return [(i, sum(self.blocks[: i + 1])) for i in range(len(self.blocks) - 1)]


TWO_WAY = Plan("iter3_two_way", "ternary", "model", "ternary", anchor_rate=0.1, carry=1.0)
PLANS = {
    p.name: p
    for p in (
        Plan("iter3_plain"),
        Plan("iter3_quantized", "ternary2"),
        Plan("iter3_ternary", "ternary"),
        Plan("iter3_sparsified", "sparsify"),
        Plan("iter3_sign", "sign"),
        Plan("iter3_sign_memory", "sign", memory=1.0),
        Plan("iter3_compensated", "ternary", memory=1.0),
        Plan("iter3_difference", "ternary", anchor_rate=0.1),
        Plan("iter3_two_sided", "ternary", "gradient", "ternary", memory=1.0, carry=1.0),
        Plan("iter3_two_sided_largest_k", "largest_k", "gradient", "largest_k", memory=1.0, carry=1.0),
        Plan("iter3_all_to_all", "ternary", seed=12, peers=True),
        Plan("iter3_all_to_all_compensated", "ternary", memory=0.5, decay=0.9, seed=13, peers=True),
        TWO_WAY,
        Plan("iter3_two_way_smooth", "ternary", "gradient", "ternary", anchor_rate=0.1, carry=1.0),
        replace(TWO_WAY, name="iter3_two_way_no_carry", carry=0.0),
        replace(TWO_WAY, name="iter3_two_way_prox_l1", l1=0.02),
        replace(TWO_WAY, name="iter3_two_way_lineitem", block=4, k=2),
        replace(TWO_WAY, name="iter3_two_way_label_skew"),
        replace(TWO_WAY, name="iter3_two_way_two_codecs", up="ternary2", down_codec="sign", carry=0.5),
        replace(TWO_WAY, name="iter3_two_way_uneven_blocks", blocks=(10, 7, 40, 7)),
        replace(TWO_WAY, name="iter3_two_way_decay", steps=(0.1, 0.05, 0.025)),
        replace(TWO_WAY, name="iter3_two_way_horizon", step=horizon_step(3, 10, 4.0, 4 * 1.5 * 2.5 / 10, 0.2)),
        replace(TWO_WAY, name="iter3_two_way_seeded", start="seed"),
        replace(TWO_WAY, name="iter3_two_way_exact_next", precise=True),
    )
}


def _block(p: Plan) -> Column:
    out = F.lit(len(p.blocks) - 1) if p.blocks else F.floor(F.col("coord") / p.block)
    for i, end in reversed(p.edges()):
        out = F.when(F.col("coord") < end, i).otherwise(out)
    return out


def _snap(p: Plan):
    return (lambda c: F.floor(c + 0.5).cast("long")) if p.grid else (lambda c: c)


def _coded(frame: DataFrame, p: Plan, codec: str, v: str, to: str, k: int, leg: str, worker: Column | None) -> DataFrame:
    """The frame with the coded value of column ``v`` as column ``to``, looking at the other coordinates of its block through windows."""
    mine = [] if worker is None else ["worker"]
    x, snap, kind = F.col(v), _snap(p), "long" if p.grid else "double"
    if codec == "identity":
        return frame.withColumn(to, x)
    u = draw(p.seed, F.lit(k), F.lit(leg), F.lit(0) if worker is None else worker, F.col("coord"), mode="portable" if p.grid else "fast")
    if codec == "sparsify":
        return frame.withColumn(to, F.when(u < 0.25, x * 4).otherwise(F.lit(0).cast(kind)))
    if codec == "largest_k":  # the best of every range of coordinates first, and of those the best: no task sorts a whole vector
        best = lambda *by: F.row_number().over(Window.partitionBy(*by).orderBy(F.abs(x).desc(), "coord"))
        some = frame.select(*mine, "coord", v).withColumn("at", best(*mine, F.floor(F.col("coord") / RANGE))).where(F.col("at") <= p.k).drop("at")
        some = some.withColumn("at", best("worker")).where(F.col("at") <= p.k).select("worker", "coord", F.lit(True).alias("kept")) if mine else (
            some.orderBy(F.abs(x).desc(), "coord").limit(p.k).select("coord", F.lit(True).alias("kept"))
        )
        return frame.join(some, [*mine, "coord"], "left").withColumn(to, F.when(F.col("kept"), x).otherwise(F.lit(0).cast(kind))).drop("kept")
    w = Window.partitionBy(*mine, _block(p))
    if codec == "sign":
        return frame.withColumn(to, (F.signum(x) * snap(F.sum(F.abs(x)).over(w) / F.count("*").over(w))).cast(kind))
    scale = F.max(F.abs(x)).over(w) if codec == "ternary" else snap(F.sqrt(F.sum(x * x).over(w).cast("double")))
    return frame.withColumn(to, F.when(u * scale < F.abs(x), (F.signum(x) * scale).cast(kind)).otherwise(F.lit(0).cast(kind)))


@dataclass
class Iterations:
    """Tables by iteration: models (coord, x: shared, z: precise, c: carry, am: mean anchor, r: what was coded on the way back), 0 the first; workers (worker, coord,
    a: anchor, m: error, v: what was coded, q: its code), 0 the first; rows of each worker."""

    models: list[DataFrame]
    workers: list[DataFrame]
    rows: DataFrame


def worker_gradients(samples: DataFrame, targets: DataFrame, rows: DataFrame, model: DataFrame, p: Plan, by: tuple[str, ...] = (), within: tuple[str, ...] = ()) -> DataFrame:
    """(by, worker, within, coord, g): mean gradients of workers for every model of a table (by, coord, x), over rows that agree in ``within``; a worker's sums are 0 where
    its samples have no value.  ``rows``: worker, within, rows."""
    snap, unit = _snap(p), float(UNIT) if p.grid else 1.0
    said = samples.join(model, "coord").groupBy(*by, "row_id").agg(F.sum(F.col("v") * F.col("x")).alias("s"))
    errors = targets.join(said, "row_id").select(*by, "row_id", (snap(F.col("s") / unit) - F.col("y")).alias("e"))
    sums = samples.join(errors, "row_id").groupBy(*by, "worker", *within, "coord").agg(F.sum(F.col("v") * F.col("e")).alias("s"))
    every = model.crossJoin(F.broadcast(rows)).join(sums, [*by, "worker", *within, "coord"], "left")
    return every.select(*by, "worker", *within, "coord", snap(F.coalesce(F.col("s").cast("double"), F.lit(0.0)) / unit / F.col("rows") + F.lit(p.l2) * F.col("x")).alias("g"))


def run(samples: DataFrame, targets: DataFrame, p: Plan) -> Iterations:
    """The plan's iterations.  samples: row_id, worker, coord, v (no row where v is 0 is needed); targets: row_id, worker, y (both in units of the plan's arithmetic).

    Every worker has state for every coordinate of the model, whether its samples hold it or not.
    """
    snap, kind, one = _snap(p), "long" if p.grid else "double", GRID if p.grid else 1
    zero = F.lit(0).cast(kind)
    folder = shared_folder(samples.sparkSession)
    samples, targets = written(samples, folder, "samples"), written(targets, folder, "targets")
    rows = written(targets.groupBy("worker").agg(F.count("*").alias("rows")), folder, "rows")
    n = rows.count()
    first = snap((draw(p.seed, F.lit("start"), F.col("coord"), mode="portable") - 0.5) * one) if p.start == "seed" else zero
    model = written(samples.select("coord").distinct().select("coord", first.cast(kind).alias("x"), first.cast(kind).alias("z"), zero.alias("c"), zero.alias("am"), zero.alias("r")), folder, "model-0")
    workers = model.select("coord").crossJoin(F.broadcast(rows.select("worker"))).select("worker", "coord", *[zero.alias(c) for c in "amvq"])
    out = Iterations([model], [written(workers, folder, "workers-0")], rows)
    for k in range(p.iterations):
        model, step = out.models[-1], p.step_at(k)
        gradient = worker_gradients(samples, targets, rows, model.select("coord", "x"), p)
        value = out.workers[-1].drop("v", "q").join(gradient, ["worker", "coord"])
        value = value.withColumn("v", F.col("g") - F.col("a") + snap(F.lit(p.memory) * F.col("m")) if p.memory else F.col("g") - F.col("a"))
        coded = _coded(value, p, p.up, "v", "q", k, "up", F.col("worker"))
        error = zero if not p.memory else F.col("v") - F.col("q") if p.decay is None else snap(F.lit(p.decay) * F.col("m")) + F.col("g") - F.col("q")
        workers = coded.select("worker", "coord", (F.col("a") + snap(F.lit(p.anchor_rate) * F.col("q"))).alias("a"), error.alias("m"), "v", "q")
        out.workers.append(written(workers, folder, f"workers-{k + 1}"))
        sent = out.workers[-1].select("worker", "coord", "q")
        if p.peers:  # a message to every worker, itself included; all add up the same
            heard = sent.crossJoin(F.broadcast(rows.select(F.col("worker").alias("receiver")))).groupBy("receiver", "coord").agg(snap(F.sum("q").cast("double") / n).alias("d"))
            mean = heard.groupBy("coord").agg(F.max("d").alias("d"), F.min("d").alias("d0"))
            mean = mean.select("coord", F.when(F.col("d") == F.col("d0"), F.col("d")).otherwise(F.raise_error(F.lit("workers disagree")).cast(kind)).alias("d"))
        else:
            mean = sent.groupBy("coord").agg(snap(F.sum("q").cast("double") / n).alias("d"))
        est = model.drop("r").join(mean, "coord").withColumn("g", F.col("am") + F.col("d")).withColumn("am", F.col("am") + snap(F.lit(p.anchor_rate) * F.col("d")))
        stepped = F.col("z" if p.precise else "x") - snap(F.lit(step) * F.col("g"))
        if p.l1:
            t = F.lit(int(step * p.l1 * one + 0.5) if p.grid else step * p.l1)
            stepped = (F.signum(stepped) * F.greatest(F.abs(stepped) - t, zero)).cast(kind)
        est = est.withColumn("z", stepped)
        if p.down == "raw":
            made = est.select("coord", F.col("z").alias("x"), "z", "c", "am", zero.alias("r"))
        else:
            carried = snap(F.lit(p.carry) * F.col("c"))
            r = F.col("z") - F.col("x") + carried if p.down == "model" else F.col("g") + carried
            back = _coded(est.withColumn("r", r), p, p.down_codec, "r", "w", k, "down", None)
            x = F.col("x") + snap(F.lit(p.apply) * F.col("w")) if p.down == "model" else F.col("x") - snap(F.lit(step * p.apply) * F.col("w"))
            made = back.select("coord", x.alias("x"), "z", (F.col("r") - F.col("w")).alias("c"), "am", "r")
        out.models.append(written(made, folder, f"model-{k + 1}"))
    return out


# ---- samples of the given tables, in grid units ------------------------------------------------------------------------


def embedding_samples(emb: DataFrame, by_label: bool = False) -> tuple[DataFrame, DataFrame]:
    """Embeddings times 8 as features, centred label as target; dealt to ten workers by id, or by label."""
    who = (F.col("label") if by_label else F.col("vec_id") % 10).cast("long")
    base = emb.select(F.col("vec_id").alias("row_id"), who.alias("worker"), "embedding", "label")
    v = F.floor(F.col("e").cast("double") * 8.0 * UNIT + 0.5).cast("long")
    long = base.select("row_id", "worker", F.posexplode("embedding").alias("coord", "e")).select("row_id", "worker", F.col("coord").cast("long").alias("coord"), v.alias("v"))
    return long, base.select("row_id", "worker", ((F.col("label") * 2 - 9) * (GRID // 2)).cast("long").alias("y"))


def lineitem_samples(lines: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Four scaled columns of lineitem with a planted linear target."""
    cols = [F.floor((F.col("l_quantity") - 25) / 15 * UNIT + 0.5), F.floor(F.col("l_discount") * 20 * UNIT + 0.5), F.floor(F.col("l_tax") * 20 * UNIT + 0.5), F.floor((F.col("l_linenumber") - 4) / 2 * UNIT + 0.5)]
    base = lines.select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("row_id"), (F.col("l_orderkey") % 10).alias("worker"), F.array(*[c.cast("long") for c in cols]).alias("f"))
    long = base.select("row_id", "worker", F.posexplode("f").alias("coord", "v")).withColumn("coord", F.col("coord").cast("long"))
    y = (F.get("f", F.lit(0)) * 2 - F.get("f", F.lit(1)) + F.get("f", F.lit(3))) * (GRID // UNIT)
    return long, base.select("row_id", "worker", y.alias("y"))


def samples_for(spark, sf_dir: str, p: Plan):
    if p.name.endswith("lineitem"):
        return lineitem_samples(spark.read.parquet(f"{sf_dir}/lineitem.parquet"))
    return embedding_samples(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), p.name.endswith("label_skew"))


def query(spark, sf_dir: str, name: str) -> DataFrame:
    model = run(*samples_for(spark, sf_dir, PLANS[name]), PLANS[name]).models[-1]
    return model.select("coord", F.col("x").alias("x_grid"), F.col("am").alias("anchor_grid"), F.col("c").alias("carry_grid"))


# ---- the same as SQL text ------------------------------------------------------------------------------------------------


def _block_sql(p: Plan) -> str:
    if not p.blocks:
        return f"floor(coord / {p.block})"
    return "CASE " + " ".join(f"WHEN coord < {end} THEN {i}" for i, end in p.edges()) + f" ELSE {len(p.blocks) - 1} END"


def _code_sql(p: Plan, codec: str, v: str, k: int, leg: str, up: bool) -> str:
    w = f"(PARTITION BY {'worker, ' if up else ''}{_block_sql(p)})"
    u = draw_sql(p.seed, str(k), repr(leg), "worker" if up else "0", "coord")
    if codec == "identity":
        return v
    if codec == "sparsify":
        return f"CASE WHEN {u} < 0.25 THEN {v} * 4 ELSE 0 END"
    if codec == "largest_k":
        part = "PARTITION BY worker " if up else ""
        return f"CASE WHEN row_number() OVER ({part}ORDER BY abs({v}) DESC, coord) <= {p.k} THEN {v} ELSE 0 END"
    if codec == "sign":
        return f"CAST(sign({v}) * floor(CAST(sum(abs({v})) OVER {w} AS DOUBLE) / count(*) OVER {w} + 0.5) AS BIGINT)"
    scale = f"max(abs({v})) OVER {w}" if codec == "ternary" else f"floor(sqrt(CAST(sum({v} * {v}) OVER {w} AS DOUBLE)) + 0.5)"
    return f"CASE WHEN {u} * ({scale}) < abs({v}) THEN CAST(sign({v}) * ({scale}) AS BIGINT) ELSE 0 END"


def _snap_sql(expression: str) -> str:
    return f"CAST(floor({expression} + 0.5) AS BIGINT)"


def sql_iterations(p: Plan, tag: str = "") -> list[str]:
    """Common table expressions of a grid plan over samples, targets and sized: models and workers by iteration, names ending in the iteration, ``tag`` first."""
    first = _snap_sql(f"({draw_sql(p.seed, repr('start'), 'coord')} - 0.5) * {GRID}") if p.start == "seed" else "CAST(0 AS BIGINT)"
    nil = "CAST(0 AS BIGINT)"
    parts = [
        f"{tag}model0 AS MATERIALIZED (SELECT coord, {first} AS x, {first} AS z, {nil} AS c, {nil} AS am, {nil} AS r FROM (SELECT DISTINCT coord FROM samples))",
        f"{tag}workers0 AS MATERIALIZED (SELECT worker, coord, {nil} AS a, {nil} AS m, {nil} AS v, {nil} AS q FROM {tag}model0, (SELECT worker FROM sized))",
    ]
    l2, rate = f"{p.l2!r}::DOUBLE", f"{p.anchor_rate!r}::DOUBLE"
    for k in range(p.iterations):
        step = f"{p.step_at(k)!r}::DOUBLE"
        gradient = _snap_sql(f"coalesce(CAST(g.s AS DOUBLE), 0) / {UNIT}.0::DOUBLE / n_rows + {l2} * o.x")
        stepped = f"{'z' if p.precise else 'x'} - {_snap_sql(f'{step} * g')}"
        if p.l1:
            t = int(p.step_at(k) * p.l1 * GRID + 0.5)
            stepped = f"CAST(sign({stepped}) * greatest(abs({stepped}) - {t}, 0) AS BIGINT)"
        carried = _snap_sql(f"{p.carry!r}::DOUBLE * c")
        remembered = f"{_snap_sql(f'{p.memory!r}::DOUBLE * m')}" if p.memory else "0"
        error = nil if not p.memory else "v - q" if p.decay is None else f"{_snap_sql(f'{p.decay!r}::DOUBLE * m')} + g - q"
        parts += [
            f"{tag}said{k} AS (SELECT s.row_id, CAST(sum(s.v * o.x) AS BIGINT) AS s FROM samples s JOIN {tag}model{k} o USING (coord) GROUP BY s.row_id)",
            f"{tag}errors{k} AS MATERIALIZED (SELECT t.row_id, {_snap_sql(f's / {UNIT}.0::DOUBLE')} - y AS e FROM targets t JOIN {tag}said{k} USING (row_id))",
            f"{tag}sums{k} AS (SELECT s.worker, s.coord, CAST(sum(s.v * e.e) AS BIGINT) AS s FROM samples s JOIN {tag}errors{k} e USING (row_id) GROUP BY s.worker, s.coord)",
            f"{tag}value{k} AS MATERIALIZED (SELECT worker, coord, a, m, g, g - a + {remembered} AS v FROM (SELECT w.worker, w.coord, w.a, w.m, {gradient} AS g FROM {tag}workers{k} w LEFT JOIN {tag}sums{k} g USING (worker, coord) JOIN sized z USING (worker) JOIN {tag}model{k} o USING (coord)))",
            f"{tag}coded{k} AS MATERIALIZED (SELECT *, {_code_sql(p, p.up, 'v', k, 'up', True)} AS q FROM {tag}value{k})",
            f"{tag}workers{k + 1} AS MATERIALIZED (SELECT worker, coord, a + {_snap_sql(f'{rate} * q')} AS a, {error} AS m, v, q FROM {tag}coded{k})",
            f"{tag}mean{k} AS (SELECT coord, {_snap_sql('CAST(sum(q) AS DOUBLE) / (SELECT count(*) FROM sized)')} AS d FROM {tag}coded{k} GROUP BY coord)",
            f"{tag}est{k} AS MATERIALIZED (SELECT coord, x, c, g, am, {stepped} AS z FROM (SELECT coord, x, z, c, am + d AS g, am + {_snap_sql(f'{rate} * d')} AS am FROM {tag}model{k} JOIN {tag}mean{k} USING (coord)))",
        ]
        if p.down == "raw":
            parts.append(f"{tag}model{k + 1} AS MATERIALIZED (SELECT coord, z AS x, z, c, am, {nil} AS r FROM {tag}est{k})")
        else:
            r = f"z - x + {carried}" if p.down == "model" else f"g + {carried}"
            x = f"x + {_snap_sql(f'{p.apply!r}::DOUBLE * w')}" if p.down == "model" else f"x - {_snap_sql(f'{p.step_at(k) * p.apply!r}::DOUBLE * w')}"
            parts += [
                f"{tag}res{k} AS MATERIALIZED (SELECT coord, x, z, am, {r} AS r FROM {tag}est{k})",
                f"{tag}sent{k} AS MATERIALIZED (SELECT coord, x, z, am, r, {_code_sql(p, p.down_codec, 'r', k, 'down', False)} AS w FROM {tag}res{k})",
                f"{tag}model{k + 1} AS MATERIALIZED (SELECT coord, {x} AS x, z, CAST(r - w AS BIGINT) AS c, am, r FROM {tag}sent{k})",
            ]
    return parts


def sql_samples(base: str, y: str) -> list[str]:
    """Common table expressions samples, targets and sized of rows (row_id, worker, f: features)."""
    return [
        f"base AS MATERIALIZED ({base})",
        "samples AS MATERIALIZED (SELECT row_id, worker, unnest(f) AS v, unnest(range(0, len(f))) AS coord FROM base)",
        f"targets AS MATERIALIZED (SELECT row_id, worker, {y} AS y FROM base)",
        "sized AS MATERIALIZED (SELECT worker, count(*) AS n_rows FROM targets GROUP BY worker)",
    ]


FEATURES_SQL = f"list_transform(embedding, lambda e: CAST(floor(CAST(e AS DOUBLE) * 8.0 * {UNIT} + 0.5) AS BIGINT))"


def sql(name: str) -> str:
    """DuckDB text of a grid plan: one chain of common table expressions."""
    p = PLANS[name]
    if name.endswith("lineitem"):
        f = [f"CAST(floor({e} * {UNIT} + 0.5) AS BIGINT)" for e in ("(l_quantity - 25) / 15", "l_discount * 20", "l_tax * 20", "(l_linenumber - 4) / 2")]
        base = f"SELECT l_orderkey * 8 + l_linenumber AS row_id, l_orderkey % 10 AS worker, [{', '.join(f)}] AS f FROM lineitem"
        y = f"(f[1] * 2 - f[2] + f[4]) * {GRID // UNIT}"
    else:
        who = "CAST(label AS BIGINT)" if name.endswith("label_skew") else "vec_id % 10"
        base = f"SELECT vec_id AS row_id, {who} AS worker, {FEATURES_SQL} AS f, label FROM embeddings"
        y = f"CAST((label * 2 - 9) * {GRID // 2} AS BIGINT)"
    return "WITH " + ",\n".join(sql_samples(base, y) + sql_iterations(p)) + f"\nSELECT coord, x AS x_grid, am AS anchor_grid, c AS carry_grid FROM model{p.iterations}"
