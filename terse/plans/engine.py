"""Training loops over partitioned tables.

Gradients come from a source: sufficient statistics of a quadratic (one pass over the table, whatever the number of iterations), a Spark job per iteration
over cached samples (any objective; several methods share each pass), or rows small enough to be held.  Model state stays on the driver up to
``STATE_LIMIT`` bytes; larger models go through ``terse.plans.sharded``, where state are tables of blocks.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from terse.functions.draws import draw, draws, generator
from terse.operators.objectives import Objective, Ridge
from terse.plans.methods import Method, Schedule, State, iterate

STATE_LIMIT = 64 << 20
AHEAD = 512
"""Iterations at most whose batches one pass draws."""


SUM_BLOCK, SUM_SALTS = 4096, 32
"""Numbers of a sum that travel together, and parts that tasks' sums of one block are dealt into before they are added up."""


@dataclass(frozen=True)
class Sampler:
    """batch: rows a worker draws in an iteration (none: all of its rows); scope: of its own rows ('local') or of all rows ('global').

    A batch are the rows with the smallest draws for the iteration, exactly ``batch`` of them or all there are: without replacement, every row as likely, so the mean
    gradient is unbiased; wherever the rows are held, the same batches are drawn.
    """

    batch: int | None = None
    scope: str = "local"


def dense(column) -> np.ndarray:
    """An Arrow list column as a matrix."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    n = len(column)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(n, -1).astype(float) if n else np.zeros((0, 0))


class SparseRows:
    """A matrix by the filled places of its rows: what objectives that are linear in it need (x @ w, x.T @ r), rows by a mask."""

    def __init__(self, row: np.ndarray, at: np.ndarray, v: np.ndarray, shape: tuple[int, int]):
        self.row, self.at, self.v, self.shape = row, at, v, shape

    @classmethod
    def of(cls, column, width: int) -> SparseRows:
        """From an Arrow column of structs: places (at) and numbers (v) of each row."""
        column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
        places, numbers = column.field("at"), column.field("v")
        row = np.repeat(np.arange(len(column)), places.value_lengths().to_numpy(zero_copy_only=False))
        return cls(row, places.flatten().to_numpy(zero_copy_only=False), numbers.flatten().to_numpy(zero_copy_only=False), (len(column), width))

    @property
    def T(self) -> SparseRows:
        return SparseRows(self.at, self.row, self.v, self.shape[::-1])

    def __len__(self) -> int:
        return self.shape[0]

    def __getitem__(self, mask: np.ndarray) -> SparseRows:
        kept = mask[self.row]
        return SparseRows((np.cumsum(mask) - 1)[self.row[kept]], self.at[kept], self.v[kept], (int(mask.sum()), self.shape[1]))

    def __matmul__(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, self.v * w[self.at], self.shape[0])


# ---- sources ----------------------------------------------------------------------------------------------------------


def _parts_of(sums: dict[int, np.ndarray]) -> pa.RecordBatch:
    """A task's sums by worker, cut into blocks."""
    from pyspark import TaskContext

    task = TaskContext.get().partitionId() if TaskContext.get() else 0
    rows = [(w, task, b, v[b * SUM_BLOCK : (b + 1) * SUM_BLOCK]) for w, v in sums.items() for b in range(-(-len(v) // SUM_BLOCK))]
    values = pa.ListArray.from_arrays(np.cumsum([0, *(len(r[3]) for r in rows)]).astype(np.int32), np.concatenate([*(r[3] for r in rows), np.zeros(0)]))
    return pa.RecordBatch.from_arrays([*(pa.array([r[i] for r in rows], pa.int64()) for i in range(3)), values], names=["worker_id", "task", "block", "s"])


PART = "worker_id bigint, task bigint, block bigint, s array<double>"


def added(parts: DataFrame) -> tuple[list[int], np.ndarray]:
    """Workers, and the sum of each over all tasks: by block in two levels, so that no group grows with the number of tasks beyond its share."""

    def merge(t: pa.Table) -> pa.Table:
        t = t.sort_by("task")  # the same order of adding whichever task comes first
        whole = dense(t.column("s")).sum(0)
        first = [t.column(c).slice(0, 1) for c in ("worker_id", "task", "block")]
        return pa.table([*first, pa.ListArray.from_arrays(np.array([0, len(whole)], np.int32), whole)], names=["worker_id", "task", "block", "s"])

    some = parts.groupBy("worker_id", "block", F.pmod("task", F.lit(SUM_SALTS)).alias("salt")).applyInArrow(merge, PART)
    found = some.groupBy("worker_id", "block").applyInArrow(merge, PART).toArrow().sort_by([("worker_id", "ascending"), ("block", "ascending")])
    who, values = found.column("worker_id").to_numpy(), found.column("s").combine_chunks()
    sizes = values.value_lengths().to_numpy(zero_copy_only=False)
    flat = values.flatten().to_numpy(zero_copy_only=False)
    workers = np.unique(who)
    return workers.tolist(), flat.reshape(len(workers), -1) if len(workers) else np.zeros((0, int(sizes.sum())))


class QuadraticSource:
    """Least squares by per-worker sums of x x', x y, y y and counts: exact full gradients at the price of d^2 numbers a worker."""

    def __init__(self, gram, moment, square, counts, l2: float):
        self.gram, self.moment, self.square, self.counts, self.l2 = gram, moment, square, counts, l2
        self.n, self.d = moment.shape

    @classmethod
    def from_samples(cls, samples: DataFrame, l2: float) -> QuadraticSource:
        """samples: worker_id, x array, y.  Each task adds up its rows per worker; its sums are shuffled by block."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[int, np.ndarray] = {}
            for b in batches:
                if not b.num_rows:
                    continue
                x, y, who = dense(b.column("x")), b.column("y").to_numpy(), b.column("worker_id").to_numpy()
                z = np.column_stack((x, y))
                for w in np.unique(who):
                    part = z[who == w]
                    extra = np.zeros(part.shape[1] ** 2 + 1)
                    extra[:-1], extra[-1] = (part.T @ part).reshape(-1), len(part)
                    sums[int(w)] = sums.get(int(w), 0) + extra
            yield _parts_of(sums)

        rows = samples.select(F.col("worker_id").cast("long").alias("worker_id"), "x", F.col("y").cast("double").alias("y"))
        _, s = added(rows.mapInArrow(run, PART))
        d = int(round((s.shape[1] - 1) ** 0.5)) - 1
        if s.nbytes > STATE_LIMIT:
            raise MemoryError("the sums of squares exceed the driver's limit; use SparkSource or the sharded plan")
        full, counts = s[:, :-1].reshape(-1, d + 1, d + 1), s[:, -1]
        return cls(full[:, :d, :d] / counts[:, None, None], full[:, :d, d] / counts[:, None], full[:, d, d] / counts, counts, l2)

    def gradients(self, x: np.ndarray, sampler: Sampler, seed: int, k: int) -> np.ndarray:
        if sampler.batch is not None:
            raise ValueError("sums have no batches; use another source")
        return self.gram @ x - self.moment + self.l2 * x

    def loss(self, x: np.ndarray) -> float:
        return float(np.mean(0.5 * (np.einsum("i,nij,j->n", x, self.gram, x) - 2 * self.moment @ x + self.square)) + 0.5 * self.l2 * x @ x)

    def optimum(self) -> np.ndarray:
        return np.linalg.solve(self.gram.mean(0) + self.l2 * np.eye(self.d), self.moment.mean(0))

    def curvature(self) -> tuple[float, float]:
        """Largest curvature of any worker's function and least of them."""
        ends = [np.linalg.eigvalsh(g) for g in self.gram]
        return max(e[-1] for e in ends) + self.l2, min(e[0] for e in ends) + self.l2


def bytes_of(samples: DataFrame) -> int:
    """Size of the samples as matrices, counted where they are."""
    return samples.agg(F.coalesce(F.sum(F.size("x") + 3), F.lit(0)) * 8).first()[0]


def source_of(samples: DataFrame, objective: Objective, limit: int = STATE_LIMIT) -> RowSource | SparkSource:
    """Samples below the limit are held as rows; larger tables stay where they are, with a job per iteration."""
    return RowSource.from_samples(samples, objective, limit) if bytes_of(samples) <= limit else SparkSource(samples, objective)


class RowSource:
    """Rows held in memory, by worker: for tables below the driver's limit, and inside tests."""

    def __init__(self, x: list[np.ndarray], y: list[np.ndarray], objective: Objective, ids: list[np.ndarray] | None = None, workers: list[int] | None = None):
        self.x, self.y, self.objective, self.n = x, y, objective, len(x)
        cuts = np.cumsum([0, *map(len, y)])
        self.ids = ids or [np.arange(a, b) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        self.workers = workers or list(range(self.n))
        self.features = x[0].shape[1]
        self.d = objective.size(self.features)
        self.every = None

    @classmethod
    def from_samples(cls, samples: DataFrame, objective: Objective, limit: int = STATE_LIMIT) -> RowSource:
        if bytes_of(samples) > limit:
            raise MemoryError("too many rows for the driver; use SparkSource")
        found = samples.select("row_id", "worker_id", "x", "y").toArrow().sort_by([("worker_id", "ascending"), ("row_id", "ascending")])
        x, y, who = dense(found.column("x")), found.column("y").to_numpy(), found.column("worker_id").to_numpy()
        ids, own = found.column("row_id").to_numpy(), [who == w for w in np.unique(who)]
        return cls([x[o] for o in own], [y[o] for o in own], objective, [ids[o] for o in own], np.unique(who).tolist())

    def rows(self, i: int, sampler: Sampler, seed: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        if sampler.scope == "global":
            if self.every is None:
                self.every = np.concatenate(self.x), np.concatenate(self.y), np.concatenate(self.ids)
            x, y, ids = self.every
            keys = (k, ids, np.full(len(ids), self.workers[i]))
        else:
            x, y, ids = self.x[i], self.y[i], self.ids[i]
            keys = (k, ids)
        if sampler.batch is None or sampler.batch >= len(y):
            return x, y
        u = draws(seed, *keys)
        near = np.flatnonzero(u < _enough(sampler.batch, len(y)))
        if len(near) < sampler.batch:
            near = np.arange(len(y))
        take = near[np.lexsort((ids[near], u[near]))[: sampler.batch]]
        return x[take], y[take]

    def gradients(self, x, sampler, seed, k):
        return np.array([self.objective.value_grad(x, *self.rows(i, sampler, seed, k))[1] for i in range(self.n)])

    def loss(self, x):
        return float(np.mean([self.objective.value(x, a, b) for a, b in zip(self.x, self.y, strict=True)]))


def _enough(batch: int, rows: float) -> float:
    """Draws below this make a batch from so many rows, but for one case in 10^12 or so."""
    return 2.0 if rows <= batch else min(2.0, (batch + 8 * batch**0.5 + 32) / rows)


class SparkSource:
    """A job per iteration over cached samples (row_id, worker_id, x, y); ``gradients_of`` serves several models in one pass.

    Rows with small draws are candidates, a few more than wanted, and of these the smallest are the batch (``Sampler``); a task that runs again takes the same rows.
    With scope 'global' every worker draws for itself from all rows.  Should candidates not suffice, which their number makes all but impossible, all rows are.
    ``close`` frees the samples.

    A run (``fit``) says in ``until`` which iteration is its last: batches do not depend on the model, so those of many iterations are drawn in one pass and held, as
    many as fit half of ``STATE_LIMIT``.

    With a ``width``, x is a struct of places (at) and numbers (v) of so wide a row, for objectives that are linear in it.
    """

    def __init__(self, samples: DataFrame, objective: Objective, width: int | None = None):
        self.samples = samples.select("row_id", F.col("worker_id").cast("long").alias("worker_id"), "x", F.col("y").cast("double").alias("y")).persist()
        self.objective = objective
        counts = self.samples.groupBy("worker_id").count().orderBy("worker_id").collect()
        self.workers = [r["worker_id"] for r in counts]
        self.counts = np.array([r["count"] for r in counts], float)
        self.n = len(self.workers)
        self.width = width
        self.features = width or len(self.samples.select("x").first()["x"])
        self.d = objective.size(self.features)
        self.until: int | None = None
        self.drawn_as, self.drawn = None, {}

    def gradients_of(self, models: list[np.ndarray], sampler: Sampler, seed: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Mean gradients (models, workers, d) and losses (models, workers)."""
        if len(models) * self.n * self.d * 8 > STATE_LIMIT:
            raise MemoryError("state beyond the driver's limit; use the sharded plan")
        found = self._sums(models, sampler, seed, k, candidates=True)
        return found if found else self._sums(models, sampler, seed, k, candidates=False)

    def _batch(self, sampler: Sampler, seed: int, k: int, candidates: bool) -> DataFrame:
        rows, size = self.samples, sampler.batch
        if sampler.scope == "global":
            share = 2.0 if size is None or not candidates else _enough(size, self.counts.sum())
            takers = F.filter(F.array(*[F.lit(w) for w in self.workers]).cast("array<bigint>"), lambda w: draw(seed, k, F.col("row_id"), w) < share)
            rows = rows.select(F.explode(takers).alias("worker_id"), "row_id", "x", "y")
            u = draw(seed, k, F.col("row_id"), F.col("worker_id"))
        elif size is None:
            return rows
        else:
            u = draw(seed, k, F.col("row_id"))
            if candidates:
                share = F.element_at(F.create_map(*[F.lit(v) for w, c in zip(self.workers, self.counts, strict=True) for v in (w, _enough(size, c))]), F.col("worker_id"))
                rows = rows.where(u < share)
        if size is None:
            return rows
        place = F.row_number().over(Window.partitionBy("worker_id").orderBy("u", "row_id"))
        return rows.withColumn("u", u).withColumn("place", place).where(F.col("place") <= size)

    def _sums(self, models: list[np.ndarray], sampler: Sampler, seed: int, k: int, candidates: bool) -> tuple[np.ndarray, np.ndarray] | None:
        rows = self._batch(sampler, seed, k, candidates)
        shared = rows.sparkSession.sparkContext.broadcast(models)
        objective, m, width = self.objective, len(models), self.width

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[int, np.ndarray] = {}
            for b in batches:
                if not b.num_rows:
                    continue
                x, y, who = SparseRows.of(b.column("x"), width) if width else dense(b.column("x")), b.column("y").to_numpy(), b.column("worker_id").to_numpy()
                for w in np.unique(who):
                    own = who == w
                    found = [objective.value_grad(p, x[own], y[own]) for p in shared.value]
                    row = np.concatenate([np.concatenate((g, [v, 1.0])) for v, g in found]) * own.sum()
                    sums[int(w)] = sums.get(int(w), 0) + row
            yield _parts_of(sums)

        who, s = added(rows.select("worker_id", "x", "y").mapInArrow(run, PART))
        s = s.reshape(len(who), m, -1)
        if sampler.batch is not None:
            wanted = np.minimum(sampler.batch, self.counts.sum() if sampler.scope == "global" else self.counts)
            if len(who) < self.n or (np.rint(s[:, 0, -1]) != wanted).any():
                if candidates:
                    return None
                raise RuntimeError("a batch is not complete")
        at = np.searchsorted(self.workers, who)
        out, loss = np.zeros((m, self.n, self.d)), np.zeros((m, self.n))
        for j in range(m):
            out[j, at] = s[:, j, :-2] / s[:, j, -1:]
            loss[j, at] = s[:, j, -2] / s[:, j, -1]
        return out, loss

    def gradients(self, x, sampler, seed, k):
        if sampler.batch is not None and self.until is not None and k <= self.until:
            if (sampler, seed) != self.drawn_as or k not in self.drawn:
                self.drawn_as, self.drawn = (sampler, seed), self._ahead(sampler, seed, k)
            if k in self.drawn:
                return np.array([self.objective.value_grad(x, *rows)[1] for rows in self.drawn[k]])
        return self.gradients_of([x], sampler, seed, k)[0][0]

    def _ahead(self, sampler: Sampler, seed: int, first: int) -> dict[int, list[tuple[np.ndarray, np.ndarray]]]:
        """Batches (x, y) of all workers for iterations from ``first`` on; an iteration whose candidates do not suffice is left out."""
        size, by_all = sampler.batch, sampler.scope == "global"
        counts = np.full(self.n, self.counts.sum()) if by_all else self.counts
        wanted = np.minimum(size, counts).astype(int)
        last = min(self.until, first + AHEAD - 1, first - 1 + STATE_LIMIT // 2 // int(wanted.sum() * (self.features + 4) * 8))
        if last <= first or self.width:
            return {}
        workers, share = np.array(self.workers), np.array([_enough(size, c) for c in counts])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                ids, own = b.column("row_id").to_numpy(), np.searchsorted(workers, b.column("worker_id").to_numpy())
                for k in range(first, last + 1):
                    for i in range(len(workers)) if by_all else (None,):
                        u = draws(seed, k, ids, np.full(len(ids), workers[i])) if by_all else draws(seed, k, ids)
                        near = np.flatnonzero(u < (share[i] if by_all else share[own]))
                        if len(near):
                            who = np.full(len(near), workers[i]) if by_all else workers[own[near]]
                            rows = b.take(pa.array(near))
                            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(near), k)), pa.array(who), pa.array(u[near]), *(rows.column(c) for c in ("row_id", "x", "y"))], names=["k", "worker_id", "u", "row_id", "x", "y"])

        place = F.row_number().over(Window.partitionBy("k", "worker_id").orderBy("u", "row_id"))
        kind = {f.name: f.dataType.simpleString() for f in self.samples.schema}
        near = self.samples.mapInArrow(run, f"k bigint, worker_id bigint, u double, row_id {kind['row_id']}, x {kind['x']}, y double").withColumn("place", place)
        found = near.where(F.col("place") <= size).toArrow().sort_by([(c, "ascending") for c in ("k", "worker_id", "place")])
        x, y = dense(found.column("x")), found.column("y").to_numpy()
        at = (found.column("k").to_numpy() - first) * self.n + np.searchsorted(workers, found.column("worker_id").to_numpy())
        has = np.bincount(at, minlength=(last - first + 1) * self.n).reshape(-1, self.n)
        ends = np.cumsum([0, *has.reshape(-1)])
        parts = [(x[a:z], y[a:z]) for a, z in zip(ends[:-1], ends[1:], strict=True)]
        return {first + j: parts[j * self.n : (j + 1) * self.n] for j in range(len(has)) if (has[j] == wanted).all()}

    def close(self) -> None:
        self.samples.unpersist()
        self.drawn_as, self.drawn = None, {}

    def loss(self, x):
        return float(self.gradients_of([x], Sampler(), 0, 0)[1].mean())


# ---- loop -------------------------------------------------------------------------------------------------------------

TRACE = "method string, iter bigint, step double, loss double, dist double, up_norm double, up_norm_max double, down_norm double, bits_up double, bits_down double, test_loss double"


@dataclass
class Fit:
    model: np.ndarray
    trace: list[dict]
    state: State
    invariant: float = 0.0

    def column(self, name: str) -> np.ndarray:
        return np.array([r[name] for r in self.trace], float)


def validate(method: Method, d: int, strict: bool = False) -> list[str]:
    """What of the method's settings lies outside the region that the analysis covers."""
    from terse.plans import theory

    out = []
    if method.down == "model" and method.codec_down.unbiased:
        c = method.codec_down.constant(d)
        if method.apply_rate > theory.apply_rate_max(c) + 1e-12:
            out.append(f"apply_rate {method.apply_rate} above {theory.apply_rate_max(c):.4g}")
        if method.carry_weight and c:
            out.append("carry_weight above 0 needs apply_rate below its bound")
    if strict and out:
        raise ValueError("; ".join(out))
    return out


def fit(
    source, method: Method, schedule: Schedule, iterations: int, *, x0=None, optimum=None, sampler: Sampler | None = None, seed: int = 1, every: int = 1, measure_loss: bool = False, test=None, stop=None, state=None, init: str = "seed"
) -> Fit:
    """Runs a method; every ``every`` iterations a row of the trace is kept.  ``stop`` ends the run once the distance to the optimum is below it.

    ``state``, of an earlier run, goes on where that ended: iterations, draws, steps, bits and snapshots are counted from there.  ``init`` says how workers got the
    first model: all of them from the same seed, or by a broadcast that is paid for once.
    """
    sampler = sampler or Sampler()
    x0 = np.zeros(source.d) if x0 is None else np.asarray(x0, float)
    state = state or State.start(x0, source.n, 32.0 * source.d if init == "broadcast" else 0.0)
    trace, gap = [], 0.0
    per_up, per_down = method.bits(source.d, source.n)
    last = state.iteration + iterations - 1
    if isinstance(source, SparkSource):
        source.until = last
    for k in range(state.iteration, last + 1):
        step = schedule.at(k)
        g = source.gradients(state.shared, sampler, seed, k)
        if method.refresh is not None:
            if state.at_snapshot is None or generator(seed, k, 9).random() < method.refresh:
                state.snapshot, state.at_snapshot = state.shared.copy(), source.gradients(state.shared, Sampler(), seed, k)
            g = g - source.gradients(state.snapshot, sampler, seed, k) + state.at_snapshot
        told = iterate(method, state, g, step, seed, k)
        state.iteration, state.bits_up, state.bits_down = k + 1, state.bits_up + per_up, state.bits_down + per_down
        if method.anchor_rate is not None:
            gap = max(gap, float(np.abs(state.anchors.mean(0) - state.anchor_mean).max()))
        dist = float(np.linalg.norm(state.shared - optimum)) if optimum is not None else None
        if k % every == 0 or k == last:
            row = {"method": method.name, "iter": k + 1, "step": step, "dist": dist, "bits_up": state.bits_up, "bits_down": state.bits_down} | {c: told[c] for c in ("up_norm", "up_norm_max", "down_norm")}
            row["loss"] = source.loss(state.shared) + method.prox.penalty(state.shared) if measure_loss else None
            row["test_loss"] = test(state.shared) if test else None
            trace.append(row)
        if not np.isfinite(state.shared).all() or float(np.abs(state.shared).max()) > 1e12 or (stop is not None and dist is not None and dist < stop):
            break
    if isinstance(source, SparkSource):
        source.until = None
    return Fit(state.shared, trace, state, gap)


def trace_frame(spark: SparkSession, fits: list[Fit]) -> DataFrame:
    """The traces of several runs as one table."""
    names = [c.split()[0] for c in TRACE.split(", ")]
    rows = [tuple(None if r[c] is None else r[c] if c in ("method", "iter") else float(r[c]) for c in names) for f in fits for r in f.trace]
    return spark.createDataFrame(rows, TRACE)


def regularised_optimum(source: QuadraticSource, prox, iterations: int = 20_000) -> np.ndarray:
    """Accelerated proximal descent to machine precision, the ground truth where there is no closed form."""
    gram, moment = source.gram.mean(0), source.moment.mean(0)
    top = np.linalg.eigvalsh(gram)[-1] + source.l2
    x = z = np.zeros(source.d)
    t = 1.0
    for _ in range(iterations):
        new = prox.apply(z - (gram @ z - moment + source.l2 * z) / top, 1 / top)
        t_new = (1 + (1 + 4 * t * t) ** 0.5) / 2
        z = new + (t - 1) / t_new * (new - x)
        if np.abs(new - x).max() < 1e-15:
            return new
        x, t = new, t_new
    return x


def optimum_by_products(source, iterations: int | None = None, tolerance: float = 1e-10) -> np.ndarray:
    """Least-squares optimum by conjugate gradients, for models whose matrix of sums would not fit: a pass over the source an iteration, state of size d."""
    pull = lambda v: source.gradients(v, Sampler(), 0, 0).mean(0)
    at_zero = pull(np.zeros(source.d))
    x, r = np.zeros(source.d), -at_zero
    p, size = r.copy(), float(r @ r)
    goal = tolerance * size**0.5
    for _ in range(iterations or 2 * source.d):
        if size**0.5 <= goal:
            break
        bent = pull(p) - at_zero
        along = size / float(p @ bent)
        x, r = x + along * p, r - along * bent
        size, before = float(r @ r), size
        p = r + size / before * p
    return x


STATE_ARRAYS = ("shared", "precise", "anchors", "anchor_mean", "errors", "carry", "snapshot", "at_snapshot")


def save(fit_: Fit, spark: SparkSession, path: str) -> None:
    """A run's whole state as one row, to go on from later."""
    s = fit_.state
    columns = {c: None if getattr(s, c) is None else np.asarray(getattr(s, c)).reshape(-1).tolist() for c in STATE_ARRAYS}
    ddl = ", ".join(f"{c} array<double>" for c in columns) + ", last_step double, bits_up double, bits_down double, iteration bigint, n int"
    row = (*columns.values(), float(s.last_step), float(s.bits_up), float(s.bits_down), s.iteration, len(s.anchors))
    spark.createDataFrame([row], ddl).coalesce(1).write.mode("overwrite").parquet(path)


def resume(spark: SparkSession, path: str) -> State:
    r = spark.read.parquet(path).first()
    shape = lambda c: (r["n"], -1) if c in ("anchors", "errors", "at_snapshot") else -1
    arrays = {c: None if r[c] is None else np.array(r[c]).reshape(shape(c)) for c in STATE_ARRAYS}
    return State(**arrays, last_step=r["last_step"], bits_up=r["bits_up"], bits_down=r["bits_down"], iteration=r["iteration"])


def ridge_problem(rng_seed: int = 3, rows: int = 1200, features: int = 500, workers: int = 20, scale: str = "half", noise: float = 0.1, l2: float = 0.1):
    """The synthetic regression: a random matrix at one of three scales, a planted model, Gaussian targets, rows dealt evenly in order."""
    rng = np.random.default_rng(rng_seed)
    a = rng.random((rows, features)) / 8 if scale == "uniform" else rng.normal(0, {"half": 0.5, "one": 1.0}[scale], (rows, features))
    planted = rng.normal(0, 1, features)
    y = a @ planted + rng.normal(0, noise, rows)
    parts = np.array_split(np.arange(rows), workers)
    return RowSource([a[p] for p in parts], [y[p] for p in parts], Ridge(l2))


def quadratic(source: RowSource) -> QuadraticSource:
    """Sums of a held least-squares source."""
    gram = np.array([x.T @ x / len(x) for x in source.x])
    moment = np.array([x.T @ y / len(y) for x, y in zip(source.x, source.y, strict=True)])
    return QuadraticSource(gram, moment, np.array([y @ y / len(y) for y in source.y]), np.array([len(y) for y in source.y], float), source.objective.l2)
