from __future__ import annotations

from math import inf

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from terse.operators import codecs as C
from terse.operators import objectives as O
from terse.operators import wire
from terse.functions.draws import draw, draws
from terse.plans import engine
from terse.plans import methods as M
from terse.plans import sharded, theory, traced
from terse.plans.engine import QuadraticSource, RowSource, Sampler, SparkSource, fit, optimum_by_products, quadratic, regularised_optimum, resume, ridge_problem, save, source_of, validate
from terse.workloads import embedding_ridge, lineitem_features, residual_net

UNBIASED = [C.RandomSparsify(0.3), C.NormTernary(inf, 4), C.NormTernary(2, None), C.NormTernary(1, 8), C.NormTernary(3.0, None), C.MultiLevel(4), C.BudgetSparsify(4.0), C.Blocked(C.NormTernary(inf, None), (3, 5))]


# ---- codecs and wire ----------------------------------------------------------------------------------------------


@pytest.mark.parametrize("codec", UNBIASED, ids=lambda c: f"{type(c).__name__}{getattr(c, 'p', '')}")
def test_unbiased_with_bounded_variance(codec):
    v = np.array([3.0, -1.0, 0.0, 4.0, 0.5, -2.0, 1.0, 0.25])
    ratio, bias = C.measured_constant(codec, v, 20_000)
    bound = codec.constant(len(v))
    spread = np.sqrt(max(ratio, 1e-9)) * np.linalg.norm(v) / np.sqrt(20_000)
    assert bias < 5 * spread
    if np.isfinite(bound):
        assert ratio <= bound * 1.03 + 1e-12


class Given:
    """Draws that are given."""

    def __init__(self, u):
        self.u, self.at = u, 0

    def random(self, shape):
        n = int(np.prod(shape))
        part = np.resize(self.u[self.at : self.at + n], n)
        self.at += n
        return part.reshape(shape)


FORMS = [
    C.Identity(), C.LevelRounding((-4.0, -1.0, 0.0, 2.0, 5.0)), C.RandomSparsify(0.3), C.NormTernary(inf, 4), C.NormTernary(2, 5), C.NormTernary(1, None), C.NormTernary(3.0, 4),
    C.Blocked(C.NormTernary(2, None), (3, 9, 1)), C.MultiLevel(4), C.SignScale(5), C.SignScale(), C.LargestK(4), C.LargestK(None, 0.3),
]


@pytest.mark.parametrize("codec", FORMS, ids=str)
def test_array_expressions_equal_kernels(spark, codec):
    rng = np.random.default_rng(5)
    v, u = np.round(rng.normal(0, 1.5, (20, 13)).clip(-4, 5), 3), rng.random((20, 13))
    v[0], v[1] = 0.0, 1.0
    rows = spark.createDataFrame([(i, a.tolist(), b.tolist()) for i, (a, b) in enumerate(zip(v, u, strict=True))], "i int, v array<double>, u array<double>")
    found = rows.select("i", codec.as_column(F.col("v"), lambda i: F.get("u", i)).alias("q")).orderBy("i").collect()
    for r in found:
        assert np.allclose(r["q"], codec.apply(v[r["i"]], Given(u[r["i"]])), rtol=1e-12, atol=1e-12)


def test_users_codecs_are_known_by_name():
    class Halves(C.Codec):
        def apply(self, v, rng):
            return np.round(np.asarray(v) * 2) / 2

    class Short(C.Codec):
        def apply(self, v, rng):
            return np.asarray(v)[:-1]

    C.register_codec("halves", Halves)
    assert C.CODECS.pop("halves") is Halves
    with pytest.raises(ValueError):
        C.register_codec("short", Short)


def test_known_example():
    v = np.array([3.0, -1.0, 0.0, 4.0])
    ratio, _ = C.measured_constant(C.NormTernary(inf, None), v, 40_000)
    assert abs(ratio - 6 / 26) < 0.01
    assert C.norm_constant(inf, 256) == 7.5 and C.norm_constant(2, 256) == 15 and C.norm_constant(1, 4) == 3
    assert abs(C.norm_constant(3.0, 4) - 0.7) < 0.5


@pytest.mark.parametrize("v", [np.zeros(17), np.eye(1, 17)[0], np.ones(17), np.full(17, 1e300), np.full(17, 1e-300), np.array([2.0])])
def test_edge_vectors(v):
    for codec in (C.NormTernary(inf, 16), C.NormTernary(2, 16), C.MultiLevel(), C.SignScale(), C.LargestK(3), C.BudgetSparsify()):
        if np.abs(v).max() > 1e200 and isinstance(codec, (C.MultiLevel, C.BudgetSparsify)):
            continue
        out = codec.apply(v, np.random.default_rng(0))
        assert len(out) == len(v) and np.isfinite(out).all()
    with pytest.raises(ValueError):
        C.NormTernary().apply(np.array([np.nan]), np.random.default_rng(0))


@settings(max_examples=80, deadline=None)
@given(st.lists(st.sampled_from([-1, 0, 0, 0, 1]), min_size=1, max_size=70))
def test_wire_round_trips(trits):
    t = np.array(trits, np.int8)
    for coder in (wire.PrefixTernary, wire.Base3, wire.GapCode):
        assert (coder.unpack(coder.pack(t), len(t)) == t).all()
    v = t * 1.5
    assert (wire.SparsePairs.unpack(wire.SparsePairs.pack(v), len(v)) == v).all()
    assert (wire.RawFloats.unpack(wire.RawFloats.pack(v, 64), len(v)) == v).all()
    q = np.array(C.NormTernary(inf, 8).apply(v, np.random.default_rng(1)), np.float32).astype(float)
    assert np.allclose(wire.unpack_ternary(wire.pack_ternary(q, 8), len(q), 8), q)


def test_prices():
    m = M.two_way_residual(256)
    up, down = m.bits(1 << 20)
    raw = 64.0 * (1 << 20)
    assert abs(1 - (up + down) / raw - 0.949219) < 1e-6
    up, down = M.gradient_difference(256).bits(1 << 20)
    assert abs(1 - (up + down) / raw - 0.474609) < 1e-6


# ---- objectives -----------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("objective", [O.Ridge(0.1), O.Logistic(), O.Softmax(3, 0.01), O.Perceptron(5, 3), O.ConvNet((2, 3), 3), O.ResidualNet(4, 2, 3)], ids=lambda o: type(o).__name__)
def test_gradients_are_right(objective):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(6, 64))
    y = rng.integers(0, 2, 6).astype(float)
    w = objective.start(64, 2) + rng.normal(0, 0.05, objective.size(64))
    _, g = objective.value_grad(w, x, y)
    for i in rng.choice(len(w), 25, replace=False):
        e = np.zeros(len(w))
        e[i] = 1e-6
        near = (objective.value(w + e, x, y) - objective.value(w - e, x, y)) / 2e-6
        assert abs(near - g[i]) < 1e-4 * max(1, abs(g[i]))


@pytest.mark.parametrize("prox", [O.L1(0.3), O.SquaredL2(0.5), O.ElasticNet(0.2, 0.3), O.Box(-0.5, 0.5), O.GroupL2(0.4, 3), O.Ball(1.0)])
def test_proximal_maps_minimise(prox):
    rng = np.random.default_rng(1)
    v, step = rng.normal(size=6), 0.7
    z = prox.apply(v, step)
    best = prox.penalty(z) + ((z - v) ** 2).sum() / (2 * step)
    for _ in range(200):
        other = z + rng.normal(0, 0.1, 6)
        assert prox.penalty(other) + ((other - v) ** 2).sum() / (2 * step) >= best - 1e-9


# ---- methods ----------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def small():
    return quadratic(ridge_problem(rows=200, features=32, workers=5))


def same(a, b, tolerance=1e-12):
    assert np.abs(a.model - b.model).max() < tolerance


def test_reductions(small):
    run = lambda m, **k: fit(small, m, M.Schedule(0.05), 40, **k)
    raw = C.Identity()
    same(run(M.plain()), run(M.two_way_residual(codec_up=raw, codec_down=raw)))
    same(run(M.plain()), run(M.two_sided_compensated(codec=raw)))
    same(run(M.plain()), run(M.two_sided_largest_k(k=32)))
    same(run(M.gradient_difference(8)), run(M.two_way_residual(8, codec_down=raw, carry_weight=0.0)))
    same(run(M.ternary_gradient(8)), run(M.quantized_gradient(codec=C.NormTernary(inf, 8))))
    same(run(M.all_to_all_quantized(8)), run(M.ternary_gradient(8)))
    same(run(M.two_way_residual(8)), run(M.two_way_residual_smooth(8)), 1e-9)
    assert M.plan_method(M.two_way_residual(8)).down == "gradient"


def test_smooth_form_under_a_changing_step(small):
    schedule = M.Schedule(0.05, 0.5, 10)
    a, b = fit(small, M.two_way_residual(8), schedule, 40), fit(small, M.two_way_residual_smooth(8), schedule, 40)
    same(a, b, 1e-9)


def test_mean_of_anchors_is_the_masters(small):
    assert fit(small, M.two_way_residual(8), M.Schedule(0.05), 100).invariant < 1e-12


@pytest.mark.parametrize("name", sorted(M.BASELINES))
def test_every_method_runs(small, name):
    f = fit(small, M.BASELINES[name](), M.Schedule(0.02), 60, optimum=small.optimum())
    assert len(f.trace) == 60 and np.isfinite(f.model).all()


def test_shapes_of_the_seven_curves(spark, sf_dir):
    source = QuadraticSource.from_samples(embedding_ridge(spark, sf_dir), 0.1)
    best = source.optimum()
    end = {m.name: fit(source, m, M.Schedule(0.05), 1000, optimum=best, every=10) for m in M.seven_curves(16)}
    for name in ("plain", "gradient_difference", "two_way_residual"):
        assert end[name].trace[-1]["dist"] < 1e-9, name
    for name in ("quantized_gradient", "compensated_gradient", "two_sided_compensated", "two_sided_largest_k"):
        assert end[name].trace[-1]["dist"] > 1e-3, name
    up, down = end["two_way_residual"].column("up_norm"), end["two_way_residual"].column("down_norm")
    k = np.arange(40)
    for norms in (up, down):  # residuals fall exponentially
        logs = np.log(norms[:40] + 1e-300)
        assert np.polyfit(k, logs, 1)[0] < 0 and np.corrcoef(k, logs)[0, 1] ** 2 > 0.9


def test_synthetic_regression_at_default_settings():
    source = quadratic(ridge_problem())
    best = source.optimum()
    runs = {m.name: fit(source, m, M.Schedule(0.05), 700, optimum=best, every=10) for m in M.seven_curves(256)}
    start = np.linalg.norm(best)
    assert runs["two_way_residual"].trace[-1]["dist"] < 1e-2 * start
    assert abs(np.log10(runs["two_way_residual"].trace[-1]["dist"] / runs["plain"].trace[-1]["dist"])) < 1
    assert runs["two_sided_compensated"].trace[-1]["dist"] > runs["two_sided_largest_k"].trace[-1]["dist"]


@pytest.mark.xfail(reason="reported to diverge at this step; on this matrix it turns back from 4.2 and settles near 8, of 14.7 at the start", strict=False)
def test_norm_coded_two_sided_method_diverges_at_the_larger_step():
    source = quadratic(ridge_problem())
    best = source.optimum()
    run = fit(source, M.two_sided_compensated(256), M.Schedule(0.05), 700, optimum=best, every=100)
    assert run.trace[-1]["dist"] > np.linalg.norm(best)


def test_proximal_run_reaches_the_regularised_optimum(small):
    prox = O.L1(0.02)
    best = regularised_optimum(small, prox)
    f = fit(small, M.two_way_residual(8, prox=prox), M.Schedule(0.05), 3000, optimum=best, stop=1e-9)
    assert f.trace[-1]["dist"] < 1e-6
    assert np.abs(prox.apply(best - 0.1 * (small.gram.mean(0) @ best - small.moment.mean(0) + small.l2 * best), 0.1) - best).max() < 1e-10


def test_spark_gradients_equal_sums_under_any_partitioning(spark, sf_dir):
    samples = embedding_ridge(spark, sf_dir)
    sums = QuadraticSource.from_samples(samples, 0.1)
    w = np.random.default_rng(0).normal(size=64)
    for parts in (1, 7):
        source = SparkSource(samples.repartition(parts), O.Ridge(0.1))
        assert np.allclose(source.gradients(w, Sampler(), 1, 0), sums.gradients(w, Sampler(), 1, 0))
        assert abs(source.loss(w) - sums.loss(w)) < 1e-9
        batch = source.gradients(w, Sampler(10), 1, 3)
        assert batch.shape == (10, 64)
        source.samples.unpersist()


SCHEDULES = {"constant": M.Schedule(0.02), "falling": M.Schedule(0.02, 0.5, 7), "slow": M.Schedule(0.02, slow=5), "horizon": M.Schedule.horizon(20, 5, 4.0, 1.0, 0.1)}


@pytest.mark.parametrize("name", sorted(M.BASELINES))
def test_resume_goes_on_as_if_never_stopped(spark, tmp_path, name):
    source, path = ridge_problem(rows=100, features=16, workers=5), f"file://{tmp_path}/state"
    for k, schedule in enumerate(SCHEDULES.values()):
        run = lambda n, **more: fit(source, M.BASELINES[name](), schedule, n, sampler=Sampler(6, ("local", "global")[k % 2]), init="broadcast", **more)  # noqa: B023, E731
        whole, half = run(20), run(10)
        state = half.state
        if k < 2:
            save(half, spark, path)
            state = resume(spark, path)
        rest = run(10, state=state)
        assert np.array_equal(rest.model, whole.model) and half.trace + rest.trace == whole.trace
        assert rest.state.iteration == 20 and rest.trace[-1]["bits_down"] == whole.trace[-1]["bits_down"]


def test_first_model_by_broadcast_costs_a_vector(small):
    runs = [fit(small, M.two_way_residual(8), M.Schedule(0.05), 5, init=how) for how in ("seed", "broadcast")]
    assert np.array_equal(runs[0].model, runs[1].model)
    assert runs[1].trace[-1]["bits_down"] - runs[0].trace[-1]["bits_down"] == 32 * small.d


def test_numpy_draws_equal_those_of_plans(spark):
    ids = np.array([0, 1, -5, 2**40, 7])
    rows = spark.createDataFrame([(int(i),) for i in ids], "i bigint").select("i", draw(3, 9, F.col("i")).alias("a"), draw(2**33, F.col("i"), F.col("i") + 1).alias("b")).toPandas()
    assert np.array_equal(draws(3, 9, ids), rows.a) and np.array_equal(draws(2**33, ids, ids + 1), rows.b)


@pytest.mark.parametrize("sampler", [Sampler(2), Sampler(7), Sampler(7, "global"), Sampler(10**6), Sampler(None, "global")], ids=str)
def test_batches_do_not_depend_on_where_rows_are(spark, sf_dir, sampler):
    samples = embedding_ridge(spark, sf_dir, workers=4)
    held, tables = RowSource.from_samples(samples, O.Ridge(0.1)), SparkSource(samples.repartition(5), O.Ridge(0.1))
    x = np.linspace(-1, 1, held.d)
    for k in range(3):
        a, b = held.gradients(x, sampler, 4, k), tables.gradients(x, sampler, 4, k)
        assert np.allclose(a, b, rtol=1e-12, atol=1e-12) and (np.abs(a).sum(1) > 0).all()
    tables.close()


def test_batch_gradients_are_unbiased():
    source = ridge_problem(rows=60, features=5, workers=3)
    x = np.ones(5)
    mean = np.mean([source.gradients(x, Sampler(2), 1, k) for k in range(4000)], 0)
    exact = source.gradients(x, Sampler(), 1, 0)
    each = np.std([source.gradients(x, Sampler(2), 1, k) for k in range(200)], 0)
    assert (np.abs(mean - exact) < 5 * each / 4000**0.5).all()


def test_sums_are_added_in_blocks(spark, sf_dir, monkeypatch):
    samples = embedding_ridge(spark, sf_dir, workers=3).repartition(9)
    whole = QuadraticSource.from_samples(samples, 0.1)
    monkeypatch.setattr(engine, "SUM_BLOCK", 1000)
    parts = QuadraticSource.from_samples(samples, 0.1)
    assert np.allclose(whole.gram, parts.gram) and np.allclose(whole.moment, parts.moment) and np.array_equal(whole.counts, parts.counts)


# ---- theory ----------------------------------------------------------------------------------------------------------


def test_theory_values():
    r = theory.recommended(7.5, 7.5, 20, 0.5, 5.0)
    assert [round(r[k], 6) for k in ("anchor_rate", "apply_rate", "extra", "step", "factor")] == [0.058824, 0.117647, 12.75, 0.207792, 44.996875]
    assert theory.recommended(0, 0, 10, 1, 4)["factor"] == 2
    assert np.allclose(theory.anchor_rate_interval(1.5, 10, 3.0), (0.058579, 0.341421), atol=1e-6)
    assert theory.anchor_rate_interval(1.5, 10, 1.0) is None
    assert np.allclose(theory.carry_weight_bounds(1.5, 0.2, 0.2, 1.5, 1, 4), (0.187184, 0.969697), atol=1e-6)
    assert np.allclose(theory.step_interval(0.1, 0.2, 1.5, 1, 4), (0.056818, 0.307692), atol=1e-6)
    assert abs(theory.nonconvex_step_max(0.4, 0.2, 1.5, 1.5, 4) - min((np.sqrt(1 + 48 * 16 / 1.5) - 1) / 48, 1 / (6 * 4 * 0.4 * 1.3 * 2.5))) < 1e-9
    assert validate(M.two_way_residual(256), 500)
    with pytest.raises(ValueError):
        validate(M.two_way_residual(256), 500, strict=True)


def potentials(source, method, step, c_down, extra, sampler, iterations, seeds):
    """Mean over seeds of the convex potential by iteration."""
    best = source.optimum() if hasattr(source, "optimum") else quadratic(source).optimum()
    own, out = source.gradients(best, Sampler(), 0, 0), np.zeros((seeds, iterations))
    for s in range(seeds):
        state, down = M.State.start(np.zeros(source.d), source.n), np.zeros(source.d)
        for k in range(iterations):
            out[s, k] = theory.convex_potential(down, state.shared, best, state.anchors, own, method.apply_rate, c_down, method.carry_weight, extra, step)
            before = state.shared.copy()
            told = M.iterate(method, state, source.gradients(before, sampler, s, k), step, s, k)
            down = np.full(source.d, told["down_norm"] / np.sqrt(source.d))
    return out.mean(0)


def test_contraction_holds_in_the_proven_region(small):
    smooth, mu = small.curvature()
    c = C.norm_constant(inf, 8)
    r = theory.recommended(c, c, small.n, mu, smooth)
    rate = theory.contraction(0.0, r["apply_rate"], r["anchor_rate"], r["step"], c, mu, smooth)
    method = M.two_way_residual(8, r["anchor_rate"], r["apply_rate"], 0.0)
    found = potentials(small, method, r["step"], c, r["extra"], Sampler(), 301, 12)
    assert rate < 1
    for k in (1, 10, 50, 150, 300):
        assert found[k] <= rate**k * found[0] * 1.02


def test_noise_settles_within_the_bound():
    rows = ridge_problem(rows=200, features=16, workers=5)
    sums = quadratic(rows)
    smooth, mu = sums.curvature()
    c, batch = C.norm_constant(inf, 8), Sampler(4)
    r = theory.recommended(c, c, rows.n, mu, smooth)
    rate = theory.contraction(0.0, r["apply_rate"], r["anchor_rate"], r["step"], c, mu, smooth)
    near = [sums.optimum() + np.random.default_rng(i).normal(0, 1, rows.d) for i in range(5)]
    sigma2 = max(np.mean([((rows.gradients(x, batch, 9, k) - rows.gradients(x, Sampler(), 0, 0)) ** 2).sum(1).mean() for k in range(40)]) for x in near)
    ball = theory.noise_ball(0.0, r["apply_rate"], r["anchor_rate"], r["step"], r["extra"], rows.n, rate, sigma2)
    found = potentials(rows, M.two_way_residual(8, r["anchor_rate"], r["apply_rate"], 0.0), r["step"], c, r["extra"], batch, 500, 4)
    assert 0 < found[-100:].mean() <= ball + rate**400 * found[0]


def test_mean_gradient_stays_below_the_nonconvex_bound():
    source = ridge_problem(rows=120, features=16, workers=4)
    sums = quadratic(source)
    smooth, _ = sums.curvature()
    c, k = C.norm_constant(inf, 8), 200
    anchor, apply, extra = 1 / (2 * (c + 1)), 1 / (c + 1), 4 * c * (c + 1) / source.n
    step = theory.horizon_step(k, source.n, smooth, extra, anchor)
    assert step <= theory.nonconvex_step_max(apply, anchor, extra, c, smooth) and M.Schedule.horizon(k, source.n, smooth, extra, anchor).at(7) == step
    batch = Sampler(8, "global")
    sigma2 = max(((source.gradients(np.zeros(16), batch, 3, j) - source.gradients(np.zeros(16), Sampler(scope="global"), 0, 0)) ** 2).sum(1).mean() for j in range(40))
    run, means = M.two_way_residual(8, anchor, apply, 0.0), []
    for s in range(3):
        state = M.State.start(np.zeros(16), source.n)
        for j in range(k):
            means.append((sums.gradients(state.shared, Sampler(), 0, 0).mean(0) ** 2).sum())
            M.iterate(run, state, source.gradients(state.shared, batch, s, j), step, s, j)
    excess = sums.loss(np.zeros(16)) - sums.loss(sums.optimum())
    gap = theory.nonconvex_potential(np.zeros(16), excess, np.zeros((4, 16)), apply, c, extra, smooth, step)
    assert gap == pytest.approx(excess)
    left, bound = theory.nonconvex_bound(apply, anchor, extra, c, smooth, step, sigma2, source.n, k, gap)
    assert left > 0 and left * np.mean(means) <= bound


def test_orders_of_rates():
    rate = theory.asymptotic_rate
    for k in (10**4, 10**6):
        assert rate("two_way_residual", k, 10) == rate("gradient_difference", k, 10) < rate("two_sided_compensated", k, 10)
        assert rate("quantized_gradient", k, 10, bound=1.0) > 1
    speed = rate("two_way_residual", 10**8, 1) / rate("two_way_residual", 10**8, 16)
    assert speed == pytest.approx(4, rel=0.01)
    assert theory.carry_stability(7.5, 1.0) and not theory.carry_stability(0.2, 1.0) and theory.constant_from_norm(inf, 256) == 7.5


def test_methods_reach_the_target_sooner_with_more_workers():
    """With batches drawn from all rows, the squared distance at which runs settle falls with the number of workers."""
    floors = []
    for n in (1, 4, 16):
        source = ridge_problem(rows=320, features=12, workers=n, noise=0.5)
        f = fit(source, M.two_way_residual(4), M.Schedule(0.05), 400, optimum=quadratic(ridge_problem(rows=320, features=12, workers=1, noise=0.5)).optimum(), sampler=Sampler(4, "global"))
        floors.append(np.mean(f.column("dist")[-150:] ** 2))
    assert floors[0] > 2 * floors[1] > 4 * floors[2]


def test_nets_come_in_the_reported_order(spark, sf_dir):
    last = residual_net(spark, sf_dir).toPandas().sort_values("iter").groupby("method").tail(1).set_index("method")
    assert len(last) == 7
    for c in ("loss", "test_loss"):
        near = last[c].drop("two_sided_compensated")
        assert near.max() - near.min() < 0.01 and last[c]["two_sided_compensated"] > near.max() + 0.01 and near.max() < 0.6


def test_two_sided_norm_coder_diverges_at_the_largest_scale():
    source = quadratic(ridge_problem(scale="one"))
    best = source.optimum()
    end = {m.name: fit(source, m, M.Schedule(0.05), 200, optimum=best, every=200).trace[-1]["dist"] / np.linalg.norm(best) for m in (M.plain(), M.gradient_difference(256), M.two_way_residual(256, carry_weight=0.0), M.two_sided_compensated(256))}
    assert end["two_sided_compensated"] > 1e3 > 0.1 > max(end["plain"], end["gradient_difference"], end["two_way_residual"])


def test_products_reach_the_closed_form():
    source = quadratic(ridge_problem(rows=200, features=30, workers=4))
    assert np.allclose(optimum_by_products(source), source.optimum(), atol=1e-7)


def test_tables_beyond_the_limit_stay_in_spark(spark, sf_dir):
    samples = embedding_ridge(spark, sf_dir, workers=3)
    small, large = source_of(samples, O.Ridge(0.1)), source_of(samples, O.Ridge(0.1), limit=1000)
    assert isinstance(small, RowSource) and isinstance(large, SparkSource)
    x = np.linspace(-1, 1, small.d)
    assert np.allclose(small.gradients(x, Sampler(), 1, 0), large.gradients(x, Sampler(), 1, 0))
    with pytest.raises(MemoryError):
        RowSource.from_samples(samples, O.Ridge(0.1), limit=1000)
    every = np.tile(large.gradients(x, Sampler(), 1, 0).T @ large.counts / large.counts.sum(), (3, 1))
    assert np.allclose(large.gradients(x, Sampler(scope="global"), 1, 0), every)
    drawn = large.gradients(x, Sampler(20, "global"), 1, 0)
    assert np.array_equal(drawn, large.gradients(x, Sampler(20, "global"), 1, 0)) and not np.allclose(drawn[0], drawn[1])
    large.samples.unpersist()


def test_order_lines_as_samples(spark, sf_dir):
    """Standardised columns, one row for every line, and the order of methods that the regression on random data shows."""
    rows = lineitem_features(spark, sf_dir)
    assert rows.count() == spark.read.parquet(f"{sf_dir}/lineitem.parquet").count()
    source = QuadraticSource.from_samples(rows, 1.0)
    best = source.optimum()
    last = {m.name: fit(source, m, M.Schedule(0.05), 500, optimum=best, every=500).trace[-1]["dist"] for m in (M.plain(), M.gradient_difference(16), M.two_way_residual(16), M.quantized_gradient(16))}
    assert max(last["plain"], last["gradient_difference"], last["two_way_residual"]) < 1e-6 < 1e-4 < last["quantized_gradient"]


# ---- iterations on tables ------------------------------------------------------------------------------------------------


@pytest.mark.parametrize(("plan", "method"), [
    (sharded.Plan("p", grid=False, iterations=4), M.plain()),
    (sharded.Plan("k", "largest_k", "gradient", "largest_k", memory=1.0, carry=1.0, k=3, grid=False, iterations=4), M.two_sided_largest_k(k=3)),
    (sharded.Plan("s", "sign", memory=1.0, block=4, grid=False, iterations=4), M.Method("s", C.SignScale(4), memory=1.0)),
    (sharded.Plan("r", down="model", anchor_rate=0.1, carry=1.0, l1=0.02, grid=False, iterations=4), M.two_way_residual(codec_up=C.Identity(), codec_down=C.Identity(), prox=O.L1(0.02))),
    (sharded.Plan("x", "sign", "model", "largest_k", anchor_rate=0.1, carry=0.5, k=4, block=4, steps=(0.1, 0.05, 0.05, 0.02), grid=False, iterations=4), M.Method("x", C.SignScale(4), C.LargestK(4), "model", 0.1, carry_weight=0.5)),
], ids=lambda x: x.name)
def test_tables_of_floats_equal_the_loop(spark, monkeypatch, plan, method):
    """Sparse samples: values of 0 have no row, and one worker has none at all for some coordinates."""
    monkeypatch.setattr(sharded, "RANGE", 5)
    rng = np.random.default_rng(2)
    x = np.where(rng.random((40, 12)) < 0.3, rng.normal(size=(40, 12)), 0.0)
    x[:10, 6:] = 0.0
    y, who = x @ rng.normal(size=12), np.repeat(np.arange(4), 10)
    i, j = np.nonzero(x)
    samples = spark.createDataFrame([(int(a), int(who[a]), int(b), float(x[a, b])) for a, b in zip(i, j, strict=True)], "row_id bigint, worker bigint, coord bigint, v double")
    targets = spark.createDataFrame([(int(a), int(who[a]), float(y[a])) for a in range(40) if x[a].any()], "row_id bigint, worker bigint, y double")
    made = sharded.run(samples, targets, plan)
    keep = x.any(1)
    source = RowSource([x[(who == w) & keep] for w in range(4)], [y[(who == w) & keep] for w in range(4)], O.Ridge(0.1))
    schedule = M.Schedule(0.05)
    if plan.steps:
        monkeypatch.setattr(M.Schedule, "at", lambda self, k: plan.steps[k])
    want = fit(source, method, schedule, 4)
    got = np.array([r["x"] for r in made.models[-1].orderBy("coord").collect()])
    assert np.allclose(got, want.model, atol=1e-12)


def test_no_window_of_a_plan_holds_a_whole_table(spark, sf_dir):
    p = sharded.PLANS["iter3_two_sided_largest_k"]
    frame = spark.range(100).select(F.col("id").alias("coord"), F.rand(1).alias("r"))
    plan = sharded._coded(frame, p, "largest_k", "r", "w", 0, "down", None)._jdf.queryExecution().toString()
    assert "TakeOrderedAndProject" in plan and "windowspecdefinition(abs" not in plan.replace(" ", "").lower()


def test_anchors_follow_gradients_in_the_mean(spark, sf_dir):
    rows = traced.QUERIES["measure_anchor_tracking"](spark, sf_dir).toPandas()
    scale = np.abs(rows.expected).mean()
    assert abs((rows.total - rows.expected).mean()) < 0.05 * scale


def test_traced_methods_near_the_planted_model(spark, sf_dir):
    d = traced.QUERIES["measure_distance"](spark, sf_dir).toPandas().pivot(index="iter", columns="method", values="d2")
    assert (d.iloc[-1] < d.iloc[0]).all() and d["plain"].is_monotonic_decreasing
    assert (traced.QUERIES["measure_heterogeneity"](spark, sf_dir).toPandas().norm2 > 0).all()


def test_sparse_rows_give_the_dense_gradients(spark):
    rng = np.random.default_rng(2)
    x, y = rng.normal(size=(40, 9)) * (rng.random((40, 9)) < 0.3), (rng.random(40) < 0.5).astype(float)
    x[3] = 0
    whole = [(i, i % 3, row.tolist(), float(t)) for i, (row, t) in enumerate(zip(x, y, strict=True))]
    sparse = [(i, w, (np.flatnonzero(row).tolist(), [v for v in row if v]), t) for i, w, row, t in whole]
    ddl = "row_id long, worker_id long, x {}, y double"
    a = SparkSource(spark.createDataFrame(whole, ddl.format("array<double>")), O.Logistic())
    b = SparkSource(spark.createDataFrame(sparse, ddl.format("struct<at: array<int>, v: array<double>>")), O.Logistic(), 9)
    models = [rng.normal(size=9), np.zeros(9)]
    for ours, theirs in zip(b.gradients_of(models, Sampler(), 1, 0), a.gradients_of(models, Sampler(), 1, 0), strict=True):
        assert np.allclose(ours, theirs, rtol=1e-12, atol=1e-12)
    a.close()
    b.close()


def test_hashed_words_are_counted_whole(spark, sf_dir):
    from terse.workloads import hashed_words

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").join(spark.read.parquet(f"{sf_dir}/labels.parquet"), "doc_id").where("text is not null")
    words = docs.select("doc_id", F.explode(F.split(F.lower("text"), " ")).alias("w")).select("doc_id", F.expr("pmod(xxhash64(w), 64)").alias("b"))
    want: dict = {}
    for r in words.groupBy("doc_id", "b").count().collect():
        want.setdefault(r["doc_id"], {})[r["b"]] = r["count"]
    rows = hashed_words(spark, sf_dir, 64).collect()
    assert len(rows) == len(want)
    for r in rows:
        counts = want[r["doc_id"]]
        norm = sum(c * c for c in counts.values()) ** 0.5
        assert dict(zip(r["x"]["at"], r["x"]["v"], strict=True)) == pytest.approx({b: c / norm * 4 for b, c in counts.items()})


@pytest.mark.parametrize("sampler", [Sampler(3), Sampler(3, "global"), Sampler(10**6)], ids=str)
def test_batches_are_drawn_ahead(spark, sf_dir, monkeypatch, sampler):
    samples = embedding_ridge(spark, sf_dir, workers=4)
    held, tables = RowSource.from_samples(samples, O.Ridge(0.1)), SparkSource(samples.repartition(3), O.Ridge(0.1))
    jobs, drawn = [], SparkSource._ahead
    monkeypatch.setattr(SparkSource, "_sums", lambda *a, **b: pytest.fail("a job for an iteration"))
    monkeypatch.setattr(SparkSource, "_ahead", lambda *a: jobs.append(a[-1]) or drawn(*a))
    monkeypatch.setattr(engine, "AHEAD", 7)
    runs = [fit(s, M.two_way_residual(16), M.Schedule(0.05), 17, sampler=sampler) for s in (held, tables)]
    assert np.allclose(runs[0].model, runs[1].model, rtol=1e-9, atol=1e-12) and jobs == [0, 7, 14]
    tables.close()
