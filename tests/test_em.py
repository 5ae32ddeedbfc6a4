import numpy as np
import pytest

from relmix.models.em import best_of, fit, rounds_to
from relmix.models.families import EmptyComponentError, ExpertMixture, Gaussian, LinearMixture, gaussian1d
from relmix.models.init import init_from, init_quantile, init_sample, init_spread, init_uniform
from relmix.operators.features import InvalidRowsError, bind_features
from relmix.plans import fused
from relmix.plans.base import choose


def frame(spark, x, y=None):
    names = ["tid"] + [f"x{j}" for j in range(x.shape[1])] + (["y"] if y is not None else [])
    data = [(i, *map(float, r), *([float(y[i])] if y is not None else [])) for i, r in enumerate(x)]
    return spark.createDataFrame(data, ", ".join(f"{n} {'bigint' if n == 'tid' else 'double'}" for n in names)).cache()


def reference(x, params, rounds):
    """Plain EM for full-covariance mixtures."""
    w, mu, s = params["weight"].copy(), params["mu"].copy(), params["sigma"].copy()
    trace = []
    for _ in range(rounds):
        dens = np.stack([w[k] * np.exp(-0.5 * np.einsum("ni,ij,nj->n", x - mu[k], np.linalg.inv(s[k]), x - mu[k])) / np.sqrt(np.linalg.det(2 * np.pi * s[k])) for k in range(len(w))], 1)
        trace.append(np.log(dens.sum(1)).sum())
        p = dens / dens.sum(1, keepdims=True)
        nk = p.sum(0)
        mu = p.T @ x / nk[:, None]
        s = np.stack([(p[:, k : k + 1] * (x - mu[k])).T @ (x - mu[k]) / nk[k] for k in range(len(w))])
        w = nk / len(x)
    return w, mu, s, trace


@pytest.fixture(scope="module")
def blobs():
    rng = np.random.default_rng(0)
    return np.concatenate([rng.normal(m, 1, (150, 2)) for m in ([-3, 0], [3, 1], [0, 5])])


START = {"weight": np.full(3, 1 / 3), "mu": np.array([[-2.0, 0], [2, 0], [0, 3]]), "sigma": np.repeat(np.eye(2)[None] * 2, 3, 0)}


@pytest.mark.parametrize("plan", ["fused", "explode", "arrow", "relational"])
def test_every_plan_equals_the_reference(spark, blobs, plan):
    done = fit(frame(spark, blobs), Gaussian(2), START, 3, plan=plan)
    w, mu, s, trace = reference(blobs, START, 3)
    assert np.allclose(done.params["weight"], w) and np.allclose(done.params["mu"], mu) and np.allclose(done.params["sigma"], s)
    assert np.allclose([t[1] for t in done.trace], trace)
    assert all(a <= b + 1e-9 for a, b in zip(trace, trace[1:], strict=False))


@pytest.mark.parametrize("plan", ["wide", "coordinate", "hybrid", "arrow"])
def test_diagonal_plans_agree(spark, blobs, plan):
    data = frame(spark, blobs)
    a, b = (fit(data, Gaussian(2, cov="diag"), START, 2, plan=p).params for p in ("fused", plan))
    assert all(np.allclose(a[k], b[k]) for k in a)


def test_one_step_by_hand(spark):
    """Two points, two components a distance 2 apart with unit spread: responsibilities 1 / (1 + e^-2)."""
    done = fit(frame(spark, np.array([[-1.0], [1.0]])), Gaussian(1), gaussian1d([0.5, 0.5], [-1, 1], [1, 1]), 1)
    p = 1 / (1 + np.exp(-2))
    assert np.allclose(done.params["mu"].ravel(), [1 - 2 * p, 2 * p - 1])
    assert np.allclose(done.params["sigma"].ravel(), 1 - (2 * p - 1) ** 2)
    assert np.allclose(done.params["weight"], 0.5)


def test_invariants_permutation_shift_and_offset(spark, blobs):
    data = frame(spark, blobs)
    base = fit(data, Gaussian(2), START, 3).params
    turned = {k: v[[2, 0, 1]] for k, v in START.items()}
    other = fit(data, Gaussian(2), turned, 3).params
    assert np.allclose(other["mu"], base["mu"][[2, 0, 1]]) and np.isclose(base["weight"].sum(), 1)
    moved = START | {"mu": START["mu"] + 1e6}
    far = fit(frame(spark, blobs + 1e6), Gaussian(2), moved, 3).params
    assert np.allclose(far["sigma"], base["sigma"], rtol=1e-5) and np.allclose(far["mu"] - 1e6, base["mu"], atol=1e-6)
    assert (np.linalg.eigvalsh(base["sigma"]) > 0).all()


def test_resume_stop_and_trace(spark, blobs):
    data = frame(spark, blobs)
    ten = fit(data, Gaussian(2), START, 6)
    first = fit(data, Gaussian(2), START, 2)
    rest = fit(data, Gaussian(2), first.params, 4, start=first)
    assert np.allclose(rest.params["mu"], ten.params["mu"]) and [t[0] for t in rest.trace] == [1, 2, 3, 4, 5, 6]
    stopped = fit(data, Gaussian(2), START, 50, eps=1e-3)
    assert stopped.converged and stopped.rounds() < 50
    assert rounds_to(stopped.trace, 1e-3) <= stopped.rounds()
    assert len(fit(data, Gaussian(2), START, 3, keep_history=True).history) == 3


def test_covariance_kinds(spark, blobs):
    data = frame(spark, blobs)
    tied = fit(data, Gaussian(2, cov="tied"), START, 2).params["sigma"]
    assert np.allclose(tied[0], tied[1])
    round_ = fit(data, Gaussian(2, cov="spherical"), START, 2).params["sigma"]
    assert np.allclose(round_[:, 0, 0], round_[:, 1, 1]) and np.allclose(round_[:, 0, 1], 0)


def test_degenerate_components(spark):
    x = np.array([[0.0], [0.0], [0.1], [0.2]])
    start = gaussian1d([0.5, 0.5], [0.1, 1e4], [1.0, 1e-3])
    data = frame(spark, x)
    kept = fit(data, Gaussian(1), start, 2).params
    assert np.isfinite(kept["mu"]).all() and kept["mu"][1, 0] == 1e4
    seeded = fit(data, Gaussian(1, on_empty="reseed"), start, 2).params
    assert abs(seeded["mu"][1, 0]) < 5
    with pytest.raises(EmptyComponentError):
        fit(data, Gaussian(1, on_empty="error"), start, 2)
    same = fit(frame(spark, np.zeros((5, 1))), Gaussian(1, floor=1e-4), gaussian1d([1.0], [0.5], [1.0]), 3).params
    assert np.isclose(same["sigma"].ravel()[0], 1e-4)
    assert fit(data.limit(0), Gaussian(1), start, 3).rounds() == 0


def lines(n=400):
    rng = np.random.default_rng(5)
    x = rng.uniform(-1, 1, (n, 1))
    label = np.arange(n) % 2
    return x, np.where(label == 0, 2 * x[:, 0] + 1, -x[:, 0] - 1) + rng.normal(0, 0.1, n), label


LINES = {"weight": np.array([0.5, 0.5]), "beta": np.array([[1.0, 0.5], [-0.5, -0.5]]), "var": np.array([0.5, 0.5])}


@pytest.mark.parametrize("plan", ["fused", "explode", "arrow"])
def test_linear_mixture_recovers_lines(spark, plan):
    x, y, _ = lines()
    done = fit(frame(spark, x, y), LinearMixture(1), LINES, 15, plan=plan)
    assert np.allclose(done.params["beta"], [[2, 1], [-1, -1]], atol=0.05)
    gains = [t[1] for t in done.trace]
    assert all(a <= b + 1e-6 for a, b in zip(gains, gains[1:], strict=False))


def test_linear_mixture_without_intercept(spark):
    x, _, label = lines()
    y = np.where(label == 0, 2 * x[:, 0], -x[:, 0])
    start = {"weight": np.array([0.5, 0.5]), "beta": np.array([[1.0], [-0.5]]), "var": np.array([0.5, 0.5])}
    got = fit(frame(spark, x, y), LinearMixture(1, intercept=False), start, 10).params["beta"]
    assert np.allclose(got.ravel(), [2, -1], atol=0.02)


@pytest.mark.parametrize(("gate", "steps"), [("ls", 1), ("newton1", 1), ("irls", 3)])
def test_expert_mixture_learns_a_gate(spark, gate, steps):
    """Left of zero one line holds, right of it the other."""
    rng = np.random.default_rng(6)
    x = rng.uniform(-2, 2, (500, 1))
    y = np.where(x[:, 0] < 0, 2 * x[:, 0] + 1, -x[:, 0] - 1) + rng.normal(0, 0.1, 500)
    start = {k: LINES[k] for k in ("beta", "var")} | {"theta": np.array([[-0.5, 0.0], [0.5, 0.0]])}
    done = fit(frame(spark, x, y), ExpertMixture(1, gate=gate), start, 12, gate_steps=steps)
    assert done.trace[-1][1] > done.trace[0][1]
    assert done.params["theta"][1, 0] > 0.5 > -0.5 > done.params["theta"][0, 0]
    assert np.allclose(done.params["theta"].sum(0), 0, atol=1e-9)
    plain = fit(frame(spark, x, y), LinearMixture(1), LINES, 12)
    assert done.trace[-1][1] > plain.trace[-1][1]


def test_planner_and_plan_shapes(spark, blobs):
    data = frame(spark, blobs)
    assert choose(Gaussian(1), gaussian1d([0.5, 0.5], [0, 1], [1, 1])) == "fused" and choose(Gaussian(2), START) == "arrow"
    big = {"weight": np.full(8, 1 / 8), "mu": np.zeros((8, 20)), "sigma": np.repeat(np.eye(20)[None], 8, 0)}
    assert choose(Gaussian(20), big) == "arrow"
    plan = fused.round_frame(data, Gaussian(2), START)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "Join" not in plan and "Window" not in plan
    grouped = fused.run_round(data, Gaussian(2), START, groups=3)
    whole = fused.run_round(data, Gaussian(2), START)
    assert np.isclose(grouped.loglik, whole.loglik) and np.allclose(grouped.stats, whole.stats)


def test_starts(spark, blobs):
    data, family = frame(spark, blobs), Gaussian(2)
    for p in (init_uniform(data, family, 3, 1), init_quantile(data, family, 3), init_sample(data, family, 3, 1), init_spread(data, family, 3, 1)):
        assert p["mu"].shape == (3, 2) and np.isclose(p["weight"].sum(), 1)
    again = init_sample(data, family, 3, 1)
    assert np.allclose(again["mu"], init_sample(data, family, 3, 1)["mu"])
    relation = spark.createDataFrame(family.rows(START), family.schema)
    assert np.allclose(init_from(relation, family)["mu"], START["mu"])
    best = best_of(data, family, [START, init_uniform(data, family, 3, 4)], 4)
    assert best.trace[-1][1] >= fit(data, family, START, 4).trace[-1][1]
    assert init_uniform(frame(spark, *lines()[:2]), LinearMixture(1), 2, 1)["beta"].shape == (2, 2)


def test_invalid_numbers(spark):
    df = spark.createDataFrame([(1, 1.0), (2, None), (3, float("nan")), (4, float("inf"))], "id int, v double")
    assert bind_features(df, ["v"], tid="id").count() == 1
    with pytest.raises(InvalidRowsError):
        bind_features(df, ["v"], on_invalid="error")


def test_agrees_with_mllib_likelihood(spark, blobs):
    from pyspark.ml.clustering import GaussianMixture
    from pyspark.ml.feature import VectorAssembler

    data = frame(spark, blobs)
    ours = fit(data, Gaussian(2), START, 40, eps=1e-4).trace[-1][1]
    theirs = GaussianMixture(k=3, seed=3, maxIter=100, tol=1e-5).fit(VectorAssembler(inputCols=["x0", "x1"], outputCol="features").transform(data)).summary.logLikelihood
    assert ours >= theirs - 2
