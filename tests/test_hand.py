"""Small cases worked by hand."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from codedreg.functions.hashrand import gauss, with_gauss
from codedreg.operators import coding, delay, privacy, theory
from codedreg.operators import gradients as grad
from codedreg.plans import training


def examples(spark, rows):
    return spark.createDataFrame(rows, "row_id long, client int, x array<double>, y array<double>")


def test_one_bit():
    assert privacy.gaussian_information([0.0, 1.0], 3, 0.0, 0) == 1.0


def test_cover_takes_the_least_column(spark):
    ex = examples(spark, [(0, 0, [3.0, 1.0], [0.0]), (1, 0, [4.0, 1.0], [0.0])])
    row = privacy.privacy_budget(ex, 3, 0.0).first()
    assert row["h2"] == pytest.approx(1.0) and row["eps_bits"] == pytest.approx(1.0)


def test_single_row_without_noise_is_uncovered(spark):
    ex = examples(spark, [(0, 0, [0.5, 0.7], [0.0])])
    assert privacy.privacy_budget(ex, 3, 0.0).first()["eps_bits"] == math.inf
    assert privacy.privacy_budget(ex, 3, 1.0).first()["eps_bits"] == pytest.approx(1.0)


def test_budget_inverses(spark):
    cover = spark.createDataFrame([(0, 5, 2.0), (1, 5, 0.5)], "client int, l long, h2 double")
    sigma = {r["client"]: r["sigma"] for r in privacy.sigma_for_budget(cover, 16, 0.9).collect()}
    for client, h2 in ((0, 2.0), (1, 0.5)):
        assert 0.5 * math.log2(1 + 16 / (h2 + sigma[client] ** 2)) == pytest.approx(0.9)
    assert {r["coded_rows"] for r in privacy.coded_rows_for_budget(cover, 1.0, 0.0).collect()} == {6, 1}


@pytest.mark.parametrize("deadline, k, p", [(0.99, 0, 0.0), (1.0, 1, 0.9), (1.5, 2, 0.99)])
def test_arrival_probability(spark, deadline, k, p):
    timed = spark.createDataFrame([(0, 0.25, 0.5, 0.25, 0.1)], "client int, t_c double, tau double, t_d double, p_erase double")
    row = delay.arrival_probability(timed, deadline).first()
    assert (row["k_max"], row["p_arrive"]) == (k, pytest.approx(p))


@pytest.mark.parametrize("drop, kept", [(0.0, 20), (0.05, 19), (0.1, 18), (0.5, 10)])
def test_share_kept(spark, drop, kept):
    arrivals = spark.range(20).selectExpr("0 as epoch", "cast(id as int) as client", "cast(id as double) as t")
    assert delay.first_arrivals(arrivals, drop).count() == kept


def test_planner_equals_brute_force(spark):
    rows = [(0, 2e5, 3e5, 1e6, 0.1, 40, 5), (1, 9e5, 9e5, 1e6, 0.1, 40, 5), (2, 3e4, 4e5, 1e6, 0.0, 40, 5)]
    plan = {(r["client"]): r["worth"] for r in delay.plan_loads(delay.profiles_of(spark, rows), 100.0, 1000.0, [0.02]).collect()}
    for client, mac, up, down, erase, l, _ in rows:  # noqa: E741
        best = 0.0
        for b in range(1, l + 1):
            k = math.floor((0.02 - b * 100.0 / mac - 1000.0 / down) / (1000.0 / up) + 1e-12)
            best = max(best, b * (1 - (erase**k if erase else 0.0)) if k >= 1 else 0.0)
        assert plan.get(client, 0.0) == pytest.approx(best)


def test_random_numbers_agree(spark):
    k, i = np.arange(30) * 1000003, np.arange(30) * 7919 + 5
    rows = spark.createDataFrame([(int(a), int(b)) for a, b in zip(k, i)], "k long, i long")
    got = [r["z"] for r in with_gauss(rows, "z", "k", "i", 9).orderBy("k").collect()]
    assert np.allclose(got, gauss(9, k, i), atol=1e-9)


def test_coding_is_linear_and_layout_free(spark):
    rng = np.random.default_rng(0)
    rows = [(i, i % 3, rng.normal(size=4).tolist(), rng.normal(size=2).tolist()) for i in range(60)]
    ex = examples(spark, rows)
    whole = coding.collect_composite(coding.compose(coding.encode_clients(ex, 6, 0.2)))
    spread = coding.collect_composite(coding.compose(coding.encode_clients(ex.repartition(7), 6, 0.2)))
    for a, b in zip(whole, spread):
        assert np.allclose(a, b, rtol=1e-9)
    x = np.array([r[2] for r in rows])
    g = gauss(coding.GAUSS_SEED, np.arange(6)[:, None], np.arange(60)[None, :])
    noise = sum(gauss(coding.NOISE_SEED, np.arange(6)[:, None], (c * 4 + np.arange(4))[None, :]) for c in range(3))
    assert np.allclose(whole[0], g @ x + 0.2 * noise)


def test_philox_moments(spark):
    ex = examples(spark, [(i, 0, [1.0 if j == i else 0.0 for j in range(8)], [0.0]) for i in range(8)])
    x, _ = coding.collect_composite(coding.compose(coding.encode_clients(ex, 400, generator="philox")))
    assert ((x.T @ x / 400 - np.eye(8)) ** 2).sum() == pytest.approx(theory.concentration("g", 400, 8), rel=0.6)


def test_gradients_and_optimum(spark):
    rng = np.random.default_rng(1)
    x, y, w = rng.normal(size=(50, 3)), rng.normal(size=(50, 2)), rng.normal(size=(3, 2))
    ex = examples(spark, [(i, i % 4, x[i].tolist(), y[i].tolist()) for i in range(50)])
    assert np.allclose(grad.full_gradient(ex, w), x.T @ (x @ w - y))
    assert grad.loss(ex, w) == pytest.approx(0.5 * ((x @ w - y) ** 2).sum())
    best = grad.exact_solution(ex)
    assert np.allclose(x.T @ (x @ best - y), 0, atol=1e-9)
    total = grad.grams(ex, [])[()]
    assert np.allclose(total.gradient(w), x.T @ (x @ w - y)) and total.loss(w) == pytest.approx(grad.loss(ex, w))
    assert grad.validate_examples(ex) == (3, 2)
    bad = ex.withColumn("x", F.when(F.col("row_id") == 7, F.array(F.lit(float("nan")), F.lit(0.0), F.lit(0.0))).otherwise(F.col("x")))
    with pytest.raises(ValueError):
        grad.validate_examples(bad)


class Fixed:
    """Arrivals by hand."""

    def __init__(self, p, seed):
        self.p = p
        self.draw = np.random.default_rng(seed)

    def arrived(self, epoch):
        return [i for i, p in self.p.items() if self.draw.random() < p]


class Rows:
    """Two clients in memory, whose batch is drawn anew every time."""

    def __init__(self, parts, b, seed):
        self.parts, self.b, self.draw = parts, b, np.random.default_rng(seed)
        self.clients, self.shape = sorted(parts), None

    def combined(self, steps, weights, epoch):
        (step,), (w,) = steps, weights
        out = np.zeros(w.shape)
        for i, c in step.clients.items():
            x, y = self.parts[i]
            own = self.draw.choice(len(x), self.b, replace=False)
            out += c * x[own].T @ (x[own] @ w - y[own]) * len(x) / self.b
        return [out]


def draws(correct=True, reweight=True, sigma=0.4, count=4000):
    rng = np.random.default_rng(5)
    parts = {i: (rng.normal(size=(6, 3)) / 2, rng.normal(size=(6, 1))) for i in range(2)}
    w = rng.normal(size=(3, 1))
    x, y = (np.concatenate([parts[i][j] for i in range(2)]) for j in (0, 1))
    source, epochs = Rows(parts, 3, 6), Fixed({0: 0.6, 1: 0.9}, 7)
    config = training.Config(b_server=5, sigma=sigma, correct=correct, reweight=reweight, deadline=1.0)
    out = []
    for i in range(count):
        noise = sum(rng.normal(size=(12, 3)) for _ in range(2))
        g = rng.normal(size=(12, 12))
        table = training.Composite(g @ x + sigma * noise, g @ y)
        step = training.corrected(source, epochs, table, config, i, w)
        out.append(source.combined([step], [w], i)[0] + step.server)
    return np.array(out), x.T @ (x @ w - y), parts, w


def test_aggregate_is_unbiased():
    found, true, _, _ = draws()
    error = found.std(0) / math.sqrt(len(found))
    assert (np.abs(found.mean(0) - true) < 4.5 * error).all()


@pytest.mark.parametrize("change", [{"correct": False}, {"reweight": False}])
def test_without_either_correction_it_is_biased(change):
    found, true, _, _ = draws(**change)
    error = found.std(0) / math.sqrt(len(found))
    assert (np.abs(found.mean(0) - true) > 4.5 * error).any()


def test_exact_variance(spark):
    found, true, parts, w = draws()
    measured = ((found - true) ** 2).sum((1, 2)).mean()
    rows = [(i * 6 + j, i, x.tolist(), y.tolist()) for i, (xs, ys) in parts.items() for j, (x, y) in enumerate(zip(xs, ys))]
    ex = examples(spark, rows).withColumn("b", F.lit(3))
    arrivals = spark.createDataFrame([(0, 0.6), (1, 0.9)], "client int, p_arrive double")
    setting = theory.Setting(12, 5, 0.4, 3, float((w**2).sum()))
    totals = theory.data_constants(ex, w).agg(F.sum("zeta").alias("zeta"), F.sum("kappa").alias("kappa")).first().asDict()
    exact = theory.exact_gradient_variance(theory.client_variance(ex, w), arrivals, totals, setting, w, true, 2)
    assert measured == pytest.approx(exact, rel=0.12)
    clients = theory.data_constants(ex, w).join(arrivals, "client").withColumn("b", F.lit(3))
    bound = theory.variance_bound(clients, setting, "rederived").first()["rho"]
    assert exact <= bound


def test_bound_falls_with_coded_rows_and_rises_with_noise(spark):
    clients = spark.createDataFrame([(0, 10, 5, 0.9, 3.0, 2.0), (1, 10, 5, 0.8, 2.0, 4.0)], "client int, l long, b int, p_arrive double, zeta double, kappa double")
    rho = lambda c, s: theory.variance_bound(clients, theory.Setting(c, 8, s, 4, 1.0)).first()["rho"]
    assert rho(16, 0.3) > rho(64, 0.3) > rho(64, 0.1)


def test_unreachable_client(spark):
    clients = spark.createDataFrame([(0, 10, 5, 0.0, 3.0, 2.0)], "client int, l long, b int, p_arrive double, zeta double, kappa double")
    assert theory.variance_bound(clients, theory.Setting(16, 8, 0.1, 4, 1.0)).first()["rho"] == math.inf


def test_rates():
    assert theory.learning_rate("constant", 9, 10, base=0.5) == 0.5
    late, early = (theory.learning_rate("theory_epoch", e, 10, zeta=2.0, rho=3.0, phi2=1.0) for e in (9, 0))
    assert late < early < 0.5
    assert theory.learning_rate("theory_horizon", 0, 10, zeta=2.0, rho=3.0, phi2=1.0) == late
