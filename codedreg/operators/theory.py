"""Variance of the aggregated gradient, exact and bounded, and what it means for convergence.

`mode` of the bound: "printed" keeps the six terms as the reference states them; "printed_fixed" corrects two of their
constants (a sum of n normals has a variance that enters squared; the mixed term lacks a factor c); "rederived" is a
proven bound, from the exact variance.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.functions.vectors import dot, literal, norm2
from codedreg.operators.gradients import client_gradients, gradient_sums  # noqa: F401  (re-exported for measures)


def residuals(ex: DataFrame, w: np.ndarray) -> DataFrame:
    """Add r = xW - y, in built-in expressions; for a small number of outputs."""
    parts = [dot("x", literal(w[:, q])) - F.col("y")[q] for q in range(w.shape[1])]
    return ex.withColumn("r", F.array(*parts))


def data_constants(ex: DataFrame, w: np.ndarray) -> DataFrame:
    """client, l, alpha (= zeta: squared feature norm) and kappa (squared residual norm at w)."""
    rows = residuals(ex, w)
    return rows.groupBy("client").agg(F.count("*").alias("l"), F.sum(norm2("x")).alias("zeta"), F.sum(norm2("r")).alias("kappa"))


@dataclass(frozen=True)
class Setting:
    """What the formulas need beside the clients' constants."""

    c: int
    b_server: int
    sigma: float
    d: int
    phi2: float


def variance_bound(clients: DataFrame, s: Setting, mode: str = "printed") -> DataFrame:
    """One row: the bound, from clients(l, b, p_arrive, zeta, kappa); infinite if a client cannot arrive.

    zeta and kappa are squared quantities, summed over clients where the formula wants totals.
    """
    zk = F.col("zeta") * F.col("kappa")
    p = F.when(F.col("p_arrive") > 0, F.col("p_arrive"))
    late = (1 - p) / p
    spread = F.col("l") * (F.col("l") - F.col("b")) / F.col("b")
    sums = clients.agg(F.count("*").cast("double").alias("n"), F.sum("l").cast("double").alias("m"), F.sum("zeta").alias("z"), F.sum("kappa").alias("k"), F.sum(late * zk).alias("late"), F.sum(spread * zk).alias("batch"), F.min("p_arrive").alias("least"),
        F.sum(zk * (late + (F.col("l") - F.col("b")) / (F.col("b") * p) * F.when(F.col("l") > 1, F.col("l") / (F.col("l") - 1)).otherwise(0))).alias("client_part"))
    n, m, z, k = (F.col(x) for x in "nmzk")
    c, b, s2, d, phi2 = float(s.c), float(s.b_server), s.sigma**2, float(s.d), s.phi2
    if mode == "rederived":
        server = 2 * (z + n * (d * s2)) * (k + n * (s2 * phi2)) / b
        rho = 0.25 * (F.col("client_part") + server)
    else:
        fixed = mode == "printed_fixed"
        noise = (n * n if fixed else n) * ((d + d * d) * s2 * s2 * phi2 / c)
        mixed = m * n * (d * s2 / (c if fixed else c * c)) * (z * phi2 + k)
        rho = z * k * ((c - b) / (4 * c * b)) + (m + m * m) / c * z * k + noise + mixed + 0.5 * F.col("late") + 0.5 * F.col("batch")
    return sums.select(F.when(F.col("least") > 0, rho).otherwise(float("inf")).alias("rho"))


def client_variance(ex: DataFrame, w: np.ndarray, sampler: str = "fixed") -> DataFrame:
    """client, l, b, grad2 (squared norm of the full gradient), s (variance of the batch gradient); ex has b.

    One pass: per-row products and the gradient's components are summed together.
    """
    rows = residuals(ex, w)
    o, d = w.shape[1], w.shape[0]
    parts = [F.sum(F.col("x")[j] * F.col("r")[q]).alias(f"g_{j}_{q}") for j in range(d) for q in range(o)]
    sums = rows.groupBy("client").agg(F.count("*").alias("l"), F.max("b").alias("b"), F.sum(norm2("x") * norm2("r")).alias("q"), *parts)
    grad2 = sum((F.pow(f"g_{j}_{q}", 2) for j in range(d) for q in range(o)), F.lit(0.0))
    l, b = F.col("l"), F.col("b")
    if sampler == "bernoulli":
        s = (l / b - 1) * F.col("q")
    else:
        s = F.when(l > 1, (l - b) / b * l / F.when(l > 1, l - 1) * (F.col("q") - F.col("grad2") / l)).otherwise(0.0)
    return sums.withColumn("grad2", grad2).select("client", "l", "b", "grad2", s.alias("s"))


def exact_client_variance(variances: DataFrame, arrivals: DataFrame) -> DataFrame:
    """client, s, with_arrivals: the variance once a late result counts nothing and an early one 1/p (null if p = 0)."""
    met = variances.join(F.broadcast(arrivals.select("client", "p_arrive")), "client")
    return met.select("client", "s", ((F.col("grad2") + F.col("s")) / F.when(F.col("p_arrive") > 0, F.col("p_arrive")) - F.col("grad2")).alias("with_arrivals"))


def exact_server_variance(composite: DataFrame, w: np.ndarray, b: int, sampler: str = "fixed") -> DataFrame:
    """One row: sampling variance of the server's gradient, its composite given."""
    rows = residuals(composite, w)
    d, o = w.shape
    parts = [F.sum(F.col("x")[j] * F.col("r")[q]).alias(f"g_{j}_{q}") for j in range(d) for q in range(o)]
    sums = rows.agg(F.count("*").alias("c"), F.sum(norm2("x") * norm2("r")).alias("q"), *parts)
    grad2 = sum((F.pow(f"g_{j}_{q}", 2) for j in range(d) for q in range(o)), F.lit(0.0))
    c = F.col("c")
    if sampler == "bernoulli":
        value = (c - b) / (F.lit(float(b)) * c * c) * F.col("q")
    else:
        value = (c - b) / (F.lit(float(b)) * (c - 1)) * (F.col("q") / c - grad2 / (c * c))
    return sums.select(value.alias("server_variance"))


def exact_gradient_variance(variances: DataFrame, arrivals: DataFrame, totals: dict[str, float], s: Setting, w: np.ndarray, gradient: np.ndarray, n: int, sampler: str = "fixed") -> float:
    """Variance of the aggregated gradient over fresh composites, batches and arrivals; totals has zeta and kappa."""
    v_client = exact_client_variance(variances, arrivals).agg(F.sum("with_arrivals")).first()[0]
    s2 = s.sigma**2
    a, b = totals["zeta"] + n * s.d * s2, totals["kappa"] + n * s2 * float((w**2).sum())
    u = float(((gradient + n * s2 * w) ** 2).sum())
    if sampler == "bernoulli":
        v_server = (1 / s.b_server - 1 / s.c) * (a * b + 2 * u) + (a * b + u) / s.c
    else:
        v_server = (a * b + u) / s.b_server
    return 0.25 * (v_client + v_server)


def gap_bound(rho: float, zeta: float, phi2: float, epochs: int) -> float:
    """Upper bound of the optimality gap of the mean iterate."""
    return math.sqrt(4 * phi2 * rho / epochs) + 2 * phi2 * zeta / epochs


def time_to_gap(rho: float, zeta: float, phi2: float, deadline: float, gap: float) -> float:
    """Order of the time until the gap: one epoch's duration by the number of epochs either term asks for."""
    return deadline * max(4 * phi2 * rho / gap**2, 2 * phi2 * zeta / gap)


def learning_rate(kind: str, epoch: int, horizon: int, *, base: float = 0.0, zeta: float = 1.0, rho: float = 1.0, phi2: float = 1.0) -> float:
    """Step size of an epoch (from 0): constant, decaying with its root, or as the theorem sets it."""
    if kind == "constant":
        return base
    if kind == "sqrt":
        return base / math.sqrt(epoch + 1)
    count = epoch + 1 if kind == "theory_epoch" else horizon
    gamma = math.sqrt(4 * phi2 / (rho * count))
    return 1 / (zeta + 1 / gamma)


def concentration(kind: str, count: int, size: int, keep: int = 0, clients: int = 1) -> float:
    """Closed form of the expected squared deviation from the identity: count coded rows, matrices of this size.

    g: of G'G / c; n: of N'N / c from n times the identity; s: of the scaled sampling matrix keeping `keep` of size.
    """
    if kind == "g":
        return (size + size**2) / count
    if kind == "n":
        return clients**2 * (size + size**2) / count
    return size * (size - keep) / keep
