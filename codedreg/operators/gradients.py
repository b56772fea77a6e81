"""Least-squares objective, its gradients on clients and server, and their aggregation.

Weights are d x o arrays on the driver; tasks turn Arrow batches into matrices, and what leaves a task is one d x o sum
for each key it met.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.functions.vectors import sum_vectors
from codedreg.operators.coding import dense, lists


def _by_key(ex: DataFrame, keys: list[str], kernel: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> DataFrame:
    """keys, n, v: the kernel's sums over the rows of each key."""
    schema = ", ".join(f"{k} {ex.schema[k].dataType.simpleString()}" for k in keys)
    kinds = [batch_type(ex, k) for k in keys]

    def run(batches):
        sums: dict[tuple, np.ndarray] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            x, y = dense(batch.column("x")), dense(batch.column("y"))
            if keys:
                codes = [np.unique(np.asarray(batch.column(k)), return_inverse=True) for k in keys]
                joint = np.zeros(len(x), np.int64)
                for values, inverse in codes:
                    joint = joint * len(values) + inverse
                order = np.argsort(joint, kind="stable")
                cuts = np.flatnonzero(np.diff(joint[order], prepend=-1))
                groups = [order[a:z] for a, z in zip(cuts, [*cuts[1:], len(order)])]
                names = [tuple(values[inverse[g[0]]].item() for values, inverse in codes) for g in groups]
            else:
                groups, names = [np.arange(len(x))], [()]
            for name, own in zip(names, groups):
                part = np.append(len(own), kernel(x[own], y[own]))
                sums[name] = sums[name] + part if name in sums else part
        if sums:
            table = np.array(list(sums.values()))
            columns = [pa.array([n[i] for n in sums], kind) for i, kind in enumerate(kinds)]
            yield pa.RecordBatch.from_arrays([*columns, lists(table)], [*keys, "v"])

    partial = ex.select(*keys, "x", "y").mapInArrow(run, (schema + ", " if keys else "") + "v array<double>")
    total = sum_vectors(partial, keys, ["v"])
    return total.select(*keys, F.col("v")[0].cast("long").alias("n"), F.expr("slice(v, 2, size(v) - 1)").alias("v"))


def batch_type(df: DataFrame, column: str) -> pa.DataType:
    return {"int": pa.int32(), "bigint": pa.int64(), "string": pa.string(), "double": pa.float64()}[df.schema[column].dataType.simpleString()]


def gradient_sums(ex: DataFrame, w: np.ndarray, keys: list[str]) -> DataFrame:
    """keys, n, v: X'(XW - Y) of each key's rows, row-major, unscaled."""
    return _by_key(ex, keys, lambda x, y: (x.T @ (x @ w - y)).ravel())


def weighted_gradients(ex: DataFrame, weights: list[np.ndarray], coefficients: list[dict[int, float]]) -> list[np.ndarray]:
    """For each of several weight matrices the sum over rows of the coefficient of the row's client times the row's gradient.

    One pass serves them all; what leaves a task is one d x o sum for each of them, whatever the number of clients.
    """
    d, o = weights[0].shape
    wide, many = np.hstack(weights), len(weights)

    def run(batches):
        total = None
        for batch in batches:
            if not batch.num_rows:
                continue
            x, y = dense(batch.column("x")), dense(batch.column("y"))
            names, inverse = np.unique(np.asarray(batch.column("client")), return_inverse=True)
            share = np.array([[c.get(i, 0.0) for c in coefficients] for i in names.tolist()])[inverse]
            rest = (x @ wide - np.tile(y, many)) * np.repeat(share, o, axis=1)
            part = x.T @ rest
            total = part if total is None else total + part
        if total is not None:
            yield pa.RecordBatch.from_arrays([lists(total.reshape(1, -1))], ["v"])

    clients = sorted({i for c in coefficients for i, v in c.items() if v})
    if not clients:
        return [np.zeros((d, o)) for _ in weights]
    rows = ex.where(F.col("client").isin(clients)).select("client", "x", "y").mapInArrow(run, "v array<double>")
    found = dense(sum_vectors(rows, [], ["v"]).toArrow().column("v").combine_chunks())
    table = found.reshape(d, many * o) if found.size else np.zeros((d, many * o))
    return [table[:, i * o : (i + 1) * o] for i in range(many)]


def losses(ex: DataFrame, weights: list[np.ndarray]) -> list[tuple[float, float]]:
    """(half the squared residuals, share of rows whose largest output is the target's) of several weight matrices, in one pass."""
    o, wide = weights[0].shape[1], np.hstack(weights)

    def run(batches):
        total = np.zeros((2, len(weights)))
        n = 0
        for batch in batches:
            if batch.num_rows:
                x, y = dense(batch.column("x")), dense(batch.column("y"))
                out = (x @ wide).reshape(len(x), -1, o)
                total[0] += 0.5 * ((out - y[:, None, :]) ** 2).sum((0, 2))
                total[1] += (out.argmax(2) == y.argmax(1)[:, None]).sum(0)
                n += len(x)
        yield pa.RecordBatch.from_arrays([lists(np.append(total.ravel(), n).reshape(1, -1))], ["v"])

    found = np.array(sum_vectors(ex.select("x", "y").mapInArrow(run, "v array<double>"), [], ["v"]).first()["v"])
    loss, hits = found[:-1].reshape(2, -1)
    return [(float(a), float(b / max(1.0, found[-1]))) for a, b in zip(loss, hits)]


def client_gradients(batch: DataFrame, w: np.ndarray, sizes: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """client, n, v: each client's gradient on its batch, times l / rows drawn; sizes has client and l."""
    keys = keys or ["client"]
    sums = gradient_sums(batch, w, keys)
    return sums.join(F.broadcast(sizes.select("client", "l")), "client").select(*keys, "n", F.transform("v", lambda g: g * F.col("l") / F.col("n")).alias("v"))


def server_gradient(x: np.ndarray, y: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Gradient on the drawn coded rows, over their number."""
    return x.T @ (x @ w - y) / len(x)


def bias_correction(w: np.ndarray, n_clients: int, sigma: float) -> np.ndarray:
    """What cancels, in expectation, the part of the server's gradient that comes from the noise."""
    return -n_clients * sigma**2 * w


def reweight_arrivals(gradients: DataFrame, arrivals: DataFrame) -> DataFrame:
    """client, v: gradients that arrived, over their probability to; a client that never can arrive gives nothing."""
    met = gradients.join(F.broadcast(arrivals.where("arrived and p_arrive > 0").select("client", "p_arrive")), "client")
    return met.select("client", F.transform("v", lambda g: g / F.col("p_arrive")).alias("v"))


def loss(ex: DataFrame, w: np.ndarray) -> float:
    """Half the squared residuals."""
    return 0.5 * float(_by_key(ex, [], lambda x, y: np.array([((x @ w - y) ** 2).sum()])).first()["v"][0])


def full_gradient(ex: DataFrame, w: np.ndarray) -> np.ndarray:
    return np.array(gradient_sums(ex, w, []).first()["v"]).reshape(w.shape)


def gram_sums(ex: DataFrame, keys: list[str]) -> DataFrame:
    """keys, n, v: X'X, X'Y and Y'Y of each key's rows, after which no epoch needs the data."""
    return _by_key(ex, keys, lambda x, y: np.concatenate([(x.T @ x).ravel(), (x.T @ y).ravel(), (y.T @ y).ravel()]))


class Gram:
    """Sufficient statistics of some rows."""

    def __init__(self, n: int, v, d: int, o: int):
        v = np.asarray(v)
        self.n, self.xx, self.xy, self.yy = n, v[: d * d].reshape(d, d), v[d * d : d * d + d * o].reshape(d, o), v[d * d + d * o :].reshape(o, o)

    def gradient(self, w: np.ndarray) -> np.ndarray:
        return self.xx @ w - self.xy

    def loss(self, w: np.ndarray) -> float:
        return 0.5 * float(np.einsum("ij,ik,kj->", w, self.xx, w) - 2 * (w * self.xy).sum() + np.trace(self.yy))

    def __add__(self, other: Gram) -> Gram:
        out = object.__new__(Gram)
        out.n, out.xx, out.xy, out.yy = self.n + other.n, self.xx + other.xx, self.xy + other.xy, self.yy + other.yy
        return out


def shape_of(ex: DataFrame) -> tuple[int, int]:
    row = ex.select(F.size("x").alias("d"), F.size("y").alias("o")).first()
    if row is None:
        raise ValueError("no examples")
    return row["d"], row["o"]


def grams(ex: DataFrame, keys: list[str]) -> dict[tuple, Gram]:
    d, o = shape_of(ex)
    found = gram_sums(ex, keys).toArrow().combine_chunks()
    names = zip(*(found.column(k).to_pylist() for k in keys)) if keys else [()] * found.num_rows
    return {name: Gram(n, v.values.to_numpy(), d, o) for name, n, v in zip(names, found.column("n").to_pylist(), found.column("v"))}


#: Up to this size X'X may be held on the driver.
GRAM_BYTES_MAX = 256 << 20


def exact_solution(ex: DataFrame) -> np.ndarray:
    """Least-squares optimum (of least norm): from one pass while X'X fits, else by conjugate gradients."""
    d, o = shape_of(ex)
    if 8 * d * d > GRAM_BYTES_MAX:
        return conjugate_gradients(ex, d, o)
    g = grams(ex, [])[()]
    return np.linalg.lstsq(g.xx, g.xy, rcond=None)[0]


def conjugate_gradients(ex: DataFrame, d: int, o: int, rounds: int = 200, tolerance: float = 1e-10) -> np.ndarray:
    """Solves X'XW = X'Y, all outputs at once, with one pass a round and d x o numbers on the driver."""
    w = np.zeros((d, o))
    rest = -full_gradient(ex, w)
    way, size = rest.copy(), (rest**2).sum(0)
    first = size.copy()
    for _ in range(rounds):
        if (size <= tolerance**2 * first).all():
            break
        # the gradient is affine: its change along the way is X'X times it
        along = full_gradient(ex, w + way) + rest
        step = np.divide(size, (way * along).sum(0), out=np.zeros(o), where=size > 0)
        w = w + way * step
        rest = rest - along * step
        new = (rest**2).sum(0)
        way = rest + way * np.divide(new, size, out=np.zeros(o), where=size > 0)
        size = new
    return w


def largest_eigenvalue(ex: DataFrame, d: int, o: int, rounds: int = 30) -> float:
    """Of X'X, by power iteration, one pass a round."""
    start = np.random.default_rng(0).normal(size=(d, 1)) @ np.ones((1, o))
    zero = full_gradient(ex, np.zeros((d, o)))
    value = 0.0
    for _ in range(rounds):
        start = start / np.linalg.norm(start[:, 0])
        new = full_gradient(ex, start) - zero
        value, start = float(start[:, 0] @ new[:, 0]), new
    return value


def predict(ex: DataFrame, w: np.ndarray) -> DataFrame:
    """Add yhat and predicted (the place of its largest entry)."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                out = dense(batch.column("x")) @ w
                yield batch.append_column("yhat", lists(out)).append_column("predicted", pa.array(out.argmax(1).astype(np.int32)))

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in ex.schema.fields)
    return ex.mapInArrow(run, f"{fields}, yhat array<double>, predicted int")


def validate_examples(ex: DataFrame) -> tuple[int, int]:
    """d and o, after checking every row: sizes alike, nothing null, not a number or infinite."""
    d, o = shape_of(ex)
    good = lambda c, n: (F.size(c) == n) & F.forall(c, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    bad = ex.where(~F.coalesce(good("x", d) & good("y", o), F.lit(False))).limit(1).count()
    if bad:
        raise ValueError("examples must be finite and of one size")
    return d, o
