"""Coded data: random Gaussian combinations of each client's rows, and their sum over clients.

Rows never move.  Every task adds up, for each client it meets, its share of the c coded rows; only these partial sums
(c x (d + o) numbers a client and task, whatever the number of rows) are shuffled.  The random matrices are functions
of (seed, coded row, row id) and are made in blocks inside the kernel.  Noise joins once per client, after the sum.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.functions.hashrand import PRIMES, gauss, philox_gauss
from codedreg.functions.vectors import norm2, sum_vectors
from codedreg.storage import cut

GAUSS_SEED, NOISE_SEED, LABEL_NOISE_SEED = 101, 202, 303
BLOCK_ROWS, BLOCK_CODED = 2048, 128
#: Sums of clients up to this size are held in a task before they are passed on.
HELD_BYTES = 128 << 20


def dense(column) -> np.ndarray:
    """An Arrow list column of one size as a matrix."""
    flat = np.asarray(column.flatten())
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def lists(matrix: np.ndarray) -> pa.ListArray:
    matrix = np.ascontiguousarray(matrix, dtype=float)
    return pa.ListArray.from_arrays(np.arange(len(matrix) + 1, dtype=np.int32) * matrix.shape[1], matrix.ravel())


def encode_clients(ex: DataFrame, c: int, sigma: float = 0.0, seed: int = 0, weight: str | None = None, noise_labels: bool = False, generator: str = "portable") -> DataFrame:
    """client, k, x, y: the coded table of every client; with weight, of rows multiplied by that column."""
    if c < 1 or sigma < 0:
        raise ValueError("c must be positive and sigma not negative")
    draw = {"portable": lambda k, ids: gauss(GAUSS_SEED + seed, k[:, None], ids[None, :]), "philox": lambda k, ids: philox_gauss(GAUSS_SEED + seed, ids, c)[k]}[generator]
    columns = ["client", "row_id", "x", "y", *([weight] if weight else [])]

    def run(batches):
        sums: dict[int, np.ndarray] = {}
        width = 0

        def flush():
            client = np.repeat(np.array(list(sums), np.int32), c)
            table = np.concatenate(list(sums.values()))
            k = np.tile(np.arange(c, dtype=np.int32), len(sums))
            return pa.RecordBatch.from_arrays([pa.array(client), pa.array(k), lists(table[:, :width]), lists(table[:, width:])], ["client", "k", "x", "y"])

        for batch in batches:
            if not batch.num_rows:
                continue
            clients = np.asarray(batch.column("client"))
            ids = np.asarray(batch.column("row_id")).astype(np.int64)
            x = dense(batch.column("x"))
            width = x.shape[1]
            rows = np.hstack([x, dense(batch.column("y"))])
            if generator == "portable" and ids.max(initial=0) >= PRIMES[0]:
                raise ValueError("row ids of 2^31 - 1 or more need generator='philox'")
            if weight:
                rows = rows * np.asarray(batch.column(weight)).astype(float)[:, None]
            for client in np.unique(clients).tolist():
                own = np.flatnonzero(clients == client)
                if client not in sums and (len(sums) + 1) * 8 * c * rows.shape[1] > HELD_BYTES and sums:
                    yield flush()
                    sums.clear()
                total = sums.setdefault(client, np.zeros((c, rows.shape[1])))
                for a in range(0, len(own), BLOCK_ROWS):
                    part = own[a : a + BLOCK_ROWS]
                    for k in range(0, c, BLOCK_CODED):
                        coded = np.arange(k, min(k + BLOCK_CODED, c))
                        total[coded] += draw(coded, ids[part]) @ rows[part]
        if sums:
            yield flush()

    partial = ex.select(*columns).mapInArrow(run, "client int, k int, x array<double>, y array<double>")
    coded = sum_vectors(partial, ["client", "k"], ["x", "y"])
    return add_noise(coded, sigma, seed, noise_labels) if sigma else coded


def gauss_squares(rows: DataFrame, c: int, seed: int = 0) -> DataFrame:
    """client, l, squares, trace: of GG', the c x c product of each client's random matrix with itself, the sum of squares and the trace."""

    def run(batches):
        sums: dict[int, np.ndarray] = {}
        counts: dict[int, int] = {}
        for batch in batches:
            clients, ids = np.asarray(batch.column("client")), np.asarray(batch.column("row_id")).astype(np.int64)
            if ids.max(initial=0) >= PRIMES[0]:
                raise ValueError("row ids of 2^31 - 1 or more have no coefficients of their own")
            for client in np.unique(clients).tolist():
                own = ids[clients == client]
                total = sums.setdefault(client, np.zeros((c, c)))
                for a in range(0, len(own), BLOCK_ROWS):
                    g = gauss(GAUSS_SEED + seed, np.arange(c)[:, None], own[None, a : a + BLOCK_ROWS])
                    total += g @ g.T
                counts[client] = counts.get(client, 0) + len(own)
        for client, total in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([client], pa.int32()), lists(np.append(total, counts[client]).reshape(1, -1))], ["client", "v"])

    summed = sum_vectors(rows.select("client", "row_id").mapInArrow(run, "client int, v array<double>"), ["client"], ["v"])
    v = F.slice("v", 1, c * c)
    trace = F.aggregate(F.sequence(F.lit(0), F.lit(c - 1)), F.lit(0.0), lambda acc, i: acc + F.col("v")[i * (c + 1)])
    return summed.select("client", F.col("v")[c * c].cast("long").alias("l"), norm2(v).alias("squares"), trace.alias("trace"))


def add_noise(coded: DataFrame, sigma: float, seed: int = 0, noise_labels: bool = False) -> DataFrame:
    """sigma times a normal of (k, client, column) on the features, and on request on the labels."""

    def noisy(column, k, client, stream):
        table = dense(column)
        d = table.shape[1]
        ident = np.asarray(client).astype(np.int64)[:, None] * d + np.arange(d)[None, :]
        return lists(table + sigma * gauss(stream + seed, np.asarray(k)[:, None], ident))

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                k, client = batch.column("k"), batch.column("client")
                y = noisy(batch.column("y"), k, client, LABEL_NOISE_SEED) if noise_labels else batch.column("y")
                yield pa.RecordBatch.from_arrays([client, k, noisy(batch.column("x"), k, client, NOISE_SEED), y], ["client", "k", "x", "y"])

    return coded.select("client", "k", "x", "y").mapInArrow(run, "client int, k int, x array<double>, y array<double>")


def weight_clients(coded: DataFrame, weights: dict[int, float]) -> DataFrame:
    """The coded tables as if each client's rows had been multiplied by its weight before coding, which is linear."""
    pairs = [x for i, v in sorted(weights.items()) for x in (F.lit(i), F.lit(float(v)))]
    weight = F.coalesce(F.create_map(*pairs)[F.col("client")], F.lit(1.0))
    return coded.withColumn("weight", weight).select("client", "k", *[F.transform(c, lambda v: v * F.col("weight")).alias(c) for c in ("x", "y")])


def compose(coded: DataFrame) -> DataFrame:
    """k, x, y: the clients' tables added element by element."""
    return sum_vectors(coded, ["k"], ["x", "y"])


def update_composite(composite: DataFrame, delta: DataFrame, sign: int = 1) -> DataFrame:
    """Add (or with -1 take away) the coded rows of a change; coding is linear."""
    scaled = delta.select("k", *[F.transform(c, lambda v: v * float(sign)).alias(c) for c in ("x", "y")])
    return sum_vectors(composite.select("k", "x", "y").unionByName(scaled), ["k"], ["x", "y"])


def composite_table(ex: DataFrame, c: int, sigma: float = 0.0, seed: int = 0, **more) -> DataFrame:
    """Encode and compose, materialised once before training."""
    return cut(compose(encode_clients(ex, c, sigma, seed, **more)))


def collect_composite(composite: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """The composite on the driver: c rows, whose number is a parameter and does not follow the data."""
    rows = composite.orderBy("k").collect()
    return np.array([r["x"] for r in rows]), np.array([r["y"] for r in rows])
