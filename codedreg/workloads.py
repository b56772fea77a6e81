"""The experiments: convergence time, dropped stragglers, privacy against performance, ablations, trade-off grids.

The planner sets every client's load and the deadline; a client's rows are cut into as many subsets as its load asks
for, and its batches are these subsets in turn.  So one pass over the data (or, for wide features, one job an epoch)
serves all runs of an experiment: methods, noise levels, seeds and shares dropped only differ on the driver.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from codedreg.functions.hashrand import philox_gauss
from codedreg.functions.vectors import rounded, sum_vectors
from codedreg.operators import delay, privacy, theory
from codedreg.operators import gradients as grad
from codedreg.operators.coding import dense, lists
from codedreg.operators.features import fourier_features
from codedreg.operators.partition import global_rank, split_subsets
from codedreg.plans import training
from codedreg.sources import tables
from codedreg.storage import cut

PARTS = 5
#: Expected rows an epoch, of the rows that one subset of every client would hold.
TARGET = 0.9
#: Work for a row, in multiples of its multiply-accumulates: links decide the first regime, processors the second.
REGIMES = {"payload_bound": 1.0, "compute_bound": 60.0}


class Regime:
    """Loads and deadline as planned for mini-batches, and the deadline for full batches, with the arrivals of both."""

    def __init__(self, lab: Experiment, factor: float):
        n_mac = factor * delay.macs_per_row(lab.d, lab.o)
        payload = delay.payload_bits(lab.d, lab.o)
        sized = delay.with_loads(lab.devices, lab.ex, share=1.0)
        total = lab.total
        self.n_mac = n_mac
        self.deadline, loads = delay.planned(sized, n_mac, payload, TARGET * total / lab.parts)
        self.whole_deadline, _ = delay.planned(sized, n_mac, payload, TARGET * total)
        sizes = {r["client"]: r["l"] for r in sized.collect()}
        # a client that cannot take part by the deadline still has batches, for the scheme that waits for all
        self.parts = {i: math.ceil(n / loads[i]) if loads[i] else min(n, lab.parts) for i, n in sizes.items()}
        self.batch_rows = sum(math.ceil(n / self.parts[i]) for i, n in sizes.items())
        pairs = [x for i, n in sorted(self.parts.items()) for x in (F.lit(i), F.lit(n))]
        batch = F.ceil(F.col("l") / F.create_map(*pairs)[F.col("client")]).cast("long")
        self.timed = delay.with_times(sized.withColumn("b", batch), n_mac, payload)
        self.whole_timed = delay.with_times(sized, n_mac, payload)


class Experiment:
    """Examples, their optimum and step size, and what is planned for each regime."""

    def __init__(self, spark: SparkSession, sf_dir: str, ex: DataFrame, parts: int = PARTS, clients: int = tables.CLIENTS):
        self.spark, self.parts = spark, parts
        self.ex = cut(ex)
        self.d, self.o = grad.shape_of(self.ex)
        self.total = self.ex.count()
        self.devices = cut(delay.client_profiles(tables.read(spark, sf_dir, "nation"), clients))
        self.regimes: dict[float, Regime] = {}
        self.sources: dict[float, training.GramSource | training.RowSource] = {}
        self._best: tuple[float, float] | None = None

    def regime(self, factor: float) -> Regime:
        if factor not in self.regimes:
            self.regimes[factor] = Regime(self, factor)
        return self.regimes[factor]

    def source(self, factor: float) -> training.GramSource | training.RowSource:
        """The rows in the regime's subsets: as sums of squares while these are small."""
        if factor not in self.sources:
            parts = self.regime(factor).parts
            own = training.Config(sampler="subset", parts=parts)
            self.sources[factor] = training.choose_source(cut(split_subsets(self.ex, parts)), len(parts), own)
            if self._best is None:
                source = self.sources[factor]
                self._best = source.loss(source.optimum()), 1 / source.steepest()
        return self.sources[factor]

    def config(self, factor: float, **more) -> training.Config:
        self.source(factor)
        own = self.regime(factor)
        values = {"epochs": 100, "coded_rows": 500, "b_server": 100, "deadline": own.deadline, "lr": self._best[1], "n_mac": own.n_mac, "sampler": "subset", "parts": own.parts}
        return training.Config(**values | more)

    def arrivals(self, factor: float, config: training.Config) -> training.Epochs:
        return training.Epochs(self.regime(factor).timed, config)

    def gaps(self, factor: float, weights: list[np.ndarray]) -> list[float]:
        return [x - self._best[0] for x in self.source(factor).losses(weights)]

    def gap(self, factor: float, w: np.ndarray) -> float:
        return self.gaps(factor, [w])[0]


def _frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    out = spark.createDataFrame(rows, schema)
    return out.select(*[rounded(f.name).alias(f.name) if f.dataType.simpleString() == "double" else F.col(f.name) for f in out.schema.fields])


def rivals(lab: Experiment, factor: float, seed: int = 0, coded: DataFrame | None = None, **more) -> dict[str, training.Run]:
    """Every scheme of the comparison without noise, on the loads and deadline planned; one coding pass serves all."""
    config = lab.config(factor, seed=seed, **more)
    own = lab.regime(factor)
    arrivals = lab.arrivals(factor, config)
    full_config = training.variant(config, deadline=own.whole_deadline)
    full_arrivals = training.Epochs(own.whole_timed, full_config)
    coded = cut(training.coded_clients(lab.ex, config)) if coded is None else coded
    plain = training.noisy_composite(coded, config)
    weighted = training.noisy_composite(coded, config, training.missing_weights(arrivals))
    full_weighted = training.noisy_composite(coded, config, training.missing_weights(full_arrivals))
    run, change = training.Run, training.variant
    return {
        "corrected": run("corrected", arrivals, plain, config),
        "wait_for_all": run("first_arrivals", arrivals, None, config),
        "drop_0.1": run("first_arrivals", arrivals, None, change(config, drop=0.1)),
        "drop_0.3": run("first_arrivals", arrivals, None, change(config, drop=0.3)),
        "no_compensation": run("first_arrivals", arrivals, None, change(config, drop=0.3, scale="none")),
        "weighted_full": run("weighted_full", full_arrivals, full_weighted, full_config),
        "weighted_mini": run("weighted_mini", arrivals, weighted, config),
        "server_only": run("server_only", arrivals, plain, config),
        "server_only_full": run("server_only", arrivals, plain, change(config, b_server=0)),
        "central": run("central", arrivals, None, config),
    }


def convergence(spark: SparkSession, sf_dir: str, epochs: int = 100, every: int = 10) -> DataFrame:
    """regime, method, epoch, sim_time, gap without noise, and the planned deadline and rows of an epoch: the corrected scheme
    against its rivals."""
    lab = Experiment(spark, sf_dir, tables.teacher_examples(spark, sf_dir))
    rows, coded = [], None
    for regime, factor in REGIMES.items():
        coded = cut(training.coded_clients(lab.ex, lab.config(factor))) if coded is None else coded
        runs = rivals(lab, factor, coded=coded, epochs=epochs)
        source, own = lab.source(factor), lab.regime(factor)
        for (method, run), done in zip(runs.items(), training.run_many(source, list(runs.values()), every)):
            gaps = lab.gaps(factor, [w for _, _, w in done.trace])
            rows += [(regime, method, epoch, time, gap, run.config.deadline, own.batch_rows) for (epoch, time, _), gap in zip(done.trace, gaps)]
    return _frame(spark, rows, "regime string, method string, epoch int, sim_time double, gap double, deadline double, batch_rows int")


def time_to_target(trace: DataFrame, target: float) -> DataFrame:
    """regime, method, the first recorded time at which the gap is down to the target (null: never)."""
    return trace.groupBy("regime", "method").agg(F.min(F.when(F.col("gap") <= target, F.col("sim_time"))).alias("sim_time"))


def drop_sweep(spark: SparkSession, sf_dir: str, shares: tuple[float, ...] = (0.0, 0.1, 0.2, 0.3, 0.5), epochs: int = 100) -> DataFrame:
    """shards, drop_share, sim_time, gap: dropping late clients, under label skew and without."""
    rows, factor = [], REGIMES["compute_bound"]
    for shards in ("skewed", "iid"):
        lab = Experiment(spark, sf_dir, tables.skewed_examples(spark, sf_dir, iid=shards == "iid"))
        config = lab.config(factor, epochs=epochs)
        arrivals = lab.arrivals(factor, config)
        runs = [training.Run("first_arrivals", arrivals, None, training.variant(config, drop=share)) for share in shares]
        done = training.run_many(lab.source(factor), runs, epochs)
        rows += [(shards, share, x.state.time, gap) for share, x, gap in zip(shares, done, lab.gaps(factor, [x.mean for x in done]))]
    return _frame(spark, rows, "shards string, drop_share double, sim_time double, gap double")


def budget(c: int, least: float, sigma: float) -> float:
    """Privacy budget in bits of the client with the least cover."""
    return float(0.5 * np.log2(1 + c / (least + sigma**2))) if least + sigma > 0 else math.inf


def privacy_performance(spark: SparkSession, sf_dir: str, sigmas: tuple[float, ...] = (0.0, 0.1, 0.3, 0.5), seeds: int = 3, epochs: int = 100) -> DataFrame:
    """sigma, eps_bits, method, gap (mean over seeds): the three coded schemes at one privacy budget."""
    lab, factor = Experiment(spark, sf_dir, tables.teacher_examples(spark, sf_dir)), REGIMES["payload_bound"]
    least = privacy.cover_by_client(lab.ex).agg(F.min("h2")).first()[0]
    runs: list[tuple[float, str, training.Run]] = []
    for seed in range(seeds):
        config = lab.config(factor, epochs=epochs, seed=seed)
        arrivals = lab.arrivals(factor, config)
        coded = cut(training.coded_clients(lab.ex, config))
        for sigma in sigmas:
            own = training.variant(config, sigma=sigma)
            plain, weighted = training.noisy_composite(coded, own), training.noisy_composite(coded, own, training.missing_weights(arrivals))
            for method, rule, table, correct in (("corrected", "corrected", plain, True), ("uncorrected", "corrected", plain, False), ("weighted_mini", "weighted_mini", weighted, False), ("server_only", "server_only", plain, False)):
                runs.append((sigma, method, training.Run(rule, arrivals, table, training.variant(own, correct=correct))))
    done = training.run_many(lab.source(factor), [x for _, _, x in runs], epochs)
    gaps: dict[tuple[float, str], list[float]] = {}
    for (sigma, method, _), gap in zip(runs, lab.gaps(factor, [x.mean for x in done])):
        gaps.setdefault((sigma, method), []).append(gap)
    rows = [(sigma, budget(config.coded_rows, least, sigma), method, float(np.mean(x))) for (sigma, method), x in gaps.items()]
    return _frame(spark, rows, "sigma double, eps_bits double, method string, gap double")


ABLATIONS = {"whole": {}, "no_make_up": {"correct": False}, "no_reweighting": {"reweight": False}, "clients_only": {"server_weight": 0.0}, "server_half_only": {"server_weight": 1.0}}


def ablation(spark: SparkSession, sf_dir: str, sigma: float = 0.5, epochs: int = 100) -> DataFrame:
    """variant, gap of mean and of last iterate: without make-up, reweighting, server half or client half."""
    lab, factor = Experiment(spark, sf_dir, tables.teacher_examples(spark, sf_dir)), REGIMES["payload_bound"]
    config = lab.config(factor, epochs=epochs, sigma=sigma)
    arrivals, table = lab.arrivals(factor, config), training.make_composite(lab.ex, config)
    runs = [training.Run("corrected", arrivals, table, training.variant(config, **change)) for change in ABLATIONS.values()]
    done = training.run_many(lab.source(factor), runs, epochs)
    means, lasts = (lab.gaps(factor, w) for w in ([x.mean for x in done], [x.last for x in done]))
    return _frame(spark, list(zip(ABLATIONS, means, lasts)), "variant string, gap_mean double, gap_last double")


def tradeoff_grid(spark: SparkSession, sf_dir: str, coded: tuple[int, ...] = (100, 300, 900), sigmas: tuple[float, ...] = (0.0, 0.3), epochs: int = 60) -> DataFrame:
    """c, sigma, eps_bits, gap: more coded rows or less noise against the privacy they cost."""
    lab, factor = Experiment(spark, sf_dir, tables.teacher_examples(spark, sf_dir, 1)), REGIMES["payload_bound"]
    least = privacy.cover_by_client(lab.ex).agg(F.min("h2")).first()[0]
    runs = []
    for c in coded:
        config = lab.config(factor, epochs=epochs, coded_rows=c, b_server=50)
        arrivals, table = lab.arrivals(factor, config), cut(training.coded_clients(lab.ex, config))
        for sigma in sigmas:
            own = training.variant(config, sigma=sigma)
            runs.append((c, sigma, training.Run("corrected", arrivals, training.noisy_composite(table, own), own)))
    done = training.run_many(lab.source(factor), [x for _, _, x in runs], epochs)
    rows = [(c, sigma, budget(c, least, sigma), gap) for (c, sigma, _), gap in zip(runs, lab.gaps(factor, [x.mean for x in done]))]
    return _frame(spark, rows, "c int, sigma double, eps_bits double, gap double")


#: Width of the Fourier features and subsets of a client in the first image task, subsets in the second.
FOURIER_WIDTH, FOURIER_PARTS, GIVEN_PARTS = 2000, 30, 20
GAMMA = 0.05
#: Of the full gradient's safe step, as batches of a row or two a client are noisy.
IMAGE_STEP = 0.3


def image_task(spark: SparkSession, sf_dir: str, kind: str, epochs: int = 60, every: int = 15, seeds: int = 3, width: int = FOURIER_WIDTH, **more) -> DataFrame:
    """regime, method, epoch, sim_time, loss, accuracy (means over seeds): classification over label shards without noise, over random Fourier
    features (kind fourier) or the features as given (kind given).

    Classes are the largest outputs of a planted teacher, as the given labels cannot be learnt.  A fifth of the rows, by
    hash, is held out for the accuracy.
    """
    ex = tables.skewed_examples(spark, sf_dir)
    if kind == "fourier":
        ex = fourier_features(ex, width, GAMMA)
    held = F.pmod(F.xxhash64("row_id"), F.lit(5)) == 0
    ex = cut(ex)
    lab = Experiment(spark, sf_dir, ex.where(~held), FOURIER_PARTS if kind == "fourier" else GIVEN_PARTS)
    test, rows = cut(ex.where(held)), {}
    for regime, factor in REGIMES.items():
        step = IMAGE_STEP * lab.config(factor).lr
        runs = [(method, run) for seed in range(seeds) for method, run in rivals(lab, factor, seed, epochs=epochs, lr=step, **more).items()]
        for (method, _), done in zip(runs, training.run_many(lab.source(factor), [x for _, x in runs], every)):
            for epoch, time, w in done.trace:
                rows.setdefault((regime, method, epoch), []).append((time, w))
    keys = [k for k, x in rows.items() for _ in x]
    weights = [w for x in rows.values() for _, w in x]
    fit, unseen = ([y for a in range(0, len(weights), WEIGHTS_TOGETHER) for y in grad.losses(table, weights[a : a + WEIGHTS_TOGETHER])] for table in (lab.ex, test))
    out: dict[tuple, list[tuple]] = {}
    for key, time, (loss, _), (_, accuracy) in zip(keys, (t for x in rows.values() for t, _ in x), fit, unseen):
        out.setdefault(key, []).append((time, loss / lab.total, accuracy))
    return _frame(spark, [(*key, *(float(np.mean(c)) for c in zip(*x))) for key, x in out.items()], "regime string, method string, epoch int, sim_time double, loss double, accuracy double")


#: Weight matrices evaluated in one pass.
WEIGHTS_TOGETHER = 64


def document_quality(spark: SparkSession, sf_dir: str, epochs: int = 60) -> DataFrame:
    """method, gap, accuracy of predicted quality on documents held out by hash: a task that can be learnt."""
    ex = cut(tables.document_examples(spark, sf_dir))
    held = F.pmod(F.col("row_id") * 48271, F.lit(5)) == 0
    lab, factor = Experiment(spark, sf_dir, ex.where(~held)), REGIMES["compute_bound"]
    config = lab.config(factor, epochs=epochs)
    arrivals, table = lab.arrivals(factor, config), training.make_composite(lab.ex, config)
    test = ex.where(held)
    rules = {"corrected": table, "first_arrivals": None, "server_only": table, "central": None}
    done = training.run_many(lab.source(factor), [training.Run(rule, arrivals, own, config) for rule, own in rules.items()], epochs)
    rows = []
    for rule, x, gap in zip(rules, done, lab.gaps(factor, [x.mean for x in done])):
        hit = (F.col("yhat")[0] >= 0.5) == (F.col("y")[0] >= 0.5)
        accuracy = grad.predict(test, x.mean).agg(F.avg(hit.cast("double"))).first()[0]
        rows.append((rule, gap, float(accuracy if accuracy is not None else float("nan"))))
    return _frame(spark, rows, "method string, gap double, accuracy double")


LINEITEM_CLIENTS = 25


def lineitem_regression(spark: SparkSession, sf_dir: str, epochs: int = 40) -> DataFrame:
    """client, rows, loss a row of the trained model and of the optimum: corrected training over all natural, unequal clients."""
    lab, factor = Experiment(spark, sf_dir, tables.lineitem_examples(spark, sf_dir), clients=LINEITEM_CLIENTS), REGIMES["payload_bound"]
    config = lab.config(factor, epochs=epochs, coded_rows=64, b_server=32)
    done = training.run("corrected", lab.source(factor), lab.arrivals(factor, config), training.make_composite(lab.ex, config), config, epochs)
    whole = lab.source(factor).whole
    best = lab.source(factor).optimum()
    rows = [(int(i), g.n, g.loss(done.mean) / g.n, g.loss(best) / g.n) for i, g in sorted(whole.items())]
    return _frame(spark, rows, "client int, rows long, loss double, least double")


def gradient_moments(spark: SparkSession, ex: DataFrame, timed: DataFrame, w: np.ndarray, setting: theory.Setting, deadline: float, seeds: int = 400) -> DataFrame:
    """bias2, variance of the aggregated gradient over seeds of coding, noise, batches and arrivals: all seeds in one pass.

    Rows stay where they are: a task draws each row's c coefficients of every seed from a stream of the row's own and passes on
    seeds x c x (d + o) sums.  Batches are drawn as places in a global order of the rows, which then meet their rows.
    """
    d, o = w.shape
    p = {r["client"]: (r["p_arrive"], int(r["b"])) for r in delay.arrival_probability(timed, deadline).select("client", "p_arrive", "b").collect()}
    n, c, wide = len(p), setting.c, d + o
    placed = global_rank(ex.select("row_id", "client", "x", "y"), ["client", "row_id"], "spot")
    spans = {r["client"]: (r["first"], r["l"]) for r in placed.groupBy("client").agg(F.min("spot").alias("first"), F.count("*").alias("l")).collect()}

    def code(batches):
        total = np.zeros((seeds * c, wide))
        for batch in batches:
            place = np.asarray(batch.column("spot"))
            rows = np.hstack([dense(batch.column("x")), dense(batch.column("y"))]) if len(place) else None
            for a in range(0, len(place), MOMENT_BLOCK):
                total += philox_gauss(MOMENT_SEED, place[a : a + MOMENT_BLOCK], seeds * c) @ rows[a : a + MOMENT_BLOCK]
        if total.any():
            yield pa.RecordBatch.from_arrays([pa.array(range(seeds), pa.int64()), lists(total.reshape(seeds, -1))], ["id", "v"])

    def pick(batches):
        for batch in batches:
            ids, places, shares = [], [], []
            for seed in batch.column("id").to_pylist():
                rng = np.random.default_rng([BATCH_STREAM, seed])
                for i, (chance, b) in sorted(p.items()):
                    if chance > 0 and rng.random() < chance:
                        first, l = spans[i]  # noqa: E741
                        places.append(first + rng.choice(l, b, replace=False))
                        ids += [seed] * b
                        shares += [l / b / chance] * b
            if ids:
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(np.concatenate(places), pa.int64()), pa.array(shares)], ["id", "spot", "share"])

    def batch_gradients(batches):
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            if batch.num_rows:
                x, y, ids = dense(batch.column("x")), dense(batch.column("y")), np.asarray(batch.column("id"))
                rest = (x @ w - y) * np.asarray(batch.column("share"))[:, None]
                for seed in np.unique(ids).tolist():
                    own = ids == seed
                    sums[seed] = sums.get(seed, 0) + (x[own].T @ rest[own]).ravel()
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), lists(np.array(list(sums.values())))], ["id", "g"])

    def draw(batches):
        for batch in batches:
            out = []
            for seed, v, met in zip(batch.column("id").to_pylist(), batch.column("v").to_pylist(), batch.column("g").to_pylist()):
                rng = np.random.default_rng([SERVER_STREAM, seed])
                coded = np.array(v).reshape(c, wide)
                coded[:, :d] += setting.sigma * math.sqrt(n) * rng.normal(size=(c, d))
                own = rng.choice(c, setting.b_server, replace=False)
                cx, cy = coded[own, :d], coded[own, d:]
                total = cx.T @ (cx @ w - cy) / setting.b_server - n * setting.sigma**2 * w
                out.append(((total if met is None else total + np.array(met).reshape(w.shape)) / 2).ravel())
            if out:
                yield pa.RecordBatch.from_arrays([lists(np.array(out))], ["g"])

    coded = sum_vectors(placed.select("spot", "x", "y").mapInArrow(code, "id long, v array<double>"), ["id"], ["v"])
    picks = spark.range(0, seeds, 1, 8).mapInArrow(pick, "id long, spot long, share double")
    # the batches are few rows beside the table, unless loads are shares of it
    picks = F.broadcast(picks) if seeds * sum(b for _, b in p.values()) <= MOMENT_PICKS else picks.hint("merge")
    met = placed.select("spot", "x", "y").join(picks, "spot").select("id", "share", "x", "y")
    met = sum_vectors(met.mapInArrow(batch_gradients, "id long, g array<double>"), ["id"], ["g"])
    drawn = coded.join(met, "id", "left").select("id", "v", "g").mapInArrow(draw, "g array<double>")
    base = grad.full_gradient(ex, w)
    unreached = [i for i, (chance, _) in p.items() if chance <= 0]
    if unreached:
        base = base - 0.5 * grad.full_gradient(ex.where(F.col("client").isin(unreached)), w)
    away = F.transform(F.arrays_zip("g", F.array(*[F.lit(float(v)) for v in base.ravel()]).alias("t")), lambda z: z["g"] - z["t"])
    far = drawn.select(F.posexplode(away).alias("j", "e")).groupBy("j").agg(F.avg("e").alias("mean"), F.avg(F.col("e") * F.col("e")).alias("square"))
    return far.agg(F.sum(F.col("mean") * F.col("mean")).alias("bias2"), F.sum("square").alias("variance"))


#: Streams of the moments' draws, the rows whose coefficients a task holds at once, and the most batch rows of all seeds that are broadcast.
MOMENT_SEED, BATCH_STREAM, SERVER_STREAM = 707, 708, 709
MOMENT_BLOCK, MOMENT_PICKS = 256, 1_000_000


def theorem_run(spark: SparkSession, sf_dir: str, epochs: tuple[int, ...] = (10, 50, 200), sigma: float = 0.1) -> DataFrame:
    """epochs, step, gap, bound: the corrected scheme with the theorem's step size against the theorem's bound on the gap.

    The bound uses the proven variance bound and, for the norm of the weights, the largest met on the way.
    """
    lab, factor = Experiment(spark, sf_dir, tables.teacher_examples(spark, sf_dir, 1)), REGIMES["payload_bound"]
    rows = []
    best = lab.source(factor).optimum()
    # the theorem asks for unbiased gradients: a deadline by which every client can arrive
    reach = lab.regime(factor).timed.agg(F.max(F.col("t_c") + F.col("t_d") + 3 * F.col("tau"))).first()[0]
    times = delay.arrival_probability(lab.regime(factor).timed, reach).select("client", "b", "p_arrive")
    for count in epochs:
        phi2 = 4 * float((best**2).sum())
        config = lab.config(factor, epochs=count, sigma=sigma, deadline=reach)
        clients = theory.data_constants(lab.ex, best).join(F.broadcast(times), "client")
        setting = theory.Setting(config.coded_rows, config.b_server, sigma, lab.d, phi2)
        rho = theory.variance_bound(clients, setting, "rederived").first()["rho"]
        zeta = clients.agg(F.sum("zeta")).first()[0]
        own = training.variant(config, lr_kind="theory_horizon", theory={"zeta": zeta, "rho": rho, "phi2": phi2})
        done = training.run("corrected", lab.source(factor), lab.arrivals(factor, own), training.make_composite(lab.ex, own), own, count)
        rows.append((count, theory.learning_rate("theory_horizon", 0, count, zeta=zeta, rho=rho, phi2=phi2), lab.gap(factor, done.mean), theory.gap_bound(rho, zeta, phi2, count)))
    return _frame(spark, rows, "epochs int, step double, gap double, bound double")
