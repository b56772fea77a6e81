"""Registered queries of the reference methods: each ends in a small, rounded table."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from codedreg import workloads
from codedreg.functions.hashrand import with_gauss
from codedreg.functions.vectors import long_form, rounded
from codedreg.operators import coding, delay, features, partition, privacy, sampling, theory
from codedreg.operators import gradients as grad
from codedreg.oracles import B, B_SERVER, C, D, DEADLINE, DROP, EPOCHS, LR, N_MAC, PAYLOAD, SIGMA
from codedreg.plans import training
from codedreg.sources import tables
from codedreg.storage import cut, ensure_checkpoint_dir
from codedreg.streaming import arrivals as stream

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}


def query(f: Query) -> Query:
    QUERIES[f.__name__] = f
    return f


def r(*names: str, digits: int = 6):
    return [rounded(n, digits).alias(n) for n in names]


def matrix_rows(spark: SparkSession, values: np.ndarray, name: str = "g") -> DataFrame:
    return spark.createDataFrame([(j, float(v)) for j, v in enumerate(np.ravel(values))], f"j int, {name} double").select("j", *r(name))


#: Components of a whole embedding, and the width of its Fourier features.
WHOLE, FOURIER = 64, 2000
_WIDTH = [D]


def width() -> int:
    """Components that queries see: D beside their SQL, all of them in the _whole queries."""
    return _WIDTH[0]


def scale() -> int:
    """Work, payload and deadline grow with the width, so that as many clients arrive."""
    return width() // D


def examples(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.small_examples(spark, sf_dir, width())


def whole(f: Query) -> Query:
    """The query over whole embeddings, without SQL."""

    def run(spark, sf_dir):
        _WIDTH[0] = WHOLE
        try:
            return f(spark, sf_dir)
        finally:
            _WIDTH[0] = D

    run.__name__ = f"{f.__name__}_whole"
    return query(run)


def shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition.partition_clients(tables.embedding_rows(spark, sf_dir, width()), tables.CLIENTS)


def half_teacher() -> np.ndarray:
    return tables.teacher(width(), 1) / 2


def loaded(spark: SparkSession, sf_dir: str, ex: DataFrame | None = None) -> DataFrame:
    """Profiles with loads and times; without examples, of 25 rows a client."""
    rows = delay.client_profiles(tables.read(spark, sf_dir, "nation"))
    rows = delay.with_loads(rows, ex, b=B) if ex is not None else rows.withColumns({"b": F.lit(B).cast("long"), "l": F.lit(25).cast("long")})
    return delay.with_times(rows, N_MAC * scale(), PAYLOAD * scale())


def arrived(spark: SparkSession, sf_dir: str, epochs: int = 50) -> DataFrame:
    return delay.simulate_arrivals(loaded(spark, sf_dir), DEADLINE, epochs)


@query
def shard_by_label(spark, sf_dir):
    return shards(spark, sf_dir).groupBy("client").agg(F.count("*").alias("n"), F.min("row_id").alias("low"), F.max("row_id").alias("high"))


@query
def shard_iid(spark, sf_dir):
    rows = partition.partition_clients(tables.embedding_rows(spark, sf_dir, 1), tables.CLIENTS, "iid")
    return rows.groupBy("client").agg(F.count("*").alias("n"), F.sum("row_id").alias("ids"))


@query
def shard_by_source(spark, sf_dir):
    docs = tables.read(spark, sf_dir, "documents").select("doc_id", F.regexp_extract("source", "([0-9]+)", 1).alias("number"))
    return partition.partition_clients(docs, 20, "key", key="number").groupBy("client").agg(F.count("*").alias("n"), F.min("doc_id").alias("low"))


@query
def shard_disjoint_check(spark, sf_dir):
    return partition.disjoint_check(shards(spark, sf_dir))


@query
def subset_sizes(spark, sf_dir):
    rows = partition.split_subsets(shards(spark, sf_dir).select("row_id", "client"), 5)
    return rows.groupBy("client", "subset").agg(F.count("*").alias("n"), F.sum("row_id").alias("ids"))


@query
def max_abs_scale(spark, sf_dir):
    x = F.array(F.lit(1.0), F.col("l_quantity") / 50.0, F.col("l_discount") / 0.1, F.col("l_tax") / 0.08)
    scaled = features.scale_columns(tables.read(spark, sf_dir, "lineitem").select(x.alias("x")))
    return scaled.select(F.posexplode("x").alias("j", "v")).groupBy("j").agg(rounded(F.max("v")).alias("high"), rounded(F.avg("v")).alias("mean"))


@query
def one_hot_labels(spark, sf_dir):
    hot = tables.read(spark, sf_dir, "embeddings").select(features.one_hot("label", 10).alias("x"))
    return hot.select(F.posexplode("x").alias("j", "v")).groupBy("j").agg(F.sum("v").alias("total")).where("total > 0")


@query
def text_features(spark, sf_dir):
    rows = features.text_statistics(tables.read(spark, sf_dir, "documents"), [])
    names = {"letters": 1, "digits": 2, "upper": 3, "length": 4, "repeated": 6}
    return rows.select("doc_id", *[rounded(F.col("x")[i]).alias(n) for n, i in names.items()])


@query
def fourier_features(spark, sf_dir):
    rows = features.scale_unit(tables.embedding_rows(spark, sf_dir, width())).select("row_id", "x")
    return long_form(features.fourier_features(rows, 4 if width() == D else FOURIER), ["row_id"]).select("row_id", "j", *r("v"))


@query
def hash_gauss_moments(spark, sf_dir):
    z = with_gauss(spark.range(20000).toDF("i"), "z", "i % 40", "i div 40", 7)
    return z.agg(F.count("*").alias("n"), rounded(F.avg("z")).alias("mean"), rounded(F.avg(F.pow("z", 2))).alias("second"), rounded(F.avg(F.pow("z", 4))).alias("fourth"))


#: Coded rows of the measured concentrations.
MANY = 200


@query
def concentration_g(spark, sf_dir):
    """client, l, measured, expected: squared distance of G'G / c from the identity over the client's rows of the table.

    It is taken from GG', of fixed size whatever the number of rows: the squares of both products have one sum.
    """
    rows = shards(spark, sf_dir).select("client", "row_id")
    found = coding.gauss_squares(rows, MANY)
    n, c = F.col("l"), float(MANY)
    measured = F.col("squares") / (c * c) - 2 * F.col("trace") / c + n
    return found.select("client", "l", rounded(measured).alias("measured"), rounded((n + n * n) / c).alias("expected"))


@query
def concentration_n(spark, sf_dir):
    """One row: squared distance of N'N / c from n times the identity, N the sum of the noise of the n clients that hold rows."""
    clients = shards(spark, sf_dir).select("client").distinct()
    cells = clients.crossJoin(F.broadcast(spark.range(MANY * D).selectExpr(f"id div {D} as k", f"id % {D} as i")))
    z = with_gauss(cells, "z", "k", f"client * {D} + i", coding.NOISE_SEED)
    z = cut(z.groupBy("k", "i").agg(F.sum("z").alias("z"), F.count("*").alias("n")))
    a, b = z.withColumnRenamed("z", "za"), z.select("k", F.col("i").alias("j"), F.col("z").alias("zb"))
    products = a.join(b, "k").groupBy("i", "j").agg((F.sum(F.col("za") * F.col("zb")) / MANY).alias("v"), F.max("n").alias("n"))
    d = F.col("v") - F.when(F.col("i") == F.col("j"), F.col("n")).otherwise(0)
    n = F.max("n")
    return products.agg(rounded(F.sum(d * d)).alias("measured"), rounded(n * n * theory.concentration("n", MANY, D)).alias("expected"))


@query
def concentration_s(spark, sf_dir):
    """epoch, measured, expected: squared distance of the scaled sampling matrix from the identity, over the composite of the table."""
    table = coding.composite_table(examples(spark, sf_dir), C)
    drawn = sampling.sample_composite(table.select("k"), EPOCHS, B_SERVER)
    n = F.count("*")
    return drawn.groupBy("epoch").agg(F.round(n * (C / B_SERVER - 1) ** 2 + (C - n), 6).alias("measured")).withColumn("expected", F.lit(theory.concentration("s", C, C, B_SERVER)))


@query
def client_profiles(spark, sf_dir):
    return delay.client_profiles(tables.read(spark, sf_dir, "nation")).select("client", *r("mac_rate", "up_bps", "down_bps", "p_erase"))


@query
def delay_model(spark, sf_dir):
    return loaded(spark, sf_dir).select("client", *r("t_c", "tau", "t_d", digits=9))


@query
def arrival_probability(spark, sf_dir):
    return delay.arrival_probability(loaded(spark, sf_dir), DEADLINE).select("client", "k_max", *r("p_arrive", digits=9))


@query
def arrival_trace(spark, sf_dir):
    return arrived(spark, sf_dir).select("epoch", "client", "attempts", *r("t", digits=9), "arrived")


@query
def arrival_stats(spark, sf_dir):
    return delay.arrival_stats(arrived(spark, sf_dir)).select("client", *r("realised", "expected", "attempts"), *r("slowest", digits=9))


def _plan(spark, sf_dir):
    return delay.plan_loads(loaded(spark, sf_dir).drop("t_c", "tau", "t_d"), N_MAC, PAYLOAD, [0.001, 0.0015, 0.002, 0.003])


@query
def load_plan(spark, sf_dir):
    return _plan(spark, sf_dir).select("deadline", "client", "load", "k", *r("worth"))


@query
def deadline_sweep(spark, sf_dir):
    return _plan(spark, sf_dir).groupBy("deadline").agg(rounded(F.sum("worth")).alias("expected"), F.count("*").alias("clients"))


@query
def smallest_deadline(spark, sf_dir):
    return delay.smallest_deadline(_plan(spark, sf_dir), 100.0).select("deadline", *r("expected"))


def _coded(df: DataFrame, keys: list[str]) -> DataFrame:
    return long_form(df, keys).select(*keys, "j", *r("v"))


@query
def encode_clients(spark, sf_dir):
    return _coded(coding.encode_clients(examples(spark, sf_dir), C), ["client", "k"])


@query
def encode_clients_noisy(spark, sf_dir):
    return _coded(coding.encode_clients(examples(spark, sf_dir), C, SIGMA), ["client", "k"])


@query
def encode_labels(spark, sf_dir):
    coded = coding.encode_clients(examples(spark, sf_dir), C)
    return coded.select("client", "k", rounded(F.col("y")[0]).alias("v"))


@query
def encode_weighted(spark, sf_dir):
    ex = examples(spark, sf_dir).withColumn("weight", F.sqrt((F.col("row_id") % 5) / 5.0))
    return _coded(coding.encode_clients(ex, C, weight="weight"), ["client", "k"])


@query
def composite(spark, sf_dir):
    return _coded(coding.compose(coding.encode_clients(examples(spark, sf_dir), C, SIGMA)), ["k"])


@query
def composite_incremental(spark, sf_dir):
    """All rows but a third, then that third added, a tenth added twice and taken away once."""
    ex = examples(spark, sf_dir)
    coded = lambda where: coding.compose(coding.encode_clients(ex.where(where), C))
    table = coding.update_composite(coded("row_id % 3 > 0"), coded("row_id % 3 = 0"))
    table = coding.update_composite(coding.update_composite(table, coded("row_id % 10 = 0")), coded("row_id % 10 = 0"), -1)
    return _coded(table, ["k"])


def _sized(spark, sf_dir):
    ex = examples(spark, sf_dir)
    return ex.join(F.broadcast(ex.groupBy("client").agg(F.count("*").alias("l"))), "client").withColumn("b", F.least(F.lit(B), F.col("l")))


@query
def batch_fixed(spark, sf_dir):
    return sampling.sample_batch(_sized(spark, sf_dir), EPOCHS).select("epoch", "client", "row_id")


@query
def batch_bernoulli(spark, sf_dir):
    return sampling.sample_batch(_sized(spark, sf_dir), EPOCHS, "bernoulli").select("epoch", "client", "row_id")


@query
def batch_subset(spark, sf_dir):
    rows = partition.split_subsets(examples(spark, sf_dir).select("row_id", "client"), 5)
    return sampling.sample_batch(rows, 7, "subset", parts=5).select("epoch", "client", "row_id")


@query
def loss(spark, sf_dir):
    ex = examples(spark, sf_dir)
    return spark.createDataFrame([(ex.count(), grad.loss(ex, half_teacher()))], "n long, loss double").select("n", *r("loss"))


@query
def full_gradient(spark, sf_dir):
    return matrix_rows(spark, grad.full_gradient(examples(spark, sf_dir), half_teacher()))


def _server_batch(spark, sf_dir, ex):
    table = training.Composite(*coding.collect_composite(coding.composite_table(ex, C, SIGMA)))
    return grad.server_gradient(*table.batch(0, B_SERVER, 0), half_teacher())


@query
def server_gradient(spark, sf_dir):
    return matrix_rows(spark, _server_batch(spark, sf_dir, examples(spark, sf_dir)))


def _client_gradients(ex):
    batch = sampling.sample_batch(ex, 1)
    return grad.client_gradients(batch, half_teacher(), ex.select("client", "l").distinct())


@query
def client_gradients(spark, sf_dir):
    return long_form(_client_gradients(_sized(spark, sf_dir)), ["client"], "v").select("client", "j", rounded("v").alias("g"))


@query
def aggregated_gradient(spark, sf_dir):
    ex, w = _sized(spark, sf_dir), half_teacher()
    times = delay.simulate_arrivals(loaded(spark, sf_dir, ex), DEADLINE * scale(), EPOCHS).where("epoch = 0")
    met = grad.reweight_arrivals(_client_gradients(ex), times)
    clients = np.sum([row["v"] for row in met.collect()] or [np.zeros(width())], axis=0).reshape(w.shape)
    server = _server_batch(spark, sf_dir, ex) + grad.bias_correction(w, tables.CLIENTS, SIGMA)
    return matrix_rows(spark, 0.5 * (clients + server))


@query
def privacy_budget(spark, sf_dir):
    return privacy.privacy_budget(examples(spark, sf_dir), C, SIGMA).select("client", *r("h2", "eps_bits"))


@query
def sigma_for_budget(spark, sf_dir):
    return privacy.sigma_for_budget(privacy.cover_by_client(examples(spark, sf_dir)), C, 0.9).select("client", *r("sigma"))


@query
def coded_rows_for_budget(spark, sf_dir):
    return privacy.coded_rows_for_budget(privacy.cover_by_client(examples(spark, sf_dir)), 2.0, SIGMA)


@query
def privacy_grid(spark, sf_dir):
    return privacy.privacy_grid(privacy.cover_by_client(examples(spark, sf_dir)), [16, 64, 256], [0, 0.3, 1]).select("c", "sigma", *r("eps_bits"))


@query
def privacy_overall(spark, sf_dir):
    return privacy.overall(privacy.privacy_budget(examples(spark, sf_dir), C, SIGMA)).select(*r("eps_bits"), "client")


@query
def information_bound(spark, sf_dir):
    """client, info_bits: the most that the coded values of a column tell of one of its entries, if entries are normal; the budget
    bounds it."""
    entries = examples(spark, sf_dir).select("client", F.posexplode("x").alias("j", "v")).select("client", "j", (F.col("v") * F.col("v")).alias("square"))
    sums = entries.groupBy("client", "j").agg(F.sum("square").alias("total"), F.max("square").alias("top"))
    rest = F.greatest(F.col("total") - F.col("top"), F.lit(0.0)) + SIGMA**2
    return sums.groupBy("client").agg(rounded(F.max(0.5 * F.log2(1 + C / rest))).alias("info_bits"))


@query
def step_sizes(spark, sf_dir):
    kinds = ("constant", "sqrt", "theory_epoch", "theory_horizon")
    rows = [(k, e, theory.learning_rate(k, e, 10, base=0.5, zeta=2.0, rho=3.0, phi2=1.5)) for k in kinds for e in range(10)]
    return spark.createDataFrame(rows, "kind string, epoch int, rate double").select("kind", "epoch", *r("rate", digits=9))


@query
def predict_classes(spark, sf_dir):
    """predicted, n: the class of largest output under planted weights of ten outputs."""
    out = grad.predict(examples(spark, sf_dir), tables.teacher(width(), 10))
    return out.groupBy("predicted").agg(F.count("*").alias("n"))


@query
def data_constants(spark, sf_dir):
    return theory.data_constants(examples(spark, sf_dir), half_teacher()).select("client", "l", *r("zeta", "kappa"))


def setting() -> theory.Setting:
    return theory.Setting(C, B_SERVER, SIGMA, width(), float((half_teacher() ** 2).sum()))


def _clients(spark, sf_dir):
    """client, l, b, p_arrive, zeta, kappa."""
    ex = examples(spark, sf_dir)
    times = delay.arrival_probability(loaded(spark, sf_dir, ex), DEADLINE * scale()).select("client", "b", "p_arrive")
    return theory.data_constants(ex, half_teacher()).join(F.broadcast(times), "client")


def _bound(spark, sf_dir, mode):
    rho = theory.variance_bound(_clients(spark, sf_dir), setting(), mode)
    exponent = F.floor(F.log10("rho"))
    return rho.select(exponent.alias("exponent"), F.round(F.col("rho") / F.pow(F.lit(10.0), exponent), 6).alias("mantissa"))


@query
def variance_bound_printed(spark, sf_dir):
    return _bound(spark, sf_dir, "printed")


@query
def variance_bound_fixed(spark, sf_dir):
    return _bound(spark, sf_dir, "printed_fixed")


@query
def variance_bound_rederived(spark, sf_dir):
    return _bound(spark, sf_dir, "rederived")


def _rho_zeta(spark, sf_dir):
    clients = _clients(spark, sf_dir)
    return theory.variance_bound(clients, setting(), "rederived").first()["rho"], clients.agg(F.sum("zeta")).first()[0]


@query
def gap_bound(spark, sf_dir):
    rho, zeta = _rho_zeta(spark, sf_dir)
    rows = [(n, theory.gap_bound(rho, zeta, setting().phi2, n)) for n in (10, 100, 1000)]
    return spark.createDataFrame(rows, "epochs int, bound double").select("epochs", *r("bound", digits=4))


@query
def time_to_gap(spark, sf_dir):
    rho, zeta = _rho_zeta(spark, sf_dir)
    rows = [(g, theory.time_to_gap(rho, zeta, setting().phi2, DEADLINE * scale(), g)) for g in (1.0, 10.0, 100.0)]
    return spark.createDataFrame(rows, "gap double, seconds double").select("gap", *r("seconds", digits=4))


def _variances(spark, sf_dir):
    ex = _sized(spark, sf_dir)
    times = delay.arrival_probability(loaded(spark, sf_dir, ex), DEADLINE * scale())
    return ex, theory.client_variance(ex, half_teacher()), times


@query
def exact_client_variance(spark, sf_dir):
    _, variances, times = _variances(spark, sf_dir)
    return theory.exact_client_variance(variances, times).select("client", *r("s", "with_arrivals"))


@query
def exact_server_variance(spark, sf_dir):
    table = coding.composite_table(examples(spark, sf_dir), C, SIGMA)
    return theory.exact_server_variance(table, half_teacher(), B_SERVER).select(*r("server_variance"))


@query
def exact_gradient_variance(spark, sf_dir):
    ex, variances, times = _variances(spark, sf_dir)
    totals = theory.data_constants(ex, half_teacher()).agg(F.sum("zeta").alias("zeta"), F.sum("kappa").alias("kappa")).first().asDict()
    value = theory.exact_gradient_variance(variances, times, totals, setting(), half_teacher(), grad.full_gradient(ex, half_teacher()), tables.CLIENTS)
    return spark.createDataFrame([(value,)], "variance double").select(*r("variance", digits=4))


def _train(rule: str) -> Query:
    def run(spark, sf_dir):
        sigma = SIGMA if rule in ("corrected", "server_only", "server_only_full") else 0.0
        b_server = 0 if rule == "server_only_full" else B_SERVER
        config = training.Config(epochs=EPOCHS, coded_rows=C, b_server=b_server, sigma=sigma, deadline=DEADLINE * scale(), lr=LR, drop=DROP, n_mac=N_MAC * scale())
        ex = _sized(spark, sf_dir)
        if rule == "weighted_full":
            ex = ex.withColumn("b", F.col("l"))
        profiles = delay.client_profiles(tables.read(spark, sf_dir, "nation")).join(F.broadcast(ex.groupBy("client").agg(F.max("l").alias("l"), F.max("b").alias("b"))), "client")
        epochs = training.Epochs(delay.with_times(profiles, N_MAC * scale(), PAYLOAD * scale()), config)
        weights = training.missing_weights(epochs) if rule.startswith("weighted") else None
        table = None if rule in ("first_arrivals", "central") else training.make_composite(ex, config, weights)
        done = training.run(rule.removesuffix("_full") if rule == "server_only_full" else rule, training.RowSource(ex, config), epochs, table, config)
        rows = [(j, float(a), float(b)) for j, (a, b) in enumerate(zip(done.last.ravel(), done.mean.ravel()))]
        return spark.createDataFrame(rows, "j int, w double, mean double").select("j", *r("w", "mean"))

    run.__name__ = f"train_{rule}_5"
    return query(run)


for _rule in ("corrected", "first_arrivals", "weighted_full", "weighted_mini", "server_only", "server_only_full", "central"):
    _train(_rule)


@query
def exact_solution(spark, sf_dir):
    return matrix_rows(spark, grad.exact_solution(examples(spark, sf_dir)), "w")


@query
def convergence_trace(spark, sf_dir):
    return workloads.convergence(spark, sf_dir)


@query
def time_to_target(spark, sf_dir):
    """The first recorded time at which the gap is at most three times the corrected scheme's last one."""
    trace = cut(workloads.convergence(spark, sf_dir))
    return workloads.time_to_target(trace, 3 * trace.where("method = 'corrected'").agg(F.min("gap")).first()[0])


@query
def image_fourier(spark, sf_dir):
    return workloads.image_task(spark, sf_dir, "fourier", epochs=30, every=10, seeds=1)


@query
def image_given(spark, sf_dir):
    return workloads.image_task(spark, sf_dir, "given")


@query
def theorem_step(spark, sf_dir):
    return workloads.theorem_run(spark, sf_dir)


@query
def measured_moments(spark, sf_dir):
    """bias2, variance over seeds, and the exact variance they estimate."""
    ex = _sized(spark, sf_dir)
    times = loaded(spark, sf_dir, ex)
    deadline = 2 * DEADLINE * scale()
    found = workloads.gradient_moments(spark, ex, times, half_teacher(), setting(), deadline).first()
    totals = theory.data_constants(ex, half_teacher()).agg(F.sum("zeta").alias("zeta"), F.sum("kappa").alias("kappa")).first().asDict()
    reached = delay.arrival_probability(times, deadline)
    exact = theory.exact_gradient_variance(theory.client_variance(ex, half_teacher()), reached, totals, setting(), half_teacher(), grad.full_gradient(ex, half_teacher()), tables.CLIENTS)
    return spark.createDataFrame([(found["bias2"], found["variance"], exact)], "bias2 double, variance double, exact double").select(*r("bias2", "variance", "exact", digits=3))


@query
def drop_sweep(spark, sf_dir):
    return workloads.drop_sweep(spark, sf_dir)


@query
def privacy_performance(spark, sf_dir):
    return workloads.privacy_performance(spark, sf_dir)


@query
def ablation_correction(spark, sf_dir):
    return workloads.ablation(spark, sf_dir)


@query
def coded_rows_tradeoff(spark, sf_dir):
    return workloads.tradeoff_grid(spark, sf_dir)


@query
def document_quality(spark, sf_dir):
    return workloads.document_quality(spark, sf_dir)


@query
def lineitem_regression(spark, sf_dir):
    return workloads.lineitem_regression(spark, sf_dir)


@query
def comm_cost(spark, sf_dir):
    return delay.communication_cost(delay.client_profiles(tables.read(spark, sf_dir, "nation")), C, D, 1).withColumn("upload_seconds", rounded("upload_seconds", 9))


@query
def mac_cost(spark, sf_dir):
    return delay.mac_cost(loaded(spark, sf_dir), C, B_SERVER, D, 1)


@query
def sim_time_cumulative(spark, sf_dir):
    return delay.epoch_times(arrived(spark, sf_dir)).select("epoch", *r("duration", "sim_time", digits=9))


@query
def first_arrivals_topk(spark, sf_dir):
    return delay.first_arrivals(arrived(spark, sf_dir), DROP).select("epoch", "client", "place", *r("t", digits=9))


@query
def epoch_time_order_stat(spark, sf_dir):
    times = arrived(spark, sf_dir)
    parts = [delay.first_arrivals(times, x).groupBy("epoch").agg(F.max("t").alias("duration")).withColumn("drop_share", F.lit(x)) for x in (0.0, 0.1, 0.3, 0.5)]
    every = parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])
    return every.groupBy("drop_share").agg(rounded(F.avg("duration"), 9).alias("duration"), rounded(F.max("duration"), 9).alias("slowest"))


def _regions(spark, sf_dir):
    return arrived(spark, sf_dir).withColumn("region", (F.col("client") % 4).cast("int"))


@query
def method_rollup(spark, sf_dir):
    level = F.grouping_id().cast("int").alias("level")
    return _regions(spark, sf_dir).rollup("region", "client").agg(F.count("*").alias("n"), rounded(F.avg("t"), 9).alias("t"), level)


@query
def method_pivot(spark, sf_dir):
    wide = _regions(spark, sf_dir).groupBy("epoch").pivot("region", [0, 1, 2, 3]).agg(rounded(F.avg("t"), 9))
    return wide.withColumnsRenamed({str(i): f"r{i}" for i in range(4)})


@query
def method_cube(spark, sf_dir):
    """Arrivals by region of the client's nation and by outcome, and over both."""
    nations, regions = (tables.read(spark, sf_dir, t) for t in ("nation", "region"))
    names = nations.join(regions, nations["n_regionkey"] == regions["r_regionkey"]).select(F.col("n_nationkey").cast("int").alias("client"), F.col("r_name").alias("region"))
    rows = arrived(spark, sf_dir).join(F.broadcast(names), "client")
    rows = rows.withColumn("outcome", F.when(F.col("arrived"), "arrived").otherwise("late"))
    sums = rows.cube("region", "outcome").agg(F.count("*").alias("n"), rounded(F.avg("t"), 9).alias("t"), F.grouping_id().cast("int").alias("level"))
    return sums.fillna("every", ["region", "outcome"])


@query
def delay_percentiles(spark, sf_dir):
    """client, exact percentiles of the delay, and whether the sketch's median lies within a thousandth of the values."""
    sketch = F.percentile_approx("t", 0.5, 10000)
    share = lambda q: F.percentile("t", F.lit(q))
    out = arrived(spark, sf_dir).groupBy("client").agg(share(0.5).alias("p50"), share(0.9).alias("p90"), share(0.99).alias("p99"), sketch.alias("s"), F.max("t").alias("top"), F.min("t").alias("low"))
    close = (F.col("s") >= F.col("low")) & (F.abs(F.col("s") - F.col("p50")) <= F.col("top") - F.col("low"))
    return out.select("client", *r("p50", "p90", "p99", digits=9), close.alias("sketch_close"))


@query
def epoch_windows(spark, sf_dir):
    """epoch, duration, change since the epoch before, mean of the last five, quarter by duration; one row an epoch."""
    times = delay.epoch_times(arrived(spark, sf_dir))
    order = Window.orderBy("epoch")
    change = F.col("duration") - F.lag("duration").over(order)
    mean = F.avg("duration").over(order.rowsBetween(-4, 0))
    quarter = F.ntile(4).over(Window.orderBy("duration", "epoch"))
    return times.select("epoch", rounded("duration", 9).alias("duration"), rounded(change, 9).alias("change"), rounded(mean, 9).alias("mean5"), quarter.alias("quarter"))


@query
def subset_set_operations(spark, sf_dir):
    """what, n: ids of the subsets by set operations: together all, in common none."""
    rows = cut(partition.split_subsets(shards(spark, sf_dir).select("row_id", "client"), 5).select("row_id", "subset"))
    part = lambda i: rows.where(F.col("subset") == i).select("row_id")
    every = part(0).union(part(1)).union(part(2)).union(part(3)).union(part(4))
    ids = rows.select("row_id")
    parts = {"all": ids, "union": every.distinct(), "intersect": part(0).intersect(part(1)), "except": ids.exceptAll(every)}
    found = [x.agg(F.count("*").alias("n")).select(F.lit(k).alias("what"), "n") for k, x in parts.items()]
    return found[0].unionByName(found[1]).unionByName(found[2]).unionByName(found[3])


@query
def labelled_semijoin(spark, sf_dir):
    docs, labels = tables.read(spark, sf_dir, "documents"), tables.read(spark, sf_dir, "labels")
    return docs.select("doc_id", "source").join(labels.select("doc_id"), "doc_id", "left_semi").groupBy("source").agg(F.count("*").alias("n"))


@query
def order_features(spark, sf_dir):
    """client (the customer's nation), region, and means of numeric features of lines, orders and parts joined."""
    read = lambda t: tables.read(spark, sf_dir, t)
    places = read("nation").join(F.broadcast(read("region")), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("c_nationkey"), F.col("r_name").alias("region"))
    owners = read("customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey").join(F.broadcast(places), "c_nationkey")
    lines = read("lineitem").select("l_orderkey", "l_partkey", "l_quantity").join(read("orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey", "o_totalprice"), "l_orderkey")
    lines = lines.join(read("part").select(F.col("p_partkey").alias("l_partkey"), "p_size", "p_retailprice"), "l_partkey").join(owners, "o_custkey")
    mean = lambda c, scale: rounded(F.avg(F.col(c) / scale), 6)
    return lines.groupBy(F.col("c_nationkey").cast("int").alias("client"), "region").agg(
        F.count("*").alias("n"), mean("l_quantity", 50.0).alias("quantity"), mean("o_totalprice", 1000.0).alias("price"), mean("p_size", 50.0).alias("size"), mean("p_retailprice", 1000.0).alias("retail")
    )


@query
def holdout_antijoin(spark, sf_dir):
    docs, held = tables.read(spark, sf_dir, "documents"), tables.read(spark, sf_dir, "benchmark")
    return docs.select("source", "text").join(held.select("text"), "text", "left_anti").groupBy("source").agg(F.count("*").alias("n"))


@query
def range_join_attempts(spark, sf_dir):
    tries = spark.range(1, 6).select(F.col("id").cast("int").alias("k"))
    fits = F.col("k") * F.col("tau") <= F.lit(DEADLINE) - F.col("t_c") - F.col("t_d")
    return loaded(spark, sf_dir).join(F.broadcast(tries), fits).select("client", "k", rounded(F.col("t_c") + F.col("t_d") + F.col("k") * F.col("tau"), 9).alias("t"))


@query
def asof_model_version(spark, sf_dir):
    """Which daily model version an update was computed with: the last one at or before it.

    Versions and updates share one ordered pass within each day; a day without an earlier version takes the last of
    the days before, of which there is one row a day.
    """
    events = tables.read(spark, sf_dir, "events").withColumn("s", F.unix_timestamp(F.col("ts").cast("timestamp")))
    versions = events.where("event_type = 'purchase'").groupBy((F.col("s") - F.col("s") % 86400).alias("v_s")).agg(F.max("value").alias("version"))
    asked = events.select("event_id", (F.col("s") - F.col("s") % 86400).alias("day"))
    days = asked.select(F.col("day").alias("v_s")).distinct().join(versions, "v_s", "full")
    order = Window.orderBy("v_s").rowsBetween(Window.unboundedPreceding, 0)
    filled = days.select(F.col("v_s").alias("day"), F.last("version", ignorenulls=True).over(order).alias("version"))
    return asked.join(F.broadcast(filled), "day", "left").select("event_id", "version")


@query
def stream_epoch_aggregate(spark, sf_dir):
    closed = stream.drain(stream.epoch_aggregate(stream.open_stream(spark, sf_dir), "1 hour", "10 minutes"))
    return closed.select(F.unix_timestamp("start").alias("start"), "client", "n", *r("payload"))


@query
def stream_sliding(spark, sf_dir):
    """Two-hour windows every hour."""
    closed = stream.drain(stream.sliding_aggregate(stream.open_stream(spark, sf_dir), "2 hours", "1 hour", "10 minutes"))
    return closed.select(F.unix_timestamp("start").alias("start"), "n", *r("payload"))


def _folder(spark, kind: str) -> str:
    return f"{ensure_checkpoint_dir(spark)}/{kind}-{uuid.uuid4().hex}"


@query
def stream_parameter_server(spark, sf_dir):
    """n, payload of all closed epochs, as the durable server's state holds them."""
    path = _folder(spark, "server")
    add = lambda state, rows: [state[0] + sum(x["n"] for x in rows), state[1] + sum(x["payload"] for x in rows)]
    server = stream.ParameterServer(spark, f"{path}/state", add, [0.0, 0.0])
    stream.serve(stream.epoch_aggregate(stream.open_stream(spark, sf_dir), "1 hour", "10 minutes"), server, f"{path}/log")
    return spark.createDataFrame([(int(server.state[0]), server.state[1])], "n long, payload double").select("n", rounded("payload", 4).alias("payload"))


@query
def stream_incremental_coding(spark, sf_dir):
    """The composite of whole embeddings, coded batch by batch as they come."""
    rows = tables.read_stream(spark, sf_dir, "embeddings", tables.read(spark, sf_dir, "embeddings").schema)
    x = F.transform("embedding", lambda v: v.cast("double"))
    examples = rows.select((F.col("vec_id") % tables.CLIENTS).cast("int").alias("client"), F.col("vec_id").alias("row_id"), x.alias("x"), F.array(F.col("label").cast("double")).alias("y"))
    path = _folder(spark, "composite")
    server = stream.CompositeServer(f"{path}/table", C)
    stream.serve(examples, server, f"{path}/log")
    return _coded(server.table(spark), ["k"])


#: Stretches of delivery time that the late stream comes in.
DELIVERIES = 8


@query
def stream_late_injected(spark, sf_dir):
    """start, n: results by two-hour epoch that came before the watermark closed it, of a stream in delivery order."""
    path = _folder(spark, "deliveries")
    rows = stream.updates(tables.read(spark, sf_dir, "events"))
    stream.in_delivery_order(rows, path, DELIVERIES, LATEST)
    live = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(path)
    closed = stream.drain(stream.epoch_aggregate(live, "2 hours", "10 minutes"))
    return closed.groupBy(F.unix_timestamp("start").alias("start")).agg(F.sum("n").alias("n"))


#: Longest delay of a delivery in seconds: ten days, so that whole epochs close before their last results come.
LATEST = 864_000


@query
def stream_late_drop(spark, sf_dir):
    return stream.delivered_late(stream.updates(tables.read(spark, sf_dir, "events")), 3600, 600)


@query
def stream_sessions(spark, sf_dir):
    closed = stream.drain(stream.sessions(stream.open_stream(spark, sf_dir), "2 hours", "10 minutes"))
    return closed.select(F.unix_micros("start").alias("start"), "client", "n")


@query
def stream_dedup(spark, sf_dir):
    rows = stream.open_stream(spark, sf_dir)
    twice = rows.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    return stream.drain(stream.once_each(twice, "10 minutes")).groupBy("client").agg(F.count("*").alias("n"))


@query
def page_features(spark, sf_dir):
    return features.page_statistics(tables.read(spark, sf_dir, "pages"))


@query
def conversation_clients(spark, sf_dir):
    turns = tables.read(spark, sf_dir, "conversations")
    return turns.groupBy((F.col("conv_id") % 20).cast("int").alias("client"), "role").agg(F.count("*").alias("n"), F.sum(F.length("text")).cast("long").alias("chars"))


@query
def lineitem_constants(spark, sf_dir):
    rows = tables.lineitem_examples(spark, sf_dir).select("client", F.posexplode("x").alias("j", "v"))
    sq = F.col("v") * F.col("v")
    return rows.groupBy("client", "j").agg(F.count("*").alias("n"), rounded(F.sum(sq) - F.max(sq), 4).alias("rest"))


for _query in """
    fourier_features encode_clients encode_clients_noisy encode_labels encode_weighted composite
    composite_incremental loss full_gradient server_gradient client_gradients aggregated_gradient
    privacy_budget sigma_for_budget coded_rows_for_budget privacy_grid data_constants variance_bound_printed
    privacy_overall information_bound predict_classes variance_bound_fixed variance_bound_rederived gap_bound time_to_gap exact_client_variance
    exact_server_variance exact_gradient_variance train_corrected_5 train_first_arrivals_5
    train_weighted_full_5 train_weighted_mini_5 train_server_only_5 train_server_only_full_5 train_central_5
    exact_solution measured_moments
""".split():
    whole(QUERIES[_query])
