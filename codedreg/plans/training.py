"""Training by the corrected coded scheme and by its rivals, over one loop.

Every scheme is a rule that says, for an epoch, with which coefficients the clients' gradients add up (on batches or on
all their rows), what the server adds, and how long the epoch lasts.  What the rules ask of the data comes from a source:
`GramSource` holds sums of squares of each client and subset after a single pass, so epochs cost no pass at all;
`RowSource` runs one job an epoch, which serves all runs of an experiment, reads only the epoch's own files and returns one d x o sum a
run, however many clients there are.  `choose_source` picks by the size of the sums; results are the same.

Weights leave Spark every epoch, so lineage does not grow; a run can stop and go on from its state with the same result,
because all random numbers are functions of (seed, epoch, id).
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.functions.hashrand import uniform
from codedreg.operators import delay
from codedreg.operators.coding import add_noise, collect_composite, compose, encode_clients, weight_clients
from codedreg.operators.gradients import GRAM_BYTES_MAX, Gram, bias_correction, conjugate_gradients, grams, largest_eigenvalue, losses, server_gradient, shape_of, weighted_gradients
from codedreg.operators.sampling import SERVER_SEED, sample_batch
from codedreg.operators.theory import learning_rate
from codedreg.storage import laid_out


@dataclass(frozen=True)
class Config:
    """Parameters of a run; every one is echoed in its result."""

    epochs: int = 50
    coded_rows: int = 64
    b_server: int = 16
    sigma: float = 0.0
    deadline: float = 1.0
    lr: float = 0.01
    lr_kind: str = "constant"
    seed: int = 0
    sampler: str = "fixed"
    parts: int | dict[int, int] = 1
    server_weight: float = 0.5
    correct: bool = True
    reweight: bool = True
    drop: float = 0.0
    scale: str = "rows"
    average: str = "all"
    n_mac: float = 0.0
    theory: dict = field(default_factory=dict)


@dataclass
class State:
    """Enough to go on with: the next epoch, weights, sum of iterates, simulated time."""

    epoch: int
    w: np.ndarray
    total: np.ndarray
    time: float = 0.0


@dataclass
class Result:
    """Iterates' mean, last weights, and (epoch, sim_time, weights) of the epochs recorded."""

    mean: np.ndarray
    last: np.ndarray
    trace: list[tuple[int, float, np.ndarray]]
    state: State
    unreachable: list[int]


@dataclass
class Step:
    """What an epoch asks for: coefficients of the clients' gradients (scaled to all their rows), whether these are taken on
    all rows instead of batches, the server's part, and how long the epoch lasts."""

    clients: dict[int, float]
    server: np.ndarray
    duration: float
    whole: bool = False


class GramSource:
    """Batches are the subsets of a client's cycle (parts, a number or one for each client) or whole clients; all from one pass."""

    def __init__(self, ex: DataFrame, parts: int | dict[int, int] = 1):
        self.ex, self.parts = ex, parts
        keys = ["client"] if parts == 1 else ["client", "subset"]
        self.by = grams(ex, keys)
        self.clients = sorted({k[0] for k in self.by})
        self.whole: dict[int, Gram] = {}
        for key, g in self.by.items():
            self.whole[key[0]] = self.whole[key[0]] + g if key[0] in self.whole else g
        self.all = sum(list(self.whole.values())[1:], next(iter(self.whole.values())))
        self.shape = self.all.xy.shape

    def rows(self, client: int) -> int:
        return self.whole[client].n

    def batch_gradient(self, client: int, epoch: int, w: np.ndarray) -> np.ndarray:
        """Gradient on the epoch's subset, scaled to the whole client."""
        if self.parts == 1:
            return self.whole[client].gradient(w)
        g = self.by.get((client, epoch % parts_of(self.parts, client)))
        return np.zeros(self.shape) if g is None else g.gradient(w) * self.rows(client) / g.n

    def combined(self, steps: list[Step], weights: list[np.ndarray], epoch: int) -> list[np.ndarray]:
        """For each step the clients' gradients, added with its coefficients."""
        out = []
        for step, w in zip(steps, weights):
            own = ((c, self.whole[i].gradient(w) if step.whole else self.batch_gradient(i, epoch, w)) for i, c in step.clients.items())
            out.append(sum((c * g for c, g in own), np.zeros(self.shape)))
        return out

    def loss(self, w: np.ndarray) -> float:
        return self.all.loss(w)

    def losses(self, weights: list[np.ndarray]) -> list[float]:
        return [self.all.loss(w) for w in weights]

    def optimum(self) -> np.ndarray:
        return np.linalg.lstsq(self.all.xx, self.all.xy, rcond=None)[0]

    def steepest(self) -> float:
        """Largest eigenvalue of X'X."""
        return float(np.linalg.eigvalsh(self.all.xx)[-1])


class RowSource:
    """Batches drawn by the sampler; ex has subset, or b and l of its client.

    Rows lie in a folder for each subset, or drawn batches, prepared for `ahead` epochs at a time, in a folder for each epoch.
    """

    def __init__(self, ex: DataFrame, config: Config, ahead: int = 20):
        self.config, self.ahead = config, ahead
        self.shape = shape_of(ex)
        self.by_subset = config.sampler == "subset"
        self.ex = laid_out(ex, "subset") if self.by_subset else ex
        keys = ["client", "subset"] if self.by_subset else ["client"]
        counts = {tuple(r[k] for k in keys): r["n"] for r in self.ex.groupBy(*keys).agg(F.count("*").alias("n")).collect()}
        self.drawn = counts
        self.sizes: dict[int, int] = {}
        for key, n in counts.items():
            self.sizes[key[0]] = self.sizes.get(key[0], 0) + n
        if not self.by_subset:
            b = {r["client"]: r["b"] for r in ex.groupBy("client").agg(F.max("b").alias("b")).collect()}
            self.drawn = b if config.sampler == "bernoulli" else {i: min(n, self.sizes[i]) for i, n in b.items()}
        self.clients = sorted(self.sizes)
        self.prepared: tuple[int, DataFrame] | None = None
        self.gram: Gram | None = None

    def rows(self, client: int) -> int:
        return self.sizes[client]

    def _batch(self, epoch: int) -> DataFrame:
        c = self.config
        if self.by_subset:
            if isinstance(c.parts, dict):
                now = [f"(client = {i} and subset = {epoch % n})" for i, n in sorted(c.parts.items())]
                return self.ex.where(F.col("subset").isin(sorted({epoch % n for n in c.parts.values()}))).where(" or ".join(now))
            return self.ex.where(F.col("subset") == epoch % c.parts)
        first = epoch - epoch % self.ahead
        if self.prepared is None or self.prepared[0] != first:
            rows = sample_batch(self.ex, min(self.ahead, c.epochs - first), c.sampler, seed=c.seed, first_epoch=first)
            self.prepared = first, laid_out(rows, "epoch")
        return self.prepared[1].where(F.col("epoch") == epoch)

    def _scale(self, client: int, epoch: int) -> float:
        """All rows of a client over those drawn."""
        n = self.drawn.get((client, epoch % parts_of(self.config.parts, client)), 0) if self.by_subset else self.drawn[client]
        return self.sizes[client] / n if n else 0.0

    def combined(self, steps: list[Step], weights: list[np.ndarray], epoch: int) -> list[np.ndarray]:
        out: list[np.ndarray] = [np.zeros(self.shape)] * len(steps)
        for whole in (False, True):
            own = [i for i, s in enumerate(steps) if s.whole == whole and s.clients]
            if own:
                scale = (lambda i: 1.0) if whole else (lambda i: self._scale(i, epoch))
                coefficients = [{i: c * scale(i) for i, c in steps[j].clients.items()} for j in own]
                rows = self.ex if whole else self._batch(epoch)
                for j, g in zip(own, weighted_gradients(rows, [weights[j] for j in own], coefficients)):
                    out[j] = g
        return out

    def loss(self, w: np.ndarray) -> float:
        return self.losses([w])[0]

    def losses(self, weights: list[np.ndarray]) -> list[float]:
        return [a for a, _ in losses(self.ex, weights)] if weights else []

    def _gram(self) -> Gram | None:
        """Sums of squares of all rows, while they fit."""
        if 8 * self.shape[0] ** 2 > GRAM_BYTES_MAX:
            return None
        if self.gram is None:
            self.gram = grams(self.ex, [])[()]
        return self.gram

    def optimum(self) -> np.ndarray:
        g = self._gram()
        return np.linalg.lstsq(g.xx, g.xy, rcond=None)[0] if g else conjugate_gradients(self.ex, *self.shape)

    def steepest(self) -> float:
        g = self._gram()
        return float(np.linalg.eigvalsh(g.xx)[-1]) if g else largest_eigenvalue(self.ex, *self.shape)


def parts_of(parts: int | dict[int, int], client: int) -> int:
    return parts[client] if isinstance(parts, dict) else parts


def choose_source(ex: DataFrame, clients: int, config: Config) -> GramSource | RowSource:
    """Sums of squares if batches are whole clients or fixed subsets and the sums are small; else rows."""
    d, o = shape_of(ex)
    cells = sum(config.parts.values()) if isinstance(config.parts, dict) else clients * config.parts
    if config.sampler == "subset" and cells * (d * d + d * o + o * o) * 8 <= GRAM_BYTES_MAX:
        return GramSource(ex, config.parts)
    return RowSource(ex, config)


class Epochs:
    """Arrivals of all epochs: which clients' results count, their probabilities, and how long each epoch lasts."""

    def __init__(self, timed: DataFrame, config: Config):
        rows = delay.simulate_arrivals(timed, config.deadline, config.epochs, config.seed).collect()
        self.by: dict[int, list] = {}
        for r in rows:
            self.by.setdefault(r["epoch"], []).append(r)
        self.p = {r["client"]: r["p_arrive"] for r in rows}

    def arrived(self, epoch: int) -> list[int]:
        return sorted(r["client"] for r in self.by[epoch] if r["arrived"] and r["p_arrive"] > 0)

    def first(self, epoch: int, drop: float) -> tuple[list[int], float]:
        order = sorted(self.by[epoch], key=lambda r: (r["t"], r["client"]))
        kept = order[: math.ceil(round((1 - drop) * len(order), 9))]
        return sorted(r["client"] for r in kept), max((r["t"] for r in kept), default=0.0)


class Composite:
    """The coded table on the server, drawn from for each epoch."""

    def __init__(self, x: np.ndarray, y: np.ndarray):
        self.x, self.y = x, y

    def batch(self, epoch: int, b: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
        u = uniform(SERVER_SEED + seed, epoch, np.arange(len(self.x)))
        own = np.lexsort((np.arange(len(u)), u))[:b]
        return self.x[own], self.y[own]


def corrected(source, epochs: Epochs, composite: Composite | None, config: Config, epoch: int, w: np.ndarray) -> Step:
    """Half the clients' arrived gradients over their probabilities, half the server's, and the make-up for noise."""
    share = config.server_weight if composite is not None else 0.0
    clients = {i: (1 - share) / (epochs.p[i] if config.reweight else 1.0) for i in epochs.arrived(epoch)}
    server = np.zeros(w.shape)
    if share:
        server = server_gradient(*composite.batch(epoch, config.b_server, config.seed), w)
        if config.correct:
            server = server + bias_correction(w, len(epochs.p), config.sigma)
    return Step(clients, share * server, config.deadline)


def first_arrivals(source, epochs: Epochs, composite, config: Config, epoch: int, w: np.ndarray) -> Step:
    """The first results of an epoch alone, scaled up by rows, by clients, or not at all."""
    kept, duration = epochs.first(epoch, config.drop)
    scale = 1.0
    if config.scale == "rows":
        scale = sum(map(source.rows, source.clients)) / max(1, sum(map(source.rows, kept)))
    elif config.scale == "count":
        scale = len(source.clients) / max(1, len(kept))
    return Step(dict.fromkeys(kept, scale), np.zeros(w.shape), duration)


def weighted_full(source, epochs: Epochs, composite: Composite, config: Config, epoch: int, w: np.ndarray) -> Step:
    """Arrived full gradients, and the whole weighted coded table for what misses."""
    return Step(dict.fromkeys(epochs.arrived(epoch), 1.0), server_gradient(composite.x, composite.y, w), config.deadline, whole=True)


def weighted_mini(source, epochs: Epochs, composite: Composite, config: Config, epoch: int, w: np.ndarray) -> Step:
    """As weighted_full, on batches of both; noise, if any, stays uncorrected."""
    return Step(dict.fromkeys(epochs.arrived(epoch), 1.0), server_gradient(*composite.batch(epoch, config.b_server, config.seed), w), config.deadline)


def server_only(source, epochs: Epochs, composite: Composite, config: Config, epoch: int, w: np.ndarray) -> Step:
    """The server's gradient alone, on a batch or (b_server = 0) the whole coded table."""
    x, y = composite.batch(epoch, config.b_server, config.seed) if config.b_server else (composite.x, composite.y)
    return Step({}, server_gradient(x, y, w), delay.server_time(len(x), config.n_mac))


def central(source, epochs: Epochs, composite, config: Config, epoch: int, w: np.ndarray) -> Step:
    """Full gradients of everyone: the reference."""
    return Step(dict.fromkeys(source.clients, 1.0), np.zeros(w.shape), 0.0, whole=True)


RULES = {"corrected": corrected, "first_arrivals": first_arrivals, "weighted_full": weighted_full, "weighted_mini": weighted_mini, "server_only": server_only, "central": central}


@dataclass
class Run:
    """A scheme with what it needs, and where it stands."""

    rule: str
    epochs: Epochs
    composite: Composite | None
    config: Config
    state: State | None = None


def run_many(source, runs: list[Run], every: int = 1, until: int | None = None) -> list[Result]:
    """Go through the epochs of all runs together, so that an epoch asks the source once; record every so many of them.

    The runs start at one epoch and last as long as the first one.
    """
    fresh = lambda: State(0, np.zeros(source.shape), np.zeros(source.shape))
    states = [replace(r.state) if r.state else fresh() for r in runs]
    stop = runs[0].config.epochs if until is None else until
    traces: list[list] = [[] for _ in runs]
    for epoch in range(states[0].epoch, stop):
        steps = [RULES[r.rule](source, r.epochs, r.composite, r.config, epoch, s.w) for r, s in zip(runs, states)]
        sums = source.combined(steps, [s.w for s in states], epoch)
        for r, s, step, clients, trace in zip(runs, states, steps, sums, traces):
            c = r.config
            s.total = s.total + s.w
            s.w = s.w - learning_rate(c.lr_kind, epoch, c.epochs, base=c.lr, **c.theory) * (clients + step.server)
            s.time += step.duration
            s.epoch = epoch + 1
            if (epoch + 1) % every == 0 or epoch + 1 == stop:
                trace.append((epoch + 1, s.time, s.total / (epoch + 1) if c.average == "all" else s.w))
    away = lambda r: sorted(i for i, p in r.epochs.p.items() if p == 0) if r.epochs else []
    return [Result(s.total / max(1, stop), s.w, trace, s, away(r)) for r, s, trace in zip(runs, states, traces)]


def run(rule: str, source, epochs: Epochs, composite: Composite | None, config: Config, every: int = 1, state: State | None = None, until: int | None = None) -> Result:
    """One run alone."""
    return run_many(source, [Run(rule, epochs, composite, config, state)], every, until)[0]


def coded_clients(ex: DataFrame, config: Config) -> DataFrame:
    """Noise-free coded tables; one coding pass serves all weights and noise levels."""
    return encode_clients(ex, config.coded_rows, 0.0, config.seed)


def noisy_composite(coded: DataFrame, config: Config, weights: dict[int, float] | None = None) -> Composite:
    """The composite of coded tables, weighted by client, with the noise of the configuration."""
    coded = weight_clients(coded, weights) if weights else coded
    noisy = add_noise(coded, config.sigma, config.seed) if config.sigma else coded
    return Composite(*collect_composite(compose(noisy)))


def make_composite(ex: DataFrame, config: Config, weights: dict[int, float] | None = None) -> Composite:
    """Encode and compose, once before training."""
    return noisy_composite(coded_clients(ex, config), config, weights)


def missing_weights(epochs: Epochs) -> dict[int, float]:
    """Square roots of the probabilities of not arriving, for the weighted schemes."""
    return {i: math.sqrt(1 - p) for i, p in epochs.p.items()}


def variant(config: Config, **changes) -> Config:
    return replace(config, **changes)
