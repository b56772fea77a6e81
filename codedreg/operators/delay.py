"""Delays of clients of unequal speed, arrival within a deadline, and the planning of loads.

A client's epoch takes compute time, a geometric number of upload attempts, and the download; all are column
expressions over a few rows of profiles.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from codedreg.functions.hashrand import with_uniform

#: The simulated devices.
UPLINK_BPS, DOWNLINK_BPS, UPLINK_RANGE = 1e6, 1e6, (0.3, 1.0)
CLIENT_MACS, SERVER_MACS, MAC_RANGE = 1_536_000.0, 15_360_000.0, (0.1, 1.0)
ERASURE = 0.1
CLIENTS = 20

RATE_SEED, LINK_SEED, ATTEMPT_SEED = 21, 22, 23


def client_profiles(nation: DataFrame, n: int = CLIENTS) -> DataFrame:
    """client, mac_rate, up_bps, down_bps, p_erase: the first n nation keys as devices, rates by hash."""
    base = nation.where(F.col("n_nationkey") < n).select(F.col("n_nationkey").cast("int").alias("client"))
    drawn = with_uniform(with_uniform(base, "um", "client", "0", RATE_SEED), "uu", "client", "0", LINK_SEED)
    span = lambda u, lo, hi: F.lit(lo) + F.lit(hi - lo) * F.col(u)
    return drawn.select("client", (span("um", *MAC_RANGE) * CLIENT_MACS).alias("mac_rate"), (span("uu", *UPLINK_RANGE) * UPLINK_BPS).alias("up_bps"), F.lit(DOWNLINK_BPS).alias("down_bps"), F.lit(ERASURE).alias("p_erase"))


def with_loads(profiles: DataFrame, ex: DataFrame, share: float | None = None, b: int | None = None) -> DataFrame:
    """Add l (the client's rows) and b (a share of them, or a number, clamped to 1..l)."""
    sizes = ex.groupBy("client").agg(F.count("*").alias("l"))
    batch = F.ceil(F.col("l") * share) if share is not None else F.lit(b)
    return profiles.join(F.broadcast(sizes), "client").withColumn("b", F.greatest(F.lit(1), F.least(batch, F.col("l"))).cast("long"))


def macs_per_row(d: int, o: int) -> int:
    return 2 * d * o


def payload_bits(d: int, o: int) -> int:
    return 32 * d * o


def with_times(profiles: DataFrame, n_mac: float, payload: float) -> DataFrame:
    """Add compute time t_c (on b rows), one attempt's time tau, and download time t_d."""
    return profiles.withColumns({"t_c": F.col("b") * F.lit(float(n_mac)) / F.col("mac_rate"), "tau": F.lit(float(payload)) / F.col("up_bps"), "t_d": F.lit(float(payload)) / F.col("down_bps")})


def server_time(b: int, n_mac: float, rate: float = SERVER_MACS) -> float:
    return b * n_mac / rate


def _chance(attempts: Column) -> Column:
    """That one of so many attempts succeeds."""
    missed = F.when(F.col("p_erase") > 0, F.pow("p_erase", attempts)).otherwise(0.0)
    return F.when(attempts >= 1, 1.0 - missed).otherwise(0.0)


def arrival_probability(timed: DataFrame, deadline: float | Column) -> DataFrame:
    """Add k_max (attempts that fit) and p_arrive; the column may vary by row."""
    limit = F.lit(float(deadline)) if isinstance(deadline, (int, float)) else deadline
    fits = F.floor((limit - F.col("t_c") - F.col("t_d")) / F.col("tau"))
    return timed.withColumn("k_max", fits).withColumn("p_arrive", _chance(F.col("k_max")))


def simulate_arrivals(timed: DataFrame, deadline: float, epochs: int, seed: int = 0) -> DataFrame:
    """epoch, client, attempts, t, arrived, p_arrive of all epochs at once."""
    wide = arrival_probability(timed, deadline).withColumn("epoch", F.explode(F.sequence(F.lit(0), F.lit(epochs - 1))))
    drawn = with_uniform(wide, "u__", "epoch", "client", ATTEMPT_SEED + seed)
    attempts = F.when(F.col("p_erase") > 0, 1 + F.floor(F.ln("u__") / F.ln("p_erase"))).otherwise(1)
    t = F.col("t_c") + F.col("attempts") * F.col("tau") + F.col("t_d")
    out = drawn.withColumn("attempts", attempts.cast("long")).withColumn("t", t)
    return out.withColumn("arrived", F.col("attempts") <= F.col("k_max")).select("epoch", "client", "attempts", "t", "arrived", "p_arrive")


def arrival_stats(arrivals: DataFrame) -> DataFrame:
    """client, realised and expected share of arrivals, mean attempts, slowest epoch."""
    return arrivals.groupBy("client").agg(F.avg(F.col("arrived").cast("double")).alias("realised"), F.max("p_arrive").alias("expected"), F.avg("attempts").alias("attempts"), F.max("t").alias("slowest"))


def first_arrivals(arrivals: DataFrame, drop: float) -> DataFrame:
    """The clients whose results arrive first in each epoch, a share of them dropped; with place."""
    order = Window.partitionBy("epoch").orderBy("t", "client")
    n = F.count("*").over(Window.partitionBy("epoch"))
    kept = F.ceil(F.round((1 - F.lit(float(drop))) * n, 9))
    return arrivals.withColumn("place", F.row_number().over(order)).withColumn("kept", kept).where("place <= kept").drop("kept")


def epoch_times(arrivals: DataFrame, drop: float = 0.0) -> DataFrame:
    """epoch, duration (the last result waited for), and simulated time so far."""
    lasting = first_arrivals(arrivals, drop).groupBy("epoch").agg(F.max("t").alias("duration"))
    # one row an epoch: its number is a parameter, so one window over all of them is bounded
    return lasting.withColumn("sim_time", F.sum("duration").over(Window.orderBy("epoch")))


def load_candidates(profiles: DataFrame, n_mac: float, payload: float, deadlines: list[float]) -> DataFrame:
    """For each client, deadline and number of attempts that fits: the largest batch that leaves time for them, and its worth.

    Batch times arrival probability only peaks where a whole number of attempts fills the time left, so these candidates
    decide.  A client that cannot take part by a deadline has none.
    """
    spark = profiles.sparkSession
    times = spark.createDataFrame([(float(t),) for t in deadlines], "deadline double")
    tau, t_d = F.lit(float(payload)) / F.col("up_bps"), F.lit(float(payload)) / F.col("down_bps")
    fits = F.floor((F.col("deadline") - t_d) / tau).cast("int")
    wide = profiles.crossJoin(F.broadcast(times)).where(fits >= 1).withColumn("k", F.explode(F.sequence(F.lit(1), fits)))
    most = F.floor(F.col("mac_rate") / F.lit(float(n_mac)) * (F.col("deadline") - t_d - F.col("k") * tau) + F.lit(1e-9))
    wide = wide.withColumn("load", F.least(F.col("l"), most)).where("load >= 1")
    return wide.withColumn("worth", F.col("load") * _chance(F.col("k").cast("double")))


def plan_loads(profiles: DataFrame, n_mac: float, payload: float, deadlines: list[float]) -> DataFrame:
    """deadline, client, load (0 if it cannot take part), k, worth: the best candidate of each."""
    best = load_candidates(profiles, n_mac, payload, deadlines).groupBy("deadline", "client").agg(F.max(F.struct("worth", "load", F.col("k").cast("long").alias("k"))).alias("m"))
    return best.select("deadline", "client", "m.load", "m.k", "m.worth")


def smallest_deadline(plan: DataFrame, target: float) -> DataFrame:
    """deadline, expected: the least deadline by which the expected number of processed rows reaches the target."""
    totals = plan.groupBy("deadline").agg(F.sum("worth").alias("expected")).where(F.col("expected") >= target)
    return totals.agg(F.min(F.struct("deadline", "expected")).alias("m")).select("m.deadline", "m.expected")


def deadline_grid(profiles: DataFrame, n_mac: float, payload: float, points: int = 64) -> list[float]:
    """Deadlines from the first at which any client can send a row to the last at which each could send all its rows at
    the tenth attempt, in equal ratios."""
    tau, t_d = F.lit(float(payload)) / F.col("up_bps"), F.lit(float(payload)) / F.col("down_bps")
    row = F.lit(float(n_mac)) / F.col("mac_rate")
    low, high = profiles.agg(F.min(t_d + tau + row), F.max(t_d + 10 * tau + row * F.col("l"))).first()
    ratio = (high / low) ** (1 / (points - 1)) if points > 1 else 1.0
    return [low * ratio**i * (1 + 1e-9) for i in range(points)]


def planned(profiles: DataFrame, n_mac: float, payload: float, target: float, points: int = 64) -> tuple[float, dict[int, int]]:
    """The least deadline of the grid by which the target number of rows is expected, and every client's load for it (0: cannot
    take part)."""
    plan = plan_loads(profiles, n_mac, payload, deadline_grid(profiles, n_mac, payload, points))
    found = smallest_deadline(plan, target).first()
    if found is None or found["deadline"] is None:
        raise ValueError("no deadline of the grid meets the target")
    loads = {r["client"]: 0 for r in profiles.select("client").collect()}
    loads |= {r["client"]: int(r["load"]) for r in plan.where(F.col("deadline") == found["deadline"]).collect()}
    return found["deadline"], loads


def communication_cost(profiles: DataFrame, c: int, d: int, o: int) -> DataFrame:
    """client, one-time upload of coded data (bits, expected seconds), bits up and down in an epoch."""
    bits = 32.0 * c * (d + o)
    expected = F.lit(bits) / F.col("up_bps") / (1 - F.col("p_erase"))
    return profiles.select("client", F.lit(bits).alias("upload_bits"), expected.alias("upload_seconds"), F.lit(float(payload_bits(d, o))).alias("up_bits"), F.lit(float(payload_bits(d, o))).alias("down_bits"))


def mac_cost(profiles: DataFrame, c: int, b_server: int, d: int, o: int) -> DataFrame:
    """client, multiply-accumulates for coding and for an epoch, and the server's."""
    return profiles.select("client", (F.col("l") * float(c * (d + o))).alias("coding_macs"), (F.col("b") * float(macs_per_row(d, o))).alias("epoch_macs"), F.lit(float(b_server * macs_per_row(d, o))).alias("server_macs"))


def profiles_of(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """Profiles from literal rows (client, mac_rate, up_bps, down_bps, p_erase, l, b)."""
    return spark.createDataFrame(rows, "client int, mac_rate double, up_bps double, down_bps double, p_erase double, l long, b long")
