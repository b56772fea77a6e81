"""SQL for DuckDB that recomputes the deterministic queries from the same tables, in long form (row, column, value)."""

from __future__ import annotations

from codedreg.functions.hashrand import gauss_columns, sql_with, uniform_columns
from codedreg.operators import coding, delay, features, sampling
from codedreg.sources import tables

D, C, B, B_SERVER, SIGMA, EPOCHS, LR = 8, 16, 5, 8, 0.3, 5, 0.002
DEADLINE = 0.0011
N_MAC, PAYLOAD = 2 * D, 32 * D
DROP = 0.3


def gauss_sql(source: str, name: str, k: str, ident: str, seed: int) -> str:
    return sql_with(source, gauss_columns(name, k, ident, seed))


def uniform_sql(source: str, name: str, k: str, ident: str, seed: int) -> str:
    return sql_with(source, uniform_columns(name, k, ident, seed))


def query(ctes: list[tuple[str, str]], last: str) -> str:
    return "with " + ",\n".join(f"{name} as ({body})" for name, body in ctes) + "\n" + last


#: row_id, label, x of the first D entries, scaled to a largest absolute value of 1; shards in label order.
SCALED = [
    ("e0", f"select vec_id as row_id, label, list_transform(embedding[1:{D}], lambda v: v::double) as x from embeddings"),
    ("top", "select max(abs(v)) as m from (select unnest(x) as v from e0)"),
    ("e1", "select row_id, label, list_transform(x, lambda v: v / m) as x from e0, top"),
    ("ex0", f"select row_id, x, (((row_number() over (order by label, row_id) - 1) * {tables.CLIENTS}) // count(*) over ())::int as client from e1"),
]
#: xs(row_id, client, j, v) and ys(row_id, client, y), with the planted weights t(j, t).
EXAMPLES = [
    *SCALED,
    ("xs", f"select row_id, client, unnest(range({D})) as j, unnest(x) as v from ex0"),
    ("t", "select j, t from (" + gauss_sql(f"(select unnest(range({D})) as j)", "t", "j", "0", tables.TEACHER_SEED) + ")"),
    ("z", gauss_sql("(select row_id, client from ex0)", "z", "0", "row_id", tables.NOISE_SEED)),
    ("ys", "select z.row_id, z.client, sum(v * t) + 0.1::double * any_value(z.z) as y from z join xs using (row_id) join t using (j) group by 1, 2"),
    ("sizes", "select client, count(*) as l from ex0 group by 1"),
]


def profiles() -> list[tuple[str, str]]:
    lo_m, hi_m = delay.MAC_RANGE
    lo_u, hi_u = delay.UPLINK_RANGE
    base = "(select n_nationkey::int as client from nation where n_nationkey < 20)"
    one = "(" + uniform_sql(base, "um", "client", "0", delay.RATE_SEED) + ")"
    return [
        ("p0", uniform_sql(one, "uu", "client", "0", delay.LINK_SEED)),
        ("profiles", f"select client, ({lo_m}::double + {hi_m - lo_m}::double * um) * {delay.CLIENT_MACS}::double as mac_rate, ({lo_u}::double + {hi_u - lo_u}::double * uu) * {delay.UPLINK_BPS}::double as up_bps, {delay.DOWNLINK_BPS}::double as down_bps, {delay.ERASURE}::double as p_erase from p0"),
    ]


def timed(b: str = f"least({B}, 25)", l: str = "25") -> list[tuple[str, str]]:  # noqa: E741
    return [
        *profiles(),
        ("loaded", f"select *, {b} as b, {l} as l from profiles"),
        ("timed", f"select *, b * {N_MAC}::double / mac_rate as t_c, {PAYLOAD}::double / up_bps as tau, {PAYLOAD}::double / down_bps as t_d from loaded"),
        ("chance", f"select *, floor(({DEADLINE}::double - t_c - t_d) / tau) as k_max from timed"),
        ("arrive", "select *, case when k_max >= 1 then 1 - pow(p_erase, k_max) else 0 end as p_arrive from chance"),
    ]


def arrivals(epochs: int, **loads) -> list[tuple[str, str]]:
    wide = f"(select arrive.*, epoch from arrive, (select unnest(range({epochs})) as epoch))"
    return [
        *timed(**loads),
        ("drawn", uniform_sql(wide, "ua", "epoch", "client", delay.ATTEMPT_SEED)),
        ("tries", "select *, (1 + floor(ln(ua) / ln(p_erase)))::bigint as attempts from drawn"),
        ("arrivals", "select epoch::int as epoch, client, attempts, t_c + attempts * tau + t_d as t, attempts <= k_max as arrived, p_arrive from tries"),
    ]


def coded(weight: str = "1", sigma: float = 0.0, rows: str = "xs", labels: str = "ys", prefix: str = "") -> list[tuple[str, str]]:
    """cx(client, k, j, v) and cy(client, k, v)."""
    p = prefix
    pairs = f"(select row_id, client, k from (select row_id, client from {labels}), (select unnest(range({C})) as k))"
    out = [
        (f"{p}g", gauss_sql(pairs, "g", "k", "row_id", coding.GAUSS_SEED)),
        (f"{p}cx0", f"select g.client, k, j, sum(g * v * {weight}) as v from {p}g g join {rows} x using (row_id) group by 1, 2, 3"),
        (f"{p}cy", f"select g.client, k, sum(g * y * {weight}) as v from {p}g g join {labels} y using (row_id) group by 1, 2"),
    ]
    if sigma:
        noisy = gauss_sql(f"{p}cx0", "n", "k", f"(client * {D} + j)", coding.NOISE_SEED)
        return [*out, (f"{p}cx", f"select client, k, j, v + {sigma}::double * n as v from ({noisy})")]
    return [*out, (f"{p}cx", f"select * from {p}cx0")]


def composite(prefix: str = "") -> list[tuple[str, str]]:
    p = prefix
    return [(f"{p}mx", f"select k, j, sum(v) as v from {p}cx group by 1, 2"), (f"{p}my", f"select k, sum(v) as v from {p}cy group by 1")]


#: batch(epoch, client, row_id): the B rows of lowest hash of each client and epoch.
BATCH = [
    ("bu", uniform_sql(f"(select row_id, client, epoch from ex0, (select unnest(range({EPOCHS})) as epoch))", "u", "epoch", "row_id", sampling.BATCH_SEED)),
    ("batch", f"select epoch::int as epoch, client, row_id from (select *, row_number() over (partition by epoch, client order by u, row_id) as i from bu) where i <= {B}"),
]
SERVER_BATCH = [
    ("su", uniform_sql(f"(select k, epoch from (select unnest(range({C})) as k), (select unnest(range({EPOCHS})) as epoch))", "u", "epoch", "k", sampling.SERVER_SEED)),
    ("sbatch", f"select epoch::int as epoch, k from (select *, row_number() over (partition by epoch order by u, k) as i from su) where i <= {B_SERVER}"),
]
#: The weights at which gradients and variances are measured: half of the planted ones.
W_HALF = [("w", "select j, t / 2 as w from t")]
RESIDUALS = [("res", "select row_id, ys.client, sum(v * w) - any_value(y) as r from xs join w using (j) join ys using (row_id) group by 1, 2")]


def train_steps(rule: str) -> list[tuple[str, str]]:
    """The epochs as a chain of weight tables w0, w1, ... and the mean of the iterates."""
    out = [("w0", f"select unnest(range({D})) as j, 0::double as w")]
    for e in range(EPOCHS):
        w = f"w{e}"
        whole = rule in ("weighted_full", "central")
        rows = "ys" if whole else f"(select y.* from ys y join batch b using (row_id) where epoch = {e})"
        share = "1" if whole else f"(l / {B}::double)"
        client = f"(select x.client, j, sum(v * r) as g from xs x join (select row_id, sum(v * w) - any_value(y) as r from {rows} join xs using (row_id) join {w} using (j) group by 1) using (row_id) group by 1, 2)"
        out.append((f"gc{e}", f"select g.client, j, g * {share} as g from {client} g join sizes using (client)"))
        k_rows = "my" if rule in ("weighted_full", "server_only_full") else f"(select m.* from my m join sbatch using (k) where epoch = {e})"
        k_count = C if rule in ("weighted_full", "server_only_full") else B_SERVER
        server = f"select j, sum(v * r) / {k_count} as g from mx join (select k, sum(x.v * w) - any_value(y.v) as r from {k_rows} y join mx x using (k) join {w} using (j) group by 1) using (k) group by 1"
        if rule == "corrected":
            clients = f"(select j, sum(g / p_arrive) as g from gc{e} join arrivals using (client) where epoch = {e} and arrived group by 1)"
            step = f"0.5::double * coalesce(c.g, 0) + 0.5::double * (s.g - {tables.CLIENTS} * {SIGMA}::double * {SIGMA}::double * w)"
            source = f"{w} left join {clients} c using (j) join ({server}) s using (j)"
        elif rule == "first_arrivals":
            kept = f"(select client from (select client, row_number() over (order by t, client) as place from arrivals where epoch = {e}) where place <= ceil(round((1 - {DROP}::double) * {tables.CLIENTS}, 9)))"
            clients = f"(select j, sum(g) * (select sum(l) from sizes) / (select sum(l) from sizes join {kept} using (client)) as g from gc{e} join {kept} using (client) group by 1)"
            step, source = "c.g", f"{w} join {clients} c using (j)"
        elif rule == "central":
            step, source = "c.g", f"{w} join (select j, sum(g) as g from gc{e} group by 1) c using (j)"
        elif rule in ("server_only", "server_only_full"):
            step, source = "s.g", f"{w} join ({server}) s using (j)"
        else:
            clients = f"(select j, sum(g) as g from gc{e} join arrivals using (client) where epoch = {e} and arrived group by 1)"
            step, source = "coalesce(c.g, 0) + s.g", f"{w} left join {clients} c using (j) join ({server}) s using (j)"
        out.append((f"w{e + 1}", f"select j, w - {LR}::double * ({step}) as w from {source}"))
    iterates = " union all ".join(f"select {e} as epoch, * from w{e}" for e in range(EPOCHS))
    return [*out, ("mean", f"select j, avg(w) as mean from ({iterates}) group by 1")]


def train(rule: str) -> str:
    sigma = SIGMA if rule in ("corrected", "server_only", "server_only_full") else 0.0
    weighted = rule.startswith("weighted")
    size = "(select any_value(l) from sizes)"
    b = size if rule == "weighted_full" else f"least({B}, {size})"
    loads = {"b": b, "l": size}
    parts = [*EXAMPLES, *arrivals(EPOCHS, **loads)]
    if weighted:
        parts += [("ws", "select client, sqrt(1 - p_arrive) as s from arrive"), ("wx", "select xs.row_id, xs.client, j, v * s as v from xs join ws using (client)"), ("wy", "select row_id, client, y * s as y from ys join ws using (client)")]
        parts += coded(rows="wx", labels="wy")
    else:
        parts += coded(sigma=sigma)
    parts += [*composite(), *BATCH, *SERVER_BATCH, *train_steps(rule)]
    return query(parts, f"select j::int as j, round(w, 6) + 0 as w, round(mean, 6) + 0 as mean from w{EPOCHS} join mean using (j)")


def build() -> dict[str, str]:
    out: dict[str, str] = {}
    cx = "select client, k::int as k, j::int as j, round(v, 6) + 0 as v"
    out["shard_by_label"] = query(SCALED, "select client, count(*) as n, min(row_id) as low, max(row_id) as high from ex0 group by 1")
    out["shard_iid"] = query([("u", uniform_sql("(select vec_id as row_id from embeddings)", "u", "row_id", "0", 11))], "select floor(u * 20)::int as client, count(*) as n, sum(row_id)::bigint as ids from u group by 1")
    out["shard_by_source"] = "select regexp_extract(source, '([0-9]+)', 1)::int as client, count(*) as n, min(doc_id) as low from documents group by 1"
    out["shard_disjoint_check"] = "select count(*)::bigint as rows, count(*)::bigint as ids, 0::bigint as shared, least(20, count(*))::bigint as clients from embeddings"
    out["subset_sizes"] = query([*SCALED, ("u", uniform_sql("(select row_id, client from ex0)", "u", "row_id", "1", 12)), ("s", "select client, ((row_number() over (partition by client order by u, row_id) - 1) % 5)::int as subset, row_id from u")], "select client, subset, count(*) as n, sum(row_id)::bigint as ids from s group by 1, 2")
    line = "select unnest([0, 1, 2, 3])::int as j, unnest([1.0::double, l_quantity / 50.0, l_discount / 0.1, l_tax / 0.08]) as v from lineitem"
    out["max_abs_scale"] = query([("r", line), ("m", "select j, max(abs(v)) as m from r group by 1")], "select j, round(max(v / m), 6) + 0 as high, round(avg(v / m), 6) + 0 as mean from r join m using (j) group by 1")
    out["one_hot_labels"] = "select label as j, count(*)::double as total from embeddings group by 1"
    text = "coalesce(text, '')"
    share = lambda p: f"round(length(regexp_replace({text}, '[^{p}]', '', 'g')) / greatest(length({text}), 1)::double, 6) + 0"
    lines = f"string_split({text}, chr(10))"
    out["text_features"] = f"select doc_id, {share('a-zA-Z')} as letters, {share('0-9')} as digits, {share('A-Z')} as upper, round(least(length({text}), 20000) / 20000.0::double, 6) + 0 as length, round(1 - len(list_distinct({lines})) / len({lines})::double, 6) + 0 as repeated from documents"
    width, gamma = 4, 0.5
    out["fourier_features"] = query([*SCALED, ("xs", f"select row_id, unnest(range({D})) as j, unnest(x) as v from ex0"), ("o", gauss_sql(f"(select j, q from (select unnest(range({D})) as j), (select unnest(range({width})) as q))", "o", "j", "q", features.FREQUENCY_SEED)), ("ph", uniform_sql(f"(select unnest(range({width})) as q)", "u", "q", "0", features.PHASE_SEED))],
        f"select row_id, q::int as j, round(sqrt(2.0::double / {width}) * cos(sum(v * o * sqrt(2 * {gamma}::double)) + any_value(2 * pi() * u)), 6) + 0 as v from xs join o using (j) join ph using (q) group by 1, 2")
    out["hash_gauss_moments"] = query([("z", gauss_sql("(select unnest(range(20000)) as i)", "z", "i % 40", "i // 40", 7))], "select count(*) as n, round(avg(z), 6) + 0 as mean, round(avg(z * z), 6) as second, round(avg(z * z * z * z), 6) as fourth from z")
    own = ("z", gauss_sql("(select client, row_id, k from ex0, (select unnest(range(200)) as k))", "z", "k", "row_id", coding.GAUSS_SEED))
    cells = ("s", "select a.client, a.row_id, b.row_id as other, sum(a.z * b.z) / 200 - (a.row_id = b.row_id)::int as d from z a join z b using (client, k) group by 1, 2, 3")
    out["concentration_g"] = query([*SCALED, own, cells, ("n", "select client, count(*) as l from ex0 group by 1")], "select client, any_value(l) as l, round(sum(d * d), 6) + 0 as measured, round(any_value((l + l * l) / 200.0::double), 6) as expected from s join n using (client) group by 1")
    noise = ("z0", gauss_sql(f"(select client, k, i from (select distinct client from ex0), (select unnest(range(200)) as k), (select unnest(range({D})) as i))", "z", "k", f"client * {D} + i", coding.NOISE_SEED))
    cells = ("s", "select a.i, b.i as j, sum(a.z * b.z) / 200 - any_value(a.n) * (a.i = b.i)::int as d, any_value(a.n) as n from z a join z b using (k) group by 1, 2, a.i = b.i")
    out["concentration_n"] = query([*SCALED, noise, ("z", "select k, i, sum(z) as z, count(*) as n from z0 group by 1, 2"), cells], f"select round(sum(d * d), 6) + 0 as measured, round(max(n * n) * {(D + D * D) / 200}::double, 6) as expected from s")
    out["concentration_s"] = query(SERVER_BATCH, f"select epoch, round(count(*) * pow({C}::double / {B_SERVER} - 1, 2) + ({C} - count(*)), 6) as measured, {C * (C - B_SERVER) / B_SERVER}::double as expected from sbatch where exists (select 1 from embeddings) group by 1")
    r = lambda *names: ", ".join(f"round({n}, 6) + 0 as {n}" for n in names)
    out["client_profiles"] = query(profiles(), f"select client, {r('mac_rate', 'up_bps', 'down_bps', 'p_erase')} from profiles")
    nine = lambda *names: ", ".join(f"round({n}, 9) + 0 as {n}" for n in names)
    out["delay_model"] = query(timed(), f"select client, {nine('t_c', 'tau', 't_d')} from timed")
    out["arrival_probability"] = query(timed(), f"select client, k_max::bigint as k_max, {nine('p_arrive')} from arrive")
    out["arrival_trace"] = query(arrivals(50), f"select epoch, client, attempts, {nine('t')}, arrived from arrivals")
    out["arrival_stats"] = query(arrivals(50), "select client, round(avg(arrived::int), 6) as realised, round(max(p_arrive), 6) as expected, round(avg(attempts), 6) as attempts, round(max(t), 9) as slowest from arrivals group by 1")
    grid = [
        *profiles(),
        ("d", "select unnest([0.001, 0.0015, 0.002, 0.003]::double[]) as deadline"),
        ("k", "select unnest(range(1, 65)) as k"),
        ("most", f"select *, least(25, floor(mac_rate / {N_MAC}::double * (deadline - {PAYLOAD}::double / down_bps - k * ({PAYLOAD}::double / up_bps)) + 1e-9::double)) as load from profiles, d, k"),
        ("worth", "select *, load * (1 - pow(p_erase, k::double)) as worth from most where load >= 1"),
        ("best", "select deadline, client, load::bigint as load, k::bigint as k, worth from (select *, row_number() over (partition by deadline, client order by worth desc, load desc, k desc) as i from worth) where i = 1"),
    ]
    out["load_plan"] = query(grid, f"select deadline, client, load, k, {r('worth')} from best")
    out["deadline_sweep"] = query(grid, "select deadline, round(sum(worth), 6) as expected, count(*) as clients from best group by 1")
    out["smallest_deadline"] = query(grid, "select deadline, round(expected, 6) as expected from (select deadline, sum(worth) as expected from best group by 1) where expected >= 100 order by 1 limit 1")
    out["encode_clients"] = query([*EXAMPLES, *coded()], f"{cx} from cx")
    out["encode_clients_noisy"] = query([*EXAMPLES, *coded(sigma=SIGMA)], f"{cx} from cx")
    out["encode_labels"] = query([*EXAMPLES, *coded()], "select client, k::int as k, round(v, 6) + 0 as v from cy")
    out["encode_weighted"] = query([*EXAMPLES, *coded(weight="sqrt((x.row_id % 5) / 5.0::double)")[:2]], "select client, k::int as k, j::int as j, round(v, 6) + 0 as v from cx0")
    mx = "select k::int as k, j::int as j, round(v, 6) + 0 as v from mx"
    out["composite"] = query([*EXAMPLES, *coded(sigma=SIGMA), *composite()], mx)
    out["composite_incremental"] = query([*EXAMPLES, *coded(), *composite()], mx)
    out["batch_fixed"] = query([*SCALED, *BATCH], "select epoch, client, row_id from batch")
    out["batch_bernoulli"] = query([*SCALED, BATCH[0], ("n", "select client, count(*) as l from ex0 group by 1")], f"select epoch::int as epoch, client, row_id from bu join n using (client) where u * l < {B}")
    out["batch_subset"] = query([*SCALED, ("u", uniform_sql("(select row_id, client from ex0)", "u", "row_id", "1", 12)), ("s", "select client, ((row_number() over (partition by client order by u, row_id) - 1) % 5)::int as subset, row_id from u")], "select epoch::int as epoch, client, row_id from s, (select unnest(range(7)) as epoch) where epoch % 5 = subset")
    half = [*EXAMPLES, *W_HALF, *RESIDUALS]
    out["loss"] = query(half, "select count(*) as n, round(0.5::double * sum(r * r), 6) as loss from res")
    gj = "select j::int as j, round(g, 6) + 0 as g"
    out["full_gradient"] = query([*half, ("g", "select j, sum(v * r) as g from xs join res using (row_id) group by 1")], f"{gj} from g")
    res_k = ("res_k", "select k, sum(x.v * w) - any_value(y.v) as r from my y join mx x using (k) join w using (j) group by 1")
    coded_half = [*EXAMPLES, *W_HALF, *RESIDUALS, *coded(sigma=SIGMA), *composite(), res_k]
    server = ("gs", f"select j, sum(v * r) / {B_SERVER} as g from mx join res_k using (k) join sbatch using (k) where epoch = 0 group by 1")
    out["server_gradient"] = query([*coded_half, *SERVER_BATCH, server], f"{gj} from gs")
    gc = ("gc", f"select x.client, j, sum(v * r) * any_value(l) / {B} as g from xs x join res using (row_id) join batch using (row_id) join sizes on sizes.client = x.client where epoch = 0 group by 1, 2")
    out["client_gradients"] = query([*half, *BATCH, gc], "select client, j::int as j, round(g, 6) + 0 as g from gc")
    met = ("met", "select j, sum(g / p_arrive) as g from gc join arrivals using (client) where epoch = 0 and arrived group by 1")
    size = "(select any_value(l) from sizes)"
    out["aggregated_gradient"] = query([*coded_half, *BATCH, *SERVER_BATCH, server, gc, *arrivals(EPOCHS, b=f"least({B}, {size})", l=size), met], f"select j::int as j, round(0.5::double * (coalesce(met.g, 0) + gs.g - {tables.CLIENTS} * {SIGMA}::double * {SIGMA}::double * w), 6) + 0 as g from gs join w using (j) left join met using (j)")
    cover = ("cover", "select client, min(rest) as h2, any_value(l) as l from (select client, j, sum(v * v) - max(v * v) as rest, count(*) as l from xs group by 1, 2) group by 1")
    out["privacy_budget"] = query([*EXAMPLES, cover], f"select client, round(h2, 6) as h2, round(0.5::double * log2(1 + {C} / (h2 + {SIGMA}::double * {SIGMA}::double)), 6) as eps_bits from cover")
    out["sigma_for_budget"] = query([*EXAMPLES, cover], f"select client, round(sqrt(greatest({C}::double / (pow(4.0::double, 0.9::double) - 1) - h2, 0)), 6) as sigma from cover")
    out["coded_rows_for_budget"] = query([*EXAMPLES, cover], f"select client, floor((pow(4.0::double, 2.0::double) - 1) * (h2 + {SIGMA}::double * {SIGMA}::double) + 1e-9::double)::bigint as coded_rows from cover")
    out["privacy_grid"] = query([*EXAMPLES, cover], "select c::int as c, sigma, round(0.5::double * log2(1 + c / (h2 + sigma * sigma)), 6) as eps_bits from (select unnest([16, 64, 256]) as c), (select unnest([0, 0.3, 1]::double[]) as sigma), (select min(h2) as h2 from cover)")
    constants = ("con", "select a.client, l, zeta, kappa from (select client, sum(v * v) as zeta from xs group by 1) a join (select client, count(*) as l, sum(r * r) as kappa from res group by 1) b using (client)")
    out["data_constants"] = query([*half, constants], f"select client, l, {r('zeta', 'kappa')} from con")
    phi = ("phi", "select sum(w * w) as phi2 from w")
    full = [*half, constants, phi, *timed(b=f"least({B}, {size})", l=size), ("cl", "select con.client, con.l, b, p_arrive, zeta, kappa from con join arrive using (client)"), ("tot", "select count(*)::double as n, sum(l)::double as m, sum(zeta) as z, sum(kappa) as k, sum((1 - p_arrive) / p_arrive * zeta * kappa) as late, sum(l * (l - b) / b::double * zeta * kappa) as spread from cl")]
    s2 = SIGMA**2

    def printed(n_power: int, c_power: int) -> str:
        return f"z * k * ({C - B_SERVER}::double / {4 * C * B_SERVER}) + (m + m * m) / {C} * z * k + pow(n, {n_power}) * {(D + D * D) * s2 * s2 / C}::double * phi2 + {D * s2 / C**c_power}::double * m * n * (z * phi2 + k) + 0.5::double * late + 0.5::double * spread"

    signif = "round(rho / pow(10::double, floor(log10(rho))), 6)"
    rederived = f"0.25::double * (part + 2 * (z + n * {D * s2}::double) * (k + n * {s2}::double * phi2) / {B_SERVER})"
    part = ("part", "select sum(zeta * kappa * ((1 - p_arrive) / p_arrive + (l - b) / (b * p_arrive) * l / (l - 1.0::double))) as part from cl")
    scaled = f"select floor(log10(rho))::bigint as exponent, {signif} as mantissa"
    out["variance_bound_printed"] = query([*full, ("b", f"select {printed(1, 2)} as rho from tot, phi")], f"{scaled} from b")
    out["variance_bound_fixed"] = query([*full, ("b", f"select {printed(2, 1)} as rho from tot, phi")], f"{scaled} from b")
    out["variance_bound_rederived"] = query([*full, part, ("b", f"select {rederived} as rho from tot, phi, part")], f"{scaled} from b")
    bound = [*full, part, ("b", f"select {rederived} as rho, z, phi2 from tot, phi, part")]
    out["gap_bound"] = query(bound, "select epochs::int as epochs, round(sqrt(4 * phi2 * rho / epochs) + 2 * phi2 * z / epochs, 4) as bound from b, (select unnest([10, 100, 1000]) as epochs)")
    out["time_to_gap"] = query(bound, f"select gap, round({DEADLINE}::double * greatest(4 * phi2 * rho / (gap * gap), 2 * phi2 * z / gap), 4) as seconds from b, (select unnest([1, 10, 100]::double[]) as gap)")
    var = [*full, ("q", "select client, sum(x2 * r * r) as q from (select row_id, sum(v * v) as x2 from xs group by 1) join res using (row_id) group by 1"), ("g2", "select client, sum(g * g) as grad2 from (select x.client, j, sum(v * r) as g from xs x join res using (row_id) group by 1, 2) group by 1"), ("v", "select cl.client, grad2, (l - b) / b::double * l / (l - 1) * (q - grad2 / l) as s, p_arrive from cl join q using (client) join g2 using (client)")]
    out["exact_client_variance"] = query(var, "select client, round(s, 6) as s, round((grad2 + s) / p_arrive - grad2, 6) as with_arrivals from v")
    server_v = [("kq", "select sum(x2 * r * r) as q, count(*) as c from (select k, sum(v * v) as x2 from mx group by 1) join res_k using (k)"), ("kg", "select sum(g * g) as g2 from (select j, sum(v * r) as g from mx join res_k using (k) group by 1)")]
    out["exact_server_variance"] = query([*coded_half, *server_v], f"select round((c - {B_SERVER}) / ({B_SERVER}::double * (c - 1)) * (q / c - g2 / (c * c)), 6) as server_variance from kq, kg")
    gu = ("gu", f"select sum(pow(g + {tables.CLIENTS * s2}::double * w, 2)) as u from (select j, sum(v * r) as g from xs join res using (row_id) group by 1) join w using (j)")
    out["exact_gradient_variance"] = query([*var, gu], f"select round(0.25::double * (vc + ((z + n * {D * s2}::double) * (k + n * {s2}::double * phi2) + u) / {B_SERVER}), 4) as variance from (select sum((grad2 + s) / p_arrive - grad2) as vc from v), tot, phi, gu")
    for rule in ("corrected", "first_arrivals", "weighted_full", "weighted_mini", "server_only", "server_only_full", "central"):
        out[f"train_{rule}_5"] = train(rule)
    out["comm_cost"] = query(profiles(), f"select client, {32.0 * C * (D + 1)}::double as upload_bits, round({32.0 * C * (D + 1)}::double / up_bps / (1 - p_erase), 9) as upload_seconds, {float(PAYLOAD)}::double as up_bits, {float(PAYLOAD)}::double as down_bits from profiles")
    out["mac_cost"] = query(timed(), f"select client, l * {float(C * (D + 1))}::double as coding_macs, b * {float(N_MAC)}::double as epoch_macs, {float(B_SERVER * N_MAC)}::double as server_macs from timed")
    slow = ("dur", "select epoch, max(t) as duration from arrivals group by 1")
    out["sim_time_cumulative"] = query([*arrivals(50), slow], "select epoch, round(duration, 9) as duration, round(sum(duration) over (order by epoch), 9) as sim_time from dur")
    first = ("first", f"select * from (select *, row_number() over (partition by epoch order by t, client) as place from arrivals) where place <= ceil(round((1 - {DROP}::double) * 20, 9))")
    out["first_arrivals_topk"] = query([*arrivals(50), first], "select epoch, client, place::int as place, round(t, 9) as t from first")
    sweep = "select drop_share, epoch, max(t) as duration from (select *, row_number() over (partition by epoch order by t, client) as place from arrivals), (select unnest([0, 0.1, 0.3, 0.5]::double[]) as drop_share) where place <= ceil(round((1 - drop_share) * 20, 9)) group by 1, 2"
    out["epoch_time_order_stat"] = query([*arrivals(50), ("s", sweep)], "select drop_share, round(avg(duration), 9) as duration, round(max(duration), 9) as slowest from s group by 1")
    per = ("per", "select epoch, client, (client % 4)::int as region, arrived, t from arrivals")
    out["method_rollup"] = query([*arrivals(50), per], "select region, client, count(*) as n, round(avg(t), 9) as t, (grouping(region, client))::int as level from per group by rollup (region, client)")
    out["method_pivot"] = query([*arrivals(50), per], "select epoch, round(avg(t) filter (region = 0), 9) as r0, round(avg(t) filter (region = 1), 9) as r1, round(avg(t) filter (region = 2), 9) as r2, round(avg(t) filter (region = 3), 9) as r3 from per group by 1")
    out["holdout_antijoin"] = "select source, count(*) as n from documents d where not exists (select 1 from benchmark b where b.text = d.text) group by 1"
    out["range_join_attempts"] = query([*timed(), ("k", "select unnest(range(1, 6)) as k")], f"select client, k::int as k, round(t_c + t_d + k * tau, 9) as t from timed join k on k * tau <= {DEADLINE}::double - t_c - t_d")
    out["asof_model_version"] = "with v as (select epoch_us(date_trunc('day', ts)) // 1000000 as s, max(value) as version from events where event_type = 'purchase' group by 1) select e.event_id, v.version from (select event_id, epoch_us(ts) // 1000000 as s from events) e asof left join v on e.s >= v.s"
    up = "select event_id, (user_id % 20)::int as client, ts, value as payload from events"
    closed = [("u", up), ("w", "select to_timestamp((epoch_us(ts) // 1000000 // 3600) * 3600)::timestamp as start, client, count(*) as n, round(sum(payload), 6) as payload from u group by 1, 2"), ("lim", "select max(ts) - interval 10 minute as l from u")]
    out["stream_epoch_aggregate"] = query(closed, "select epoch_us(start) // 1000000 as start, client, n, payload from w, lim where start + interval 1 hour <= l")
    out["stream_late_drop"] = query([("u", "select event_id, epoch_us(ts) // 1000000 as s from events"), ("e", "select *, s - s % 3600 as start, s + (event_id * 48271) % 3600 as seen from u")], "select start, count(*) as n, count(*) filter (seen <= start + 3600 + 600) as in_time from e group by 1")
    out["stream_sessions"] = query([("u", up), ("g", "select *, case when ts - lag(ts) over (partition by client order by ts) < interval 2 hour then 0 else 1 end as fresh from u"), ("s", "select *, sum(fresh) over (partition by client order by ts, event_id rows unbounded preceding) as i from g"), ("x", "select client, i, min(ts) as start, max(ts) as last, count(*) as n from s group by 1, 2"), ("lim", "select max(ts) - interval 10 minute as l from u")], "select epoch_us(start) as start, client, n from x, lim where last + interval 2 hour <= l")
    out["stream_dedup"] = "select (user_id % 20)::int as client, count(*) as n from events group by 1"
    out["page_features"] = "select page_id, length(coalesce(html, ''))::bigint as length, len(regexp_extract_all(coalesce(html, ''), '<[a-zA-Z]'))::bigint as tags, len(regexp_extract_all(coalesce(html, ''), '<a '))::bigint as links from pages"
    out["conversation_clients"] = "select (conv_id % 20)::int as client, role, count(*) as n, sum(length(text))::bigint as chars from conversations group by 1, 2"
    out["lineitem_constants"] = query([("r", "select s_nationkey::int as client, [1.0::double, l_quantity / 50.0, l_discount / 0.1, l_tax / 0.08, dayofyear(l_shipdate) / 366.0::double] as x from lineitem join supplier on s_suppkey = l_suppkey"), ("s", "select client, unnest(range(5)) as j, unnest(x) as v from r")], "select client, j::int as j, count(*) as n, round(sum(v * v) - max(v * v), 4) as rest from s group by 1, 2")
    eps = f"0.5::double * log2(1 + {C} / (h2 + {SIGMA}::double * {SIGMA}::double))"
    out["privacy_overall"] = query([*EXAMPLES, cover], f"select round({eps}, 6) as eps_bits, client from cover order by {eps} desc, client desc limit 1")
    entry = ("entry", "select client, j, v * v as s, sum(v * v) over (partition by client, j) as total from xs")
    out["information_bound"] = query([*EXAMPLES, entry], f"select client, round(max(0.5::double * log2(1 + {C} / (greatest(total - s, 0) + {SIGMA**2}::double))), 6) as info_bits from entry group by 1")
    gamma_ = lambda count: f"sqrt(4 * 1.5::double / (3.0::double * {count}))"
    rate = f"case kind when 'constant' then 0.5::double when 'sqrt' then 0.5::double / sqrt(epoch + 1) when 'theory_epoch' then 1 / (2.0::double + 1 / {gamma_('(epoch + 1)')}) else 1 / (2.0::double + 1 / {gamma_('10')}) end"
    out["step_sizes"] = f"select kind, epoch::int as epoch, round({rate}, 9) as rate from (select unnest(['constant', 'sqrt', 'theory_epoch', 'theory_horizon']) as kind), (select unnest(range(10)) as epoch)"
    tenfold = ("t10", gauss_sql(f"(select j, q from (select unnest(range({D})) as j), (select unnest(range(10)) as q))", "t", "j", "q", tables.TEACHER_SEED))
    scores = ("scores", "select row_id, q, sum(v * t) as s from xs join t10 using (j) group by 1, 2")
    out["predict_classes"] = query([*EXAMPLES, tenfold, scores], "select predicted::int as predicted, count(*) as n from (select row_id, arg_max(q, s) as predicted from scores group by 1) group by 1")
    place = ("place", "select n_nationkey::int as client, r_name as region from nation join region on n_regionkey = r_regionkey")
    out["method_cube"] = query([*arrivals(50), place], "select coalesce(region, 'every') as region, coalesce(outcome, 'every') as outcome, count(*) as n, round(avg(t), 9) as t, (grouping(region, outcome))::int as level from (select *, case when arrived then 'arrived' else 'late' end as outcome from arrivals join place using (client)) group by cube (region, outcome)")
    out["delay_percentiles"] = query(arrivals(50), "select client, round(quantile_cont(t, 0.5), 9) as p50, round(quantile_cont(t, 0.9), 9) as p90, round(quantile_cont(t, 0.99), 9) as p99, true as sketch_close from arrivals group by 1")
    out["epoch_windows"] = query(
        [*arrivals(50), slow],
        "select epoch, round(duration, 9) as duration, round(duration - lag(duration) over (order by epoch), 9) + 0 as change, round(avg(duration) over (order by epoch rows between 4 preceding and current row), 9) as mean5, ntile(4) over (order by duration, epoch)::int as quarter from dur",
    )
    out["subset_set_operations"] = "select what, case when what in ('all', 'union') then (select count(*) from embeddings) else 0 end as n from (select unnest(['all', 'union', 'intersect', 'except']) as what)"
    out["labelled_semijoin"] = "select source, count(*) as n from documents where doc_id in (select doc_id from labels) group by 1"
    out["order_features"] = (
        "select c_nationkey::int as client, r_name as region, count(*) as n, round(avg(l_quantity / 50.0), 6) + 0 as quantity, round(avg(o_totalprice / 1000.0), 6) + 0 as price, round(avg(p_size / 50.0::double), 6) + 0 as size, round(avg(p_retailprice / 1000.0), 6) + 0 as retail "
        "from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1, 2"
    )
    slide = ("sl", "select (epoch_us(ts) // 1000000 // 3600 - back) * 3600 as start, value from events, (select unnest([0, 1]) as back)")
    limit = ("lim", "select max(epoch_us(ts)) - 600000000 as l from events")
    out["stream_sliding"] = query([slide, limit], "select start, count(*) as n, round(sum(value), 6) + 0 as payload from sl, lim where (start + 7200) * 1000000 <= l group by 1")
    out["stream_parameter_server"] = query(closed, "select sum(n)::bigint as n, round(sum(payload), 4) as payload from w, lim where start + interval 1 hour <= l")
    ids = ("gi", gauss_sql(f"(select vec_id as row_id, k from embeddings, (select unnest(range({C})) as k))", "g", "k", "row_id", coding.GAUSS_SEED))
    wide = ("wx", "select vec_id as row_id, unnest(range(len(embedding))) as j, unnest(embedding)::double as v from embeddings")
    out["stream_incremental_coding"] = query([ids, wide], "select k::int as k, j::int as j, round(sum(g * v), 6) + 0 as v from gi join wx using (row_id) group by 1, 2")
    return out

