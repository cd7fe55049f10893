"""DuckDB SQL of the mechanism for the oracle: recursive over triggers, noise from SHA-256."""

from __future__ import annotations

from ..functions import calibrate, tree
from ..functions.noise import normal_sql
from ..sources import synth
from ..spec import StreamSpec

LINES = "SELECT o_custkey AS unit, CAST({key} AS VARCHAR) AS key, l_orderkey || '-' || l_linenumber || '-' || l_partkey || '-' || l_suppkey AS rid, l_quantity, l_extendedprice FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
FORUM = "SELECT o_custkey AS unit, p_brand || '/' || p_type AS key, l_orderkey || '-' || l_linenumber || '-' || l_partkey || '-' || l_suppkey AS rid, l_quantity, l_extendedprice FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey"


def lines(key: str = "l_suppkey") -> str:
    return LINES.format(key=key)


def trigger(rid: str, t: int) -> str:
    return f"(('0x' || substr(sha256(CAST({rid} AS VARCHAR)), 1, 8))::BIGINT % {t} + 1)::INTEGER"


def measure(m) -> str:
    value = "1.0::DOUBLE" if m.column is None else f"greatest(-{float(m.clamp)}::DOUBLE, least({float(m.clamp)}::DOUBLE, {m.column}::DOUBLE))"
    return f"pow({value}, 2)" if m.square else value


def delta_ctes(rec: str, spec: StreamSpec) -> str:
    """rec, adm (bounded, with unit_rank), delta (key, trig, n, users, s0...); for round_distinct also
    fresh (key, trig, b, users): the users of a trigger in a round that began after trigger b."""
    t = spec.timing.triggers
    if spec.gate.count_mode == "pair_once":
        users, mark = "sum(nw)", "(row_number() OVER (PARTITION BY key, unit ORDER BY trig, rid) = 1)::BIGINT"
    else:
        users, mark = "count(DISTINCT unit)", "0::BIGINT"
    sums = ", ".join(f"sum({measure(m)}) AS s{j}" for j, m in enumerate(spec.measures))
    fresh = ""
    if spec.gate.count_mode == "round_distinct":
        fresh = f""",
seen AS (SELECT key, trig, coalesce(lag(trig) OVER (PARTITION BY key, unit ORDER BY trig), 0) AS prev FROM (SELECT DISTINCT key, unit, trig FROM adm)),
fresh AS (SELECT key, trig, b, count(*) AS users FROM seen JOIN (SELECT unnest(range(0, {t})) AS b) ON prev <= b AND b < trig GROUP BY ALL)"""
    return f"""rec AS ({rec}),
trg AS (SELECT *, {trigger("rid", t)} AS trig FROM rec),
ranked AS (SELECT *, row_number() OVER (PARTITION BY unit ORDER BY trig, rid) AS rk FROM trg),
adm AS (SELECT *, {mark} AS nw FROM ranked WHERE rk <= {spec.bound}),
delta AS (SELECT key, trig, count(*) AS n, {users}::BIGINT AS users, {sums} FROM adm GROUP BY key, trig){fresh}"""


def noise_cte(name: str, keys: str, secret: str, stream: str, rounds: int, t: int, kind: str) -> str:
    """name(key, r, i, z): standard prefix noise of every key of `keys`, round and trigger.

    One CTE a level: a block's estimate comes from its own node and the two estimates below it.
    """
    r = f"(SELECT unnest(range(1, {rounds + 1})) AS r)" if rounds else "(SELECT 0 AS r)"
    z = lambda level: normal_sql(secret, stream, "key", "r", str(level), "idx")
    grid = lambda level: f"(SELECT DISTINCT key FROM {keys}), {r}, (SELECT unnest(range(0, {t >> level})) AS idx)"
    out = [f"{name}_0 AS MATERIALIZED (SELECT key, r, idx, {z(0)} AS e FROM {grid(0)})"]
    if kind == "leaf":
        return f"{out[0]},\n{name} AS MATERIALIZED (SELECT key, r, (idx + 1) AS i, sum(e) OVER (PARTITION BY key, r ORDER BY idx) AS z FROM {name}_0)"
    levels = range(1, t.bit_length())
    for b in levels:
        own = f"(SELECT key, r, idx, {z(b)} AS z FROM {grid(b)})"
        if kind == "plain":
            out.append(f"{name}_{b} AS MATERIALIZED (SELECT key, r, idx, z AS e FROM {own})")
            continue
        w = f"{tree.block_variance(b)!r}::DOUBLE"
        kids = f"(SELECT key, r, idx // 2 AS idx, sum(e) AS e FROM {name}_{b - 1} GROUP BY key, r, idx // 2)"
        out.append(f"{name}_{b} AS MATERIALIZED (SELECT o.key, o.r, o.idx, {w} * o.z + (1.0::DOUBLE - {w}) * k.e AS e FROM {own} o JOIN {kids} k ON k.key = o.key AND k.r = o.r AND k.idx = o.idx)")
    blocks = " UNION ALL ".join(f"SELECT key, r, e, i FROM {name}_{b}, (SELECT unnest(range(1, {t + 1})) AS i) WHERE ((i >> {b}) & 1) = 1 AND idx = (i >> {b}) - 1" for b in (0, *levels))
    return ",\n".join(out) + f",\n{name} AS MATERIALIZED (SELECT key, r, i, sum(e) AS z FROM ({blocks}) GROUP BY key, r, i)"


def gate_ctes(rec: str, spec: StreamSpec, rounds: int | None = None) -> str:
    """rounds: the most rounds that any key is expected to have (all triggers by default); a key with more would lack noise and so differ."""
    p, g, t = calibrate.plan(spec), spec.gate, spec.timing.triggers
    taus = ", ".join(f"({i + 1}, {x!r}::DOUBLE)" for i, x in enumerate(p.taus))
    m = range(len(spec.measures))
    over = f"u1 >= {g.mu}" if g.pre_inclusive else f"u1 > {g.mu}"
    open_ = "n1 > 0" if g.restart else "u1 > 0"
    keep = "0" if g.restart else "u1"
    nxt = "r + 1" if g.restart else "r"
    begin = "CASE WHEN pass THEN i ELSE b0 END" if g.restart else "b0"
    values = "".join(f",\n" + noise_cte(f"vn{j}", "live", spec.secret, f"value-{x.name}", 0, t, g.variance) for j, x in enumerate(spec.measures))
    rounds = (rounds or t) if g.restart else 1
    distinct = g.count_mode == "round_distinct"
    users = "coalesce(f.users, 0)" if distinct else "coalesce(d.users, 0)"
    fresh = "LEFT JOIN fresh f ON f.key = st.key AND f.trig = st.i + 1 AND f.b = st.b0" if distinct else ""
    live = f"HAVING sum(users) {'>=' if g.pre_inclusive else '>'} {g.mu}" if g.count_mode == "pair_once" else ""
    return f"""{delta_ctes(rec, spec)},
live AS (SELECT key FROM delta GROUP BY key {live}),
{noise_cte("gn", "live", spec.secret, "gate", rounds, t, g.variance)}{values},
taus(i, tau) AS (VALUES {taus}),
st AS (
  SELECT key, 0 AS i, 1 AS r, 0::BIGINT AS u, 0::BIGINT AS n{"".join(f", 0.0::DOUBLE AS b{j}_, 0.0::DOUBLE AS rel{j}" for j in m)}, false AS pass, 0.0::DOUBLE AS q, '' AS cause, 0 AS r0, 0 AS b0, false AS tested FROM live
  UNION ALL
  SELECT key, i, CASE WHEN pass THEN {nxt} ELSE r END, CASE WHEN pass THEN {keep} ELSE u1 END, CASE WHEN pass THEN 0 ELSE n1 END
         {"".join(f", CASE WHEN pass THEN 0.0 ELSE b{j}_ END, rel{j} + CASE WHEN pass THEN b{j}_ ELSE 0.0 END" for j in m)}, pass, q, cause, r, {begin}, tested
  FROM (
    SELECT *, ({over}) AND ({open_}) AS tested, ({over}) AND ({open_}) AND q > {g.mu} + tau AS pass FROM (
      SELECT st.key, st.i + 1 AS i, st.r, st.b0, st.u + {users} AS u1, st.n + coalesce(d.n, 0) AS n1
             {"".join(f", st.b{j}_ + coalesce(d.s{j}, 0.0) AS b{j}_, st.rel{j} AS rel{j}" for j in m)},
             st.u + {users} + {p.sigma!r}::DOUBLE * gn.z AS q, taus.tau,
             CASE WHEN d.key IS NULL THEN 'silent' ELSE 'arrival' END AS cause
      FROM st JOIN taus ON taus.i = st.i + 1 JOIN gn ON gn.key = st.key AND gn.r = st.r AND gn.i = st.i + 1
      LEFT JOIN delta d ON d.key = st.key AND d.trig = st.i + 1 {fresh}
    )
  )
),
releases AS (
  SELECT st.key, st.i AS trigger_idx, st.r0 AS round, st.cause, st.q AS users_hat{"".join(f", st.rel{j} + {p.value_sigma[j]!r}::DOUBLE * vn{j}.z AS {x.name}_hat" for j, x in enumerate(spec.measures))}
  FROM st {" ".join(f"JOIN vn{j} ON vn{j}.key = st.key AND vn{j}.i = st.i" for j in m)} WHERE st.pass
)"""


def releases(rec: str, spec: StreamSpec, select: str | None = None, rounds: int | None = None) -> str:
    hats = ", ".join(f"round({m.name}_hat, 6) AS {m.name}_hat" for m in spec.measures)
    select = select if select is not None else f"SELECT key, trigger_idx, round, cause, round(users_hat, 6) AS users_hat, {hats} FROM releases"
    return f"WITH RECURSIVE {gate_ctes(rec, spec, rounds)}\n{select}"


def utility(truth: str, est: str, value: str) -> str:
    """One row of measures from CTE names truth(key, truth) and est(key, value)."""
    return f"""SELECT count(e.{value})::BIGINT AS keys, round(max(abs(coalesce(e.{value}, 0) - t.truth)), 6) AS linf, round(sum(abs(coalesce(e.{value}, 0) - t.truth)), 6) AS l1,
       round(sqrt(sum(pow(coalesce(e.{value}, 0) - t.truth, 2))), 6) AS l2,
       round(coalesce(sum(t.truth) FILTER (WHERE e.{value} IS NOT NULL), 0) / sum(t.truth), 6) AS retained_mass,
       round(coalesce(sum(abs(e.{value} - t.truth)) FILTER (WHERE e.{value} IS NOT NULL), 0) / nullif(coalesce(sum(t.truth) FILTER (WHERE e.{value} IS NOT NULL), 0), 0), 6) AS rel_error
FROM {truth} t LEFT JOIN {est} e ON e.key = t.key"""


def once(stream: str, secret: str, run: str) -> str:
    return normal_sql(secret, stream, "key", run, "0", "0")


def forecasts(rec: str, spec: StreamSpec, select: str, rounds: int | None = None) -> str:
    """arrivals (key, i, next, waste, predicted): after each trigger with data the first later one at which the buffer would pass."""
    p, mu, t = calibrate.plan(spec), spec.gate.mu, spec.timing.triggers
    return f"""WITH RECURSIVE {gate_ctes(rec, spec, rounds)},
ahead AS (SELECT st.key, st.i, min(gn.i) AS predicted FROM st JOIN gn ON gn.key = st.key AND gn.r = st.r AND gn.i > st.i JOIN taus ON taus.i = gn.i
          WHERE st.cause = 'arrival' AND st.n > 0 AND st.u > {mu} AND st.u + {p.sigma!r}::DOUBLE * gn.z > {mu} + tau GROUP BY st.key, st.i),
arrivals AS (SELECT st.key, st.i, lead(st.i) OVER (PARTITION BY st.key ORDER BY st.i) AS next, ahead.predicted,
                    CASE WHEN st.n > 0 AND st.u > {mu} THEN coalesce(ahead.predicted, {t}) - st.i ELSE 0 END AS waste
             FROM st LEFT JOIN ahead ON ahead.key = st.key AND ahead.i = st.i WHERE st.cause = 'arrival')
{select}"""


def loads(rec: str, spec: StreamSpec, rounds: int | None = None) -> str:
    t = spec.timing.triggers
    return forecasts(rec, spec, f"""SELECT (SELECT count(DISTINCT key) FROM arrivals) AS keys, (SELECT count(*) FROM st WHERE tested)::BIGINT AS tests, (SELECT sum(waste) FROM arrivals)::BIGINT AS wasted,
(SELECT sum({t} - first + 1) FROM (SELECT min(i) AS first FROM arrivals GROUP BY key))::BIGINT AS loads_naive,
(SELECT count(*) + count(*) FILTER (WHERE predicted < coalesce(next, {t + 1})) FROM arrivals)::BIGINT AS loads_forecast""", rounds)


def uniform(seed: int, name: str, value: str) -> str:
    return f"((('0x' || substr(sha256('{seed}|{name}|' || {value}), 1, 13))::BIGINT::DOUBLE + 0.5::DOUBLE) / {float(1 << 52)}::DOUBLE)"


def zipf(users: int, keys: int) -> str:
    """The generator's records: unit, key, rid."""
    law = synth.Law(keys)
    cuts = f"{law.cuts!r}"
    per = "[" + ", ".join(f"{x!r}::DOUBLE" for x in law.per_user) + "]"
    at = f"v * {law.grid}::DOUBLE"
    return f"""SELECT unit, (lo + floor(({at} - slot) * (hi - lo + 1))::BIGINT)::VARCHAR AS key, rid FROM (
SELECT *, cuts[slot + 1] AS lo, cuts[slot + 2] AS hi FROM (SELECT *, floor({at})::INTEGER AS slot, {cuts} AS cuts FROM (
SELECT unit, rid, {uniform(42, "key", "rid")} AS v FROM (
SELECT unit, unit || '-' || i AS rid FROM (SELECT unit, unnest(range(1, 2 + len(list_filter({per}, lambda c: c < u)))) AS i FROM (
SELECT range AS unit, {uniform(42, "records", "range")} AS u FROM range({users})))))))"""


UNIFORM_KEYS = f"SELECT o_custkey AS unit, floor({uniform(42, 'key', 'o_orderkey')} * (SELECT count(*) FROM customer))::BIGINT::VARCHAR AS key, o_orderkey::VARCHAR AS rid FROM orders"


#: Renyi orders at which SQL looks for the best conversion, and terms of the continued fraction of the normal tail.
ORDERS, TERMS = 4000, 80


def rho_sql(rows: str) -> str:
    """(name, rho) of rows (name, eps, delta): largest rho whose zCDP implies (eps, delta), by bisection over a grid of orders."""
    order = f"(1 + exp(-9.2 + k * 18.4 / {ORDERS}))"
    worst = f"list_min([({order} - 1) * ({order} * mid - eps) + {order} * ln(1 - 1 / {order}) - ln({order} - 1) for k in range({ORDERS})])"
    return f"""SELECT name, lo AS rho FROM (WITH RECURSIVE b AS (SELECT name, eps, ln(delta) AS ld, 0.0::DOUBLE AS lo, eps AS hi, 0 AS n FROM ({rows})
UNION ALL SELECT name, eps, ld, CASE WHEN ok THEN mid ELSE lo END, CASE WHEN ok THEN hi ELSE mid END, n + 1 FROM (SELECT *, {worst} <= ld AS ok FROM (SELECT *, (lo + hi) / 2 AS mid FROM b WHERE n < 45))) SELECT * FROM b WHERE n = 45)"""


def quantile_sql(rows: str) -> str:
    """(name, z) of rows (name, p): P(N(0, 1) > z) = p for p below 0.001, the tail as a continued fraction."""
    tail = f"(exp(-mid * mid / 2) / sqrt(2 * pi()) / list_reduce([mid::DOUBLE] || [({TERMS} - k)::DOUBLE for k in range({TERMS})], lambda a, k: mid + k / a))"
    return f"""SELECT name, lo AS z FROM (WITH RECURSIVE q AS (SELECT name, p, 3.0::DOUBLE AS lo, 40.0::DOUBLE AS hi, 0 AS n FROM ({rows})
UNION ALL SELECT name, p, CASE WHEN over THEN mid ELSE lo END, CASE WHEN over THEN hi ELSE mid END, n + 1 FROM (SELECT *, {tail} > p AS over FROM (SELECT *, (lo + hi) / 2 AS mid FROM q WHERE n < 50))) SELECT * FROM q WHERE n = 50)"""
