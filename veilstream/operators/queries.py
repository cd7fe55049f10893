"""Registered queries of the private stream engine and their oracle SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import accounting, calibrate, tree
from ..functions.noise import normal_column, normal_sql
from ..plans import replay
from ..shared import materialize
from ..sources import synth, tables
from ..spec import TEST_SECRET, Budget, GateConfig, Measure, StreamSpec, Timing
from . import aggregate, baselines, bounding, metrics, oneshot, oracle, timing, tuning

COUNT = (Measure("count"),)
#: Presets that keep keys alive on the small tables.
SUPPLIER = StreamSpec(secret=TEST_SECRET, bound=17, timing=Timing(8))
FLAGSHIP = StreamSpec(secret=TEST_SECRET, bound=10, timing=Timing(8))
FORUM = StreamSpec(secret=TEST_SECRET, bound=17, timing=Timing(16))
SUMS = replace(SUPPLIER, measures=(Measure("qty", "l_quantity", 50.0),))
MULTI = replace(SUPPLIER, measures=(Measure("count"), Measure("qty", "l_quantity", 30.0)))
SPARSE = StreamSpec(secret=TEST_SECRET, bound=17, timing=Timing(32))
#: Few, busy keys: the one-shot baselines still show some of them.
BUSY = "l_suppkey % 20"
VIEWS = StreamSpec(secret=TEST_SECRET, bound=1, timing=Timing(8), budget=Budget(eps=11.0, delta=2e-9, gate_eps_frac=10 / 11, gate_delta_frac=0.5))
TERMS = StreamSpec(secret=TEST_SECRET, bound=1, timing=Timing(16), budget=Budget(eps=4.0, delta=1.5e-10), gate=GateConfig(mu=50, restart=False))

Q: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def query(sql: str | None = None):
    def add(f):
        Q[f.__name__] = (f, sql)
        return f

    return add


def rounded(df: DataFrame, *names: str) -> DataFrame:
    names = names or tuple(f.name for f in df.schema.fields if f.dataType.typeName() == "double")
    return df.withColumns({n: F.round(F.col(n), 6) for n in names})


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Private counts a supplier, released over eight triggers."""
    return replay.run(tables.line_records(spark, sf_dir), FLAGSHIP)


# --- non-private streams and truth -------------------------------------------------------


@query("SELECT event_type AS key, CAST(ts AS DATE) AS day, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY ALL")
def plain_daily_hist(spark, sf):
    ev = tables.event_records(spark, sf)
    return ev.groupBy("key", "day").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("unit").alias("users"))


@query(f"WITH d AS (SELECT key, {oracle.trigger('rid', 8)} AS trigger_idx, count(*) AS n FROM ({oracle.lines()}) GROUP BY ALL) SELECT key, trigger_idx, sum(n) OVER (PARTITION BY key ORDER BY trigger_idx)::BIGINT AS total FROM d")
def plain_stream_updates(spark, sf):
    return aggregate.plain_stream_hist(timing.assign_triggers(tables.line_records(spark, sf), 8))


@query("SELECT event_id AS record_id, CAST(date_trunc('day', ts) AS DATE) AS window_day, least(24, floor(date_part('epoch', ts - date_trunc('day', ts)) * 24 / 86400)::INTEGER + 1)::INTEGER AS trigger_idx FROM events")
def assign_windows_triggers(spark, sf):
    ev = tables.event_records(spark, sf).withColumn("event_ts", F.col("event_ts").cast("timestamp")).withColumn("arrival_ts", F.col("event_ts"))
    out = timing.assign_triggers(timing.assign_windows(ev), 24, "arrival")
    return out.select("record_id", F.to_date("window_start").alias("window_day"), "trigger_idx")


DELAY_SQL = "(('0x' || substr(sha256(CAST(event_id AS VARCHAR)), 1, 8))::BIGINT % 7200)"


@query(f"SELECT event_id AS record_id FROM events WHERE date_part('epoch', ts - date_trunc('day', ts)) + {DELAY_SQL} < 86400 + 1800")
def late_drop(spark, sf):
    ev = tables.event_records(spark, sf).withColumn("event_ts", F.col("event_ts").cast("timestamp"))
    delay = F.conv(F.substring(F.sha2(F.col("record_id").cast("string"), 256), 1, 8), 16, 10).cast("bigint") % 7200
    ev = timing.assign_windows(ev).withColumn("arrival_ts", F.timestamp_micros(F.unix_micros("event_ts") + delay * 1_000_000))
    return timing.drop_late(ev, 86_400, 1800).select("record_id")


@query(f"SELECT trigger_idx, count(*) AS n FROM (SELECT {oracle.trigger('rid', 100)} AS trigger_idx FROM ({oracle.lines()})) GROUP BY 1")
def shuffled_triggers(spark, sf):
    return timing.assign_triggers(tables.line_records(spark, sf), 100).groupBy("trigger_idx").agg(F.count(F.lit(1)).alias("n"))


# --- bounding ----------------------------------------------------------------------------


@query(f"WITH {oracle.delta_ctes(oracle.lines(), SUPPLIER)} SELECT unit, key, rid AS record_id, trig AS trigger_idx, rk AS unit_rank FROM adm")
def bound_first_c(spark, sf):
    return replay.admitted(tables.line_records(spark, sf), SUPPLIER).select("unit", "key", "record_id", "trigger_idx", "unit_rank")


@query(f"SELECT user_id AS unit, day, event_id AS record_id FROM (SELECT user_id, CAST(ts AS DATE) AS day, event_id, row_number() OVER (PARTITION BY user_id, CAST(ts AS DATE) ORDER BY {oracle.trigger('event_id', 8)}, event_id) AS rk FROM events) WHERE rk <= 1")
def bound_per_user_day(spark, sf):
    ev = timing.assign_triggers(tables.event_records(spark, sf), 8)
    return bounding.bound_records(ev, 1, ("unit", "day")).select("unit", "day", "record_id")


@query(
    f"""WITH trg AS (SELECT *, {oracle.trigger("rid", 8)} AS trig FROM ({oracle.lines()})),
f AS (SELECT unit, key, min({{'t': trig, 'r': rid}}) AS first, sum(l_quantity) AS total FROM trg GROUP BY unit, key),
r AS (SELECT *, row_number() OVER (PARTITION BY unit ORDER BY first.t, first.r) AS k FROM f)
SELECT unit, key, greatest(-100.0, least(100.0, total)) AS total FROM r WHERE k <= 5"""
)
def bound_keys_values(spark, sf):
    return bounding.bound_keys_and_values(timing.assign_triggers(tables.line_records(spark, sf), 8), "l_quantity", 5, 100.0)


@query(f"SELECT key, round(sum(greatest(-20.0, least(20.0, l_quantity))), 6) AS total FROM ({oracle.lines()}) GROUP BY key")
def clamped_sum(spark, sf):
    return tables.line_records(spark, sf).groupBy("key").agg(F.round(F.sum(bounding.clamped(F.col("l_quantity"), 20)), 6).alias("total"))


@query(f"WITH {oracle.delta_ctes(oracle.lines(), SUPPLIER)} SELECT count(*) AS records, count(*) FILTER (WHERE rk > 17) AS dropped, count(DISTINCT unit) FILTER (WHERE rk > 17) AS units_cut, round(avg((rk > 17)::INT), 6) AS share FROM ranked")
def bounding_loss(spark, sf):
    return rounded(metrics.bounding_loss(bounding.ranked(timing.assign_triggers(tables.line_records(spark, sf), 8)), 17))


@query("WITH p AS (SELECT user_id, count(*) AS n FROM events GROUP BY 1), s AS (SELECT n, count(*) AS c FROM p GROUP BY n), a AS (SELECT n, sum(c) OVER (ORDER BY n) / sum(c) OVER () AS share FROM s) SELECT min(n) AS c FROM a WHERE share >= 0.99")
def choose_c_p99(spark, sf):
    return tuning.choose_c(tables.event_records(spark, sf), 0.99)


@query(
    f"""WITH p AS (SELECT user_id, count(*) AS n FROM events GROUP BY 1), g AS (SELECT unnest(range(1, 201)) AS c),
s AS (SELECT c, (SELECT count(*) FROM p WHERE least(n, 201) <= c) AS below, (SELECT count(*) FROM p) AS total FROM g),
u AS (SELECT c, -0.5::DOUBLE * abs(below - 0.99::DOUBLE * total) - ln(-ln((('0x' || substr(sha256('{TEST_SECRET}|quantile|' || c), 1, 13))::BIGINT::DOUBLE + 1) / {float((1 << 52) + 1)}::DOUBLE)) AS score FROM s)
SELECT c FROM u ORDER BY score DESC LIMIT 1"""
)
def choose_c_dp(spark, sf):
    return tuning.choose_c_dp(tables.event_records(spark, sf), 0.99, 1.0, 200, TEST_SECRET)


# --- deltas and user counts --------------------------------------------------------------


@query(f"WITH {oracle.delta_ctes(oracle.lines(), SUMS)} SELECT key, trig AS trigger_idx, n AS n_records, users AS new_users, s0 AS sum_qty FROM delta")
def delta_hist(spark, sf):
    return replay.delta(tables.line_records(spark, sf), SUMS)


@query(f"WITH {oracle.delta_ctes(oracle.lines(), SUPPLIER)} SELECT key, sum(nw)::BIGINT AS users FROM adm GROUP BY key")
def users_pair_once(spark, sf):
    return replay.delta(tables.line_records(spark, sf), SUPPLIER).groupBy("key").agg(F.sum("new_users").alias("users"))


BATCHES = replace(SUPPLIER, gate=GateConfig(count_mode="batch_additive"))


@query(f"WITH {oracle.delta_ctes(oracle.lines(), BATCHES)} SELECT key, trig AS trigger_idx, users AS new_users FROM delta")
def users_batch_additive(spark, sf):
    return replay.delta(tables.line_records(spark, sf), BATCHES).select("key", "trigger_idx", "new_users")


ROUNDS = replace(SUPPLIER, gate=GateConfig(count_mode="round_distinct"))


@query(f"WITH {oracle.delta_ctes(oracle.lines(), ROUNDS)} SELECT key, trig AS trigger_idx, prev AS previous, count(*) AS units FROM seen GROUP BY ALL")
def users_round_distinct(spark, sf):
    """Units of a trigger by the trigger at which they were last seen with the key."""
    deltas = replay.delta(tables.line_records(spark, sf), ROUNDS)
    return deltas.select("key", "trigger_idx", F.explode("previous").alias("p")).select("key", "trigger_idx", F.col("p.trigger").alias("previous"), F.col("p.units").alias("units"))


@query(f"WITH {oracle.delta_ctes(oracle.lines('l_partkey'), SUPPLIER)} SELECT key, sum(users)::BIGINT AS users FROM delta GROUP BY key HAVING sum(users) > 10")
def pre_threshold(spark, sf):
    return replay.delta(tables.line_records(spark, sf, "l_partkey"), SUPPLIER).groupBy("key").agg(F.sum("new_users").alias("users")).filter("users > 10")


# --- noise, trees, thresholds ------------------------------------------------------------


@query(
    f"""WITH t AS (SELECT event_type AS key, dayofyear(ts)::BIGINT AS r, {oracle.trigger("event_id", 16)}::BIGINT - 1 AS leaf FROM events),
n AS (SELECT key, r, level, leaf >> level AS idx, count(*) AS n FROM t, (SELECT unnest(range(0, 5)) AS level) GROUP BY ALL)
SELECT key, r AS round, level, idx, n, round({normal_sql(TEST_SECRET, 'demo', 'key', 'r', 'level', 'idx')}, 6) AS z FROM n"""
)
def node_noise(spark, sf):
    """Count and noise of the tree nodes that each event type's records touch in a day of 16 triggers (a day is a round)."""
    ev = timing.assign_triggers(tables.event_records(spark, sf), 16).select("key", F.dayofyear("day").cast("bigint").alias("round"), (F.col("trigger_idx") - 1).cast("bigint").alias("leaf"))
    leaves = ev.groupBy("key", "round", "leaf").agg(F.count(F.lit(1)).alias("n"))
    node = F.inline(F.array(*[F.struct(F.lit(v).cast("bigint").alias("level"), F.shiftright("leaf", v).alias("idx")) for v in range(5)]))
    nodes = leaves.select("key", "round", "n", node).groupBy("key", "round", "level", "idx").agg(F.sum("n").alias("n"))
    return nodes.withColumn("z", F.round(normal_column(TEST_SECRET, "demo", F.col("key"), F.col("round"), F.col("level"), F.col("idx")), 6))


def prefix_rows(spark, sf: str, kind: str, t: int = 16) -> DataFrame:
    """Prefix noise of every user's stream at the triggers at which events of the user arrive."""
    ev = timing.assign_triggers(tables.event_records(spark, sf, "CAST(user_id AS STRING)"), t)
    lines = ev.groupBy("key").agg(F.array_sort(F.collect_set("trigger_idx")).alias("at"))  # at most t numbers
    prefix, secret = tree.PrefixNoise, TEST_SECRET

    def run(batches):
        for b in batches:
            keys, at, z = [], [], []
            for k, triggers in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                noise = prefix(secret, "demo", k, 1, kind, t)
                keys += [k] * len(triggers)
                at += triggers
                z += [round(noise.at(i), 6) for i in triggers]
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array(at, pa.int64()), pa.array(z, pa.float64())], ["key", "i", "z"])

    return lines.mapInArrow(run, "key string, i long, z double")


def prefix_sql(kind: str) -> str:
    return f"WITH ks AS (SELECT DISTINCT CAST(user_id AS VARCHAR) AS key, {oracle.trigger('event_id', 16)} AS trig FROM events), {oracle.noise_cte('pn', 'ks', TEST_SECRET, 'demo', 1, 16, kind)} SELECT pn.key, i, round(z, 6) AS z FROM pn JOIN ks ON ks.key = pn.key AND ks.trig = i"


@query(prefix_sql("plain"))
def prefix_plain(spark, sf):
    return prefix_rows(spark, sf, "plain")


@query(prefix_sql("bottom_up"))
def prefix_bottom_up(spark, sf):
    return prefix_rows(spark, sf, "bottom_up")


@query(f"SELECT i, n, bit_count(i)::DOUBLE AS plain, round((SELECT sum(1 / (2 * (1 - pow(2.0, -(b + 1))))) FROM (SELECT unnest(range(0, 10)) AS b) WHERE (i >> b::INTEGER) & 1 = 1), 6) AS bottom_up FROM (SELECT i, sum(m) OVER (ORDER BY i)::BIGINT AS n FROM (SELECT {oracle.trigger('event_id', 150)}::BIGINT AS i, count(*) AS m FROM events GROUP BY 1))")
def prefix_variance(spark, sf):
    """Records so far, and the variance of their noisy prefix, at each of 150 triggers that has events."""
    met = timing.assign_triggers(tables.event_records(spark, sf), 150).groupBy(F.col("trigger_idx").cast("bigint").alias("i")).agg(F.count(F.lit(1)).alias("m"))
    so_far = met.select("i", F.sum("m").over(Window.orderBy("i").rowsBetween(Window.unboundedPreceding, 0)).alias("n"))  # a row a trigger
    of = tree.variance

    def run(batches):
        for b in batches:
            at = b.column(0).to_pylist()
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([of(i, "plain") for i in at], pa.float64()), pa.array([round(of(i), 6) for i in at], pa.float64())], ["i", "n", "plain", "bottom_up"])

    return so_far.mapInArrow(run, "i long, n long, plain double, bottom_up double")


def literal_sql(rows: list[tuple], names: list[str]) -> str:
    def one(v):
        return f"'{v}'" if isinstance(v, str) else f"{v!r}::DOUBLE" if isinstance(v, float) else f"{v}"

    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(one, r)) + ')' for r in rows)}) t({', '.join(names)})"


def tau_rows() -> list[tuple]:
    p = calibrate.plan(FORUM)
    z = calibrate.upper_quantile(p.beta / 16)
    return [(i, p.sigma, z) for i in range(1, 17)]


@query(
    f"""WITH {oracle.delta_ctes(oracle.FORUM, FORUM)}, t AS (SELECT i::INTEGER AS i, sigma * z * sqrt((SELECT sum(1 / (2 * (1 - pow(2.0, -(b + 1))))) FROM (SELECT unnest(range(0, 10)) AS b) WHERE (i >> b::INTEGER) & 1 = 1)) AS tau FROM ({literal_sql(tau_rows(), ['i', 'sigma', 'z'])})),
u AS (SELECT i, key, sum(users) AS users FROM delta JOIN t ON trig <= i GROUP BY ALL)
SELECT t.i AS trigger_idx, round(tau, 6) AS tau, count(key) AS keys, count(key) FILTER (WHERE users > {FORUM.gate.mu} + tau) AS keys_over FROM t LEFT JOIN u ON u.i = t.i GROUP BY t.i, tau"""
)
def tau_per_trigger(spark, sf):
    """Thresholds by trigger, keys that have data by then and those whose exact user counts are above mu and the threshold."""
    taus = F.broadcast(spark.createDataFrame([(i + 1, x) for i, x in enumerate(calibrate.plan(FORUM).taus)], "trigger_idx int, tau double"))
    deltas = replay.delta(tables.brand_type_records(spark, sf), FORUM).select("key", F.col("trigger_idx").alias("trig"), "new_users")
    so_far = deltas.join(taus, F.col("trig") <= F.col("trigger_idx")).groupBy("trigger_idx", "key").agg(F.sum("new_users").alias("users"))
    over = F.col("users") > FORUM.gate.mu + F.col("tau")
    return taus.join(so_far, "trigger_idx", "left").groupBy("trigger_idx", "tau").agg(F.count("key").alias("keys"), F.count(F.when(over, F.col("key"))).alias("keys_over")).withColumn("tau", F.round("tau", 6))


@query(
    f"""WITH {oracle.delta_ctes(oracle.lines(), MULTI)}, b AS (SELECT 6.0::DOUBLE AS eps, 1e-9::DOUBLE AS delta, 17 AS c), s AS (SELECT *, eps / 2 AS ek, delta * 2 / 3 AS dk FROM b),
l AS (SELECT 'gate tree' AS component, ek AS eps, dk / 2 AS delta, c AS fold FROM s UNION ALL SELECT 'gate threshold', 0.0, c * (exp(ek) + 1) * (dk / 2 / (c * (exp(ek) + 1))), c FROM s
UNION ALL SELECT 'value ' || m, eps - ek, delta - dk, 1 FROM s, (SELECT unnest(['count', 'qty']) AS m)),
e AS (SELECT component, round(eps, 9) AS eps, round(delta * 1e9, 9) AS delta_e9, fold FROM l
UNION ALL SELECT 'total', round(sum(eps) FILTER (WHERE component <> 'value qty'), 9), round(sum(delta) FILTER (WHERE component <> 'value qty') * 1e9, 9), 1 FROM l),
u AS (SELECT count(*) AS units, count(*) FILTER (WHERE n >= 17) AS at_bound, coalesce(sum(n), 0)::BIGINT AS records FROM (SELECT unit, count(*) AS n FROM adm GROUP BY unit))
SELECT * FROM e, u"""
)
def ledger(spark, sf):
    """The spend of two measures at eps 6, delta 1e-9 and 17 records a unit (values share one budget), and who spends it: units with
    admitted records, those at the bound, and the records."""
    rows = accounting.ledger(spark, MULTI).select("component", F.round("eps", 9).alias("eps"), F.round(F.col("delta") * 1e9, 9).alias("delta_e9"), "fold")
    units = replay.admitted(tables.line_records(spark, sf), MULTI).groupBy("unit").agg(F.count(F.lit(1)).alias("n"))
    spent = units.agg(F.count(F.lit(1)).alias("units"), F.count(F.when(F.col("n") >= MULTI.bound, 1)).alias("at_bound"), F.coalesce(F.sum("n"), F.lit(0)).alias("records"))
    return F.broadcast(rows).crossJoin(spent)


def calibration_specs() -> list[tuple[str, StreamSpec]]:
    return [("flagship", FLAGSHIP), ("forum", FORUM), ("views", VIEWS), ("terms", TERMS), ("hundred", replace(FORUM, bound=32, timing=Timing(100)))]


#: Whose records bound a preset's units: customers' lines, users' events of a day, users' events.
CALIBRATED_ON = {"flagship": "lines", "forum": "lines", "views": "days", "terms": "users", "hundred": "lines"}


def calibration_sql() -> str:
    """Noise scales and thresholds from eps, delta, T and the C of the tables (records of a unit in 99 % of the units), all in SQL."""
    rows = [(n, s.budget.eps, s.budget.delta, s.budget.gate_eps_frac, s.budget.gate_delta_frac, s.timing.triggers, s.gate.mu, CALIBRATED_ON[n]) for n, s in calibration_specs()]
    units = f"SELECT 'lines' AS src, o_custkey::VARCHAR AS unit FROM lineitem JOIN orders ON l_orderkey = o_orderkey UNION ALL SELECT 'days', user_id || ':' || CAST(ts AS DATE) FROM events UNION ALL SELECT 'users', user_id::VARCHAR FROM events"
    bounds = "SELECT src, min(n) AS c FROM (SELECT src, n, sum(m) OVER (PARTITION BY src ORDER BY n) / sum(m) OVER (PARTITION BY src) AS share FROM (SELECT src, n, count(*) AS m FROM (SELECT src, unit, count(*) AS n FROM units GROUP BY ALL) GROUP BY ALL)) WHERE share >= 0.99 GROUP BY src"
    split = f"SELECT *, eps * fe AS ek, delta * fd AS dk, eps - eps * fe AS ev, delta - delta * fd AS dv, ceil(log2(t)) + 1 AS nodes FROM ({literal_sql(rows, ['name', 'eps', 'delta', 'fe', 'fd', 't', 'mu', 'src'])}) JOIN ({bounds}) USING (src)"
    beta = "dk / 2 / (c * (exp(ek) + 1)) / t"
    return f"""WITH units AS ({units}), s AS ({split}), gr AS ({oracle.rho_sql("SELECT name, ek AS eps, dk / 2 AS delta FROM s")}), vr AS ({oracle.rho_sql("SELECT name, ev AS eps, dv AS delta FROM s")}), q AS ({oracle.quantile_sql(f"SELECT name, {beta} AS p FROM s")})
SELECT name, c, round(sqrt(nodes / (2 * gr.rho / c)), 2) AS sigma, round(c * sqrt(nodes / (2 * vr.rho)), 2) AS value_sigma, round(z, 4) AS z, round(z * sqrt(nodes / (2 * gr.rho / c)), 1) AS first_tau FROM s JOIN gr USING (name) JOIN vr USING (name) JOIN q USING (name)"""


@query()
def calibration(spark, sf):
    """Bound from the table (records of a unit in 99 % of the units), noise scales, quantile and first threshold of some presets."""
    ev = tables.event_records(spark, sf)
    days = ev.withColumn("unit", F.concat_ws(":", F.col("unit").cast("string"), F.col("day").cast("string")))
    bounds = None
    for src, rec in (("lines", tables.line_records(spark, sf)), ("days", days), ("users", ev)):
        one = tuning.choose_c(rec, 0.99).select(F.lit(src).alias("src"), F.col("c").cast("bigint").alias("c"))
        bounds = one if bounds is None else bounds.unionByName(one)
    specs, on, plan, quantile, changed = calibration_specs(), CALIBRATED_ON, calibrate.plan, calibrate.upper_quantile, replace

    def run(batches):
        for b in batches:
            rows = []
            for src, c in zip(*(x.to_pylist() for x in b.columns)):
                for name, s in specs:
                    if on[name] == src:
                        p = plan(changed(s, bound=c))
                        rows.append((name, c, round(p.sigma, 2), round(p.value_sigma[0], 2), round(quantile(p.beta / s.timing.triggers), 4), round(p.taus[0], 1)))
            names = ("name", "c", "sigma", "value_sigma", "z", "first_tau")
            kinds = (pa.string(), pa.int64(), *[pa.float64()] * 4)
            yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], k) for j, k in enumerate(kinds)], list(names))

    return bounds.mapInArrow(run, "name string, c long, sigma double, value_sigma double, z double, first_tau double")


Q["calibration"] = (calibration, calibration_sql())


# --- key gate and releases ---------------------------------------------------------------


def gate_query(name: str, spec: StreamSpec, rec_sql: str, records, select: str | None = None, then=None):
    def run(spark, sf):
        out = replay.run(records(spark, sf), spec)
        return rounded(then(out, spec) if then else out)

    run.__name__ = name
    Q[name] = (run, oracle.releases(rec_sql, spec, select))
    return run


suppliers = tables.line_records
BARE = replace(SUPPLIER, gate=GateConfig(restart=False))
UNIVERSAL = replace(FORUM, gate=GateConfig(tau_mode="universal"))
THEOREM = replace(SUPPLIER, gate=GateConfig(tau_mode="theorem"))
PLAIN = replace(FORUM, gate=GateConfig(variance="plain"))
KEYS_ONLY = "SELECT key, trigger_idx, round, round(users_hat, 6) AS users_hat FROM releases"
keys_only = lambda df, spec: df.select("key", "trigger_idx", "round", "users_hat")

gate_query("gate_bare", BARE, oracle.lines(), suppliers, KEYS_ONLY, keys_only)
gate_query("gate_rounds", FORUM, oracle.FORUM, tables.brand_type_records, KEYS_ONLY, keys_only)
gate_query("gate_universal_tau", UNIVERSAL, oracle.FORUM, tables.brand_type_records, KEYS_ONLY, keys_only)
gate_query("gate_theorem_tau", THEOREM, oracle.lines(), suppliers, KEYS_ONLY, keys_only)
gate_query("gate_plain_variance", PLAIN, oracle.FORUM, tables.brand_type_records, KEYS_ONLY, keys_only)
gate_query("gate_batch_additive", replace(SUPPLIER, bound=4, gate=GateConfig(count_mode="batch_additive")), oracle.lines("l_returnflag || '-' || l_linestatus"), lambda s, d: tables.line_records(s, d, "concat_ws('-', l_returnflag, l_linestatus)"), KEYS_ONLY, keys_only)
gate_query("gate_round_distinct", replace(FORUM, gate=GateConfig(count_mode="round_distinct")), oracle.FORUM, tables.brand_type_records)
gate_query("release_count", SUPPLIER, oracle.lines(), suppliers)
gate_query("release_sum", SUMS, oracle.lines(), suppliers)
gate_query("release_multi", MULTI, oracle.lines(), suppliers)
gate_query("forum_like_hist", FORUM, oracle.FORUM, tables.brand_type_records)
gate_query("release_avg_var", MULTI, oracle.lines(), suppliers, "SELECT key, trigger_idx, round(qty_hat / greatest(count_hat, 1.0), 6) AS avg_hat FROM releases", lambda df, spec: df.select("key", "trigger_idx", (F.col("qty_hat") / F.greatest("count_hat", F.lit(1.0))).alias("avg_hat")))
gate_query("snapshot_asof", FORUM, oracle.FORUM, tables.brand_type_records, "SELECT key, max(trigger_idx) AS trigger_idx, round(max_by(users_hat, trigger_idx), 6) AS users_hat, round(max_by(count_hat, trigger_idx), 6) AS count_hat FROM releases WHERE trigger_idx <= 10 GROUP BY key", lambda df, spec: replay.snapshot(df, spec, 10))
gate_query("rollup_of_releases", FORUM, oracle.FORUM, tables.brand_type_records, "SELECT split_part(key, '/', 1) AS brand, round(sum(c), 4) AS count_hat FROM (SELECT key, max_by(count_hat, trigger_idx) AS c FROM releases GROUP BY key) GROUP BY ROLLUP (split_part(key, '/', 1)) HAVING sum(c) IS NOT NULL", lambda df, spec: replay.snapshot(df, spec).withColumn("brand", F.split_part("key", F.lit("/"), F.lit(1))).rollup("brand").agg(F.round(F.sum("count_hat"), 4).alias("count_hat")))
gate_query("topk_noisy", FORUM, oracle.FORUM, tables.brand_type_records, "SELECT key, round(max_by(count_hat, trigger_idx), 6) AS count_hat FROM releases GROUP BY key ORDER BY 2 DESC, key LIMIT 10", lambda df, spec: replay.snapshot(df, spec).select("key", "count_hat").orderBy(F.desc("count_hat"), "key").limit(10))
gate_query("carry_forward_window", FORUM, oracle.FORUM, tables.brand_type_records, "SELECT key, i::INTEGER AS trigger_idx, round((SELECT max_by(count_hat, r.trigger_idx) FROM releases r WHERE r.key = k.key AND r.trigger_idx <= i), 6) AS count_hat FROM (SELECT DISTINCT key FROM releases) k, (SELECT unnest(range(1, 17)) AS i)", lambda df, spec: carry_forward(df, spec))
gate_query("release_deltas", FORUM, oracle.FORUM, tables.brand_type_records, "SELECT key, trigger_idx, round(count_hat - lag(count_hat, 1, 0) OVER (PARTITION BY key ORDER BY trigger_idx), 6) AS change FROM releases", lambda df, spec: df.select("key", "trigger_idx", (F.col("count_hat") - F.lag("count_hat", 1, 0.0).over(Window.partitionBy("key").orderBy("trigger_idx"))).alias("change")))
gate_query("tail_parts_suppressed", SUPPLIER, oracle.lines("l_partkey"), lambda s, d: tables.line_records(s, d, "l_partkey"), "SELECT count(DISTINCT key) AS keys FROM releases", lambda df, spec: df.agg(F.countDistinct("key").alias("keys")))


def carry_forward(releases: DataFrame, spec: StreamSpec) -> DataFrame:
    """key x trigger grid with the last release so far."""
    t = spec.timing.triggers
    grid = releases.select("key").distinct().select("key", F.explode(F.sequence(F.lit(1), F.lit(t))).alias("trigger_idx"))
    have = releases.select("key", "trigger_idx", "count_hat")
    last = F.last("count_hat", ignorenulls=True).over(Window.partitionBy("key").orderBy("trigger_idx").rowsBetween(Window.unboundedPreceding, 0))
    return grid.join(have, ["key", "trigger_idx"], "left").withColumn("count_hat", last)


FORUM_RELEASES = "SELECT key, trigger_idx, round, cause, round(users_hat, 6) AS users_hat, round(count_hat, 6) AS count_hat FROM releases"


@query(oracle.releases(oracle.FORUM, FORUM, FORUM_RELEASES))
def gate_forecast(spark, sf):
    """Releases from state loaded only when a key has data or is due: equal to testing all keys always."""
    from ..streaming import microbatch

    return rounded(microbatch.run_in_memory(tables.brand_type_records(spark, sf), FORUM))


@query(oracle.releases(oracle.FORUM, FORUM, FORUM_RELEASES))
def gate_naive(spark, sf):
    """Every key at every trigger: a dense grid of key x trigger goes through the same state machine."""
    deltas = replay.delta(tables.brand_type_records(spark, sf), FORUM)
    grid = deltas.select("key").distinct().select("key", F.explode(F.sequence(F.lit(1), F.lit(16))).alias("trigger_idx"))
    dense = grid.join(deltas, ["key", "trigger_idx"], "left").fillna(0)
    out = replay.fold(replay.timelines(dense, FORUM), FORUM)
    silent = out.join(deltas.select("key", "trigger_idx", F.lit(True).alias("_data")), ["key", "trigger_idx"], "left")
    return rounded(silent.withColumn("cause", F.when(F.col("_data"), "arrival").otherwise("silent")).drop("_data"))


@query(oracle.forecasts(oracle.FORUM, FORUM, "SELECT key, i AS made_at, predicted FROM arrivals WHERE predicted IS NOT NULL"))
def forecast_table(spark, sf):
    return replay.run(tables.brand_type_records(spark, sf), FORUM, "forecasts")


@query(oracle.loads(oracle.lines("l_partkey"), SPARSE, 3))
def state_loads(spark, sf):
    """Keys loaded and tests made, naive against forecast."""
    cost = replay.run(tables.line_records(spark, sf, "l_partkey"), SPARSE, "cost")
    return cost.agg(F.count(F.lit(1)).alias("keys"), *[F.sum(c).alias(c) for c in ("tests", "wasted", "loads_naive", "loads_forecast")])


gate_query("selected_keys_main", FORUM, oracle.FORUM, tables.brand_type_records, "SELECT DISTINCT key FROM releases", lambda df, spec: df.select("key").distinct())


@query(oracle.releases(oracle.FORUM, FORUM, "SELECT DISTINCT key FROM delta WHERE key NOT IN (SELECT key FROM releases)"))
def unreleased_anti(spark, sf):
    rec = tables.brand_type_records(spark, sf)
    return replay.delta(rec, FORUM).select("key").distinct().join(replay.run(rec, FORUM).select("key"), "key", "left_anti")


# --- applications ------------------------------------------------------------------------

VIEWS_SQL = "SELECT user_id || ':' || CAST(ts AS DATE) AS unit, event_type || '@' || CAST(ts AS DATE) AS key, event_id AS rid FROM events"


def view_records(spark, sf):
    ev = tables.event_records(spark, sf)
    return ev.select(F.concat_ws(":", F.col("unit").cast("string"), F.col("day").cast("string")).alias("unit"), F.concat_ws("@", "key", F.col("day").cast("string")).alias("key"), "record_id")


gate_query("page_views_user_day", VIEWS, VIEWS_SQL, view_records)


#: One record a user and day, as in VIEWS, over 150 triggers.
EPS_SWEEP = replace(VIEWS, timing=Timing(150))


def eps_sweep_rows() -> list[tuple]:
    return [(e, calibrate.equivalent_threshold(e, 1e-9, 150)) for e in (1.0, 3.0, 10.0)]


@query(
    f"""WITH {oracle.delta_ctes(VIEWS_SQL, EPS_SWEEP)}, u AS (SELECT key, count(DISTINCT unit) AS users FROM adm GROUP BY key),
e AS (SELECT unnest([1.0::DOUBLE, 3.0::DOUBLE, 10.0::DOUBLE]) AS eps), s AS (SELECT eps::VARCHAR AS name, eps, 5e-10::DOUBLE AS delta FROM e), r AS ({oracle.rho_sql("SELECT * FROM s")}),
q AS ({oracle.quantile_sql("SELECT name, delta / (exp(eps) + 1) AS p FROM s")}), th AS (SELECT eps, z * sqrt((ceil(log2(150)) + 1) / (2 * rho)) AS threshold FROM s JOIN r USING (name) JOIN q USING (name))
SELECT eps, round(threshold, 2) AS threshold, count(key) AS keys, count(key) FILTER (WHERE users >= threshold) AS keys_over, coalesce(sum(users) FILTER (WHERE users >= threshold), 0)::BIGINT AS users_over FROM th LEFT JOIN u ON true GROUP BY eps, threshold"""
)
def eps_sweep_thresholds(spark, sf):
    """Users that a key needs by eps, and how many (event type, day) keys and users of them are at or above that."""
    users = replay.admitted(view_records(spark, sf), EPS_SWEEP).groupBy("key").agg(F.countDistinct("unit").alias("users"))
    rows = F.broadcast(spark.createDataFrame(eps_sweep_rows(), "eps double, threshold double"))
    over = F.col("users") >= F.col("threshold")
    out = rows.join(users, how="left", on=F.lit(True)).groupBy("eps", "threshold")
    out = out.agg(F.count("key").alias("keys"), F.count(F.when(over, F.col("key"))).alias("keys_over"), F.coalesce(F.sum(F.when(over, F.col("users"))), F.lit(0)).alias("users_over"))
    return out.withColumn("threshold", F.round("threshold", 2))


TERMS_SQL = "SELECT doc_id || '-' || key AS unit, key, doc_id || '-' || key AS rid FROM (SELECT doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]+'))) AS key FROM documents)"
gate_query("term_trends", TERMS, TERMS_SQL, tables.token_records, KEYS_ONLY, keys_only)

# --- baselines and measures --------------------------------------------------------------


def once_sql(users: str, total: str, p: oneshot.OneShotPlan, secret: str, run: str, source: str, extra: str = "", kind: str = "once") -> str:
    return f"""SELECT {extra}key, users_hat, value_hat FROM (SELECT *, {users} + {p.user_sigma!r}::DOUBLE * {oracle.once(f"{kind}-users", secret, run)} AS users_hat, {total} + {p.value_sigma!r}::DOUBLE * {oracle.once(f"{kind}-value", secret, run)} AS value_hat FROM {source}) WHERE users_hat > {p.threshold!r}::DOUBLE"""


def once_plan(spec: StreamSpec, k: int) -> oneshot.OneShotPlan:
    e, d = accounting.compose_inverse(k, spec.budget.eps, spec.budget.delta)
    return oneshot.oneshot_plan(e, d, spec.bound, spec.measures[0].sensitivity, spec.budget.gate_eps_frac, spec.budget.gate_delta_frac)


ONE = once_plan(SUPPLIER, 1)
REP = once_plan(SUPPLIER, 8)
INC_K = min(SUPPLIER.bound, 8)
INC = once_plan(SUPPLIER, INC_K)
HIST = "(SELECT key, sum(users) AS users, sum(s0) AS total FROM delta GROUP BY key)"
ONE_SQL = once_sql("users", "total", ONE, TEST_SECRET, "0", HIST)
REP_SQL = once_sql("users", "total", REP, TEST_SECRET, "8", HIST)
INC_SQL = f"SELECT key, sum(users_hat) AS users_hat, sum(value_hat) AS value_hat, count(*) AS batches FROM ({once_sql('users', 's0', INC, TEST_SECRET, 'trig', 'delta', kind='batch')}) GROUP BY key"
SUP_CTES = oracle.delta_ctes(oracle.lines(BUSY), SUPPLIER)
BATCH_CTES = oracle.delta_ctes(oracle.lines(BUSY), BATCHES)
ROUND3 = "SELECT key, round(users_hat, 6) AS users_hat, round(value_hat, 6) AS value_hat FROM"


@query(f"WITH {SUP_CTES} {ROUND3} ({ONE_SQL})")
def oneshot_hist(spark, sf):
    return rounded(oneshot.oneshot_hist(replay.admitted(tables.line_records(spark, sf, BUSY), SUPPLIER), SUPPLIER))


CAP = oneshot.oneshot_plan(6.0, 1e-9, 10, 5.0, max_keys=10, max_value=5.0)


@query(
    f"""WITH trg AS (SELECT *, {oracle.trigger("rid", 8)} AS trig FROM ({oracle.lines(BUSY)})), f AS (SELECT unit, key, min({{'t': trig, 'r': rid}}) AS first, count(*)::DOUBLE AS total FROM trg GROUP BY unit, key),
r AS (SELECT *, row_number() OVER (PARTITION BY unit ORDER BY first.t, first.r) AS k FROM f), h AS (SELECT key, count(*) AS users, sum(least(5.0, total)) AS total FROM r WHERE k <= 10 GROUP BY key) {ROUND3} ({once_sql("users", "total", CAP, TEST_SECRET, "0", "h")})"""
)
def oneshot_capped(spark, sf):
    return rounded(oneshot.oneshot_capped(timing.assign_triggers(tables.line_records(spark, sf, BUSY), 8), SUPPLIER, 10, 5.0))


def supplier_deltas(spark, sf, spec=SUPPLIER):
    return replay.delta(tables.line_records(spark, sf, BUSY), spec)


@query(f"WITH {SUP_CTES} {ROUND3} ({REP_SQL})")
def baseline_repeated(spark, sf):
    return rounded(baselines.repeated_queries(supplier_deltas(spark, sf), SUPPLIER)).drop("trigger_idx")


@query(f"WITH {BATCH_CTES} SELECT key, round(users_hat, 6) AS users_hat, round(value_hat, 6) AS value_hat, batches FROM ({INC_SQL})")
def baseline_incremental(spark, sf):
    return rounded(baselines.incremental_batches(supplier_deltas(spark, sf, BATCHES), SUPPLIER))


ALL_SQL = f"(SELECT key, i, sum(users) AS users, sum(s0) AS total FROM delta JOIN (SELECT unnest(range(1, 9)) AS i) ON trig <= i GROUP BY key, i)"


@query(f"WITH {SUP_CTES} SELECT trigger_idx, key, round(users_hat, 6) AS users_hat, round(value_hat, 6) AS value_hat FROM ({once_sql('users', 'total', REP, TEST_SECRET, 'i', ALL_SQL, 'i::INTEGER AS trigger_idx, ')})")
def baseline_repeated_all_triggers(spark, sf):
    return rounded(baselines.repeated_queries(supplier_deltas(spark, sf), SUPPLIER, last_only=False))


TRUTH = "truth AS (SELECT key, count(*)::DOUBLE AS truth FROM rec GROUP BY key)"
LAST = "est AS (SELECT key, max_by(count_hat, trigger_idx) AS count_hat FROM releases GROUP BY key)"


@query(oracle.releases(oracle.lines(BUSY), SUPPLIER, "").rstrip() + f",\n{TRUTH}, {LAST} " + oracle.utility("truth", "est", "count_hat"))
def utility_norms_main(spark, sf):
    rec = tables.line_records(spark, sf, BUSY)
    return rounded(metrics.utility(aggregate.plain_hist(rec), replay.snapshot(replay.run(rec, SUPPLIER), SUPPLIER), "count_hat"))


@query(f"WITH {SUP_CTES}, {TRUTH}, est AS ({REP_SQL}) " + oracle.utility("truth", "est", "value_hat"))
def utility_norms_b1(spark, sf):
    return rounded(metrics.utility(aggregate.plain_hist(tables.line_records(spark, sf, BUSY)), baselines.repeated_queries(supplier_deltas(spark, sf), SUPPLIER)))


@query(f"WITH {BATCH_CTES}, {TRUTH}, est AS ({INC_SQL}) " + oracle.utility("truth", "est", "value_hat"))
def utility_norms_b2(spark, sf):
    return rounded(metrics.utility(aggregate.plain_hist(tables.line_records(spark, sf, BUSY)), baselines.incremental_batches(supplier_deltas(spark, sf, BATCHES), SUPPLIER)))


@query(oracle.releases(VIEWS_SQL, VIEWS, "").rstrip() + f",\n{TRUTH}, shown AS (SELECT DISTINCT key, true AS s FROM releases), rates AS (SELECT unnest([0.0, 1.0, 60.0]) AS rate) SELECT rate::DOUBLE AS rate, count(*) AS keys, round(sum(CASE WHEN s THEN truth ELSE 0.0 END) / sum(truth), 6) AS retained FROM truth t LEFT JOIN shown USING (key), rates WHERE truth >= rate * 24 GROUP BY rate")
def retained_mass(spark, sf):
    rec = view_records(spark, sf)
    return rounded(metrics.retained_mass(aggregate.plain_hist(rec), replay.run(rec, VIEWS), 24.0))


@query(oracle.releases(oracle.FORUM, FORUM, "").rstrip() + f",\n{TRUTH}, {LAST} SELECT round(sum(abs(count_hat - truth)) / sum(truth), 6) AS total_rel, round(avg(abs(count_hat - truth) / truth), 6) AS mean_rel FROM truth JOIN est USING (key)")
def relative_error(spark, sf):
    rec = tables.brand_type_records(spark, sf)
    both = aggregate.plain_hist(rec).join(replay.snapshot(replay.run(rec, FORUM), FORUM), "key")
    err = F.abs(F.col("count_hat") - F.col("truth"))
    return rounded(both.agg((F.sum(err) / F.sum("truth")).alias("total_rel"), F.avg(err / F.col("truth")).alias("mean_rel")))


SWEEP = (1, 2, 5, 10, 17, 25, 32, 50, 77)


def sweep_plan(c: int) -> oneshot.OneShotPlan:
    return oneshot.oneshot_plan(6.0, 1e-9, c, 1.0)


SWEEP_ROWS = [(c, sweep_plan(c).user_sigma, sweep_plan(c).value_sigma, sweep_plan(c).threshold) for c in SWEEP]


@query(
    f"""WITH g AS ({literal_sql(SWEEP_ROWS, ["c", "us", "vs", "th"])}), {oracle.delta_ctes(oracle.FORUM, FORUM)}, {TRUTH},
h AS (SELECT c, us, vs, th, key, count(DISTINCT unit) AS users, count(*)::DOUBLE AS total FROM ranked JOIN g ON rk <= c GROUP BY ALL),
e AS (SELECT c, key, total + vs * {normal_sql(TEST_SECRET, "sweep-value", "key", "c", "0", "0")} AS hat FROM h WHERE users + us * {normal_sql(TEST_SECRET, "sweep-users", "key", "c", "0", "0")} > th)
SELECT g.c::INTEGER AS c, count(hat) AS keys, round(max(abs(coalesce(hat, 0) - truth)), 6) AS linf, round(sum(abs(coalesce(hat, 0) - truth)), 6) AS l1, round(sqrt(sum(pow(coalesce(hat, 0) - truth, 2))), 6) AS l2
FROM truth t CROSS JOIN g LEFT JOIN e ON e.c = g.c AND e.key = t.key GROUP BY g.c"""
)
def c_sweep(spark, sf):
    rec = timing.assign_triggers(tables.brand_type_records(spark, sf), 16)
    return rounded(tuning.c_sweep(bounding.ranked(rec), SWEEP, aggregate.plain_hist(rec), lambda c: (sweep_plan(c).user_sigma, sweep_plan(c).value_sigma), lambda c: sweep_plan(c).threshold, TEST_SECRET))


# --- ablations ---------------------------------------------------------------------------


@query(f"WITH {SUP_CTES}, h AS (SELECT key, trig, sum(s0) OVER (PARTITION BY key ORDER BY trig) AS total FROM delta) SELECT key, trig AS trigger_idx, round(total + {17 * (8 / (2 * calibrate.plan(SUPPLIER).rho_value)) ** 0.5!r}::DOUBLE * {oracle.once('fresh', TEST_SECRET, 'trig')}, 6) AS count_hat FROM h")
def independent_noise_ablation(spark, sf):
    """Fresh noise for every release of every trigger: variance grows with T."""
    run = F.sum("sum_count").over(Window.partitionBy("key").orderBy("trigger_idx").rowsBetween(Window.unboundedPreceding, 0))
    sigma = 17 * (8 / (2 * calibrate.plan(SUPPLIER).rho_value)) ** 0.5
    return rounded(supplier_deltas(spark, sf).select("key", "trigger_idx", (run + sigma * normal_column(TEST_SECRET, "fresh", F.col("key"), F.col("trigger_idx"), F.lit(0), F.lit(0))).alias("count_hat")))


@query(f"WITH {SUP_CTES}, {oracle.noise_cte('ln', 'delta', TEST_SECRET, 'leaf', 1, 8, 'leaf')}, h AS (SELECT key, trig, sum(s0) OVER (PARTITION BY key ORDER BY trig) AS total FROM delta) SELECT h.key, trig AS trigger_idx, round(total + {17 * (1 / (2 * calibrate.plan(SUPPLIER).rho_value)) ** 0.5!r}::DOUBLE * z, 6) AS count_hat FROM h JOIN ln ON ln.key = h.key AND ln.i = h.trig")
def leaf_noise_ablation(spark, sf):
    """Noise on the leaves alone, summed: variance grows with the trigger."""
    sigma = 17 * (1 / (2 * calibrate.plan(SUPPLIER).rho_value)) ** 0.5
    leaf = sum((F.when(F.col("trigger_idx") > j, normal_column(TEST_SECRET, "leaf", F.col("key"), F.lit(1), F.lit(0), F.lit(j))).otherwise(F.lit(0.0)) for j in range(8)), F.lit(0.0))
    run = F.sum("sum_count").over(Window.partitionBy("key").orderBy("trigger_idx").rowsBetween(Window.unboundedPreceding, 0))
    return rounded(supplier_deltas(spark, sf).select("key", "trigger_idx", (run + sigma * leaf).alias("count_hat")))


def sqrt_coeffs() -> list[float]:
    return [float(x) for x in tree.sqrt_factor(8)]


SQRT_SIGMA = 17 * tree.sqrt_sensitivity(8) / (2 * calibrate.plan(SUPPLIER).rho_value) ** 0.5


@query(
    f"WITH {SUP_CTES}, f AS (SELECT unnest({sqrt_coeffs()!r}) AS w, unnest(range(0, 8)) AS d), z AS (SELECT key, j, {normal_sql(TEST_SECRET, 'factor', 'key', '1', '0', 'j')} AS z FROM (SELECT DISTINCT key FROM delta), (SELECT unnest(range(0, 8)) AS j)), h AS (SELECT key, trig, sum(s0) OVER (PARTITION BY key ORDER BY trig) AS total FROM delta) SELECT h.key, h.trig AS trigger_idx, round(total + {SQRT_SIGMA!r}::DOUBLE * (SELECT sum(w * z) FROM z JOIN f ON f.d = h.trig - 1 - z.j WHERE z.key = h.key AND z.j < h.trig), 6) AS count_hat FROM h"
)
def sqrt_factor_release(spark, sf):
    """Matrix-factorization noise instead of the tree."""
    c = sqrt_coeffs()
    noise = sum((F.when(F.col("trigger_idx") > j, F.get(F.lit(c), F.col("trigger_idx") - 1 - j) * normal_column(TEST_SECRET, "factor", F.col("key"), F.lit(1), F.lit(0), F.lit(j))).otherwise(F.lit(0.0)) for j in range(8)), F.lit(0.0))
    run = F.sum("sum_count").over(Window.partitionBy("key").orderBy("trigger_idx").rowsBetween(Window.unboundedPreceding, 0))
    return rounded(supplier_deltas(spark, sf).select("key", "trigger_idx", (run + SQRT_SIGMA * noise).alias("count_hat")))


# --- relational operators around the methods ---------------------------------------------


@query("SELECT event_type, CAST(ts AS DATE) AS day, count(*) AS n FROM events GROUP BY CUBE (event_type, CAST(ts AS DATE))")
def cube_truth(spark, sf):
    return tables.event_records(spark, sf).select(F.col("key").alias("event_type"), "day").cube("event_type", "day").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT event_type, CAST(ts AS DATE) AS day, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), (CAST(ts AS DATE)))")
def grouping_sets_truth(spark, sf):
    ev = tables.event_records(spark, sf).select(F.col("key").alias("event_type"), "day")
    return ev.groupingSets([["event_type"], ["day"]], "event_type", "day").agg(F.count(F.lit(1)).alias("n"))


#: Which keys the main method and the repeated query show: the busy keys, of which the latter shows some.
BOTH_SQL = oracle.releases(oracle.lines(BUSY), SUPPLIER, "").rstrip() + f",\nb AS ({REP_SQL})"


@query(f"{BOTH_SQL} SELECT key FROM releases INTERSECT SELECT key FROM b")
def selected_intersect(spark, sf):
    rec = tables.line_records(spark, sf, BUSY)
    return replay.run(rec, SUPPLIER).select("key").intersect(baselines.repeated_queries(replay.delta(rec, SUPPLIER), SUPPLIER).select("key"))


@query(oracle.releases(oracle.FORUM, FORUM, "").rstrip() + f",\nb AS ({once_sql('users', 'total', once_plan(FORUM, 16), TEST_SECRET, '16', HIST)}) SELECT key FROM releases EXCEPT SELECT key FROM b")
def selected_except(spark, sf):
    rec = tables.brand_type_records(spark, sf)
    return replay.run(rec, FORUM).select("key").subtract(baselines.repeated_queries(replay.delta(rec, FORUM), FORUM).select("key"))


@query("SELECT CAST(w AS DATE) AS day, event_type AS key, count(*) AS n FROM events, LATERAL (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS w) GROUP BY ALL")
def sliding_truth(spark, sf):
    ev = tables.event_records(spark, sf).withColumn("event_ts", F.col("event_ts").cast("timestamp"))
    return ev.groupBy(F.window("event_ts", "2 days", "1 day").alias("w"), "key").agg(F.count(F.lit(1)).alias("n")).select(F.to_date("w.start").alias("day"), "key", "n")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id AS unit, count(*) AS n FROM s GROUP BY user_id, k")
def session_truth(spark, sf):
    ev = tables.event_records(spark, sf).withColumn("event_ts", F.col("event_ts").cast("timestamp"))
    return ev.groupBy("unit", F.session_window("event_ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("unit", "n")


@query("SELECT a.event_id AS view_id, b.event_id AS buy_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = (SELECT min(event_type) FROM events) AND b.event_type = (SELECT max(event_type) FROM events) AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
def interval_join_truth(spark, sf):
    ev = tables.event_records(spark, sf)
    kinds = ev.agg(F.min("key").alias("lo"), F.max("key").alias("hi"))
    a = ev.join(F.broadcast(kinds.select("lo")), F.col("key") == F.col("lo")).select(F.col("unit").alias("ua"), F.col("record_id").alias("view_id"), F.col("event_ts").alias("ta"))
    b = ev.join(F.broadcast(kinds.select("hi")), F.col("key") == F.col("hi")).select(F.col("unit").alias("ub"), F.col("record_id").alias("buy_id"), F.col("event_ts").alias("tb"))
    near = (F.col("tb") >= F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("INTERVAL 1 DAY"))
    return a.join(b, (F.col("ua") == F.col("ub")) & near).select("view_id", "buy_id")


@query("SELECT event_id AS record_id, (SELECT count(*) FROM (SELECT unnest(range(0, 24)) AS h) WHERE date_trunc('day', ts) + to_hours(h) <= ts)::INTEGER AS trigger_idx FROM events")
def range_join_trigger(spark, sf):
    """Record to trigger range join, rewritten to arithmetic."""
    ev = tables.event_records(spark, sf).withColumn("event_ts", F.col("event_ts").cast("timestamp")).withColumn("arrival_ts", F.col("event_ts"))
    return timing.assign_triggers(timing.assign_windows(ev), 24, "arrival").select("record_id", "trigger_idx")


@query("SELECT json_extract_string(props, '$.k') AS key, count(*) AS n, round(sum(greatest(-100.0, least(100.0, value))), 6) AS total FROM events GROUP BY 1")
def json_key_hist(spark, sf):
    ev = tables.event_records(spark, sf, "props.k")
    return ev.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(bounding.clamped(F.col("value"), 100)), 6).alias("total"))


@query("SELECT regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS key, count(*) AS n FROM pages GROUP BY 1")
def host_hist(spark, sf):
    return tables.host_records(spark, sf).groupBy("key").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT key, count(*) AS n FROM (SELECT unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]+'))) AS key FROM documents) GROUP BY key")
def token_hist(spark, sf):
    return tables.token_records(spark, sf).groupBy("key").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT role AS key, count(*) AS n, count(DISTINCT conv_id) AS users FROM conversations GROUP BY role")
def role_hist(spark, sf):
    return tables.role_records(spark, sf).groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("unit").alias("users"))


@query("SELECT r_name AS region, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def region_label_broadcast(spark, sf):
    """Dimension joins; Spark broadcasts the small sides by their size."""
    li, s, n, r = (tables.load(spark, sf, x) for x in ("lineitem", "supplier", "nation", "region"))
    lab = s.join(n, s.s_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey).select("s_suppkey", F.col("r_name").alias("region"))
    return li.select("l_suppkey").join(lab, F.col("l_suppkey") == F.col("s_suppkey")).groupBy("region").agg(F.count(F.lit(1)).alias("n"))


@query(oracle.releases(oracle.lines(), SUPPLIER))
def parallel_ranges(spark, sf):
    """Disjoint key ranges folded one by one after a global bounding: the same releases."""
    deltas = replay.delta(tables.line_records(spark, sf), SUPPLIER)
    part = F.pmod(F.xxhash64("key"), F.lit(3))
    out = None
    for k in range(3):
        one = replay.fold(replay.timelines(deltas.filter(part == k), SUPPLIER), SUPPLIER)
        out = one if out is None else out.unionByName(one)
    return rounded(out)


# --- experiment workloads ----------------------------------------------------------------

MOMENTS = replace(SUPPLIER, measures=(Measure("count"), Measure("qty", "l_quantity", 50.0), Measure("sq", "l_quantity", 50.0, square=True)))
MOMENTS_HAT = "sq_hat / greatest(count_hat, 1.0) - pow(qty_hat / greatest(count_hat, 1.0), 2)"
gate_query("release_variance", MOMENTS, oracle.lines(), suppliers, f"SELECT key, trigger_idx, round(greatest(0.0, {MOMENTS_HAT}), 6) AS variance_hat FROM releases", lambda df, spec: df.select("key", "trigger_idx", F.greatest(F.lit(0.0), F.expr(MOMENTS_HAT)).alias("variance_hat")))


@query(oracle.releases(oracle.lines(), SUPPLIER))
def release_table_function(spark, sf):
    """The gate as a SQL table function over deltas: the same releases."""
    from .. import surface

    surface.register_gate(spark, SUPPLIER, "veil_releases")
    deltas = replay.delta(tables.line_records(spark, sf), SUPPLIER)
    return rounded(spark.sql("SELECT * FROM veil_releases(TABLE({d}) PARTITION BY key ORDER BY trigger_idx)", d=deltas))


def spec_grid(name: str, specs: dict, records, rec_sql: str):
    """Utility of the main method for several specs, one row each."""
    parts = [f"SELECT {v} AS {name}, x.* FROM (" + oracle.releases(rec_sql, s, "").rstrip() + f", {TRUTH}, {LAST} " + oracle.utility("truth", "est", "count_hat") + ") x" for v, s in specs.items()]

    def run(spark, sf):
        rec = records(spark, sf)
        truth, out = aggregate.plain_hist(rec), None
        for v, s in specs.items():
            row = metrics.utility(truth, replay.snapshot(replay.run(rec, s), s), "count_hat").withColumn(name, F.lit(v))
            out = row if out is None else out.unionByName(row)
        return rounded(out)

    return run, " UNION ALL ".join(parts)


def register_grid(query_name: str, name: str, specs: dict, records, rec_sql: str) -> None:
    Q[query_name] = spec_grid(name, specs, records, rec_sql)


register_grid("c_sweep_main", "c", {c: replace(FORUM, bound=c) for c in (2, 5, 10, 17, 25, 32, 50)}, tables.brand_type_records, oracle.FORUM)
register_grid("trigger_sweep_main", "t", {t: replace(FORUM, timing=Timing(t)) for t in (4, 8, 16, 32)}, tables.brand_type_records, oracle.FORUM)
register_grid("eps_sweep_main", "eps", {e: replace(FORUM, budget=Budget(eps=float(e))) for e in (2, 6, 12)}, tables.brand_type_records, oracle.FORUM)
register_grid("noise_draws_main", "draw", {i: replace(FORUM, secret=f"{TEST_SECRET}-{i}") for i in (1, 2, 3)}, tables.brand_type_records, oracle.FORUM)

GAIN_COLUMNS = ("linf", "l1", "l2")
GAINS_SQL = (
    oracle.releases(oracle.FORUM, FORUM, "").rstrip()
    + f", {TRUTH}, {LAST}, b AS ({once_sql('users', 'total', once_plan(FORUM, 16), TEST_SECRET, '16', HIST)}), o AS ({oracle.utility('truth', 'est', 'count_hat')}), t AS ({oracle.utility('truth', 'b', 'value_hat')}) SELECT "
    + ", ".join(f"round(1 - o.{n} / t.{n}, 5) AS {n}_change, round(t.{n} / o.{n}, 5) AS {n}_ratio" for n in GAIN_COLUMNS)
    + " FROM o, t"
)


@query(GAINS_SQL)
def utility_gains(spark, sf):
    """Errors of the main method relative to the repeated query."""
    rec = tables.brand_type_records(spark, sf)
    truth = aggregate.plain_hist(rec)
    ours = metrics.utility(truth, replay.snapshot(replay.run(rec, FORUM), FORUM), "count_hat")
    theirs = metrics.utility(truth, baselines.repeated_queries(replay.delta(rec, FORUM), FORUM))
    out = metrics.relative_change(ours, theirs, GAIN_COLUMNS)
    return out.select(*[F.round(c, 5).alias(c) for c in out.columns])


def three_methods(spark, rec: DataFrame, spec: StreamSpec, draws: tuple[str, ...]) -> DataFrame:
    """method and the mean over noise draws of keys, linf, l1 and l2, with standard errors."""
    truth, deltas = aggregate.plain_hist(rec), materialize(replay.delta(rec, spec), "grid-deltas")
    batches = materialize(replay.delta(rec, replace(spec, gate=GateConfig(count_mode="batch_additive"))), "grid-batches")
    rows = None
    for d in draws:
        s = replace(spec, secret=d)
        runs = {"main": (replay.snapshot(replay.fold(replay.timelines(deltas, s), s), s), "count_hat"), "repeated": (baselines.repeated_queries(deltas, s), "value_hat"), "incremental": (baselines.incremental_batches(batches, s), "value_hat")}
        for name, (est, value) in runs.items():
            row = metrics.utility(truth, est, value).select(F.lit(name).alias("method"), F.col("keys").cast("double").alias("keys"), "linf", "l1", "l2")
            rows = row if rows is None else rows.unionByName(row)
    out = metrics.average(rows, ["method"], ["keys", "linf", "l1", "l2"])
    return out.select("method", *[F.round(c, 4).alias(c) for c in out.columns if c != "method"])


def three_methods_sql(rec: str, spec: StreamSpec, draws: tuple[str, ...], rounds: int) -> str:
    t, k, parts = spec.timing.triggers, min(spec.bound, spec.timing.triggers), []
    batch = replace(spec, gate=GateConfig(count_mode="batch_additive"))
    for d in draws:
        rep = once_sql("users", "total", once_plan(spec, t), d, str(t), HIST)
        inc = f"SELECT key, sum(value_hat) AS value_hat FROM ({once_sql('users', 's0', once_plan(spec, k), d, 'trig', 'delta', kind='batch')}) GROUP BY key"
        parts += [
            f"SELECT 'main' AS method, x.* FROM ({oracle.releases(rec, replace(spec, secret=d), '', rounds).rstrip()}, {TRUTH}, {LAST} {oracle.utility('truth', 'est', 'count_hat')}) x",
            f"SELECT 'repeated' AS method, x.* FROM (WITH {oracle.delta_ctes(rec, spec)}, {TRUTH}, est AS ({rep}) {oracle.utility('truth', 'est', 'value_hat')}) x",
            f"SELECT 'incremental' AS method, x.* FROM (WITH {oracle.delta_ctes(rec, batch)}, {TRUTH}, est AS ({inc}) {oracle.utility('truth', 'est', 'value_hat')}) x",
        ]
    names = ("keys", "linf", "l1", "l2")
    return f"SELECT method, {', '.join(f'round(avg({n}), 4) AS {n}, round(coalesce(stddev({n}), 0) / sqrt(count(*)), 4) AS {n}_se' for n in names)} FROM ({' UNION ALL '.join(parts)}) GROUP BY method"


DRAWS = tuple(f"{TEST_SECRET}-{i}" for i in (1, 2, 3))
FORUM_100, FORUM_1000 = (replace(FORUM, timing=Timing(t)) for t in (100, 1000))
TAIL_16, TAIL_100, TAIL_1000 = (replace(FORUM, bound=32, timing=Timing(t)) for t in (16, 100, 1000))


def register_methods(name: str, spec: StreamSpec, records, rec_sql: str, draws: tuple[str, ...] = DRAWS) -> None:
    def run(spark, sf):
        return three_methods(spark, records(spark, sf), spec, draws)

    run.__name__ = name
    Q[name] = (run, three_methods_sql(rec_sql, spec, draws, 4))


register_methods("forum_methods_t100", FORUM_100, tables.brand_type_records, oracle.FORUM)
register_methods("forum_methods_t1000", FORUM_1000, tables.brand_type_records, oracle.FORUM)
register_methods("synthetic_long_tail", TAIL_16, lambda spark, sf: synth.zipf_mandelbrot(spark, 40_000, 4_000), oracle.zipf(40_000, 4_000), DRAWS[:1])
register_methods("long_tail_methods_t100", TAIL_100, lambda spark, sf: synth.zipf_mandelbrot(spark, 60_000, 1_000), oracle.zipf(60_000, 1_000))
register_methods("long_tail_methods_t1000", TAIL_1000, lambda spark, sf: synth.zipf_mandelbrot(spark, 60_000, 1_000), oracle.zipf(60_000, 1_000), DRAWS[:1])


@query(oracle.loads(oracle.UNIFORM_KEYS, SPARSE, 3))
def uniform_key_loads(spark, sf):
    """Orders under uniform keys, as many as customers: state loads of the naive gate against those with forecasts."""
    cost = replay.run(tables.uniform_key_records(spark, sf), SPARSE, "cost")
    return cost.agg(F.count(F.lit(1)).alias("keys"), *[F.sum(c).alias(c) for c in ("tests", "wasted", "loads_naive", "loads_forecast")])


#: Two-day windows every day: a record touches two windows, and noise is scaled for both.
SLIDING = StreamSpec(secret=TEST_SECRET, bound=2, timing=Timing(8), budget=Budget(22, 2e-9), measures=(Measure("count"), Measure("sum_value", "value", 300.0)))
SLIDING_SQL = f"""SELECT unit, length(w::VARCHAR) || ':' || w || '{{"key":"' || event_type || '"}}' AS key, rid, value FROM (
SELECT user_id AS unit, event_type, event_id AS rid, value, unnest([epoch_us(date_trunc('day', ts)), epoch_us(date_trunc('day', ts)) - 86400000000]) AS w FROM (
SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY {oracle.trigger("event_id", 8)}, event_id) AS k FROM events) WHERE k <= 1)"""


@query(
    oracle.releases(
        SLIDING_SQL,
        SLIDING,
        "SELECT CAST(make_timestamp(split_part(split_part(key, '{', 1), ':', 2)::BIGINT) AS DATE) AS day, split_part(key, '\"', 4) AS key, trigger_idx, round, cause, round(users_hat, 6) AS users_hat, round(count_hat, 6) AS count_hat, round(sum_value_hat, 6) AS sum_value_hat, round(sum_value_hat / greatest(count_hat, 1.0), 6) AS avg_value_hat FROM releases",
        2,
    )
)
def sliding_releases(spark, sf):
    """Counts and means of one record a user in two-day windows that begin every day."""
    from ..surface import PrivateHistogram

    ev = tables.event_records(spark, sf)
    made = PrivateHistogram(ev).unit("unit").keys("key").record_id("record_id").count().avg("value", 300).bound(1).triggers(8).budget(22, 2e-9).secret(TEST_SECRET)
    out = made.window("event_ts", 172_800, 86_400).releases()
    return rounded(out.withColumn("day", F.to_date("window_start")).drop("window_start"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {n: f for n, (f, _) in Q.items()}


def oracle_sql() -> dict[str, str]:
    return {n: s for n, (_, s) in Q.items() if s}
