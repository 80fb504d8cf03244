"""Every method, baseline, measure and experiment as a named query with its SQL twin."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import noise, privacy, shares
from .operators import baselines, budget, derive, leakage, metrics, multilevel, owner_sync, query, release, steps, truncate
from .params import Params
from .plans import oracles as sql
from .plans import workloads as wl
from .plans.views import REGISTERED, ViewSpec
from .sources.tables import load, stored


@dataclass(frozen=True)
class Query:
    run: Callable[[SparkSession, str], DataFrame]
    sql: str | None = None


QUERIES: dict[str, Query] = {}


def add(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = Query(run, sql)


def sums(spec: ViewSpec, spark: SparkSession, sf_dir: str, strict: bool = True) -> DataFrame:
    """The step summaries, computed once and kept as a file of one row a step: traces read them several times."""
    return kept(derive.summaries(spec, *wl.sides(spec, spark, sf_dir), strict=strict))


def kept(steps_frame: DataFrame) -> DataFrame:
    return stored(steps_frame.coalesce(1), "summaries")


Run = tuple[str, str, Params]
COLUMNS = ["run", "step", "c", "fires", "sz", "want", "real_out", "dummy_out", "purge_real", "purge_dummy", "discarded", "deferred", "truth", "answer", "view_rows", "l1"]


def shown(d: DataFrame) -> DataFrame:
    big = ("real_out", "dummy_out", "truth", "answer", "view_rows", "l1", "deferred", "c", "want")
    return d.select(*(F.round("sz", 6).alias("sz") if c == "sz" else F.col(c).cast("long").alias(c) if c in big else F.col(c) for c in COLUMNS))


SHOWN_SQL = "SELECT " + ", ".join("round(sz, 6) AS sz" if c == "sz" else c if c in ("run", "step", "fires") else f"CAST({c} AS BIGINT) AS {c}" for c in COLUMNS) + " FROM traced"


def add_trace(name: str, spec: ViewSpec, runs: list[Run]) -> None:
    add(name, lambda s, d: shown(release.trace(sums(spec, s, d), runs)), sql.trace_sql(spec, runs, SHOWN_SQL))


def add_over_trace(name: str, spec: ViewSpec, runs: list[Run], f: Callable[[DataFrame], DataFrame], select: str) -> None:
    add(name, lambda s, d: f(release.trace(sums(spec, s, d), runs)), sql.trace_sql(spec, runs, select))


def add_over_sums(name: str, spec: ViewSpec, f: Callable[[DataFrame], DataFrame], select: str) -> None:
    add(name, lambda s, d: f(sums(spec, s, d)), f"WITH {sql.sums_ctes(spec)} {select}")


def both(p: Params, tag: str = "") -> list[Run]:
    return [(f"interval{tag}", "interval", p), (f"threshold{tag}", "threshold", p)]


ERRORS_SQL = """SELECT run, round(avg(abs(truth - answer)), 6) AS mean_l1,
  round(avg(CASE WHEN truth > 0 THEN abs(truth - answer) / CAST(truth AS DOUBLE) END), 6) AS rel_mean,
  round(avg(abs(truth - answer)) / avg(truth), 6) AS rel_of_means FROM traced GROUP BY run"""
SIZES_SQL = """SELECT run, round(avg(view_rows), 6) AS mean_rows, round(avg(view_rows) * 16 * 2 / 1e6, 6) AS mean_mb,
  CAST(max(view_rows) AS BIGINT) AS last_rows FROM traced GROUP BY run"""
SWEEP_SQL = """SELECT run, round(avg(l1), 6) AS mean_l1, round(avg(view_rows), 6) AS mean_rows, CAST(sum(view_rows) AS BIGINT) AS scanned_rows,
  CAST(sum(CASE WHEN fires THEN 1 ELSE 0 END) AS BIGINT) AS releases FROM traced GROUP BY run"""


def sweep(t: DataFrame) -> DataFrame:
    """Error beside query cost (rows that one query at every step scans in all) and number of releases, by run."""
    return t.groupBy("run").agg(F.round(F.avg("l1"), 6).alias("mean_l1"), F.round(F.avg("view_rows"), 6).alias("mean_rows"), F.sum("view_rows").cast("long").alias("scanned_rows"), F.sum(F.col("fires").cast("long")).alias("releases"))


# --- truth and truncation ------------------------------------------------------------------------------------------

for _spec in (wl.W1, wl.W1D, wl.W1W, wl.W2, wl.W2M240, wl.W2M72, wl.W2M24):
    add(
        f"{_spec.name}_truth_by_step",
        lambda s, d, spec=_spec: derive.true_pairs(spec, *wl.sides(spec, s, d)).groupBy(F.col("born_step").alias("step")).agg(F.count("*").alias("n_true")),
        f"WITH {sql.pairs_ctes(_spec)} SELECT born_step AS step, count(*) AS n_true FROM truth GROUP BY 1",
    )
for _spec in (wl.W1, wl.W1D, wl.W1W, wl.W2, wl.W2B30, wl.W2M240, wl.W2M72):
    add(
        f"{_spec.name}_pairs_truncated",
        lambda s, d, spec=_spec: derive.derive(spec, *wl.sides(spec, s, d)),
        f"WITH {sql.pairs_ctes(_spec)} SELECT born_step, key, l_rid, r_rid FROM kept",
    )
for _spec in (wl.W1W, wl.W2, wl.W2S):
    add_over_sums(f"{_spec.name}_step_summaries", _spec, lambda d: d, "SELECT * FROM sums")
for _w in (1, 2, 10):

    def _blocks(s: SparkSession, d: str, omega: int = _w) -> DataFrame:
        left, right = (f(s, d) for f in (wl.lines_side("l_partkey", "R", 5), wl.lines_side("l_partkey", "A", 5)))
        left = left.select("key", "step", F.col("rid").alias("l_rid"))
        right = right.select("key", "step", F.col("rid").alias("r_rid"))
        return truncate.merge_join(left, right, ["key", "step"], ["l_rid"], ["r_rid"], omega, truncate.HOT_GROUP).select("key", "step", "l_rid", "r_rid")

    _side = "SELECT *, (row_number() OVER (PARTITION BY key, step ORDER BY rid) - 1) // {} AS blk FROM ({})"
    add(
        f"trunc_join_w{_w}",
        _blocks,
        f"WITH a AS ({_side.format(_w, sql.lines_sql('l_partkey', 'R', 5))}), b AS ({_side.format(_w, sql.lines_sql('l_partkey', 'A', 5))}) "
        "SELECT a.key, a.step, a.rid AS l_rid, b.rid AS r_rid FROM a JOIN b USING (key, step, blk)",
    )
add(
    "trunc_cap_private",
    lambda s, d: derive.derive(wl.w2m(240, 120, 2), *wl.sides(wl.w2m(240, 120, 2), s, d)),
    f"WITH {sql.pairs_ctes(wl.w2m(240, 120, 2))} SELECT born_step, key, l_rid, r_rid FROM kept",
)
add(
    "trunc_filter_dummies",
    lambda s, d: wl.W1W.right(s, d).withColumn("is_view", F.col("step") > 100).groupBy("is_view").agg(F.count("*").alias("n")),
    f"SELECT step > 100 AS is_view, count(*) AS n FROM ({sql.lines_sql('l_orderkey', 'R', 10)}) GROUP BY 1",
)


def _theta(s: SparkSession, d: str) -> DataFrame:
    """Errors with the purchases of the same user and step that are worth more: no equality to rank by."""
    e = load(s, d, "events").select("event_id", "user_id", "event_type", "value", wl.step_of_hours(F.col("ts"), wl.EVENTS_ORIGIN, 240).alias("born_step"))
    side = lambda kind, *names: e.filter(F.col("event_type") == kind).select("born_step", F.col("user_id").alias("key"), *(F.col(c).alias(n) for c, n in zip(("event_id", "value"), names, strict=True)))
    return truncate.theta_join(side("error", "l_rid", "l_value"), side("purchase", "r_rid", "r_value"), ["born_step", "key"], lambda: F.col("l_value") < F.col("r_value"), 2).select("born_step", "key", "l_rid", "r_rid")


add("trunc_theta", _theta)
add(
    "max_contribution",
    lambda s, d: derive.true_pairs(wl.W2M240, *wl.sides(wl.W2M240, s, d)).groupBy("key", "l_rid").agg(F.count("*").alias("k")).agg(F.max("k").alias("most")),
    f"WITH {sql.pairs_ctes(wl.W2M240)} SELECT max(k) AS most FROM (SELECT count(*) AS k FROM truth GROUP BY key, l_rid)",
)
add(
    "lifetime_contribution",
    lambda s, d: derive.derive(wl.W2, *wl.sides(wl.W2, s, d)).groupBy("key", "l_rid").agg(F.count("*").alias("k")).groupBy("k").agg(F.count("*").alias("rows")),
    f"WITH {sql.pairs_ctes(wl.W2)} SELECT k, count(*) AS rows FROM (SELECT count(*) AS k FROM kept GROUP BY key, l_rid) GROUP BY k",
)

# --- budget, padding, shares, noise --------------------------------------------------------------------------------

add(
    "budget_ledger",
    lambda s, d: budget.ledger(wl.W1W.left(s, d), 120, wl.W1W.params),
    f"SELECT rid, key, step, CAST(greatest(0, least(120 - step + 1, 10)) AS BIGINT) AS used, CAST(10 - greatest(0, least(120 - step + 1, 10)) AS BIGINT) AS budget_left FROM ({sql.orders_sql(10)})",
)
add(
    "budget_active",
    lambda s, d: budget.active(wl.W1W.left(s, d), 120, wl.W1W.params).groupBy("step").agg(F.count("*").alias("n")),
    f"SELECT step, count(*) AS n FROM ({sql.orders_sql(10)}) WHERE step BETWEEN 111 AND 120 GROUP BY 1",
)
add(
    "budget_retired",
    lambda s, d: budget.retired(wl.W1W.left(s, d), 120, wl.W1W.params).agg(F.count("*").alias("n")),
    f"SELECT count(*) AS n FROM ({sql.orders_sql(10)}) WHERE step <= 110",
)
add(
    "step_padding",
    lambda s, d: steps.pad_counted(wl.W1W.left(s, d)),
    f"WITH b AS (SELECT step, count(*) AS n FROM ({sql.orders_sql(10)}) GROUP BY 1) SELECT step, n AS n_rows, (SELECT max(n) FROM b) - n AS n_dummy, (SELECT max(n) FROM b) AS n_total FROM b",
)
add(
    "step_padding_physical",
    lambda s, d: steps.pad_physical(wl.W1W.left(s, d)).groupBy("step").agg(F.count("*").alias("n"), F.count_if("is_real").alias("n_real")),
    f"WITH b AS (SELECT step, count(*) AS n FROM ({sql.orders_sql(10)}) GROUP BY 1) SELECT step, (SELECT max(n) FROM b) AS n, n AS n_real FROM b",
)


def _shares(s: SparkSession, d: str) -> DataFrame:
    o = load(s, d, "orders").select("o_orderkey", "o_custkey")
    a, b = shares.split(F.col("o_custkey"), noise.hash_word("7", "s0", "share", F.col("o_orderkey")))
    return o.select("o_orderkey", a.alias("share_0"), b.alias("share_1"), shares.recover(a, b).alias("recovered"))


_W = sql.word("'7'", 0, "share", "o_orderkey")
add("xor_shares", _shares, f"SELECT o_orderkey, {_W} AS share_0, xor({_W}, o_custkey) AS share_1, o_custkey AS recovered FROM orders")


def _reshare(s: SparkSession, d: str) -> DataFrame:
    o = load(s, d, "orders").select("o_orderkey", "o_custkey")
    a, b = shares.reshare(F.col("o_custkey"), *(noise.hash_word("7", f"s{k}", "reshare", F.col("o_orderkey")) for k in (0, 1)))
    return o.select("o_orderkey", a.alias("share_0"), b.alias("share_1"))


_J = sql.joint("'7'", "reshare", "o_orderkey")
add("reshare", _reshare, f"SELECT o_orderkey, {_J} AS share_0, xor({_J}, o_custkey) AS share_1 FROM orders")


def _nserver(s: SparkSession, d: str) -> DataFrame:
    o = load(s, d, "orders").select("o_orderkey", "o_custkey")
    parts = shares.split_n(F.col("o_custkey"), [noise.hash_word("7", f"s{k}", "n", F.col("o_orderkey")) for k in (0, 1)])
    return o.select("o_orderkey", *(x.alias(f"share_{k}") for k, x in enumerate(parts)), shares.recover_array(F.array(*parts)).alias("recovered"))


_N = [sql.word("'7'", k, "n", "o_orderkey") for k in (0, 1)]
add("nserver_shares", _nserver, f"SELECT o_orderkey, {_N[0]} AS share_0, {_N[1]} AS share_1, xor(xor({_N[0]}, {_N[1]}), o_custkey) AS share_2, o_custkey AS recovered FROM orders")


def daily_steps(s: SparkSession, d: str) -> DataFrame:
    """The steps at which orders arrive, day by day: each is a step that draws noise."""
    return wl.orders_side(1)(s, d).select("step").distinct()


_DAILY = f"(SELECT DISTINCT step FROM ({sql.orders_sql(1)}))"


def _noise(s: SparkSession, d: str, servers: int = 2) -> DataFrame:
    z = noise.joint_word("7", "rel", F.col("step"), servers)
    return daily_steps(s, d).select("step", z.alias("word"), F.round(noise.laplace(z, 10 / 1.5), 6).alias("noise"))


for _name, _n in (("joint_noise", 2), ("joint_noise_three_servers", 3)):
    _z = sql.joint("'7'", "rel", "step", _n)
    add(_name, lambda s, d, n=_n: _noise(s, d, n), f"SELECT step, {_z} AS word, round({sql.laplace(_z, '10 / 1.5')}, 6) AS noise FROM {_DAILY}")
add(
    "agg_noise_stats",
    lambda s, d: _noise(s, d).agg(F.round(F.avg("noise"), 4).alias("mean"), F.round(F.var_pop("noise"), 3).alias("variance"), F.round(F.corr(F.signum("noise"), F.abs("noise")), 4).alias("sign_size_corr")),
    f"SELECT round(avg(noise), 4) AS mean, round(var_pop(noise), 3) AS variance, round(corr(sign(noise), abs(noise)), 4) AS sign_size_corr FROM ({QUERIES['joint_noise'].sql})",
)
add(
    "geometric_noise",
    lambda s, d: daily_steps(s, d).select("step", noise.geometric(noise.joint_word("7", "geo", F.col("step")), 10 / 1.5).alias("k")),
    f"""WITH z AS (SELECT step, {sql.joint("'7'", "geo", "step")} AS w, exp(-1.5 / 10) AS q FROM {_DAILY})
      SELECT step, CAST(greatest(0, floor(ln(((w & 2147483647) + 0.5) / 2147483648.0 * (1 + q) / (2 * q)) / ln(q)) + 1) * (CASE WHEN w >= 2147483648 THEN 1 ELSE -1 END) AS BIGINT) AS k FROM z""",
)

# --- counter, releases, views --------------------------------------------------------------------------------------

add_over_sums("counter_by_step", wl.W1W, derive.counter, "SELECT step, n_real, CAST(sum(n_real) OVER (ORDER BY step) AS BIGINT) AS c FROM sums")
_P1, _P2 = wl.W1W.params, wl.W2.params
add_trace("interval_release", wl.W1W, [("interval", "interval", _P1)])
add_trace("interval_release_w2", wl.W2, [("interval", "interval", _P2)])
add_trace("interval_purge", wl.W1W, [("interval", "interval", _P1.but(purge_every=50, purge_size=5))])
add_trace("threshold_release", wl.W1W, [("threshold", "threshold", _P1)])
add_trace("threshold_release_w2", wl.W2, [("threshold", "threshold", _P2)])
add_trace("threshold_purge", wl.W1W, [("threshold", "threshold", _P1.but(purge_every=100, purge_size=10))])
add_trace("threshold_mechanism_scale", wl.W1W, [("threshold", "threshold", _P1.but(scale_release="mechanism"))])
add_trace("w2m_72_releases", wl.W2M72, both(wl.W2M72.params))
for _name, _sizes in (("threshold_fold", release.threshold_sizes), ("threshold_grouped", release.threshold_sizes_grouped)):
    add(
        _name,
        lambda s, d, f=_sizes: shown(release.series(release.buffer_depth(f(release.with_runs(sums(wl.W1W, s, d), [("threshold", "threshold", _P1)]))))),
        QUERIES["threshold_release"].sql,
    )
_RESET = _P1.but(purge_every=35, purge_size=5, purge_resets_counter=True)
add_trace("purge_resets_counter", wl.W1W, both(_RESET))


def _system(s: SparkSession, d: str) -> DataFrame:
    """Two runs on words from the system: no seed foretells them, so only what holds for all noise is shown."""
    t = release.trace(sums(wl.W1W, s, d), both(_P1.but(system_noise=True)))
    ok = (F.col("want") == F.col("real_out") + F.col("dummy_out")) & (F.col("deferred") >= 0) & (F.col("fires") | (F.col("want") == 0))
    return t.groupBy("run").agg(F.count("*").alias("steps"), F.bool_and(ok).alias("consistent"))


add("system_noise", _system, f"WITH {sql.sums_ctes(wl.W1W)} SELECT run, count(*) AS steps, TRUE AS consistent FROM sums, (VALUES ('interval'), ('threshold')) AS v(run) GROUP BY run")


def _udtf(s: SparkSession, d: str) -> DataFrame:
    from .functions.udtf import trace_with_udtf

    return trace_with_udtf(sums(wl.W1W, s, d), both(_P1))


add("udtf_release_trace", _udtf, sql.trace_sql(wl.W1W, both(_P1), "SELECT run, step, CAST(c AS BIGINT) AS c, fires, CAST(want AS BIGINT) AS want, CAST(real_out AS BIGINT) AS real_out, CAST(deferred AS BIGINT) AS deferred, CAST(discarded AS BIGINT) AS discarded FROM traced"))


def placed(spec: ViewSpec, run: Run, s: SparkSession, d: str) -> DataFrame:
    left, right = wl.sides(spec, s, d)
    t = kept(release.trace(kept(derive.summaries(spec, left, right)), [run]))
    return release.place_rows(derive.numbered(derive.derive(spec, left, right)), t, run[2].purge_every)


PLACED_SQL = """numbered AS (SELECT *, row_number() OVER (PARTITION BY born_step ORDER BY ((key + l_rid) % 64 + 64) % 64, key, l_rid, r_rid) AS ord FROM kept),
  q AS (SELECT step, (step - 1) // purge_every AS epoch, real_out + purge_real AS k,
      sum(real_out + purge_real) OVER (PARTITION BY (step - 1) // purge_every ORDER BY step) AS hi,
      sum(n_real) OVER (PARTITION BY (step - 1) // purge_every ORDER BY step) - n_real AS before FROM traced),
  placed AS (SELECT n.born_step, n.key, n.l_rid, n.r_rid, q.step AS release_step FROM numbered n JOIN q o ON o.step = n.born_step
    JOIN q ON q.epoch = o.epoch AND q.k > 0 AND o.before + n.ord > q.hi - q.k AND o.before + n.ord <= q.hi)"""


def placed_sql(spec: ViewSpec, run: Run, select: str) -> str:
    return f"WITH RECURSIVE {sql.runs_values([run])}, {sql.sums_ctes(spec)}, {sql.trace_ctes([run])}, {PLACED_SQL} {select}"


_VIEW = ["born_step", "key", "l_rid", "r_rid", "release_step"]
_I, _T = ("interval", "interval", _P1), ("threshold", "threshold", _P1)
_IP = ("interval", "interval", _P1.but(purge_every=50, purge_size=5))
for _name, _run in (("interval_view_rows", _I), ("threshold_view_rows", _T), ("purged_view_rows", _IP)):
    add(_name, lambda s, d, run=_run: placed(wl.W1W, run, s, d).select(*_VIEW), placed_sql(wl.W1W, _run, f"SELECT {', '.join(_VIEW)} FROM placed"))
add("view_count", lambda s, d: query.answer(placed(wl.W1W, _I, s, d), 200), placed_sql(wl.W1W, _I, "SELECT count(*) AS answer FROM placed WHERE release_step <= 200"))
add(
    "view_groupby",
    lambda s, d: query.answer(placed(wl.W1W, _I, s, d), 240, F.count("*").alias("n"), F.min("born_step").alias("oldest"), F.round(F.avg(F.col("release_step") - F.col("born_step")), 6).alias("mean_wait"), by=["release_step"]),
    placed_sql(wl.W1W, _I, "SELECT release_step, count(*) AS n, min(born_step) AS oldest, round(avg(release_step - born_step), 6) AS mean_wait FROM placed WHERE release_step <= 240 GROUP BY 1"),
)


def _with_buffer(s: SparkSession, d: str) -> DataFrame:
    left, right = wl.sides(wl.W1W, s, d)
    pairs = derive.derive(wl.W1W, left, right).withColumn("is_view", F.lit(True))
    view = placed(wl.W1W, _I, s, d)
    late = pairs.join(view.filter("release_step <= 205").select("born_step", "key", "l_rid", "r_rid"), ["born_step", "key", "l_rid", "r_rid"], "left_anti")
    return query.answer(view, 205, buffer=late)


add("view_count_with_buffer", _with_buffer, f"WITH {sql.pairs_ctes(wl.W1W)} SELECT count(*) AS answer FROM kept WHERE born_step <= 205")
add(
    "view_dummy_rows",
    lambda s, d: release.dummy_rows(release.trace(sums(wl.W1W, s, d), [_T])).groupBy("release_step").agg(F.count("*").alias("n")),
    sql.trace_sql(wl.W1W, [_T], "SELECT step AS release_step, CAST(dummy_out + purge_dummy AS BIGINT) AS n FROM traced WHERE dummy_out + purge_dummy > 0"),
)


def _rewritten(s: SparkSession, d: str) -> DataFrame:
    from .plans.views import rewrite

    return rewrite(s, "SELECT count(*) AS answer, count(DISTINCT key) AS keys FROM w1w", wl.W1W, placed(wl.W1W, _I, s, d), 150)


add("view_sql_rewrite", _rewritten, placed_sql(wl.W1W, _I, "SELECT count(*) AS answer, count(DISTINCT key) AS keys FROM placed WHERE release_step <= 150"))

# --- baselines -----------------------------------------------------------------------------------------------------

_TRUTH = "CAST(sum(n_true) OVER (ORDER BY step) AS BIGINT)"
add_over_sums("nm_by_step", wl.W1W, baselines.nm, f"SELECT step, {_TRUTH} AS truth, {_TRUTH} AS answer, CAST(0 AS BIGINT) AS view_rows, CAST(sum(up_left + up_right) OVER (ORDER BY step) AS BIGINT) AS scanned_rows FROM sums")
add("nm_query", lambda s, d: baselines.nm_query(wl.W1W, *wl.sides(wl.W1W, s, d), 200), f"WITH {sql.pairs_ctes(wl.W1W)} SELECT count(*) AS answer FROM truth WHERE born_step <= 200")
for _name, _trunc in (("ep", True), ("ep_exact", False)):
    _pad = "CAST(sum(n_padded) OVER (ORDER BY step) AS BIGINT)"
    add_over_sums(_name, wl.W1W, lambda d, t=_trunc: baselines.ep(d, t), f"SELECT step, {_TRUTH} AS truth, CAST(sum({'n_real' if _trunc else 'n_true'}) OVER (ORDER BY step) AS BIGINT) AS answer, {_pad} AS view_rows, {_pad} AS scanned_rows FROM sums")
_OLD = "CAST(sum(CASE WHEN step <= 5 THEN n_real ELSE 0 END) OVER (ORDER BY step) AS BIGINT)"
add_over_sums("otm", wl.W1W, lambda d: baselines.otm(d, 5), f"SELECT step, {_TRUTH} AS truth, {_OLD} AS answer, {_OLD} AS view_rows, {_OLD} AS scanned_rows FROM sums")
add_over_sums("immediate_transcript", wl.W1W, baselines.immediate, "SELECT step, n_real AS observed_rows FROM sums")
_ONCE = f"CAST(greatest(0, floor(sum(n_real) + {sql.laplace(sql.joint(chr(39) + '7' + chr(39), 'once', '0'), '10 / 1.5')} + 0.5)) AS BIGINT)"
add_over_sums("one_shot", wl.W1W, lambda d: baselines.one_shot(d, _P1), f"SELECT CAST(sum(n_real) AS BIGINT) AS c, {_ONCE} AS view_rows, least(CAST(sum(n_real) AS BIGINT), {_ONCE}) AS answer FROM sums")

# --- measures ------------------------------------------------------------------------------------------------------

add_over_trace("errors_w1w", wl.W1W, both(_P1), lambda t: metrics.errors(t, ["run"]), ERRORS_SQL)
add_over_trace("errors_w2", wl.W2, both(_P2), lambda t: metrics.errors(t, ["run"]), ERRORS_SQL)
add_over_trace("errors_w2_b30", wl.W2B30, both(wl.W2B30.params), lambda t: metrics.errors(t, ["run"]), ERRORS_SQL)
add_over_trace("view_size_w1w", wl.W1W, both(_P1), lambda t: metrics.view_size(t, ["run"]), SIZES_SQL)
add_over_trace("view_size_w2", wl.W2, both(_P2), lambda t: metrics.view_size(t, ["run"]), SIZES_SQL)
add_over_trace(
    "update_frequency",
    wl.W1W,
    both(_P1),
    lambda t: metrics.update_frequency(t, ["run"]),
    "SELECT run, count(*) AS releases, round(avg(gap), 6) AS mean_gap FROM (SELECT run, step - lag(step) OVER (PARTITION BY run ORDER BY step) AS gap FROM traced WHERE fires) GROUP BY run",
)
_SPLIT = "SELECT run, step, truth, answer, sum(n_within - n_real) OVER w AS truncation_loss, sum(n_true - n_within) OVER w AS retirement_loss, deferred, sum(discarded) OVER w AS purge_loss FROM traced WINDOW w AS (PARTITION BY run ORDER BY step)"
_SPLIT_COLS = ["truth", "answer", "truncation_loss", "retirement_loss", "deferred", "purge_loss"]
add_over_trace("error_split", wl.W2, both(_P2.but(purge_every=100)), metrics.error_split, "SELECT run, step, " + ", ".join(f"CAST({c} AS BIGINT) AS {c}" for c in _SPLIT_COLS) + f" FROM ({_SPLIT})")
add_over_trace(
    "buffer_rows",
    wl.W1W,
    both(_P1.but(purge_every=50)),
    metrics.buffer_rows,
    """SELECT run, step, CAST(CASE WHEN step % purge_every = 0 THEN 0 ELSE greatest(0, sum(n_padded - want) OVER (PARTITION BY run, (step - 1) // purge_every ORDER BY step)) END AS BIGINT) AS buffer_rows, CAST(deferred AS BIGINT) AS deferred FROM traced""",
)
_LG = "ceil(log2(greatest({0}, 1)))"
_COST = f"CAST(pow(2.0, {_LG}) / 4 * {_LG} * ({_LG} + 1) AS BIGINT)"
WORK_SQL = f"""SELECT run, CAST(sum({_COST.format("n_padded")}) AS BIGINT) AS derive_work, CAST(sum(CASE WHEN fires THEN {_COST.format("sorted")} ELSE 0 END) AS BIGINT) AS release_work,
      CAST(sum(view_rows) AS BIGINT) AS query_work FROM (SELECT *, coalesce(lag(held) OVER (PARTITION BY run ORDER BY step), 0) + n_padded AS sorted FROM (SELECT *,
      CAST(CASE WHEN step % purge_every = 0 THEN 0 ELSE greatest(0, sum(n_padded - want) OVER (PARTITION BY run, (step - 1) // purge_every ORDER BY step)) END AS BIGINT) AS held FROM traced)) GROUP BY run"""
add_over_trace("oblivious_cost", wl.W1W, both(_P1.but(purge_every=50)), metrics.work, WORK_SQL)


def comparison(spec: ViewSpec, p: Params):
    """One row for each strategy: error, view size and rows a query scans, as the end-to-end comparison needs."""

    def run(s: SparkSession, d: str) -> DataFrame:
        q = sums(spec, s, d)
        cols = lambda x, n: x.select(F.lit(n).alias("strategy"), "step", "truth", "answer", "view_rows", F.col("scanned_rows" if "scanned_rows" in x.columns else "view_rows").alias("scanned"))
        t = release.trace(q, both(p)).withColumn("strategy", F.col("run"))
        parts = [t.select("strategy", "step", "truth", "answer", "view_rows", F.col("view_rows").alias("scanned"))]
        parts += [cols(baselines.nm(q), "nm"), cols(baselines.ep(q), "ep"), cols(baselines.otm(q), "otm")]
        out = parts[0]
        for x in parts[1:]:
            out = out.unionByName(x)
        e = metrics.errors(out, ["strategy"]).drop("rel_of_means")
        # a view is scanned; without one, a query joins all uploads again
        work = F.when(F.col("strategy") == "nm", metrics.oblivious_cost(F.col("scanned"))).otherwise(F.col("scanned"))
        v = out.groupBy("strategy").agg(F.round(F.avg("view_rows"), 6).alias("mean_view_rows"), F.round(F.avg("scanned"), 6).alias("mean_scanned_rows"), F.round(F.avg(work), 6).alias("mean_query_work"))
        return e.join(v, "strategy")

    union = " UNION ALL ".join(
        f"SELECT '{n}', step, sum(n_true) OVER (ORDER BY step), {a}, {v}, {c} FROM sums"
        for n, a, v, c in (
            ("nm", "sum(n_true) OVER (ORDER BY step)", "0", "sum(up_left + up_right) OVER (ORDER BY step)"),
            ("ep", "sum(n_real) OVER (ORDER BY step)", "sum(n_padded) OVER (ORDER BY step)", "sum(n_padded) OVER (ORDER BY step)"),
            ("otm", "0", "0", "0"),
        )
    )
    select = f"""SELECT strategy, round(avg(abs(truth - answer)), 6) AS mean_l1, round(avg(CASE WHEN truth > 0 THEN abs(truth - answer) / CAST(truth AS DOUBLE) END), 6) AS rel_mean,
      round(avg(view_rows), 6) AS mean_view_rows, round(avg(scanned), 6) AS mean_scanned_rows,
      round(avg(CASE WHEN strategy = 'nm' THEN {_COST.format("scanned")} ELSE scanned END), 6) AS mean_query_work FROM (
      SELECT run AS strategy, step, truth, answer, view_rows, view_rows AS scanned FROM traced UNION ALL {union}) GROUP BY strategy"""
    return run, sql.trace_sql(spec, both(p), select)


for _name, _spec in (("comparison_w1w", wl.W1W), ("comparison_w2", wl.W2), ("comparison_w2b30", wl.W2B30)):
    add(_name, *comparison(_spec, _spec.params))

#: How many times smaller a strategy's measure is than a baseline's: gain, measure, baseline.
GAINS = [
    ("accuracy_gain_over_otm", "mean_l1", "otm"),
    ("size_gain_over_ep", "mean_view_rows", "ep"),
    ("query_gain_over_ep", "mean_query_work", "ep"),
    ("query_gain_over_nm", "mean_query_work", "nm"),
]


def _gains(spec: ViewSpec, s: SparkSession, d: str) -> DataFrame:
    table = comparison(spec, spec.params)[0](s, d)
    parts = [metrics.improvement(table, base, value).withColumnRenamed("gain", name) for name, value, base in GAINS]
    out = parts[0]
    for part in parts[1:]:
        out = out.join(part, "strategy")
    return out


for _tag in ("w1w", "w2", "w2b30"):
    _cols = ", ".join(f"round((SELECT {value} FROM c WHERE strategy = '{base}') / nullif({value}, 0), 4) AS {name}" for name, value, base in GAINS)
    add(f"improvement_{_tag}", lambda s, d, spec=REGISTERED[_tag]: _gains(spec, s, d), f"WITH c AS ({QUERIES[f'comparison_{_tag}'].sql}) SELECT strategy, {_cols} FROM c")
_BUDGET = replace(wl.W1W, params=_P1.but(pad_rule="budget"))
add_over_sums("padding_by_budget", _BUDGET, lambda d: d.select("step", "n_padded"), "SELECT step, n_padded FROM sums")


def _timings(spec: ViewSpec, s: SparkSession, d: str) -> DataFrame:
    """Seconds of derive, release and one query for each strategy, totals, and gains over the baselines."""
    from .experiments import gains, run, totals

    rows = run(s, d, spec)
    return rows.join(totals(rows), "strategy").join(gains(rows), "strategy")


for _tag in ("w1w", "w2b30"):
    add(f"timings_{_tag}", lambda s, d, spec=REGISTERED[_tag]: _timings(spec, s, d))


def _udf(s: SparkSession, d: str) -> DataFrame:
    from .functions.vectorized import laplace_udf

    z = noise.joint_word("7", "rel", F.col("step"))
    return daily_steps(s, d).select("step", z.alias("word"), F.round(laplace_udf(z, 10 / 1.5), 6).alias("noise"))


add("udf_noise", _udf, QUERIES["joint_noise"].sql)


def _udaf(s: SparkSession, d: str) -> DataFrame:
    from .functions.vectorized import max_contribution_udaf

    pairs = derive.true_pairs(wl.W2M72, *wl.sides(wl.W2M72, s, d))
    return max_contribution_udaf(pairs, "born_step", "l_rid")


add("udaf_max_contrib", _udaf, f"WITH {sql.pairs_ctes(wl.W2M72)} SELECT born_step, max(k) AS most FROM (SELECT born_step, l_rid, count(*) AS k FROM truth GROUP BY 1, 2) GROUP BY 1")

# --- leakage and privacy -------------------------------------------------------------------------------------------

#: Declared batch sizes of the transcripts (public; fixed values).
_CAPS = (4096, 4096)


def transcript_queries(name: str, spec: ViewSpec, strategy: str) -> None:
    """transcript_..: the sizes that a run moved; simulator_..: the same from the mechanism's output alone.

    The declared sizes stay as tables grow: a batch above them is shown at its declared size, as the twin shows it.
    """
    run = (strategy, strategy, spec.params)
    mech = {"interval": leakage.mech_interval, "threshold": leakage.mech_threshold}[strategy]

    def transcript(s: SparkSession, d: str) -> DataFrame:
        q = sums(spec, s, d, strict=False)
        return leakage.transcript(q, release.trace(q, [run]), spec)

    private = "up_left" if spec.right_public else "up_left + up_right"
    text = sql.trace_sql(spec, [run], f"""SELECT t.step, CAST({private} AS BIGINT) AS uploaded, t.n_padded AS cached, CAST(t.real_out + t.dummy_out AS BIGINT) AS released,
      CAST(t.purge_real + t.purge_dummy AS BIGINT) AS purged FROM traced t JOIN sums s USING (step)""")
    add(f"transcript_{name}", transcript, text)
    add(f"simulator_{name}", lambda s, d: leakage.simulate(mech(sums(spec, s, d, strict=False), spec.params), spec), text)


_OPEN1 = replace(wl.W1W, params=_P1.but(batch_cap=_CAPS, pad_rule="budget", purge_every=50))
_OPEN2 = replace(wl.W2B30, params=wl.W2B30.params.but(batch_cap=_CAPS, purge_every=100))
for _s in ("interval", "threshold"):
    transcript_queries(_s, _OPEN1, _s)
    transcript_queries(f"{_s}_w2", _OPEN2, _s)
QUERIES["simulator_sizes"] = QUERIES["simulator_interval"]
add("mech_interval", lambda s, d: leakage.mech_interval(sums(wl.W1W, s, d), _P1), sql.trace_sql(wl.W1W, [_I], "SELECT step, CAST(want AS BIGINT) AS v FROM traced"))
add("mech_threshold", lambda s, d: leakage.mech_threshold(sums(wl.W1W, s, d), _P1), sql.trace_sql(wl.W1W, [_T], "SELECT step, CAST(want AS BIGINT) AS v FROM traced"))


def _composed(s: SparkSession, d: str) -> DataFrame:
    spec = wl.W2
    left = spec.left(s, d)
    h = spec.params.horizon
    uses = left.select(F.concat_ws("|", "key", "rid").alias("rid"), F.explode(F.sequence("step", F.col("step") + h - 1)).alias("invocation")).withColumn("q", F.lit(float(spec.params.omega)))
    losses = uses.select("invocation").distinct().withColumn("eps", F.lit(spec.params.eps / spec.params.budget))
    return privacy.composed(uses, losses).select(F.round("eps", 6).alias("eps"))


add("composed_privacy", _composed, f"SELECT round(max(spent), 6) AS eps FROM (SELECT sum(10.0 * (1.5 / 20)) AS spent FROM (SELECT key, rid, unnest(generate_series(step, step + 1)) AS t FROM ({sql.lines_sql('l_partkey', 'R', 5)})) GROUP BY key, rid)")
add("user_level_ell", lambda s, d: privacy.rows_per_user(load(s, d, "events"), "user_id"), "SELECT max(n) AS ell FROM (SELECT count(*) AS n FROM events GROUP BY user_id)")


def _user_eps(s: SparkSession, d: str) -> DataFrame:
    return privacy.rows_per_user(load(s, d, "events"), "user_id").select("ell", F.round(F.lit(1.5) / F.col("ell"), 9).alias("event_eps"))


add("user_level_eps", _user_eps, "SELECT max(n) AS ell, round(1.5 / max(n), 9) AS event_eps FROM (SELECT count(*) AS n FROM events GROUP BY user_id)")

# --- extensions ----------------------------------------------------------------------------------------------------

_UP = """uploads AS (SELECT step, count(*) AS n FROM ({side}) GROUP BY 1), g AS (SELECT CAST(unnest(generate_series(1, (SELECT max(step) FROM uploads))) AS INTEGER) AS step),
  sums AS (SELECT g.step, coalesce(n, 0) AS n_real, coalesce(n, 0) AS n_true, coalesce(n, 0) AS n_within, 0 AS n_padded, 0 AS up_left, 0 AS up_right FROM g LEFT JOIN uploads USING (step))"""
for _s in ("interval", "threshold"):
    _run = ("owner", _s, _P1.but(budget=1, omega=1))
    add(
        f"owner_{_s}",
        lambda s, d, k=_s: owner_sync.uploads(wl.W1W.left(s, d), k, _P1),
        f"WITH RECURSIVE {sql.runs_values([_run])}, {_UP.format(side=sql.orders_sql(10))}, {sql.trace_ctes([_run])} SELECT step, n_real AS arrived, CAST(want AS BIGINT) AS want, CAST(real_out AS BIGINT) AS real_out, CAST(deferred AS BIGINT) AS deferred FROM traced",
    )
add(
    "owner_sync_recompute",
    lambda s, d: baselines.owner_sync_nm(owner_sync.uploads(wl.W1W.left(s, d), "interval", _P1), sums(wl.W1W, s, d)),
    f"""WITH RECURSIVE {sql.runs_values([("owner", "interval", _P1.but(budget=1, omega=1))])}, {_UP.format(side=sql.orders_sql(10))}, {sql.trace_ctes([])},
      rr AS (SELECT step, count(*) AS n FROM ({sql.lines_sql("l_orderkey", "R", 10)}) GROUP BY 1)
      SELECT t.step, CAST(sum(want) OVER w AS BIGINT) AS uploaded_rows, CAST(sum(want + coalesce(rr.n, 0)) OVER w AS BIGINT) AS scanned_rows FROM traced t LEFT JOIN rr USING (step) WINDOW w AS (ORDER BY t.step)""",
)
_LEVELS = [("interval", _P1.but(eps=1.0)), ("threshold", _P1.but(eps=0.5, seed="8"))]
add(
    "multilevel_chain",
    lambda s, d: shown(multilevel.chain(sums(wl.W1W, s, d), _LEVELS)),
    f"""WITH RECURSIVE {sql.runs_values([("level1", *_LEVELS[0])])}, {sql.sums_ctes(wl.W1W)}, {sql.trace_ctes([], into="first_level")},
      runs2 AS (SELECT * FROM (VALUES {sql.runs_values([("level2", *_LEVELS[1])]).split("(VALUES ", 1)[1][:-1]}) AS x(run, strategy, eps, budget, every_steps, theta, purge_every, purge_size, seed, rel_k, resets)),
      sums2 AS (SELECT step, real_out + purge_real AS n_real, n_true, 0 AS n_within, 0 AS n_padded, 0 AS up_left, 0 AS up_right FROM first_level),
      {sql.trace_ctes([], sums="sums2").replace("FROM runs r", "FROM runs2 r").replace("JOIN runs r", "JOIN runs2 r")} {SHOWN_SQL}""",
)

_FIRST = ("interval", Params(eps=1.0, omega=1, budget=1, interval=1))
_SECOND = ("threshold", wl.W2B30.params.but(eps=0.5, seed="8"))


def _two_operators(s: SparkSession, d: str) -> DataFrame:
    lines = wl.lines_side("l_partkey", None, 5, "l_returnflag")(s, d)
    return shown(multilevel.filter_then_join(wl.W2B30, lines, wl.W2B30.right(s, d), F.col("l_returnflag") == "R", _FIRST, _SECOND))


add(
    "multilevel_operators",
    _two_operators,
    sql.over_sent(wl.W2B30, sql.lines_sql("l_partkey", None, 5).replace(" FROM lineitem", ", l_returnflag AS flag FROM lineitem"), ("filter", *_FIRST), ("level2", *_SECOND), SHOWN_SQL, "count(*) FILTER (flag = 'R')", "flag = 'R'"),
)
_OWNER = {k: Params(eps=1.0, omega=1, budget=1, interval=2, theta=40) for k in ("interval", "threshold")}


def _owner_view(strategy: str, s: SparkSession, d: str) -> DataFrame:
    """A view over what the owner has uploaded by its own policy: errors of both levels beside their joint bound."""
    spec, p = wl.W2B30, _OWNER[strategy]
    left, right = wl.sides(spec, s, d)
    queue = kept(owner_sync.queue(left, strategy, p))
    q = kept(owner_sync.view_sums(spec, left, right, owner_sync.uploaded(left, queue, p)))
    return owner_sync.bounded(release.trace(q, [("interval", "interval", spec.params)]), queue, spec)


for _s in ("interval", "threshold"):
    add(
        f"owner_view_{_s}",
        lambda s, d, k=_s: _owner_view(k, s, d),
        sql.over_sent(
            wl.W2B30,
            sql.lines_sql("l_partkey", "R", 5),
            ("owner", _s, _OWNER[_s]),
            ("interval", "interval", wl.W2B30.params),
            """SELECT step, CAST(coalesce(o.deferred, 0) AS BIGINT) AS owner_deferred, CAST(t.deferred AS BIGINT) AS deferred, CAST(t.answer AS BIGINT) AS answer, CAST(t.truth AS BIGINT) AS truth, CAST(t.l1 AS BIGINT) AS l1,
              round(30 * coalesce(o.deferred, 0) + 2 * 30 / 1.5 * sqrt(greatest(floor(step / 3), 10) * ln(10)), 6) AS bound FROM traced t LEFT JOIN (SELECT step, deferred FROM ot) o USING (step)""",
        ),
    )

# --- experiments ---------------------------------------------------------------------------------------------------


def seeds(p: Params, tag: str, strategies: tuple[str, ...] = ("interval", "threshold"), n: int = 2) -> list[Run]:
    return [(f"{s}|{tag}|{k}", s, p.but(seed=str(100 + k))) for s in strategies for k in range(n)]


EPS_RUNS = {w.name: [r for e in wl.EPS_SWEEP for r in seeds(w.params.but(eps=e), f"eps={e}")] for w in (wl.W1W, wl.W2)}
add_over_trace("eps_sweep_w1w", wl.W1W, EPS_RUNS["w1w"], sweep, SWEEP_SQL)
add_over_trace("eps_sweep_w2", wl.W2, EPS_RUNS["w2"], sweep, SWEEP_SQL)
T_RUNS = [r for e in (0.1, 1.0, 10.0) for t in wl.T_SWEEP for r in seeds(_P1.but(eps=e, interval=t, theta=3.0 * t), f"eps={e},T={t}", n=1)]
add_over_trace("t_theta_sweep", wl.W1W, T_RUNS, sweep, SWEEP_SQL)
T_RUNS2 = [r for e in (0.1, 1.0, 10.0) for t in wl.T_SWEEP for r in seeds(_P2.but(eps=e, interval=t, theta=10.0 * t), f"eps={e},T={t}", n=1)]
add_over_trace("t_theta_sweep_w2", wl.W2, T_RUNS2, sweep, SWEEP_SQL)


def _omega(s: SparkSession, d: str) -> DataFrame:
    out = None
    for w in wl.OMEGA_SWEEP:
        spec = wl.w2m(72, 36, w)
        x = sweep(release.trace(sums(spec, s, d), seeds(spec.params, f"omega={w}")))
        out = x if out is None else out.unionByName(x)
    return out


_OMEGA_SQL = " UNION ALL ".join(f"SELECT * FROM ({sql.trace_sql(wl.w2m(72, 36, w), seeds(wl.w2m(72, 36, w).params, f'omega={w}'), SWEEP_SQL)})" for w in wl.OMEGA_SWEEP)
add("omega_sweep", _omega, _OMEGA_SQL)


def _omega_kept(s: SparkSession, d: str) -> DataFrame:
    out = None
    for w in wl.OMEGA_SWEEP:
        spec = wl.w2m(240, 120, w)
        x = derive.derive(spec, *wl.sides(spec, s, d)).agg(F.count("*").alias("kept")).select(F.lit(w).alias("omega"), "kept")
        out = x if out is None else out.unionByName(x)
    return out


add("omega_kept_pairs", _omega_kept, " UNION ALL ".join(f"SELECT * FROM (WITH {sql.pairs_ctes(wl.w2m(240, 120, w))} SELECT {w} AS omega, count(*) AS kept FROM kept)" for w in wl.OMEGA_SWEEP))

WORK_AND_ERRORS_SQL = f"SELECT w.*, s.* EXCLUDE (run) FROM ({WORK_SQL}) w JOIN ({SWEEP_SQL}) s USING (run)"


def work_and_errors(t: DataFrame) -> DataFrame:
    return metrics.work(t).join(sweep(t), "run")


def omega_costs(name: str, spec_of: Callable[[int], ViewSpec]) -> None:
    """Error, view rows, and the modelled work of derive, release and queries for every truncation bound."""

    def run(s: SparkSession, d: str) -> DataFrame:
        out = None
        for w in wl.OMEGA_SWEEP:
            spec = spec_of(w)
            x = work_and_errors(release.trace(sums(spec, s, d), seeds(spec.params, f"omega={w}", n=1)))
            out = x if out is None else out.unionByName(x)
        return out

    add(name, run, " UNION ALL ".join(f"SELECT * FROM ({sql.trace_sql(spec_of(w), seeds(spec_of(w).params, f'omega={w}', n=1), WORK_AND_ERRORS_SQL)})" for w in wl.OMEGA_SWEEP))


omega_costs("omega_sweep_w2m_240", lambda w: wl.w2m(240, 120, w))
omega_costs("omega_sweep_w2s", lambda w: replace(wl.W2S, params=wl.W2S.params.but(omega=w, budget=2 * w)))

_OFFSET = 1 << 40


def copies_sql(n: int) -> Callable[[str, str], str]:
    return lambda k, q: f"SELECT rid, key + c * {_OFFSET} AS key, day, step FROM ({q}), (VALUES {', '.join(f'({c})' for c in range(n))}) AS v(c)"


SCALES = {
    "half": (lambda l, r: (wl.half(l), wl.half(r)), lambda k, q: f"SELECT * FROM ({q}) WHERE {sql.HALF}"),
    "once": (lambda l, r: (l, r), lambda k, q: q),
    "twice": (lambda l, r: (wl.burst(l), wl.burst(r)), copies_sql(2)),
    "four_times": (lambda l, r: (wl.burst(l, 4), wl.burst(r, 4)), copies_sql(4)),
}
for _size, (_f, _wrap) in SCALES.items():
    for _tag in ("w1w", "w2b30"):
        _spec = REGISTERED[_tag]
        add(
            f"scale_{_size}_{_tag}",
            lambda s, d, f=_f, spec=_spec: work_and_errors(release.trace(kept(derive.summaries(spec, *f(*wl.sides(spec, s, d)))), seeds(spec.params, "default", n=1))),
            sql.trace_sql(_spec, seeds(_spec.params, "default", n=1), WORK_AND_ERRORS_SQL, _wrap),
        )
WRAPS = {
    "density_sparse": (lambda l, r: (l, wl.sparse(r)), lambda k, q: f"SELECT * FROM ({q}) WHERE {sql.SPARSE}" if k == "r" else q),
    "density_burst": (lambda l, r: (wl.burst(l), wl.burst(r)), copies_sql(2)),
    "scale_replicate": (lambda l, r: (wl.burst(l, 4), wl.burst(r, 4)), copies_sql(4)),
}
for _name, (_f, _wrap) in WRAPS.items():
    for _tag, _spec in (("", wl.W1W), ("_w2", wl.W2)):
        add(
            _name + _tag,
            lambda s, d, f=_f, spec=_spec: sweep(release.trace(kept(derive.summaries(spec, *f(*wl.sides(spec, s, d)))), seeds(spec.params, "default"))),
            sql.trace_sql(_spec, seeds(_spec.params, "default"), SWEEP_SQL, _wrap),
        )

_BOUND_SEEDS, _BETA = 200, 0.1


def bound_query(name: str, strategy: str, p: Params, last: int, deferred_bound: float, dummy_bound: float) -> None:
    """Over 200 seeds at one step: the bounds on deferred rows and on dummy rows in the view, the most there were, and
    the share of seeds beyond each."""
    runs = [(f"seed{k}", strategy, p.but(seed=str(1000 + k))) for k in range(_BOUND_SEEDS)]

    def run(s: SparkSession, d: str) -> DataFrame:
        t = release.trace(sums(wl.W1W, s, d).filter(F.col("step") <= last), runs).filter(F.col("step") == last).withColumn("dummies", F.col("view_rows") - F.col("answer"))
        over = lambda c, most: F.round(F.avg((F.col(c) >= most).cast("double")), 6)
        return t.agg(
            F.round(F.lit(deferred_bound), 6).alias("deferred_bound"), F.max("deferred").alias("most_deferred"), over("deferred", deferred_bound).alias("deferred_exceeded"),
            F.round(F.lit(dummy_bound), 6).alias("dummy_bound"), F.max("dummies").alias("most_dummies"), over("dummies", dummy_bound).alias("dummies_exceeded"),
        )

    over = lambda c, most: f"round(avg(CASE WHEN {c} >= {most!r} THEN 1.0 ELSE 0.0 END), 6)"
    add(name, run, sql.trace_sql(wl.W1W, runs, f"""SELECT round(CAST({deferred_bound!r} AS DOUBLE), 6) AS deferred_bound, CAST(max(deferred) AS BIGINT) AS most_deferred, {over("deferred", deferred_bound)} AS deferred_exceeded,
      round(CAST({dummy_bound!r} AS DOUBLE), 6) AS dummy_bound, CAST(max(view_rows - answer) AS BIGINT) AS most_dummies, {over("(view_rows - answer)", dummy_bound)} AS dummies_exceeded FROM traced WHERE step = {last}"""))


# one release a step, so that 200 steps are 200 releases; the threshold rule with the default parameters
_EACH = _P1.but(interval=1, purge_every=100, purge_size=15)
bound_query("deferred_bound", "interval", _EACH, 199, privacy.deferred_bound_interval(_P1.eps, _P1.budget, 199, _BETA), privacy.view_bound_interval(_P1.eps, _P1.budget, 199, 1, 100, 15, _BETA))
bound_query("threshold_bound", "threshold", _P1.but(purge_every=100, purge_size=15), 199, *privacy.bounds_threshold(_P1.eps, _P1.budget, 199, 100, 15))
