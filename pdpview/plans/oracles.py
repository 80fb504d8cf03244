"""SQL twins for an independent engine: the same semantics by recursion over steps and plain windows."""

from __future__ import annotations

from ..params import Params
from ..sources.tables import EVENTS_ORIGIN, LINE_ID, ORDERS_ORIGIN


def orders_sql(days: int) -> str:
    return f"""SELECT o_orderkey AS rid, o_orderkey AS key, CAST(o_orderdate AS DATE) AS day,
      CAST(floor(datediff('day', DATE '{ORDERS_ORIGIN}', CAST(o_orderdate AS DATE)) / {days}) + 1 AS INTEGER) AS step
      FROM orders WHERE o_orderkey IS NOT NULL AND o_orderdate IS NOT NULL"""


def lines_sql(key: str, flag: str | None, days: int) -> str:
    where = f"AND l_returnflag = '{flag}'" if flag else ""
    return f"""SELECT ('0x' || substr(md5(concat_ws('|', {", ".join(LINE_ID)})), 1, 15))::BIGINT AS rid, {key} AS key,
      CAST(l_shipdate AS DATE) AS day,
      CAST(floor(datediff('day', DATE '{ORDERS_ORIGIN}', CAST(l_shipdate AS DATE)) / {days}) + 1 AS INTEGER) AS step
      FROM lineitem WHERE {key} IS NOT NULL AND l_shipdate IS NOT NULL AND l_returnflag IS NOT NULL {where}"""


def events_sql(kind: str, hours: int) -> str:
    return f"""SELECT event_id AS rid, user_id AS key, ts AS day,
      CAST(floor(datediff('second', TIMESTAMP '{EVENTS_ORIGIN}', date_trunc('second', ts)) / {3600 * hours}) + 1 AS INTEGER) AS step
      FROM events WHERE event_id IS NOT NULL AND ts IS NOT NULL AND user_id IS NOT NULL AND event_type = '{kind}'"""


HALF = "(('0x' || substr(md5(CAST(key AS VARCHAR)), 1, 8))::BIGINT) % 2 = 0"
SPARSE = "(('0x' || substr(md5(concat_ws('|', key, rid)), 1, 8))::BIGINT) % 10 = 0"


def sides_sql(name: str, omega: int | None = None) -> tuple[str, str]:
    """SQL of the left and right side of a workload."""
    if name.startswith("w1"):
        days = 10 if name == "w1w" else 1
        return orders_sql(days), lines_sql("l_orderkey", None if name == "w1d" else "R", days)
    if name.startswith("w2m"):
        hours = {"w2m_240": 120, "w2m_72": 36, "w2m_24": 12}[name]
        return events_sql("error", hours), events_sql("purchase", hours)
    key = "l_suppkey" if name.startswith("w2s") else "l_partkey"
    return lines_sql(key, "R", 5), lines_sql(key, "A", 5)


def pairs_ctes(spec, wrap=lambda side, sql: sql) -> str:
    """CTEs l, r, truth, within_h, kept (columns born_step, key, l_rid, r_rid)."""
    p = spec.params
    left, right = (wrap(k, s) for k, s in zip("lr", sides_sql(spec.name), strict=True))
    lag = {"step": "r.step - l.step", "day": "datediff('day', l.day, r.day)", "hour": "(epoch_us(r.day) - epoch_us(l.day)) / 3.6e9"}[spec.lag_unit]
    born = "greatest(l.step, r.step)"
    late = f"{born} - {'l.step' if spec.right_public else 'least(l.step, r.step)'}"
    if spec.right_public:
        kept = f"""kept AS (SELECT born_step, key, l_rid, r_rid FROM (SELECT *, row_number() OVER
          (PARTITION BY born_step, key, l_rid ORDER BY r_day, r_rid) AS k FROM within_h) WHERE k <= {p.omega})"""
    else:
        kept = f"""arr AS (SELECT DISTINCT key, step AS t FROM r),
        old_l AS (SELECT a.t, l.key, l.rid, (row_number() OVER (PARTITION BY a.t, l.key ORDER BY l.step, l.rid) - 1) // {p.omega} AS blk
          FROM l JOIN arr a ON a.key = l.key AND l.step <= a.t AND a.t < l.step + {p.horizon}),
        new_r AS (SELECT step AS t, key, rid, (row_number() OVER (PARTITION BY step, key ORDER BY rid) - 1) // {p.omega} AS blk FROM r),
        kept AS (SELECT o.t AS born_step, o.key, o.rid AS l_rid, n.rid AS r_rid FROM old_l o JOIN new_r n USING (t, key, blk))"""
    return f"""l AS ({left}), r AS ({right}),
    truth AS (SELECT {born} AS born_step, l.key, l.rid AS l_rid, r.rid AS r_rid, r.day AS r_day, {late} AS late
      FROM l JOIN r ON l.key = r.key WHERE {lag} BETWEEN {spec.lag_lo} AND {spec.lag_hi}),
    within_h AS (SELECT * FROM truth WHERE late < {p.horizon}),
    {kept}"""


def sums_ctes(spec, wrap=lambda side, sql: sql) -> str:
    p = spec.params
    private = "up_left" if spec.right_public else "up_left + up_right"
    ups = p.batch_cap or ("max(n_left) OVER ()", "max(n_right) OVER ()")
    up_right = "n_right" if spec.right_public else ups[1]
    if p.pad_rule == "budget":
        padded = f"{p.budget} * ({private})"
    else:
        padded = f"{p.omega} * sum({private}) OVER (ORDER BY step ROWS BETWEEN {p.horizon - 1} PRECEDING AND CURRENT ROW)"
    count = lambda cte, c: f"(SELECT {c} AS step, count(*) AS n FROM {cte} GROUP BY 1)"
    return f"""{pairs_ctes(spec, wrap)},
    last_step AS (SELECT max(s) AS m FROM (SELECT max(step) AS s FROM l UNION ALL SELECT max(step) FROM r)),
    grid AS (SELECT CAST(unnest(generate_series(1, m)) AS INTEGER) AS step FROM last_step),
    sums0 AS (SELECT g.step, coalesce(a.n, 0) AS n_true, coalesce(b.n, 0) AS n_within, coalesce(c.n, 0) AS n_real,
        coalesce(d.n, 0) AS n_left, coalesce(e.n, 0) AS n_right
      FROM grid g LEFT JOIN {count("truth", "born_step")} a USING (step) LEFT JOIN {count("within_h", "born_step")} b USING (step)
      LEFT JOIN {count("kept", "born_step")} c USING (step) LEFT JOIN {count("l", "step")} d USING (step)
      LEFT JOIN {count("r", "step")} e USING (step)),
    sums1 AS (SELECT *, CAST({ups[0]} AS BIGINT) AS up_left, CAST({up_right} AS BIGINT) AS up_right FROM sums0),
    sums AS (SELECT step, n_true, n_within, n_real, CAST({padded} AS BIGINT) AS n_padded, n_left, n_right, up_left, up_right FROM sums1)"""


def word(seed: str, server: int, purpose: str, step: str) -> str:
    return f"(('0x' || substr(md5(concat_ws('|', {seed}, 's{server}', '{purpose}', {step})), 1, 8))::BIGINT)"


def joint(seed: str, purpose: str, step: str, servers: int = 2) -> str:
    out = word(seed, 0, purpose, step)
    for k in range(1, servers):
        out = f"xor({out}, {word(seed, k, purpose, step)})"
    return out


def laplace(z: str, scale: str) -> str:
    return f"(({scale}) * ln((({z} & 2147483647) + 0.5) / 2147483648.0) * (CASE WHEN {z} >= 2147483648 THEN 1.0 ELSE -1.0 END))"


def runs_values(runs: list[tuple[str, str, Params]]) -> str:
    rows = ", ".join(f"('{n}', '{s}', CAST({p.eps} AS DOUBLE), {p.budget}, {p.interval}, CAST({float(p.theta)} AS DOUBLE), {p.purge_every}, {p.purge_size}, '{p.seed}', {4.0 if p.scale_release == 'mechanism' else 2.0}, {str(p.purge_resets_counter).upper()})" for n, s, p in runs)
    return f"runs(run, strategy, eps, budget, every_steps, theta, purge_every, purge_size, seed, rel_k, resets) AS (VALUES {rows})"


def trace_ctes(runs: list[tuple[str, str, Params]], sums: str = "sums", into: str = "traced") -> str:
    """CTEs that step through every run one step at a time; ``into`` has the columns of a trace."""
    base = "(r.budget / r.eps)"
    z = {k: joint("r.seed", k, "s.step") for k in ("chk", "rel", "thr")}
    rel_scale = f"{base} * (CASE WHEN r.strategy = 'interval' THEN 1.0 ELSE r.rel_k END)"
    sim = f"""{into}_sim AS (
      SELECT r.run, 0 AS step, CAST(0 AS BIGINT) AS kept_c, r.theta + {laplace(joint("r.seed", "thr", "0"), base + " * 4.0")} AS bound,
        CAST(0 AS BIGINT) AS deferred, CAST(0 AS BIGINT) AS c, FALSE AS fires, CAST(NULL AS DOUBLE) AS sz, CAST(0 AS BIGINT) AS want,
        CAST(0 AS BIGINT) AS real_out, CAST(0 AS BIGINT) AS purge_real, CAST(0 AS BIGINT) AS discarded
      FROM runs r
      UNION ALL
      SELECT run, step, CASE WHEN fires OR (resets AND flush) THEN 0 ELSE c END, CASE WHEN fires THEN theta + thr ELSE bound END,
        CASE WHEN flush THEN 0 ELSE depth - real_out END, c, fires, sz, want, real_out,
        CASE WHEN flush THEN least(depth - real_out, purge_size) ELSE 0 END,
        CASE WHEN flush THEN greatest(depth - real_out - purge_size, 0) ELSE 0 END
      FROM (SELECT *, least(depth, want) AS real_out FROM (SELECT *,
          CASE WHEN fires THEN CAST(greatest(0, floor(sz + 0.5)) AS BIGINT) ELSE CAST(0 AS BIGINT) END AS want
        FROM (SELECT *, CASE WHEN fires THEN c + rel END AS sz FROM (
          SELECT n.*, p.bound, p.deferred + n.n_real AS depth, p.kept_c + n.n_real AS c,
            CASE WHEN n.strategy = 'interval' THEN n.step % n.every_steps = 0 ELSE p.kept_c + n.n_real + n.chk >= p.bound END AS fires,
            n.step % n.purge_every = 0 AS flush
          FROM {into}_sim p JOIN {into}_nz n ON n.run = p.run AND n.step = p.step + 1) q1) q2) q3) q4)"""
    return f"""{into}_nz AS MATERIALIZED (SELECT r.*, s.step, s.n_real,
        {laplace(z["chk"], base + " * 8.0")} AS chk, {laplace(z["rel"], rel_scale)} AS rel, {laplace(z["thr"], base + " * 4.0")} AS thr
      FROM runs r, {sums} s),
    {sim},
    {into} AS (SELECT t.run, r.strategy, t.step, s.n_real, s.n_true, s.n_within, s.n_padded, s.n_up, t.c, t.bound, t.fires, t.sz, t.want, t.real_out,
        t.want - t.real_out AS dummy_out, t.purge_real, CASE WHEN t.step % r.purge_every = 0 THEN r.purge_size - t.purge_real ELSE 0 END AS purge_dummy,
        t.discarded, t.deferred, r.purge_every, r.purge_size, r.budget,
        sum(s.n_true) OVER w AS truth, sum(t.real_out + t.purge_real) OVER w AS answer,
        sum(t.want + CASE WHEN t.step % r.purge_every = 0 THEN r.purge_size ELSE 0 END) OVER w AS view_rows,
        abs(sum(s.n_true) OVER w - sum(t.real_out + t.purge_real) OVER w) AS l1
      FROM {into}_sim t JOIN runs r USING (run) JOIN (SELECT step, n_real, n_true, n_within, n_padded, up_left + up_right AS n_up FROM {sums}) s USING (step)
      WHERE t.step > 0 WINDOW w AS (PARTITION BY t.run ORDER BY t.step))"""


def trace_sql(spec, runs: list[tuple[str, str, Params]], select: str, wrap=lambda side, sql: sql) -> str:
    return f"WITH RECURSIVE {runs_values(runs)}, {sums_ctes(spec, wrap)}, {trace_ctes(runs)} {select}"


PART = "(({key} + {rid}) % 64 + 64) % 64"


def sent_ctes(rows: str, run: tuple[str, str, Params], count: str = "count(*)", only: str = "TRUE") -> str:
    """CTEs of a first stage over plain rows (CTE ``own``: rid, key, day, step, ...): ``ot``, its trace, and ``sent``,
    its released rows at their release step. ``count`` counts the rows that it releases, ``only`` selects them."""
    return f"""{runs_values([run]).replace("runs(", "runs1(", 1)}, own AS ({rows}),
    oup AS (SELECT step, {count} AS n FROM own GROUP BY 1),
    og AS (SELECT CAST(unnest(generate_series(1, (SELECT max(step) FROM oup))) AS INTEGER) AS step),
    osums AS (SELECT og.step, coalesce(n, 0) AS n_real, coalesce(n, 0) AS n_true, coalesce(n, 0) AS n_within, 0 AS n_padded, 0 AS up_left, 0 AS up_right FROM og LEFT JOIN oup USING (step)),
    {trace_ctes([], sums="osums", into="ot").replace("FROM runs r", "FROM runs1 r").replace("JOIN runs r", "JOIN runs1 r")},
    onum AS (SELECT *, row_number() OVER (PARTITION BY step ORDER BY {PART.format(key="key", rid="rid")}, key, rid) AS ord FROM own WHERE {only}),
    oq AS (SELECT step, (step - 1) // purge_every AS epoch, real_out + purge_real AS k,
      sum(real_out + purge_real) OVER (PARTITION BY (step - 1) // purge_every ORDER BY step) AS hi,
      sum(n_real) OVER (PARTITION BY (step - 1) // purge_every ORDER BY step) - n_real AS before FROM ot),
    sent AS (SELECT n.rid, n.key, n.day, q.step FROM onum n JOIN oq o ON o.step = n.step
      JOIN oq q ON q.epoch = o.epoch AND q.k > 0 AND o.before + n.ord > q.hi - q.k AND o.before + n.ord <= q.hi)"""


def over_sent(spec, rows: str, first: tuple[str, str, Params], second: tuple[str, str, Params], select: str, count: str = "count(*)", only: str = "TRUE") -> str:
    """A view over rows that a first stage has sent, with the truth of all rows: CTEs ot (first trace) and traced."""
    return f"""WITH RECURSIVE {runs_values([second])}, {sent_ctes(rows, first, count, only)},
    {sums_ctes(spec, lambda side, q: "SELECT rid, key, day, step FROM sent" if side == "l" else q)},
    whole AS (SELECT greatest(l.step, r.step) AS step, count(*) AS n FROM own l JOIN r ON l.key = r.key
      WHERE {only} AND datediff('day', l.day, r.day) BETWEEN {spec.lag_lo} AND {spec.lag_hi} GROUP BY 1),
    vsums AS (SELECT step, coalesce(n, 0) AS n_true, coalesce(n_within, 0) AS n_within, coalesce(n_real, 0) AS n_real,
      coalesce(n_padded, 0) AS n_padded, coalesce(up_left, 0) AS up_left, coalesce(up_right, 0) AS up_right FROM sums FULL JOIN whole USING (step)),
    {trace_ctes([], sums="vsums")} {select}"""
