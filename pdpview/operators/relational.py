"""The relational surface around the views: scans, joins, aggregates, windows, sets and functions, with SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import QUERIES, Query, sums
from ..functions import noise
from ..plans import oracles as sql
from ..plans import workloads as wl
from ..sources.tables import LINE_ORDER, clean, load, surrogate_rid
from . import derive, release


def op(name: str, twin: str | None = None):
    def put(f):
        QUERIES[name] = Query(f, twin)
        return f

    return put


D = lambda c: F.to_date(c)
W1W_SIDES = f"l AS ({sql.orders_sql(10)}), r AS ({sql.lines_sql('l_orderkey', 'R', 10)})"

# --- scans, cleaning, filters --------------------------------------------------------------------------------------


@op("scan_pruned", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderdate >= TIMESTAMP '1996-01-01' AND o_orderdate < TIMESTAMP '1996-02-01'")
def scan_pruned(s: SparkSession, d: str) -> DataFrame:
    day = lambda x: F.lit(x).cast("timestamp_ntz")
    return load(s, d, "orders").filter((F.col("o_orderdate") >= day("1996-01-01 00:00:00")) & (F.col("o_orderdate") < day("1996-02-01 00:00:00"))).select("o_orderkey", "o_custkey")


@op("clean_rows", "SELECT count(*) AS n_before, count(*) FILTER (WHERE l_shipdate IS NOT NULL AND l_orderkey IS NOT NULL) AS n_after FROM lineitem")
def clean_rows(s, d):
    x = load(s, d, "lineitem").select("l_orderkey", "l_shipdate")
    return x.agg(F.count("*").alias("n_before")).crossJoin(clean(x, ["l_orderkey", "l_shipdate"]).agg(F.count("*").alias("n_after")))


@op("surrogate_rid", f"SELECT row_number() OVER (ORDER BY {', '.join(LINE_ORDER)}) AS rid, l_orderkey, l_linenumber, l_partkey FROM lineitem")
def rid(s, d):
    return surrogate_rid(load(s, d, "lineitem"), LINE_ORDER).select("rid", "l_orderkey", "l_linenumber", "l_partkey")


@op("filter_lag", "SELECT o_orderkey, l_linenumber, CAST(datediff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS INTEGER) AS lag FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE datediff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) BETWEEN 0 AND 10")
def filter_lag(s, d):
    lag = F.datediff(D("l_shipdate"), D("o_orderdate"))
    j = load(s, d, "orders").join(load(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.select("o_orderkey", "l_linenumber", lag.alias("lag")).filter(F.col("lag").between(0, 10))


@op("filter_oblivious", "SELECT o_orderkey, o_totalprice > 100000 AS is_view FROM orders")
def filter_oblivious(s, d):
    from .truncate import oblivious_filter

    return oblivious_filter(load(s, d, "orders"), F.col("o_totalprice") > 100000).select("o_orderkey", "is_view")


@op("project_case", "SELECT CASE l_returnflag WHEN 'R' THEN 'private' WHEN 'A' THEN 'public' ELSE 'none' END AS side, count(*) AS n FROM lineitem GROUP BY 1")
def project_case(s, d):
    side = F.when(F.col("l_returnflag") == "R", "private").when(F.col("l_returnflag") == "A", "public").otherwise("none")
    return load(s, d, "lineitem").groupBy(F.coalesce(side, F.lit("none")).alias("side")).agg(F.count("*").alias("n"))


# --- joins ---------------------------------------------------------------------------------------------------------

PAIR_SQL = "SELECT o_orderkey, l_linenumber, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_returnflag = 'R' AND o_orderstatus = 'F'"


def hinted(hint: str):
    def run(s, d):
        o = load(s, d, "orders").filter("o_orderstatus = 'F'").select("o_orderkey")
        li = load(s, d, "lineitem").filter("l_returnflag = 'R'").select("l_orderkey", "l_linenumber", "l_partkey")
        return li.join(o.hint(hint), F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "l_linenumber", "l_partkey")

    return run


op("join_hash", PAIR_SQL)(hinted("shuffle_hash"))
op("join_merge", PAIR_SQL)(hinted("merge"))


@op("join_broadcast", "SELECT n_name, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def join_broadcast(s, d):
    n = F.broadcast(load(s, d, "nation").select("n_nationkey", "n_name"))  # 25 rows at every size
    c = load(s, d, "customer").select("c_custkey", "c_nationkey")
    return load(s, d, "orders").select("o_custkey").join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@op("join_nested_loop", "SELECT r_regionkey, count(*) AS n FROM region JOIN (SELECT DISTINCT l_linenumber FROM lineitem) ON l_linenumber > r_regionkey GROUP BY 1")
def join_nested_loop(s, d):
    n = load(s, d, "lineitem").select("l_linenumber").distinct()
    return load(s, d, "region").join(n, F.col("l_linenumber") > F.col("r_regionkey")).groupBy("r_regionkey").agg(F.count("*").alias("n"))


HOURS_SQL = "SELECT e.event_id AS error_id, p.event_id AS purchase_id FROM events e JOIN events p ON e.user_id = p.user_id AND p.ts >= e.ts AND p.ts <= e.ts + INTERVAL 12 HOUR WHERE e.event_type = 'error' AND p.event_type = 'purchase'"


@op("join_range", HOURS_SQL)
def join_range(s, d):
    """Within 12 hours: both sides fall into 12-hour buckets, the left one also looks into the next; then an equi-join."""
    e = load(s, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("us"))
    w = 12 * 3600 * 1_000_000
    left = e.filter("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.col("us").alias("a"), F.explode(F.array(F.floor(F.col("us") / w), F.floor(F.col("us") / w) + 1)).alias("bucket"))
    right = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("us").alias("b"), F.floor(F.col("us") / w).alias("bucket"))
    return left.join(right, ["user_id", "bucket"]).filter((F.col("b") >= F.col("a")) & (F.col("b") <= F.col("a") + w)).select("error_id", "purchase_id")


@op("join_asof", "SELECT p.event_id, (SELECT max(e.ts) FROM events e WHERE e.user_id = p.user_id AND e.event_type = 'error' AND e.ts < p.ts) AS last_error FROM events p WHERE p.event_type = 'purchase'")
def join_asof(s, d):
    e = load(s, d, "events").filter(F.col("event_type").isin("error", "purchase"))
    # equal times do not count: errors sort after purchases of the same time
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    last = F.last(F.when(F.col("event_type") == "error", F.col("ts")), ignorenulls=True).over(w)
    return e.withColumn("last_error", last).filter("event_type = 'purchase'").select("event_id", "last_error")


def outer(how: str):
    def run(s, d):
        o = load(s, d, "orders").select("o_orderkey", "o_orderstatus")
        li = load(s, d, "lineitem").filter("l_returnflag = 'R'").groupBy("l_orderkey").agg(F.count("*").alias("n"))
        j = o.join(li, F.col("o_orderkey") == F.col("l_orderkey"), how)
        return j.groupBy("o_orderstatus").agg(F.count("*").alias("rows"), F.sum(F.coalesce("n", F.lit(0))).alias("returns"))

    return run


for _how in ("left", "full"):
    op(f"join_{_how}_outer", f"SELECT o_orderstatus, count(*) AS rows, CAST(sum(coalesce(n, 0)) AS BIGINT) AS returns FROM orders {_how} JOIN (SELECT l_orderkey, count(*) AS n FROM lineitem WHERE l_returnflag = 'R' GROUP BY 1) ON o_orderkey = l_orderkey GROUP BY 1")(outer(_how))


def exists(how: str):
    def run(s, d):
        li = load(s, d, "lineitem").filter("l_returnflag = 'R'").select(F.col("l_orderkey").alias("o_orderkey"))
        return load(s, d, "orders").select("o_orderkey", "o_custkey").join(li, "o_orderkey", how)

    return run


for _how, _not in (("left_semi", ""), ("left_anti", "NOT")):
    op(f"join_{_how[5:]}", f"SELECT o_orderkey, o_custkey FROM orders WHERE {_not} EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R')")(exists(_how))


@op("join_self", "SELECT a.l_partkey, count(*) AS n FROM lineitem a JOIN lineitem b ON a.l_partkey = b.l_partkey WHERE a.l_returnflag = 'R' AND b.l_returnflag = 'A' AND datediff('day', CAST(a.l_shipdate AS DATE), CAST(b.l_shipdate AS DATE)) BETWEEN 0 AND 10 GROUP BY 1")
def join_self(s, d):
    li = load(s, d, "lineitem").select("l_partkey", "l_returnflag", D("l_shipdate").alias("day"))
    a, b = li.filter("l_returnflag = 'R'").alias("a"), li.filter("l_returnflag = 'A'").alias("b")
    return a.join(b, F.col("a.l_partkey") == F.col("b.l_partkey")).filter(F.datediff("b.day", "a.day").between(0, 10)).groupBy(F.col("a.l_partkey").alias("l_partkey")).agg(F.count("*").alias("n"))


@op("join_cross", f"SELECT n_nationkey AS seed, step, {sql.word('n_nationkey', 0, 'x', 'step')} AS word FROM nation, (SELECT DISTINCT step FROM ({sql.orders_sql(10)}))")
def join_cross(s, d):
    """A word for each nation, as one server's seed, at each step at which orders arrive."""
    seeds = load(s, d, "nation").select(F.col("n_nationkey").alias("seed"))
    steps = wl.W1W.left(s, d).select("step").distinct()
    return steps.crossJoin(F.broadcast(seeds)).select("seed", "step", noise.hash_word(F.col("seed"), "s0", "x", F.col("step")).alias("word"))


@op("public_multi_join", "SELECT r_name, n_name, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")
def public_multi_join(s, d):
    n = F.broadcast(load(s, d, "nation").join(F.broadcast(load(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name"))
    c = load(s, d, "customer").select("c_custkey", "c_nationkey")
    o = load(s, d, "orders").select("o_custkey", "o_totalprice")
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name", "n_name").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


# --- aggregates ----------------------------------------------------------------------------------------------------


@op("agg_steps", f"WITH {W1W_SIDES} SELECT step, count(*) FILTER (WHERE side = 'L') AS n_left, count(*) FILTER (WHERE side = 'R') AS n_right FROM (SELECT step, 'L' AS side FROM l UNION ALL SELECT step, 'R' FROM r) GROUP BY 1")
def agg_steps(s, d):
    left, right = wl.sides(wl.W1W, s, d)
    u = left.select("step", F.lit("L").alias("side")).unionByName(right.select("step", F.lit("R").alias("side")))
    return u.groupBy("step").agg(F.count_if(F.col("side") == "L").alias("n_left"), F.count_if(F.col("side") == "R").alias("n_right"))


@op("agg_distinct", "SELECT CAST(ts AS DATE) AS day, count(DISTINCT user_id) AS users, count(*) AS n FROM events GROUP BY 1")
def agg_distinct(s, d):
    return load(s, d, "events").groupBy(D("ts").alias("day")).agg(F.countDistinct("user_id").alias("users"), F.count("*").alias("n"))


@op("agg_approx")
def agg_approx(s, d):
    return load(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", [0.5, 0.9], 1000).alias("quantiles"))


@op("agg_filtered", "SELECT l_returnflag, count(*) FILTER (WHERE l_quantity > 25) AS n_real, count(*) FILTER (WHERE l_quantity <= 25) AS n_dummy FROM lineitem GROUP BY 1")
def agg_filtered(s, d):
    return load(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_if(F.col("l_quantity") > 25).alias("n_real"), F.count_if(F.col("l_quantity") <= 25).alias("n_dummy"))


LINES3 = "SELECT year(l_shipdate) AS yr, l_returnflag, l_linestatus FROM lineitem"
for _kind, _sql in (("rollup", "ROLLUP (yr, l_returnflag, l_linestatus)"), ("cube", "CUBE (yr, l_returnflag, l_linestatus)")):

    @op(f"agg_{_kind}", f"SELECT CAST(yr AS INTEGER) AS yr, l_returnflag, l_linestatus, count(*) AS n FROM ({LINES3}) GROUP BY {_sql}")
    def _multi(s, d, kind=_kind):
        x = load(s, d, "lineitem").select(F.year("l_shipdate").alias("yr"), "l_returnflag", "l_linestatus")
        return getattr(x, kind)("yr", "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@op("agg_grouping_sets", f"SELECT CAST(yr AS INTEGER) AS yr, l_returnflag, count(*) AS n FROM ({LINES3}) GROUP BY GROUPING SETS ((yr), (l_returnflag), ())")
def agg_grouping_sets(s, d):
    x = load(s, d, "lineitem").select(F.year("l_shipdate").alias("yr"), "l_returnflag")
    return x.groupingSets([["yr"], ["l_returnflag"], []], "yr", "l_returnflag").agg(F.count("*").alias("n"))


_P = wl.W1W.params
_BOTH = [("interval", "interval", _P), ("threshold", "threshold", _P)]


@op("agg_pivot", sql.trace_sql(wl.W1W, _BOTH, "SELECT step, CAST(max(l1) FILTER (WHERE run = 'interval') AS BIGINT) AS interval, CAST(max(l1) FILTER (WHERE run = 'threshold') AS BIGINT) AS threshold FROM traced GROUP BY step"))
def agg_pivot(s, d):
    return release.trace(sums(wl.W1W, s, d), _BOTH).groupBy("step").pivot("run", ["interval", "threshold"]).agg(F.max("l1"))


@op("agg_having", "SELECT l_partkey, count(*) AS n FROM lineitem WHERE l_returnflag = 'A' GROUP BY 1 HAVING count(*) > 10")
def agg_having(s, d):
    return load(s, d, "lineitem").filter("l_returnflag = 'A'").groupBy("l_partkey").agg(F.count("*").alias("n")).filter("n > 10")


# --- windows -------------------------------------------------------------------------------------------------------

_RANK_ORDER = "PARTITION BY l_suppkey ORDER BY CAST(l_shipdate AS DATE)"
_TOTAL_ORDER = f"PARTITION BY l_suppkey ORDER BY {', '.join(LINE_ORDER)}"
for _fn, _order, _call in (("row_number", _TOTAL_ORDER, "row_number()"), ("rank", _RANK_ORDER, "rank()"), ("dense_rank", _RANK_ORDER, "dense_rank()"), ("ntile", _TOTAL_ORDER, "ntile(4)")):

    @op(f"win_{_fn}", f"SELECT l_suppkey, l_orderkey, l_linenumber, l_partkey, CAST({_call} OVER ({_order}) AS INTEGER) AS k FROM lineitem WHERE l_returnflag = 'R'")
    def _rank(s, d, fn=_fn):
        x = load(s, d, "lineitem").filter("l_returnflag = 'R'")
        w = Window.partitionBy("l_suppkey").orderBy(*(LINE_ORDER if fn in ("row_number", "ntile") else [D("l_shipdate")]))
        k = F.ntile(4) if fn == "ntile" else getattr(F, fn)()
        return x.select("l_suppkey", "l_orderkey", "l_linenumber", "l_partkey", k.over(w).alias("k"))


def over_trace(name: str, select: str, f, runs=_BOTH) -> None:
    op(name, sql.trace_sql(wl.W1W, runs, select))(lambda s, d: f(release.trace(sums(wl.W1W, s, d), runs)))




def by_step():
    return Window.partitionBy("run").orderBy("step")


over_trace(
    "win_lag_lead",
    "SELECT run, step, step - lag(step) OVER w AS since, lead(step) OVER w - step AS until FROM traced WHERE fires WINDOW w AS (PARTITION BY run ORDER BY step)",
    lambda t: t.filter("fires").select("run", "step", (F.col("step") - F.lag("step").over(by_step())).alias("since"), (F.lead("step").over(by_step()) - F.col("step")).alias("until")),
)
over_trace("win_running_sum", "SELECT run, step, CAST(sum(n_real) OVER (PARTITION BY run ORDER BY step) AS BIGINT) AS total FROM traced", lambda t: t.select("run", "step", F.sum("n_real").over(by_step()).alias("total")))
over_trace("win_running_min", "SELECT run, step, CAST(min(n_real - want) OVER (PARTITION BY run ORDER BY step) AS BIGINT) AS low FROM traced", lambda t: t.select("run", "step", F.min(F.col("n_real") - F.col("want")).over(by_step()).alias("low")))
over_trace("win_rows_between", "SELECT run, step, round(avg(l1) OVER (PARTITION BY run ORDER BY step ROWS 9 PRECEDING), 6) AS recent_l1 FROM traced", lambda t: t.select("run", "step", F.round(F.avg("l1").over(by_step().rowsBetween(-9, 0)), 6).alias("recent_l1")))
over_trace("win_range_between", "SELECT run, step, CAST(sum(n_real) OVER (PARTITION BY run ORDER BY step RANGE BETWEEN 9 PRECEDING AND CURRENT ROW) AS BIGINT) AS arrived FROM traced", lambda t: t.select("run", "step", F.sum("n_real").over(by_step().rangeBetween(-9, 0)).alias("arrived")))
over_trace(
    "win_first_last",
    "SELECT run, step, last_value(CASE WHEN fires THEN step END IGNORE NULLS) OVER (PARTITION BY run ORDER BY step ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_release FROM traced",
    lambda t: t.select("run", "step", F.last(F.when(F.col("fires"), F.col("step")), ignorenulls=True).over(by_step().rowsBetween(Window.unboundedPreceding, 0)).alias("last_release")),
)
over_trace("topk_steps", "SELECT run, step, CAST(l1 AS BIGINT) AS l1 FROM traced ORDER BY l1 DESC, run, step LIMIT 10", lambda t: t.select("run", "step", "l1").orderBy(F.desc("l1"), "run", "step").limit(10))


@op("topk_keys", "SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1 ORDER BY n DESC, l_suppkey LIMIT 10")
def topk_keys(s, d):
    return load(s, d, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_suppkey").limit(10)


@op("sort_real_first", f"SELECT key, rid, is_view, CAST(row_number() OVER (ORDER BY is_view DESC, step, key, rid) AS INTEGER) AS place FROM (SELECT *, step > 200 AS is_view FROM ({sql.lines_sql('l_orderkey', 'R', 10)}) WHERE step BETWEEN 195 AND 205)")
def sort_real_first(s, d):
    x = wl.W1W.right(s, d).filter("step BETWEEN 195 AND 205").withColumn("is_view", F.col("step") > 200)
    return x.select("key", "rid", "is_view", F.row_number().over(Window.orderBy(F.desc("is_view"), "step", "key", "rid")).alias("place"))


# --- sets ----------------------------------------------------------------------------------------------------------


@op("set_union_all", f"WITH {sql.pairs_ctes(wl.W1W)}, s AS (SELECT t.born_step, l.step AS ls, r.step AS rs FROM truth t JOIN l ON l.rid = t.l_rid AND l.key = t.key JOIN r ON r.rid = t.r_rid AND r.key = t.key) SELECT part, count(*) AS n FROM (SELECT 'old x new' AS part FROM s WHERE ls < rs UNION ALL SELECT 'new x old' FROM s WHERE ls > rs UNION ALL SELECT 'new x new' FROM s WHERE ls = rs) GROUP BY 1")
def set_union_all(s, d):
    """The three parts of a delta, as one union."""
    t = derive.true_pairs(wl.W1W, *wl.sides(wl.W1W, s, d))
    part = lambda cond, name: t.filter(cond).select(F.lit(name).alias("part"))
    return part("l_step < r_step", "old x new").unionByName(part("l_step > r_step", "new x old")).unionByName(part("l_step = r_step", "new x new")).groupBy("part").agg(F.count("*").alias("n"))


@op("set_except", "SELECT CAST(0 AS BIGINT) AS n")
def set_except(s, d):
    """View rows that are not true pairs: none."""
    sides = wl.sides(wl.W1W, s, d)
    keys = ["key", "l_rid", "r_rid"]
    return derive.derive(wl.W1W, *sides).select(keys).exceptAll(derive.true_pairs(wl.W1W, *sides).select(keys)).agg(F.count("*").alias("n"))


for _name, _word in (("intersect", "INTERSECT"), ("union", "UNION")):

    @op(f"set_{_name}", f"SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R' {_word} SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'A'")
    def _sets(s, d, name=_name):
        li = load(s, d, "lineitem").select("l_orderkey", "l_returnflag")
        a, b = (li.filter(F.col("l_returnflag") == f).select("l_orderkey") for f in "RA")
        return a.intersect(b) if name == "intersect" else a.union(b).distinct()


# --- functions -----------------------------------------------------------------------------------------------------


@op("fn_bits", "SELECT o_orderkey, xor(o_orderkey, o_custkey) AS x, o_orderkey & 255 AS low, o_orderkey >> 3 AS sh, lower(hex(o_orderkey)) AS h, md5(CAST(o_orderkey AS VARCHAR)) AS m FROM orders")
def fn_bits(s, d):
    k = F.col("o_orderkey")
    return load(s, d, "orders").select("o_orderkey", k.bitwiseXOR(F.col("o_custkey")).alias("x"), k.bitwiseAND(255).alias("low"), F.shiftright(k, 3).alias("sh"), F.lower(F.hex(k)).alias("h"), F.md5(k.cast("string")).alias("m"))


@op("fn_math", "SELECT o_orderkey, round(ln(o_totalprice), 6) AS l, CAST(floor(o_totalprice / 7) AS BIGINT) AS f, CAST(((o_orderkey - 50) % 7 + 7) % 7 AS BIGINT) AS p, greatest(o_orderkey, o_custkey) AS g, least(o_orderkey, o_custkey) AS s, CAST(sign(o_totalprice - 150000) AS DOUBLE) AS sg FROM orders")
def fn_math(s, d):
    c = F.col
    return load(s, d, "orders").select("o_orderkey", F.round(F.log("o_totalprice"), 6).alias("l"), F.floor(c("o_totalprice") / 7).alias("f"), F.pmod(c("o_orderkey") - 50, F.lit(7)).alias("p"), F.greatest("o_orderkey", "o_custkey").alias("g"), F.least("o_orderkey", "o_custkey").alias("s"), F.signum(c("o_totalprice") - 150000).alias("sg"))


@op("fn_dates", "SELECT o_orderkey, CAST(datediff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, CAST(CAST(o_orderdate AS DATE) + INTERVAL 10 DAY AS DATE) AS due, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q FROM orders")
def fn_dates(s, d):
    day = D("o_orderdate")
    return load(s, d, "orders").select("o_orderkey", F.datediff(day, F.lit("1995-01-01").cast("date")).alias("days"), F.trunc(day, "month").alias("month"), F.date_add(day, 10).alias("due"), F.year(day).alias("y"), F.quarter(day).alias("q"))


@op("fn_strings", "SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host, substr(url, 1, 5) AS scheme, CAST(length(url) AS INTEGER) AS n, concat_ws('|', CAST(page_id AS VARCHAR), upper(substr(url, 1, 3))) AS tag FROM pages")
def fn_strings(s, d):
    u = F.col("url")
    return load(s, d, "pages").select("page_id", F.regexp_extract(u, "://([^/?#]*)", 1).alias("host"), F.substring(u, 1, 5).alias("scheme"), F.length(u).alias("n"), F.concat_ws("|", F.col("page_id").cast("string"), F.upper(F.substring(u, 1, 3))).alias("tag"))


@op("fn_json", "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY 1")
def fn_json(s, d):
    return load(s, d, "events").groupBy("event_type").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("total"))


@op("fn_arrays", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm2, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS n_pos FROM embeddings")
def fn_arrays(s, d):
    dot = F.aggregate(F.zip_with("embedding", "embedding", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return load(s, d, "embeddings").select("vec_id", F.round(dot, 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("n_pos"))


@op("fn_maps", "SELECT name, value, count(*) AS n FROM (SELECT 'status' AS name, o_orderstatus AS value FROM orders UNION ALL SELECT 'priority', o_orderpriority FROM orders) GROUP BY 1, 2")
def fn_maps(s, d):
    """Each order's attributes as a map; its entries are counted."""
    m = F.create_map(F.lit("status"), "o_orderstatus", F.lit("priority"), "o_orderpriority")
    e = load(s, d, "orders").select(F.explode(F.map_entries(m)).alias("e")).select(F.col("e.key").alias("name"), F.col("e.value").alias("value"))
    return e.groupBy("name", "value").agg(F.count("*").alias("n"))


EVENT_TS = lambda s, d: load(s, d, "events").withColumn("t", F.col("ts").cast("timestamp"))


@op("win_tumbling", "SELECT CAST(epoch_us(ts) // 43200000000 AS BIGINT) AS w, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def win_tumbling(s, d):
    return EVENT_TS(s, d).groupBy(F.window("t", "12 hours").alias("x"), "event_type").agg(F.count("*").alias("n")).select(F.floor(F.unix_seconds("x.start") / 43200).alias("w"), "event_type", "n")


@op("win_sliding", "SELECT w, count(*) AS n FROM (SELECT CAST(unnest([epoch_us(ts) // 21600000000, epoch_us(ts) // 21600000000 - 1]) AS BIGINT) AS w FROM events) GROUP BY 1")
def win_sliding(s, d):
    return EVENT_TS(s, d).groupBy(F.window("t", "12 hours", "6 hours").alias("x")).agg(F.count("*").alias("n")).select(F.floor(F.unix_seconds("x.start") / 21600).alias("w"), "n")


@op("win_session", "SELECT user_id, count(*) AS sessions FROM (SELECT user_id, epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) AS gap FROM events) WHERE gap IS NULL OR gap >= 21600000000 GROUP BY 1")
def win_session(s, d):
    return EVENT_TS(s, d).groupBy("user_id", F.session_window("t", "6 hours")).agg(F.count("*").alias("n")).groupBy("user_id").agg(F.count("*").alias("sessions"))


@op("sample_hash", f"SELECT key, rid FROM ({sql.lines_sql('l_orderkey', 'R', 10)}) WHERE {sql.SPARSE}")
def sample_hash(s, d):
    return wl.sparse(wl.W1W.right(s, d)).select("key", "rid")


@op("replicate_keys", f"SELECT rid, key + c * {1 << 40} AS key, step FROM ({sql.orders_sql(10)}), (VALUES (0), (1), (2), (3)) AS v(c)")
def replicate_keys(s, d):
    return wl.burst(wl.W1W.left(s, d), 4).select("rid", "key", "step")


# --- the other given tables ----------------------------------------------------------------------------------------


@op("docs_filter_view", "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents WHERE lang = 'en' GROUP BY 1, 2")
def docs_filter_view(s, d):
    return load(s, d, "documents").filter("lang = 'en'").groupBy("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@op("docs_labels_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def docs_labels_semi(s, d):
    return load(s, d, "documents").select("doc_id", "lang").join(load(s, d, "labels").filter("quality = 1").select("doc_id"), "doc_id", "left_semi")


@op("conversation_last_turn", "SELECT conv_id, turn, role FROM (SELECT *, max(turn) OVER (PARTITION BY conv_id) AS m FROM conversations) WHERE turn = m")
def conversation_last_turn(s, d):
    c = load(s, d, "conversations").select("conv_id", "turn", "role")
    return c.withColumn("m", F.max("turn").over(Window.partitionBy("conv_id"))).filter("turn = m").drop("m")


@op("benchmark_anti", "SELECT item_id FROM benchmark WHERE item_id NOT IN (SELECT doc_id FROM labels)")
def benchmark_anti(s, d):
    return load(s, d, "benchmark").select("item_id").join(load(s, d, "labels").select(F.col("doc_id").alias("item_id")), "item_id", "left_anti")
