"""Timed end-to-end runs: the stages of both release rules and the baselines' queries, on stored views."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import baselines, derive, metrics, query, release
from .plans import workloads as wl
from .plans.views import ViewSpec
from .sources.tables import stored

SCHEMA = "strategy string, derive_s double, release_s double, qet_s double, view_rows long, answer long, truth long"


def run(spark: SparkSession, sf_dir: str, spec: ViewSpec) -> DataFrame:
    """One row for each strategy: seconds of derive and release over the whole history, seconds of one query at the
    end, rows in the view, and the query's answer beside the truth."""
    left, right = (stored(x, "side") for x in wl.sides(spec, spark, sf_dir))

    def clock(f):
        t = time.perf_counter()
        out = f()
        return out, time.perf_counter() - t

    pairs, derive_s = clock(lambda: stored(derive.numbered(derive.derive(spec, left, right)), "pairs"))
    sums = stored(derive.summaries(spec, left, right).coalesce(1), "summaries")
    last = sums.agg(F.max("step")).first()[0] or 0
    truth, nm_s = clock(lambda: baselines.nm_query(spec, left, right, last).first()[0])
    rows = [("nm", 0.0, 0.0, nm_s, 0, truth, truth)]
    for s in ("interval", "threshold"):

        def build(s=s):
            t = stored(release.trace(sums, [(s, s, spec.params)]).coalesce(1), "trace")
            real = release.place_rows(pairs, t, spec.params.purge_every)
            return t, stored(real.unionByName(release.dummy_rows(t), allowMissingColumns=True), "view")

        (t, view), release_s = clock(build)
        answer, qet = clock(lambda view=view: query.answer(view, last).first()[0])
        rows.append((s, derive_s, release_s, qet, view.count(), answer, truth))
    # the padded view holds every slot as a row
    padded = sums.filter("n_padded > 0").select(F.col("step").alias("release_step"), F.explode(F.sequence(F.lit(1).cast("long"), "n_padded")).alias("k"), "n_real")
    ep = stored(padded.select("release_step", (F.col("k") <= F.col("n_real")).alias("is_view")), "padded")
    answer, qet = clock(lambda: query.answer(ep, last).first()[0])
    rows.append(("ep", derive_s, 0.0, qet, ep.count(), answer, truth))
    return spark.createDataFrame(rows, SCHEMA)


def totals(runs: DataFrame) -> DataFrame:
    """strategy, maintenance_s, query_s: sums over runs (replicated data, several views)."""
    return runs.groupBy("strategy").agg(F.round(F.sum(F.col("derive_s") + F.col("release_s")), 3).alias("maintenance_s"), F.round(F.sum("qet_s"), 3).alias("query_s"))


def gains(runs: DataFrame) -> DataFrame:
    """Gains in query time over each baseline."""
    out = None
    for base in ("nm", "ep"):
        g = metrics.improvement(runs, base, "qet_s").select("strategy", F.col("gain").alias(f"gain_over_{base}"))
        out = g if out is None else out.join(g, "strategy")
    return out


def mean_over_seeds(sums: DataFrame, settings: list[tuple[str, str, object]], seeds: int = 20) -> DataFrame:
    """setting, strategy, l1, rel, rows, releases: means over seeds of a run's mean over steps."""
    runs = [(f"{name}|{strategy}|{k}", strategy, p.but(seed=str(500 + k))) for name, strategy, p in settings for k in range(seeds)]
    t = release.trace(sums, runs)
    one = t.groupBy("run").agg(
        F.avg("l1").alias("l1"),
        F.avg(F.when(F.col("truth") > 0, F.col("l1") / F.col("truth"))).alias("rel"),
        F.avg("view_rows").alias("rows"),
        F.sum(F.col("fires").cast("long")).alias("releases"),
    )
    parts = F.split("run", r"\|")
    return one.groupBy(parts[0].alias("setting"), parts[1].alias("strategy")).agg(*(F.round(F.avg(c), 3).alias(c) for c in ("l1", "rel", "rows", "releases")))


def report(spark: SparkSession, sf_dir: str, seeds: int = 20) -> str:
    """The experiments' tables as Markdown: comparison, privacy, density, interval and threshold, omega, scale."""
    from .catalog import comparison

    out: list[str] = []

    def table(title: str, df: DataFrame, order: list[str]) -> None:
        rows = df.orderBy(*order).collect()
        out.append(f"\n### {title}\n\n| {' | '.join(df.columns)} |\n|{' --- |' * len(df.columns)}")
        out.extend("| " + " | ".join("" if v is None else f"{v:.6g}" if isinstance(v, float) else str(v) for v in r) + " |" for r in rows)

    two = lambda name, p: [(name, s, p) for s in ("interval", "threshold")]
    table("w2: strategies, paper's budget of two uses", comparison(wl.W2, wl.W2.params)[0](spark, sf_dir), ["strategy"])
    for spec in (wl.W1W, wl.W2B30):
        p = spec.params
        left, right = (stored(x, "side") for x in wl.sides(spec, spark, sf_dir))
        sums = stored(derive.summaries(spec, left, right).coalesce(1), "summaries")
        table(f"{spec.name}: strategies, default parameters", comparison(spec, p)[0](spark, sf_dir), ["strategy"])
        table(f"{spec.name}: seconds on stored views", run(spark, sf_dir, spec), ["strategy"])
        table(f"{spec.name}: privacy", mean_over_seeds(sums, [x for e in wl.EPS_SWEEP for x in two(f"eps {e:05.2f}", p.but(eps=e))], seeds), ["strategy", "setting"])
        rate = sums.agg(F.avg("n_real")).first()[0]
        steps = [(t, max(1.0, round(rate * t))) for t in wl.T_SWEEP]
        for e in (0.1, 1.0, 10.0):
            table(f"{spec.name}: interval and threshold at eps {e}", mean_over_seeds(sums, [x for t, th in steps for x in two(f"T {t:>3} theta {th:g}", p.but(eps=e, interval=t, theta=th))], seeds), ["strategy", "setting"])
        dens = []
        for name, f in (("sparse", lambda a, b: (a, wl.sparse(b))), ("burst", lambda a, b: (wl.burst(a), wl.burst(b))), ("4 x", lambda a, b: (wl.burst(a, 4), wl.burst(b, 4)))):
            s = stored(derive.summaries(spec, *f(left, right)).coalesce(1), "summaries")
            dens.append(mean_over_seeds(s, two(name, p), seeds))
        table(f"{spec.name}: density and scale", dens[0].unionByName(dens[1]).unionByName(dens[2]), ["setting", "strategy"])
    rows = None
    for w in wl.OMEGA_SWEEP:
        spec = wl.w2m(72, 36, w)
        sums = stored(derive.summaries(spec, *wl.sides(spec, spark, sf_dir)).coalesce(1), "summaries")
        x = mean_over_seeds(sums, two(f"omega {w:>2}", spec.params), seeds)
        x = x.crossJoin(F.broadcast(sums.agg(F.sum("n_true").alias("true_pairs"), F.sum("n_real").alias("kept_pairs"), F.sum("n_padded").alias("padded_slots"))))
        rows = x if rows is None else rows.unionByName(x)
    table("w2m_72: truncation bound, budget twice the bound", rows, ["strategy", "setting"])
    return "\n".join(out)


if __name__ == "__main__":
    import sys

    session = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    session.sparkContext.setLogLevel("ERROR")
    print(report(session, sys.argv[1]))
