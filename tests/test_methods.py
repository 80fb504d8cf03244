"""Worked fixtures and brute force for the methods."""

from __future__ import annotations

import math
import random
from dataclasses import replace

import pytest
from pyspark.sql import functions as F
from twins import differences, duck

from pdpview.catalog import QUERIES
from pdpview.functions import noise, privacy, shares
from pdpview.functions.udtf import walk
from pdpview.operators import buffer, budget, derive, leakage, metrics, multilevel, query, release, steps, truncate
from pdpview.params import Params
from pdpview.plans import workloads as wl
from pdpview.plans.views import ViewSpec


def one(spark, *cols):
    return spark.range(1).select(*cols).first()


def test_shares(spark):
    w = F.lit(2147483653).cast("long")
    a, b = shares.split(F.lit(13).cast("long"), w)
    assert tuple(one(spark, a, b, shares.recover(a, b))) == (2147483653, 2147483656, 13)
    assert tuple(one(spark, *shares.reshare(F.lit(9).cast("long"), F.lit(6).cast("long"), F.lit(3).cast("long")))) == (5, 12)
    assert one(spark, *shares.split_n(F.lit(7).cast("long"), [F.lit(1).cast("long"), F.lit(2).cast("long")]))[2] == 4


def test_noise_values(spark):
    r = one(spark, *(noise.laplace(F.lit(z).cast("long"), 10 / 1.5) for z in (0xC0000000, 0x40000000, 0)))
    assert r[0] == pytest.approx(10 / 1.5 * math.log((2**30 + 0.5) / 2**31)) and r[1] == -r[0] and math.isfinite(r[2])
    assert noise.laplace_value(0xC0000000, 10 / 1.5) == pytest.approx(r[0])


def test_noise_moments(spark):
    g = spark.range(100_000).select(noise.laplace(noise.joint_word("3", "x", F.col("id")), 1.0).alias("x"), noise.geometric(noise.joint_word("4", "x", F.col("id")), 5.0).alias("k"))
    m = g.agg(F.avg("x"), F.var_pop("x"), F.corr(F.signum("x"), F.abs("x")), F.avg("k"), F.avg(F.abs("k"))).first()
    assert abs(m[0]) < 0.02 and abs(m[1] - 2) < 0.06 and abs(m[2]) < 0.02
    q = math.exp(-1 / 5)
    assert abs(m[3]) < 0.1 and abs(m[4] - 2 * q / (1 - q * q)) < 0.1


def test_geometric_mass(spark):
    """Every value's share is that of the two-sided law, so neighbouring counts differ by e^(1/scale) at most."""
    n, scale = 400_000, 10 / 1.5
    q = math.exp(-1 / scale)
    k = spark.range(n).select(noise.geometric(noise.joint_word("9", "geo", F.col("id")), scale).alias("k"))
    share = {r.k: r["count"] / n for r in k.groupBy("k").count().collect()}
    for v in range(-25, 26):
        want = (1 - q) / (1 + q) * q ** abs(v)
        assert abs(share.get(v, 0) - want) < 5 * math.sqrt(want / n), v
    words = [0, 1, (1 << 31) - 1, 1 << 31, (1 << 32) - 1]
    got = [one(spark, noise.geometric(F.lit(w).cast("long"), scale))[0] for w in words]
    assert got[2] == got[4] == 0 and got[0] < got[1] < -60 and got[3] > 60


def test_parameters():
    assert Params(omega=1, budget=10).horizon == 10 and Params(omega=10, budget=20).horizon == 2
    for bad in ({"omega": 10, "budget": 5}, {"eps": 0}, {"interval": 0}, {"pad_rule": "x"}, {"pad_rule": "scan"}, {"batch_cap": (0, 5)}):
        with pytest.raises(ValueError):
            Params(**bad)


def scan_brute(n1: int, n2: int, omega: int) -> set:
    """The scan over the sorted union: a right tuple meets left tuples in order while both have room."""
    used_l, used_r, out = [0] * n1, [0] * n2, set()
    for j in range(n2):
        for i in range(n1):
            if used_l[i] < omega and used_r[j] < omega:
                used_l[i] += 1
                used_r[j] += 1
                out.add((i, j))
    return out


def test_blocks_equal_scan(spark):
    cases = [(g, n1, n2) for g, (n1, n2) in enumerate((a, b) for a in range(8) for b in range(8))]
    left = spark.createDataFrame([(g, i) for g, n, _ in cases for i in range(n)], "g int, l_rid long")
    right = spark.createDataFrame([(g, j) for g, _, n in cases for j in range(n)], "g int, r_rid long")
    for omega in (1, 2, 3, 5):
        got: dict[int, set] = {}
        for r in truncate.merge_join(left, right, ["g"], ["l_rid"], ["r_rid"], omega).collect():
            got.setdefault(r.g, set()).add((r.l_rid, r.r_rid))
        full = left.join(right, "g")
        greedy: dict[int, set] = {}
        for r in truncate.scan(full, ["g"], omega).collect():
            greedy.setdefault(r.g, set()).add((r.l_rid, r.r_rid))
        for g, n1, n2 in cases:
            assert got.get(g, set()) == scan_brute(n1, n2, omega) == greedy.get(g, set())
    assert [len(scan_brute(3, 5, w)) for w in (1, 2, 3, 5)] == [3, 6, 9, 15]


def test_ranks_of_hot_groups(spark):
    """Groups ranked in parts have the ranks of a plain window, whatever is hot."""
    rng = random.Random(4)
    ids = rng.sample(range(-(1 << 59), 1 << 59), 700)
    rows = [(int(rng.random() < 0.3), rng.randint(0, 2), i) for i in ids[:400]] + [(2, rng.randint(0, 2), k) for k in range(300)] + [(3, 0, 5), (None, 0, 6), (None, 1, 7)]
    df = spark.createDataFrame(rows, "g int, step int, rid long").repartition(5)
    for order in (["rid"], ["step", "rid"]):
        want = {}
        for r in sorted((r for r in rows if r[0] is not None), key=lambda r: (r[0], *((r[1],) if len(order) > 1 else ()), r[2])):
            want[r] = want[r] + 1 if r in want else 1 + max((v for k, v in want.items() if k[0] == r[0]), default=0)
        for hot in (10, 299, 10_000):
            got = {tuple(r)[:3]: r.k for r in truncate.ranked(df.filter("g IS NOT NULL"), ["g"], order, "k", hot).select("g", "step", "rid", "k").collect()}
            assert got == want
    left, right = (df.filter("g IS NOT NULL").select("g", F.col("rid").alias(n)) for n in ("l_rid", "r_rid"))
    plain, parts = (truncate.merge_join(left, right, ["g"], ["l_rid"], ["r_rid"], 3, hot) for hot in (None, 20))
    assert sorted(map(tuple, plain.collect())) == sorted(map(tuple, parts.select(plain.columns).collect()))


def test_span_loses_no_pair(spark, small):
    """Pairs looked for among neighbouring steps are the pairs of the whole history."""
    for spec in (wl.W1, wl.W1W, wl.W2, wl.W2S, wl.W2M240, wl.W2M72, wl.W2M24):
        sides = wl.sides(spec, spark, small)
        near, all_ = (derive.true_pairs(x, *sides) for x in (spec, replace(spec, span=None)))
        assert near.exceptAll(all_).count() == all_.exceptAll(near).count() == 0 < all_.count()


def test_theta_join(spark, small):
    from pdpview.catalog import QUERIES
    from pdpview.sources.tables import load, step_of_hours

    got = {}
    for r in QUERIES["trunc_theta"].run(spark, small).collect():
        got.setdefault((r.born_step, r.key), set()).add((r.l_rid, r.r_rid))
    e = load(spark, small, "events").withColumn("step", step_of_hours(F.col("ts"), "2024-01-01", 240)).collect()
    groups = {}
    for r in e:
        if r.event_type in ("error", "purchase"):
            groups.setdefault((r.step, r.user_id), {}).setdefault(r.event_type, []).append((r.event_id, r.value))
    want = {}
    for k, g in groups.items():
        used_l, used_r, out = {}, {}, set()
        for b, vb in sorted(g.get("purchase", [])):
            for a, va in sorted(g.get("error", [])):
                if va < vb and used_l.get(a, 0) < 2 and used_r.get(b, 0) < 2:
                    used_l[a], used_r[b] = used_l.get(a, 0) + 1, used_r.get(b, 0) + 1
                    out.add((a, b))
        if out:
            want[k] = out
    assert got == want and len(want) > 10


def test_removal_changes_count_by_omega():
    import pandas as pd

    rng = random.Random(5)
    for _ in range(300):
        n1, n2, omega = rng.randint(1, 6), rng.randint(1, 6), rng.randint(1, 3)
        pairs = [(i, j) for j in range(n2) for i in range(n1) if rng.random() < 0.6]
        count = lambda ps: len(truncate.greedy(pd.DataFrame(ps, columns=["l_rid", "r_rid"]), omega))  # noqa: E731, B023
        for i in range(n1):
            assert abs(count(pairs) - count([p for p in pairs if p[0] != i])) <= omega


def random_sides(spark, seed: int):
    rng = random.Random(seed)
    rows = lambda n, side: [(k, rng.randint(0, 3), None, rng.randint(1, 8)) for k in range(n)]  # noqa: E731, ARG005
    schema = "rid long, key long, day date, step int"
    return spark.createDataFrame(rows(25, "l"), schema), spark.createDataFrame(rows(25, "r"), schema)


@pytest.mark.parametrize("seed", range(4))
def test_batch_equals_steps(spark, seed):
    p = Params(omega=1 + seed % 2, budget=4)
    spec = ViewSpec("t", None, None, 0, p.horizon - 1, params=p)
    left, right = random_sides(spark, seed)
    whole = sorted(map(tuple, derive.derive(spec, left, right).collect()))
    single = sorted(tuple(r) for t in range(1, 9) for r in derive.increment(spec, left, right, t).collect())
    assert whole == single
    per_use = {}
    for t, k, a, b in whole:
        for side, rid in (("l", a), ("r", b)):
            per_use[t, k, side, rid] = per_use.get((t, k, side, rid), 0) + 1
    assert max(per_use.values(), default=0) <= p.omega
    life = {}
    for (_, k, side, rid), n in per_use.items():
        life[k, side, rid] = life.get((k, side, rid), 0) + n
    assert max(life.values(), default=0) <= p.budget
    truth = {tuple(r) for r in derive.true_pairs(spec, left, right).select("born_step", "key", "l_rid", "r_rid").collect()}
    assert set(whole) <= truth


@pytest.mark.parametrize("seed", range(2))
def test_private_by_public_increments(spark, seed):
    spec = ViewSpec("t", None, None, 0, 5, right_public=True, params=Params(omega=2, budget=6))
    left, right = random_sides(spark, 10 + seed)
    whole = sorted(map(tuple, derive.derive(spec, left, right).collect()))
    assert whole == sorted(tuple(r) for t in range(1, 9) for r in derive.increment(spec, left, right, t).collect())


def test_ledger_is_horizon(spark):
    p = Params(omega=3, budget=10)
    df = spark.createDataFrame([(k, 0, k) for k in range(1, 12)], "rid long, key long, step int")
    for t in (1, 4, 9, 15):
        left = {}
        for step in range(1, 12):
            money, uses = p.budget, 0
            for now in range(step, t + 1):
                if money >= p.omega:
                    money, uses = money - p.omega, now
            left[step] = (money, uses == t)
        led = {r.step: r.budget_left for r in budget.ledger(df, t, p).collect()}
        act = {r.step for r in budget.active(df, t, p).collect()}
        for s in range(1, 12):
            assert led[s] == left[s][0]
            assert (s in act) == (s <= t and left[s][1])


ARRIVALS = [3, 0, 2, 4, 1, 0]


def sized(spark, strategy: str, wants: list[int], every: int, size: int):
    rows = [("r", t, a, a, w, every, size) for t, (a, w) in enumerate(zip(ARRIVALS, wants, strict=True), 1)]
    return spark.createDataFrame(rows, "run string, step int, n_real long, n_true long, want long, purge_every int, purge_size int")


def test_interval_trace(spark):
    t = release.series(release.buffer_depth(sized(spark, "interval", [0, 2, 0, 8, 0, 0], 100, 0))).orderBy("step").collect()
    assert [r.real_out for r in t] == [0, 2, 0, 7, 0, 0]
    assert [r.dummy_out for r in t] == [0, 0, 0, 1, 0, 0]
    assert [r.deferred for r in t] == [3, 1, 3, 0, 1, 1]
    assert [r.view_rows for r in t] == [0, 2, 2, 10, 10, 10]
    assert [r.l1 for r in t] == [3, 1, 3, 0, 1, 1]


def test_purge_trace(spark):
    t = release.series(release.buffer_depth(sized(spark, "interval", [0, 2, 0, 8, 0, 0], 5, 0))).orderBy("step").collect()
    assert (t[4].discarded, t[5].deferred) == (1, 0)
    t = release.series(release.buffer_depth(sized(spark, "interval", [0, 2, 0, 8, 0, 0], 5, 2))).orderBy("step").collect()
    assert (t[4].purge_real, t[4].purge_dummy, t[5].answer, t[5].l1, t[5].view_rows) == (1, 1, 10, 0, 12)


def test_threshold_walk():
    zs = [{"chk": c, "rel": r, "thr": 0.0} for c, r in zip([0.4, -1, 0.2, 2, 0, 4], [0, 0, 0, -2, 0, 1], strict=True)]
    zs[3]["thr"] = -0.8
    w = walk("threshold", ARRIVALS, zs, {"theta": 5.0, "thr0": 0.5, "every_steps": 1, "purge_every": 100, "purge_size": 0})
    assert [r[2] for r in w] == [False, False, False, True, False, True]
    assert [r[3] for r in w] == [0, 0, 0, 7, 0, 2] and [r[5] for r in w] == [3, 3, 5, 2, 3, 1]


@pytest.mark.parametrize("seed", range(5))
def test_depth_is_loop(spark, seed):
    rng = random.Random(seed)
    n, every, size = 60, rng.choice([7, 13, 1000]), rng.randint(0, 4)
    rows = [("r", t, rng.randint(0, 5), 0, rng.choice([0, 0, rng.randint(0, 12)]), every, size) for t in range(1, n + 1)]
    got = release.buffer_depth(spark.createDataFrame(rows, "run string, step int, n_real long, n_true long, want long, purge_every int, purge_size int")).orderBy("step").collect()
    d = 0
    for r, g in zip(rows, got, strict=True):
        d += r[2]
        out = min(r[4], d)
        d -= out
        gone = pr = 0
        if r[1] % every == 0:
            pr = min(size, d)
            gone, d = d - pr, 0
        assert (g.real_out, g.deferred, g.purge_real, g.discarded) == (out, d, pr, gone)


def test_three_forms_agree(spark, small):
    sums = derive.summaries(wl.W2M72, *wl.sides(wl.W2M72, spark, small)).cache()
    p = wl.W2M72.params
    runs = [(f"t{k}", "threshold", p.but(seed=str(k), eps=e)) for k, e in enumerate((0.5, 1.5, 20.0))]
    frame = release.with_runs(sums, runs)
    cols = ["run", "step", "c", "fires", "want"]
    a = sorted(map(tuple, release.threshold_sizes(frame).select(cols).collect()))
    assert a == sorted(map(tuple, release.threshold_sizes_grouped(frame).select(cols).collect()))


@pytest.mark.parametrize("resets", [False, True])
def test_purge_and_counter(spark, small, resets):
    """Both rules, set-based and as a grouped function, against plain iteration when purges come between releases."""
    sums = derive.summaries(wl.W2M72, *wl.sides(wl.W2M72, spark, small)).cache()
    p = wl.W2M72.params.but(eps=20.0, interval=4, theta=40, purge_every=6, purge_size=4, purge_resets_counter=resets)
    arrivals = [r.n_real for r in sums.orderBy("step").collect()]
    z = release.threshold_noise(release.with_runs(sums, [("t", "threshold", p)])).orderBy("step").collect()
    for strategy in ("interval", "threshold"):
        half = 0.5 if strategy == "interval" else 1.0
        zs = [{"chk": r.chk, "rel": r.rel * half, "thr": r.thr} for r in z]
        want = walk(strategy, arrivals, zs, {"theta": p.theta, "thr0": z[0].thr0 - p.theta, "every_steps": 4, "purge_every": 6, "purge_size": 4, "purge_resets_counter": resets})
        t = release.trace(sums, [("x", strategy, p)]).orderBy("step").collect()
        assert [(r.step, r.c, r.fires, r.want, r.real_out, r.deferred, r.discarded) for r in t] == want
    grouped = release.threshold_sizes_grouped(release.with_runs(sums, [("x", "threshold", p)])).orderBy("step").collect()
    assert [(r.c, r.fires, r.want) for r in grouped] == [(r.c, r.fires, r.want) for r in t]


def test_system_noise_is_drawn_once(spark, small):
    """A frame on system words gives the same sizes each time it is read, and other sizes when it is made again."""
    sums = derive.summaries(wl.W2M72, *wl.sides(wl.W2M72, spark, small)).cache()
    p = wl.W2M72.params.but(system_noise=True, interval=1)
    runs = [("i", "interval", p), ("t", "threshold", p), ("h", "interval", p.but(system_noise=False))]
    a, b = release.trace(sums, runs), release.trace(sums, runs)
    rows = lambda t, run: [(r.step, r.want) for r in t.filter(F.col("run") == run).orderBy("step").collect()]
    for run in "it":
        assert rows(a, run) == rows(a, run)
    assert rows(a, "i") != rows(b, "i") and rows(a, "h") == rows(b, "h") == rows(release.trace(sums, [("h", "interval", p.but(system_noise=False))]), "h")
    with pytest.raises(ValueError):
        leakage.mech_interval(sums, p)


def test_placement_is_first_in_first_out(spark, small):
    left, right = wl.sides(wl.W2M72, spark, small)
    run = ("i", "interval", wl.W2M72.params.but(eps=5.0, purge_every=7, purge_size=3))
    t = release.trace(derive.summaries(wl.W2M72, left, right), [run]).cache()
    pairs = derive.numbered(derive.derive(wl.W2M72, left, right)).cache()
    placed = release.place_rows(pairs, t, 7).collect()
    queue, out = [], {}
    by_step: dict[int, list] = {}
    for r in sorted(pairs.collect(), key=lambda r: (r.born_step, r.ord)):
        by_step.setdefault(r.born_step, []).append((r.born_step, r.key, r.l_rid, r.r_rid))
    for r in t.orderBy("step").collect():
        queue += by_step.get(r.step, [])
        k = r.real_out + r.purge_real
        for x in queue[:k]:
            out[x] = r.step
        queue = [] if r.step % 7 == 0 else queue[k:]
    assert {(r.born_step, r.key, r.l_rid, r.r_rid): r.release_step for r in placed} == out


def test_error_split_adds_up(spark, small):
    for spec in (wl.W2M72, wl.W1W):
        p = spec.params.but(purge_every=11, purge_size=1)
        t = release.trace(derive.summaries(spec, *wl.sides(spec, spark, small)), [("i", "interval", p), ("t", "threshold", p)])
        for r in metrics.error_split(t).collect():
            assert r.truth - r.answer == r.truncation_loss + r.retirement_loss + r.deferred + r.purge_loss


@pytest.mark.parametrize("strategy", ["interval", "threshold"])
def test_transcript_follows_from_mechanism(spark, small, strategy):
    """What a run moves equals the simulator's sizes, and uploads and cached rows do not move with the data."""
    mech = {"interval": leakage.mech_interval, "threshold": leakage.mech_threshold}[strategy]
    for base, rule in ((wl.W1W, "budget"), (wl.W1W, "omega"), (wl.W2M72, "budget"), (wl.W2M72, "omega")):
        p = base.params.but(batch_cap=(300, 310), pad_rule=rule, purge_every=9, purge_size=4)
        spec = replace(base, params=p)
        left, right = wl.sides(spec, spark, small)

        def run(left, spec=spec, right=right):
            sums = derive.summaries(spec, left, right).cache()
            seen = leakage.transcript(sums, release.trace(sums, [("x", strategy, spec.params)]), spec)
            return sums, sorted(map(tuple, seen.select("step", "uploaded", "cached", "released", "purged").collect()))

        sums, seen = run(left)
        made = leakage.simulate(mech(sums, p), spec).select("step", "uploaded", "cached", "released", "purged")
        assert seen == sorted(map(tuple, made.collect())) and sum(x[3] for x in seen) > 0
        busy = left.groupBy("step").count().filter("step < 15").orderBy(F.desc("count")).first().step
        gone = left.filter(F.col("step") == busy).first().rid
        for other in (left.filter(F.col("rid") != gone), left.filter(F.col("step") != busy)):  # a row, and a whole batch
            assert [x[:3] for x in run(other)[1]] == [x[:3] for x in seen]
    with pytest.raises(ValueError):
        leakage.simulate(mech(sums, p), wl.W1W)


def test_batch_above_its_declared_size_is_an_error(spark, small):
    spec = replace(wl.W2M72, params=wl.W2M72.params.but(batch_cap=(2, 2)))
    with pytest.raises(Exception, match="declared size"):
        derive.summaries(spec, *wl.sides(spec, spark, small)).collect()


@pytest.fixture(scope="session")
def crowded(spark, small, tmp_path_factory):
    """The smallest tables with one order of 4,500 lines, returned and kept, in one step: above the declared 4,096."""
    folder = tmp_path_factory.mktemp("crowded")
    orders, lines = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("orders", "lineitem"))
    o = orders.filter("o_orderdate >= '1996-02-01'").orderBy("o_orderkey").limit(1).withColumn("o_orderkey", F.lit(10_000_000).cast("long"))
    more = lines.limit(1).drop("l_returnflag").join(spark.range(9000).select(F.col("id").alias("k")))
    more = more.join(o.select(F.col("o_orderdate").alias("at"))).withColumns({"l_orderkey": F.lit(10_000_000).cast("long"), "l_linenumber": F.col("k").cast("int"), "l_shipdate": F.col("at"), "l_returnflag": F.when(F.col("k") % 2 == 0, "R").otherwise("A")})
    orders.union(o).write.parquet(f"{folder}/orders.parquet")
    lines.union(more.withColumn("l_partkey", F.col("k") % 2000).select(*lines.columns)).write.parquet(f"{folder}/lineitem.parquet")
    return str(folder)


@pytest.mark.parametrize("name", ["simulator_interval", "simulator_sizes", "simulator_threshold", "transcript_interval", "transcript_threshold", "simulator_interval_w2", "simulator_threshold_w2", "transcript_interval_w2", "transcript_threshold_w2"])
def test_queries_with_batches_above_the_declared_size(spark, crowded, name):
    q = QUERIES[name]
    assert differences(q.run(spark, crowded), q.sql, duck(crowded)) == ""


def queue_brute(arrivals: dict[int, list], traced) -> dict:
    """First in, first out, with purges: the step at which each row leaves."""
    waiting, out = [], {}
    for r in traced:
        waiting += arrivals.get(r.step, [])
        k = r.real_out + r.purge_real
        for x in waiting[:k]:
            out[x] = r.step
        waiting = [] if r.step % r.purge_every == 0 else waiting[k:]
    return out


def test_two_operators(spark, small):
    """Filter, release, join, release: rows reach the second level when the first has released them."""
    lines = wl.lines_side("l_partkey", None, 5, "l_returnflag")(spark, small).cache()
    right, spec = wl.W2B30.right(spark, small), wl.W2B30
    p = Params(eps=1.0, omega=1, budget=1, interval=2, purge_every=20, purge_size=3)
    traced, sent = multilevel.released_rows(lines, F.col("l_returnflag") == "R", "interval", p)
    flagged = lines.filter("l_returnflag = 'R'").collect()
    arrivals: dict[int, list] = {}
    for r in sorted(flagged, key=lambda r: (r.step, (r.key + r.rid) % 64, r.key, r.rid)):
        arrivals.setdefault(r.step, []).append(r.rid)
    want = queue_brute(arrivals, traced.orderBy("step").collect())
    assert {r.rid: r.step for r in sent.collect()} == want and 0 < len(want) < len(flagged)
    t = multilevel.filter_then_join(spec, lines, right, F.col("l_returnflag") == "R", ("interval", p), ("interval", spec.params)).orderBy("step").collect()
    steps_, days = want, {r.rid: (r.key, r.day) for r in flagged}
    pairs = {}
    for r in right.collect():
        for a, (key, day) in days.items():
            if key == r.key and 0 <= (r.day - day).days <= 10 and a in steps_:
                born = max(steps_[a], r.step)
                if born - steps_[a] < spec.params.horizon:
                    pairs.setdefault((born, a), []).append(r.rid)
    real: dict[int, int] = {}
    for (born, _), rs in pairs.items():
        real[born] = real.get(born, 0) + min(len(rs), spec.params.omega)
    assert {r.step: r.n_real for r in t if r.n_real} == real
    assert t[-1].truth == derive.true_pairs(wl.W2B30, *wl.sides(wl.W2B30, spark, small)).count()


def test_owner_uploads_feed_the_view(spark, small):
    """Errors stay within b times what the owner holds plus the view's own bound, for both owner policies."""
    from pdpview.catalog import QUERIES

    for name in ("owner_view_interval", "owner_view_threshold"):
        rows = QUERIES[name].run(spark, small).collect()
        assert sum(r.l1 > r.bound for r in rows) <= 0.1 * len(rows) and any(r.owner_deferred for r in rows) and any(r.answer for r in rows)


def test_allocation_by_work():
    levels = [(5000, 1), (800, 30)]
    split, work, error = multilevel.allocate(1.5, levels, 100, 4000.0)
    assert abs(sum(split) - 1.5) < 1e-9 and error <= 4000
    best = None
    for k in range(1, 40):
        e = (1.5 * k / 40, 1.5 * (40 - k) / 40)
        bounds = [2 * b / x * math.sqrt(100 * math.log(10)) for x, (_, b) in zip(e, levels, strict=True)]
        cost = sum(100 * metrics.oblivious_cost_value(math.ceil(n / 100 + d)) for d, (n, _) in zip(bounds, levels, strict=True))
        if sum(bounds) <= 4000 and (best is None or cost < best):
            best = cost
    assert work == best
    assert multilevel.allocate(1.5, levels, 100, 10.0) is None
    loose, tight = (multilevel.allocate(1.5, levels, 100, x) for x in (10_000.0, 1300.0))
    assert loose[1] <= tight[1] and tight[2] <= 1300


def test_neighbours_differ_within_bounds(spark, small):
    spec = wl.W2M72
    left, right = wl.sides(spec, spark, small)
    rid = derive.derive(spec, left, right).groupBy("l_rid").count().orderBy(F.desc("count")).first().l_rid
    n = {r.step: r.n_real for r in derive.summaries(spec, left, right).collect()}
    m = {r.step: r.n_real for r in derive.summaries(spec, left.filter(F.col("rid") != rid), right).collect()}
    gaps = [abs(n[t] - m.get(t, 0)) for t in n]
    assert max(gaps) <= spec.params.omega and sum(gaps) <= spec.params.budget and sum(gaps) > 0


def test_buffer_read(spark):
    b = spark.createDataFrame([(True, 1, 1), (True, 1, 2), (True, 2, 1), (False, 1, 3), (False, 2, 2)], "is_view boolean, born_step int, ord int")
    for size, real, dummy in ((2, 2, 0), (4, 3, 1), (7, 3, 4), (-3, 0, 0)):
        got, rest = buffer.read(b, size)
        got = got.collect()
        assert (sum(r.is_view for r in got), sum(not r.is_view for r in got)) == (real, dummy)
        assert rest.count() == 5 - min(max(size, 0), 5)


def test_privacy_numbers(spark):
    assert privacy.deferred_bound_interval(1.5, 10, 200, 0.1) == pytest.approx(286.13, abs=0.01)
    with pytest.raises(ValueError):
        privacy.deferred_bound_interval(1.5, 10, 3, 0.1)
    uses = spark.createDataFrame([(1, 1, 2.0), (1, 3, 1.0), (1, 4, 1.0)], "rid long, invocation int, q double")
    losses = spark.createDataFrame([(t, 0.1) for t in range(1, 5)], "invocation int, eps double")
    assert privacy.composed(uses, losses).first().eps == pytest.approx(0.4)
    assert privacy.user_level(1.0, 4) == 0.25 and privacy.through_stable(3, 0.5) == 1.5
    assert privacy.compose_owner(0.5, 1.0) == 1.5 and privacy.correlated_range(1.0, 3) == (1.0, 3.0)
    assert metrics.oblivious_cost_value(1000) == 1024 * 10 * 11 // 4


def test_deferred_bound_holds():
    rng, over, k, b, eps, beta = random.Random(1), 0, 200, 10, 1.5, 0.1
    alpha = privacy.deferred_bound_interval(eps, b, k, beta)
    for _ in range(300):
        walk_, low = 0.0, 0.0
        for _ in range(k):
            walk_ -= noise.laplace_value(rng.getrandbits(32), b / eps)
            low = min(low, walk_)
        over += walk_ - low >= alpha
    assert over / 300 <= beta


def test_padding(spark):
    side = spark.createDataFrame([(1,), (1,), (2,)], "step int")
    assert sorted(map(tuple, steps.pad_counted(side, 4).collect())) == [(1, 2, 2, 4), (2, 1, 3, 4)]
    p = steps.pad_physical(side)
    assert p.count() == 4 and p.filter("is_real").count() == 3


def test_empty_tables(spark):
    schema = "rid long, key long, day date, step int"
    empty = spark.createDataFrame([], schema)
    some = spark.createDataFrame([(1, 1, None, 1), (2, None, None, 2)], schema)
    spec = ViewSpec("t", None, None, 0, 9, params=Params())
    for left, right in ((empty, empty), (some, empty), (empty, some)):
        sums = derive.summaries(spec, left, right)
        t = release.trace(sums, [("i", "interval", spec.params), ("t", "threshold", spec.params)])
        assert all(r.answer == 0 for r in t.collect())


def test_large_eps_leaves_timing_only(spark, small):
    spec = wl.W1W
    sums = derive.summaries(spec, *wl.sides(spec, spark, small))
    t = release.trace(sums, [("i", "interval", spec.params.but(eps=1e6, interval=1))])
    assert t.agg(F.max("deferred"), F.max("dummy_out")).first()[:] == (0, 0)


def test_answers_ignore_dummies(spark):
    v = spark.createDataFrame([(1, True), (1, False), (2, True)], "release_step int, is_view boolean")
    assert query.answer(v, 1).first().answer == 1 and query.answer(v, 2).first().answer == 2
