"""URL filters: rules on hosts and paths, and link-graph propagation of trust and distrust between hosts.

A rule names a host and the beginning of a path; it fits the host and its subdomains; of the rules that fit, the
longest wins (the longer host on a tie). Pages without a rule get their host's verdict from the link graph: trust
flows along links from hosts with allowed pages (personalised PageRank), distrust flows against links from hosts
with blocked pages. Seeds are shares: a host's seed is the part of its pages that a rule allows or blocks. A host
without links onward keeps its own score, so no mass moves through a global sum.

A flowing score depends on how many links a host has. Verdicts rest on its share of what the host would get if every
host's seed were 1: an average of seeds, within 0..1, that links to the host (for trust: from it) do not change. A
host's own seed is the least it is judged by. A host is blocked where its distrust reaches ``block_from`` and is
above its trust.

Edge cases: null urls and urls without ``://`` have empty host and path and get ``allow``; repeated pages each get
a row and count in the shares; null or link-less html adds no edge; empty tables give no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .texts import Scratch, lookup, stored

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def name(self) -> str:
        return self.host + self.path


@dataclass(frozen=True)
class RankConfig:
    damping: float = 0.85
    #: Scores are iterated until none moves by more; each round shrinks moves by the damping, so the rounds are few.
    tolerance: float = 1e-6
    block_from: float = 0.5


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def rule_of(host: Column, path: Column, rules: list[Rule], what) -> Column:
    """``what(rule)`` of the winning rule, else null: one expression over the user's list of rules."""
    out = None
    for r in sorted(rules, key=lambda r: (-len(r.name), -len(r.host), r.name)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        out = F.when(fits, F.lit(what(r))) if out is None else out.when(fits, F.lit(what(r)))
    return F.lit(None).cast("string") if out is None else out


def host_edges(pages: DataFrame, html: str = "html") -> DataFrame:
    """src, dst, n: links between different hosts, of ``host`` and the page's html."""
    links = pages.select("host", F.explode(F.regexp_extract_all(F.coalesce(F.col(html), F.lit("")), F.lit(r"""(?i)\bhref\s*=\s*["']?\s*((?:[a-z][a-z0-9+.-]*:)?//[^"'\s>]*)"""), 1)).alias("to"))
    to = F.when(F.col("to").startswith("//"), F.concat(F.lit("http:"), F.col("to"))).otherwise(F.col("to"))
    return links.select(F.col("host").alias("src"), host_of(to).alias("dst")).filter((F.col("src") != "") & (F.col("dst") != "") & (F.col("src") != F.col("dst"))).groupBy("src", "dst").agg(F.count("*").alias("n"))


def propagate(seeds: DataFrame, edges: DataFrame, cfg: RankConfig = RankConfig()) -> DataFrame:
    """host, trust, distrust, own_ (the seeds), all_ (the scores if every seed were 1), linked: ``seeds`` has host,
    trust, distrust; hosts that are only linked to are added."""
    with Scratch(seeds.sparkSession) as keep:
        edges = keep(edges, "edges")
        if not edges.isEmpty():
            return stored(flow(seeds, edges, cfg, keep), "ranks")
    return seeds.select("host", "trust", "distrust", F.col("trust").alias("own_trust"), F.col("distrust").alias("own_distrust"), F.lit(1.0).alias("all_trust"), F.lit(1.0).alias("all_distrust"), F.lit(False).alias("linked"))


def flow(seeds: DataFrame, edges: DataFrame, cfg: RankConfig, keep: Scratch) -> DataFrame:
    """``propagate`` over at least one edge."""
    out_sum, in_sum = edges.groupBy("src").agg(F.sum("n").alias("o")), edges.groupBy("dst").agg(F.sum("n").alias("i"))
    flows = keep(edges.join(out_sum, "src").join(in_sum, "dst").select("src", "dst", (F.col("n") / F.col("o")).alias("w_out"), (F.col("n") / F.col("i")).alias("w_in")), "flows")
    ends = flows.select(F.col("src").alias("host")).union(flows.select(F.col("dst").alias("host"))).distinct()
    base = ends.join(seeds, "host", "full").select("host", *(F.coalesce(c, F.lit(0.0)).alias("own_" + c) for c in ("trust", "distrust")))
    base = base.join(out_sum.select(F.col("src").alias("host"), F.lit(True).alias("gives")), "host", "left").join(in_sum.select(F.col("dst").alias("host"), F.lit(True).alias("taken")), "host", "left")
    base = keep(base.fillna(False, ["gives", "taken"]), "hosts")
    ahead_of, back_of = ("trust", "all_trust"), ("distrust", "all_distrust")
    scores = (*ahead_of, *back_of)
    seed = {"trust": F.col("own_trust"), "distrust": F.col("own_distrust"), "all_trust": F.lit(1.0), "all_distrust": F.lit(1.0)}
    now = base.select("host", *(seed[c].alias(c) for c in scores))
    first, a = True, cfg.damping
    while True:
        ahead = flows.join(now.select(F.col("host").alias("src"), *ahead_of), "src").select(F.col("dst").alias("host"), *((F.col(c) * F.col("w_out")).alias("to_" + c) for c in ahead_of), *(F.lit(0.0).alias("to_" + c) for c in back_of))
        back = flows.join(now.select(F.col("host").alias("dst"), *back_of), "dst").select(F.col("src").alias("host"), *(F.lit(0.0).alias("to_" + c) for c in ahead_of), *((F.col(c) * F.col("w_in")).alias("to_" + c) for c in back_of))
        got = ahead.unionByName(back).groupBy("host").agg(*(F.sum("to_" + c).alias("to_" + c) for c in scores))
        score = lambda c: (1 - a) * seed[c] + a * (F.coalesce("to_" + c, F.lit(0.0)) + F.when(F.col("gives" if c in ahead_of else "taken"), 0.0).otherwise(F.col(c)))
        new = base.join(now, "host").join(got, "host", "left").select("host", *(score(c).alias(c) for c in scores), *(F.col(c).alias("old_" + c) for c in scores))
        new = keep(new, "ranks")
        moved = new.agg(F.max(F.greatest(*(F.abs(F.col(c) - F.col("old_" + c)) for c in scores)))).first()[0]
        if not first:
            keep.drop_previous()
        now, first = new.select("host", *scores), False
        if moved is None or moved < cfg.tolerance:
            break
    return now.join(base, "host").select("host", "trust", "distrust", "own_trust", "own_distrust", "all_trust", "all_distrust", (F.col("gives") | F.col("taken")).alias("linked"))


def judge_urls(pages: DataFrame, rules: list[Rule], cfg: RankConfig = RankConfig(), id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """page_id, host, path, rule, verdict, trust, distrust (the host's, as judged) for each row of ``pages``."""
    host, path = host_of(F.col(url_col)), path_of(F.col(url_col))
    p = pages.select(F.col(id_col).alias("page_id"), host.alias("host"), path.alias("path"))
    p = p.select("*", rule_of(F.col("host"), F.col("path"), rules, lambda r: r.name).alias("rule"), rule_of(F.col("host"), F.col("path"), rules, lambda r: r.verdict).alias("said"))
    seeds = p.filter(F.col("host") != "").groupBy("host").agg(F.avg(F.when(F.col("said") == "allow", 1.0).otherwise(0.0)).alias("trust"), F.avg(F.when(F.col("said") == "block", 1.0).otherwise(0.0)).alias("distrust"))
    ranks = propagate(seeds, host_edges(pages.select(host.alias("host"), F.col(html_col).alias("html"))), cfg)
    judged = lambda c: F.when(F.col("linked"), F.greatest(F.col("own_" + c), F.col(c) / F.col("all_" + c))).otherwise(F.col("own_" + c))
    bad = ranks.select("host", *(judged(c).alias(c) for c in ("trust", "distrust")))
    verdict = F.when(F.col("said").isNotNull(), F.col("said")).when((F.col("distrust") >= cfg.block_from) & (F.col("distrust") > F.col("trust")), "block").otherwise("allow")
    # pages of a hot host are dealt out; Spark broadcasts the hosts if they turn out to be few
    return lookup(p, bad, "host", "page_id", "left", hint=None).select("page_id", "host", "path", "rule", verdict.alias("verdict"), "trust", "distrust")
