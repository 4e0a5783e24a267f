"""URL filters: path rules first, then trust and distrust that flow over the links between hosts.

Trust starts at every host with pages that the rules allow and follows links; distrust starts at every host with pages that they block
and flows against the links, to those who link there.  A seed weighs as much as the share of its host's pages.  Both are personalised
PageRanks over the host graph, iterated together until they stand still.  A host
is blocked if distrust makes up most of what has reached it; a host that neither reaches is allowed.

Defined results: a null url, or one without "://", has empty host and path, fits no rule and is judged as the empty host; null html
has no links; links that begin with "//" lead to the host that they name; others without "://" lead to the page's own host and aren't edges; repeated pages and links count each; rules of
equal length are tried in text order; an empty table gives an empty result; further columns pass through unless an output column
has their name.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut_lineage, table

#: Fixed values: (verdict, host and path).
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
DAMPING = 0.85
TOLERANCE = 1e-9
#: A host is blocked beyond this share of distrust.
BLOCK_SHARE = 0.5
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_URL = "(?s)^.*?://([^/?#]*)([^?#]*)"


def host_of(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, _URL, 1), F.lit("")), _UPPER, _LOWER)


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, _URL, 2), F.lit(""))


def rule_for(host: Column, path: Column, rules: tuple[tuple[str, str], ...] = RULES) -> Column:
    """The longest rule that fits, as struct(rule, verdict), or null."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, rule in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        name, slash, start = rule.partition("/")
        fits = ((host == name) | F.endswith(host, F.lit("." + name))) & F.startswith(path, F.lit(slash + start))
        out = F.when(fits, F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def host_edges(pages: DataFrame) -> DataFrame:
    """(src, dst, n): links between different hosts, counted before they travel."""
    links = F.regexp_extract_all("html", F.lit("(?i)<a\\s[^>]*?href\\s*=\\s*[\"']?([^\"'\\s>]+)"), F.lit(1))
    whole = F.transform(links, lambda u: F.when(F.startswith(u, F.lit("//")), F.concat(F.lit("http:"), u)).otherwise(u))
    far = pages.select(host_of(F.col("url")).alias("src"), F.explode(F.filter(whole, lambda u: F.contains(u, F.lit("://")))).alias("u"))
    return far.select("src", host_of(F.col("u")).alias("dst")).where("src <> dst").groupBy("src", "dst").agg(F.count("*").alias("n"))


def rounds_to(tolerance: float, damping: float = DAMPING) -> int:
    """Rounds after which ranks that sum to 1 change by no more than the tolerance."""
    return math.ceil(math.log(tolerance / 2) / math.log(damping)) + 2


def propagate(edges: DataFrame, seeds: DataFrame, damping: float = DAMPING, rounds: int | None = None, tolerance: float = TOLERANCE) -> DataFrame:
    """(kind, host, rank) of personalised PageRank along edges (kind, src, dst, n) from seeds (kind, host, seed that sums to 1).

    What hosts without a way out hold goes back to the seeds.  Without a number of rounds it goes on until the ranks change by less than
    the tolerance: a round shrinks the change by the damping, so the number of rounds is known, and missing it is an error.
    """
    out_of = edges.groupBy("kind", "src").agg(F.sum("n").alias("_all"))
    weighted = cut_lineage(edges.join(out_of, ["kind", "src"]).select("kind", "src", "dst", (F.col("n") / F.col("_all")).alias("w")))
    if weighted.isEmpty():
        return seeds.select("kind", "host", F.col("seed").alias("rank"))
    hosts = weighted.select("kind", F.col("src").alias("host")).union(weighted.select("kind", F.col("dst").alias("host"))).union(seeds.select("kind", "host")).distinct()
    nodes = cut_lineage(hosts.join(seeds, ["kind", "host"], "left").select("kind", "host", F.coalesce("seed", F.lit(0.0)).alias("seed")))
    ranks = nodes.select("kind", "host", F.col("seed").alias("rank"))
    enough = rounds_to(tolerance, damping) if rounds is None else rounds
    for _ in range(enough):
        moved = weighted.join(ranks.withColumnRenamed("host", "src"), ["kind", "src"]).groupBy("kind", F.col("dst").alias("host")).agg(F.sum(F.col("w") * F.col("rank")).alias("inflow"))
        kept = moved.groupBy("kind").agg(F.sum("inflow").alias("moved"))
        # `kept` has one row for each kind, two at most
        nxt = nodes.join(moved, ["kind", "host"], "left").join(F.broadcast(kept), "kind", "left").join(ranks.withColumnRenamed("rank", "old"), ["kind", "host"])
        inflow, through = F.coalesce("inflow", F.lit(0.0)), F.coalesce("moved", F.lit(0.0))
        nxt = cut_lineage(nxt.select("kind", "host", "old", (F.col("seed") * (1 - damping * through) + damping * inflow).alias("rank")))
        change = nxt.agg(F.coalesce(F.sum(F.abs(F.col("rank") - F.col("old"))), F.lit(0.0))).first()[0]
        ranks = nxt.select("kind", "host", "rank")
        if change < tolerance:
            break
    else:
        if rounds is None:
            raise RuntimeError(f"ranks still change by {change} after {enough} rounds")
    return ranks


def host_verdicts(pages: DataFrame, rules: tuple[tuple[str, str], ...] = RULES) -> DataFrame:
    """(host, trust, distrust, verdict) of every host of a page or link."""
    judged = pages.select(host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path")).select("host", rule_for(F.col("host"), F.col("path"), rules)["verdict"].alias("v"))
    share = lambda v: F.avg(F.coalesce((F.col("v") == v).cast("double"), F.lit(0.0))).alias(v)
    shares = cut_lineage(judged.groupBy("host").agg(share("allow"), share("block")))
    chosen = shares.where(F.col("allow") > 0).select(F.lit("trust").alias("kind"), "host", F.col("allow").alias("s")).union(shares.where(F.col("block") > 0).select(F.lit("distrust"), "host", F.col("block")))
    totals = chosen.groupBy("kind").agg(F.sum("s").alias("_t"))
    seeds = cut_lineage(chosen.join(F.broadcast(totals), "kind").select("kind", "host", (F.col("s") / F.col("_t")).alias("seed")))
    links = cut_lineage(host_edges(pages))
    edges = links.select(F.lit("trust").alias("kind"), "src", "dst", "n").union(links.select(F.lit("distrust"), "dst", "src", "n"))
    ranks = propagate(edges, seeds)
    flows = ranks.groupBy("host").agg(F.sum(F.when(F.col("kind") == "trust", F.col("rank"))).alias("trust"), F.sum(F.when(F.col("kind") == "distrust", F.col("rank"))).alias("distrust"))
    every = shares.select("host").union(flows.select("host")).distinct().join(flows, "host", "left")
    trust, distrust = F.coalesce("trust", F.lit(0.0)), F.coalesce("distrust", F.lit(0.0))
    blocked = (distrust > 0) & (distrust > BLOCK_SHARE * (trust + distrust))
    return every.select("host", trust.alias("trust"), distrust.alias("distrust"), F.when(blocked, "block").otherwise("allow").alias("verdict"))


def filter_urls(pages: DataFrame, rules: tuple[tuple[str, str], ...] = RULES) -> DataFrame:
    """pages with host, path, rule and verdict."""
    hosts = host_verdicts(pages, rules).select(F.col("host").alias("_h"), F.col("verdict").alias("_v"))
    keep = [c for c in pages.columns if c not in ("host", "path", "rule", "verdict")]
    split = pages.select(*(F.col(f"`{c}`") for c in keep), host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    ruled = split.withColumn("_r", rule_for(F.col("host"), F.col("path"), rules))
    joined = ruled.join(hosts, F.col("host") == F.col("_h"), "left")
    return joined.select(*(F.col(f"`{c}`") for c in keep), "host", "path", F.col("_r.rule").alias("rule"), F.coalesce("_r.verdict", "_v").alias("verdict"))


def op4_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")
