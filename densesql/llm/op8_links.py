"""URL filters: list rules, then link-graph propagation for what no rule decides.

Hosts are nodes; a page's absolute links give edges from its host, and hosts that
share their registered domain (their last two labels) are tied to that domain's node,
so that standing reaches subdomains.  Personalised PageRank spreads trust along links
from hosts that a rule allows; distrust spreads against the links from hosts that a
rule blocks, because linking to bad hosts is bad company.  A host without a rule is
blocked where its distrust exceeds its trust by a margin, as a share of their sum, so
that the verdict does not depend on how many hosts share the walks' mass.

Scores are sums of what has arrived so far, so after k steps damping^(k+1) of each walk
is still under way and no score can grow by more.  Steps go on until no new host is
reached and no verdict can be changed by that rest, or until the rest is below
``tolerance``; differences within rounding of a tie are ties, and ties are allowed.

All of it is DataFrame functions.  Edges are summed before they are joined, both
walks move in the same join each step, and every few steps are staged.

Defined results: a null url, or one without ``://``, has empty host and path, no rule
and verdict allow; null html has no links; repeated rows give one result row each; with
no seed of a kind that kind's score is zero; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from densesql.llm.common import documents
from densesql.plans.staging import Staging

# The rules as (host, path, verdict).
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))

#: Share that follows a link, the margin by which distrust must exceed trust (share of their sum), and the rest of a walk that ends it.
DAMPING, MARGIN, TOLERANCE = 0.85, 0.0, 1e-12
#: Steps between two looks at the verdicts, and the share of a sum within which two scores tie.
BLOCK, ROUNDING = 8, 1e-9
#: Links in a page that name a host.
LINK = r"""(?i)(?:href|src)\s*=\s*["']?(?:[a-z][a-z0-9+.-]*:)?//([^/?#"'\s>]+)"""

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def split_url(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a url; both empty without ``://``."""
    rest = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://(.*)$", 1)
    host = F.translate(F.regexp_extract(rest, r"^[^/?#]*", 0), UPPER, LOWER)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return host, path


def rule_of(host: Column, path: Column, rules: tuple = RULES) -> Column:
    """Struct (rule, verdict) of the longest rule that fits, else null."""
    by_length = sorted(rules, key=lambda r: -len(r[0] + r[1]))
    arms = [
        F.when(
            ((host == h) | host.endswith("." + h)) & path.startswith(p), F.struct(F.lit(h + p).alias("rule"), F.lit(v).alias("verdict"))
        )
        for h, p, v in by_length
    ]
    return F.coalesce(*arms)


def domain_of(host: Column) -> Column:
    return F.substring_index(host, ".", -2)


def host_edges(pages: DataFrame) -> DataFrame:
    """(src, dst, weight): links between hosts, and ties between a host and its domain's node."""
    linked = pages.select("host", F.explode(F.regexp_extract_all("html", F.lit(LINK), 1)).alias("raw"))
    links = linked.select(F.col("host").alias("src"), F.translate("raw", UPPER, LOWER).alias("dst"))
    links = links.where("src != '' and dst != '' and src != dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("weight"))
    hosts = links.select(F.explode(F.array("src", "dst")).alias("host")).union(pages.select("host").where("host != ''")).distinct()
    ties = hosts.select("host", F.concat(F.lit("*."), domain_of(F.col("host"))).alias("node"))
    one = F.lit(1).cast("long")
    return links.union(ties.select("host", "node", one)).union(ties.select("node", "host", one))


def standing(scores: DataFrame) -> DataFrame:
    """(host, trust, distrust) from (walk, host, score)."""
    return scores.groupBy("host").agg(*[F.coalesce(F.sum(F.when(F.col("walk") == w, F.col("score"))), F.lit(0.0)).alias(w) for w in ("trust", "distrust")])


def lead_of(margin: float = MARGIN) -> Column:
    """By how much distrust is above what it takes to block, zero at a tie."""
    both = F.col("distrust") + F.col("trust")
    lead = F.col("distrust") - F.col("trust") - margin * both
    return F.when(F.abs(lead) > ROUNDING * both, lead).otherwise(0.0)


def propagate(
    edges: DataFrame, seeds: DataFrame, staging: Staging, damping: float = DAMPING, margin: float = MARGIN, tolerance: float = TOLERANCE
) -> DataFrame:
    """(walk, host, score) of personalised walks; ``edges`` (walk, src, dst, weight), ``seeds`` (walk, host, weight)."""
    out = edges.groupBy("walk", "src").agg(F.sum("weight").alias("out"))
    moves = staging.table(edges.join(out, ["walk", "src"]).select("walk", "src", "dst", (F.col("weight") / F.col("out")).alias("p")), "moves")
    sums = seeds.groupBy("walk").agg(F.sum("weight").alias("all"))
    start = seeds.join(F.broadcast(sums), "walk").select("walk", "host", ((1 - damping) * F.col("weight") / F.col("all")).alias("score"))
    rank = start = staging.table(start, "start")
    reached, steps = start.count(), 0
    while True:
        for _ in range(BLOCK):
            moved = rank.withColumnRenamed("host", "src").join(moves, ["walk", "src"])
            moved = moved.select("walk", F.col("dst").alias("host"), (F.col("score") * F.col("p") * damping).alias("score"))
            rank = moved.union(start).groupBy("walk", "host").agg(F.sum("score").alias("score"))
        steps += BLOCK
        rank = staging.table(rank, f"rank-{steps}")
        if steps > BLOCK:
            staging.drop(f"rank-{steps - BLOCK}")
        before, reached, rest = reached, rank.count(), damping ** (steps + 1)
        if reached > before:
            continue
        lead = F.abs(lead_of(margin))
        if rest <= tolerance or standing(rank).where((lead > 0) & (lead <= (1 + abs(margin)) * rest)).isEmpty():
            return rank


def judge_pages(pages: DataFrame, rules: tuple = RULES, damping: float = DAMPING, margin: float = MARGIN, tolerance: float = TOLERANCE) -> DataFrame:
    """(page_id, host, path, rule, verdict, trust, distrust) for every page."""
    staging = Staging(pages.sparkSession, "links")
    host, path = split_url(F.col("url"))
    parted = pages.select("page_id", host.alias("host"), path.alias("path"), "html")
    ruled = parted.withColumn("fit", rule_of(F.col("host"), F.col("path"), rules))
    edges = staging.table(host_edges(parted), "edges")
    walks = edges.select(F.lit("trust").alias("walk"), "src", "dst", "weight").union(
        edges.select(F.lit("distrust").alias("walk"), F.col("dst"), F.col("src"), "weight")
    )
    walk = F.when(F.col("fit.verdict") == "allow", "trust").otherwise("distrust")
    seeds = ruled.where("fit is not null").groupBy(walk.alias("walk"), "host").agg(F.count(F.lit(1)).alias("weight"))
    by_host = standing(propagate(walks, seeds, staging, damping, margin, tolerance))
    named = ruled.select("page_id", "host", "path", "fit").join(by_host, "host", "left").fillna(0.0, ["trust", "distrust"])
    bad = (F.col("host") != "") & (lead_of(margin) > 0)
    verdict = F.coalesce(F.col("fit.verdict"), F.when(bad, "block").otherwise("allow"))
    return named.select("page_id", "host", "path", F.col("fit.rule").alias("rule"), verdict.alias("verdict"), "trust", "distrust")


def op8_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_pages(documents(spark, sf_dir, "pages"))
