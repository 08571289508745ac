"""URL filters: longest-match host and path rules, then trust and distrust over the host link graph.

Hosts that the rules allow or block are seeds. Trust is personalised PageRank from the trusted seeds along
links; distrust is the same from the blocked seeds against the links, since a host that points at bad
hosts is suspect. A host whose distrust share exceeds its trust share is blocked. DataFrame operations only.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spanfocus.session import cut

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: (verdict, host, path prefix)
Rule = tuple[str, str, str]


def _after_scheme(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(url.isNull() | (at == 0), F.lit("")).otherwise(F.substring(url, at + 3, F.length(url)))


def host_of(url: Column) -> Column:
    """What follows the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z in lower case; else empty."""
    return F.translate(F.regexp_extract(_after_scheme(url), r"^([^/?#]*)", 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    """What follows the host up to ``?``, ``#`` or the end; empty where there is no host part."""
    return F.regexp_extract(_after_scheme(url), r"^[^/?#]*([^?#]*)", 1)


def rule_name(rule: Rule) -> str:
    return rule[1] + rule[2]


def matched_rule(host: Column, path: Column, rules: Sequence[Rule]) -> Column:
    """Struct (rule, verdict) of the longest rule that fits, null where none does.

    A rule fits its host and all subdomains if the path starts with the rule's path. Rules of equal
    length: the later name in sort order is looked at last and loses.
    """
    out = F.lit(None).cast("struct<rule: string, verdict: string>")
    for rule in sorted(rules, key=lambda r: (len(rule_name(r)), rule_name(r))):
        verdict, name, prefix = rule
        fits = ((host == name) | F.endswith(host, F.lit("." + name))) & F.startswith(path, F.lit(prefix))
        out = F.when(fits, F.struct(F.lit(rule_name(rule)).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def host_links(pages: DataFrame, url: str = "url", html: str = "html") -> DataFrame:
    """(src, dst, links): links between different hosts, counted; links within a host and null pages give none.

    A link without a scheme (``//host/path``) takes that of its page.
    """
    found = F.regexp_extract_all(F.col(html), F.lit(r"""(?i)\bhref\s*=\s*["']?((?:[a-z][a-z0-9+.-]*:)?//[^"'\s>]+)"""), 1)
    scheme = F.substring_index(F.col(url), "://", 1)
    edges = pages.select(host_of(F.col(url)).alias("src"), scheme.alias("scheme"), F.explode(found).alias("to"))
    to = F.when(F.startswith("to", F.lit("//")), F.concat("scheme", F.lit(":"), "to")).otherwise(F.col("to"))
    edges = edges.select("src", host_of(to).alias("dst"))
    return edges.where("src <> dst and src <> '' and dst <> ''").groupBy("src", "dst").agg(F.count("*").alias("links"))


def personalised_rank(edges: DataFrame, seeds: DataFrame, damping: float = 0.85, rounds: int | None = 10, tolerance: float = 1e-6) -> DataFrame:
    """(host, rank): random walk with restarts at ``seeds`` (host, weight) along ``edges`` (src, dst, links).

    Power iteration until the ranks of all hosts together change by less than ``tolerance`` and no further
    host is reached, or for ``rounds`` rounds where given. A walk at a host without links restarts. The
    weights of the seeds are scaled to sum to one. No seeds: an empty result.
    """
    total = seeds.agg(F.sum("weight")).first()[0]
    if not total:
        return seeds.select("host", F.col("weight").cast("double").alias("rank")).where("false")
    start = seeds.select("host", (F.col("weight") / F.lit(float(total))).alias("s"))
    out = edges.groupBy("src").agg(F.sum("links").alias("all"))
    shares = cut(edges.join(out, "src").select("src", "dst", (F.col("links") / F.col("all")).alias("share")))
    start = cut(start)
    rank = start.select("host", F.col("s").alias("rank"))
    if shares.isEmpty():
        return rank
    reached, done = start.count(), 0
    while rounds is None or done < rounds:
        moved = (
            shares.join(rank.withColumnRenamed("host", "src"), "src")
            .groupBy(F.col("dst").alias("host"))
            .agg((F.sum(F.col("share") * F.col("rank")) * damping).alias("rank"))
        )
        moved = cut(moved)
        kept = float(moved.agg(F.sum("rank")).first()[0] or 0.0)
        new = cut(
            moved.unionByName(start.select("host", (F.col("s") * (1 - kept)).alias("rank")))
            .groupBy("host")
            .agg(F.sum("rank").alias("rank"))
        )
        was = rank.withColumnRenamed("rank", "was")
        gap = F.abs(F.coalesce("rank", F.lit(0.0)) - F.coalesce("was", F.lit(0.0)))
        change, hosts = new.join(was, "host", "full").agg(F.sum(gap), F.count("rank")).first()
        rank, done = new, done + 1
        if change < tolerance and hosts == reached:
            break
        reached = hosts
    return rank


def judge_urls(
    pages: DataFrame, rules: Sequence[Rule], key: str = "page_id", url: str = "url", html: str = "html",
    threshold: float = 0.5, damping: float = 0.85, rounds: int | None = None,
) -> DataFrame:
    """(key, host, path, rule, verdict, trust, distrust) of every row.

    A fitting rule decides. Else the host is blocked where distrust exceeds ``threshold`` of its trust and
    distrust together, each a share of its own walk's mass; hosts that no walk reaches, and urls without a
    host, are allowed. Null urls have empty host and path; a null page text has no links; repeated rows stay
    and count as seeds once per row.
    """
    found = pages.select(key, host_of(F.col(url)).alias("host"), path_of(F.col(url)).alias("path"))
    found = found.withColumn("m", matched_rule(F.col("host"), F.col("path"), rules))
    judged = found.select(key, "host", "path", F.col("m.rule").alias("rule"), F.col("m.verdict").alias("by_rule"))
    marks = cut(judged.where("host <> ''").groupBy("host", "by_rule").agg(F.count("*").alias("weight")))
    edges = cut(host_links(pages, url, html))
    trusted = marks.where("by_rule = 'allow'").select("host", "weight")
    blocked = marks.where("by_rule = 'block'").select("host", "weight")
    back = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "links")
    trust = personalised_rank(edges, trusted, damping, rounds).withColumnRenamed("rank", "trust")
    distrust = personalised_rank(back, blocked, damping, rounds).withColumnRenamed("rank", "distrust")
    hosts = trust.join(distrust, "host", "full").select(
        "host", F.coalesce("trust", F.lit(0.0)).alias("trust"), F.coalesce("distrust", F.lit(0.0)).alias("distrust")
    )
    out = judged.join(hosts, "host", "left")
    share = F.col("distrust") / (F.col("trust") + F.col("distrust"))
    by_graph = F.when(F.coalesce(share > threshold, F.lit(False)), "block").otherwise("allow")
    return out.select(
        key, "host", "path", "rule", F.coalesce("by_rule", by_graph).alias("verdict"),
        F.coalesce("trust", F.lit(0.0)).alias("trust"), F.coalesce("distrust", F.lit(0.0)).alias("distrust"),
    )
