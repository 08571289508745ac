"""Selection of documents under a budget, random draws, and comparison of selections."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spanfocus.functions.text import random_order
from spanfocus.operators.ranks import range_sums, running_in_groups
from spanfocus.session import cut
from spanfocus.sources.tables import require

#: Decimal places that scores are rounded to before they are ranked.
PLACES = 6
COLUMNS = ("doc_id", "domain", "score", "domain_rank", "n_tokens", "cum_tokens", "quota_tokens")


def select_top(df: DataFrame, n: int, score: str = "score") -> DataFrame:
    """The ``n`` rows of highest rounded score, ties to the smaller doc_id."""
    return require(df, "doc_id", score).orderBy(F.desc(F.round(score, PLACES)), "doc_id").limit(n)


def domain_shares(df: DataFrame) -> DataFrame:
    """(domain, tokens): token totals by domain, the mix that a selection keeps."""
    return df.groupBy("domain").agg(F.sum("n_tokens").cast("bigint").alias("tokens"))


def quotas(shares: DataFrame, budget: int) -> DataFrame:
    """(domain, quota_tokens): the budget in proportion to tokens, rounded by largest remainder, ties by name."""
    whole = Window.partitionBy(F.lit(0))
    exact = F.coalesce(F.try_divide(F.lit(float(budget)) * F.col("tokens"), F.sum("tokens").over(whole)), F.lit(0.0))
    rows = shares.withColumn("exact", F.round(exact, PLACES)).withColumn("floor", F.floor("exact").cast("bigint"))
    order = Window.partitionBy(F.lit(0)).orderBy(F.desc(F.round(F.col("exact") - F.col("floor"), PLACES)), "domain")
    extra = F.row_number().over(order) <= F.lit(budget) - F.sum("floor").over(whole)
    return rows.select("domain", (F.col("floor") + extra.cast("bigint")).alias("quota_tokens"))


def by_quota(df: DataFrame, budget: int, *order: Column | str) -> DataFrame:
    """Rows of each domain in the given order while their running tokens stay within the domain's quota."""
    placed = running_in_groups(df, "domain", *order, F.col("doc_id")).join(quotas(domain_shares(df), budget), "domain")
    return placed.where(F.col("cum_tokens") <= F.col("quota_tokens"))


def select_by_domain(df: DataFrame, budget: int, score: str = "score") -> DataFrame:
    """Best-scored rows of every domain under a token budget that keeps the domains' token shares.

    ``df`` has doc_id, domain, n_tokens and the score. Scores are rounded before ranking; ties go to the
    smaller doc_id; the budget is never overshot. Running sums are taken over ranges of the order, so no
    domain has to fit a task. :func:`select_by_threshold` gives the same rows and orders fewer.
    """
    rows = require(df, "doc_id", "domain", "n_tokens", score).withColumn("score", F.round(score, PLACES))
    return by_quota(rows, budget, F.desc("score")).select(*COLUMNS)


def select_by_threshold(df: DataFrame, budget: int, score: str = "score") -> DataFrame:
    """The rows of :func:`select_by_domain` without ordering whole domains: (doc_id, domain, score, n_tokens).

    Ranges of (domain, score, doc_id), even in rows whatever the scores, are summed; those above a domain's
    cut are taken and those below left as they are, and only the range of the cut is summed row by row.
    """
    rows = require(df, "doc_id", "domain", "n_tokens", score).select("doc_id", "domain", "n_tokens", F.round(score, PLACES).alias("score"))
    ranged, ranges = range_sums(rows, "domain", F.desc("score"), F.col("doc_id"))
    plan = ranges.join(quotas(domain_shares(ranged), budget), "domain").withColumnRenamed("domain", "_g")
    placed = ranged.join(plan, F.col("domain").eqNullSafe(F.col("_g")) & (F.col("_part") == F.col("_range")))
    keep = ["doc_id", "domain", "score", "n_tokens"]
    sure = placed.where(F.col("_before") + F.col("_size") <= F.col("quota_tokens")).select(*keep)
    edge = placed.where((F.col("_before") <= F.col("quota_tokens")) & (F.col("_before") + F.col("_size") > F.col("quota_tokens")))
    order = Window.partitionBy("domain", "_part").orderBy(F.desc("score"), "doc_id").rowsBetween(Window.unboundedPreceding, 0)
    edge = edge.withColumn("run", F.col("_before") + F.sum("n_tokens").over(order)).where(F.col("run") <= F.col("quota_tokens"))
    return sure.unionByName(edge.select(*keep))


def select_fraction(df: DataFrame, fraction: float, score: str = "score") -> DataFrame:
    """The best ``fraction`` of each domain's rows, rounded down; ties to the smaller doc_id."""
    rows = require(df, "doc_id", "domain", score).withColumn("score", F.round(score, PLACES)).withColumn("_one", F.lit(1))
    sizes = rows.groupBy("domain").agg(F.floor(F.count("*") * F.lit(fraction) + 1e-9).cast("int").alias("k"))
    placed = running_in_groups(rows, "domain", F.desc("score"), F.col("doc_id"), total="_one").join(sizes, "domain")
    return placed.where(F.col("domain_rank") <= F.col("k")).select("doc_id", "domain", "score", "domain_rank")


def select_per_domain(df: DataFrame, k: int, score: str = "score") -> DataFrame:
    """The best ``k`` rows of each domain: the rank limit reaches below the shuffle."""
    window = Window.partitionBy("domain").orderBy(F.desc(F.round(score, PLACES)), "doc_id")
    return df.withColumn("domain_rank", F.row_number().over(window)).where(F.col("domain_rank") <= k)


def select_random(df: DataFrame, budget: int, seed: int) -> DataFrame:
    """The same quotas filled in random order: md5 of seed and doc_id, the same on any engine."""
    rows = require(df, "doc_id", "domain", "n_tokens").withColumn("score", F.lit(0.0)).withColumn("o", random_order("doc_id", seed))
    return by_quota(rows, budget, "o").select(*COLUMNS)


def over_seeds(measure: Callable[[int], DataFrame], seeds: Sequence[int], by: Sequence[str], value: str) -> DataFrame:
    """Mean of a measure over seeds: ``measure(seed)`` gives (by, value)."""
    frames = [measure(s).select(*by, value) for s in seeds]
    rows = frames[0]
    for f in frames[1:]:
        rows = rows.unionByName(f)
    return rows.groupBy(*by).agg(F.avg(value).alias(value), F.count("*").alias("n_seeds"))


def budget_sweep(scored: DataFrame, budgets: dict[str, int], methods: dict[str, Callable[[DataFrame, int], DataFrame]]) -> DataFrame:
    """(method, budget, domain, docs, tokens) of every method at every budget, on one written score table."""
    table, out = cut(scored), None
    for name, fn in methods.items():
        for label, budget in budgets.items():
            made = fn(table, budget).groupBy("domain").agg(F.count("*").alias("docs"), F.sum("n_tokens").cast("bigint").alias("tokens"))
            made = made.select(F.lit(name).alias("method"), F.lit(label).alias("budget"), "domain", "docs", "tokens")
            out = made if out is None else out.unionByName(made)
    return out


def select_labelled(df: DataFrame, labels: DataFrame) -> DataFrame:
    """Rows labelled of quality and not toxic."""
    return df.join(labels.where("quality = 1 AND toxic = 0"), "doc_id", "left_semi")


def overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """(in_a, in_b, in_both, jaccard, overlap_share) of two sets of doc_id."""
    both = a.select("doc_id").distinct().withColumn("a", F.lit(1)).join(b.select("doc_id").distinct().withColumn("b", F.lit(1)), "doc_id", "full")
    n_a, n_b, n_ab = F.count("a"), F.count("b"), F.count_if(F.col("a").isNotNull() & F.col("b").isNotNull())
    return both.agg(n_a.alias("in_a"), n_b.alias("in_b"), n_ab.alias("in_both"), F.count("*").alias("either")).select(
        "in_a", "in_b", "in_both", F.try_divide("in_both", "either").alias("jaccard"),
        F.try_divide(F.col("in_both"), F.least("in_a", "in_b")).alias("overlap_share"),
    )


def mix(selection: DataFrame) -> DataFrame:
    """(domain, docs, tokens, share) of a selection."""
    rows = selection.groupBy("domain").agg(F.count("*").alias("docs"), F.sum("n_tokens").cast("bigint").alias("tokens"))
    return rows.withColumn("share", F.try_divide("tokens", F.sum("tokens").over(Window.partitionBy(F.lit(0)))))
