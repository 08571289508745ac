"""From pairwise attention mass to span focus to a document's dependency score."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spanfocus.geometry import Geometry
from spanfocus.operators.ranks import exact_medians

#: variant: (deviation weight, distance weight of a pair, position weight of a row)
VARIANTS = {
    "full": (True, True, True),
    "flat_sigma": (False, True, True),
    "flat_length": (True, False, False),
    "flat_pair_length": (True, False, True),
    "flat_row_length": (True, True, False),
}


def in_geometry(geometry: Geometry, j: str = "j", i: str = "i") -> Column:
    """Whether (j, i) is one of the geometry's used pairs."""
    first, low = geometry.first_row + geometry.col_phase, geometry.skip_first + geometry.row_phase
    row = (F.col(j) >= first) & (F.col(j) < geometry.n_spans) & ((F.col(j) - first) % geometry.col_stride == 0)
    col = (F.col(i) >= low) & (F.col(i) < F.col(j) - geometry.skip_near) & ((F.col(i) - low) % geometry.row_stride == 0)
    return row & col


def span_focus(pairs: DataFrame, geometry: Geometry, variant: str = "full", ddof: int = 0) -> DataFrame:
    """(doc_id, j, n_terms, sigma, weighted_sum, span_focus) from (doc_id, j, i, pair_focus).

    One aggregate. A row with a single pair has deviation 0; a row without pairs has no output row and
    counts as 0 further on. ``ddof`` 1 takes the sample deviation.
    """
    by_sigma, by_pair, _ = VARIANTS[variant]
    used = pairs.where(in_geometry(geometry))
    distance = (F.col("j") - F.col("i")) / geometry.n_spans if by_pair else F.lit(1.0)
    sigma = F.coalesce(F.stddev_samp("pair_focus") if ddof else F.stddev_pop("pair_focus"), F.lit(0.0))
    rows = used.groupBy("doc_id", "j").agg(
        F.count("*").cast("int").alias("n_terms"), sigma.alias("sigma"), F.sum(distance * F.col("pair_focus")).alias("weighted_sum")
    )
    return rows.withColumn("span_focus", (F.col("sigma") if by_sigma else F.lit(1.0)) * F.col("weighted_sum"))


def dependency(span_rows: DataFrame, geometry: Geometry, variant: str = "full", documents: DataFrame | None = None) -> DataFrame:
    """(doc_id, dependency) from span focus rows; with ``documents`` those without any row get 0."""
    by_row = VARIANTS[variant][2]
    weight = F.col("j") / geometry.n_spans if by_row else F.lit(1.0)
    scored = span_rows.groupBy("doc_id").agg(F.sum(weight * F.col("span_focus")).alias("dependency"))
    if documents is None:
        return scored
    return documents.select("doc_id").join(scored, "doc_id", "left").withColumn("dependency", F.coalesce("dependency", F.lit(0.0)))


def fold_matrix(mass: np.ndarray, rows: Sequence[int], geometry: Geometry, variant: str = "full", ddof: int = 0, sigma_over: str = "used") -> float:
    """Dependency score from a (spans, rows) mass matrix. ``sigma_over='all'`` ignores the row stride for the deviation."""
    by_sigma, by_pair, by_row = VARIANTS[variant]
    wanted, total = set(geometry.rows()), 0.0
    for k, j in enumerate(rows):
        cols = geometry.cols(j)
        if j not in wanted or not cols:
            continue
        values = mass[cols, k]
        spread = mass[geometry.skip_first : j - geometry.skip_near, k] if sigma_over == "all" else values
        sigma = float(np.std(spread, ddof=ddof)) if len(spread) > ddof else 0.0
        weights = (j - np.asarray(cols)) / geometry.n_spans if by_pair else 1.0
        total += (sigma if by_sigma else 1.0) * float((weights * values).sum()) * (j / geometry.n_spans if by_row else 1.0)
    return total


def _stats(pairs: DataFrame, by: Sequence[str]) -> DataFrame:
    means = pairs.groupBy(*by).agg(F.avg("pair_focus").alias("mean_focus"))
    middle = exact_medians(pairs.withColumn("median_focus", F.col("pair_focus")), by, ["median_focus"])
    return middle.join(means, list(by)).select(*by, F.col("n").alias("n_pairs"), "median_focus", "mean_focus")


def long_range_stats(pairs: DataFrame, min_gap: int, by: Sequence[str]) -> DataFrame:
    """Median and mean pair focus of pairs at least ``min_gap`` spans apart, by the columns ``by``; ``pairs`` is read several times."""
    return _stats(pairs.where(F.col("j") - F.col("i") >= min_gap), by)


def by_distance(pairs: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """Median and mean pair focus by distance in spans."""
    return _stats(pairs.withColumn("gap", F.col("j") - F.col("i")), [*by, "gap"])


def top_pairs(pairs: DataFrame, k: int) -> DataFrame:
    """The ``k`` strongest pairs of each document: (doc_id, rank, j, i, pair_focus)."""
    strength = F.round("pair_focus", 6)
    order = Window.partitionBy("doc_id").orderBy(F.desc(strength), "j", "i")
    return (
        pairs.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("doc_id", "rank", "j", "i", "pair_focus")
    )
