"""Bounded, deterministic samples of labelled rows, drawn by a hash of the row's id."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_BUCKETS = 1 << 30


def fold(key: str, parts: int) -> Column:
    """crc32 of the id as text, modulo ``parts``."""
    return F.crc32(F.col(key).cast("string").cast("binary")) % parts


def bounded_sample(df: DataFrame, key: str, by: str, per_class: int, classes: int = 256) -> DataFrame:
    """About ``per_class`` rows of each value of ``by``, chosen by the hash of ``key``.

    One count over two columns, then a filter: no window, no shuffle of the rows themselves. A class with
    fewer rows is taken whole. Every value of ``by`` is used; beyond ``classes`` of them the filter is a join
    with the counts. Null ids or null classes take no part.
    """
    counts = df.where(F.col(by).isNotNull()).groupBy(by).count()
    found = counts.limit(classes + 1).collect()
    draw = F.pmod(F.xxhash64(F.col(key), F.lit("sample")), F.lit(_BUCKETS))
    if len(found) > classes:
        share = F.least(F.lit(1.0), F.lit(float(per_class)) / F.col("_n"))
        sized = df.join(counts.select(F.col(by).alias("_by"), F.col("count").alias("_n")), F.col(by) == F.col("_by"))
        return sized.where(F.col(key).isNotNull() & (draw < F.floor(F.lit(_BUCKETS) * share))).select(*df.columns)
    keep = F.lit(False)
    for value, n in found:
        keep = keep | ((F.col(by) == F.lit(value)) & (draw < int(_BUCKETS * min(1.0, per_class / n))))
    return df.where(keep & F.col(key).isNotNull())
