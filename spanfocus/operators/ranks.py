"""Global ranks without gathering all rows in one task."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spanfocus.session import cut


def global_row_number(df: DataFrame, *order: Column | str, name: str = "place") -> DataFrame:
    """Adds the row's 1-based place in a total order.

    Rows are range-partitioned and numbered inside their partition; the sizes of the partitions before it
    (as many numbers as there are partitions) are then added. The partitioned rows are written once, so a
    lost task cannot deal them differently. Rows that tie in ``order`` must be told apart by it.
    """
    ranged = cut(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()))
    inside = ranged.withColumn("_n", F.row_number().over(Window.partitionBy("_part").orderBy(*order)))
    sizes = ranged.groupBy("_part").agg(F.count("*").alias("_size"))
    before = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("_part", F.coalesce(F.sum("_size").over(before), F.lit(0)).alias("_before"))
    made = inside.join(offsets, "_part").withColumn(name, (F.col("_before") + F.col("_n")).cast("bigint"))
    return made.drop("_part", "_n", "_before")


def average_rank(df: DataFrame, value: str, key: str, name: str = "rank") -> DataFrame:
    """Adds the 1-based rank of ``value``, ties sharing the mean of their places."""
    placed = global_row_number(df, F.col(value), F.col(key), name="_at")
    ties = placed.groupBy(F.col(value).alias("_v")).agg(F.avg("_at").alias(name))
    return placed.drop("_at").join(ties, F.col(value).eqNullSafe(F.col("_v"))).drop("_v")


def running_in_groups(df: DataFrame, group: str, *order: Column | str, total: str = "n_tokens") -> DataFrame:
    """Adds ``domain_rank``, ``cum_tokens`` (of ``total``) and ``_part`` to rows in the given order within their group.

    As :func:`global_row_number`: ranges of (group, order) are summed apart, and what lies before a range in
    its group is added. A large group, many equal values or a few far ones are spread over many ranges.
    """
    inside, ranges = range_sums(df, group, *order, total=total)
    window = Window.partitionBy("_part", group).orderBy(*order)
    upto = F.sum(total).over(window.rowsBetween(Window.unboundedPreceding, 0))
    placed = inside.withColumn("_n", F.row_number().over(window)).withColumn("_t", upto)
    made = placed.join(ranges.withColumnRenamed(group, "_g"), (F.col(group).eqNullSafe(F.col("_g"))) & (F.col("_part") == F.col("_range")))
    rank, tokens = (F.col("_rows_before") + F.col("_n")).cast("int"), (F.col("_before") + F.col("_t")).cast("bigint")
    return made.withColumn("domain_rank", rank).withColumn("cum_tokens", tokens).drop("_n", "_t", "_g", "_range", "_rows_before", "_before", "_size")


def range_sums(df: DataFrame, group: str, *order: Column | str, total: str = "n_tokens") -> tuple[DataFrame, DataFrame]:
    """Rows with ``_part``, their range of (group, order); and (group, _range, _rows_before, _before, _size) of the ranges.

    The rows are written once, so a lost task cannot deal them differently. There are as many ranges as
    shuffle partitions, and one more for each group that ends inside one.
    """
    ranged = cut(df.repartitionByRange(F.col(group), *order).withColumn("_part", F.spark_partition_id()))
    sizes = ranged.groupBy(group, F.col("_part").alias("_range")).agg(F.count("*").alias("_rows"), F.sum(total).alias("_size"))
    before = Window.partitionBy(group).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    ranges = sizes.select(
        group, "_range", F.coalesce(F.sum("_rows").over(before), F.lit(0)).alias("_rows_before"),
        F.coalesce(F.sum("_size").over(before), F.lit(0)).alias("_before"), "_size",
    )
    return ranged, ranges


def exact_medians(df: DataFrame, by: Sequence[str], values: Sequence[str], most: int = 200_000) -> DataFrame:
    """(by, n, a median for each of ``values``): the mean of the two middle values, nulls left out.

    Up to ``most`` rows a group are taken in one aggregate. In larger groups a sketch brackets the middle, the
    bracket is counted exactly and narrowed until it holds ``most`` rows or one value; only those are ordered.
    """
    sizes = df.groupBy(*by).agg(F.count("*").alias("n"))
    if (sizes.agg(F.max("n")).first()[0] or 0) <= most:
        return df.groupBy(*by).agg(F.count("*").alias("n"), *(F.median(v).alias(v) for v in values))
    rows, out = cut(df.select(*by, *values)), sizes
    for v in values:
        out = out.join(_median_of(rows.where(F.col(v).isNotNull()), list(by), v, most), list(by), "left")
    return out.select(*by, "n", *values)


def _median_of(rows: DataFrame, by: list[str], value: str, most: int) -> DataFrame:
    held = rows.select(*by, F.col(value).alias("v"))
    totals = cut(held.groupBy(*by).agg(F.count("*").alias("of"), F.min("v").alias("low"), F.max("v").alias("high")))
    for _ in range(40):
        place = F.lit(0.5) if "below" not in totals.columns else (F.col("of") / 2 - F.col("below")) / F.col("inside")
        inside = held.join(totals, by).where(F.col("v").between(F.col("low"), F.col("high")))
        edges = inside.groupBy(*by).agg(F.percentile_approx("v", F.array(*(F.lit(k / 100) for k in range(101))), 10_000).alias("q"))
        at = F.greatest(F.lit(0.0), F.least(F.lit(1.0), place)) * 100
        low = F.when(at >= 2, F.element_at("q", F.floor(at - 1).cast("int") + 1)).otherwise(F.col("low"))
        high = F.when(at <= 98, F.element_at("q", F.ceil(at + 1).cast("int") + 1)).otherwise(F.col("high"))
        tried = totals.join(edges, by).select(*by, "of", F.least(low, "high").alias("low"), F.greatest(high, "low").alias("high"))
        counted = held.join(tried, by).groupBy(*by, "of", "low", "high").agg(
            F.count_if(F.col("v") < F.col("low")).alias("below"), F.count_if(F.col("v").between(F.col("low"), F.col("high"))).alias("inside")
        )
        one, two = F.floor((F.col("of") - 1) / 2), F.floor(F.col("of") / 2)
        counted = cut(counted.withColumn("holds", (F.col("below") <= one) & (two < F.col("below") + F.col("inside"))))
        if not counted.where(~F.col("holds")).isEmpty():
            raise RuntimeError("a sketch missed the median's bracket")
        totals = counted.drop("holds")
        if totals.where((F.col("inside") > most) & (F.col("low") < F.col("high"))).isEmpty():
            break
    middle = held.join(totals.where("low < high"), by).where(F.col("v").between(F.col("low"), F.col("high")))
    window = Window.partitionBy(*by).orderBy("v")
    placed = middle.withColumn("at", F.col("below") + F.row_number().over(window) - 1)
    wanted = placed.where((F.col("at") == F.floor((F.col("of") - 1) / 2)) | (F.col("at") == F.floor(F.col("of") / 2)))
    found = wanted.groupBy(*by).agg(F.avg("v").alias(value))
    return found.unionByName(totals.where("low = high").select(*by, F.col("low").alias(value)))
