"""Evaluation measures: needle retrieval, task roll-ups, correlations, medians, agreement, answer scores."""

from __future__ import annotations

from collections.abc import Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from spanfocus.functions.text import token_hashes, tokens_of
from spanfocus.geometry import Geometry, cost_of
from spanfocus.operators.ranks import average_rank, exact_medians, global_row_number

DEPTHS = (0.0, 0.25, 0.5, 0.75, 1.0)


def context_lengths(geometry: Geometry, steps: int = 8) -> list[int]:
    return [geometry.length * k // steps for k in range(1, steps + 1)]


def needle_cases(
    hay: DataFrame, needles: DataFrame, geometry: Geometry, lengths: Sequence[int] | None = None, depths: Sequence[float] = DEPTHS, hashed: bool = False
) -> DataFrame:
    """(hay_doc, needle_id, context_len, depth, needle_span, needle_spans, n_spans, tokens).

    Haystacks (doc_id, tokens) and needles (item_id, text) pair up by rank: each haystack gets one needle.
    The needle's whole spans go to span m + floor(depth * room), outside the first m and nearest n spans; the
    last span of the context repeats the needle's first span and asks for it. Cells without room are left out.
    ``hashed`` gives token hashes instead of tokens: they are made once per text, not once per cell.
    """
    g = geometry
    pins = needles.select("item_id", tokens_of("text").alias("pin")).where(F.size("pin") >= g.span)
    if hashed:
        hay, pins = hay.withColumn("tokens", token_hashes("tokens")), pins.withColumn("pin", token_hashes("pin"))
    pins = global_row_number(pins, F.col("item_id"))
    usable = pins.count()
    if not usable:
        raise ValueError("no needle of at least one span")
    ids = global_row_number(hay.select("doc_id"), F.col("doc_id")).withColumn("place", (F.col("place") - 1) % usable + 1)
    # Each haystack becomes dozens of cases: adaptive coalescing would judge the rows by their size before that.
    parts = max(hay.sparkSession.sparkContext.defaultParallelism, hay.rdd.getNumPartitions())
    placed = hay.join(ids, "doc_id").join(pins, "place").repartition(parts, "doc_id")
    cells = F.array(*(F.struct(F.lit(c).alias("context_len"), F.lit(float(d)).alias("depth")) for c in lengths or context_lengths(g) for d in depths))
    rows = placed.select("doc_id", "item_id", "tokens", "pin", F.explode(cells).alias("cell")).select("*", "cell.*")
    n, k = (F.col("context_len") / g.span).cast("int"), F.floor(F.size("pin") / g.span).cast("int")
    room = n - 1 - g.skip_near - k - g.skip_first
    rows = rows.withColumn("n_spans", n).withColumn("needle_spans", k).withColumn("room", room).where("room >= 0")
    rows = rows.withColumn("needle_span", (g.skip_first + F.floor(F.col("depth") * F.col("room"))).cast("int"))
    start, size = F.col("needle_span") * g.span, F.col("needle_spans") * g.span
    tokens = F.concat(
        F.slice("tokens", F.lit(1), start),
        F.slice("pin", F.lit(1), size),
        F.slice("tokens", start + 1, F.col("context_len") - g.span - size - start),
        F.slice("pin", 1, g.span),
    )
    return rows.select(
        F.col("doc_id").alias("hay_doc"), F.col("item_id").alias("needle_id"), "context_len", "depth", "needle_span", "needle_spans", "n_spans",
        tokens.alias("tokens"),
    )


def needle_accuracy(cases: DataFrame) -> DataFrame:
    """(context_len, depth, n_cases, accuracy) from cases with ``hit``."""
    return cases.groupBy("context_len", "depth").agg(F.count("*").alias("n_cases"), F.avg(F.col("hit").cast("double")).alias("accuracy"))


def needle_by_length(grid: DataFrame) -> DataFrame:
    """(context_len, accuracy): mean over depths, and a row with null length for the mean over lengths."""
    rows = grid.groupBy("context_len").agg(F.avg("accuracy").alias("accuracy"))
    return rows.unionByName(rows.agg(F.avg("accuracy").alias("accuracy")).select(F.lit(None).cast("int").alias("context_len"), "accuracy"))


def needle_heatmap(grid: DataFrame, lengths: Sequence[int]) -> DataFrame:
    """Depths as rows, context lengths as columns ``len_<n>``."""
    named = grid.withColumn("c", F.concat(F.lit("len_"), F.col("context_len").cast("string")))
    return named.groupBy("depth").pivot("c", [f"len_{n}" for n in lengths]).agg(F.first("accuracy"))


def task_rollup(scores: DataFrame) -> DataFrame:
    """(model, method, budget, level, category, score): category means of tasks, overall = mean of category means."""
    by = ["model", "method", "budget"]
    category = scores.groupBy(*by, "category").agg(F.avg("score").alias("score"))
    overall = category.groupBy(*by).agg(F.avg("score").alias("score"))
    return category.select(*by, F.lit("category").alias("level"), "category", "score").unionByName(
        overall.select(*by, F.lit("overall").alias("level"), F.lit("overall").alias("category"), "score")
    )


def improvement(rollup: DataFrame, method: str, base: str) -> DataFrame:
    """(model, category, score, base_score, gain) of one method over another; a last row averages overall gains."""
    keys = ["model", "category"]
    a = rollup.where(F.col("method") == method).select(*keys, "score")
    b = rollup.where(F.col("method") == base).select(*keys, F.col("score").alias("base_score"))
    rows = a.join(b, keys).withColumn("gain", F.col("score") - F.col("base_score"))
    mean = rows.where("category = 'overall'").agg(*(F.avg(c).alias(c) for c in ("score", "base_score", "gain")))
    return rows.unionByName(mean.select(F.lit("mean").alias("model"), F.lit("overall").alias("category"), "score", "base_score", "gain"))


def safe_corr(a: Column, b: Column) -> Column:
    """Pearson's r, null where one side does not vary (plain ``corr`` raises there under ANSI rules)."""
    return F.try_divide(F.covar_pop(a, b), F.stddev_pop(a) * F.stddev_pop(b))


def score_correlation(scores: DataFrame, reference: str, columns: Sequence[str], top_n: int) -> DataFrame:
    """(setting, n_docs, pearson, spearman, overlap_at_n): each score column against the reference column."""
    rows = scores
    for c in dict.fromkeys([reference, *columns]):
        rows = average_rank(rows.withColumn("_r", F.round(c, 6)), "_r", "doc_id", f"rank:{c}")
        top = scores.orderBy(F.desc(F.round(c, 6)), "doc_id").limit(top_n).select("doc_id", F.lit(True).alias(f"top:{c}"))
        rows = rows.drop("_r").join(top, "doc_id", "left").withColumn(f"top:{c}", F.coalesce(f"`top:{c}`", F.lit(False)))
    made = [
        F.struct(
            F.lit(c).alias("setting"),
            F.count("*").alias("n_docs"),
            safe_corr(F.round(c, 6), F.round(reference, 6)).alias("pearson"),
            safe_corr(F.col(f"`rank:{c}`"), F.col(f"`rank:{reference}`")).alias("spearman"),
            (F.count_if(F.col(f"`top:{c}`") & F.col(f"`top:{reference}`")) / F.lit(top_n)).alias("overlap_at_n"),
        )
        for c in columns
    ]
    return rows.agg(F.array(*made).alias("a")).select(F.inline("a"))


def cost_rows(spark, profiles: Sequence[tuple[str, int, int]]) -> DataFrame:
    """(profile, row_stride, col_stride, rows, pairs, logits) of some geometries."""
    rows = [(p, a, b, *cost_of(Geometry.named(p).with_strides(a, b)).values()) for p, a, b in profiles]
    return spark.createDataFrame(rows, "profile string, row_stride int, col_stride int, rows bigint, pairs bigint, logits bigint")


def category_medians(scores: DataFrame, category: str, one: str = "dependency", two: str = "delta") -> DataFrame:
    """(category, n_docs, two medians, their ranks): medians resist outliers; rank 1 is the highest."""
    named = scores.select(F.col(category).alias("category"), F.col(one).alias("m1"), F.col(two).alias("m2"))
    middle = exact_medians(named, ["category"], ["m1", "m2"])
    rows = middle.select("category", F.col("n").alias("n_docs"), F.round("m1", 6).alias("median_dependency"), F.round("m2", 6).alias("median_delta"))
    rank = lambda c: F.row_number().over(Window.orderBy(F.desc(c), "category"))
    return rows.select("*", rank("median_dependency").alias("rank_dependency"), rank("median_delta").alias("rank_delta"))


def category_disagreement(medians: DataFrame) -> DataFrame:
    """(category, rank_dependency, rank_delta, shift): how far the two scorers rank a category apart."""
    return medians.select("category", "rank_dependency", "rank_delta", (F.col("rank_delta") - F.col("rank_dependency")).alias("shift"))


def extremes(scores: DataFrame, docs: DataFrame, k: int, score: str = "score", chars: int = 80) -> DataFrame:
    """(domain, side, rank, doc_id, score, excerpt): best and worst ``k`` documents of each domain."""
    value = F.round(score, 6)
    best = F.row_number().over(Window.partitionBy("domain").orderBy(F.desc(value), "doc_id"))
    worst = F.row_number().over(Window.partitionBy("domain").orderBy(value, "doc_id"))
    rows = scores.select("doc_id", "domain", value.alias("score"), F.struct(best.alias("top"), worst.alias("bottom")).alias("r"))
    sides = F.array(F.struct(F.lit("top").alias("side"), F.col("r.top").alias("rank")), F.struct(F.lit("bottom").alias("side"), F.col("r.bottom").alias("rank")))
    cut = rows.select("doc_id", "domain", "score", F.explode(sides).alias("s")).where(F.col("s.rank") <= k)
    return cut.join(docs.select("doc_id", F.substring("text", 1, chars).alias("excerpt")), "doc_id").select("domain", "s.side", "s.rank", "doc_id", "score", "excerpt")


def label_agreement(scores: DataFrame, labels: DataFrame, score: str = "score", label: str = "quality") -> DataFrame:
    """(n_docs, positives, auc, point_biserial): area under the curve by rank sum, ties half, null where one class
    has no row; correlation with the label."""
    rows = scores.select("doc_id", F.round(score, 6).alias("s")).join(labels.select("doc_id", F.col(label).alias("y")), "doc_id")
    ranked = average_rank(rows, "s", "doc_id", "r")
    n1, n = F.sum("y"), F.count("*")
    area = F.try_divide(F.sum(F.when(F.col("y") == 1, F.col("r"))) - n1 * (n1 + 1) / 2, n1 * (n - n1))
    return ranked.agg(n.alias("n_docs"), n1.cast("bigint").alias("positives"), area.alias("auc"), safe_corr(F.col("s"), F.col("y").cast("double")).alias("point_biserial"))


def _bag(text: Column) -> Column:
    return tokens_of(F.lower(text), "word")


def token_f1(answer: Column, truth: Column) -> Column:
    """F1 of the token multisets of two texts; 0 where nothing is shared."""
    a, b = _bag(answer), _bag(truth)
    shared = F.aggregate(
        F.array_distinct(a), F.lit(0),
        lambda n, t: n + F.least(F.size(F.filter(a, lambda x: x == t)), F.size(F.filter(b, lambda x: x == t))),
    )
    return F.when(shared == 0, F.lit(0.0)).otherwise(2 * shared / (F.size(a) + F.size(b)))


def exact_match(answer: Column, truth: Column) -> Column:
    return (F.array_join(_bag(answer), " ") == F.array_join(_bag(truth), " ")).cast("int")


def edit_similarity(answer: Column, truth: Column) -> Column:
    """One minus the edit distance over the longer length; two empty texts are equal."""
    longest = F.greatest(F.length(answer), F.length(truth))
    return F.when(longest == 0, F.lit(1.0)).otherwise(1 - F.levenshtein(answer, truth) / longest)


@F.pandas_udf(DoubleType())
def rouge_l(answer: pd.Series, truth: pd.Series) -> pd.Series:
    """F1 of the longest common subsequence of blank-separated tokens."""

    def one(a: str, b: str) -> float:
        x, y = (a or "").split(), (b or "").split()
        if not x or not y:
            return 0.0
        row = [0] * (len(y) + 1)
        for t in x:
            diagonal = 0
            for k, u in enumerate(y, 1):
                diagonal, row[k] = row[k], diagonal + 1 if t == u else max(row[k], row[k - 1])
        return 2 * row[-1] / (len(x) + len(y))

    return pd.Series([one(a, b) for a, b in zip(answer, truth, strict=True)], dtype="float64")
