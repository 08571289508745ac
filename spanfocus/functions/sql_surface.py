"""What SQL users call: table functions over tokens, a scalar span function, a grouped rank statistic."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from spanfocus.geometry import Geometry
from spanfocus.operators.lexical import focus_matrix
from spanfocus.session import ship_package


@F.udtf(returnType="j int, span_tokens string")
class SpanTable:
    """Rows (j, span_tokens) of a text cut into spans of ``length`` tokens; an incomplete last span is left out."""

    def eval(self, text: str, length: int):
        words = [w for w in (text or "").replace("\t", " ").replace("\n", " ").replace("\r", " ").split(" ") if w]
        for j in range(len(words) // length):
            yield j, " ".join(words[j * length : (j + 1) * length])


@F.udtf(returnType="j int, i int, pair_focus double")
class FocusPairs:
    """Rows (j, i, pair_focus) of hashed tokens and their weights, both of the geometry's length."""

    def eval(self, hashes: list, weights: list, span: int, skip_first: int, skip_near: int, row_stride: int, col_stride: int, first_row: int):
        g = Geometry(len(hashes), span, skip_first, skip_near, row_stride, col_stride, first_row)
        rows = g.rows()
        mass = focus_matrix(np.array(hashes, np.int64), np.array(weights, float), g, rows)
        for k, j in enumerate(rows):
            for i in g.cols(j):
                yield j, i, float(mass[i, k])


@F.pandas_udf(DoubleType())
def rank_auc(score: pd.Series, positive: pd.Series) -> float:
    """Area under the curve by rank sum, ties half, null without both classes; for groups that fit a task."""
    ranks, n = score.rank(), int((positive == 1).sum())
    rest = len(score) - n
    return float((ranks[positive == 1].sum() - n * (n + 1) / 2) / (n * rest)) if n and rest else float("nan")


def register(spark: SparkSession) -> None:
    """Make the functions callable from SQL under the prefix ``spanfocus_``."""
    ship_package(spark)
    spark.udtf.register("spanfocus_span_table", SpanTable)
    spark.udtf.register("spanfocus_focus_pairs", FocusPairs)
    spark.udf.register("spanfocus_rank_auc", rank_auc)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION spanfocus_span_index(pos INT, span INT) RETURNS INT RETURN CAST(floor(pos / span) AS INT)")
