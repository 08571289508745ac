"""Names of all queries outside the training-data subpackage, with their oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from spanfocus.operators import relational
from spanfocus.plans import method_queries, workloads
from spanfocus.streaming import arriving

arriving.register(method_queries.TABLE.oracles["dependency_arrow"], method_queries.TABLE.oracles["select_domain_budget"])

TABLES = (method_queries.TABLE, workloads.TABLE, relational.TABLE, arriving.TABLE)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return method_queries.flagship(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {n: q for t in TABLES for n, q in t.queries.items()}


def oracle_sql() -> dict[str, str]:
    return {n: q for t in TABLES for n, q in t.oracles.items()}
