"""Reading and writing tables: explicit columns, several formats, partitioned and line-wise sinks."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

FORMATS = ("parquet", "orc", "json", "csv", "text")
DOCUMENTS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def require(df: DataFrame, *columns: str) -> DataFrame:
    """The frame itself; ValueError naming the first missing column."""
    for c in columns:
        if c not in df.columns:
            raise ValueError(f"missing column {c!r}; there are {', '.join(df.columns)}")
    return df


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A Parquet table of a data directory, pruned to ``columns`` where some are named."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return require(df, *columns).select(*columns) if columns else df


def read_corpus(spark: SparkSession, path: str | Sequence[str], kind: str = "parquet", schema: str | StructType = DOCUMENTS) -> DataFrame:
    """Documents in any of FORMATS. JSON and CSV keep broken rows in ``_corrupt_record``; text has one column."""
    if kind not in FORMATS:
        raise ValueError(f"unknown format {kind!r}; known: {', '.join(FORMATS)}")
    paths = [path] if isinstance(path, str) else list(path)
    if kind == "text":
        return spark.read.text(paths, wholetext=True)
    reader = spark.read.format(kind)
    full = StructType.fromDDL(schema) if isinstance(schema, str) else schema
    if kind in ("json", "csv"):
        full = StructType(full.fields).add("_corrupt_record", "string")
        reader = reader.option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "_corrupt_record")
    if kind == "csv":
        reader = reader.option("header", "true").option("multiLine", "true").option("escape", '"')
    return reader.schema(full).load(paths)


def stream_documents(spark: SparkSession, path: str, schema: str = DOCUMENTS, files_per_trigger: int = 1) -> DataFrame:
    """Arriving Parquet files as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def write_by_domain(df: DataFrame, path: str, domain: str = "domain", mode: str = "overwrite") -> None:
    """Parquet, one folder per domain, rows of a domain spread over as many tasks as AQE sees fit."""
    require(df, domain).hint("rebalance", domain).write.mode(mode).partitionBy(domain).parquet(path)


def write_lines(df: DataFrame, path: str, mode: str = "overwrite") -> None:
    """JSON lines for trainers."""
    df.write.mode(mode).json(path)


def run_only(df: DataFrame) -> None:
    """Compute everything, keep nothing: for timing."""
    df.write.format("noop").mode("overwrite").save()
