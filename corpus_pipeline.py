"""From raw documents to token ids: language ID, toxicity, near duplicates, source mixing, BPE.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; what one stage returns is written as Parquet
and read again as the next one's docs. Stages but the last return the columns of documents.
"""

from __future__ import annotations

import os
import tempfile
import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanfocus.llm import bpe_codec, language_id, similar_texts, source_mixing, toxic_passages
from spanfocus.llm.entries import MIX, MIX_WEIGHTS, with_levels
from spanfocus.session import cut, release

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
#: Score under which the language of a text counts as not told: hardly above chance for two families of two.
LEAST_SURE = 0.3


def identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language can be told, with it: a null ``lang`` becomes the predicted one.

    Those without any letter go, and those of which the model is less sure than ``LEAST_SURE``. A stated
    language stays as it is. Null and repeated ids change nothing here.
    """
    model = language_id.fit_language_model(docs.where(language_id.fold("doc_id", 3) != 1))
    made = language_id.identify_language(docs, model, carry=COLUMNS)
    told = (F.col("lang_pred") != language_id.UNDETERMINED) & (F.col("score") >= LEAST_SURE)
    return made.where(told).withColumn("lang", F.coalesce("lang", "lang_pred")).select(*COLUMNS)


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that are not scored toxic."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = toxic_passages.fit_toxicity(docs, labels.where(toxic_passages.fold("doc_id", 4) != 2))
    made = toxic_passages.score_toxicity(docs, model, carry=COLUMNS)
    return made.where("predicted = 0").select(*COLUMNS)


def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of texts that are alike in 5-word shingles (Jaccard 0.8 or more): the smallest id.

    A group without any id keeps one document too: that of the smallest text digest. Null ids stay null.
    """
    groups = similar_texts.similar_text_groups(docs, words=5, least=0.8)
    first = groups.groupBy("root").agg(F.min(F.struct(F.col("first_id").isNull(), "first_id", "digest")).alias("k")).select("k.first_id", "k.digest").withColumnRenamed("first_id", "doc_id")
    first = first.withColumnsRenamed({"doc_id": "_id", "digest": "_digest"})
    same = F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("digest") == F.col("_digest"))
    rows = docs.select(*COLUMNS, similar_texts.text_digest().alias("digest"))
    keep = cut(rows.select("doc_id", "digest").join(first.hint("merge"), same).groupBy("_id", "_digest").agg(F.count("*").alias("rows")))
    kept = rows.join(keep.select("_id", "_digest").hint("merge"), same, "left_semi")
    # Only rows that repeat need the texts grouped once more.
    return (kept if keep.where("rows > 1").isEmpty() else kept.dropDuplicates(["doc_id", "digest"])).select(*COLUMNS)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents chosen for the target weights; one taken in two passes comes twice.

    Documents are drawn by a digest of the whole row, so null and repeated ids are documents as any other;
    rows equal in all columns come as often as all of them were taken.
    """
    parts = (F.coalesce(F.col(c).cast("string"), F.lit("\x01")) for c in COLUMNS)
    rows = docs.select(*COLUMNS, F.md5(F.concat_ws("\x00", *parts)).alias("row_key"))
    taken = source_mixing.mix(with_levels(rows), weights=MIX_WEIGHTS, key="row_key", **MIX)
    taken = cut(taken.groupBy("row_key").agg(F.sum("copies").cast("int").alias("copies"), F.count("*").alias("rows")))
    # Only rows that repeat need the texts grouped once more.
    once = rows if taken.where("rows > 1").isEmpty() else rows.dropDuplicates(["row_key"])
    chosen = once.join(taken.select("row_key", "copies").hint("merge"), "row_key")
    return chosen.withColumn("pass", F.explode(F.sequence(F.lit(1), "copies"))).select(*COLUMNS)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document, with the digests of ids and decoded text."""
    return bpe_codec.encode_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("language_id", identified),
    ("toxicity", clean),
    ("near_duplicates", distinct),
    ("source_mixing", mixed),
    ("bpe", encoded),
]

#: SQL cannot express the models and the merges; tests compare the stages with brute force.
ORACLE_SQL = None


def stage_folder(spark: SparkSession) -> str:
    """A new folder for stage tables under the shared checkpoint folder; a local one only where none is set."""
    shared = spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="spanfocus-pipeline-")
    return os.path.join(shared, f"corpus-pipeline-{uuid.uuid4().hex}")


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply all stages to the table documents; each but the last is written and read again."""
    docs, folder = spark.read.parquet(f"{sf_dir}/documents.parquet"), stage_folder(spark)
    for number, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if number + 1 < len(STAGES):
            path = f"{folder}/{number}-{name}"
            docs.write.parquet(path)
            docs = spark.read.parquet(path)
            release(spark)
    return docs
