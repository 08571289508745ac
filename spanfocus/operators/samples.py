"""Sample preparation: tokens, eligibility, spans, chunks, concatenations, draws and folding."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spanfocus.functions import text as T
from spanfocus.geometry import Geometry
from spanfocus.operators.ranks import global_row_number
from spanfocus.sources.tables import require


def tokenize(df: DataFrame, text: str = "text", mode: str = "space") -> DataFrame:
    """Adds ``tokens`` and ``n_tokens``. Null text has no tokens."""
    return require(df, text).withColumn("tokens", T.tokens_of(text, mode)).withColumn("n_tokens", F.size("tokens"))


def eligible(df: DataFrame, min_tokens: int, text: str = "text", mode: str = "space") -> DataFrame:
    """Tokenised rows of at least ``min_tokens`` tokens.

    A bound on characters goes first, so that short rows are dropped in the scan where ``n_chars`` is there.
    """
    bound = T.at_least_chars(min_tokens)
    by = F.col("n_chars") if "n_chars" in df.columns else F.length(text)
    rows = require(df, text).where(by >= bound)
    # The nested array keeps the tokens from being extracted once for the filter and once for the output.
    rows = rows.withColumn("_t", F.explode(F.array(T.tokens_of(text, mode)))).where(F.size("_t") >= min_tokens)
    return rows.withColumn("n_tokens", F.size("_t")).withColumnRenamed("_t", "tokens")


def truncate(df: DataFrame, length: int) -> DataFrame:
    """``tokens`` cut to exactly ``length``."""
    return require(df, "tokens").withColumn("tokens", F.slice("tokens", 1, length))


def samples(df: DataFrame, geometry: Geometry, domain: str = "source", mode: str = "space") -> DataFrame:
    """(doc_id, domain, n_tokens, tokens): eligible documents cut to the geometry's length.

    ``n_tokens`` is what a sample brings to a budget: the length it was cut to.
    """
    rows = truncate(eligible(require(df, "doc_id", domain), geometry.length, mode=mode), geometry.length)
    return rows.select("doc_id", F.col(domain).alias("domain"), F.size("tokens").alias("n_tokens"), "tokens")


def spans(df: DataFrame, geometry: Geometry, form: str = "nested") -> DataFrame:
    """Spans of samples: ``nested`` adds an array of token arrays, ``long`` gives (doc_id, j, span_tokens)."""
    cut = F.transform(
        F.sequence(F.lit(0), F.lit(geometry.n_spans - 1)), lambda j: F.slice("tokens", j * geometry.span + 1, geometry.span)
    )
    if form == "nested":
        return df.withColumn("spans", cut)
    if form != "long":
        raise ValueError("form must be 'nested' or 'long'")
    return df.select("doc_id", F.posexplode(cut).alias("j", "span_tokens"))


def positions(df: DataFrame) -> DataFrame:
    """Long form (doc_id, pos, token) of tokenised rows."""
    return df.select("doc_id", F.posexplode("tokens").alias("pos", "token"))


def chunk(df: DataFrame, length: int) -> DataFrame:
    """(doc_id, chunk_no, tokens): every document as consecutive samples of ``length``; the rest is dropped."""
    n = F.floor(F.size("tokens") / length).cast("int")
    whole = df.where(n > 0)
    made = F.transform(F.sequence(F.lit(0), n - 1), lambda k: F.slice("tokens", k * length + 1, length))
    return whole.select("doc_id", F.posexplode(made).alias("chunk_no", "tokens"))


def concatenate(df: DataFrame, length: int, piece: int, seed: int = 1) -> DataFrame:
    """(sample_id, piece_len, parts, tokens): samples of ``length`` tokens from unrelated pieces.

    Each document gives its first ``piece`` tokens; documents stand in md5 order of the seed and are taken
    ``length // piece`` at a time. An incomplete last sample is dropped.
    """
    k = length // piece
    if piece * k != length:
        raise ValueError("piece must divide length")
    placed = df.where(F.size("tokens") >= piece).select("doc_id", F.slice("tokens", 1, piece).alias("tokens"))
    # The order is over ids alone; the tokens join afterwards.
    ids = placed.select("doc_id", T.random_order("doc_id", seed).alias("o"))
    ids = global_row_number(ids, F.col("o"), F.col("doc_id")).withColumn("place", F.col("place") - 1)
    ids = ids.select("doc_id", F.floor(F.col("place") / k).cast("int").alias("sample_id"), (F.col("place") % k).cast("int").alias("piece_no"))
    grouped = placed.join(ids, "doc_id").groupBy("sample_id").agg(F.sort_array(F.collect_list(F.struct("piece_no", "doc_id", "tokens"))).alias("p"))
    return grouped.where(F.size("p") == k).select(
        "sample_id",
        F.lit(piece).alias("piece_len"),
        F.transform("p", lambda x: F.struct(x["doc_id"].alias("doc_id"), x["piece_no"].alias("piece_no"))).alias("parts"),
        F.flatten(F.transform("p", lambda x: x["tokens"])).alias("tokens"),
    )


def training_sequences(df: DataFrame, length: int, token_budget: int, seed: int = 1) -> DataFrame:
    """(doc_id, place, tokens): sequences of ``length`` tokens, drawn in md5 order until the budget is used."""
    n = token_budget // length
    drawn = df.where(F.size("tokens") >= length).select("doc_id", F.slice("tokens", 1, length).alias("tokens"))
    ids = global_row_number(drawn.select("doc_id", T.random_order("doc_id", seed).alias("o")), F.col("o"), F.col("doc_id"))
    placed = ids.where(F.col("place") <= n).select("doc_id", F.col("place").cast("int").alias("place"))
    return drawn.join(placed, "doc_id").select("doc_id", "place", "tokens")


def fold_conversations(turns: DataFrame) -> DataFrame:
    """(conv_id, n_turns, text): the turns of a conversation as one text, ``role: text`` a line."""
    line = F.concat(F.coalesce("role", F.lit("")), F.lit(": "), F.coalesce("text", F.lit("")))
    rows = require(turns, "conv_id", "turn", "role", "text").groupBy("conv_id").agg(
        F.sort_array(F.collect_list(F.struct("turn", line.alias("line")))).alias("t")
    )
    return rows.select(
        "conv_id", F.size("t").cast("bigint").alias("n_turns"), F.array_join(F.transform("t", lambda x: x["line"]), "\n").alias("text")
    )


def length_census(df: DataFrame, length: int, domain: str = "source") -> DataFrame:
    """(domain, docs, tokens, share, long_docs, long_tokens, kept_share) of the corpus by domain.

    ``df`` is tokenised. ``share`` is of all tokens; ``kept_share`` of the tokens of documents that reach
    ``length``, each counted with ``length`` tokens.
    """
    counted: Column = F.col("n_tokens") >= length
    rows = df.groupBy(F.col(domain).alias("domain")).agg(
        F.count("*").alias("docs"),
        F.sum("n_tokens").cast("bigint").alias("tokens"),
        F.count_if(counted).alias("long_docs"),
        (F.count_if(counted) * length).alias("long_tokens"),
    )
    whole = Window.partitionBy(F.lit(0))
    return rows.select(
        "domain", "docs", "tokens", F.try_divide("tokens", F.sum("tokens").over(whole)).alias("share"), "long_docs", "long_tokens",
        F.try_divide("long_tokens", F.sum("long_tokens").over(whole)).alias("kept_share"),
    )
