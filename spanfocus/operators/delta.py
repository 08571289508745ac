"""The delta-perplexity baseline: how much a segment's perplexity falls when an earlier segment is given.

The language model is a smoothed unigram model over all documents; a given segment mixes in as a cache
with weight ``mix``. Only tokens that two segments share change the perplexity.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from spanfocus.functions.text import token_hashes, tokens_of
from spanfocus.operators.lexical import MAX_EXACT, Weights, WeightRows, WeightTable, with_weights
from spanfocus.session import cut


def unigram_counts(df: DataFrame, text: str = "text", mode: str = "space") -> DataFrame:
    """(token, n) over all documents."""
    return df.select(F.explode(tokens_of(text, mode)).alias("token")).groupBy("token").agg(F.count("*").alias("n"))


def unigram_table(df: DataFrame, alpha: float = 1.0, text: str = "text", mode: str = "space", max_exact: int = MAX_EXACT) -> Weights:
    """p(t) = (n(t) + alpha) / (T + alpha (V + 1)): broadcast up to ``max_exact`` tokens, beyond that a table to be joined."""
    counts = df.select(F.explode(token_hashes(tokens_of(text, mode))).alias("h")).groupBy("h").agg(F.count("*").alias("n")).persist()
    try:
        v, total = counts.agg(F.count("*"), F.sum("n")).first()
        whole = (total or 0) + alpha * (v + 1)
        if v > max_exact:
            return WeightRows(cut(counts.select("h", ((F.col("n") + F.lit(float(alpha))) / F.lit(float(whole))).alias("weight"))))
        rows = counts.toArrow()
    finally:
        counts.unpersist()
    h, p = rows["h"].to_numpy().astype(np.int64), (rows["n"].to_numpy().astype(np.float64) + alpha) / whole
    order = np.argsort(h)
    return WeightTable(h[order], p[order])


#: Later segments whose perplexities are computed at once.
_LATER = 16


@dataclass(frozen=True)
class DeltaOptions:
    """``strength`` absolute or relative gain; ``distance_weight`` multiplies (j-i)/(N-1); ``specificity``
    multiplies the share of distinct tokens of the later segment; gains not above ``threshold`` count as 0;
    ``pairs`` bounds the distance i..j to so many segments (0: all pairs); ``sampled`` is the share of pairs
    that a seeded draw keeps, and the sum is over those."""

    segment: int = 32
    mix: float = 0.5
    strength: str = "absolute"
    distance_weight: bool = False
    specificity: bool = False
    threshold: float | None = None
    pairs: int = 0
    sampled: float = 1.0
    seed: int = 1

    def __post_init__(self) -> None:
        if self.strength not in ("absolute", "relative"):
            raise ValueError("strength must be 'absolute' or 'relative'")


def gains(h: np.ndarray, p: np.ndarray, o: DeltaOptions) -> tuple[np.ndarray, np.ndarray]:
    """Perplexity of each segment alone, (segments,), and given each earlier one, (given i, segment j).

    Later segments are taken a few at a time; for these, only the counts of their own tokens are spread out.
    """
    n, size = len(h) // o.segment, o.segment
    codes, p = np.unique(h, return_inverse=True)[1][: n * size], p[: n * size]
    alone = np.exp(-np.log(p).reshape(n, size).mean(axis=1))
    # Occurrences by code: what segments hold a code, and how often.
    held, times = np.unique(codes * n + np.repeat(np.arange(n), size), return_counts=True)
    of, segment = held // n, held % n
    given = np.empty((n, n))
    for a in range(0, n, _LATER):
        b = min(n, a + _LATER)
        own, at = np.unique(codes[a * size : b * size], return_inverse=True)
        begin, end = np.searchsorted(of, own), np.searchsorted(of, own, "right")
        column = np.repeat(np.arange(len(own)), end - begin)
        places = np.arange(len(column)) - np.repeat(np.cumsum(end - begin) - (end - begin), end - begin) + np.repeat(begin, end - begin)
        counts = np.zeros((n, len(own)))
        counts[segment[places], column] = times[places]
        mixed = (1 - o.mix) * p[a * size : b * size] + o.mix * counts[:, at] / size
        given[:, a:b] = np.exp(-np.log(mixed).reshape(n, b - a, size).mean(axis=2))
    return alone, given


def drawn_pairs(i: np.ndarray, j: np.ndarray, share: float, seed: int, key: int) -> np.ndarray:
    """Whether a pair is in the seeded draw: a mixed number of document, pair and seed below the share."""
    number = (key % 1_000_003) * 31 + i * 7_919 + j * 104_729 + seed * 13
    return number * 2_654_435_761 % 4_294_967_296 < share * 4_294_967_296


def delta_matrix(h: np.ndarray, p: np.ndarray, o: DeltaOptions, key: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """alone (j), given (i, j) and weighted gain (i, j) with zeros where i >= j or the pair is not used."""
    alone, given = gains(h, p, o)
    n = len(alone)
    gain = alone[None, :] - given
    if o.strength == "relative":
        gain = gain / alone[None, :]
    i, j = np.indices((n, n))
    if o.threshold is not None:
        gain = np.where(gain > o.threshold, gain, 0.0)
    if o.distance_weight and n > 1:
        gain = gain * (j - i) / (n - 1)
    if o.specificity:
        distinct = [len(np.unique(h[k * o.segment : (k + 1) * o.segment])) / o.segment for k in range(n)]
        gain = gain * np.array(distinct)[None, :]
    used = (i < j) & ((j - i <= o.pairs) if o.pairs else True)
    if o.sampled < 1:
        used &= drawn_pairs(i, j, o.sampled, o.seed, key)
    return alone, given, np.where(used, gain, 0.0)


def delta_perplexity(samples: DataFrame, table: Weights, options: dict[str, DeltaOptions] | None = None) -> DataFrame:
    """(doc_id, domain, n_tokens, a column per named option): the summed gain over all pairs, in one pass."""
    named = options or {"delta_score": DeltaOptions()}
    weighted, weights_of = with_weights(samples.select("doc_id", "domain", "n_tokens", token_hashes("tokens").alias("h")), table)
    schema = StructType(samples.select("doc_id", "domain", "n_tokens").schema.fields)
    for n in named:
        schema = schema.add(n, "double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made: list[list[float]] = [[] for _ in named]
            for k in range(batch.num_rows):
                h, key = batch.column(3)[k].values.to_numpy(zero_copy_only=False), batch.column(0)[k].as_py()
                p = weights_of(batch, k, h)
                for column, o in zip(made, named.values(), strict=True):
                    column.append(float(delta_matrix(h, p, o, key if isinstance(key, int) else 0)[2].sum()))
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], *(pa.array(m, pa.float64()) for m in made)], names=schema.fieldNames())

    return weighted.mapInArrow(run, schema)


def delta_pairs(samples: DataFrame, table: Weights, options: DeltaOptions = DeltaOptions()) -> DataFrame:
    """(doc_id, j, i, ppl_alone, ppl_given, gain) of all pairs i < j."""
    weighted, weights_of = with_weights(samples.select("doc_id", token_hashes("tokens").alias("h")), table)
    schema = StructType([samples.schema["doc_id"], *StructType.fromDDL("j int, i int, ppl_alone double, ppl_given double, gain double").fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                h = batch.column(1)[k].values.to_numpy(zero_copy_only=False)
                alone, given, gain = delta_matrix(h, weights_of(batch, k, h), options)
                i, j = np.triu_indices(len(alone), 1)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.repeat(batch.column(0)[k], len(i)), pa.array(j.astype(np.int32)), pa.array(i.astype(np.int32)),
                        pa.array(alone[j]), pa.array(given[i, j]), pa.array(gain[i, j]),
                    ],
                    names=schema.fieldNames(),
                )

    return weighted.mapInArrow(run, schema)


def segment_perplexity(samples: DataFrame, table: Weights, segment: int = 32) -> DataFrame:
    """(doc_id, j, ppl_alone) of every segment under the unigram model."""
    weighted, weights_of = with_weights(samples.select("doc_id", token_hashes("tokens").alias("h")), table)
    schema = StructType([samples.schema["doc_id"], *StructType.fromDDL("j int, ppl_alone double").fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                p = weights_of(batch, k, batch.column(1)[k].values.to_numpy(zero_copy_only=False))
                n = len(p) // segment
                alone = np.exp(-np.log(p[: n * segment]).reshape(n, segment).mean(axis=1))
                yield pa.RecordBatch.from_arrays([pa.repeat(batch.column(0)[k], n), pa.array(np.arange(n, dtype=np.int32)), pa.array(alone)], names=schema.fieldNames())

    return weighted.mapInArrow(run, schema)
