"""Count language models of selections, and perplexity of held-out text by context window.

Two ways give the same numbers: counts of checked size are sent to the workers, and one kernel pass over the
held-out texts serves all selections, models and windows (:func:`perplexities`); larger counts stay tables,
joined to the texts token by token (:func:`perplexity`).
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spanfocus.functions.text import token_hashes
from spanfocus.operators.samples import positions
from spanfocus.session import cut, ship_package
from spanfocus.sources.tables import require

#: Counts of all selections together that are sent to the workers at most: 16 bytes each.
MAX_COUNTS = 4_000_000
_TOKEN, _BEFORE, _PAIR = 0, 1, 2

#: name: (bigrams, cache) — the four models that stand for a scale of models.
MODELS = {"unigram": (False, False), "unigram_cache": (False, True), "bigram": (True, False), "bigram_cache": (True, True)}


@dataclass
class CountModel:
    """Unigram (token, n) and bigram (before, token, n, n_before) counts with their totals."""

    unigrams: DataFrame
    bigrams: DataFrame
    total: int
    vocabulary: int
    alpha: float = 1.0
    pull: float = 50.0
    cache: float = 0.2


def fit_lm(df: DataFrame, alpha: float = 1.0, pull: float = 50.0, cache: float = 0.2) -> CountModel:
    """Counts over tokenised rows. ``pull`` is the weight of the unigram model inside a bigram, ``cache`` the
    share of the text's own earlier tokens."""
    rows = positions(require(df, "doc_id", "tokens"))
    unigrams = rows.groupBy("token").agg(F.count("*").alias("n"))
    before = F.lag("token").over(Window.partitionBy("doc_id").orderBy("pos"))
    pairs = rows.withColumn("before", before).where("before IS NOT NULL").groupBy("before", "token").agg(F.count("*").alias("n"))
    bigrams = pairs.withColumn("n_before", F.sum("n").over(Window.partitionBy("before")))
    v, total = unigrams.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
    return CountModel(unigrams, bigrams, int(total), int(v), alpha, pull, cache)


def token_probabilities(df: DataFrame, lm: CountModel, length: int) -> DataFrame:
    """(doc_id, pos, p_unigram, p_bigram, p_cache) of the first ``length`` tokens of each row."""
    cut = df.select("doc_id", F.slice("tokens", 1, length).alias("tokens"))
    rows = positions(cut)
    seen = F.row_number().over(Window.partitionBy("doc_id", "token").orderBy("pos")) - 1
    before = F.lag("token").over(Window.partitionBy("doc_id").orderBy("pos"))
    rows = rows.withColumn("seen", seen).withColumn("before", before)
    rows = rows.join(lm.unigrams.select("token", F.col("n").alias("n_token")), "token", "left")
    rows = rows.join(lm.bigrams.select("before", "token", F.col("n").alias("n_pair")), ["before", "token"], "left")
    totals = lm.bigrams.groupBy("before").agg(F.max("n_before").alias("n_before"))
    rows = rows.join(totals, "before", "left")
    plain = (F.coalesce("n_token", F.lit(0)) + lm.alpha) / (lm.total + lm.alpha * (lm.vocabulary + 1))
    rows = rows.withColumn("p_unigram", plain)
    pair = (F.coalesce("n_pair", F.lit(0)) + lm.pull * F.col("p_unigram")) / (F.coalesce("n_before", F.lit(0)) + lm.pull)
    p_cache = F.when(F.col("pos") > 0, F.col("seen") / F.col("pos"))
    return rows.select("doc_id", "pos", "p_unigram", pair.alias("p_bigram"), p_cache.alias("p_cache"))


def perplexity(df: DataFrame, lm: CountModel, windows: Sequence[int], models: Sequence[str] = tuple(MODELS)) -> DataFrame:
    """(model, window, n_docs, ppl): per text exp of the mean negative log probability of its first ``window``
    tokens, averaged over the texts that long. One pass serves all windows and models."""
    length = max(windows)
    p = token_probabilities(df, lm, length)

    def probability(bigrams: bool, cache: bool):
        base = F.col("p_bigram" if bigrams else "p_unigram")
        mixed = (1 - lm.cache) * base + lm.cache * F.col("p_cache")
        return F.when(F.col("p_cache").isNotNull(), mixed).otherwise(base) if cache else base

    sums = [
        F.sum(F.when(F.col("pos") < w, F.log(probability(*MODELS[m])))).alias(f"{m}:{w}") for m in models for w in windows
    ]
    per_doc = p.groupBy("doc_id").agg(F.count("*").alias("n"), *sums)
    cells = F.explode(
        F.array(*(F.struct(F.lit(m).alias("model"), F.lit(w).alias("window"), F.col(f"{m}:{w}").alias("s")) for m in models for w in windows))
    )
    rows = per_doc.select("n", cells.alias("c")).select("n", "c.*").where(F.col("n") >= F.col("window"))
    return rows.groupBy("model", "window").agg(F.count("*").alias("n_docs"), F.avg(F.exp(-F.col("s") / F.col("window"))).alias("ppl"))


def _pair_hashes(tokens: str) -> Column:
    """Hash of every token with the one before it."""
    at = F.sequence(F.lit(1), F.greatest(F.size(tokens) - 1, F.lit(1)))
    made = F.transform(at, lambda i: F.xxhash64(F.get(F.col(tokens), i - 1), F.get(F.col(tokens), i)))
    return F.when(F.size(tokens) > 1, made).otherwise(F.array().cast("array<bigint>"))


def selection_counts(chosen: dict[str, DataFrame]) -> DataFrame:
    """(method, kind, key, n): tokens, tokens that another one follows, and pairs of neighbours, in one aggregate."""
    parts = []
    for method, df in chosen.items():
        h = token_hashes("tokens")
        kinds = ((_TOKEN, h), (_BEFORE, F.slice(h, F.lit(1), F.greatest(F.size("tokens") - 1, F.lit(0)))), (_PAIR, _pair_hashes("tokens")))
        marked = [F.arrays_zip(F.array_repeat(F.lit(kind), F.size(keys)).alias("kind"), keys.alias("key")) for kind, keys in kinds]
        parts.append(require(df, "tokens").select(F.lit(method).alias("method"), F.explode(F.concat(*marked)).alias("c")))
    rows = reduce(DataFrame.unionByName, parts).select("method", "c.kind", "c.key")
    return rows.groupBy("method", "kind", "key").agg(F.count("*").alias("n"))


@dataclass
class CountTables:
    """Sorted keys and counts by kind, for one selection."""

    tables: dict[int, tuple[np.ndarray, np.ndarray]]
    alpha: float = 1.0
    pull: float = 50.0
    cache: float = 0.2

    def of(self, kind: int, keys: np.ndarray) -> np.ndarray:
        known, n = self.tables[kind]
        if not known.size:
            return np.zeros(keys.shape)
        at = np.minimum(np.searchsorted(known, keys), known.size - 1)
        return np.where(known[at] == keys, n[at], 0)

    def logs(self, h: np.ndarray, pairs: np.ndarray) -> dict[str, np.ndarray]:
        """Log probability of each token of a text by model."""
        counts = self.tables[_TOKEN][1]
        plain = (self.of(_TOKEN, h) + self.alpha) / (counts.sum() + self.alpha * (len(counts) + 1))
        n_pair, n_before = (np.concatenate([[0], self.of(kind, keys)]) for kind, keys in ((_PAIR, pairs), (_BEFORE, h[:-1])))
        paired = (n_pair + self.pull * plain) / (n_before + self.pull)
        order = np.argsort(h, kind="stable")
        seen = np.empty(len(h), np.int64)
        seen[order] = np.arange(len(h)) - np.searchsorted(h[order], h[order])
        own = seen / np.maximum(np.arange(len(h)), 1)
        out = {}
        for model, (bigrams, cache) in MODELS.items():
            p = paired if bigrams else plain
            if cache:
                p = np.concatenate([p[:1], (1 - self.cache) * p[1:] + self.cache * own[1:]])
            out[model] = np.log(p)
        return out


def perplexities(chosen: dict[str, DataFrame], test: DataFrame, windows: Sequence[int], most: int = MAX_COUNTS) -> DataFrame:
    """(method, model, window, n_docs, ppl) of the count models of several selections, as :func:`perplexity` gives them."""
    counts = cut(selection_counts(chosen))
    if counts.count() > most:
        made = [perplexity(test, fit_lm(rows.select("doc_id", "tokens")), windows).withColumn("method", F.lit(m)) for m, rows in chosen.items()]
        return reduce(DataFrame.unionByName, made).select("method", "model", "window", "n_docs", "ppl")
    held, models = counts.toArrow(), {}
    method, kind, key, n = (held.column(c).to_numpy(zero_copy_only=False) for c in ("method", "kind", "key", "n"))
    for m in chosen:
        tables = {}
        for k in (_TOKEN, _BEFORE, _PAIR):
            own = (method == m) & (kind == k)
            order = np.argsort(key[own])
            tables[k] = (key[own][order], n[own][order])
        models[m] = CountTables(tables)
    spark = test.sparkSession
    ship_package(spark)
    shared = spark.sparkContext.broadcast(models)  # at most ``most`` counts

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            for h, pairs in zip(*(batch.column(c) for c in (0, 1)), strict=True):
                h, pairs = (x.values.to_numpy(zero_copy_only=False) for x in (h, pairs))
                fitting = [w for w in windows if w <= len(h)]
                for m, model in shared.value.items() if fitting else ():
                    for name, logs in model.logs(h, pairs).items():
                        sums = np.cumsum(logs)
                        out += [(m, name, w, float(np.exp(-sums[w - 1] / w))) for w in fitting]
            columns = list(zip(*out, strict=True)) or [(), (), (), ()]
            types = (pa.string(), pa.string(), pa.int32(), pa.float64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=["method", "model", "window", "v"])

    longest = F.slice("tokens", 1, max(windows)).alias("tokens")
    rows = test.select(longest).select(token_hashes("tokens").alias("h"), _pair_hashes("tokens").alias("pairs"))
    made = rows.mapInArrow(run, "method string, model string, window int, v double")
    return made.groupBy("method", "model", "window").agg(F.count("*").alias("n_docs"), F.avg("v").alias("ppl"))
