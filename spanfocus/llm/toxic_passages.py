"""Toxic passages: maximal-scoring segments over token log-odds, with extreme-value calibration.

Every token gets a log-odds score between toxic and clean labelled texts under an informative Dirichlet
prior (the token's share of the whole corpus); scores that are not significant count as a small penalty.
One linear scan finds every maximal-scoring segment of a text. A segment's score is turned into nats above
what the best segment of a clean text of that length reaches (lambda and K of the extreme-value law); the
significant segments add up, and a monotone curve fitted on the labelled rows maps the sum to 0 ... 1.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanfocus.llm.arrow_rows import map_texts, text_blocks
from spanfocus.llm.samples import bounded_sample, fold
from spanfocus.session import cut, ship_package

_WORD = re.compile(r"[^\W\d_]+")
_HELD = 200_000
#: Lengths of word beginnings that are counted beside whole words, for words not seen before.
STEMS = (4, 6)
_REMEMBERED = 300_000
#: Candidate tokens that are sent to the executors at most.
SENT = 500_000


def stems(word: str) -> list[str]:
    """A longer word's beginnings, marked so that no word equals one."""
    return ["^" + word[:n] for n in STEMS if len(word) > n]


@dataclass
class Passage:
    """Tokens [start, stop) and their characters [char_start, char_stop), with score and nats above chance."""

    start: int
    stop: int
    char_start: int
    char_stop: int
    score: float
    nats: float


def maximal_segments(places: list[int], gains: list[float], penalty: float) -> list[tuple[int, int, float]]:
    """All maximal-scoring segments (first place, last place, score) of a sparse score sequence, in one pass.

    ``places`` are the positions of the positive scores in ``gains``, ascending; every other position costs
    ``penalty``. Segments are disjoint, each starts and ends on a positive score, and none can be extended
    or cut to a higher score.
    """
    # Each candidate: first place, last place, sum before it, sum through it, index of the next candidate
    # to its left whose sum before is lower (-1: none).
    found: list[tuple[int, int, float, float, int]] = []
    total, at = 0.0, 0
    for place, gain in zip(places, gains, strict=True):
        before = total - penalty * (place - at)
        total, at = before + gain, place + 1
        first, low, high = place, before, total
        left = len(found) - 1
        while True:
            while left >= 0 and found[left][2] >= low:
                left = found[left][4]
            if left < 0 or found[left][3] >= high:
                break
            first, low = found[left][0], found[left][2]
            del found[left:]
            left -= 1
        found.append((first, place, low, high, left))
    return [(a, b, high - low) for a, b, low, high, _ in found]


@dataclass
class ToxicityModel:
    """Fitted scorer; its token table holds the significant tokens of a bounded sample."""

    gain: dict[str, float] = field(default_factory=dict)
    penalty: float = 0.05
    decay: float = 1.0
    log_k: float = 0.0
    curve_x: list[float] = field(default_factory=list)
    curve_y: list[float] = field(default_factory=list)
    base: float = 0.0
    known: dict[str, float] = field(default_factory=dict, repr=False)

    def gains(self, words: list[str]) -> list[float]:
        """Gain of each word: its own or that of its best beginning, zero if neither is significant."""
        known, gain = self.known, self.gain.get
        if new := set(words).difference(known):
            if len(known) + len(new) > _REMEMBERED:
                known.clear()
                new = set(words)
            for w in new:
                known[w] = gain(w) or max((gain(x, 0.0) for x in stems(w)), default=0.0)
        return list(map(known.__getitem__, words))

    def _tokens(self, text: str) -> tuple[int, list[int], list[float], list[tuple[int, int]]]:
        """Number of tokens; place, gain and character span of those with a positive score."""
        n, places, gains, spans = 0, [], [], []
        times: Counter[str] = Counter()
        lowered = text.lower()
        whole = len(lowered) < _HELD * 4
        matches = None if whole else _WORD.finditer(lowered)
        while True:
            some = None if whole else list(islice(matches, _HELD))
            words = _WORD.findall(lowered) if whole else [m.group() for m in some]
            found = self.gains(words)
            at = [i for i, g in enumerate(found) if g]
            for i in at:
                # A word said again is no independent evidence: each time counts half the time before.
                gains.append(found[i] * 0.5 ** min(times[words[i]], 60))
                times[words[i]] += 1
            places += [n + i for i in at]
            if whole and at:
                wanted = set(at)
                spans = [m.span() for i, m in enumerate(_WORD.finditer(lowered)) if i in wanted]
            elif at:
                spans += [some[i].span() for i in at]
            n += len(words)
            if whole or not words:
                return n, places, gains, spans

    def analyse(self, text: str) -> tuple[float, list[Passage]]:
        """Raw value and significant passages (those above zero nats) of a whole text.

        The raw value is the sum of the passages' nats; without any, the best segment's nats, floored.
        """
        n, places, gains, spans = self._tokens(text)
        if not places:
            return -20.0, []
        shift = self.log_k + math.log(max(n, 2))
        segments = maximal_segments(places, gains, self.penalty)
        nats = [self.decay * s - shift for _, _, s in segments]
        span_of = dict(zip(places, spans, strict=True))
        found = [
            Passage(a, b + 1, span_of[a][0], span_of[b][1], s, x) for (a, b, s), x in zip(segments, nats, strict=True) if x > 0
        ]
        return (sum(p.nats for p in found) if found else max(-19.0, max(nats))), found

    def best_segment(self, text: str) -> tuple[int, float]:
        n, places, gains, _ = self._tokens(text)
        return n, max((s for _, _, s in maximal_segments(places, gains, self.penalty)), default=0.0)

    def score(self, raw: float) -> float:
        """Probability-like score of a raw value; strictly increasing, so that ties come from equal raws only."""
        if not self.curve_x:
            return self.base
        p = float(np.interp(raw, self.curve_x, self.curve_y))
        return min(1.0, max(0.0, 0.999 * p + 0.001 * (raw + 20) / (abs(raw) + 40)))


def _counted(df: DataFrame, text: str, label: str | None, wanted: Broadcast | None) -> DataFrame:
    """(token, toxic, n): in how many texts a token occurs, by label; blocks are counted before the shuffle.

    ``wanted`` holds packed tokens (:func:`_packed`): with it only those are counted. Without a label, a null
    token bears the number of all occurrences.
    """
    ship_package(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, Counter[str | None]] = {0: Counter(), 1: Counter()}
        asked = None if wanted is None else _unpacked(wanted.value)

        def flush() -> Iterator[pa.RecordBatch]:
            for toxic, s in sums.items():
                tokens, counts = list(s), list(s.values())
                s.clear()
                arrays = [pa.array(tokens, pa.string()), pa.array([toxic] * len(tokens), pa.int32()), pa.array(counts, pa.int64())]
                yield pa.RecordBatch.from_arrays(arrays, names=["token", "toxic", "n"])
            pa.default_memory_pool().release_unused()

        for block, texts in text_blocks(batches, text):
            marks = block.column(block.schema.get_field_index(label)).to_pylist() if label else [0] * len(texts)
            for t, mark in zip(texts, marks, strict=True):
                words = set(_WORD.findall(t.lower()))
                words |= {x for w in words for x in stems(w)}
                if label is None:
                    sums[0][None] += len(words)
                if asked is not None:
                    words &= asked
                sums[1 if mark == 1 else 0].update(words)
            if len(sums[0]) + len(sums[1]) > 200_000:
                yield from flush()
        yield from flush()

    columns = [text, label] if label else [text]
    made = df.select(*columns).mapInArrow(run, "token string, toxic int, n bigint")
    return made.groupBy("token", "toxic").agg(F.sum("n").alias("n"))


def _packed(tokens: pa.Array) -> bytes:
    """Tokens, none of which holds a blank, as compressed bytes."""
    return zlib.compress(" ".join(tokens.to_pylist()).encode(), 1)


@lru_cache(maxsize=1)
def _unpacked(data: bytes) -> frozenset[str]:
    return frozenset(zlib.decompress(data).decode().split(" "))


def log_odds(
    docs: DataFrame, sample: DataFrame, text: str, label: str, prior: float = 1.0, least_z: float = 3.0, least_texts: int = 3
) -> tuple[dict[str, float], float]:
    """Significant tokens with their lower-bound log-odds, and their expected number per clean token.

    Candidates are all tokens that at least ``least_texts`` toxic texts of the sample hold and that are
    commoner there than in clean ones. The more candidates there are, the higher is the largest deviation
    that chance gives: the bar rises with the root of twice the logarithm of their number, from ``least_z``
    up. The test is made in Spark; the driver gets the tokens that pass it.

    Prior: a pseudo-corpus of ``prior`` times the toxic counts, distributed as the whole corpus is; the
    candidates' shares of it are counted over all of ``docs``. Up to ``SENT`` candidates are sent to the
    executors, so that only they are shuffled; beyond, all tokens are counted and joined.
    """
    counts = _counted(sample, text, label, None)
    by_label = (F.coalesce(F.sum(F.when(F.col("toxic") == k, F.col("n"))), F.lit(0)).alias(c) for k, c in ((1, "toxic"), (0, "clean")))
    table = cut(counts.groupBy("token").agg(*by_label))
    toxic, clean = (float(x or 0) for x in table.agg(F.sum("toxic"), F.sum("clean")).first())
    if not toxic or not clean:
        return {}, 0.0
    likely = table.where((F.col("toxic") >= least_texts) & (F.col("toxic") * F.lit(clean) > F.col("clean") * F.lit(toxic)))
    candidates = likely.count()
    if not candidates:
        return {}, 0.0
    wanted = docs.sparkSession.sparkContext.broadcast(_packed(likely.select("token").toArrow().column(0))) if candidates <= SENT else None
    seen = _counted(docs, text, None, wanted).select("token", "n")
    seen = cut(seen.where("token IS NULL").unionByName(seen.join(likely.select("token"), "token")) if wanted is None else seen)
    total, mass = max(1.0, float(seen.where("token IS NULL").first().n)), prior * toxic
    bar = max(least_z, math.sqrt(2 * math.log(candidates)) - 0.5)
    share = F.greatest(F.coalesce("n", F.lit(0)), F.col("toxic") + F.col("clean")) / F.lit(total)
    tested = likely.join(seen.where("token IS NOT NULL"), "token", "left").select(
        "token", "clean", (F.col("toxic") + share * mass).alias("one"), (F.col("clean") + share * mass).alias("two")
    )
    delta = F.log(F.col("one") / (toxic + mass - F.col("one"))) - F.log(F.col("two") / (clean + mass - F.col("two")))
    spread = F.sqrt(1 / F.col("one") + 1 / F.col("two"))
    tested = tested.select("token", "clean", delta.alias("delta"), spread.alias("spread"))
    kept = tested.where((F.col("delta") > 0) & (F.col("delta") >= bar * F.col("spread")))
    found = kept.select("token", (F.col("delta") - F.col("spread")).alias("gain"), "clean").toArrow()
    gain = dict(sorted(zip(found.column("token").to_pylist(), found.column("gain").to_pylist(), strict=True)))
    return gain, sum(c + 0.5 for c in found.column("clean").to_pylist()) / clean


def _decay(gains: list[float], rate: float, penalty: float) -> float:
    """Positive root of the expected exponential score being one under clean text; bisection."""
    if not gains:
        return 1.0
    share = rate / len(gains)

    def excess(x: float) -> float:
        return sum(share * math.exp(min(x * g, 600)) for g in gains) + (1 - rate) * math.exp(-x * penalty) - 1

    low, high = 1e-6, 1.0
    while excess(high) < 0 and high < 64:
        high *= 2
    if excess(low) > 0:
        return 0.5  # no drift to measure: a mild scale
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (mid, high) if excess(mid) < 0 else (low, mid)
    return low


def _monotone(values: list[float], weights: list[float]) -> list[float]:
    """Weighted least-squares increasing fit by pooling neighbours."""
    pools: list[list[float]] = []
    for v, w in zip(values, weights, strict=True):
        pools.append([v, w, 1])
        while len(pools) > 1 and pools[-2][0] >= pools[-1][0]:
            b, a = pools.pop(), pools.pop()
            pools.append([(a[0] * a[1] + b[0] * b[1]) / (a[1] + b[1]), a[1] + b[1], a[2] + b[2]])
    return [v for v, _, n in pools for _ in range(int(n))]


def fit_toxicity(
    docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic",
    per_class: int = 25_000, penalty: float = 0.05,
) -> ToxicityModel:
    """Fit on at most about ``per_class`` labelled rows of each class; corpus shares come from all rows.

    Copies of one text with one label count once. Repeated or contradicting labels of an id: the largest
    label holds. With no toxic or no clean row the model gives every text the labels' mean.
    """
    one = labels.where(F.col(label).isin(0, 1)).groupBy(key).agg(F.max(label).alias(label))
    judged = bounded_sample(one, key, label, per_class, classes=2)
    texts = docs.select(key, F.xxhash64(F.coalesce(text, F.lit(""))).alias("h")).join(F.broadcast(judged), key)
    judged = texts.groupBy("h", label).agg(F.min(key).alias(key)).select(key, label)
    judged = cut(judged)  # bounded by per_class: ids and labels only
    spark = docs.sparkSession
    model = ToxicityModel(penalty=penalty)
    marks = {int(r[label]): r["count"] for r in judged.groupBy(label).count().collect()}
    if not marks:
        return model
    model.base = marks.get(1, 0) / sum(marks.values())
    if len(marks) < 2:
        return model
    sample = cut(docs.select(key, text).join(F.broadcast(judged), key))  # read four times
    model.gain, rate = log_odds(docs, sample, text, label)
    if not model.gain:
        return model
    model.decay = _decay(list(model.gain.values()), min(rate, 0.5), penalty)

    shared = spark.sparkContext.broadcast(model)

    def best(texts: list[str]) -> dict[str, list]:
        found = [shared.value.best_segment(t) for t in texts]
        return {"n": [n for n, _ in found], "best": [s for _, s in found]}

    clean = map_texts(sample.where(F.col(label) == 0), [key], text, "n bigint, best double", best)
    fitted = clean.where("best > 0 and n > 1").agg(F.avg(F.col("best") * model.decay - F.log("n")), F.count("*")).first()
    # The mean of a Gumbel variable is its mode plus Euler's constant; clean texts without any hit count as -1.
    model.log_k = float(fitted[0]) - 0.5772156649 if fitted[1] else 0.0
    shared = spark.sparkContext.broadcast(model)

    def raws(texts: list[str]) -> dict[str, list]:
        return {"bin": [int(max(-40, min(400, round(shared.value.analyse(t)[0] * 2)))) for t in texts]}

    binned = map_texts(sample, [key, label], text, "bin int", raws).groupBy("bin").agg(F.count("*").alias("n"), F.sum(label).alias("t"))
    points = sorted(binned.collect())
    smooth = _monotone([(t + 0.2 * model.base) / (n + 0.2) for _, n, t in points], [float(n) for _, n, _ in points])
    model.curve_x, model.curve_y = [b / 2 for b, _, _ in points], smooth
    return model


def score_toxicity(
    docs: DataFrame, model: ToxicityModel, key: str = "doc_id", text: str = "text", threshold: float = 0.3, carry: tuple[str, ...] = ()
) -> DataFrame:
    """(key, carried columns, score, predicted, passages) of every row, from the text alone.

    ``passages`` lists the significant passages as character spans with their nats above chance. Null and
    empty texts have none and get the score of a text without any hit. Repeated rows stay.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the token table's limit

    def run(texts: list[str]) -> dict[str, list]:
        m = shared.value
        made = [m.analyse(t) for t in texts]
        scores = [m.score(raw) for raw, _ in made]
        spans = [[{"start": p.char_start, "stop": p.char_stop, "nats": p.nats} for p in found] for _, found in made]
        return {"score": scores, "predicted": [int(s >= threshold) for s in scores], "passages": spans}

    schema = "score double, predicted int, passages array<struct<start: int, stop: int, nats: double>>"
    return map_texts(docs, [key, *carry], text, schema, run)


def predict_with_holdout(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", parts: int = 4, held: int = 2) -> DataFrame:
    """Labels outside the held-out fold teach, every row is scored: (key, held_out, score, predicted, passages)."""
    model = fit_toxicity(docs, labels.where(fold(key, parts) != held), key, text)
    made = score_toxicity(docs, model, key, text)
    return made.withColumn("held_out", F.coalesce(fold(key, parts) == held, F.lit(False)))
