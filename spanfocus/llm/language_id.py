"""Language identification in two levels: the family first, then one-versus-one linear SVMs inside it.

Texts become counts of hashed character n-grams (one to three characters). Level one is a one-versus-rest
linear SVM over language families; level two votes between each pair of languages of the chosen family.
Families come from a table of known branches; a language outside it forms a family of its own.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass, field
from functools import reduce
from itertools import combinations

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spanfocus.llm.arrow_rows import map_texts
from spanfocus.llm.samples import bounded_sample, fold
from spanfocus.session import cut

# Branches of some languages by their two-letter codes.
FAMILIES = {
    "germanic": ("de", "en", "nl", "sv", "da", "no", "is"),
    "romance": ("fr", "es", "it", "pt", "ro", "ca"),
    "slavic": ("ru", "pl", "cs", "uk", "bg", "sk"),
}

SLOTS = 4096
#: Name of the task that separates the families.
TOP = "all families"
UNDETERMINED = "und"
_LETTER = regex.compile(r"\p{L}")
_WINDOW_CHARS = 1 << 20


def family_of(lang: str) -> str:
    return next((f for f, members in FAMILIES.items() if lang in members), f"only-{lang}")


def ngram_counts(text: str, slots: int = SLOTS) -> np.ndarray:
    """Counts of hashed 1-, 2- and 3-grams over the whole lower-cased text, in windows of bounded size."""
    counts = np.zeros(slots, np.int64)
    for at in range(0, len(text), _WINDOW_CHARS):
        part = text[max(0, at - 2) : at + _WINDOW_CHARS].lower()
        c = np.frombuffer(part.encode("utf-32-le", "replace"), np.uint32)
        two = c[:-1] * np.uint32(0x9E3779B1) ^ c[1:]
        three = two[:-1] * np.uint32(0x85EBCA77) ^ c[2:]
        for gram in (c, two, three):
            mixed = (gram ^ gram >> np.uint32(15)) * np.uint32(0x2C1B3C6D)
            counts += np.bincount((mixed >> np.uint32(12)) % slots, minlength=slots)
    return counts


def features(text: str, slots: int = SLOTS) -> np.ndarray:
    """Damped counts scaled to length one; zeros for an empty text."""
    x = np.sqrt(ngram_counts(text, slots)).astype(np.float32)
    return x / max(float(np.linalg.norm(x)), 1e-9)


def linear_svm(x: np.ndarray, y: np.ndarray, cost: float = 10.0, rounds: int = 30, seed: int = 7) -> np.ndarray:
    """Weights (bias last) of an SVM with squared hinge loss, by dual coordinate descent; y is -1 or 1.

    ``x`` is read row by row and never copied.
    """
    share = np.where(y > 0, (y > 0).mean(), (y < 0).mean())
    spread = 1 / (2 * cost * 0.5 / np.maximum(share, 1e-9))
    alpha, w, bias = np.zeros(len(x)), np.zeros(x.shape[1], np.float32), 0.0
    norm = np.einsum("ij,ij->i", x, x, dtype=np.float64) + 1 + spread
    order = np.random.default_rng(seed)
    for _ in range(rounds):
        moved = 0.0
        for i in order.permutation(len(x)):
            new = max(0.0, alpha[i] - (y[i] * (float(x[i] @ w) + bias) - 1 + spread[i] * alpha[i]) / norm[i])
            if new != alpha[i]:
                step = (new - alpha[i]) * y[i]
                w += np.float32(step) * x[i]
                bias += step
                moved = max(moved, abs(new - alpha[i]))
                alpha[i] = new
        if moved < 1e-3:
            break
    return np.append(w, np.float32(bias))


@dataclass
class LanguageModel:
    """The fitted two-level model; small (one weight row per family and per pair inside a family)."""

    families: dict[str, list[str]] = field(default_factory=dict)
    top: np.ndarray | None = None
    pairs: dict[str, tuple[list[tuple[int, int]], np.ndarray]] = field(default_factory=dict)
    sharpness: float = 4.0

    @classmethod
    def of_weights(cls, langs: list[str], weights: dict[str, np.ndarray]) -> LanguageModel:
        """The model of sorted languages and the weight rows of each task (``TOP`` or a family), in order."""
        model = cls()
        for lang in sorted(langs):
            model.families.setdefault(family_of(lang), []).append(lang)
        if len(model.families) > 1:
            model.top = weights[TOP]
        for f, members in model.families.items():
            pairs = list(combinations(range(len(members)), 2))
            model.pairs[f] = (pairs, weights[f] if pairs else np.zeros((0, SLOTS + 1), np.float32))
        return model

    def predict(self, texts: list[str]) -> tuple[list[str], list[float]]:
        """Language and score (0 to 1) of each text; undetermined with 0 where there is no letter or no model."""
        names, out, scores = list(self.families), [], []
        for text in texts:
            if not names or _LETTER.search(text) is None:
                out.append(UNDETERMINED)
                scores.append(0.0)
                continue
            x = np.append(features(text), np.float32(1))
            share = np.ones(1)
            if self.top is not None:
                margins = self.sharpness * (self.top @ x)
                share = np.exp(margins - margins.max())
                share /= share.sum()
            best = int(share.argmax())
            members = self.families[names[best]]
            pairs, rows = self.pairs[names[best]]
            votes, backing = np.zeros(len(members)), np.zeros(len(members))
            for (a, b), m in zip(pairs, rows @ x if pairs else (), strict=True):
                votes[a if m >= 0 else b] += 1
                p = 1 / (1 + np.exp(-2 * self.sharpness * m))
                backing[a] += p
                backing[b] += 1 - p
            chosen = max(range(len(members)), key=lambda k: (votes[k], backing[k], -k))
            inside = backing[chosen] / (len(members) - 1) if len(members) > 1 else 1.0
            out.append(members[chosen])
            scores.append(float(min(1.0, max(0.0, share[best] * inside))))
        return out, scores


def task_weights(task: str, x: np.ndarray, langs: list[str]) -> np.ndarray:
    """Weight rows of one task: a family against the rest for each (``TOP``), or every pair inside a family."""
    of = np.array(langs)
    if task == TOP:
        names = list(dict.fromkeys(family_of(v) for v in sorted(set(langs))))
        family = np.array([family_of(v) for v in langs])
        return np.array([linear_svm(x, np.where(family == f, 1.0, -1.0)) for f in names])
    rows = []
    for a, b in combinations(sorted(set(langs)), 2):
        own = (of == a) | (of == b)
        rows.append(linear_svm(x if own.all() else x[own], np.where(of[own] == a, 1.0, -1.0)))
    return np.array(rows)


def fit_language_model(
    docs: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang", per_language: int = 400, top_rows: int = 6400
) -> LanguageModel:
    """Fit on about ``per_language`` rows of each language (and a short window of each, for short texts).

    Each family's separators are fitted in a task of their own, on that family's rows; those between families
    in one more task, on about ``top_rows`` rows of all languages at most. The driver gets the weights only.
    Rows with null text or language are unused; without any the model is empty.
    """
    sample = bounded_sample(docs.where(F.col(text).isNotNull()), key, lang, per_language)

    def run(texts: list[str]) -> dict[str, list]:
        whole = [features(t).astype(np.float16).tobytes() for t in texts]
        middles = [len(t) // 3 for t in texts]
        short = [features(t[m : m + 40]).astype(np.float16).tobytes() for t, m in zip(texts, middles, strict=True)]
        return {"whole": whole, "short": short}

    rows = cut(map_texts(sample, [key, lang], text, "whole binary, short binary", run))
    langs = [r[0] for r in rows.select(lang).distinct().collect()]  # every value has at least one weight row
    members = Counter(map(family_of, langs))
    if not langs:
        return LanguageModel()
    quota = max(1, top_rows // (2 * len(langs)))
    jobs = []
    if len(members) > 1:
        draw = F.row_number().over(Window.partitionBy(lang).orderBy(F.xxhash64(key, F.lit("top")), key, "whole"))
        jobs.append(rows.withColumn("draw", draw).where(F.col("draw") <= quota).drop("draw").withColumn("task", F.lit(TOP)))
    family = F.create_map(*(F.lit(x) for v in langs for x in (v, family_of(v))))[F.col(lang)]
    large = [f for f, n in members.items() if n > 1]
    if large:
        jobs.append(rows.withColumn("task", family).where(F.col("task").isin(large)))

    def fit(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values([key, lang, "whole"])  # the fit does not depend on the partitions
        x = np.empty((2 * len(frame), SLOTS), np.float32)
        for at, data in enumerate([*frame["whole"], *frame["short"]]):
            x[at] = np.frombuffer(data, np.float16)
        task = str(frame["task"].iloc[0])
        return pd.DataFrame({"task": [task], "weights": [task_weights(task, x, frame[lang].tolist() * 2).tobytes()]})

    if not jobs:
        return LanguageModel.of_weights(langs, {})
    fitted = reduce(DataFrame.unionByName, jobs).groupBy("task").applyInPandas(fit, "task string, weights binary").collect()
    return LanguageModel.of_weights(langs, {r.task: np.frombuffer(r.weights, np.float32).reshape(-1, SLOTS + 1) for r in fitted})


def identify_language(
    docs: DataFrame, model: LanguageModel, key: str = "doc_id", text: str = "text", carry: tuple[str, ...] = ()
) -> DataFrame:
    """(key, carried columns, lang_pred, score) of every row, from the text alone.

    Null, empty and letterless texts are ``und`` with score 0; so is all if the model saw no row. Repeated
    rows stay. Ties of votes go to the larger summed probability, then to the first language by name.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)  # a few weight rows: bounded by the languages

    def run(texts: list[str]) -> dict[str, list]:
        langs, scores = shared.value.predict(texts)
        return {"lang_pred": langs, "score": scores}

    return map_texts(docs, [key, *carry], text, "lang_pred string, score double", run)


def predict_with_holdout(docs: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang", parts: int = 3, held: int = 1) -> DataFrame:
    """Fit on the rows outside the held-out fold, predict all rows: (key, held_out, lang_pred, score)."""
    model = fit_language_model(docs.where(fold(key, parts) != held), key, text, lang)
    made = identify_language(docs, model, key, text)
    return made.select(key, F.coalesce(fold(key, parts) == held, F.lit(False)).alias("held_out"), "lang_pred", "score")
