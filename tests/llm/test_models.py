import math
import random
import re
from collections import Counter

import numpy as np
import pytest

from spanfocus.llm import language_id as L
from spanfocus.llm import toxic_passages as T
from tests.llm.fixtures import edge_docs, no_docs


@pytest.fixture(scope="module")
def middle(spark):
    d = "/root/testdata/sf0.01"
    return spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")


def test_svm_separates():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(200, 5)).astype(np.float32)
    y = np.where(x[:, 0] + 0.5 * x[:, 1] > 0.1, 1.0, -1.0)
    w = L.linear_svm(x, y)
    assert (np.sign(x @ w[:-1] + w[-1]) == y).mean() > 0.97


def test_vote_equals_a_plain_one(spark, middle):
    """Family by the largest separator, then a vote of all pairs of its languages, spelled out."""
    docs, _ = middle
    model = L.fit_language_model(docs.where(L.fold("doc_id", 3) != 1))
    assert model.families == {"germanic": ["de", "en"], "romance": ["es", "fr"]}
    some = docs.limit(60).collect()
    found = {r.doc_id: r.lang_pred for r in L.identify_language(docs.limit(60), model).collect()}
    for r in some:
        if not any(c.isalpha() for c in r.text):
            assert found[r.doc_id] == "und"
            continue
        x = L.features(r.text).astype(float)
        sides = {f: float(w[:-1] @ x + w[-1]) for f, w in zip(model.families, model.top, strict=True)}
        family = max(sides, key=sides.get)
        votes = dict.fromkeys(model.families[family], 0)
        pairs, rows = model.pairs[family]
        for (a, b), w in zip(pairs, rows, strict=True):
            votes[model.families[family][a if float(w[:-1] @ x + w[-1]) >= 0 else b]] += 1
        assert found[r.doc_id] == max(votes, key=votes.get)


def test_ngram_windows(monkeypatch):
    text = "Straße und Häuser " * 40
    whole = L.ngram_counts(text)
    assert whole.sum() == 3 * len(text) - 3
    monkeypatch.setattr(L, "_WINDOW_CHARS", 50)
    parts = L.ngram_counts(text)
    # A window's two leading characters repeat shorter n-grams; the longest are counted once.
    assert abs(int(parts.sum()) - int(whole.sum())) <= 5 * (len(text) // 50 + 1)


def test_held_out_languages(spark, middle):
    docs, _ = middle
    rows = L.predict_with_holdout(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in rows if r.held_out]
    assert len(rows) == docs.count() and len(held) > 200
    assert np.mean([r.lang == r.lang_pred for r in held]) > 0.98
    assert all(0 <= r.score <= 1 for r in rows)


def test_language_edges(spark):
    docs = edge_docs(spark)
    rows = L.predict_with_holdout(docs).collect()
    assert len(rows) == docs.count()
    und = {r.doc_id for r in rows if r.lang_pred == "und"}
    assert und == {1, 2, 6, 8}
    assert L.predict_with_holdout(no_docs(spark)).count() == 0
    only = docs.where("lang = 'en'")
    assert {r.lang_pred for r in L.predict_with_holdout(only).collect()} <= {"en", "und"}


def plain_segments(scores):
    """Maximal segments by their definition: best segment first, then the same to its left and right."""
    best = None
    for a in range(len(scores)):
        total = 0.0
        for b in range(a, len(scores)):
            total += scores[b]
            if total > 1e-12 and (best is None or total > best[2] + 1e-9):
                best = (a, b, total)
    if best is None:
        return []
    a, b, total = best
    right = [(x + b + 1, y + b + 1, s) for x, y, s in plain_segments(scores[b + 1 :])]
    return plain_segments(scores[:a]) + [(a, b, total)] + right


def test_maximal_segments():
    rnd = random.Random(4)
    for _ in range(200):
        scores = [rnd.choice([1, 2, 3.5, 0.7]) + rnd.random() * 0.01 if rnd.random() < 0.35 else -0.5 for _ in range(rnd.randint(1, 30))]
        at = [i for i, s in enumerate(scores) if s > 0]
        found = T.maximal_segments(at, [scores[i] for i in at], 0.5)
        assert [(a, b, round(s, 6)) for a, b, s in found] == [(a, b, round(s, 6)) for a, b, s in plain_segments(scores)]


def test_monotone_fit():
    assert T._monotone([0.1, 0.5, 0.3, 0.9], [1, 1, 1, 1]) == [0.1, 0.4, 0.4, 0.9]


def test_held_out_toxicity(spark, middle):
    docs, labels = middle
    rows = T.predict_with_holdout(docs, labels).join(labels.select("doc_id", "toxic"), "doc_id").collect()
    held = [r for r in rows if r.held_out]
    hit = sum(r.predicted for r in held if r.toxic)
    wrong = sum(r.predicted for r in held if not r.toxic)
    assert hit >= 0.5 * sum(r.toxic for r in held) and wrong <= 0.03 * len(held)
    assert all((r.score >= 0.3) == bool(r.predicted) for r in rows)
    assert all(p.stop > p.start and p.nats > 0 for r in rows for p in r.passages)


def plain_log_odds(docs, labelled, prior=1.0, least_z=3.0):
    """Counts, prior, test and bound of the tokens, spelled out."""

    def tokens(text):
        words = set(re.findall(r"[^\W\d_]+", text.lower()))
        return words | {"^" + w[:n] for w in words for n in (4, 6) if len(w) > n}

    by = {0: Counter(), 1: Counter()}
    for text, mark in labelled:
        by[mark].update(tokens(text))
    corpus = Counter(t for text in docs for t in tokens(text))
    toxic, clean, total = (float(sum(c.values())) for c in (by[1], by[0], corpus))
    found = [t for t, n in by[1].items() if n >= 3 and n * clean > by[0][t] * toxic]
    bar, mass, out = max(least_z, math.sqrt(2 * math.log(len(found))) - 0.5), prior * toxic, {}
    for t in found:
        pseudo = max(corpus[t], by[1][t] + by[0][t]) / total * mass
        one, two = by[1][t] + pseudo, by[0][t] + pseudo
        delta = math.log(one / (toxic + mass - one)) - math.log(two / (clean + mass - two))
        spread = math.sqrt(1 / one + 1 / two)
        if delta > 0 and delta >= bar * spread:
            out[t] = delta - spread
    return out, sum(by[0][t] + 0.5 for t in out) / clean


def test_log_odds_equal_plain_ones(spark, middle, monkeypatch):
    docs, labels = middle
    sample = docs.select("doc_id", "text").join(labels.select("doc_id", "toxic"), "doc_id")
    expected, rate = plain_log_odds([r.text for r in docs.collect()], [(r.text, r.toxic) for r in sample.collect()])
    assert len(expected) > 10
    for sent in (T.SENT, 0):
        monkeypatch.setattr(T, "SENT", sent)
        gain, found = T.log_odds(docs, sample, "text", "toxic")
        assert gain == pytest.approx(expected) and found == pytest.approx(rate)


def test_calibration_equals_a_plain_one(spark, middle):
    docs, labels = middle
    sample = docs.join(labels.select("doc_id", "toxic"), "doc_id").dropDuplicates(["text", "toxic"])
    model = T.fit_toxicity(docs, labels)
    gains, rate = plain_log_odds([r.text for r in docs.collect()], [(r.text, r.toxic) for r in sample.collect()])
    assert model.gain == pytest.approx(gains)
    # lambda: the expected exponential score of a clean token is one.
    mean = sum(rate / len(gains) * math.exp(model.decay * g) for g in gains.values()) + (1 - rate) * math.exp(-model.decay * model.penalty)
    assert mean == pytest.approx(1, abs=1e-6)
    best = [model.best_segment(r.text) for r in sample.where("toxic = 0").collect()]
    over = [model.decay * s - math.log(n) for n, s in best if s > 0 and n > 1]
    assert model.log_k == pytest.approx(sum(over) / len(over) - 0.5772156649, abs=1e-6)
    assert model.curve_y == sorted(model.curve_y) and model.curve_x == sorted(model.curve_x)


def test_passages_are_found():
    model = T.ToxicityModel(gain={"idiot": 4.0, "scum": 4.0}, penalty=0.5, decay=1.0, log_k=0.0)
    text = "calm words here " * 3 + "you idiot absolute SCUM idiot " + "more calm words " * 3
    raw, found = model.analyse(text)
    assert len(found) == 1 and text[found[0].char_start : found[0].char_stop] == "idiot absolute SCUM idiot"
    assert raw == pytest.approx(found[0].nats) and model.analyse("calm words") == (-20.0, [])


def test_long_text_equals_short(monkeypatch):
    model = T.ToxicityModel(gain={"idiot": 4.0}, penalty=0.1)
    text = ("quiet words and so on " * 20 + "idiot idiot ") * 10
    whole = model._tokens(text)
    monkeypatch.setattr(T, "_HELD", 13)
    assert model._tokens(text) == whole


def test_toxicity_edges(spark):
    docs = edge_docs(spark)
    for rows in ([], [(2, 0)], [(2, 1), (3, 0), (3, 1), (99, None), (None, 1)]):
        labels = spark.createDataFrame(rows, "doc_id bigint, toxic int")
        made = T.predict_with_holdout(docs, labels).collect()
        assert len(made) == docs.count() and all(0 <= r.score <= 1 for r in made)
    assert T.predict_with_holdout(no_docs(spark), spark.createDataFrame([], "doc_id bigint, toxic int")).count() == 0
