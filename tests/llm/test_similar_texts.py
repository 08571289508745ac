import random

import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline as P
from spanfocus.llm import near_copies
from spanfocus.llm import similar_texts as S
from tests.llm.fixtures import no_docs

KINDS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def plain_roots(texts, words=5, least=0.8):
    def shingles(t):
        w = (t or "").lower().split()
        return {" ".join(w[i : i + words]) for i in range(max(1, len(w) - words + 1))}

    sets, roots = [shingles(t) for t in texts], list(range(len(texts)))

    def root(i):
        while roots[i] != i:
            i = roots[i]
        return i

    for a in range(len(texts)):
        for b in range(a):
            if len(sets[a] & sets[b]) >= least * len(sets[a] | sets[b]) - 1e-9:
                x, y = root(a), root(b)
                roots[max(x, y)] = min(x, y)
    return [root(i) for i in range(len(texts))]


def edited(rnd, words, n):
    out = list(words)
    for i in rnd.sample(range(len(out)), n):
        out[i] = f"new{rnd.random()}"
    return out


def planted():
    rnd, texts = random.Random(4), ["", None, " ", "one two", "One  two", "one two three"]
    for _ in range(12):
        base = [f"w{rnd.randrange(900)}" for _ in range(rnd.randint(60, 200))]
        texts += [" ".join(edited(rnd, base, n)) for n in (0, 1, 1, 2, 3, 4, 6, 12)]
        texts.append(" ".join(base[: len(base) * 9 // 10]))
    line = [f"common{i}" for i in range(30)]
    texts += [" ".join([*line, *(f"x{rnd.random()}" for _ in range(20))]) for _ in range(40)]
    return texts


def test_groups_equal_brute_force(spark, monkeypatch):
    texts = planted()
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id bigint, text string")
    wanted = {}
    for t, r in zip(texts, plain_roots(texts), strict=True):
        wanted.setdefault(r, set()).add(t or "")
    for prints, sets in ((S.BLOCK_PRINTS, S.BLOCK_SETS), (5, 3)):
        monkeypatch.setattr(S, "BLOCK_PRINTS", prints)
        monkeypatch.setattr(S, "BLOCK_SETS", sets)
        groups, names = {}, {i: t or "" for i, t in enumerate(texts)}
        for r in S.similar_text_groups(docs).collect():
            groups.setdefault(r.root, set()).add(names[r.first_id])
        assert sorted(map(sorted, groups.values())) == sorted(map(sorted, wanted.values()))
    assert S.similar_text_groups(no_docs(spark)).count() == 0


def test_intersections_by_columns(monkeypatch):
    rng = np.random.default_rng(5)
    sets = [np.unique(rng.integers(0, 300, n)) for n in (1, 40, 90, 90, 200, 3)]
    monkeypatch.setattr(S, "_COLUMNS", 7)
    assert S.shared_counts(sets).tolist() == [[len(np.intersect1d(a, b)) for b in sets] for a in sets]


def test_stage_drops_copies_beyond_three_bits(spark, sf):
    texts = planted()
    docs = spark.createDataFrame([(i, t, "en", "src0", 1) for i, t in enumerate(texts)], KINDS)
    left = P.distinct(spark, docs, sf).collect()
    assert sorted(r.doc_id for r in left) == sorted(set(plain_roots(texts)))


def test_a_common_line_makes_no_neighbourhood(spark, monkeypatch):
    """Only texts that are alike are dealt out for comparison, however many others hold their line."""
    rnd, line, dealt = random.Random(6), [f"common{i}" for i in range(14)], []
    texts = [" ".join([*line, *(f"x{rnd.random()}" for _ in range(rnd.randint(16, 60)))]) for _ in range(1500)]
    texts += [" ".join(edited(rnd, texts[0].split(), 1)) for _ in range(3)]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id bigint, text string")
    verified = S._verified
    monkeypatch.setattr(S, "_verified", lambda rows, least: dealt.append(rows.count()) or verified(rows, least))
    monkeypatch.setattr(S, "BLOCK_SETS", 100)
    S.similar_text_groups(docs).count()
    assert dealt[0] < 100


def test_joins_of_growing_tables_are_not_broadcast(spark, sf):
    """A small estimate, as of rows made from few bytes, sends nothing through the driver."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    fps = spark.range(100).select(F.col("id").alias("fp"))
    for made in (near_copies.links(fps), P.distinct(spark, docs, sf), P.mixed(spark, docs, sf)):
        made.collect()
        assert "BroadcastHashJoin" not in made._jdf.queryExecution().executedPlan().toString()
