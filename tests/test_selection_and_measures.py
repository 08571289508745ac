import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from spanfocus.functions import published
from spanfocus.geometry import Geometry
from spanfocus.operators import lm, measures, ranks, relational, samples, select, trained

SCORED = "doc_id bigint, domain string, n_tokens int, score double"


def scored(spark, n=300, seed=1):
    rnd = random.Random(seed)
    return spark.createDataFrame([(i, rnd.choice(["a", "a", "b", "c"]), rnd.randint(1, 40), rnd.choice([0.1, 0.2, rnd.random(), rnd.random() * 1e-8])) for i in range(n)], SCORED)


def plain_selection(rows, budget):
    total, by = sum(r.n_tokens for r in rows), {}
    for r in rows:
        by.setdefault(r.domain, []).append(r)
    exact = {d: round(budget * sum(r.n_tokens for r in rs) / total, 6) for d, rs in by.items()}
    quota = {d: int(x) for d, x in exact.items()}
    rest = budget - sum(quota.values())
    for d in sorted(exact, key=lambda d: (-round(exact[d] - quota[d], 6), d))[: max(0, rest)]:
        quota[d] += 1
    out = set()
    for d, rs in by.items():
        run = 0
        for r in sorted(rs, key=lambda r: (-round(r.score, 6), r.doc_id)):
            run += r.n_tokens
            if run > quota[d]:
                break
            out.add(r.doc_id)
    return out


@pytest.mark.parametrize("share", [0.0, 0.3, 0.77, 1.0, 5.0])
def test_budget_selection_equals_plain_and_threshold(spark, share):
    df = scored(spark)
    rows = df.collect()
    budget = int(sum(r.n_tokens for r in rows) * share)
    expected = plain_selection(rows, budget)
    made = select.select_by_domain(df, budget)
    assert {r.doc_id for r in made.collect()} == expected
    assert made.agg(F.coalesce(F.sum("n_tokens"), F.lit(0))).first()[0] <= budget
    assert {r.doc_id for r in select.select_by_threshold(df, budget).collect()} == expected


def test_selection_of_heavy_tails_and_ties(spark):
    """One far outlier and many equal scores: ranges of rows, not of values, so both ways agree with the plain one."""
    rows = [(i, "a" if i % 3 else "b", 1 + i % 5, 1e9 if i == 7 else 0.0 if i % 2 else i / 1000) for i in range(900)]
    df = spark.createDataFrame(rows, SCORED).repartition(5)
    for share in (0.1, 0.6):
        budget = int(sum(r[2] for r in rows) * share)
        expected = plain_selection(df.collect(), budget)
        made = select.select_by_domain(df, budget)
        assert {r.doc_id for r in made.collect()} == expected == {r.doc_id for r in select.select_by_threshold(df, budget).collect()}
        placed = made.orderBy("domain", "domain_rank").collect()
        for d in "ab":
            assert [r.domain_rank for r in placed if r.domain == d] == list(range(1, 1 + sum(r.domain == d for r in placed)))


def test_medians_of_large_groups(spark):
    rnd = random.Random(3)
    rows = [("heavy", rnd.random() ** 30 * 1e6) for _ in range(3000)] + [("ties", rnd.choice([1.0, 1.0, 2.0])) for _ in range(2001)]
    rows += [("even", float(i)) for i in range(500)] + [("one", 4.0), ("none", None)]
    df = spark.createDataFrame(rows, "g string, v double")
    expected = {r.g: r.v for r in df.groupBy("g").agg(F.median("v").alias("v")).collect()}
    for most in (10**6, 40):
        found = {r.g: (r.n, r.v) for r in ranks.exact_medians(df, ["g"], ["v"], most).collect()}
        assert {g: v for g, (_, v) in found.items()} == expected
        assert found["heavy"][0] == 3000 and found["none"][0] == 1


def test_selection_edges(spark):
    none = scored(spark).where("false")
    assert select.select_by_domain(none, 100).count() == 0 and select.select_by_threshold(none, 100).count() == 0
    same = spark.createDataFrame([(i, "a", 1, 0.5) for i in (5, 3, 9)], SCORED)
    assert [r.doc_id for r in select.select_by_domain(same, 2).orderBy("domain_rank").collect()] == [3, 5]
    assert [r.doc_id for r in select.select_top(same, 2).collect()] == [3, 5]
    with pytest.raises(ValueError):
        select.select_by_domain(same.drop("score"), 2)


def test_random_selection_keeps_the_mix(spark):
    df = scored(spark, 2000)
    total = df.agg(F.sum("n_tokens")).first()[0]
    one, two = (select.select_random(df, total // 4, s) for s in (1, 2))
    assert {r.doc_id for r in one.collect()} != {r.doc_id for r in two.collect()}
    whole = {r.domain: r.share for r in select.mix(df).collect()}
    assert all(abs(r.share - whole[r.domain]) < 0.01 for r in select.mix(one).collect())
    assert select.overlap(one, one).first().jaccard == 1.0


def test_rank_limit_reaches_below_the_shuffle(spark):
    plan = select.select_per_domain(scored(spark), 3)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan


def test_scan_is_pruned_and_kernel_not_shuffled(spark, sf):
    from spanfocus.operators import lexical

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    g = Geometry.named("smoke")
    plan = lexical.score_documents(samples.samples(docs, g), lexical.weight_table(docs), g)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "lang" not in plan.split("ReadSchema")[1].split(">")[0]
    assert "GreaterThanOrEqual(n_chars,511)" in plan


def test_perplexity_by_hand(spark):
    train = spark.createDataFrame([(1, list("abab")), (2, list("ac"))], "doc_id bigint, tokens array<string>")
    model = lm.fit_lm(train)
    assert (model.total, model.vocabulary) == (6, 3)
    test = spark.createDataFrame([(9, list("abz"))], "doc_id bigint, tokens array<string>")
    made = {(r.model, r.window): r.ppl for r in lm.perplexity(test, model, (2, 3, 9)).collect()}
    pu = {"a": 4 / 10, "b": 3 / 10, "z": 1 / 10}
    assert made[("unigram", 3)] == pytest.approx((pu["a"] * pu["b"] * pu["z"]) ** (-1 / 3))
    second = (2 + 50 * pu["b"]) / (3 + 50)
    assert made[("bigram", 2)] == pytest.approx((pu["a"] * second) ** -0.5)
    assert made[("unigram_cache", 2)] == pytest.approx((pu["a"] * (0.8 * pu["b"] + 0.2 * 0)) ** -0.5)
    assert ("unigram", 9) not in made


def test_perplexity_in_one_pass_equals_joins(spark, sf):
    docs = samples.tokenize(spark.read.parquet(f"{sf}/documents.parquet")).where("n_tokens >= 1").select("doc_id", "tokens")
    chosen = {"odd": docs.where("doc_id % 2 = 1"), "few": docs.where("doc_id % 7 = 1"), "none": docs.where("false")}
    test = docs.where("doc_id % 2 = 0")
    one, two = ({(r.method, r.model, r.window): (r.n_docs, r.ppl) for r in lm.perplexities(chosen, test, (1, 16, 64), most).collect()} for most in (lm.MAX_COUNTS, 0))
    assert len(one) == 3 * 4 * 3 and one.keys() == two.keys()
    assert all(one[k][0] == two[k][0] and one[k][1] == pytest.approx(two[k][1]) for k in one)


def test_longer_windows_help_a_cache(spark, sf):
    docs = samples.tokenize(spark.read.parquet(f"{sf}/documents.parquet")).where("n_tokens >= 256").select("doc_id", "tokens")
    made = {(r.model, r.window): r.ppl for r in lm.perplexity(docs.where("doc_id % 2 = 0"), lm.fit_lm(docs.where("doc_id % 2 = 1")), (64, 256)).collect()}
    assert made[("unigram_cache", 256)] < made[("unigram", 256)] and made[("bigram_cache", 64)] < made[("bigram", 64)]


def test_published_arithmetic(spark):
    made = measures.improvement(measures.task_rollup(published.task_scores(spark)), "dependency", "delta")
    gain = {(r.model, r.category): r.gain for r in made.collect()}
    assert gain[("mean", "overall")] == pytest.approx(2.16, abs=0.01)
    assert gain[("M-7B", "single_doc")] == pytest.approx(10.09, abs=0.01) and gain[("M-7B", "multi_doc")] == pytest.approx(4.66, abs=0.01)
    two = {(r[0], r[1], r[2], r[3]): r[4] for r in published.budget_rows()}
    assert two[("L-7B", "dependency", "1B", "overall")] - two[("L-7B", "random", "2B", "overall")] == pytest.approx(1.31)
    assert two[("M-7B", "dependency", "1B", "overall")] - two[("M-7B", "random", "2B", "overall")] == pytest.approx(2.27)


def test_needles_are_found(spark, sf):
    from spanfocus.plans.workloads import lexical_hits

    g = Geometry.named("desk")
    hay = samples.samples(spark.read.parquet(f"{sf}/documents.parquet"), g)
    assert lexical_hits(spark, sf, hay).agg(F.avg("hit")).first()[0] > 0.95


def test_needle_layout(spark):
    g = Geometry(64, 4, 1, 2, 1, 1, 2)
    hay = spark.createDataFrame([(1, [f"h{i}" for i in range(64)])], "doc_id bigint, tokens array<string>")
    pins = spark.createDataFrame([(7, "p1 p2 p3 p4 p5 p6 p7 p8 p9"), (8, "too short")], "item_id bigint, text string")
    rows = measures.needle_cases(hay, pins, g, lengths=(16, 32, 64), depths=(0.0, 1.0)).collect()
    assert {r.context_len for r in rows} == {32, 64}
    for r in rows:
        t = r.tokens
        assert len(t) == r.context_len and t[-4:] == ["p1", "p2", "p3", "p4"] and r.needle_spans == 2
        assert t[r.needle_span * 4 : r.needle_span * 4 + 8] == [f"p{i}" for i in range(1, 9)]
        assert r.needle_span >= 1 and r.needle_span + 2 <= r.n_spans - 1 - 2
    with pytest.raises(ValueError):
        measures.needle_cases(hay, pins.where("false"), g)


def test_answer_scores(spark):
    rows = [("a b c", "a c d"), ("", ""), ("same", "same"), ("x", None), ("the cat sat", "cat the sat")]
    df = spark.createDataFrame(rows, "a string, b string")
    made = df.select(measures.token_f1(F.col("a"), F.coalesce("b", F.lit(""))).alias("f"), measures.rouge_l("a", "b").alias("r"), measures.edit_similarity(F.col("a"), F.coalesce("b", F.lit(""))).alias("e"), measures.exact_match(F.col("a"), F.coalesce("b", F.lit(""))).alias("x")).collect()
    assert [round(r.f, 4) for r in made] == [0.6667, 0.0, 1.0, 0.0, 1.0]
    assert [round(r.r, 4) for r in made] == [0.6667, 0.0, 1.0, 0.0, 0.6667]
    assert [round(r.e, 4) for r in made] == [round(1 - 3 / 5, 4), 1.0, 1.0, 0.0, round(1 - 6 / 11, 4)] or made[0].e == pytest.approx(0.6)
    assert [r.x for r in made] == [0, 1, 1, 0, 0]


def plain_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def test_edit_similarity_of_long_texts(spark):
    rnd = random.Random(2)
    rows = [("".join(rnd.choice("abcé ") for _ in range(rnd.randint(1, 150))), "".join(rnd.choice("abcé ") for _ in range(rnd.randint(1, 150)))) for _ in range(20)]
    made = spark.createDataFrame(rows, "a string, b string").select("a", "b", measures.edit_similarity(F.col("a"), F.col("b")).alias("e")).collect()
    assert all(r.e == pytest.approx(1 - plain_distance(r.a, r.b) / max(len(r.a), len(r.b))) for r in made)


def test_label_agreement_by_hand(spark):
    df = spark.createDataFrame([(1, 0.1), (2, 0.5), (3, 0.5), (4, 0.9)], "doc_id bigint, score double")
    labels = spark.createDataFrame([(1, 0), (2, 0), (3, 1), (4, 1)], "doc_id bigint, quality int")
    assert measures.label_agreement(df, labels).first().auc == pytest.approx((1 + 0.5 + 1 + 1) / 4)


def test_correlation_with_itself(spark):
    df = spark.createDataFrame([(i, float(i % 7), float(-i)) for i in range(50)], "doc_id bigint, a double, b double")
    made = {r.setting: r for r in measures.score_correlation(df, "a", ["a", "b"], 10).collect()}
    assert made["a"].pearson == pytest.approx(1) and made["a"].overlap_at_n == 1.0 and made["b"].pearson < 1


def test_gradient_is_right():
    c = trained.Calculator.fresh(trained.Config(vocabulary=7, dim=4, heads=2))
    ids = np.random.default_rng(1).integers(0, 7, 9)
    loss, grad = trained.loss_and_gradient(c, ids)
    for name, w in c.weights.items():
        for at in [(0, 0), (3, 2), (1, 3)]:
            old = w[at]
            w[at] = old + 1e-5
            up = trained.loss_and_gradient(c, ids)[0]
            w[at] = old - 1e-5
            down = trained.loss_and_gradient(c, ids)[0]
            w[at] = old
            assert grad[name][at] == pytest.approx((up - down) / 2e-5, abs=1e-5)


def test_rotary_depends_on_distance():
    x = np.random.default_rng(1).normal(size=(1, 6))
    turned = trained.rotate(np.repeat(x, 20, axis=0), trained.rotary_phase(20, 6, 10_000.0))
    assert turned[3] @ turned[8] == pytest.approx(turned[11] @ turned[16])


def test_training_learns_and_repeats(spark, tmp_path):
    rnd = random.Random(3)
    rows = []
    for i in range(24):
        t = [rnd.choice("abcdefgh") for _ in range(16)]
        rows.append((i + 1, t * 3))
    df = spark.createDataFrame(rows, "place int, tokens array<string>")
    config = trained.Config(vocabulary=64, dim=16)
    one = trained.train_calculator(df, config, rounds=4)
    again = trained.train_calculator(df.repartition(5), config, rounds=4)
    assert np.mean(one.losses[-3:]) < np.mean(one.losses[:3]) and one.tokens_seen == 4 * 24 * 48
    assert all((one.weights[n] == again.weights[n]).all() for n in one.weights)
    spread = trained.train_calculator(df.limit(8), config, rounds=1, distributed=True)
    local = trained.train_calculator(df.limit(8), config, rounds=1)
    assert all(np.allclose(spread.weights[n], local.weights[n]) for n in local.weights)
    # One group that trains apart is the local way; several learn as well, whatever the partitions.
    alone = trained.train_calculator(df, config, rounds=2, groups=1)
    whole = trained.train_calculator(df, config, rounds=2)
    assert all(np.allclose(alone.weights[n], whole.weights[n]) for n in whole.weights) and alone.tokens_seen == whole.tokens_seen
    apart, same = (trained.train_calculator(d, config, rounds=6, groups=3) for d in (df, df.repartition(5)))
    assert apart.losses[-1] < apart.losses[0] and all((apart.weights[n] == same.weights[n]).all() for n in apart.weights)
    trained.save_calculator(spark, one, str(tmp_path / "w"))
    back = trained.load_calculator(spark, str(tmp_path / "w"))
    assert back.config == one.config and all(np.allclose(one.weights[n], back.weights[n]) for n in one.weights)
    assert back.with_rotary_base(5e5).config.rotary_base == 5e5


def test_close_pairs_equal_brute_force_without_pairs_of_rows(spark):
    rng = random.Random(3)
    rows = [(rng.choice([None, *range(40)]), rng.choice(["a", "b", None]), rng.choice([None, float("nan"), float("inf"), -0.0, *(n / 10 for n in range(-60, 60, 5))])) for _ in range(300)]
    df = spark.createDataFrame(rows, "k bigint, g string, v double")
    want = {}
    for k, g, v in rows:
        for m, h, w in rows:
            if None not in (k, g, v, m, h, w) and g == h and k < m and abs(v - w) <= 5:
                want[g] = want.get(g, 0) + 1
    assert dict(relational.close_pairs(df, "g", "k", "v", 5).collect()) == want
    # Half a million rows of two prices: over 10^11 pairs, counted without making one.
    many = spark.range(500_000).select(F.col("id").alias("k"), F.lit("a").alias("g"), (F.col("id") % 2).cast("double").alias("v"))
    assert [tuple(r) for r in relational.close_pairs(many, "g", "k", "v", 5).collect()] == [("a", 500_000 * 499_999 // 2)]


def test_gradients_do_not_depend_on_blocks(monkeypatch):
    ids, c, made = np.random.default_rng(5).integers(0, 512, 150), trained.Calculator.fresh(), []
    for block in (1_000, 64, 7):
        monkeypatch.setattr(trained, "_BLOCK", block)
        made.append(trained.loss_and_gradient(c, ids))
    for loss, grad in made[1:]:
        assert loss == pytest.approx(made[0][0]) and all(np.allclose(grad[n], made[0][1][n], atol=1e-12) for n in grad)
