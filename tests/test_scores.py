"""Hand example, invariants, planted orderings and equivalences of the scores."""

import random
import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from spanfocus.geometry import PROFILES, Geometry, cost_of
from spanfocus.operators import delta, focus, lexical, samples, states, trained
from spanfocus.operators.focus import VARIANTS, fold_matrix

DESK = Geometry.named("desk")


def codes(tokens):
    names = {t: i for i, t in enumerate(dict.fromkeys(tokens))}
    return np.array([names[t] for t in tokens], np.int64)


def lexical_score(tokens, gain, g, variant="full"):
    rows = g.rows()
    mass = lexical.focus_matrix(codes(tokens), np.full(len(tokens), np.exp(gain) - 1), g, rows)
    return fold_matrix(mass, rows, g, variant)


def dense(tokens, gain, g, j, causal=True):
    """Softmax row by row, token by token."""
    out = np.zeros(g.n_spans)
    for p in range(j * g.span, (j + 1) * g.span):
        last = p + 1 if causal else (j + 1) * g.span
        logits = np.array([gain if tokens[k] == tokens[p] else 0.0 for k in range(last)])
        soft = np.exp(logits) / np.exp(logits).sum()
        for k in range(last):
            out[k // g.span] += soft[k]
    return out


def test_hand_example(spark):
    g = Geometry(8, 2, 0, 1, 1, 1, 2)
    tokens, gain = list("abcabdab"), np.log(3)
    mass = lexical.focus_matrix(codes(tokens), np.full(8, 2.0), g, [1, 2, 3])
    expected = {(0, 1): 9 / 10, (0, 2): 25 / 36, (1, 2): 17 / 36, (0, 3): 54 / 91, (1, 3): 41 / 91, (2, 3): 40 / 91}
    for (i, j), v in expected.items():
        assert mass[i, j - 1] == pytest.approx(v)
    assert lexical_score(tokens, gain, g) == pytest.approx(0.0359105181)
    df = spark.createDataFrame([(1, "s", 8, tokens)], "doc_id bigint, domain string, n_tokens int, tokens array<string>")
    weights = spark.createDataFrame([(t, 2.0) for t in "abcd"], "token string, weight double")
    rows = focus.span_focus(lexical.pair_focus(df, weights, g), g)
    found = {r.j: (r.sigma, r.span_focus) for r in rows.collect()}
    assert found[2] == (0.0, 0.0) and found[3] == (pytest.approx(1 / 14), pytest.approx(0.0478806907))
    assert focus.dependency(rows, g).first().dependency == pytest.approx(0.0359105181)


@pytest.mark.parametrize("causal", [True, False])
def test_sparse_equals_dense(causal):
    rnd, g = random.Random(3), Geometry(64, 4, 1, 2, 1, 1, 2)
    tokens = [rnd.choice("abcdefgh") for _ in range(64)]
    mass = lexical.focus_matrix(codes(tokens), np.full(64, np.exp(1.5) - 1), g, g.rows(), causal)
    for k, j in enumerate(g.rows()):
        row = dense(tokens, 1.5, g, j, causal)
        assert np.allclose(mass[: j + 1, k], row[: j + 1], atol=1e-12)
        assert row.sum() == pytest.approx(g.span) and mass[: j + 1, k].sum() == pytest.approx(g.span)


def noise():
    return [f"n{i}" for i in range(512)]


def echo(pairs, shuffle=False):
    """Noise whose span j repeats span i, for (j, i) in pairs."""
    t = noise()
    for j, i in pairs:
        part = t[i * 8 : i * 8 + 8]
        t[j * 8 : j * 8 + 8] = part
    return t


ROWS = (44, 48, 52, 56, 60)
PLANTED = {
    "noise": noise(),
    "constant": ["x"] * 512,
    "far": echo([(j, j - 43) for j in ROWS]),
    "near": echo([(j, j - 7) for j in ROWS]),
    "early": echo([(j, j - 7) for j in range(16, 48, 4)]),
    "same": echo([(j, 9) for j in ROWS]),
    "half": noise()[:256] * 2,
}


def score(name, variant="full", g=DESK):
    return lexical_score(PLANTED[name], 4.0, g, variant)


def test_planted_orderings():
    assert score("far") == pytest.approx(1.103819, abs=1e-5) and score("near") == pytest.approx(0.682152, abs=1e-5)
    assert score("far") > score("same") > score("near") > score("noise")
    assert score("noise") == pytest.approx(0, abs=1e-9) and score("constant") == pytest.approx(0, abs=1e-9)
    # The deviation weight: without it a constant text beats a real echo.
    assert score("constant") < score("near") and score("constant", "flat_sigma") > score("near", "flat_sigma")
    # The length weights: without them many early near echoes beat far ones.
    assert score("far") > score("early") and score("far", "flat_length") < score("early", "flat_length")


def test_stride_aliasing():
    """With both strides 4 only distances of 3 modulo 4 are seen; a phase or a row stride of 1 sees the rest."""
    assert score("half") == pytest.approx(0, abs=1e-9)
    assert score("half", g=DESK.with_strides(1, 4)) > 1 and score("half", g=DESK.with_strides(4, 1)) > 1
    assert score("half", g=Geometry(512, 8, 1, 4, 4, 4, 16, row_phase=3)) > 0


def test_cost_counters():
    table = {("desk", 4, 4): (12, 102, 29952), ("desk", 2, 2): (24, 420, 61440), ("paper", 4, 4): (60, 1950, 132710400), ("paper", 2, 4): (60, 3900, 132710400), ("paper", 4, 2): (120, 3960, 267386880)}
    for (p, a, b), v in table.items():
        assert tuple(cost_of(Geometry.named(p).with_strides(a, b)).values()) == v
    assert PROFILES["paper"].n_spans == 256


def test_geometry_is_checked():
    for bad in ({"length": 10, "span": 3}, {"row_stride": 0}, {"skip_first": -1}):
        with pytest.raises(ValueError):
            Geometry(**bad)
    with pytest.raises(ValueError):
        Geometry.named("no such profile")
    assert Geometry(64, 8, first_row=16).rows() == []


def test_options_of_the_deviation():
    g, rows = Geometry(64, 4, 1, 2, 3, 2, 4), Geometry(64, 4, 1, 2, 3, 2, 4).rows()
    mass = np.random.default_rng(1).random((16, len(rows)))
    by_hand = 0.0
    for k, j in enumerate(rows):
        c = g.cols(j)
        v = mass[c, k]
        sd = np.std(v, ddof=1) if len(v) > 1 else 0
        by_hand += sd * sum((j - i) / 16 * mass[i, k] for i in c) * j / 16
    assert fold_matrix(mass, rows, g, ddof=1) == pytest.approx(by_hand)
    assert fold_matrix(mass, rows, g, sigma_over="all") != fold_matrix(mass, rows, g)


def edge_table(spark):
    texts = {1: None, 2: "", 3: "w " * 511, 4: "w " * 512, 5: "ünï çödé " * 400, 6: " ".join(f"t{i}" for i in range(600)), 7: "a b c d " * 128 + "e f g h " * 64}
    return spark.createDataFrame([(i, t, "s") for i, t in texts.items()], "doc_id bigint, text string, source string")


def test_edge_rows_and_paths_agree(spark):
    docs = edge_table(spark)
    rows = samples.samples(docs, DESK)
    assert sorted(r.doc_id for r in rows.collect()) == [4, 5, 6, 7]
    table = lexical.weight_table(docs)
    kernel = {r.doc_id: r for r in lexical.score_documents(rows, table, DESK, tuple(VARIANTS), [(4, 4), (2, 2)]).collect()}
    for v in VARIANTS:
        pairs = lexical.pair_focus(rows, lexical.token_weights(docs), DESK)
        made = focus.dependency(focus.span_focus(pairs, DESK, v), DESK, v, rows)
        for r in made.collect():
            assert r.dependency == pytest.approx(kernel[r.doc_id][f"{v}_4_4"], abs=1e-9)
    assert kernel[4].full_4_4 == pytest.approx(0, abs=1e-9) and kernel[4].logits == 29952
    none = rows.where("false")
    assert lexical.score_documents(none, table, DESK).count() == 0
    with pytest.raises(ValueError):
        samples.samples(docs.drop("source"), DESK)
    with pytest.raises(ValueError):
        lexical.score_documents(rows, table, DESK, ("no such variant",))


def test_folded_weights_stay_close(spark):
    docs = edge_table(spark)
    exact, folded = lexical.weight_table(docs), lexical.weight_table(docs, max_exact=10, slots=1 << 16)
    h = np.array([r[0] for r in docs.select(F.explode(F.transform(F.split("text", " "), lambda t: F.xxhash64(t)))).distinct().collect()], np.int64)
    assert folded.slots and np.mean(np.isclose(folded.of(h), exact.of(h)) | (exact.of(h) == 0)) > 0.95


def test_scores_do_not_depend_on_partitions(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    g = Geometry.named("smoke")
    table = lexical.weight_table(docs)
    one, many = (dict(lexical.score_documents(samples.samples(docs.repartition(n), g), table, g).select("doc_id", "full_2_2").collect()) for n in (1, 7))
    assert one == many


def test_states_equal_brute_force():
    rng, g = np.random.default_rng(2), Geometry(24, 4, 0, 0, 1, 1, 1)
    q, k = rng.normal(size=(2, 24, 5))
    for causal in (True, False):
        mass = states.state_focus(q, k, g, g.rows(), causal)
        for at, j in enumerate(g.rows()):
            row = np.zeros(6)
            for p in range(j * 4, j * 4 + 4):
                last = p + 1 if causal else (j + 1) * 4
                e = np.exp([q[p] @ k[c] / np.sqrt(5) for c in range(last)])
                for c in range(last):
                    row[c // 4] += e[c] / e.sum()
            assert np.allclose(mass[:, at], row)
    heads = rng.normal(size=(3, 24, 5))
    each = [states.state_focus(h, h, g, g.rows()) for h in heads]
    for how, want in (("mean", np.mean(each, axis=0)), ("max", np.max(each, axis=0)), ("last", each[2]), ([0, 1], np.mean(each[:2], axis=0))):
        assert np.allclose(states.merge_heads(heads, heads, g, g.rows(), heads=how), want)


def test_external_model_hook(spark):
    rows = samples.samples(edge_table(spark), DESK)

    def model(tokens):
        x = np.array([[len(t), ord(t[0]) % 7, 1.0] for t in tokens])[None]
        return x, x

    made = states.score_with_model(rows, model, DESK, ("full", "flat_sigma"))
    assert made.count() == 4 and made.columns == ["doc_id", "domain", "n_tokens", "full", "flat_sigma"]


def test_delta_by_hand():
    h, p = np.array([1, 2, 1, 3]), np.array([0.4, 0.3, 0.4, 0.1])
    alone, given, gain = delta.delta_matrix(h, p, delta.DeltaOptions(segment=2))
    assert alone[1] == pytest.approx((0.4 * 0.1) ** -0.5)
    assert given[0, 1] == pytest.approx(((0.2 + 0.25) * 0.05) ** -0.5)
    assert gain[0, 1] == pytest.approx(alone[1] - given[0, 1]) and gain[1, 0] == 0
    relative = delta.delta_matrix(h, p, delta.DeltaOptions(segment=2, strength="relative"))[2]
    assert relative[0, 1] == pytest.approx(gain[0, 1] / alone[1])
    assert delta.delta_matrix(h, p, delta.DeltaOptions(segment=2, threshold=1e9))[2].sum() == 0
    special = delta.delta_matrix(np.array([1, 2, 1, 1]), p, delta.DeltaOptions(segment=2, specificity=True))[2]
    assert special[0, 1] == pytest.approx(delta.delta_matrix(np.array([1, 2, 1, 1]), p, delta.DeltaOptions(segment=2))[2][0, 1] / 2)


def test_gains_equal_the_dense_form_in_little_memory():
    rng = np.random.default_rng(3)

    def dense(h, p, o):
        n = len(h) // o.segment
        c = np.unique(h, return_inverse=True)[1][: n * o.segment].reshape(n, o.segment)
        given = np.empty((n, n))
        for i in range(n):
            for j in range(n):
                times = (c[i][:, None] == c[j][None, :]).sum(axis=0)
                given[i, j] = np.exp(-np.log((1 - o.mix) * p[j * o.segment : (j + 1) * o.segment] + o.mix * times / o.segment).mean())
        return given

    for length, segment in ((512, 32), (1000, 7), (64, 64), (40, 1)):
        h, p = rng.zipf(1.3, length) % 200, rng.random(length) + 0.01
        o = delta.DeltaOptions(segment=segment)
        assert np.allclose(delta.gains(h, p, o)[1], dense(h, p, o), rtol=1e-12)
    # The published geometry: 1,024 segments of 32 tokens.
    h, p = rng.zipf(1.3, 32_768) % 30_000, rng.random(32_768) * 1e-3 + 1e-6
    tracemalloc.start()
    delta.gains(h, p, delta.DeltaOptions())
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 100e6


def test_sampled_pairs_are_a_share():
    i, j = np.indices((300, 300))
    drawn = delta.drawn_pairs(i, j, 0.25, 2, 77)
    assert abs(drawn.mean() - 0.25) < 0.02 and (drawn != delta.drawn_pairs(i, j, 0.25, 2, 78)).any()
    assert delta.drawn_pairs(i, j, 1.0, 2, 77).all()


def test_published_geometry_equals_dense_rows():
    """32,768 tokens, spans of 128, 60 query spans: the kernel against a dense softmax of some rows."""
    g, rng = Geometry.named("paper"), np.random.default_rng(9)
    h = rng.zipf(1.2, g.length) % 5_000
    w = (rng.random(5_000) * 50)[h]
    rows = g.rows()
    assert len(rows) == 60 and sum(len(g.cols(j)) for j in rows) == 1_950
    mass = lexical.focus_matrix(h, w, g, rows)
    for k in (0, 31, 59):
        j, total = rows[k], np.zeros(g.n_spans)
        for q in range(j * g.span, (j + 1) * g.span):
            m = np.where(h[: q + 1] == h[q], 1 + w[q], 1.0)
            m /= m.sum()
            total += np.bincount(np.arange(q + 1) // g.span, m, g.n_spans)
        assert np.allclose(mass[: j + 1, k], total[: j + 1], atol=1e-9)


def test_repeated_chat_pleases_the_delta_baseline():
    """Stock turns repeat near by: the baseline prefers them to far echoes, the dependency score does not."""
    rnd = random.Random(7)
    stock = [[f"s{k}_{i}" for i in range(8)] for k in range(12)]
    chat = [t for _ in range(64) for t in rnd.choice(stock)]
    p = np.full(512, 1 / 20000)
    change = lambda t: delta.delta_matrix(codes(t), p, delta.DeltaOptions())[2].sum()
    assert change(chat) > change(PLANTED["far"]) and lexical_score(chat, 4.0, DESK) < score("far")


def test_concatenation_loses_the_echo():
    """Texts whose second half repeats the first: uncut samples keep the mass at the echo distance, pieces lose it."""
    docs = [[f"d{d}_{i}" for i in range(256)] * 2 for d in range(8)]
    g = Geometry(512, 8, 0, 0, 1, 1, 32)

    def at_echo(tokens):
        mass = lexical.focus_matrix(codes(tokens), np.full(512, np.exp(4) - 1), g, g.rows())
        return np.median([mass[j - 32, k] for k, j in enumerate(g.rows())])

    mixed = [t for d in docs for t in d[:64]]
    assert np.median([at_echo(d) for d in docs]) > 2 * at_echo(mixed)


def test_joined_weights_equal_broadcast_ones(spark):
    docs = edge_table(spark)
    again = docs.unionByName(docs.withColumn("doc_id", F.lit(None).cast("bigint")))  # ids that are null and repeat
    rows = samples.samples(again, DESK)
    seen = {}
    for most in (lexical.MAX_EXACT, 10):
        idf, p = lexical.weight_table(docs, max_exact=most), delta.unigram_table(docs, max_exact=most)
        made = (
            lexical.score_documents(rows, idf, DESK).select("doc_id", "full_4_4"), lexical.pair_focus_kernel(rows, idf, DESK),
            delta.delta_perplexity(rows, p).select("doc_id", "delta_score"), delta.segment_perplexity(rows, p), delta.delta_pairs(rows, p),
        )
        seen[most] = [sorted((tuple("null" if v is None else f"{v:.6g}" if isinstance(v, float) else str(v) for v in r)) for r in d.collect()) for d in made]
    assert isinstance(idf, lexical.WeightRows) and isinstance(p, lexical.WeightRows)
    assert all(seen[10]) and seen[10] == seen[lexical.MAX_EXACT]


def test_states_by_token_equal_a_whole_call(spark):
    rnd = random.Random(4)
    model = trained.Calculator.fresh()
    for n in (8, 64, 512):
        tokens = [f"t{rnd.randrange(90)}" for _ in range(n)]
        want = states.merge_heads(*model(tokens), Geometry(n, DESK.span), [n // DESK.span - 1], True, "mean")[:, 0]
        assert model.by_token(512).last_span_mass(model.ids(tokens), DESK.span) == pytest.approx(want, abs=1e-9)
