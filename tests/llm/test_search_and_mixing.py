import random

import duckdb
import numpy as np

from spanfocus.llm import bit_sliced_search as B
from spanfocus.llm import source_mixing as S
from spanfocus.llm.entries import MIX, MIX_WEIGHTS, op10_source_mixing, oracle_sql, with_levels
from tests.llm.fixtures import edge_docs, no_docs


def test_scores_and_top_k_in_memory():
    rng = np.random.default_rng(1)
    for n, width, spread in ((1, 3, 5), (70, 8, 200), (300, 16, 3), (64, 1, 1), (129, 4, 0)):
        values = rng.integers(-spread, spread + 1, (n, width))
        ids = rng.permutation(n * 3)[:n]
        index = B.BitSlices(ids, values)
        for query in (rng.integers(-spread - 2, spread + 3, width), np.zeros(width, np.int64)):
            score = dict(zip(ids.tolist(), (values @ query).tolist(), strict=True))
            for own in (None, int(ids[0])):
                rest = {i: s for i, s in score.items() if i != own}
                expected = sorted(rest.items(), key=lambda x: (-x[1], x[0]))[:5]
                assert index.top(query, 5, own) == expected


def test_upper_slices_leave_few_rows_and_lose_none(monkeypatch):
    """The first pass adds the upper slices only; all slices follow just where it leaves many rows, as among near copies."""
    passes = []
    near_top = B.BitSlices._near_top

    def noted(self, queries, k, rows, drop, weight_bits):
        near = near_top(self, queries, k, rows, drop, weight_bits)
        passes.append((drop, len(queries), int(np.bitwise_count(near).sum())))
        return near

    monkeypatch.setattr(B.BitSlices, "_near_top", noted)
    rng = np.random.default_rng(4)
    unit = rng.normal(size=(3000, 64))
    spread = np.floor(unit / np.linalg.norm(unit, axis=1)[:, None] * 256).astype(np.int64)
    close = spread.copy()
    close[:1500] = spread[0] + rng.integers(-1, 2, (1500, 64))
    ids = rng.permutation(9000)[:3000]
    for values, second in ((spread, False), (close, True)):
        passes.clear()
        found = B.BitSlices(ids, values).top_many(values[:40], 5, ids[:40])
        for i, best in enumerate(found):
            score = values @ values[i]
            assert best == sorted(((int(d), int(s)) for d, s in zip(ids, score, strict=True) if d != ids[i]), key=lambda x: (-x[1], x[0]))[:5]
        assert sum(n for drop, n, _ in passes if drop) == 40
        assert any(drop == 0 for drop, _, _ in passes) == second
        assert second or sum(left for _, _, left in passes) < 40 * 3000 * B.MANY


def test_scores_beyond_64_bits_and_least_ids():
    values = np.array([[2**61, -5, 3], [-(2**61), 7, 1], [2**61 - 1, 0, 0], [2**61, -5, 3]], np.int64)
    ids = np.array([4, 2**63 - 1, -(2**63), 1])
    queries = np.array([[2**62, 1, 1], [-(2**62), 9, -9], [0, 0, 1]])
    for query, best in zip(queries, B.BitSlices(ids, values).top_many(queries, 3, np.array([9, 2**63 - 1, -(2**63)])), strict=True):
        score = values.astype(object) @ query.astype(object)
        own = {2**62: 9, -(2**62): 2**63 - 1, 0: -(2**63)}[int(query[0])]
        assert best == sorted(((int(i), s) for i, s in zip(ids, score, strict=True) if i != own), key=lambda x: (-x[1], x[0]))[:3]


def plain_top(rows, k, nth):
    ok = {i: np.floor(np.array(v, float) * 256).astype(int) for i, v in rows if i is not None and v and all(x is not None and np.isfinite(x) for x in v)}
    out = []
    for q in ok:
        if q % nth == 0:
            s = sorted(((int(ok[q] @ ok[i]), i) for i in ok if i != q), key=lambda x: (-x[0], x[1]))[:k]
            out += [(q, r, i, x) for r, (x, i) in enumerate(s, 1)]
    return sorted(out)


def test_query_equals_brute_force(spark):
    rng = np.random.default_rng(2)
    rows = [(int(i), [float(x) for x in rng.normal(0, 0.3, 6).round(1)]) for i in rng.permutation(400)[:150]]
    rows += [(1000, None), (1001, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (1050, [float("nan")] * 6), (1100, [float("inf")] * 6), (1150, []), (None, [0.1] * 6)]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "vec_id bigint, embedding array<float>, score string")
    q = B.quantised(df)
    for blocks in ({}, {"block_rows": 40, "block_queries": 3}):
        found = sorted(map(tuple, B.top_k(q, B.every_nth(q, 10), 5, **blocks).collect()))
        assert found == plain_top([(i, None if v is None else [None if x is None else float(np.float32(x)) for x in v]) for i, v in rows], 5, 10)
    assert B.top_k(q.where("false"), q.where("false")).count() == 0
    few = q.where("vec_id < 10")
    assert B.top_k(few, few.limit(1)).count() <= max(0, few.count() - 1)
    stored = B.index_blocks(q, block_rows=40).collect()
    assert sum(r.n_rows for r in stored) == 150 and max(r.n_rows for r in stored) <= 40


def test_repeated_candidates_and_unequal_widths(spark):
    """Rows equal in id and vector count as often as places can be filled; shorter vectors are filled with zeros."""
    rows = [(1, [1.0, 2.0])] * 9 + [(2, [1.0])] * 2 + [(3, [0.5, 0.5, 9.0]), (0, [1.0, 1.0])]
    q = B.quantised(spark.createDataFrame(rows, "vec_id bigint, embedding array<float>"))
    made = B.top_k(q, q.where("vec_id in (0, 3)"), 5).orderBy("query_id", "rank").collect()
    assert [(r.vec_id, r.score) for r in made if r.query_id == 0] == [(1, 3 * 65536)] * 5
    assert [(r.vec_id, r.score) for r in made if r.query_id == 3] == [(1, int(1.5 * 65536))] * 5


def leaves(spark, rows):
    return spark.createDataFrame(rows, "domain string, lang string, source string, tokens bigint")


def test_shortages_go_to_siblings_first(spark):
    rows = [("a", "en", "s1", 100), ("a", "en", "s2", 1000), ("a", "de", "s3", 1000), ("b", "en", "s4", 1000)]
    made = {r.source: r.share for r in S.leaf_budgets(leaves(spark, rows), 1200 / 3100, {}, 1).collect()}
    # Each domain 600, a's languages 300, en's sources 150: s1 is short by 50, which its sibling takes.
    assert {k: round(v, 6) for k, v in made.items()} == {"s1": 100, "s2": 200, "s3": 300, "s4": 600}
    rows = [("a", "en", "s1", 100), ("a", "de", "s2", 200), ("b", "en", "s3", 5000), (None, "en", None, 10)]
    made = {r.source: r.share for r in S.leaf_budgets(leaves(spark, rows), 1200 / 5310, {}, 1).collect()}
    assert {k: round(v, 6) for k, v in made.items()} == {"s1": 100, "s2": 200, "s3": 890, None: 10}


def plain_budgets(tree, budget, weights, epochs):
    """The tree (name: children or tokens) by water-filling in small steps: a node hands on what its children refuse."""

    def capacity(depth, name, node):
        if weights.get(LEVELS[depth], {}).get(name, 1.0) <= 0:
            return 0.0
        return node * epochs if isinstance(node, int) else sum(capacity(depth + 1, k, v) for k, v in node.items())

    def deal(depth, node, budget, path):
        if isinstance(node, int):
            return {path: budget}
        can = {k: capacity(depth, k, v) for k, v in node.items()}
        weight = {k: weights.get(LEVELS[depth], {}).get(k, 1.0) for k in node}
        share, left = dict.fromkeys(node, 0.0), budget
        while left > 1e-9 and (open_ := [k for k in node if share[k] < can[k] - 1e-9 and weight[k] > 0]):
            total = sum(weight[k] for k in open_)
            given = {k: min(left * weight[k] / total, can[k] - share[k]) for k in open_}
            for k, x in given.items():
                share[k] += x
            left -= sum(given.values())
        return {p: x for k, v in node.items() for p, x in deal(depth + 1, v, share[k], (*path, k)).items()}

    return deal(0, tree, budget, ())


LEVELS = ("domain", "lang", "source")


def test_shortages_go_to_ancestors_past_weights_of_zero(spark):
    made = S.leaf_budgets(leaves(spark, [("a", "en", "s", 100), ("a", "de", "s", 900), ("b", "en", "s", 1000)]), 0.5, {"lang": {"de": 0.0}}, 1)
    assert {(r.domain, r.lang): r.share for r in made.collect()} == {("a", "en"): 100, ("a", "de"): 0, ("b", "en"): 900}
    rnd = random.Random(6)
    for _ in range(6):
        tree = {d: {x: {s: rnd.randint(1, 500) for s in "pqr"[: rnd.randint(1, 3)]} for x in ("en", "de", "fr")[: rnd.randint(1, 3)]} for d in "abc"}
        weights = {n: {k: rnd.choice([0.0, 0.5, 1.0, 3.0]) for k in ks} for n, ks in zip(LEVELS, ("abc", ("en", "de", "fr"), "pqr"), strict=True)}
        rows = [(d, x, s, n) for d, xs in tree.items() for x, ss in xs.items() for s, n in ss.items()]
        total = sum(r[3] for r in rows)
        expected = plain_budgets(tree, 0.7 * total, weights, 2)
        found = {(r.domain, r.lang, r.source): r.share for r in S.leaf_budgets(leaves(spark, rows), 0.7, weights, 2).collect()}
        assert found.keys() == expected.keys() and all(abs(found[k] - expected[k]) < 1e-5 for k in found)


def test_budget_beyond_all_and_zero(spark):
    rows = [("a", "en", "s1", 100), ("b", "en", "s2", 50)]
    assert sum(r.share for r in S.leaf_budgets(leaves(spark, rows), 9.0, {}, 2).collect()) == 300
    assert sum(r.share for r in S.leaf_budgets(leaves(spark, rows), 0.0, {}, 2).collect()) == 0


def test_mix_edges(spark):
    docs = with_levels(edge_docs(spark))
    made = S.mix(docs, 0.5, {"lang": {"en": 0.2}}, 2, 1).collect()
    total = docs.agg({"n_tokens": "sum"}).first()[0]
    assert sum(r.n_tokens * r.copies for r in made) <= total * 0.5 + 1e-6
    assert {r.copies for r in made} <= {1, 2}
    assert S.mix(with_levels(no_docs(spark))).count() == 0


def test_weights_move_the_mix(spark):
    rnd = random.Random(3)
    rows = [(i, rnd.choice("ab"), "en", "s", rnd.randint(1, 50)) for i in range(2000)]
    df = spark.createDataFrame(rows, "doc_id bigint, domain string, lang string, source string, n_tokens bigint")
    share = {}
    for r in S.mix(df, 0.4, {"domain": {"a": 3.0, "b": 1.0}}, 2, 5).collect():
        share[r.domain] = share.get(r.domain, 0) + r.n_tokens * r.copies
    assert abs(share["a"] / sum(share.values()) - 0.75) < 0.01


def test_query_equals_oracle(spark, sf):
    con = duckdb.connect()
    con.sql(f"create view documents as select * from '{sf}/documents.parquet'")
    expected = {(r[0], r[-1]) for r in con.sql(oracle_sql()["op10_source_mixing"]).fetchall()}
    assert {(r.doc_id, r.copies) for r in op10_source_mixing(spark, sf).collect()} == expected
    assert MIX["max_epochs"] == 2 and set(MIX_WEIGHTS) == {"domain", "lang"}
