import random

import numpy as np
import xxhash

from spanfocus.llm import near_copies as N
from tests.llm.fixtures import edge_docs, no_docs


def plain_fingerprint(text):
    words = [w for w in text.encode().lower().split()]
    if not words:
        return 0
    grams = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def plain_components(fps):
    roots = {i: i for i in fps}

    def root(i):
        while roots[i] != i:
            i = roots[i]
        return i

    ids = sorted(fps)
    for a in ids:
        for b in ids:
            if a < b and (fps[a] ^ fps[b]).bit_count() <= 3:
                x, y = root(a), root(b)
                roots[max(x, y)] = min(x, y)
    return {i: root(i) for i in ids}


def test_fingerprint(monkeypatch):
    rnd = random.Random(2)
    texts = ["", "a", "A b", "a b c", " \t\n", "ß É é x"] + [" ".join(rnd.choice("abcdef") for _ in range(rnd.randint(1, 60))) for _ in range(50)]
    expected = [plain_fingerprint(t) for t in texts]
    assert [N.fingerprint(t) for t in texts] == expected
    monkeypatch.setattr(N, "_HASHES", 7)
    assert [N.fingerprint(t) for t in texts] == expected


def test_anchors_cover():
    h = np.random.default_rng(1).integers(0, 2**32, 3000, dtype=np.uint32)
    home, near = N.anchors_of(h)
    assert (N._syndromes(home & np.uint32(0x7FFFFFFF)) == 0).all()
    assert (np.bitwise_count((home ^ h) & np.uint32(0x7FFFFFFF)) <= 1).all()
    for bit in range(32):
        moved, _ = N.anchors_of(h ^ np.uint32(1 << bit))
        assert ((moved == home) | (near == moved[:, None]).any(axis=1)).all()


def planted(n_groups=12, chain=6, crowd=120, seed=3):
    """Fingerprints with chains of small steps, a crowded ball, and strangers."""
    rnd, out = random.Random(seed), []
    for _ in range(n_groups):
        x = rnd.getrandbits(64)
        for _ in range(chain):
            out.append(x)
            for b in rnd.sample(range(64), rnd.randint(1, 4)):
                x ^= 1 << b
    centre = rnd.getrandbits(64)
    out += [centre ^ sum(1 << b for b in rnd.sample(range(64), rnd.randint(0, 4))) for _ in range(crowd)]
    out += [rnd.getrandbits(64) for _ in range(100)] + [0, 1, 2**64 - 1]
    return sorted(set(out))


def run(spark, fps, **how):
    signed = np.array(fps, np.uint64).view(np.int64).tolist()
    edges = N.links(spark.createDataFrame([(x,) for x in signed], "fp bigint"), **how)
    return {r.node: r.root for r in N.components(edges).collect()}, signed


def test_links_and_components_equal_brute_force(spark):
    fps = planted()
    expected = plain_components(dict(enumerate(fps)))
    for block in (2048, 8):
        found, signed = run(spark, fps, block=block)
        groups = {}
        for i, x in enumerate(signed):
            groups.setdefault(found.get(x, x), set()).add(i)
        wanted = {}
        for i, r in expected.items():
            wanted.setdefault(r, set()).add(i)
        assert sorted(map(sorted, groups.values())) == sorted(map(sorted, wanted.values()))


def test_cells_that_span_batches(spark):
    fps = planted(seed=8)
    key, old = "spark.sql.execution.arrow.maxRecordsPerBatch", spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set(key, 37)
    try:
        found, signed = run(spark, fps, block=64)
    finally:
        spark.conf.set(key, old)
    whole, _ = run(spark, fps)
    assert {x: found.get(x, x) for x in signed} == {x: whole.get(x, x) for x in signed}
    expected = plain_components(dict(enumerate(fps)))
    assert len(set(expected.values())) == len({found.get(x, x) for x in signed})


def test_long_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(300)] + [(1000, 1001), (5, 5)], "u bigint, v bigint")
    roots = {r.node: r.root for r in N.components(edges).collect()}
    assert all(roots[i] == 0 for i in range(1, 301)) and roots[1001] == 1000 and 5 in roots


def test_documents(spark):
    docs = edge_docs(spark)
    rows = N.near_duplicate_groups(docs).collect()
    assert len(rows) == docs.count()
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    assert all(r.fp & (2**64 - 1) == plain_fingerprint(texts[r.doc_id]) for r in rows)
    by_id = {r.doc_id: r.component_id for r in rows}
    assert by_id[1] == by_id[2] == by_id[6] == 1 and by_id[3] == by_id[4] == 3
    assert N.near_duplicate_groups(no_docs(spark)).count() == 0
    shown = docs.sparkSession.createDataFrame([(1,), (-1,), (0,)], "fp bigint").select(N.hex_fingerprint()).collect()
    assert [r[0] for r in shown] == ["0" * 15 + "1", "f" * 16, "0" * 16]


def test_whole_small_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = N.near_duplicate_groups(docs).collect()
    expected = plain_components({r.doc_id: r.fp & (2**64 - 1) for r in rows})
    assert {r.doc_id: r.component_id for r in rows} == expected


def test_component_rounds_send_nothing_through_the_driver(spark, monkeypatch):
    plans, cut = [], N.cut

    def watched(df):
        df.collect()
        plans.append(df._jdf.queryExecution().executedPlan().toString())
        return cut(df)

    monkeypatch.setattr(N, "cut", watched)
    edges = spark.createDataFrame([(k, k + 1) for k in range(40)] + [(100, 101)], "u bigint, v bigint")
    made = {r.node: r.root for r in N.components(edges).collect()}
    assert made == {k: 0 for k in range(1, 41)} | {101: 100}
    assert any("SortMergeJoin" in p for p in plans) and not any("BroadcastHashJoin" in p for p in plans)
