from pyspark.sql import functions as F

from spanfocus import registry
from spanfocus.operators import trained
from spanfocus.plans import workloads as W


def test_needles_by_method_uses_all_lengths_and_whole_selections(spark, sf, monkeypatch):
    seen, train = [], trained.train_calculator
    monkeypatch.setattr(trained, "train_calculator", lambda *a, **k: seen.append(train(*a, **k)) or seen[-1])
    rows = W.workload_needles_by_method(spark, sf).collect()
    sizes = [d.count() * W.DESK.length for d in W.selections(spark, sf).values()]
    assert [c.tokens_seen for c in seen] == [2 * n for n in sizes]
    lengths = {m: {r.context_len for r in rows if r.method == m} for m in ("dependency", "delta", "random_1", "lexical")}
    assert all(v == set(W.LENGTHS) for v in lengths.values())


def test_published_strides_correlate_all_samples(spark, sf, monkeypatch):
    rows = W.strides_published(spark, sf).collect()
    monkeypatch.setattr(W, "_DRAWN", 5)
    assert sorted(W.strides_published(spark, sf).collect()) == sorted(rows)
    assert {r.n_docs for r in W.score_correlation(spark, sf).collect()} == {5}
    assert "LIMIT" not in registry.oracle_sql()["strides_published"]


def test_parts_of_a_round_lie_in_tasks_of_their_own(spark, monkeypatch):
    rows = spark.range(80).select((F.col("id") + 1).alias("place"), F.array_repeat(F.lit("a"), 9).alias("tokens"))
    held, cut = [], trained.cut
    monkeypatch.setattr(trained, "cut", lambda df: held.append(cut(df)) or held[-1])
    made = trained.train_calculator(rows, rounds=1, groups=8)
    assert made.tokens_seen == 720
    parts = held[0].select(F.spark_partition_id().alias("task"), "part").distinct()
    assert parts.count() == parts.select("task").distinct().count() == 8
