from collections import Counter

import corpus_pipeline as P
from tests.llm.fixtures import edge_docs


def test_documents_without_id_stay(spark, sf):
    docs = edge_docs(spark)
    once = [r.doc_id for r in P.distinct(spark, docs, sf).collect()]
    assert len(once) == 7 and set(once) == {1, 3, 5, 7, 8, 9, None}
    alone = docs.where("doc_id IS NULL")
    taken = P.mixed(spark, alone.unionByName(alone.withColumn("text", P.F.lit("another row of six words"))), sf).collect()
    # Each is shorter than 60 % of both together: one at least is taken.
    assert taken and all(r.doc_id is None for r in taken)


def test_repeated_and_null_ids_are_rows_as_any_other(spark, sf):
    """One id on several texts, texts without id, and rows equal in all columns: none is lost, none comes too often."""
    kinds = "doc_id bigint, text string, lang string, source string, n_chars bigint"
    words = [f"w{i} " * 12 + f"x{i} y{i} z{i}" for i in range(30)]
    rows = [(1, t, "en", "src0", 9) for t in words[:10]] + [(None, t, "de", "src1", 9) for t in words[10:20]] + [(2, words[20], "fr", "src2", 9)] * 5
    docs = spark.createDataFrame(rows, kinds)
    kept = P.distinct(spark, docs, sf).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0, r.text) for r in kept) == sorted({(r[0] is None, r[0] or 0, r[1]) for r in rows})
    # Weights and shares that take every document of every leaf twice.
    taken = P.mixed(spark, docs, sf).collect()
    given, found = Counter(rows), Counter(tuple(r) for r in taken)
    assert found.keys() <= given.keys() and all(n <= 2 * given[r] for r, n in found.items())
    total = lambda c: sum(n * len(r[1].split()) for r, n in c.items())
    assert 0.3 * total(given) < total(found) <= 0.6 * total(given)


def test_missing_languages_are_filled(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    blank = docs.withColumn("lang", P.F.when(P.F.col("doc_id") % 5 != 0, P.F.col("lang")))
    left = {r.doc_id: r.lang for r in P.identified(spark, blank, sf).collect()}
    known = {r.doc_id: r.lang for r in docs.collect()}
    filled = [i for i in left if i % 5 == 0]
    assert all(left.values()) and all(left[i] == known[i] for i in left if i % 5)
    assert filled and sum(left[i] == known[i] for i in filled) > 0.9 * len(filled)
