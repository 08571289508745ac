import json
import random
import shutil
import subprocess
import sys
import time
from pathlib import Path

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

import __spark_entry__ as entry
from spanfocus import registry
from spanfocus.functions.text import random_order
from spanfocus.operators import relational
from spanfocus.sources import tables

ROOT = Path(__file__).resolve().parent.parent


def test_entry_gives_rows(spark):
    assert entry.entry(spark).count() > 0


def test_oracles_belong_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries()) and set(registry.queries()) <= set(entry.queries())


def test_entry_without_the_optional_folders(tmp_path):
    shutil.copytree(ROOT / "spanfocus", tmp_path / "spanfocus", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    code = "import json, __spark_entry__ as e; print(json.dumps(sorted(e.queries())))"
    made = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, check=True, env={"PATH": "/usr/bin:/bin", "HOME": str(tmp_path)})
    assert json.loads(made.stdout.splitlines()[-1]) == sorted(registry.queries())


def test_nothing_else_imports_the_optional_folders():
    for path in (ROOT / "spanfocus").rglob("*.py"):
        if "llm" not in path.relative_to(ROOT).parts:
            assert "spanfocus.llm" not in path.read_text()


def test_formats_round_trip(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    expected = sorted(docs.collect())
    docs.write.orc(str(tmp_path / "orc"))
    tables.write_lines(docs, str(tmp_path / "json"))
    docs.write.option("header", "true").option("escape", '"').csv(str(tmp_path / "csv"))
    for kind in ("orc", "json", "csv"):
        made = tables.read_corpus(spark, str(tmp_path / kind), kind)
        assert sorted(made.select(docs.columns).collect()) == expected
    (tmp_path / "json" / "broken.json").write_text("not json\n")
    made = tables.read_corpus(spark, str(tmp_path / "json"), "json").cache()
    assert made.where("_corrupt_record IS NOT NULL").count() == 1
    tables.write_by_domain(docs.withColumnRenamed("source", "domain"), str(tmp_path / "parts"))
    assert (tmp_path / "parts" / "domain=src0").exists()
    (tmp_path / "a.txt").write_text("one\ntwo")
    assert tables.read_corpus(spark, str(tmp_path / "a.txt"), "text").first().value == "one\ntwo"
    with pytest.raises(ValueError):
        tables.read_corpus(spark, "x", "xml")
    with pytest.raises(ValueError):
        tables.require(docs, "nothing")


def test_near_duplicates_equal_brute_force(spark):
    words = [f"w{i}" for i in range(60)]
    texts = [" ".join(words), " ".join(words[:58] + ["x", "y"]), " ".join(words), "short text", "short text", None, "", " ".join(reversed(words)), " ".join(words[:30])]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    made = {(r.a, r.b): r.jaccard for r in relational.dedupe_near(df).collect()}
    sets = {}
    for i, t in enumerate(texts):
        w = (t or "").split()
        if w and t not in [texts[j] for j in sets]:
            sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}
    expected = {(a, b): len(sets[a] & sets[b]) / len(sets[a] | sets[b]) for a in sets for b in sets if a < b}
    assert made == {k: pytest.approx(v) for k, v in expected.items() if v >= 0.8} and made


def test_contamination_of_short_passages(spark, monkeypatch):
    docs = spark.createDataFrame([(1, "aa bb cc dd ee ff gg hh ii jj kk ll"), (2, "only a few"), (3, None)], "doc_id bigint, text string")
    pins = spark.createDataFrame([(1, "b cc dd ee ff gg hh ii jj k"), (2, "a few"), (3, "zz"), (4, "")], "item_id bigint, text string")
    expected = {tuple(r) for r in relational.contaminated(docs, pins).collect()}
    assert expected == {(1, 1), (2, 2)}
    # Beyond their bound, passages of one or two words are found by automata, some at a time.
    short = spark.createDataFrame([(i, p) for i, p in enumerate(["a b", "b", "zz", "a b", "c d", "", "x"])], "item_id bigint, text string")
    expected = {tuple(r) for r in relational.contaminated(docs, short).collect()}
    monkeypatch.setattr(relational, "BARE_PASSAGES", 2)
    monkeypatch.setattr(relational, "BARE_BLOCK", 2)
    assert {tuple(r) for r in relational.contaminated(docs, short).collect()} == expected


def test_stream_replay_changes_nothing(spark, sf, tmp_path):
    from spanfocus.streaming.arriving import RunningSelection

    rows = spark.createDataFrame([(i, "a", 10, i / 10) for i in range(20)], "doc_id bigint, domain string, n_tokens int, score double")
    running = RunningSelection(spark, str(tmp_path / "s"), 0.5, "score")
    running.merge(rows.where("doc_id < 10"), 0)
    running.merge(rows.where("doc_id >= 10"), 1)
    running.merge(rows.where("doc_id >= 10"), 1)
    assert sorted(r.doc_id for r in running.current().collect()) == list(range(10, 20))


def spread_files(df, n, folder, key="doc_id"):
    """Write ``df`` as ``n`` files in a random order of its key."""
    part = F.row_number().over(Window.orderBy(random_order(key, 3))) % n
    df.withColumn("_p", part).repartition(n, "_p").drop("_p").write.parquet(folder)
    return folder


def test_running_selection_reads_only_what_can_be_taken(spark, tmp_path):
    from spanfocus.operators import select
    from spanfocus.streaming.arriving import RunningSelection

    rnd = random.Random(5)
    rows = [(i, rnd.choice("abc"), rnd.randint(1, 30), rnd.choice([0.0, -2.5, rnd.random() ** 9 * 1e6, rnd.random()])) for i in range(600)]
    df = spark.createDataFrame(rows, "doc_id bigint, domain string, n_tokens int, score double")
    running = RunningSelection(spark, str(tmp_path / "s"), 0.25, "score")
    for k in range(3):
        running.merge(df.where(f"doc_id % 3 = {k}"), k)
        seen = df.where(f"doc_id % 3 <= {k}")
        budget = int(seen.agg(F.sum("n_tokens")).first()[0] * 0.25)
        expected = select.select_by_domain(seen, budget).select(*select.COLUMNS)
        assert sorted(running.current().collect()) == sorted(expected.collect())
    lows = {r.domain: r.low for r in running.cuts().collect()}
    assert all(sum(d == r[1] and RunningSelection.BINS >= 1 for r in rows) > 0 for d in lows)
    bins = df.withColumn("bin", RunningSelection.bin_of(F.col("score"))).collect()
    ordered = sorted(bins, key=lambda r: r.score)
    assert all(a.bin <= b.bin for a, b in zip(ordered, ordered[1:]))
    assert sum(r.bin >= lows[r.domain] for r in bins) < len(bins) / 2


def test_late_events(spark, tmp_path):
    """The first batch moves the watermark to 10:00. A later event of an open window counts, one of a closed window is dropped."""
    from spanfocus.streaming import arriving

    folder = str(tmp_path / "events")
    batches = [["08:10", "12:00"], ["12:05"], ["10:20", "09:59", "08:20", "12:10"], ["23:00"], ["23:30"]]
    for k, times in enumerate(batches):
        rows = [(k * 10 + i, f"2024-05-01 {t}:00", 1, "click", 1.0, None) for i, t in enumerate(times)]
        made = spark.createDataFrame(rows, arriving.EVENTS.replace("ts timestamp_ntz", "ts string")).withColumn("ts", F.col("ts").cast("timestamp_ntz"))
        made.coalesce(1).write.mode("append").parquet(folder)
        time.sleep(1.1)  # files are taken by their time
    rows = arriving.stream_events(spark, folder, 1)
    made = arriving.drained(arriving.windowed(rows, F.window("ts", "1 hour"), ["event_type"]))
    found = {r.hour: r.n for r in made.select(F.date_format("w.start", "HH").alias("hour"), "n").collect()}
    # 09:59 and 08:20 come after the watermark has passed the ends of their windows.
    assert found == {"08": 1, "10": 1, "12": 3}


def test_stream_of_many_files_equals_batch(spark, sf, tmp_path):
    from spanfocus.geometry import Geometry
    from spanfocus.operators import lexical, samples
    from spanfocus.streaming import arriving

    docs, g = spark.read.parquet(f"{sf}/documents.parquet"), Geometry.named("smoke")
    table = lexical.weight_table(docs)
    folder = spread_files(docs, 5, str(tmp_path / "docs"))
    made = arriving.drained(arriving.score_stream(tables.stream_documents(spark, folder), table, g))
    batch = lexical.score_documents(samples.samples(docs, g), table, g)
    assert sorted(made.select("doc_id", "full_2_2").collect()) == sorted(batch.select("doc_id", "full_2_2").collect())


def test_token_shards_round_trip(spark, tmp_path):
    from spanfocus.sources import shards

    shards.register(spark)
    rows = spark.createDataFrame([(i, [i, i + 1, i + 2]) for i in range(20)], "doc_id bigint, ids array<int>").repartition(3)
    folder = str(tmp_path / "shards")
    rows.write.format("token_shards").option("length", 3).mode("append").save(folder)
    made = spark.read.format("token_shards").option("length", 3).load(folder)
    assert sorted(r.ids for r in made.collect()) == [[i, i + 1, i + 2] for i in range(20)]


def test_sql_functions(spark):
    from spanfocus.functions import sql_surface

    sql_surface.register(spark)
    made = spark.sql("SELECT * FROM spanfocus_focus_pairs(array(1L, 2L, 3L, 1L, 2L, 4L, 1L, 2L), array_repeat(2.0D, 8), 2, 0, 1, 1, 1, 2)").collect()
    assert {(r.j, r.i): round(r.pair_focus, 9) for r in made} == {(2, 0): round(25 / 36, 9), (3, 0): round(54 / 91, 9), (3, 1): round(41 / 91, 9)}


def test_callable_tokens(spark):
    from pyspark.sql import functions as F

    from spanfocus.operators import samples

    df = spark.createDataFrame([(1, "a-b-c"), (2, None)], "doc_id bigint, text string")
    made = samples.tokenize(df, mode=lambda c: F.split(c, "-")).collect()
    assert made[0].tokens == ["a", "b", "c"]
