import random

import duckdb
from pyspark.sql import functions as F

from spanfocus.llm import url_filters as U
from spanfocus.llm.entries import URL_RULES, oracle_sql
from spanfocus.llm.samples import bounded_sample


def test_distrust_reaches_the_end_of_a_long_chain(spark):
    """Links without a scheme count, and a host far from the blocked one is blocked as well."""
    rows = [(i, f"http://h{i}.net/1", f'<a href="//h{i + 1}.net/1">x</a>') for i in range(12)]
    rows += [(12, "http://h12.net/1", '<a href="//bad.com/de/x">x</a>'), (13, "http://bad.com/de/x", None), (14, "http://good.org/a", None)]
    made = U.judge_urls(spark.createDataFrame(rows, "page_id bigint, url string, html string"), URL_RULES)
    assert {r.page_id for r in made.where("verdict = 'block'").collect()} == set(range(14))


def test_url_verdicts_equal_sql(spark, sf):
    """The statement's verdicts on the given pages and on a graph of hosts in which links decide."""
    rnd = random.Random(8)
    hosts = [f"h{i}.net" for i in range(30)] + ["a.com", "b.org", "example.org", "EXAMPLE.org"]
    rows = [(None, None), ("no scheme", "x"), ("http://", '<a href="//h1.net">')]
    for _ in range(150):
        links = "".join(f"""<a HREF = "{rnd.choice(["http:", "https:", ""])}//{rnd.choice(hosts)}/x">y</a>""" for _ in range(rnd.randint(0, 3)))
        rows.append((f"http://{rnd.choice(hosts)}/{rnd.choice(['de/', 'fr/', 'es/', 'en/1', ''])}{rnd.randint(1, 9)}?q#f", links))
    made = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "page_id bigint, url string, html string")
    for pages, verdicts in ((spark.read.parquet(f"{sf}/pages.parquet"), {"allow", "block"}), (made, {"allow", "block"})):
        con = duckdb.connect()
        con.register("pages", pages.select("page_id", "url", "html").toArrow())
        expected = {tuple(r) for r in con.sql(oracle_sql()["op9_url_filters"]).fetchall()}
        found = {tuple(r) for r in U.judge_urls(pages, URL_RULES).select("page_id", "host", "path", "rule", "verdict").collect()}
        assert found == expected and {r[4] for r in found} <= verdicts
    by_graph = {r[4] for r in found if r[3] is None and r[1]}
    assert by_graph == {"allow", "block"}


def test_every_class_is_sampled(spark):
    rows = spark.range(1200).select("id", F.concat(F.lit("l"), (F.col("id") % 300).cast("string")).alias("lang"))
    assert bounded_sample(rows, "id", "lang", 100).select("lang").distinct().count() == 300
