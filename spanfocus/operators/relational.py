"""Operators around the method: scans, filters, joins, aggregates, windows, sets, scalar families.

Each is a query of its own on the given tables, registered with a DuckDB oracle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from spanfocus.functions import sql_surface
from spanfocus.functions.text import tokens_of
from spanfocus.plans.entry_table import EntryTable
from spanfocus.sources.tables import read_table

TABLE = EntryTable()
TOKEN = r"[^ \t\n\r]+"


def t(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return read_table(spark, sf_dir, name, *columns)


# Scans, projections, filters.


@TABLE.query("SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem GROUP BY l_returnflag")
def op_scan_pruned(spark, sf_dir):
    rows = t(spark, sf_dir, "lineitem", "l_returnflag", "l_quantity")
    return rows.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@TABLE.query("""SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem
    WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1995-07-01' AND l_quantity BETWEEN 10 AND 12""")
def op_scan_pushdown(spark, sf_dir):
    dates = F.col("l_shipdate").between(F.expr("TIMESTAMP_NTZ'1995-01-01 00:00:00'"), F.expr("TIMESTAMP_NTZ'1995-06-30 23:59:59.999999'"))
    rows = t(spark, sf_dir, "lineitem").where(dates & F.col("l_quantity").between(10, 12))
    return rows.select("l_orderkey", "l_linenumber", "l_quantity")


@TABLE.query("SELECT event_type, count(*) AS n, round(avg((props::JSON->>'k')::DOUBLE), 6) AS mean_k FROM events GROUP BY event_type")
def op_json_props(spark, sf_dir):
    rows = t(spark, sf_dir, "events", "event_type", "props").withColumn("p", F.from_json("props", "k double"))
    return rows.groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.avg("p.k"), 6).alias("mean_k"))


@TABLE.query("SELECT doc_id, lang || '/' || source AS place, n_chars > 1000 AS is_long FROM documents")
def op_project_nested(spark, sf_dir):
    facts = F.struct(F.concat_ws("/", "lang", "source").alias("place"), (F.col("n_chars") > 1000).alias("is_long"))
    return t(spark, sf_dir, "documents", "doc_id", "lang", "source", "n_chars").select("doc_id", facts.alias("f")).select("doc_id", "f.place", "f.is_long")


@TABLE.query("""SELECT doc_id FROM documents WHERE lang IN ('de', 'fr') AND n_chars BETWEEN 500 AND 2000 AND source LIKE 'src1%'
    AND source IS DISTINCT FROM 'src13' AND regexp_matches(text, '[äöüé]')""")
def op_filter_predicates(spark, sf_dir):
    rows = t(spark, sf_dir, "documents")
    keep = F.col("lang").isin("de", "fr") & F.col("n_chars").between(500, 2000) & F.col("source").like("src1%")
    return rows.where(keep & ~F.col("source").eqNullSafe("src13") & F.col("text").rlike("[äöüé]")).select("doc_id")


_JUNK = f"""WITH a AS (
        SELECT doc_id, text, regexp_extract_all(coalesce(text, ''), '{TOKEN}') AS tokens, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents
    ) SELECT doc_id, round(CASE WHEN length(text) > 0 THEN len(regexp_extract_all(text, '[^\\p{{L}}\\p{{N}}\\s]')) / length(text) ELSE 0 END, 6) AS symbol_ratio,
        round(CASE WHEN len(tokens) > 0 THEN len(list_distinct(tokens)) / len(tokens) ELSE 0 END, 6) AS distinct_ratio,
        round(1 - len(list_distinct(lines)) / len(lines), 6) AS repeated_lines FROM a"""


def junk_profile(docs: DataFrame) -> DataFrame:
    """(doc_id, symbol_ratio, distinct_ratio, repeated_lines): what the cleaning filters look at."""
    tokens, lines = tokens_of("text"), F.split(F.coalesce("text", F.lit("")), "\n")
    symbols = F.regexp_count("text", F.lit(r"[^\p{L}\p{N}\s]")) / F.length("text")
    rows = docs.select(
        "doc_id",
        F.when(F.length("text") > 0, symbols).otherwise(0.0).alias("symbol_ratio"),
        F.when(F.size(tokens) > 0, F.size(F.array_distinct(tokens)) / F.size(tokens)).otherwise(0.0).alias("distinct_ratio"),
        (1 - F.size(F.array_distinct(lines)) / F.size(lines)).alias("repeated_lines"),
    )
    return rows.select("doc_id", *(F.round(c, 6).alias(c) for c in ("symbol_ratio", "distinct_ratio", "repeated_lines")))


@TABLE.query(_JUNK)
def op_junk_profile(spark, sf_dir):
    return junk_profile(t(spark, sf_dir, "documents", "doc_id", "text"))


def clean(docs: DataFrame, most_symbols: float = 0.2, least_distinct: float = 0.1, most_repeated: float = 0.5) -> DataFrame:
    """Documents that pass the junk filters; the optional step before scoring."""
    bad = junk_profile(docs).where((F.col("symbol_ratio") > most_symbols) | (F.col("distinct_ratio") < least_distinct) | (F.col("repeated_lines") > most_repeated))
    return docs.join(bad.select("doc_id"), "doc_id", "left_anti")


@TABLE.query(f"SELECT count(*) AS kept FROM ({_JUNK}) WHERE NOT (symbol_ratio > 0.2 OR distinct_ratio < 0.1 OR repeated_lines > 0.5)")
def op_clean(spark, sf_dir):
    return clean(t(spark, sf_dir, "documents", "doc_id", "text")).agg(F.count("*").alias("kept"))


# Duplicates and contamination.


def dedupe_exact(docs: DataFrame) -> DataFrame:
    """(doc_id, copies): the smallest id of every distinct text; texts are compared by digest, not moved."""
    return docs.groupBy(F.md5(F.coalesce("text", F.lit(""))).alias("digest")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).select("doc_id", "copies")


@TABLE.query("SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY md5(coalesce(text, ''))")
def op_dedupe_exact(spark, sf_dir):
    return dedupe_exact(t(spark, sf_dir, "documents", "doc_id", "text"))


def shingles(docs: DataFrame, words: int = 5) -> DataFrame:
    """(doc_id, s): distinct hashed word shingles of each document; a shorter text is one shingle."""
    tokens = tokens_of(F.lower(F.coalesce("text", F.lit(""))))
    starts = F.sequence(F.lit(1), F.greatest(F.size("w") - words + 1, F.lit(1)))
    made = F.transform(starts, lambda i: F.xxhash64(F.array_join(F.slice("w", i, words), " ")))
    return docs.select("doc_id", tokens.alias("w")).where(F.size("w") > 0).select("doc_id", F.explode(F.array_distinct(made)).alias("s"))


def dedupe_near(docs: DataFrame, words: int = 5, least: float = 0.8) -> DataFrame:
    """(a, b, jaccard) of representatives of distinct texts whose shingle sets are at least ``least`` alike. Exact.

    Prefix filter: two sets that alike share one of the rarest (1 - least) share of the larger's shingles,
    so only those are joined, in an order of global rarity; the candidates are then compared in full. Copies
    are represented by their smallest id, and a pair is compared once.
    """
    one = dedupe_exact(docs).select("doc_id")
    sh = shingles(docs.join(one, "doc_id", "left_semi"), words)
    order = sh.groupBy("s").agg(F.count("*").alias("f"))
    ranked = sh.join(order, "s").groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("f", "s"))).alias("x")).withColumn("n", F.size("x"))
    prefix = F.slice("x", 1, F.col("n") - F.ceil(F.lit(least) * F.col("n") - 1e-9).cast("int") + 1)
    keys = ranked.select("doc_id", "n", F.explode(F.transform(prefix, lambda p: p["s"])).alias("s"))
    a, b = keys.select(F.col("doc_id").alias("a"), F.col("n").alias("n_a"), "s"), keys.select(F.col("doc_id").alias("b"), F.col("n").alias("n_b"), "s")
    fits = (F.col("a") < F.col("b")) & (F.least("n_a", "n_b") >= F.lit(least) * F.greatest("n_a", "n_b") - 1e-9)
    pairs = a.join(b, "s").where(fits).select("a", "b", "n_a", "n_b").distinct()
    sets = ranked.select("doc_id", F.transform("x", lambda p: p["s"]).alias("v"))
    full = pairs.join(sets.withColumnsRenamed({"doc_id": "a", "v": "va"}), "a").join(sets.withColumnsRenamed({"doc_id": "b", "v": "vb"}), "b")
    shared = F.size(F.array_intersect("va", "vb"))
    return full.withColumn("jaccard", shared / (F.col("n_a") + F.col("n_b") - shared)).where(F.col("jaccard") >= least - 1e-9).select("a", "b", "jaccard")


@TABLE.query(f"""WITH one AS (SELECT min(doc_id) AS doc_id, any_value(text) AS text FROM documents GROUP BY md5(coalesce(text, ''))),
    w AS (SELECT doc_id, regexp_extract_all(lower(coalesce(text, '')), '{TOKEN}') AS w FROM one),
    s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM w WHERE len(w) > 0)),
    n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
    p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.s = y.s AND x.doc_id < y.doc_id GROUP BY ALL)
    SELECT a, b, round(c / (m.n + k.n - c), 6) AS jaccard FROM p JOIN n m ON m.doc_id = a JOIN n k ON k.doc_id = b WHERE c / (m.n + k.n - c) >= 0.8 - 1e-9""")
def op_dedupe_near(spark, sf_dir):
    return dedupe_near(t(spark, sf_dir, "documents", "doc_id", "text")).withColumn("jaccard", F.round("jaccard", 6))


#: Passages without an inner word that are looked for by plain containment, and those of one automaton beyond that.
BARE_PASSAGES, BARE_BLOCK = 1000, 50_000


def _by_automata(docs: DataFrame, bare: DataFrame) -> DataFrame:
    """(doc_id, item_id): every document with every passage in it, a pass over the texts for each block of passages."""
    spark, out = docs.sparkSession, None
    blocks = max(1, -(-bare.count() // BARE_BLOCK))
    schema = StructType([docs.schema["doc_id"], bare.schema["item_id"]])
    for b in range(blocks):
        rows = bare.where(F.pmod(F.xxhash64("passage"), F.lit(blocks)) == b).toArrow()
        shared = spark.sparkContext.broadcast((rows.column("passage").to_pylist(), rows.column("item_id").to_pylist()))  # about BARE_BLOCK rows

        def run(batches, shared=shared, kind=rows.schema.field("item_id").type):
            import ahocorasick
            import pyarrow as pa

            held: dict[str, list] = {}
            for passage, item in zip(*shared.value, strict=True):
                held.setdefault(passage, []).append(item)
            words = ahocorasick.Automaton()
            for passage, items in held.items():
                words.add_word(passage, items)
            words.make_automaton()
            for batch in batches:
                found = [{i for _, items in words.iter(text or "") for i in items} if held else () for text in batch.column(1).to_pylist()]
                at = [k for k, items in enumerate(found) for _ in items]
                ids = pa.array([i for items in found for i in items], type=kind)
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(at, pa.int64())), ids], names=schema.fieldNames())

        made = docs.select("doc_id", "text").mapInArrow(run, schema)
        out = made if out is None else out.unionByName(made)
    return out


def contaminated(docs: DataFrame, passages: DataFrame, words: int = 8) -> DataFrame:
    """(doc_id, item_id): documents that hold a whole passage. A shingle join proposes, ``contains`` decides.

    A passage is looked for by its first ``words`` inner words (the first word may continue one of the
    document's, the last may go on), or by as many as it has. Passages of one or two words have none; up to
    BARE_PASSAGES of them are tested one by one, more of them by automata. Empty passages are in no document.
    """
    tokens = tokens_of("text")
    inner = F.slice(tokens, 2, F.greatest(F.least(F.size(tokens) - 2, F.lit(words)), F.lit(0)))
    keys = passages.where(F.length("text") > 0).select("item_id", F.col("text").alias("passage"), inner.alias("h")).withColumn("size", F.size("h"))
    sizes = [r[0] for r in keys.where("size > 0").select("size").distinct().collect()]  # at most ``words`` numbers
    rows = docs.select("doc_id", tokens.alias("w"))

    def of_size(k: int) -> Column:
        starts = F.when(F.size("w") >= k, F.sequence(F.lit(1), F.size("w") - k + 1)).otherwise(F.array().cast("array<int>"))
        return F.transform(starts, lambda i: F.xxhash64(F.lit(k), F.array_join(F.slice("w", i, k), " ")))

    hits = None
    if sizes:
        made = F.array_distinct(F.concat(*map(of_size, sizes)))
        wanted = keys.where("size > 0").select("item_id", "passage", F.xxhash64("size", F.array_join("h", " ")).alias("s"))
        found = rows.select("doc_id", F.explode(made).alias("s")).join(wanted.select("item_id", "s"), "s").select("doc_id", "item_id").distinct()
        checked = found.join(docs.select("doc_id", "text"), "doc_id").join(wanted.select("item_id", "passage"), "item_id")
        hits = checked.where(F.contains("text", "passage")).select("doc_id", "item_id")
    short = keys.where("size = 0").select("item_id", "passage")
    bare = short.limit(BARE_PASSAGES + 1).collect()
    if len(bare) > BARE_PASSAGES:
        plain = _by_automata(docs, short)
        hits = plain if hits is None else hits.unionByName(plain)
    elif bare or hits is None:
        tests = [F.when(F.contains("text", F.lit(r.passage)), F.lit(r.item_id)) for r in bare] or [F.lit(None).cast(passages.schema["item_id"].dataType)]
        plain = docs.select("doc_id", F.explode(F.array_compact(F.array(*tests))).alias("item_id"))
        hits = plain if hits is None else hits.unionByName(plain)
    return hits


@TABLE.query("SELECT d.doc_id, b.item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def op_decontaminate(spark, sf_dir):
    return contaminated(t(spark, sf_dir, "documents", "doc_id", "text"), t(spark, sf_dir, "benchmark"))


@TABLE.query("SELECT count(*) AS clean_docs FROM documents d WHERE NOT EXISTS (SELECT 1 FROM benchmark b WHERE contains(d.text, b.text))")
def op_decontaminate_rest(spark, sf_dir):
    docs = t(spark, sf_dir, "documents", "doc_id", "text")
    bad = contaminated(docs, t(spark, sf_dir, "benchmark")).select("doc_id").distinct()
    return docs.join(bad, "doc_id", "left_anti").agg(F.count("*").alias("clean_docs"))


# Joins.


@TABLE.query("SELECT r_name, count(*) AS nations FROM nation JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def op_join_broadcast(spark, sf_dir):
    rows = t(spark, sf_dir, "nation").join(t(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.groupBy("r_name").agg(F.count("*").alias("nations"))


@TABLE.query("SELECT o_orderpriority, count(*) AS lines, round(sum(l_extendedprice), 2) AS price FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL")
def op_join_merge(spark, sf_dir):
    lines = t(spark, sf_dir, "lineitem", "l_orderkey", "l_extendedprice")
    rows = t(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority").join(lines.hint("merge"), F.col("o_orderkey") == F.col("l_orderkey"))
    return rows.groupBy("o_orderpriority").agg(F.count("*").alias("lines"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@TABLE.query("SELECT c_mktsegment, count(*) AS orders FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY ALL")
def op_join_shuffle_hash(spark, sf_dir):
    customers = t(spark, sf_dir, "customer", "c_custkey", "c_mktsegment").hint("shuffle_hash")
    rows = t(spark, sf_dir, "orders", "o_custkey").join(customers, F.col("c_custkey") == F.col("o_custkey"))
    return rows.groupBy("c_mktsegment").agg(F.count("*").alias("orders"))


@TABLE.query("""SELECT a.p_brand, count(*) AS pairs FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey
    AND abs(a.p_retailprice - b.p_retailprice) <= 5 GROUP BY ALL""")
def op_join_theta(spark, sf_dir):
    return close_pairs(t(spark, sf_dir, "part", "p_partkey", "p_brand", "p_retailprice"), "p_brand", "p_partkey", "p_retailprice", 5)


def close_pairs(rows: DataFrame, by: str, key: str, value: str, width: float) -> DataFrame:
    """(by, pairs): how many pairs of rows of a group have different keys, and values at most ``width`` apart.

    Values are cut into bands, so only neighbours meet, and equal ones meet as one row with their number: no
    pair of rows is ever made. Pairs of rows that share a key are counted the same way and taken off.
    """
    rows = rows.select(F.col(by).alias("g"), F.col(key).alias("k"), F.col(value).alias("v")).where("g IS NOT NULL AND k IS NOT NULL")
    rows = rows.where(F.abs("v") < float("inf"))  # a NaN is above

    def counted(df: DataFrame, *at: str) -> DataFrame:
        a = df.groupBy(*at, "v").agg(F.count("*").alias("n")).withColumn("band", F.floor(F.col("v") / width))
        b = a.select(*at, F.col("v").alias("w"), F.col("n").alias("m"), F.explode(F.sequence(F.col("band") - 1, F.col("band") + 1)).alias("band"))
        met = a.join(b, [*at, "band"]).where((F.col("v") <= F.col("w")) & (F.abs(F.col("v") - F.col("w")) <= width))
        own = F.when(F.col("v") == F.col("w"), (F.col("n") * (F.col("n") - 1) / 2).cast("bigint")).otherwise(F.col("n") * F.col("m"))
        return met.groupBy("g").agg(F.sum(own).alias("pairs"))

    again = rows.groupBy("g", "k").agg(F.count("*").alias("n")).where("n > 1").select("g", "k")
    off = counted(rows.join(again, ["g", "k"], "left_semi"), "g", "k").withColumnRenamed("pairs", "off")
    made = counted(rows, "g").join(off, "g", "left").select(F.col("g").alias(by), (F.col("pairs") - F.coalesce("off", F.lit(0))).alias("pairs"))
    return made.where("pairs > 0")


@TABLE.query("""SELECT s.event_id AS signup_id, e.event_id FROM events s JOIN events e ON s.user_id = e.user_id AND s.event_type = 'signup'
    AND e.ts > s.ts AND e.ts <= s.ts + INTERVAL 1 HOUR""")
def op_join_range(spark, sf_dir):
    """Events within the hour after a signup: hours as bins, each signup in two of them."""
    rows = t(spark, sf_dir, "events", "event_id", "user_id", "event_type", "ts").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = 3_600_000_000
    s = rows.where("event_type = 'signup'").select(F.col("event_id").alias("signup_id"), "user_id", F.col("us").alias("at"))
    s = s.withColumn("bin", F.explode(F.array(F.floor(F.col("at") / hour), F.floor(F.col("at") / hour) + 1)))
    e = rows.withColumn("bin", F.floor(F.col("us") / hour))
    return s.join(e, ["user_id", "bin"]).where((F.col("us") > F.col("at")) & (F.col("us") <= F.col("at") + hour)).select("signup_id", "event_id")


def as_of(left: DataFrame, right: DataFrame, by: str, at: str, value: str) -> DataFrame:
    """Left rows with the latest ``value`` of the right at or before ``at``: union and a running last value."""
    tagged = left.withColumn("_side", F.lit(1)).withColumn("_v", F.lit(None).cast(right.schema[value].dataType))
    other = right.select(*(F.col(c) if c in (by, at) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns), F.lit(0).alias("_side"), F.col(value).alias("_v"))
    order = Window.partitionBy(by).orderBy(at, "_side", "_v").rowsBetween(Window.unboundedPreceding, 0)
    return tagged.unionByName(other).withColumn("found", F.last("_v", ignorenulls=True).over(order)).where("_side = 1").drop("_side", "_v")


@TABLE.query("""SELECT event_id, (SELECT max(v.event_id) FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND v.ts = (
    SELECT max(w.ts) FROM events w WHERE w.user_id = p.user_id AND w.event_type = 'view' AND w.ts <= p.ts)) AS view_id FROM events p WHERE event_type = 'purchase'""")
def op_join_asof(spark, sf_dir):
    rows = t(spark, sf_dir, "events", "event_id", "user_id", "event_type", "ts")
    left = rows.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    right = rows.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("view_id"))
    return as_of(left, right, "user_id", "ts", "view_id").select("event_id", F.col("found").alias("view_id"))


@TABLE.query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def op_join_semi(spark, sf_dir):
    return t(spark, sf_dir, "documents", "doc_id").join(t(spark, sf_dir, "labels", "doc_id"), "doc_id", "left_semi")


@TABLE.query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti(spark, sf_dir):
    return t(spark, sf_dir, "documents", "doc_id").join(t(spark, sf_dir, "labels", "doc_id"), "doc_id", "left_anti")


@TABLE.query("""SELECT count(*) AS rows, count(c_custkey) AS customers, count(o_orderkey) AS orders FROM customer
    FULL JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') ON c_custkey = o_custkey""")
def op_join_full(spark, sf_dir):
    orders = t(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderstatus").where("o_orderstatus = 'F'")
    rows = t(spark, sf_dir, "customer", "c_custkey").join(orders, F.col("c_custkey") == F.col("o_custkey"), "full")
    return rows.agg(F.count("*").alias("rows"), F.count("c_custkey").alias("customers"), F.count("o_orderkey").alias("orders"))


@TABLE.query("""WITH o AS (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS n FROM orders)
    SELECT a.o_orderkey, b.o_orderkey AS next_orderkey FROM o a JOIN o b ON a.o_custkey = b.o_custkey AND b.n = a.n + 1""")
def op_join_self(spark, sf_dir):
    n = F.row_number().over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey"))
    o = t(spark, sf_dir, "orders", "o_custkey", "o_orderkey", "o_orderdate").withColumn("n", n)
    b = o.select("o_custkey", (F.col("n") - 1).alias("n"), F.col("o_orderkey").alias("next_orderkey"))
    return o.select("o_custkey", "n", "o_orderkey").join(b, ["o_custkey", "n"]).select("o_orderkey", "next_orderkey")


# Aggregates.


@TABLE.query("""SELECT l_returnflag, l_linestatus, count(*) AS n, sum((l_extendedprice * (1 - l_discount))::DECIMAL(18, 2))::DOUBLE AS revenue,
    round(avg(l_quantity), 6) AS mean_quantity, round(stddev_samp(l_discount), 6) AS dev_discount, count(*) FILTER (l_tax > 0.05) AS taxed FROM lineitem GROUP BY ALL""")
def op_agg_basic(spark, sf_dir):
    net = (F.col("l_extendedprice") * (1 - F.col("l_discount"))).cast("decimal(18,2)")
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.sum(net).cast("double").alias("revenue"), F.round(F.avg("l_quantity"), 6).alias("mean_quantity"),
        F.round(F.stddev_samp("l_discount"), 6).alias("dev_discount"), F.count_if(F.col("l_tax") > 0.05).alias("taxed"),
    )


@TABLE.query("""SELECT event_type, max_by(event_id, (value, event_id)) AS largest, min_by(event_id, (value, event_id)) AS smallest,
    round(quantile_cont(value, 0.9), 6) AS p90, round(corr(value, user_id), 6) AS r FROM events GROUP BY event_type""")
def op_agg_statistics(spark, sf_dir):
    key = F.struct("value", "event_id")
    return t(spark, sf_dir, "events").groupBy("event_type").agg(
        F.max_by("event_id", key).alias("largest"), F.min_by("event_id", key).alias("smallest"),
        F.round(F.percentile("value", 0.9), 6).alias("p90"), F.round(F.corr("value", "user_id"), 6).alias("r"),
    )


@TABLE.query(f"SELECT lang, count(DISTINCT token) AS tokens FROM (SELECT lang, unnest(regexp_extract_all(text, '{TOKEN}')) AS token FROM documents) GROUP BY lang")
def op_agg_distinct(spark, sf_dir):
    rows = t(spark, sf_dir, "documents", "lang", "text").select("lang", F.explode(tokens_of("text")).alias("token"))
    return rows.groupBy("lang").agg(F.countDistinct("token").alias("tokens"))


@TABLE.query()
def op_agg_approx_distinct(spark, sf_dir):
    """A sketch's estimate differs by engine: rows only."""
    rows = t(spark, sf_dir, "documents", "lang", "text").select("lang", F.explode(tokens_of("text")).alias("token"))
    return rows.groupBy("lang").agg(F.approx_count_distinct("token", 0.02).alias("tokens"))


_BASE = "SELECT lang, source, quality, n_chars FROM documents LEFT JOIN labels USING (doc_id)"


def _labelled(spark, sf_dir) -> DataFrame:
    return t(spark, sf_dir, "documents", "doc_id", "lang", "source", "n_chars").join(t(spark, sf_dir, "labels", "doc_id", "quality"), "doc_id", "left")


@TABLE.query(f"""SELECT lang, source, count(*) AS docs, sum(n_chars)::BIGINT AS chars, grouping_id(lang, source)::BIGINT AS level
    FROM ({_BASE}) GROUP BY GROUPING SETS ((lang, source), (lang), ())""")
def op_grouping_sets(spark, sf_dir):
    _labelled(spark, sf_dir).createOrReplaceTempView("spanfocus_labelled")
    return spark.sql("""SELECT lang, source, count(*) AS docs, sum(n_chars) AS chars, grouping_id(lang, source) AS level
        FROM spanfocus_labelled GROUP BY GROUPING SETS ((lang, source), (lang), ())""")


@TABLE.query(f"SELECT lang, quality, count(*) AS docs, grouping_id(lang, quality)::BIGINT AS level FROM ({_BASE}) GROUP BY CUBE (lang, quality)")
def op_cube(spark, sf_dir):
    return _labelled(spark, sf_dir).cube("lang", "quality").agg(F.count("*").alias("docs"), F.grouping_id("lang", "quality").alias("level"))


@TABLE.query(f"SELECT source, lang, count(*) AS docs, grouping_id(source, lang)::BIGINT AS level FROM ({_BASE}) GROUP BY ROLLUP (source, lang)")
def op_rollup(spark, sf_dir):
    return _labelled(spark, sf_dir).rollup("source", "lang").agg(F.count("*").alias("docs"), F.grouping_id("source", "lang").alias("level"))


@TABLE.query(f"SELECT lang, count(*) FILTER (quality = 0) AS q0, count(*) FILTER (quality = 1) AS q1 FROM ({_BASE}) WHERE quality IS NOT NULL GROUP BY lang")
def op_pivot(spark, sf_dir):
    rows = _labelled(spark, sf_dir).where("quality IS NOT NULL").groupBy("lang").pivot("quality", [0, 1]).agg(F.count(F.lit(1)))
    return rows.select("lang", F.coalesce("`0`", F.lit(0)).alias("q0"), F.coalesce("`1`", F.lit(0)).alias("q1"))


@TABLE.query(f"""SELECT lang, 'q0' AS grade, count(*) FILTER (quality = 0) AS docs FROM ({_BASE}) WHERE quality IS NOT NULL GROUP BY lang
    UNION ALL SELECT lang, 'q1', count(*) FILTER (quality = 1) FROM ({_BASE}) WHERE quality IS NOT NULL GROUP BY lang""")
def op_unpivot(spark, sf_dir):
    return op_pivot(spark, sf_dir).unpivot("lang", ["q0", "q1"], "grade", "docs")


# Windows, top-k, sets.


@TABLE.query("""SELECT doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id)::INT AS place,
    rank() OVER (PARTITION BY source ORDER BY n_chars DESC)::INT AS rank, dense_rank() OVER (PARTITION BY source ORDER BY n_chars DESC)::INT AS dense FROM documents""")
def op_window_rank(spark, sf_dir):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"))
    first = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    rows = t(spark, sf_dir, "documents", "doc_id", "source", "n_chars")
    return rows.select("doc_id", F.row_number().over(first).alias("place"), F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"))


@TABLE.query("""SELECT o_orderkey, lag(o_orderkey) OVER w AS before, lead(o_orderkey) OVER w AS after, first_value(o_orderkey) OVER w AS first,
    date_diff('day', lag(o_orderdate) OVER w, o_orderdate)::INT AS gap FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)""")
def op_window_offset(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    rows = t(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    return rows.select(
        "o_orderkey", F.lag("o_orderkey").over(w).alias("before"), F.lead("o_orderkey").over(w).alias("after"), F.first("o_orderkey").over(w).alias("first"),
        F.datediff("o_orderdate", F.lag("o_orderdate").over(w)).alias("gap"),
    )


@TABLE.query("SELECT doc_id, sum(n_chars) OVER (PARTITION BY lang, source ORDER BY doc_id ROWS UNBOUNDED PRECEDING)::BIGINT AS running FROM documents")
def op_window_running(spark, sf_dir):
    w = Window.partitionBy("lang", "source").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, 0)
    return t(spark, sf_dir, "documents", "doc_id", "lang", "source", "n_chars").select("doc_id", F.sum("n_chars").over(w).alias("running"))


@TABLE.query("""SELECT o_orderkey, count(*) OVER w AS orders_7d, round(sum(o_totalprice) OVER w, 2) AS price_7d FROM orders
    WINDOW w AS (PARTITION BY o_custkey ORDER BY epoch_us(o_orderdate) // 1000000 RANGE BETWEEN 604800 PRECEDING AND CURRENT ROW)""")
def op_window_range(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("s").rangeBetween(-604_800, 0)
    rows = t(spark, sf_dir, "orders").withColumn("s", F.unix_seconds(F.col("o_orderdate").cast("timestamp")))
    return rows.select("o_orderkey", F.count("*").over(w).alias("orders_7d"), F.round(F.sum("o_totalprice").over(w), 2).alias("price_7d"))


@TABLE.query("""SELECT doc_id, ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id)::INT AS quarter, round(cume_dist() OVER (PARTITION BY lang ORDER BY n_chars), 6) AS share,
    round(percent_rank() OVER (PARTITION BY lang ORDER BY n_chars), 6) AS above FROM documents""")
def op_window_distribution(spark, sf_dir):
    w, first = Window.partitionBy("lang").orderBy("n_chars"), Window.partitionBy("lang").orderBy("n_chars", "doc_id")
    rows = t(spark, sf_dir, "documents", "doc_id", "lang", "n_chars")
    return rows.select("doc_id", F.ntile(4).over(first).alias("quarter"), F.round(F.cume_dist().over(w), 6).alias("share"), F.round(F.percent_rank().over(w), 6).alias("above"))


@TABLE.query("SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20")
def op_topk_global(spark, sf_dir):
    return t(spark, sf_dir, "documents", "doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(20)


@TABLE.query("SELECT source, doc_id FROM documents QUALIFY row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) <= 3")
def op_topk_group(spark, sf_dir):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return t(spark, sf_dir, "documents", "source", "doc_id", "n_chars").withColumn("n", F.row_number().over(w)).where("n <= 3").select("source", "doc_id")


@TABLE.query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 20")
def op_sort_limit_offset(spark, sf_dir):
    return t(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(20).limit(10)


def _two(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    rows = t(spark, sf_dir, "documents", "doc_id", "lang", "n_chars")
    return rows.where("n_chars > 1000").select("lang"), rows.where("n_chars <= 1500").select("lang")


_A, _B = "SELECT lang FROM documents WHERE n_chars > 1000", "SELECT lang FROM documents WHERE n_chars <= 1500"


@TABLE.query(f"SELECT lang, count(*) AS n FROM ({_A} UNION ALL {_B}) GROUP BY lang")
def op_union(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.unionByName(b).groupBy("lang").agg(F.count("*").alias("n"))


@TABLE.query(f"SELECT lang, count(*) AS n FROM ({_A} INTERSECT ALL {_B}) GROUP BY lang")
def op_intersect(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.intersectAll(b).groupBy("lang").agg(F.count("*").alias("n"))


@TABLE.query(f"SELECT lang, count(*) AS n FROM ({_A} EXCEPT ALL {_B}) GROUP BY lang")
def op_except(spark, sf_dir):
    a, b = _two(spark, sf_dir)
    return a.exceptAll(b).groupBy("lang").agg(F.count("*").alias("n"))


# Scalar families, nested types, SQL surface.


@TABLE.query("""SELECT page_id, lower(split_part(url, '/', 3)) AS host, length(url) AS chars, reverse(substr(url, 1, 12)) AS back, replace(url, 'http', 'x') AS swapped,
    md5(url) AS digest, regexp_extract(url, '/([a-z]{2})/', 1) AS lang FROM pages""")
def op_string(spark, sf_dir):
    u = F.col("url")
    return t(spark, sf_dir, "pages", "page_id", "url").select(
        "page_id", F.lower(F.split_part(u, F.lit("/"), F.lit(3))).alias("host"), F.length(u).cast("bigint").alias("chars"),
        F.reverse(F.substring(u, 1, 12)).alias("back"), F.replace(u, F.lit("http"), F.lit("x")).alias("swapped"), F.md5(u).alias("digest"),
        F.regexp_extract(u, "/([a-z]{2})/", 1).alias("lang"),
    )


@TABLE.query("""SELECT date_trunc('month', o_orderdate)::DATE::VARCHAR AS month, count(*) AS orders, min(o_orderdate + INTERVAL 1 MONTH)::DATE::VARCHAR AS due,
    max(dayofyear(o_orderdate))::INT AS last_day, max(strftime(o_orderdate, '%Y-%m')) AS label FROM orders GROUP BY 1""")
def op_date(spark, sf_dir):
    d = F.col("o_orderdate")
    return t(spark, sf_dir, "orders", "o_orderdate").groupBy(F.date_trunc("month", d).cast("date").cast("string").alias("month")).agg(
        F.count("*").alias("orders"), F.min(F.add_months(d, 1)).cast("string").alias("due"), F.max(F.dayofyear(d)).alias("last_day"), F.max(F.date_format(d, "yyyy-MM")).alias("label")
    )


@TABLE.query("""SELECT event_id, round(ln(abs(value) + 1), 6) AS l, round(sqrt(abs(value)), 6) AS s, round(exp(-abs(value) / 100), 6) AS e, round(pow(value, 2), 4) AS p,
    greatest(value, 10.0) AS hi, least(value, 10.0) AS lo, event_id % 7 AS m FROM events""")
def op_math(spark, sf_dir):
    v = F.col("value")
    return t(spark, sf_dir, "events", "event_id", "value").select(
        "event_id", F.round(F.log(F.abs(v) + 1), 6).alias("l"), F.round(F.sqrt(F.abs(v)), 6).alias("s"), F.round(F.exp(-F.abs(v) / 100), 6).alias("e"),
        F.round(F.pow(v, F.lit(2)), 4).alias("p"), F.greatest(v, F.lit(10.0)).alias("hi"), F.least(v, F.lit(10.0)).alias("lo"), F.pmod("event_id", F.lit(7)).alias("m"),
    )


@TABLE.query(f"""WITH a AS (SELECT doc_id, regexp_extract_all(text, '{TOKEN}') AS w FROM documents)
    SELECT doc_id, len(list_distinct(w)) AS distinct_tokens, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS letters,
    len(list_filter(w, lambda x: length(x) > 8)) AS long_tokens, w[1] AS first_token, w[-1] AS last_token FROM a""")
def op_array(spark, sf_dir):
    rows = t(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", tokens_of("text").alias("w"))
    return rows.select(
        "doc_id", F.size(F.array_distinct("w")).cast("bigint").alias("distinct_tokens"),
        F.aggregate("w", F.lit(0).cast("bigint"), lambda n, x: n + F.length(x)).alias("letters"),
        F.size(F.filter("w", lambda x: F.length(x) > 8)).cast("bigint").alias("long_tokens"), F.get("w", F.lit(0)).alias("first_token"),
        F.get("w", F.size("w") - 1).alias("last_token"),
    )


@TABLE.query(f"SELECT doc_id, token, count(*) AS n FROM (SELECT doc_id, unnest(regexp_extract_all(text, '{TOKEN}')) AS token FROM documents) GROUP BY ALL HAVING count(*) >= 20")
def op_map_entries(spark, sf_dir):
    """Token counts of each document as a map, filtered, and unfolded again."""
    counts = t(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", F.explode(tokens_of("text")).alias("token")).groupBy("doc_id", "token").agg(F.count("*").alias("n"))
    maps = counts.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("token", "n"))).alias("m"))
    return maps.select("doc_id", F.explode(F.map_filter("m", lambda _, n: n >= 20)).alias("token", "n"))


@TABLE.query("""WITH c AS (SELECT label, vec_id, embedding::DOUBLE[] AS e FROM embeddings), o AS (SELECT e FROM c ORDER BY vec_id LIMIT 1)
    SELECT vec_id, round(sqrt(list_dot_product(c.e, c.e)), 5) AS norm, round(list_dot_product(c.e, o.e), 5) AS dot, round(list_cosine_similarity(c.e, o.e), 5) AS cosine FROM c, o""")
def op_vector(spark, sf_dir):
    rows = t(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    first = rows.orderBy("vec_id").limit(1).first()
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda n, x: n + x)
    one = F.array(*(F.lit(float(x)) for x in (first["e"] if first else [])))
    norm = lambda a: F.sqrt(dot(a, a))
    e = F.col("e")
    return rows.select("vec_id", F.round(norm(e), 5).alias("norm"), F.round(dot(e, one), 5).alias("dot"), F.round(dot(e, one) / (norm(e) * norm(one)), 5).alias("cosine"))


@TABLE.query("""WITH big AS (SELECT lang, avg(n_chars) AS m FROM documents GROUP BY lang)
    SELECT doc_id FROM documents d WHERE n_chars > 2 * (SELECT m FROM big WHERE big.lang = d.lang)""")
def op_cte_subquery(spark, sf_dir):
    t(spark, sf_dir, "documents").createOrReplaceTempView("spanfocus_documents")
    return spark.sql(
        """WITH big AS (SELECT lang, avg(n_chars) AS m FROM spanfocus_documents GROUP BY lang)
        SELECT doc_id FROM spanfocus_documents d WHERE n_chars > :times * (SELECT first(m) FROM big WHERE big.lang = d.lang)""",
        args={"times": 2},
    )


@TABLE.query("SELECT n_name, x.c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 1) x")
def op_lateral(spark, sf_dir):
    for name in ("nation", "customer"):
        t(spark, sf_dir, name).createOrReplaceTempView(f"spanfocus_{name}")
    return spark.sql("""SELECT n_name, x.c_custkey FROM spanfocus_nation, LATERAL (
        SELECT max_by(c_custkey, struct(c_acctbal, -c_custkey)) AS c_custkey FROM spanfocus_customer WHERE c_nationkey = n_nationkey HAVING count(*) > 0) x""")


@TABLE.query(f"""WITH a AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{TOKEN}') AS w FROM documents),
    s AS (SELECT doc_id, w, unnest(range(len(w) // 128))::INT AS j FROM a)
    SELECT doc_id, j, md5(array_to_string(w[j * 128 + 1:(j + 1) * 128], ' ')) AS span_md5 FROM s""")
def op_udtf_spans(spark, sf_dir):
    sql_surface.register(spark)
    t(spark, sf_dir, "documents", "doc_id", "text").createOrReplaceTempView("spanfocus_texts")
    return spark.sql("SELECT doc_id, j, md5(span_tokens) AS span_md5 FROM spanfocus_texts, LATERAL spanfocus_span_table(text, 128)")


@TABLE.query("SELECT doc_id, md5('5:' || doc_id::VARCHAR) AS draw FROM documents WHERE substr(md5('5:' || doc_id::VARCHAR), 1, 1) < '4'")
def op_sample_hash(spark, sf_dir):
    """A reproducible quarter of the rows: the feature is the sample."""
    draw = F.md5(F.concat_ws(":", F.lit("5"), F.col("doc_id").cast("string")))
    return t(spark, sf_dir, "documents", "doc_id").withColumn("draw", draw).where(F.substring("draw", 1, 1) < "4")


@TABLE.query("SELECT label, count(*) AS n, round(sum(x), 4) AS mass FROM (SELECT label, unnest(embedding)::DOUBLE AS x FROM embeddings) GROUP BY label")
def op_unnest(spark, sf_dir):
    rows = t(spark, sf_dir, "embeddings", "label", "embedding").select("label", F.explode(F.col("embedding").cast("array<double>")).alias("x"))
    return rows.groupBy("label").agg(F.count("*").alias("n"), F.round(F.sum("x"), 4).alias("mass"))


@TABLE.query("SELECT event_type, sum((props::JSON->>'k')::BIGINT)::BIGINT AS k, count(*) FILTER (props::JSON->>'k' IS NULL) AS without FROM events GROUP BY event_type")
def op_json_variant(spark, sf_dir):
    rows = t(spark, sf_dir, "events", "event_type", "props").withColumn("v", F.parse_json("props"))
    k = F.try_variant_get("v", "$.k", "bigint")
    return rows.groupBy("event_type").agg(F.sum(k).alias("k"), F.count_if(k.isNull()).alias("without"))


@TABLE.query("""SELECT DISTINCT o_custkey, nth_value(o_orderkey, 2) OVER w AS second, last_value(o_orderkey) OVER w AS last FROM orders
    WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def op_window_nth(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    rows = t(spark, sf_dir, "orders", "o_custkey", "o_orderkey", "o_orderdate")
    return rows.select("o_custkey", F.nth_value("o_orderkey", 2).over(w).alias("second"), F.last("o_orderkey").over(w).alias("last")).distinct()


@TABLE.query("""SELECT lang, source, docs * 2 AS doubled, docs + coalesce(q, 0) AS joined FROM (SELECT lang, source, count(*) AS docs, count(quality) AS q
    FROM documents LEFT JOIN labels USING (doc_id) GROUP BY ALL)""")
def op_map_functions(spark, sf_dir):
    """Per language a map of source to count; values transformed, two maps zipped."""
    counts = _labelled(spark, sf_dir).groupBy("lang", "source").agg(F.count("*").alias("docs"), F.count("quality").alias("q"))
    entry = lambda c: F.map_from_entries(F.collect_list(F.struct("source", c)))
    maps = counts.groupBy("lang").agg(entry("docs").alias("a"), entry("q").alias("b"))
    doubled = F.transform_values("a", lambda _, n: n * 2)
    joined = F.map_zip_with("a", "b", lambda _, x, y: x + F.coalesce(y, F.lit(0)))
    rows = maps.select("lang", F.explode(F.map_zip_with(doubled, joined, lambda _, x, y: F.struct(x.alias("doubled"), y.alias("joined")))).alias("source", "v"))
    return rows.select("lang", "source", "v.doubled", "v.joined")


@TABLE.query("SELECT doc_id, (n_chars // 128)::INT AS span FROM documents")
def op_sql_function(spark, sf_dir):
    sql_surface.register(spark)
    t(spark, sf_dir, "documents", "doc_id", "n_chars").createOrReplaceTempView("spanfocus_sizes")
    return spark.sql("SELECT doc_id, spanfocus_span_index(CAST(n_chars AS INT), 128) AS span FROM spanfocus_sizes")


@TABLE.query("""WITH r AS (SELECT lang, quality AS y, rank() OVER (PARTITION BY lang ORDER BY n_chars)
        + (count(*) OVER (PARTITION BY lang, n_chars) - 1) / 2 AS r FROM documents JOIN labels USING (doc_id))
    SELECT lang, round((sum(r) FILTER (y = 1) - sum(y) * (sum(y) + 1) / 2) / (sum(y) * (count(*) - sum(y))), 6) AS auc FROM r
    GROUP BY lang HAVING sum(y) > 0 AND sum(y) < count(*)""")
def op_grouped_pandas(spark, sf_dir):
    """Grouped pandas aggregate: does length tell quality, by language."""
    from spanfocus.session import ship_package

    ship_package(spark)
    rows = _labelled(spark, sf_dir).where("quality IS NOT NULL").withColumn("n", F.col("n_chars").cast("double"))
    made = rows.groupBy("lang").agg(sql_surface.rank_auc("n", "quality").alias("auc"))
    return made.where(F.col("auc").isNotNull() & ~F.isnan("auc")).select("lang", F.round("auc", 6).alias("auc"))


@TABLE.query()
def op_sample_strata(spark, sf_dir):
    """Spark's own stratified sample depends on its generator: rows only."""
    return t(spark, sf_dir, "documents", "doc_id", "lang").sampleBy("lang", {"en": 0.2, "de": 0.5}, seed=3)


@TABLE.query("SELECT lang, count(DISTINCT source) AS sources, list_sort(list(DISTINCT source))[1] AS first_source, bool_or(n_chars > 10000) AS any_long FROM documents GROUP BY lang")
def op_agg_collections(spark, sf_dir):
    return t(spark, sf_dir, "documents", "lang", "source", "n_chars").groupBy("lang").agg(
        F.count_distinct("source").alias("sources"), F.get(F.sort_array(F.collect_set("source")), F.lit(0)).alias("first_source"),
        F.bool_or(F.col("n_chars") > 10_000).alias("any_long"),
    )
