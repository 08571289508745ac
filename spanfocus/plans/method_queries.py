"""Registered queries of the method itself: preparation, attention, scores, selection, baselines."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanfocus.functions import text as T
from spanfocus.geometry import Geometry
from spanfocus.operators import delta, focus, lexical, samples, select, states, trained
from spanfocus.plans import oracles as O
from spanfocus.plans.entry_table import EntryTable
from spanfocus.session import cut, spread
from spanfocus.sources.tables import read_table

TABLE = EntryTable()
DESK, VECTORS = Geometry.named("desk"), Geometry.named("vectors")
#: Share of the eligible tokens that a selection takes.
BUDGET_SHARE = 0.25


def docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spread(read_table(spark, sf_dir, "documents"))


def desk(spark: SparkSession, sf_dir: str, domain: str = "source", g: Geometry = DESK) -> DataFrame:
    return samples.samples(docs(spark, sf_dir), g, domain)


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    """Six places, without a negative zero."""
    return df.withColumns({c: F.round(c, 6) + F.lit(0.0) for c in columns})


def desk_scores(spark: SparkSession, sf_dir: str, domain: str = "source", variant: str = "full", g: Geometry = DESK, keep: bool = True) -> DataFrame:
    """(doc_id, domain, n_tokens, score) by the one-pass kernel; written once, since selections read it several times."""
    table = lexical.weight_table(docs(spark, sf_dir))
    made = lexical.score_documents(desk(spark, sf_dir, domain, g), table, g, [variant])
    made = made.select("doc_id", "domain", "n_tokens", F.col(f"{variant}_{g.row_stride}_{g.col_stride}").alias("score"))
    return cut(made) if keep else made


def budget_of(scored: DataFrame, share: float = BUDGET_SHARE) -> int:
    return int((scored.agg(F.sum("n_tokens")).first()[0] or 0) * share)


def delta_scores(spark: SparkSession, sf_dir: str, options: delta.DeltaOptions = delta.DeltaOptions()) -> DataFrame:
    table = delta.unigram_table(docs(spark, sf_dir))
    return cut(delta.delta_perplexity(desk(spark, sf_dir), table, {"score": options}))


def long_pairs(spark: SparkSession, sf_dir: str, g: Geometry = DESK, **how: bool) -> DataFrame:
    return lexical.pair_focus(desk(spark, sf_dir, g=g), lexical.token_weights(docs(spark, sf_dir)), g, **how)


# Preparation.


@TABLE.query(f"SELECT doc_id, len(regexp_extract_all(coalesce(text, ''), '{O.TOKEN}'))::INT AS n_tokens FROM documents")
def tokens_per_document(spark: SparkSession, sf_dir: str) -> DataFrame:
    return samples.tokenize(docs(spark, sf_dir).select("doc_id", "text")).select("doc_id", "n_tokens")


@TABLE.query(f"{O.with_(O.base(DESK))} SELECT doc_id, domain, len(tokens)::INT AS kept, md5(array_to_string(tokens, ' ')) AS tokens_md5 FROM el")
def eligible_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = desk(spark, sf_dir)
    return made.select("doc_id", "domain", F.size("tokens").alias("kept"), F.md5(F.array_join("tokens", " ")).alias("tokens_md5"))


@TABLE.query(f"""{O.with_(O.base(DESK))} SELECT doc_id, (p // {DESK.span})::INT AS j, count(*)::INT AS span_tokens,
    md5(string_agg(token, ' ' ORDER BY p)) AS span_md5 FROM pos GROUP BY ALL""")
def span_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = samples.spans(desk(spark, sf_dir), DESK, "long")
    return made.select("doc_id", "j", F.size("span_tokens").alias("span_tokens"), F.md5(F.array_join("span_tokens", " ")).alias("span_md5"))


def _census(domain: str) -> None:
    g = DESK.length
    sql = f"""WITH t AS (SELECT {domain} AS domain, len(regexp_extract_all(coalesce(text, ''), '{O.TOKEN}')) AS n FROM documents),
        c AS (SELECT domain, count(*) AS docs, sum(n)::BIGINT AS tokens, count(*) FILTER (n >= {g}) AS long_docs,
            (count(*) FILTER (n >= {g}) * {g})::BIGINT AS long_tokens FROM t GROUP BY domain)
        SELECT domain, docs, tokens, round(tokens / sum(tokens) OVER (), 6) AS share, long_docs, long_tokens,
            round(long_tokens / sum(long_tokens) OVER (), 6) AS kept_share FROM c"""

    def census(spark: SparkSession, sf_dir: str) -> DataFrame:
        made = samples.length_census(samples.tokenize(docs(spark, sf_dir)), g, domain)
        return rounded(made, "share", "kept_share")

    TABLE.add(f"length_census_{domain}", census, sql)


_census("source")
_census("lang")


def _concatenated(piece: int) -> None:
    k = DESK.length // piece
    sql = f"""WITH t AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{O.TOKEN}') AS tokens FROM documents),
        o AS (SELECT doc_id, tokens[1:{piece}] AS tokens, row_number() OVER (ORDER BY md5('1:' || doc_id::VARCHAR), doc_id) - 1 AS place
            FROM t WHERE len(tokens) >= {piece}),
        s AS (SELECT (place // {k})::INT AS sample_id, list(doc_id ORDER BY place) AS parts,
            flatten(list(tokens ORDER BY place)) AS tokens FROM o GROUP BY ALL HAVING count(*) = {k})
        SELECT sample_id, {piece} AS piece_len, len(parts)::INT AS n_parts, array_to_string(parts, ',') AS part_ids,
            len(tokens)::INT AS n_tokens, md5(array_to_string(tokens, ' ')) AS tokens_md5 FROM s"""

    def concatenated(spark: SparkSession, sf_dir: str) -> DataFrame:
        made = samples.concatenate(samples.tokenize(docs(spark, sf_dir)), DESK.length, piece)
        ids = F.array_join(F.transform("parts", lambda p: p["doc_id"].cast("string")), ",")
        return made.select(
            "sample_id", "piece_len", F.size("parts").alias("n_parts"), ids.alias("part_ids"), F.size("tokens").alias("n_tokens"),
            F.md5(F.array_join("tokens", " ")).alias("tokens_md5"),
        )

    TABLE.add(f"concatenated_samples_{piece}", concatenated, sql)


for _piece in (64, 128, 256):
    _concatenated(_piece)


@TABLE.query(f"""{O.with_(O.base(DESK))}, o AS (SELECT doc_id, tokens, row_number() OVER (ORDER BY md5('1:' || doc_id::VARCHAR), doc_id)::INT AS place FROM el)
    SELECT doc_id, place, md5(array_to_string(tokens, ' ')) AS tokens_md5 FROM o WHERE place <= {20_000 // DESK.length}""")
def training_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = samples.training_sequences(samples.tokenize(docs(spark, sf_dir)), DESK.length, 20_000)
    return made.select("doc_id", "place", F.md5(F.array_join("tokens", " ")).alias("tokens_md5"))


@TABLE.query("""SELECT conv_id, count(*) AS n_turns, string_agg(coalesce(role, '') || ': ' || coalesce(text, ''), chr(10) ORDER BY turn) AS text
    FROM conversations GROUP BY conv_id""")
def folded_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return samples.fold_conversations(read_table(spark, sf_dir, "conversations"))


def _page_sql() -> str:
    steps = (
        (r"(?is)<script[^>]*>.*?</script>", " "), (r"(?is)<style[^>]*>.*?</style>", " "), (r"(?s)<!--.*?-->", " "),
        (r"(?s)<[^>]*>", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&"), (r"[ \t\r\n]+", " "),
    )
    out = "html"
    for pattern, to in steps:
        out = f"regexp_replace({out}, '{pattern}', '{to}', 'g')"
    return f"SELECT page_id, length(trim({out})) AS chars, md5(trim({out})) AS text_md5 FROM pages"


@TABLE.query(_page_sql())
def page_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = read_table(spark, sf_dir, "pages", "page_id", "html").select("page_id", T.page_text("html").alias("t"))
    return made.select("page_id", F.length("t").cast("bigint").alias("chars"), F.md5("t").alias("text_md5"))


@TABLE.query(f"""WITH t AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{O.TOKEN}') AS tokens FROM documents),
    c AS (SELECT doc_id, tokens, unnest(range(len(tokens) // {DESK.length}))::INT AS chunk_no FROM t)
    SELECT doc_id, chunk_no, md5(array_to_string(tokens[chunk_no * {DESK.length} + 1:(chunk_no + 1) * {DESK.length}], ' ')) AS tokens_md5 FROM c""")
def chunked_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = samples.chunk(samples.tokenize(docs(spark, sf_dir)), DESK.length)
    return made.select("doc_id", "chunk_no", F.md5(F.array_join("tokens", " ")).alias("tokens_md5"))


# Attention.


@TABLE.query(f"""SELECT token, count(*) AS df FROM (
    SELECT DISTINCT doc_id, unnest(regexp_extract_all(coalesce(text, ''), '{O.TOKEN}')) AS token FROM documents) GROUP BY token""")
def document_frequency(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lexical.document_frequency(docs(spark, sf_dir))


_PAIRS = "SELECT doc_id, j, i, round(pair_focus, 6) AS pair_focus FROM pf"


@TABLE.query(f"{O.with_(O.base(DESK), O.pairs(DESK))} {_PAIRS}")
def pair_focus_lexical(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(long_pairs(spark, sf_dir), "pair_focus")


@TABLE.query(f"{O.with_(O.base(DESK), O.pairs(DESK))} {_PAIRS}")
def pair_focus_arrow(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = lexical.pair_focus_kernel(desk(spark, sf_dir), lexical.weight_table(docs(spark, sf_dir)), DESK)
    return rounded(made, "pair_focus")


@TABLE.query(f"{O.with_(O.base(DESK), O.pairs(DESK, causal=False))} {_PAIRS}")
def pair_focus_literal_mask(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(long_pairs(spark, sf_dir, causal=False), "pair_focus")


_SMALL = Geometry(256, 8, 1, 2, 2, 2, 8)


@TABLE.query(f"""{O.with_(O.base(_SMALL), O.pairs(_SMALL, everything=True))}
    SELECT doc_id, j, count(*) AS spans, round(sum(pair_focus), 6) AS mass FROM pf GROUP BY ALL""")
def focus_matrix_row_mass(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole matrix, own span included: each row sums to the span length."""
    pairs = long_pairs(spark, sf_dir, _SMALL, all_pairs=True)
    return rounded(pairs.groupBy("doc_id", "j").agg(F.count("*").alias("spans"), F.sum("pair_focus").alias("mass")), "mass")


def _states_sql(tail: str) -> str:
    g = VECTORS
    first = g.first_row
    return f"""WITH v AS (
        SELECT label, embedding, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS p FROM embeddings WHERE embedding IS NOT NULL
    ),
    x AS (SELECT * FROM v WHERE p < {g.length} AND label IN (SELECT label FROM v GROUP BY label HAVING count(*) >= {g.length})),
    mass AS (
        SELECT q.label AS doc_id, q.p AS qp, q.p // {g.span} AS j, k.p // {g.span} AS i,
            exp(list_dot_product(q.embedding::DOUBLE[], k.embedding::DOUBLE[]) / sqrt(len(q.embedding))) AS m
        FROM x q JOIN x k ON q.label = k.label AND k.p <= q.p
        WHERE q.p // {g.span} >= {first} AND (q.p // {g.span} - {first}) % {g.col_stride} = 0
    ),
    total AS (SELECT doc_id, qp, sum(m) AS z FROM mass GROUP BY ALL),
    pf AS (
        SELECT doc_id, j::INT AS j, i::INT AS i, sum(m / z) AS pair_focus FROM mass JOIN total USING (doc_id, qp)
        WHERE i >= {g.skip_first} AND i < j - {g.skip_near} AND (i - {g.skip_first}) % {g.row_stride} = 0 GROUP BY ALL
    ) {tail}"""


@TABLE.query(_states_sql("SELECT doc_id AS label, j, i, round(pair_focus, 6) AS pair_focus FROM pf"))
def pair_focus_states(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = states.pair_focus_states(states.label_samples(read_table(spark, sf_dir, "embeddings"), VECTORS), VECTORS)
    return rounded(made, "pair_focus")


def small_calculator(spark: SparkSession, sf_dir: str, token_budget: int = 20_000, base: float = 10_000.0) -> trained.Calculator:
    drawn = samples.training_sequences(samples.tokenize(docs(spark, sf_dir)), 128, token_budget)
    return trained.train_calculator(drawn, trained.Config(rotary_base=base))


@TABLE.query()
def pair_focus_trained(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pair focus by the trained calculator; SQL cannot state its training."""
    return rounded(states.focus_with_model(desk(spark, sf_dir), small_calculator(spark, sf_dir), DESK), "pair_focus")


@TABLE.query()
def dependency_trained(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = states.score_with_model(desk(spark, sf_dir), small_calculator(spark, sf_dir, base=500_000.0), DESK, ("full", "flat_sigma"))
    return rounded(made, "full", "flat_sigma")


# Scores.

# Ten places first: a value on the half of the sixth place then rounds the same way whatever its last bits are.
_SPAN_VALUES = ("sigma", "weighted_sum", "span_focus")
_SPANS = f"SELECT doc_id, j, n_terms, {', '.join(f'round(round({c}, 10), 6) AS {c}' for c in _SPAN_VALUES)} FROM sf"


def _span_query(name: str, ddof: int) -> None:
    def spans(spark: SparkSession, sf_dir: str) -> DataFrame:
        made = focus.span_focus(long_pairs(spark, sf_dir), DESK, ddof=ddof)
        return rounded(made.withColumns({c: F.round(c, 10) for c in _SPAN_VALUES}), *_SPAN_VALUES)

    TABLE.add(name, spans, f"{O.with_(O.base(DESK), O.pairs(DESK), O.span_rows(DESK, ddof=ddof))} {_SPANS}")


_span_query("span_focus", 0)
_span_query("span_focus_sample_sd", 1)

_DEP = "SELECT doc_id, round(score, 6) AS dependency FROM dep"


def _dependency_query(name: str, variant: str, g: Geometry) -> None:
    def scores(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = focus.span_focus(long_pairs(spark, sf_dir, g), g, variant)
        return rounded(focus.dependency(rows, g, variant, desk(spark, sf_dir, g=g)), "dependency")

    TABLE.add(name, scores, f"{O.with_(O.scored(g, variant))} {_DEP}")


_dependency_query("dependency", "full", DESK)
for _variant in ("flat_sigma", "flat_length", "flat_pair_length", "flat_row_length"):
    _dependency_query(f"dependency_{_variant}", _variant, DESK)
for _a, _b in ((2, 4), (4, 2), (2, 2)):
    _dependency_query(f"dependency_stride_{_a}_{_b}", "full", DESK.with_strides(_a, _b))
_PHASED = Geometry(512, 8, 1, 4, 4, 4, 16, row_phase=1, col_phase=2)
_dependency_query("dependency_phased", "full", _PHASED)


@TABLE.query(f"{O.with_(O.scored(DESK))} {_DEP}")
def dependency_arrow(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(desk_scores(spark, sf_dir, keep=False).select("doc_id", F.col("score").alias("dependency")), "dependency")


@TABLE.query(
    _states_sql(
        f""", sf AS (SELECT doc_id, j, stddev_pop(pair_focus) * sum((j - i) / {VECTORS.n_spans}.0 * pair_focus) AS s FROM pf GROUP BY ALL)
        SELECT doc_id AS label, round(sum(j / {VECTORS.n_spans}.0 * s), 6) AS dependency FROM sf GROUP BY doc_id"""
    )
)
def dependency_states(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = states.pair_focus_states(states.label_samples(read_table(spark, sf_dir, "embeddings"), VECTORS), VECTORS)
    made = focus.dependency(focus.span_focus(pairs.withColumnRenamed("label", "doc_id"), VECTORS), VECTORS)
    return rounded(made.withColumnRenamed("doc_id", "label"), "dependency")


def pieces_table(spark: SparkSession, sf_dir: str, pieces: tuple[int, ...] = (64, 128, 256, 512)) -> DataFrame:
    """(doc_id, domain, n_tokens, tokens) of concatenated samples; the domain is the piece length."""
    rows, out = samples.tokenize(docs(spark, sf_dir)).select("doc_id", "tokens"), None
    for piece in pieces:
        made = samples.concatenate(rows, DESK.length, piece)
        made = made.select(
            (F.col("sample_id") + F.lit(piece * 1_000_000)).cast("bigint").alias("doc_id"), F.lit(piece).alias("domain"),
            F.lit(DESK.length).alias("n_tokens"), "tokens",
        )
        out = made if out is None else out.unionByName(made)
    return out


def _piece_ctes(pieces: tuple[int, ...] = (64, 128, 256, 512)) -> str:
    g = DESK
    parts = " UNION ALL ".join(
        f"""SELECT (place // {g.length // p} + {p * 1_000_000})::BIGINT AS doc_id, {p} AS domain, {g.length} AS n_tokens,
            flatten(list(tokens[1:{p}] ORDER BY place)) AS tokens
        FROM (SELECT doc_id, tokens, row_number() OVER (ORDER BY md5('1:' || doc_id::VARCHAR), doc_id) - 1 AS place FROM tok WHERE len(tokens) >= {p})
        GROUP BY place // {g.length // p} HAVING count(*) = {g.length // p}"""
        for p in pieces
    )
    text = O.base(g)
    start, end = text.index("el AS ("), text.index("idf AS (")
    return text[:start] + f"el AS ({parts}),\n    " + text[end:]


@TABLE.query(f"""{O.with_(_piece_ctes(), O.pairs(DESK))}
    SELECT domain AS piece_len, count(*) AS n_pairs, round(median(pair_focus), 6) AS median_focus, round(avg(pair_focus), 6) AS mean_focus
    FROM pf JOIN el USING (doc_id) WHERE j - i >= 32 GROUP BY domain""")
def long_range_median_by_piece(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = pieces_table(spark, sf_dir)
    pairs = lexical.pair_focus_kernel(rows, lexical.weight_table(docs(spark, sf_dir)), DESK)
    tagged = cut(pairs.where("j - i >= 32").select(F.floor(F.col("doc_id") / 1_000_000).cast("int").alias("piece_len"), "j", "i", "pair_focus"))
    return rounded(focus.long_range_stats(tagged, 32, ["piece_len"]), "median_focus", "mean_focus")


@TABLE.query(f"""{O.with_(O.base(DESK), O.pairs(DESK))} SELECT * FROM (
    SELECT doc_id, row_number() OVER (PARTITION BY doc_id ORDER BY round(pair_focus, 6) DESC, j, i)::INT AS rank, j, i, round(pair_focus, 6) AS pair_focus
    FROM pf) WHERE rank <= 3""")
def explain_score_top_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(focus.top_pairs(long_pairs(spark, sf_dir), 3), "pair_focus")


# Selection.

_CHOSEN = "SELECT doc_id, domain, score, domain_rank, n_tokens, cum_tokens, quota_tokens FROM sel"


@TABLE.query(f"""{O.with_(O.scored(DESK))} SELECT doc_id, round(score, 6) AS score FROM dep ORDER BY round(score, 6) DESC, doc_id LIMIT 50""")
def select_top_global(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(select.select_top(desk_scores(spark, sf_dir), 50).select("doc_id", "score"), "score")


def _budget_query(name: str, domain: str) -> None:
    def chosen(spark: SparkSession, sf_dir: str) -> DataFrame:
        scored = desk_scores(spark, sf_dir, domain)
        return rounded(select.select_by_domain(scored, budget_of(scored)), "score")

    TABLE.add(name, chosen, f"{O.with_(O.scored(DESK, domain=domain), O.quota(BUDGET_SHARE), O.chosen('sel', 'dep'))} {_CHOSEN}")


_budget_query("select_domain_budget", "source")
_budget_query("select_domain_budget_lang", "lang")


@TABLE.query(f"""{O.with_(O.scored(DESK, domain="lang"))} SELECT doc_id, domain, score, domain_rank FROM (
    SELECT doc_id, domain, round(score, 6) AS score, row_number() OVER (PARTITION BY domain ORDER BY round(score, 6) DESC, doc_id)::INT AS domain_rank,
        floor(count(*) OVER (PARTITION BY domain) * 0.1::DOUBLE + 1e-9) AS k FROM dep) WHERE domain_rank <= k""")
def select_domain_fraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(select.select_fraction(desk_scores(spark, sf_dir, "lang"), 0.1), "score")


@TABLE.query(f"""{O.with_(O.scored(DESK), O.quota(BUDGET_SHARE), O.chosen('sel', 'dep'))} SELECT doc_id, domain, score, n_tokens FROM sel""")
def select_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = desk_scores(spark, sf_dir)
    return rounded(select.select_by_threshold(scored, budget_of(scored)), "score")


def _random_order(seed: int) -> str:
    return O.chosen("sel", "el", f"md5('{seed}:' || doc_id::VARCHAR)", "0.0::DOUBLE")


def _random_query(seed: int) -> None:
    def chosen(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = desk(spark, sf_dir)
        return select.select_random(rows, budget_of(rows), seed)

    TABLE.add(f"select_random_seed_{seed}", chosen, f"{O.with_(O.base(DESK), O.quota(BUDGET_SHARE), _random_order(seed))} {_CHOSEN}")


for _seed in (1, 2, 3):
    _random_query(_seed)

_DELTA = O.base(DESK), O.unigrams(), O.deltas(), O.delta_score()


@TABLE.query(f"{O.with_(*_DELTA, O.quota(BUDGET_SHARE), O.chosen('sel', 'del', 'round(score, 3) DESC', 'round(score, 3)'))} {_CHOSEN}")
def select_delta_perplexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Delta scores reach millions: three places are what both engines agree on."""
    scored = delta_scores(spark, sf_dir).withColumn("score", F.round("score", 3))
    return select.select_by_domain(scored, budget_of(scored))


@TABLE.query(f"""{O.with_(O.scored(DESK, domain="lang"), O.quota(BUDGET_SHARE), O.chosen('sel', 'dep'))}
    SELECT domain, count(*) AS docs, sum(n_tokens)::BIGINT AS tokens, round(sum(n_tokens) / sum(sum(n_tokens)) OVER (), 6) AS share FROM sel GROUP BY domain""")
def selection_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = desk_scores(spark, sf_dir, "lang")
    return rounded(select.mix(select.select_by_domain(scored, budget_of(scored))), "share")


@TABLE.query(f"""{O.with_(O.scored(DESK), O.quota(BUDGET_SHARE), O.chosen('a', 'dep'), _random_order(1).replace('sel AS', 'b AS', 1))}
    SELECT count(a.doc_id) AS in_a, count(b.doc_id) AS in_b, count(*) FILTER (a.doc_id IS NOT NULL AND b.doc_id IS NOT NULL) AS in_both,
        round(in_both / count(*), 6) AS jaccard, round(in_both / least(in_a, in_b), 6) AS overlap_share
    FROM a FULL JOIN b ON a.doc_id = b.doc_id""")
def selection_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = desk_scores(spark, sf_dir)
    budget = budget_of(scored)
    made = select.overlap(select.select_by_domain(scored, budget), select.select_random(scored, budget, 1))
    return rounded(made, "jaccard", "overlap_share")


@TABLE.query("SELECT DISTINCT e.doc_id, e.domain FROM (%s) e JOIN labels l ON e.doc_id = l.doc_id WHERE l.quality = 1 AND l.toxic = 0" % f"{O.with_(O.base(DESK))} SELECT doc_id, domain FROM el")
def select_labelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    return select.select_labelled(desk(spark, sf_dir), read_table(spark, sf_dir, "labels")).select("doc_id", "domain")


# The delta-perplexity baseline.


@TABLE.query(f"{O.with_(O.base(DESK), O.unigrams())} SELECT u.token, u.n, round(p * 1e6, 6) AS p_millionths FROM uni u JOIN prob USING (token)")
def unigram_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = cut(delta.unigram_counts(docs(spark, sf_dir)))
    v, total = counts.agg(F.count("*"), F.sum("n")).first()
    p = (F.col("n") + 1.0) / F.lit(float((total or 0) + v + 1))
    return counts.select("token", "n", F.round(p * 1e6, 6).alias("p_millionths"))


@TABLE.query(f"{O.with_(O.base(DESK), O.unigrams(), O.deltas())} SELECT doc_id, j, round(ppl_alone, 3) AS ppl_alone FROM alone")
def segment_perplexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = delta.segment_perplexity(desk(spark, sf_dir), delta.unigram_table(docs(spark, sf_dir)))
    return made.withColumn("ppl_alone", F.round("ppl_alone", 3))


@TABLE.query(f"""{O.with_(O.base(DESK), O.unigrams(), O.deltas())}
    SELECT doc_id, j, i, round(ppl_alone, 3) AS ppl_alone, round(ppl_given, 3) AS ppl_given, round(ppl_alone - ppl_given, 3) + 0.0 AS gain FROM delta""")
def delta_perplexity_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = delta.delta_pairs(desk(spark, sf_dir), delta.unigram_table(docs(spark, sf_dir)))
    return made.withColumns({c: F.round(c, 3) + F.lit(0.0) for c in ("ppl_alone", "ppl_given", "gain")})


def _delta_query(name: str, options: delta.DeltaOptions, value: str, places: int) -> None:
    def scores(spark: SparkSession, sf_dir: str) -> DataFrame:
        made = delta_scores(spark, sf_dir, options)
        return made.select("doc_id", "domain", F.round("score", places).alias("delta_score"))

    ctes = O.with_(O.base(DESK), O.unigrams(), O.deltas(), O.delta_score(value))
    TABLE.add(name, scores, f"{ctes} SELECT doc_id, domain, round(score, {places}) AS delta_score FROM del")


_delta_query("delta_perplexity_score", delta.DeltaOptions(), "ppl_alone - ppl_given", 3)
_delta_query("delta_relative", delta.DeltaOptions(strength="relative"), "(ppl_alone - ppl_given) / ppl_alone", 6)
_last = DESK.length // 32 - 1
_delta_query("delta_distance", delta.DeltaOptions(distance_weight=True), f"(ppl_alone - ppl_given) * (j - i) / {_last}.0", 3)
_delta_query("delta_threshold", delta.DeltaOptions(strength="relative", threshold=0.0), "greatest((ppl_alone - ppl_given) / ppl_alone, 0)", 6)
_delta_query("delta_near_pairs", delta.DeltaOptions(pairs=4), "CASE WHEN j - i <= 4 THEN ppl_alone - ppl_given ELSE 0 END", 3)
_distinct = "(SELECT count(DISTINCT token) FROM seg s WHERE s.doc_id = delta.doc_id AND s.j = delta.j)"
_delta_query("delta_specificity", delta.DeltaOptions(specificity=True), f"(ppl_alone - ppl_given) * {_distinct} / 32.0", 3)
_number = "((doc_id % 1000003) * 31 + i * 7919 + j * 104729 + 2 * 13)::HUGEINT * 2654435761 % 4294967296"
_delta_query("delta_sampled_pairs", delta.DeltaOptions(sampled=0.25, seed=2), f"CASE WHEN {_number} < 0.25 * 4294967296 THEN ppl_alone - ppl_given ELSE 0 END", 3)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Small profile: score by the kernel, select by source under a quarter of the tokens."""
    scored = desk_scores(spark, sf_dir, g=Geometry.named("smoke"))
    return rounded(select.select_by_domain(scored, budget_of(scored)), "score")
