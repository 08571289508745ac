"""Registered queries of the experiments: needles, perplexity, budgets, strides, ablation, categories, proxies."""

from __future__ import annotations

import re
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spanfocus.functions import published
from spanfocus.functions import text as T
from spanfocus.geometry import Geometry, cost_of
from spanfocus.operators import delta, lexical, lm, measures, relational, samples, select, states, trained
from spanfocus.operators.focus import VARIANTS, long_range_stats
from spanfocus.plans import oracles as O
from spanfocus.plans.entry_table import EntryTable
from spanfocus.plans.method_queries import (
    BUDGET_SHARE,
    DESK,
    _piece_ctes,
    budget_of,
    delta_scores,
    desk,
    desk_scores,
    docs,
    pieces_table,
    rounded,
    small_calculator,
)
from spanfocus.session import cut, ship_package
from spanfocus.sources.tables import read_table

TABLE = EntryTable()
WINDOWS = tuple(DESK.length // k for k in (16, 8, 4, 2, 1))
LENGTHS = measures.context_lengths(DESK)


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), frames)


# Needle retrieval.


def lexical_hits(spark: SparkSession, sf_dir: str, hay: DataFrame) -> DataFrame:
    """(hay_doc, context_len, depth, hit) by the kernel: the last span's strongest earlier span, ties to the first."""
    g = DESK
    ship_package(spark)
    shared = spark.sparkContext.broadcast(lexical.gathered(lexical.weight_table(docs(spark, sf_dir))))  # 16 bytes a token
    cases = measures.needle_cases(hay.select("doc_id", "tokens"), read_table(spark, sf_dir, "benchmark"), g, hashed=True)

    def run(batches):
        for batch in batches:
            hits = []
            for first, size, hashes in zip(*(batch.column(c) for c in (3, 4, 5)), strict=True):
                h = hashes.values.to_numpy(zero_copy_only=False)
                last = len(h) // g.span - 1
                mass = lexical.focus_matrix(h, shared.value.of(h), Geometry(len(h), g.span), [last])[g.skip_first : last - g.skip_near, 0]
                best = g.skip_first + int(np.round(mass, 6).argmax()) if mass.size else -1
                hits.append(int(first.as_py() <= best < first.as_py() + size.as_py()))
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(hits, pa.int32())], names=["hay_doc", "context_len", "depth", "hit"])

    columns = ("hay_doc", "context_len", "depth", "needle_span", "needle_spans")
    return cases.select(*columns, "tokens").mapInArrow(run, "hay_doc bigint, context_len int, depth double, hit int")


_NEEDLES = O.with_(O.base(DESK), O.needles(DESK, "el", LENGTHS, measures.DEPTHS))
_GRID = "SELECT context_len, depth, count(*) AS n_cases, round(avg(hit), 6) AS accuracy FROM hits GROUP BY ALL"


@TABLE.query(f"""{_NEEDLES} SELECT hay_doc, needle_id, context_len, depth, needle_span, needle_spans::INT AS needle_spans,
    md5(array_to_string(tokens, ' ')) AS tokens_md5 FROM cases""")
def needle_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = measures.needle_cases(desk(spark, sf_dir).select("doc_id", "tokens"), read_table(spark, sf_dir, "benchmark"), DESK)
    return made.select(
        "hay_doc", "needle_id", "context_len", "depth", "needle_span", "needle_spans", F.md5(F.array_join("tokens", " ")).alias("tokens_md5")
    )


@TABLE.query(f"{_NEEDLES} {_GRID}")
def needle_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(measures.needle_accuracy(lexical_hits(spark, sf_dir, desk(spark, sf_dir))), "accuracy")


@TABLE.query(f"{_NEEDLES}, g AS ({_GRID}) SELECT depth, {', '.join(f'max(accuracy) FILTER (context_len = {n}) AS len_{n}' for n in LENGTHS)} FROM g GROUP BY depth")
def needle_heatmap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.needle_heatmap(needle_accuracy(spark, sf_dir), LENGTHS)


@TABLE.query(f"""{O.with_(_piece_ctes(), O.needles(DESK, "el", LENGTHS, measures.DEPTHS))},
    g AS (SELECT hay_doc // 1000000 AS piece_len, context_len, depth, avg(hit) AS a FROM hits GROUP BY ALL),
    l AS (SELECT piece_len, context_len, avg(a) AS a FROM g GROUP BY ALL)
    SELECT piece_len::INT AS piece_len, context_len, round(a, 6) AS accuracy FROM l
    UNION ALL SELECT piece_len::INT, NULL, round(avg(a), 6) FROM l GROUP BY piece_len""")
def workload_needles_by_piece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Retrieval by the lexical calculator from haystacks built of pieces of several lengths, with the mean."""
    hits = lexical_hits(spark, sf_dir, pieces_table(spark, sf_dir)).withColumn("piece_len", F.floor(F.col("hay_doc") / 1_000_000).cast("int"))
    grid = hits.groupBy("piece_len", "context_len", "depth").agg(F.avg("hit").alias("a"))
    by_length = grid.groupBy("piece_len", "context_len").agg(F.avg("a").alias("accuracy"))
    mean = by_length.groupBy("piece_len").agg(F.avg("accuracy").alias("accuracy")).select("piece_len", F.lit(None).cast("int").alias("context_len"), "accuracy")
    return rounded(by_length.unionByName(mean), "accuracy")


#: Tasks that train apart in a round.
GROUPS = 8


def trained_on(tokens: DataFrame) -> trained.Calculator:
    """A calculator trained on whole rows of (doc_id, tokens), in md5 order, without gathering them."""
    rows = tokens.select("doc_id", "tokens")
    return trained.train_calculator(cut(samples.training_sequences(rows, DESK.length, DESK.length * rows.count())), groups=GROUPS)


def haystacks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Written needle cases of all lengths and depths, in uncut documents."""
    made = measures.needle_cases(desk(spark, sf_dir).select("doc_id", "tokens"), read_table(spark, sf_dir, "benchmark"), DESK, lengths=LENGTHS)
    return cut(made.withColumn("n_spans", F.col("n_spans").cast("int")))


def trained_grid(cases: DataFrame, models: dict[str, trained.Calculator], name: str) -> DataFrame:
    """(name, context_len, depth, n_cases, accuracy) of several calculators in one pass over the cases.

    A case is hit if the last span's strongest earlier span, ties to the first, is one of the needle's.
    """
    g = DESK
    ship_package(cases.sparkSession)
    shared = cases.sparkSession.sparkContext.broadcast(models)

    def run(batches):
        tables = {n: (model, model.by_token(g.length)) for n, model in shared.value.items()}
        for batch in batches:
            hits: dict[str, list[int]] = {n: [] for n in tables}
            for first, size, tokens in zip(*(batch.column(c).to_pylist() for c in (3, 4, 5)), strict=True):
                last, ids = len(tokens) // g.span - 1, {}
                for n, (model, table) in tables.items():
                    v = model.config.vocabulary
                    if v not in ids:
                        ids[v] = model.ids(tokens)
                    mass = table.last_span_mass(ids[v], g.span)[g.skip_first : last - g.skip_near]
                    best = g.skip_first + int(np.round(mass, 6).argmax()) if mass.size else -1
                    hits[n].append(int(first <= best < first + size))
            for n, made in hits.items():
                columns = [pa.array([n] * batch.num_rows, pa.string()), *batch.columns[:3], pa.array(made, pa.int32())]
                yield pa.RecordBatch.from_arrays(columns, names=[name, "hay_doc", "context_len", "depth", "hit"])

    rows = cases.select("hay_doc", "context_len", "depth", "needle_span", "needle_spans", "tokens")
    made = rows.mapInArrow(run, f"{name} string, hay_doc bigint, context_len int, depth double, hit int")
    return made.groupBy(name, "context_len", "depth").agg(F.count("*").alias("n_cases"), F.avg("hit").alias("accuracy"))


def _with_mean(grid: DataFrame, *by: str) -> DataFrame:
    """(by, context_len, accuracy): means over depths, and a row with null length for the mean over lengths."""
    rows = grid.groupBy(*by, "context_len").agg(F.avg("accuracy").alias("accuracy"))
    mean = rows.groupBy(*by).agg(F.avg("accuracy").alias("accuracy")).withColumn("context_len", F.lit(None).cast("int"))
    return rounded(rows.unionByName(mean).select(*by, "context_len", "accuracy"), "accuracy")


PIECES = tuple(DESK.length // k for k in (8, 4, 2, 1))


def piece_calculators(spark: SparkSession, sf_dir: str) -> dict[int, trained.Calculator]:
    """A calculator for each piece length, all trained on as many samples as the scarcest pieces give."""
    rows = cut(pieces_table(spark, sf_dir, PIECES))
    least = min((r["count"] for r in rows.groupBy("domain").count().collect()), default=0)
    out = {}
    for piece in PIECES:
        some = rows.where(F.col("domain") == piece)
        out[piece] = trained.train_calculator(cut(samples.training_sequences(some, DESK.length, DESK.length * least)), groups=GROUPS)
    return out


@TABLE.query()
def workload_needles_trained_on_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Calculators trained on samples of pieces (an eighth, a quarter, half and whole), one token budget, one needle grid.

    Rows (piece_len, context_len, accuracy), a null length for the mean over lengths. SQL cannot state the training.
    """
    made = trained_grid(haystacks(spark, sf_dir), {str(p): m for p, m in piece_calculators(spark, sf_dir).items()}, "piece_len")
    return _with_mean(made.withColumn("piece_len", F.col("piece_len").cast("int")), "piece_len")


@TABLE.query()
def workload_long_range_median_trained(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Median pair focus of far pairs by piece length, by a calculator trained on uncut samples. Rows only."""
    rows = cut(pieces_table(spark, sf_dir, PIECES))
    model = trained_on(rows.where(F.col("domain") == DESK.length))
    far = states.focus_with_model(rows, model, DESK).where("j - i >= 32")
    tagged = cut(far.select(F.floor(F.col("doc_id") / 1_000_000).cast("int").alias("piece_len"), "j", "i", "pair_focus"))
    return rounded(long_range_stats(tagged, 32, ["piece_len"]), "median_focus", "mean_focus")


@TABLE.query()
def workload_needles_by_method(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Retrieval by calculators trained on each method's whole selection, and by the lexical one; rows only."""
    grid = trained_grid(haystacks(spark, sf_dir), {m: trained_on(rows) for m, rows in selections(spark, sf_dir).items()}, "method")
    lexical_grid = needle_accuracy(spark, sf_dir).withColumn("method", F.lit("lexical"))
    return rounded(grid.unionByName(lexical_grid).select("method", "context_len", "depth", "n_cases", "accuracy"), "accuracy")


# Perplexity of selections.


def candidates(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Token table, dependency scores and delta scores of the documents that are not held out, each written once."""
    free = docs(spark, sf_dir).where(~T.is_heldout("text")).select("doc_id")
    tokens = cut(desk(spark, sf_dir).join(free, "doc_id", "left_semi"))
    scored = cut(desk_scores(spark, sf_dir, keep=False).join(free, "doc_id", "left_semi"))
    changed = cut(delta_scores(spark, sf_dir).withColumn("score", F.round("score", 3)).join(free, "doc_id", "left_semi"))
    return tokens, scored, changed


def selections(
    spark: SparkSession, sf_dir: str, share: float = BUDGET_SHARE, seeds: tuple[int, ...] = (1,), found: tuple[DataFrame, DataFrame, DataFrame] | None = None
) -> dict[str, DataFrame]:
    """Token tables of the documents that each method selects, held-out texts apart."""
    tokens, scored, changed = found or candidates(spark, sf_dir)
    budget = budget_of(tokens, share)
    chosen = {"dependency": select.select_by_domain(scored, budget), "delta": select.select_by_domain(changed, budget)}
    chosen |= {f"random_{s}": select.select_random(tokens.select("doc_id", "domain", "n_tokens"), budget, s) for s in seeds}
    return {m: cut(tokens.join(c.select("doc_id"), "doc_id", "left_semi")) for m, c in chosen.items()}


def heldout(spark: SparkSession, sf_dir: str) -> DataFrame:
    texts = docs(spark, sf_dir).where(T.is_heldout("text"))
    return cut(samples.samples(texts, DESK))


def perplexities(chosen: dict[str, DataFrame], test: DataFrame, windows: tuple[int, ...] = WINDOWS) -> DataFrame:
    made = lm.perplexities(chosen, test, windows)
    return made.select("model", "method", F.col("window").alias("window_size"), "n_docs", F.round("ppl", 3).alias("ppl"))


def _selected(methods: dict[str, tuple[str, str, str]], share: float = BUDGET_SHARE, variant: str = "full") -> str:
    """CTEs: scores, a quota over the texts not held out, and one selection of tokens ``s_<method>`` each."""
    ctes = [O.scored(DESK, variant), O.unigrams(), O.deltas(), O.delta_score()]
    ctes += [
        "free AS (SELECT * FROM el WHERE substr(md5(coalesce(text, '')), 1, 1) <> '0')",
        "held AS (SELECT * FROM el WHERE substr(md5(coalesce(text, '')), 1, 1) = '0')",
        "fdep AS (SELECT * FROM dep WHERE doc_id IN (SELECT doc_id FROM free))",
        "fdel AS (SELECT * FROM del WHERE doc_id IN (SELECT doc_id FROM free))",
        O.quota(share, "free"),
    ]
    for name, (of, order, score) in methods.items():
        ctes.append(O.chosen(f"c_{name}", of, order, score))
        ctes.append(f"s_{name} AS (SELECT * FROM free WHERE doc_id IN (SELECT doc_id FROM c_{name}))")
    return ",".join(ctes)


_METHODS = {
    "dependency": ("fdep", "round(score, 6) DESC", "round(score, 6)"),
    "delta": ("fdel", "round(score, 3) DESC", "round(score, 3)"),
    "random_1": ("free", "md5('1:' || doc_id::VARCHAR)", "0.0::DOUBLE"),
}


def _ppl_union(methods) -> str:
    return " UNION ALL ".join(f"SELECT model, '{m}' AS method, window_size, n_docs, round(ppl, 3) AS ppl FROM ppl_{m}" for m in methods)


@TABLE.query(f"{O.with_(_selected(_METHODS), *(O.lm(f's_{m}', 'held', m, WINDOWS) for m in _METHODS))} {_ppl_union(_METHODS)}")
def perplexity_by_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Perplexity of held-out texts by window, for each method's selection and each of four models."""
    return perplexities(selections(spark, sf_dir), heldout(spark, sf_dir))


_SHORT = (16, 32, 64)
_SHORT_TEXT = f"short AS (SELECT doc_id, tokens FROM tok WHERE len(tokens) >= 64 AND len(tokens) < {DESK.length} AND substr(md5(coalesce(text, '')), 1, 1) = '0')"


@TABLE.query(f"{O.with_(_selected(_METHODS), _SHORT_TEXT, *(O.lm(f's_{m}', 'short', m, _SHORT) for m in _METHODS))} {_ppl_union(_METHODS)}")
def short_context_perplexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same models on held-out texts shorter than a sample."""
    texts = samples.tokenize(docs(spark, sf_dir).where(T.is_heldout("text")))
    short = texts.where((F.col("n_tokens") >= 64) & (F.col("n_tokens") < DESK.length)).select("doc_id", "tokens")
    return perplexities(selections(spark, sf_dir), short, _SHORT)


_SEEDED = {f"random_{s}": ("free", f"md5('{s}:' || doc_id::VARCHAR)", "0.0::DOUBLE") for s in (1, 2, 3)}


@TABLE.query(
    f"{O.with_(_selected(_SEEDED), *(O.lm(f's_{m}', 'held', m, WINDOWS) for m in _SEEDED))} "
    f"SELECT model, window_size, round(avg(ppl), 3) AS ppl, count(*) AS n_seeds FROM ({_ppl_union(_SEEDED)}) GROUP BY ALL"
)
def seeds_average(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The random baseline's perplexity averaged over three seeds."""
    chosen, test = selections(spark, sf_dir, seeds=(1, 2, 3)), heldout(spark, sf_dir)
    made = cut(perplexities({f"random_{s}": chosen[f"random_{s}"] for s in (1, 2, 3)}, test))
    measure = lambda s: made.where(F.col("method") == f"random_{s}")
    return select.over_seeds(measure, (1, 2, 3), ["model", "window_size"], "ppl").withColumn("ppl", F.round("ppl", 3))


_SHARES = {"12.5%": 0.125, "25%": 0.25, "37.5%": 0.375, "50%": 0.5}


def _sweep_sql() -> str:
    parts, ctes = [], [O.scored(DESK), O.unigrams(), O.deltas(), O.delta_score()]
    for label, share in _SHARES.items():
        tag = label.rstrip("%").replace(".", "_")
        quota = O.quota(share)
        quota = re.sub(r"\b(mixed|budget|exact|quota)\b", rf"\1_{tag}", quota)
        ctes.append(quota)
        for m, (of, order, score) in {
            "dependency": ("dep", "round(score, 6) DESC", "0.0"), "delta": ("del", "round(score, 3) DESC", "0.0"),
            "random": ("el", "md5('1:' || doc_id::VARCHAR)", "0.0"),
        }.items():
            ctes.append(O.chosen(f"w_{m}_{tag}", of, order, score).replace("JOIN quota", f"JOIN quota_{tag}"))
            parts.append(f"SELECT '{m}' AS method, '{label}' AS budget, domain, count(*) AS docs, sum(n_tokens)::BIGINT AS tokens FROM w_{m}_{tag} GROUP BY domain")
    return f"{O.with_(*ctes)} {' UNION ALL '.join(parts)}"


@TABLE.query(_sweep_sql())
def budget_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each method takes at four budgets, by domain."""
    one = desk_scores(spark, sf_dir).withColumnRenamed("score", "dep")
    two = delta_scores(spark, sf_dir).select("doc_id", F.round("score", 3).alias("del"))
    both = one.join(two, "doc_id")
    total = both.agg(F.sum("n_tokens")).first()[0] or 0
    return select.budget_sweep(
        both,
        {label: int(total * share) for label, share in _SHARES.items()},
        {
            "dependency": lambda t, b: select.select_by_domain(t, b, "dep"),
            "delta": lambda t, b: select.select_by_domain(t, b, "del"),
            "random": lambda t, b: select.select_random(t, b, 1),
        },
    )


def _budget_ppl_sql() -> str:
    ctes, parts = [O.scored(DESK), O.unigrams(), O.deltas(), O.delta_score()], []
    ctes += [
        "free AS (SELECT * FROM el WHERE substr(md5(coalesce(text, '')), 1, 1) <> '0')",
        "held AS (SELECT * FROM el WHERE substr(md5(coalesce(text, '')), 1, 1) = '0')",
        "fdep AS (SELECT * FROM dep WHERE doc_id IN (SELECT doc_id FROM free))",
        "fdel AS (SELECT * FROM del WHERE doc_id IN (SELECT doc_id FROM free))",
    ]
    for label, share in _SHARES.items():
        tag = label.rstrip("%").replace(".", "_")
        ctes.append(re.sub(r"\b(mixed|budget|exact|quota)\b", rf"\1_{tag}", O.quota(share, "free")))
        for m, (of, order, score) in _METHODS.items():
            ctes.append(O.chosen(f"c_{m}_{tag}", of, order, score).replace("JOIN quota", f"JOIN quota_{tag}"))
            ctes.append(f"s_{m}_{tag} AS (SELECT * FROM free WHERE doc_id IN (SELECT doc_id FROM c_{m}_{tag}))")
            ctes.append(O.lm(f"s_{m}_{tag}", "held", f"{m}_{tag}", (DESK.length,)))
            parts.append(f"SELECT '{label}' AS budget, '{m}' AS method, model, window_size, n_docs, round(ppl, 3) AS ppl FROM ppl_{m}_{tag}")
    return f"{O.with_(*ctes)} {' UNION ALL '.join(parts)}"


@TABLE.query(_budget_ppl_sql())
def budget_perplexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Held-out perplexity of the twelve selections of three methods at four budgets, at the whole window."""
    found, chosen = candidates(spark, sf_dir), {}
    for label, share in _SHARES.items():
        chosen |= {f"{label} {m}": rows for m, rows in selections(spark, sf_dir, share, found=found).items()}
    made = perplexities(chosen, heldout(spark, sf_dir), (DESK.length,))
    names = {"budget": F.substring_index("method", " ", 1), "method": F.substring_index("method", " ", -1)}
    return made.withColumns(names)


@TABLE.query()
def budget_needles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Retrieval by calculators trained on each of the twelve selections, mean over depths and lengths. Rows only."""
    found, models = candidates(spark, sf_dir), {}
    for label, share in _SHARES.items():
        models |= {f"{label} {m}": trained_on(rows) for m, rows in selections(spark, sf_dir, share, found=found).items()}
    by_length = _with_mean(trained_grid(haystacks(spark, sf_dir), models, "name"), "name").where("context_len IS NULL")
    return by_length.select(F.substring_index("name", " ", 1).alias("budget"), F.substring_index("name", " ", -1).alias("method"), "accuracy")


_ABLATION = ("full", "flat_sigma", "flat_length")


def _ablation_sql() -> str:
    ctes, parts = [O.base(DESK), O.pairs(DESK)], []
    for v in _ABLATION:
        ctes += [O.span_rows(DESK, v).replace("sf AS (", f"sf_{v} AS ("), O.dependency(DESK, v, f"dep_{v}", f"sf_{v}")]
    ctes += [
        "free AS (SELECT * FROM el WHERE substr(md5(coalesce(text, '')), 1, 1) <> '0')",
        "held AS (SELECT * FROM el WHERE substr(md5(coalesce(text, '')), 1, 1) = '0')",
        O.quota(BUDGET_SHARE, "free"),
    ]
    for v in _ABLATION:
        ctes += [
            f"f_{v} AS (SELECT * FROM dep_{v} WHERE doc_id IN (SELECT doc_id FROM free))", O.chosen(f"c_{v}", f"f_{v}"),
            f"s_{v} AS (SELECT * FROM free WHERE doc_id IN (SELECT doc_id FROM c_{v}))", O.lm(f"s_{v}", "held", v, WINDOWS),
        ]
        parts.append(f"SELECT '{v}' AS variant, model, window_size, round(ppl, 3) AS ppl FROM ppl_{v}")
    return f"{O.with_(*ctes)} {' UNION ALL '.join(parts)}"


def ablation_selections(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """Token tables selected by the full score and by the score without either weight."""
    table, rows = lexical.weight_table(docs(spark, sf_dir)), desk(spark, sf_dir)
    free = docs(spark, sf_dir).where(~T.is_heldout("text")).select("doc_id")
    scored = cut(lexical.score_documents(rows, table, DESK, _ABLATION).join(free, "doc_id", "left_semi"))
    tokens, budget = cut(rows.join(free, "doc_id", "left_semi")), budget_of(scored)
    chosen = {v: select.select_by_domain(scored, budget, f"{v}_4_4") for v in _ABLATION}
    return {v: cut(tokens.join(c.select("doc_id"), "doc_id", "left_semi")) for v, c in chosen.items()}


@TABLE.query(_ablation_sql())
def ablation_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Selections by the full score and without either weight, measured by held-out perplexity."""
    made = perplexities(ablation_selections(spark, sf_dir), heldout(spark, sf_dir))
    return made.select(F.col("method").alias("variant"), "model", "window_size", "ppl")


@TABLE.query()
def ablation_needles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same selections measured by the retrieval of calculators trained on them. Rows only."""
    models = {v: trained_on(rows) for v, rows in ablation_selections(spark, sf_dir).items()}
    return _with_mean(trained_grid(haystacks(spark, sf_dir), models, "variant"), "variant")


# Published numbers.


def _values(rows: list[tuple]) -> str:
    return ", ".join("(" + ", ".join(repr(v) for v in r) + ")" for r in rows)


_ROLLUP = """cat AS (SELECT model, method, budget, category, avg(score::DOUBLE) AS score FROM task GROUP BY ALL),
    roll AS (SELECT model, method, budget, 'category' AS level, category, score FROM cat
        UNION ALL SELECT model, method, budget, 'overall', 'overall', avg(score) FROM cat GROUP BY ALL)"""


#: Characters from which on a text counts as long.
_LONG = 1_500
#: Draws of the given documents: method, seed of its md5 order, which texts it takes.
_DRAWS = (("random", 1, "true"), ("short", 2, f"n < {_LONG}"), ("long", 3, f"n >= {_LONG}"))
_GIVEN_CTE = f"""own AS (SELECT l.quality, 1 - l.toxic AS clean, d.lang AS category, d.source AS task, length(coalesce(d.text, '')) AS n, d.doc_id
        FROM documents d JOIN labels l ON d.doc_id = l.doc_id),
    drawn AS ({" UNION ALL ".join(
        f"SELECT '{m}' AS method, '{b}' AS budget, quality, clean, category, task FROM own WHERE {rule} AND substr(md5('{seed}:' || doc_id::VARCHAR), 1, 1) < '{below}'"
        for m, seed, rule in _DRAWS for b, below in (("1B", "4"), ("2B", "8")))}),
    task AS (SELECT 'quality' AS model, method, budget, category, task, 100.0::DOUBLE * avg(quality) AS score FROM drawn GROUP BY ALL
        UNION ALL SELECT 'clean', method, budget, category, task, 100.0::DOUBLE * avg(clean) FROM drawn GROUP BY ALL)"""


def drawn_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(method, budget, quality, clean, category, task): labelled documents drawn by each method under one budget and two."""
    texts = read_table(spark, sf_dir, "documents", "doc_id", "text", "lang", "source")
    rows = texts.select("doc_id", F.col("lang").alias("category"), F.col("source").alias("task"), F.length(F.coalesce("text", F.lit(""))).alias("n"))
    labels = read_table(spark, sf_dir, "labels").select("doc_id", "quality", (1 - F.col("toxic")).alias("clean"))
    taken = []
    for method, seed, rule in _DRAWS:
        first = F.substring(T.random_order("doc_id", seed), 1, 1)
        taken += [F.when(F.expr(rule) & (first < below), F.struct(F.lit(method).alias("method"), F.lit(b).alias("budget"))) for b, below in (("1B", "4"), ("2B", "8"))]
    made = rows.join(labels, "doc_id").withColumn("d", F.explode(F.array_compact(F.array(*taken))))
    return made.select("d.method", "d.budget", "quality", "clean", "category", "task")


def given_task_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(model, method, budget, category, task, score): share of good labels in what a method draws; languages hold sources."""
    by = ["method", "budget", "category", "task"]
    shares = drawn_labels(spark, sf_dir).groupBy(*by).agg(*((100.0 * F.avg(m)).alias(m) for m in ("quality", "clean")))
    models = F.explode(F.array(*(F.struct(F.lit(m).alias("model"), F.col(m).alias("score")) for m in ("quality", "clean"))))
    return shares.select(*by, models.alias("m")).select("m.model", *by, "m.score")


@TABLE.query(f"WITH {_GIVEN_CTE}, {_ROLLUP} SELECT model, method, budget, level, category, round(score, 4) AS score FROM roll")
def task_rollup_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W7 (a): the roll-up of the published tables (task, category, overall), over scores of the given documents."""
    return measures.task_rollup(given_task_scores(spark, sf_dir)).withColumn("score", F.round("score", 4))


@TABLE.query(f"""WITH {_GIVEN_CTE}, {_ROLLUP},
    d AS (SELECT a.model, a.category, a.score, b.score AS base_score, a.score - b.score AS gain FROM roll a JOIN roll b USING (model, category)
        WHERE a.method = 'long' AND b.method = 'short' AND a.budget = '1B' AND b.budget = '1B'),
    u AS (SELECT * FROM d UNION ALL SELECT 'mean', 'overall', avg(score), avg(base_score), avg(gain) FROM d WHERE category = 'overall')
    SELECT model, category, round(score, 4) AS score, round(base_score, 4) AS base_score, round(gain, 4) AS gain FROM u""")
def improvement_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Gains of one method over another, with the mean over models, as published; over the given documents."""
    made = measures.improvement(measures.task_rollup(given_task_scores(spark, sf_dir).where("budget = '1B'")), "long", "short")
    return made.withColumns({c: F.round(c, 4) + F.lit(0.0) for c in ("score", "base_score", "gain")})


@TABLE.query(f"""WITH {_GIVEN_CTE}, {_ROLLUP}
    SELECT a.model, a.method || ' 1B' AS method, a.category, round(a.score - r.score, 2) AS gain_over_random_2b, round(a.score - d.score, 2) AS gain_over_short_2b
    FROM roll a JOIN roll r ON a.model = r.model AND a.category = r.category AND r.method = 'random' AND r.budget = '2B'
        JOIN roll d ON a.model = d.model AND a.category = d.category AND d.method = 'short' AND d.budget = '2B'
    WHERE a.method = 'long' AND a.budget = '1B'""")
def improvement_over_double_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One budget of a method against two of either baseline, over the given documents."""
    rows = measures.task_rollup(given_task_scores(spark, sf_dir))
    pick = lambda m, b, n: rows.where((F.col("method") == m) & (F.col("budget") == b)).select("model", "category", F.col("score").alias(n))
    made = pick("long", "1B", "s").join(pick("random", "2B", "r"), ["model", "category"]).join(pick("short", "2B", "d"), ["model", "category"])
    return made.select(
        "model", F.lit("long 1B").alias("method"), "category", (F.round(F.col("s") - F.col("r"), 2) + F.lit(0.0)).alias("gain_over_random_2b"),
        (F.round(F.col("s") - F.col("d"), 2) + F.lit(0.0)).alias("gain_over_short_2b"),
    )


@TABLE.query(f"""WITH {_GIVEN_CTE}, {_ROLLUP},
    pooled AS (SELECT 'quality' AS model, method, budget, category, 100.0::DOUBLE * avg(quality) AS stated FROM drawn GROUP BY ALL
        UNION ALL SELECT 'clean', method, budget, category, 100.0::DOUBLE * avg(clean) FROM drawn GROUP BY ALL)
    SELECT model, method, budget, category, round(stated, 4) AS stated, round(r.score, 4) AS computed
    FROM pooled p JOIN roll r USING (model, method, budget, category) WHERE r.level = 'category' AND abs(stated - r.score) > 0.011""")
def table_inconsistencies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Averages over all documents of a category that the scores of its own tasks do not give."""
    by = ["method", "budget", "category"]
    pooled = drawn_labels(spark, sf_dir).groupBy(*by).agg(*((100.0 * F.avg(m)).alias(m) for m in ("quality", "clean")))
    models = F.explode(F.array(*(F.struct(F.lit(m).alias("model"), F.col(m).alias("stated")) for m in ("quality", "clean"))))
    pooled = pooled.select(*by, models.alias("m")).select("m.model", *by, "m.stated")
    made = measures.task_rollup(given_task_scores(spark, sf_dir)).where("level = 'category'").select("model", *by, F.col("score").alias("computed"))
    off = pooled.join(made, ["model", *by]).where(F.abs(F.col("stated") - F.col("computed")) > 0.011)
    return off.select("model", *by, F.round("stated", 4).alias("stated"), F.round("computed", 4).alias("computed"))


_BY_LENGTH = {"short": "length(text) < 4500", "long": "length(text) >= 4500", "random": "substr(md5('1:' || doc_id::VARCHAR), 1, 1) < '8'"}
_FREE = "substr(md5(coalesce(text, '')), 1, 1) <> '0'"


@TABLE.query(f"""{O.with_(O.base(DESK), "held AS (SELECT * FROM el WHERE NOT (" + _FREE + "))",
        *(f"s_{m} AS (SELECT * FROM el WHERE {_FREE} AND {rule})" for m, rule in _BY_LENGTH.items()), *(O.lm(f"s_{m}", "held", m, WINDOWS) for m in _BY_LENGTH))},
    p AS ({" UNION ALL ".join(f"SELECT model, '{m}' AS method, window_size, round(ppl, 3) AS ppl FROM ppl_{m}" for m in _BY_LENGTH)})
    SELECT a.model, a.window_size::INT AS window_size, round(min(b.ppl) - any_value(a.ppl), 3) AS margin, any_value(a.ppl) < min(b.ppl) AS lowest
    FROM p a JOIN p b ON a.model = b.model AND a.window_size = b.window_size AND b.method <> 'long' WHERE a.method = 'long' GROUP BY ALL""")
def perplexity_margins_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How far a method's perplexities lie below the better of two others, setting by setting; selections of the given documents."""
    texts = docs(spark, sf_dir).where(~T.is_heldout("text"))
    rules = {"short": F.length("text") < 4500, "long": F.length("text") >= 4500, "random": F.substring(T.random_order("doc_id", 1), 1, 1) < "8"}
    rows = perplexities({m: cut(samples.samples(texts.where(rule), DESK)) for m, rule in rules.items()}, heldout(spark, sf_dir))
    own, rest = F.min(F.when(F.col("method") == "long", F.col("ppl"))), F.min(F.when(F.col("method") != "long", F.col("ppl")))
    made = rows.groupBy("model", F.col("window_size")).agg(own.alias("own"), rest.alias("rest")).where("own IS NOT NULL AND rest IS NOT NULL")
    return made.select("model", "window_size", (F.round(F.col("rest") - F.col("own"), 3) + F.lit(0.0)).alias("margin"), (F.col("own") < F.col("rest")).alias("lowest"))


@TABLE.query(f"""WITH n AS ({TABLE.oracles["workload_needles_by_piece"]}),
    m AS (SELECT piece_len, avg(accuracy) FILTER (context_len IS NOT NULL) AS m, max(accuracy) FILTER (context_len IS NULL) AS stated FROM n GROUP BY piece_len)
    SELECT piece_len, round(m, 4) AS mean_accuracy, stated, abs(m - stated) < 0.0051 AS agrees, coalesce(m > lag(m) OVER (ORDER BY piece_len), TRUE) AS rises FROM m""")
def needles_by_piece_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Means over context lengths of the given documents' accuracies: do they give the stated means, and rise with the piece?"""
    rows = workload_needles_by_piece(spark, sf_dir)
    mean, stated = F.avg(F.when(F.col("context_len").isNotNull(), F.col("accuracy"))), F.max(F.when(F.col("context_len").isNull(), F.col("accuracy")))
    made = cut(rows.groupBy("piece_len").agg(mean.alias("m"), stated.alias("stated")))
    before = F.lag("m").over(Window.orderBy("piece_len"))
    return made.select(
        "piece_len", F.round("m", 4).alias("mean_accuracy"), "stated", (F.abs(F.col("m") - F.col("stated")) < 0.0051).alias("agrees"),
        F.coalesce(F.col("m") > before, F.lit(True)).alias("rises"),
    )


_ABLATED = ",".join((O.base(DESK, "lang"), O.pairs(DESK), *(
    o for v in _ABLATION for o in (O.span_rows(DESK, v).replace("sf AS (", f"sf_{v} AS ("), O.dependency(DESK, v, f"dep_{v}", f"sf_{v}")))))


@TABLE.query(f"""WITH {_ABLATED}, r AS ({" UNION ALL ".join(f"SELECT '{v}' AS variant, domain, score::DOUBLE AS score FROM dep_{v}" for v in _ABLATION)}),
    b AS (SELECT variant, domain AS category, avg(score) AS score FROM r GROUP BY ALL UNION ALL SELECT variant, 'overall', avg(score) FROM r GROUP BY ALL)
    SELECT x.variant, x.category, round(y.score - x.score, 4) AS falls_by, y.score > x.score AS falls
    FROM b x JOIN b y ON x.category = y.category AND y.variant = 'full' WHERE x.variant <> 'full'""")
def ablation_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the mean score of the given documents loses without either weight, by language and overall."""
    made = lexical.score_documents(desk(spark, sf_dir, "lang"), lexical.weight_table(docs(spark, sf_dir)), DESK, _ABLATION)
    cells = F.explode(F.array(*(F.struct(F.lit(v).alias("variant"), F.col(f"{v}_4_4").alias("score")) for v in _ABLATION)))
    rows = cut(made.select("domain", cells.alias("c")).select(F.explode(F.array("domain", F.lit("overall"))).alias("category"), "c.*").groupBy("category", "variant").agg(F.avg("score").alias("score")))
    full = rows.where("variant = 'full'").select("category", F.col("score").alias("whole"))
    both = rows.where("variant <> 'full'").join(full, "category")
    fall = F.round(F.col("whole") - F.col("score"), 4) + F.lit(0.0)
    return both.select("variant", "category", fall.alias("falls_by"), (F.col("whole") > F.col("score")).alias("falls"))


# Strides and cost.

_STRIDES = ((4, 4), (2, 4), (4, 2), (2, 2))
#: Samples of the stride study, as published.
_DRAWN = 5_000


def _stride_sql(most: int | None = _DRAWN) -> str:
    ctes, cols = [O.base(DESK)], []
    for a, b in _STRIDES:
        g, t = DESK.with_strides(a, b), f"{a}{b}"
        p = O.pairs(g)
        for n in ("mass", "total", "pf"):
            p = p.replace(f"{n} AS (", f"{n}{t} AS (").replace(f"FROM {n} ", f"FROM {n}{t} ").replace(f"JOIN {n} ", f"JOIN {n}{t} ")
        s = O.span_rows(g).replace("sf AS (", f"sf{t} AS (").replace("FROM pf ", f"FROM pf{t} ")
        ctes += [p, s, O.dependency(g, "full", f"dep{t}", f"sf{t}")]
        cols.append(f"round(d{t}.score, 6) AS s{t}")
    joins = " ".join(f"JOIN dep{a}{b} d{a}{b} USING (doc_id)" for a, b in _STRIDES)
    if most:
        ctes.append(f"drawn AS (SELECT doc_id FROM el ORDER BY md5('1:' || doc_id::VARCHAR), doc_id LIMIT {most})")
    ctes.append(f"v AS (SELECT doc_id, {', '.join(cols)} FROM {'drawn' if most else 'el'} {joins})")
    names = [f"s{a}{b}" for a, b in _STRIDES]
    ranks = ", ".join(
        f"rank() OVER (ORDER BY {n}) + (count(*) OVER (PARTITION BY {n}) - 1) / 2 AS r{n}, row_number() OVER (ORDER BY {n} DESC, doc_id) <= 50 AS t{n}" for n in names
    )
    ctes.append(f"w AS (SELECT *, {ranks} FROM v)")
    parts = " UNION ALL ".join(
        f"""SELECT 'full_{a}_{b}' AS setting, count(*) AS n_docs, round(corr(s{a}{b}, s44), 6) AS pearson, round(corr(rs{a}{b}, rs44), 6) AS spearman,
        round(count(*) FILTER (ts{a}{b} AND ts44) / 50.0::DOUBLE, 6) AS overlap_at_n FROM w"""
        for a, b in _STRIDES
    )
    return f"{O.with_(*ctes)} {parts}"


@TABLE.query(_stride_sql())
def score_correlation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of four stride settings in one kernel pass, against the setting (4, 4), on 5,000 samples drawn by md5."""
    drawn = desk(spark, sf_dir).select("doc_id", T.random_order("doc_id", 1).alias("o")).orderBy("o", "doc_id").limit(_DRAWN).select("doc_id")
    return stride_correlations(spark, sf_dir, desk(spark, sf_dir).join(cut(drawn), "doc_id", "left_semi"))


def stride_correlations(spark: SparkSession, sf_dir: str, rows: DataFrame) -> DataFrame:
    """(setting, n_docs, pearson, spearman, overlap_at_n) of the scores of ``rows`` by stride setting."""
    made = cut(lexical.score_documents(rows, lexical.weight_table(docs(spark, sf_dir)), DESK, ("full",), _STRIDES))
    return rounded(measures.score_correlation(made, "full_4_4", [f"full_{a}_{b}" for a, b in _STRIDES], 50), "pearson", "spearman", "overlap_at_n")


_TIMES = " UNION ALL ".join(f"SELECT 'full_{a}_{b}' AS setting, {a} AS row_stride, {b} AS col_stride, {cost_of(DESK.with_strides(a, b))['logits']} AS logits" for a, b in _STRIDES)


@TABLE.query(f"""WITH c AS ({_stride_sql(None)}), s AS ({_TIMES})
    SELECT row_stride, col_stride, round(logits / {cost_of(DESK)['logits']}.0::DOUBLE, 3) AS times, pearson AS correlation, pearson > 0.7 AS above FROM c JOIN s USING (setting)""")
def strides_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Logits a sample relative to strides of four, and whether all correlations of all given samples' scores exceed 0.7."""
    rows = [(f"full_{a}_{b}", a, b, cost_of(DESK.with_strides(a, b))["logits"] / cost_of(DESK)["logits"]) for a, b in _STRIDES]
    made = stride_correlations(spark, sf_dir, desk(spark, sf_dir)).join(spark.createDataFrame(rows, "setting string, row_stride int, col_stride int, times double"), "setting")
    return made.select("row_stride", "col_stride", F.round("times", 3).alias("times"), F.col("pearson").alias("correlation"), (F.col("pearson") > 0.7).alias("above"))


_PROFILES = ("paper", "desk", "desk-wide", "vectors")


def _cost_sql() -> str:
    parts = []
    for p in _PROFILES:
        for a, b in _STRIDES:
            g = Geometry.named(p).with_strides(a, b)
            parts.append(
                f"""SELECT '{p}' AS profile, {g.length} AS length, {a} AS row_stride, {b} AS col_stride, count(DISTINCT j) AS rows,
                sum(len(range({g.skip_first}, j - {g.skip_near}, {a})))::BIGINT AS pairs, sum((j + 1) * {g.span**2})::BIGINT AS logits
                FROM range({g.first_row}, {g.n_spans}, {b}) t(j)"""
            )
    return f"""{O.with_(O.base(DESK))}, one AS ({' UNION ALL '.join(parts)}), n AS (SELECT len(tokens) AS n FROM tok),
        k AS (SELECT profile, count(n) AS samples FROM (SELECT DISTINCT profile, length FROM one) LEFT JOIN n ON n >= length GROUP BY profile)
        SELECT profile, row_stride, col_stride, rows, pairs, logits, samples, (samples * pairs)::BIGINT AS all_pairs, (samples * logits)::BIGINT AS all_logits
        FROM one JOIN k USING (profile)"""


@TABLE.query(_cost_sql())
def cost_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counters of a sample by profile and strides, and of all samples that the given documents make."""
    n = samples.tokenize(docs(spark, sf_dir)).select("n_tokens")
    counts = n.agg(*(F.count_if(F.col("n_tokens") >= Geometry.named(p).length).alias(p) for p in _PROFILES))
    by_profile = counts.select(F.explode(F.array(*(F.struct(F.lit(p).alias("profile"), F.col(p).alias("samples")) for p in _PROFILES))).alias("s")).select("s.*")
    rows = measures.cost_rows(spark, [(p, a, b) for p in _PROFILES for a, b in _STRIDES]).join(by_profile, "profile")
    return rows.withColumns({f"all_{c}": F.col("samples") * F.col(c) for c in ("pairs", "logits")})


@TABLE.query()
def seconds_per_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Wall time of the kernel by stride setting, median of three runs after a warm-up; rows only."""
    import statistics
    import time

    from spanfocus.sources.tables import run_only

    table, rows, out = lexical.weight_table(docs(spark, sf_dir)), cut(desk(spark, sf_dir)), []
    n = max(1, rows.count())
    for a, b in _STRIDES:
        times = []
        for _ in range(4):
            began = time.perf_counter()
            run_only(lexical.score_documents(rows, table, DESK.with_strides(a, b)))
            times.append(time.perf_counter() - began)
        out.append((a, b, statistics.median(times[1:]) / n))
    return spark.createDataFrame(out, "row_stride int, col_stride int, seconds double")


# Categories.


def both_scores(spark: SparkSession, sf_dir: str, domain: str = "lang") -> DataFrame:
    one = desk_scores(spark, sf_dir, domain).withColumnRenamed("score", "dependency")
    return one.join(delta_scores(spark, sf_dir).select("doc_id", F.col("score").alias("delta")), "doc_id")


def _medians_sql(domain: str) -> str:
    return f"""{O.with_(O.scored(DESK, domain=domain), O.unigrams(), O.deltas(), O.delta_score())},
        m AS (SELECT dep.domain AS category, count(*) AS n_docs, round(median(dep.score), 6) AS median_dependency, round(median(del.score), 2) AS median_delta
            FROM dep JOIN del USING (doc_id) GROUP BY dep.domain),
        r AS (SELECT *, row_number() OVER (ORDER BY median_dependency DESC, category)::INT AS rank_dependency,
            row_number() OVER (ORDER BY median_delta DESC, category)::INT AS rank_delta FROM m)"""


def medians(spark: SparkSession, sf_dir: str, domain: str) -> DataFrame:
    return measures.category_medians(both_scores(spark, sf_dir, domain), "domain").withColumn("median_delta", F.round("median_delta", 2))


def _medians_query(name: str, domain: str) -> None:
    TABLE.add(name, lambda spark, sf_dir: medians(spark, sf_dir, domain), f"{_medians_sql(domain)} SELECT * FROM r")


_medians_query("category_medians", "lang")
_medians_query("category_medians_source", "source")


@TABLE.query(f"{_medians_sql('source')} SELECT category, rank_dependency, rank_delta, rank_delta - rank_dependency AS shift FROM r")
def category_ranks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.category_disagreement(medians(spark, sf_dir, "source"))


@TABLE.query()
def workload_pseudo_categories(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Medians over folded chats, web pages and prose together; smaller samples, as chats are short. Rows only."""
    g = Geometry.named("smoke")
    chats = samples.fold_conversations(read_table(spark, sf_dir, "conversations")).select((F.col("conv_id") + 10**12).alias("doc_id"), "text", F.lit("chat").alias("source"))
    pages = read_table(spark, sf_dir, "pages").select((F.col("page_id") + 2 * 10**12).alias("doc_id"), T.page_text("html").alias("text"), F.lit("web").alias("source"))
    prose = docs(spark, sf_dir).select("doc_id", "text", F.lit("prose").alias("source"))
    rows = cut(chats.unionByName(pages).unionByName(prose))
    kept = samples.samples(rows, g)
    dep = lexical.score_documents(kept, lexical.weight_table(rows), g).withColumnRenamed("full_2_2", "dependency")
    change = delta.delta_perplexity(kept, delta.unigram_table(rows), {"delta": delta.DeltaOptions()})
    return measures.category_medians(dep.join(change.select("doc_id", "delta"), "doc_id"), "domain").withColumn("median_delta", F.round("median_delta", 2))


@TABLE.query(f"""{O.with_(O.scored(DESK, domain="lang"))}, r AS (
        SELECT dep.doc_id, dep.domain, round(score, 6) AS score, substr(el.text, 1, 80) AS excerpt,
            row_number() OVER (PARTITION BY dep.domain ORDER BY round(score, 6) DESC, dep.doc_id)::INT AS a,
            row_number() OVER (PARTITION BY dep.domain ORDER BY round(score, 6), dep.doc_id)::INT AS b
        FROM dep JOIN el USING (doc_id))
    SELECT domain, 'top' AS side, a AS rank, doc_id, score, excerpt FROM r WHERE a <= 3
    UNION ALL SELECT domain, 'bottom', b, doc_id, score, excerpt FROM r WHERE b <= 3""")
def score_extremes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Best and worst documents of each category, with their first characters."""
    return rounded(measures.extremes(desk_scores(spark, sf_dir, "lang"), docs(spark, sf_dir), 3), "score")


@TABLE.query(f"""{O.with_(O.scored(DESK))}, j AS (SELECT round(score, 6) AS s, quality AS y FROM dep JOIN labels USING (doc_id)),
    k AS (SELECT *, rank() OVER (ORDER BY s) + (count(*) OVER (PARTITION BY s) - 1) / 2 AS r FROM j)
    SELECT count(*) AS n_docs, sum(y)::BIGINT AS positives,
        round((sum(r) FILTER (y = 1) - sum(y) * (sum(y) + 1) / 2) / nullif(sum(y) * (count(*) - sum(y)), 0), 6) AS auc, round(corr(s, y::DOUBLE), 6) AS point_biserial FROM k""")
def label_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = measures.label_agreement(desk_scores(spark, sf_dir), read_table(spark, sf_dir, "labels"))
    return rounded(made, "auc", "point_biserial")


_CLEAN = """good AS (SELECT doc_id FROM (%s) WHERE NOT (symbol_ratio > 0.2 OR distinct_ratio < 0.1 OR repeated_lines > 0.5))""" % relational._JUNK


@TABLE.query(f"""{O.with_(O.scored(DESK), _CLEAN)}, j AS (SELECT round(score, 6) AS s, quality AS y FROM dep JOIN labels USING (doc_id) WHERE doc_id IN (SELECT doc_id FROM good)),
    k AS (SELECT *, rank() OVER (ORDER BY s) + (count(*) OVER (PARTITION BY s) - 1) / 2 AS r FROM j)
    SELECT count(*) AS n_docs, sum(y)::BIGINT AS positives,
        round((sum(r) FILTER (y = 1) - sum(y) * (sum(y) + 1) / 2) / nullif(sum(y) * (count(*) - sum(y)), 0), 6) AS auc, round(corr(s, y::DOUBLE), 6) AS point_biserial FROM k""")
def label_agreement_cleaned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same over documents that pass the junk filters, which else take the top scores."""
    good = relational.clean(docs(spark, sf_dir).select("doc_id", "text")).select("doc_id")
    scored = desk_scores(spark, sf_dir).join(good, "doc_id", "left_semi")
    return rounded(measures.label_agreement(scored, read_table(spark, sf_dir, "labels")), "auc", "point_biserial")


@TABLE.query()
def perplexity_cleaned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Held-out perplexity of selections made after the junk filters; rows only, the parts have oracles."""
    good = relational.clean(docs(spark, sf_dir).where(~T.is_heldout("text")).select("doc_id", "text")).select("doc_id")
    tokens = cut(desk(spark, sf_dir).join(good, "doc_id", "left_semi"))
    scored, changed = (t.join(good, "doc_id", "left_semi") for t in (desk_scores(spark, sf_dir), delta_scores(spark, sf_dir).withColumn("score", F.round("score", 3))))
    budget = budget_of(tokens)
    chosen = {
        "dependency": select.select_by_domain(scored, budget), "delta": select.select_by_domain(changed, budget),
        "random_1": select.select_random(tokens.select("doc_id", "domain", "n_tokens"), budget, 1),
    }
    texts = docs(spark, sf_dir).where(T.is_heldout("text"))
    test = cut(samples.samples(relational.clean(texts), DESK))
    return perplexities({m: cut(tokens.join(c.select("doc_id"), "doc_id", "left_semi")) for m, c in chosen.items()}, test)


# Answer scores, on the turns of conversations as answers and their successors as truths.

_TURNS = """t AS (SELECT conv_id, turn, text AS answer, lead(text) OVER (PARTITION BY conv_id ORDER BY turn) AS truth FROM conversations),
    u AS (SELECT conv_id, turn, coalesce(answer, '') AS a, truth AS b FROM t WHERE truth IS NOT NULL)"""


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read_table(spark, sf_dir, "conversations").select(
        "conv_id", "turn", F.col("text").alias("answer"), F.lead("text").over(Window.partitionBy("conv_id").orderBy("turn")).alias("truth")
    )
    return rows.where("truth IS NOT NULL").select("conv_id", "turn", F.coalesce("answer", F.lit("")).alias("a"), F.col("truth").alias("b"))


@TABLE.query(f"""WITH {_TURNS},
    w AS (SELECT conv_id, turn, regexp_extract_all(lower(a), '[\\p{{L}}\\p{{N}}]+') AS x, regexp_extract_all(lower(b), '[\\p{{L}}\\p{{N}}]+') AS y FROM u),
    s AS (SELECT *, coalesce(list_sum(list_transform(list_distinct(x), lambda t:
        least(len(list_filter(x, lambda v: v = t)), len(list_filter(y, lambda v: v = t))))), 0) AS n FROM w)
    SELECT conv_id, turn, round(CASE WHEN n = 0 THEN 0 ELSE 2 * n / (len(x) + len(y)) END, 6) AS f1, (x = y)::INT AS exact FROM s""")
def token_f1(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = turns(spark, sf_dir).select(
        "conv_id", "turn", measures.token_f1(F.col("a"), F.col("b")).alias("f1"), measures.exact_match(F.col("a"), F.col("b")).alias("exact")
    )
    return rounded(made, "f1")


@TABLE.query()
def edit_similarity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows only: DuckDB's edit distance of long texts differs from the textbook one that the tests hold this to."""
    rows = turns(spark, sf_dir)
    return rounded(rows.select("conv_id", "turn", measures.edit_similarity(F.col("a"), F.col("b")).alias("similarity")), "similarity")


@TABLE.query()
def rouge_l(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Longest common subsequence needs a table per pair of texts: rows only, tested against brute force."""
    return rounded(turns(spark, sf_dir).select("conv_id", "turn", measures.rouge_l("a", "b").alias("rouge_l")), "rouge_l")


@TABLE.query()
def workload_task_proxies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W7 (b): proxies of the four task categories; they stand for the tasks and do not equal them. Rows only."""
    single = lexical_hits(spark, sf_dir, desk(spark, sf_dir)).agg(F.avg("hit").alias("score"), F.count("*").alias("n"))
    many = lexical_hits(spark, sf_dir, pieces_table(spark, sf_dir, (64,))).agg(F.avg("hit").alias("score"), F.count("*").alias("n"))
    rows = samples.spans(desk(spark, sf_dir), DESK)
    best = lexical.pair_focus_kernel(desk(spark, sf_dir), lexical.weight_table(docs(spark, sf_dir)), DESK)
    best = best.groupBy("doc_id").agg(F.max_by("i", F.struct(F.round("pair_focus", 6), -F.col("i"))).alias("i"))
    lead, pick = F.array_join(F.element_at("spans", 1), " "), F.array_join(F.element_at("spans", F.col("i") + 1), " ")
    summary = rows.join(best, "doc_id").agg(F.avg(measures.token_f1(lead, pick)).alias("score"), F.count("*").alias("n"))
    code = turns(spark, sf_dir).agg(F.avg(measures.edit_similarity(F.col("a"), F.col("b"))).alias("score"), F.count("*").alias("n"))
    parts = {"single_doc": single, "multi_doc": many, "summary": summary, "code": code}
    return rounded(union([d.select(F.lit(c).alias("category"), "n", "score") for c, d in parts.items()]), "score")


@TABLE.query()
def workload_calculator_budgets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores by calculators trained on a budget and on a fifth of it: correlation and overlap. Rows only."""
    large, small = (small_calculator(spark, sf_dir, b) for b in (20_000, 4_000))
    rows = cut(desk(spark, sf_dir))
    one = states.score_with_model(rows, large, DESK).select("doc_id", F.col("full").alias("large"))
    two = states.score_with_model(rows, small, DESK).select("doc_id", F.col("full").alias("small"))
    made = measures.score_correlation(cut(one.join(two, "doc_id")), "large", ["large", "small"], 50)
    return rounded(made, "pearson", "spearman", "overlap_at_n")


@TABLE.query()
def calculator_selections(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What selections by a calculator trained on a budget and on a fifth of it take, and share. Rows only."""
    rows, chosen = cut(desk(spark, sf_dir)), {}
    for name, tokens in (("large", 20_000), ("small", 4_000)):
        made = cut(states.score_with_model(rows, small_calculator(spark, sf_dir, tokens), DESK).select("doc_id", "domain", "n_tokens", F.col("full").alias("score")))
        chosen[name] = select.select_by_domain(made, budget_of(made))
    return rounded(select.overlap(chosen["large"], chosen["small"]), "jaccard", "overlap_share")


PAPER = Geometry.named("paper")


def paper_samples(spark: SparkSession, sf_dir: str, piece: int = 512) -> DataFrame:
    """(doc_id, domain, n_tokens, tokens): samples of the published length, built of whole pieces of all documents in md5 order."""
    pieces = samples.chunk(samples.tokenize(docs(spark, sf_dir)).select("doc_id", "tokens"), piece)
    named = pieces.select((F.col("doc_id") * 1_000 + F.col("chunk_no")).alias("doc_id"), "tokens")
    made = samples.concatenate(named, PAPER.length, piece)
    return made.select(F.col("sample_id").cast("bigint").alias("doc_id"), F.lit("all").alias("domain"), F.lit(PAPER.length).alias("n_tokens"), "tokens")


@TABLE.query()
def published_geometry_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both scorers at the published geometry, 32,768 tokens in 256 spans; tests hold the kernels to dense forms."""
    rows = cut(paper_samples(spark, sf_dir))
    one = lexical.score_documents(rows, lexical.weight_table(docs(spark, sf_dir)), PAPER, ("full",), _STRIDES)
    two = delta.delta_perplexity(rows, delta.unigram_table(docs(spark, sf_dir)), {"delta_score": delta.DeltaOptions()})
    columns = [f"full_{a}_{b}" for a, b in _STRIDES]
    made = one.select("doc_id", *columns).join(two.select("doc_id", F.round("delta_score", 3).alias("delta_score")), "doc_id")
    return rounded(made.withColumnRenamed("doc_id", "sample_id"), *columns)


@TABLE.query(
    f"{O.with_(_selected(_METHODS))} "
    + " UNION ALL ".join(f"SELECT '{m}' AS method, domain, count(*) AS docs, sum(n_tokens)::BIGINT AS tokens FROM c_{m} GROUP BY domain" for m in _METHODS)
)
def workload_selections(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the three methods take of each domain under one budget, held-out texts apart."""
    made = [d.groupBy("domain").agg(F.count("*").alias("docs"), F.sum("n_tokens").cast("bigint").alias("tokens")).withColumn("method", F.lit(m)) for m, d in selections(spark, sf_dir).items()]
    return union(made).select("method", "domain", "docs", "tokens")


def _variants_sql() -> str:
    ctes, cols, joins = [O.base(DESK)], [], []
    for a, b in _STRIDES:
        g, t = DESK.with_strides(a, b), f"{a}{b}"
        p = O.pairs(g)
        for n in ("mass", "total", "pf"):
            p = p.replace(f"{n} AS (", f"{n}{t} AS (").replace(f"FROM {n} ", f"FROM {n}{t} ").replace(f"JOIN {n} ", f"JOIN {n}{t} ")
        ctes.append(p)
        for v in VARIANTS:
            ctes.append(O.span_rows(g, v).replace("sf AS (", f"sf{t}_{v} AS (").replace("FROM pf ", f"FROM pf{t} "))
            ctes.append(O.dependency(g, v, f"dep{t}_{v}", f"sf{t}_{v}"))
            cols.append(f"round(d{t}_{v}.score, 6) AS {v}_{a}_{b}")
            joins.append(f"JOIN dep{t}_{v} d{t}_{v} ON d{t}_{v}.doc_id = el.doc_id")
    cost = ", ".join(f"{n}::BIGINT AS {c}" for c, n in zip(("rows_used", "pairs_used", "logits"), cost_of(DESK).values(), strict=True))
    return f"{O.with_(*ctes)} SELECT el.doc_id, el.domain, el.n_tokens, {', '.join(cols)}, {cost} FROM el {' '.join(joins)}"


@TABLE.query(_variants_sql())
def score_all_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every variant and stride setting of every document in one kernel pass."""
    made = lexical.score_documents(desk(spark, sf_dir), lexical.weight_table(docs(spark, sf_dir)), DESK, tuple(VARIANTS), _STRIDES)
    return rounded(made, *(f"{v}_{a}_{b}" for v in VARIANTS for a, b in _STRIDES))
