"""DuckDB statements of the methods, in dense form: every query token against every key token.

They share no algebra with the engine: no sparse part, no closed form. Each builder returns CTE text.
"""

from __future__ import annotations

from spanfocus.geometry import Geometry
from spanfocus.operators.focus import VARIANTS

TOKEN = r"[^ \t\n\r]+"


def with_(*ctes: str) -> str:
    return "WITH " + ",\n".join(c for c in ctes if c)


def base(g: Geometry, domain: str = "source", table: str = "documents") -> str:
    return f"""
    tok AS (SELECT doc_id, {domain} AS domain, text, regexp_extract_all(coalesce(text, ''), '{TOKEN}') AS tokens FROM {table}),
    el AS (SELECT doc_id, domain, text, {g.length} AS n_tokens, tokens[1:{g.length}] AS tokens FROM tok WHERE len(tokens) >= {g.length}),
    idf AS (
        SELECT token, (1.0 + (SELECT count(*) FROM tok)) / (1 + count(DISTINCT doc_id)) - 1 AS w
        FROM (SELECT doc_id, unnest(tokens) AS token FROM tok) GROUP BY token
    ),
    pos AS (SELECT doc_id, unnest(tokens) AS token, generate_subscripts(tokens, 1) - 1 AS p FROM el)"""


def _rows(g: Geometry, j: str) -> str:
    first = g.first_row + g.col_phase
    return f"{j} >= {first} AND ({j} - {first}) % {g.col_stride} = 0"


def _cols(g: Geometry, j: str, i: str) -> str:
    low = g.skip_first + g.row_phase
    return f"{i} >= {low} AND {i} < {j} - {g.skip_near} AND ({i} - {low}) % {g.row_stride} = 0"


def pairs(g: Geometry, causal: bool = True, everything: bool = False) -> str:
    upto = "q.p" if causal else f"(q.p // {g.span} + 1) * {g.span} - 1"
    rows = "TRUE" if everything else _rows(g, f"(q.p // {g.span})")
    cols = "TRUE" if everything else _cols(g, "j", "i")
    return f"""
    mass AS (
        SELECT q.doc_id, q.p AS qp, q.p // {g.span} AS j, k.p // {g.span} AS i,
            CASE WHEN k.token = q.token THEN 1 + coalesce(w, 0) ELSE 1 END AS m
        FROM pos q LEFT JOIN idf ON idf.token = q.token JOIN pos k ON k.doc_id = q.doc_id AND k.p <= {upto} WHERE {rows}
    ),
    total AS (SELECT doc_id, qp, sum(m) AS z FROM mass GROUP BY ALL),
    pf AS (
        SELECT doc_id, j::INT AS j, i::INT AS i, sum(m / z) AS pair_focus FROM mass JOIN total USING (doc_id, qp) WHERE {cols} GROUP BY ALL
    )"""


def span_rows(g: Geometry, variant: str = "full", ddof: int = 0) -> str:
    sigma, distance, _ = VARIANTS[variant]
    weight = f"(j - i) / {g.n_spans}.0" if distance else "1.0"
    dev = "stddev_samp" if ddof else "stddev_pop"
    return f"""
    sf AS (
        SELECT doc_id, j, count(*)::INT AS n_terms, coalesce({dev}(pair_focus), 0) AS sigma, sum({weight} * pair_focus) AS weighted_sum,
            {"coalesce(" + dev + "(pair_focus), 0)" if sigma else "1.0"} * sum({weight} * pair_focus) AS span_focus
        FROM pf GROUP BY doc_id, j
    )"""


def dependency(g: Geometry, variant: str = "full", name: str = "dep", source: str = "sf", documents: str = "el") -> str:
    weight = f"j / {g.n_spans}.0" if VARIANTS[variant][2] else "1.0"
    return f"""
    {name} AS (
        SELECT e.doc_id, e.domain, e.n_tokens, coalesce(s.score, 0) AS score FROM {documents} e
        LEFT JOIN (SELECT doc_id, sum({weight} * span_focus) AS score FROM {source} GROUP BY doc_id) s USING (doc_id)
    )"""


def scored(g: Geometry, variant: str = "full", domain: str = "source") -> str:
    return ",".join((base(g, domain), pairs(g), span_rows(g, variant), dependency(g, variant)))


def quota(share: float, of: str = "el") -> str:
    return f"""
    mixed AS (SELECT domain, sum(n_tokens) AS tokens FROM {of} GROUP BY domain),
    budget AS (SELECT floor({share} * sum(tokens)) AS b FROM mixed),
    exact AS (SELECT domain, round(b * tokens / (SELECT sum(tokens) FROM mixed), 6) AS x FROM mixed, budget),
    quota AS (
        SELECT domain, (floor(x) + CASE WHEN row_number() OVER (ORDER BY round(x - floor(x), 6) DESC, domain)
            <= (SELECT b FROM budget) - (SELECT sum(floor(x)) FROM exact) THEN 1 ELSE 0 END)::BIGINT AS quota_tokens
        FROM exact
    )"""


def chosen(name: str, of: str, order: str = "round(score, 6) DESC", score: str = "round(score, 6)") -> str:
    return f"""
    {name} AS (
        SELECT * FROM (
            SELECT doc_id, domain, {score} AS score,
                row_number() OVER (PARTITION BY domain ORDER BY {order}, doc_id)::INT AS domain_rank, n_tokens::INT AS n_tokens,
                sum(n_tokens) OVER (PARTITION BY domain ORDER BY {order}, doc_id ROWS UNBOUNDED PRECEDING)::BIGINT AS cum_tokens,
                quota_tokens
            FROM {of} JOIN quota USING (domain)
        ) WHERE cum_tokens <= quota_tokens
    )"""


def unigrams(alpha: float = 1.0) -> str:
    return f"""
    uni AS (SELECT token, count(*) AS n FROM (SELECT unnest(tokens) AS token FROM tok) GROUP BY token),
    prob AS (
        SELECT token, (n + {alpha}) / ((SELECT sum(n) FROM uni) + {alpha} * ((SELECT count(*) FROM uni) + 1)) AS p FROM uni
    )"""


def deltas(segment: int = 32, mix: float = 0.5) -> str:
    return f"""
    seg AS (SELECT doc_id, (p // {segment})::INT AS j, p AS place, token FROM pos),
    alone AS (SELECT doc_id, j, exp(-avg(ln(prob.p))) AS ppl_alone FROM seg JOIN prob USING (token) GROUP BY ALL),
    given AS (
        SELECT a.doc_id, a.j, b.j AS i, a.place, any_value(prob.p) AS p, count(*) FILTER (b.token = a.token) AS c
        FROM seg a JOIN seg b ON a.doc_id = b.doc_id AND b.j < a.j JOIN prob ON prob.token = a.token GROUP BY ALL
    ),
    delta AS (
        SELECT doc_id, j, i, ppl_alone, exp(-avg(ln((1 - {mix}) * p + {mix} * c / {segment}.0))) AS ppl_given
        FROM given JOIN alone USING (doc_id, j) GROUP BY ALL
    )"""


def delta_score(value: str = "ppl_alone - ppl_given", name: str = "del") -> str:
    return f"""
    {name} AS (
        SELECT e.doc_id, e.domain, e.n_tokens, coalesce(d.score, 0) AS score FROM el e
        LEFT JOIN (SELECT doc_id, sum({value}) AS score FROM delta GROUP BY doc_id) d USING (doc_id)
    )"""


def lm(selection: str, text: str, tag: str, windows: tuple[int, ...], alpha: float = 1.0, pull: float = 50.0, cache: float = 0.2) -> str:
    """CTE ``ppl_<tag>`` (model, window, n_docs, ppl): counts from ``selection`` (tokens), perplexity of ``text``."""
    probability = {
        "unigram": "pu", "bigram": "pb",
        "unigram_cache": f"CASE WHEN pc IS NULL THEN pu ELSE {1 - cache} * pu + {cache} * pc END",
        "bigram_cache": f"CASE WHEN pc IS NULL THEN pb ELSE {1 - cache} * pb + {cache} * pc END",
    }
    cells = " UNION ALL ".join(
        f"SELECT '{m}' AS model, {w} AS window_size, doc_id, exp(-sum(ln({e})) / {w}) AS v FROM pr_{tag} WHERE p < {w} GROUP BY doc_id HAVING count(*) = {w}"
        for m, e in probability.items()
        for w in windows
    )
    return f"""
    tr_{tag} AS (SELECT doc_id, unnest(tokens) AS token, generate_subscripts(tokens, 1) - 1 AS p FROM {selection}),
    tu_{tag} AS (SELECT token, count(*) AS n FROM tr_{tag} GROUP BY token),
    tb_{tag} AS (
        SELECT before, token, count(*) AS n FROM (
            SELECT token, lag(token) OVER (PARTITION BY doc_id ORDER BY p) AS before FROM tr_{tag}
        ) WHERE before IS NOT NULL GROUP BY ALL
    ),
    tn_{tag} AS (SELECT before, sum(n) AS nb FROM tb_{tag} GROUP BY before),
    te_{tag} AS (SELECT doc_id, unnest(tokens[1:{max(windows)}]) AS token, generate_subscripts(tokens[1:{max(windows)}], 1) - 1 AS p FROM {text}),
    tl_{tag} AS (
        SELECT *, row_number() OVER (PARTITION BY doc_id, token ORDER BY p) - 1 AS seen, lag(token) OVER (PARTITION BY doc_id ORDER BY p) AS before
        FROM te_{tag}
    ),
    pr0_{tag} AS (
        SELECT t.doc_id, t.p, (coalesce(u.n, 0) + {alpha}) / (
                (SELECT coalesce(sum(n), 0) FROM tu_{tag}) + {alpha} * ((SELECT count(*) FROM tu_{tag}) + 1)) AS pu,
            coalesce(b.n, 0) AS n2, coalesce(nb, 0) AS nb, CASE WHEN p > 0 THEN seen / p END AS pc
        FROM tl_{tag} t LEFT JOIN tu_{tag} u ON u.token = t.token LEFT JOIN tb_{tag} b ON b.token = t.token AND b.before = t.before
            LEFT JOIN tn_{tag} n ON n.before = t.before
    ),
    pr_{tag} AS (SELECT *, (n2 + {pull} * pu) / (nb + {pull}) AS pb FROM pr0_{tag}),
    ppl_{tag} AS (SELECT model, window_size, count(*) AS n_docs, avg(v) AS ppl FROM ({cells}) GROUP BY ALL)"""


def needles(g: Geometry, hay: str, lengths: list[int], depths: tuple[float, ...]) -> str:
    """CTEs ``cases`` and ``hits`` by a dense softmax of the last span's tokens over all tokens of the context."""
    s, m, n = g.span, g.skip_first, g.skip_near
    return f"""
    pins AS (
        SELECT item_id, row_number() OVER (ORDER BY item_id) AS place, pin FROM (
            SELECT item_id, regexp_extract_all(text, '{TOKEN}') AS pin FROM benchmark
        ) WHERE len(pin) >= {s}
    ),
    placed AS (
        SELECT doc_id, tokens, (row_number() OVER (ORDER BY doc_id) - 1) % greatest(1, (SELECT count(*) FROM pins)) + 1 AS place FROM {hay}
    ),
    cells AS (SELECT c.x AS context_len, d.y AS depth FROM (SELECT unnest({lengths}) AS x) c, (SELECT unnest({list(depths)}::DOUBLE[]) AS y) d),
    roomy AS (
        SELECT *, context_len // {s} AS n_spans, len(pin) // {s} AS needle_spans,
            context_len // {s} - 1 - {n} - len(pin) // {s} - {m} AS room
        FROM placed JOIN pins USING (place), cells
    ),
    spot AS (SELECT *, ({m} + floor(depth * room))::INT AS needle_span FROM roomy WHERE room >= 0),
    cases AS (
        SELECT doc_id AS hay_doc, item_id AS needle_id, context_len, depth, needle_span, needle_spans, n_spans,
            tokens[1:needle_span * {s}] || pin[1:needle_spans * {s}]
            || tokens[needle_span * {s} + 1:context_len - {s} - needle_spans * {s}] || pin[1:{s}] AS tokens
        FROM spot
    ),
    ctx AS (
        SELECT hay_doc, context_len, depth, needle_span, needle_spans, n_spans, unnest(tokens) AS token, generate_subscripts(tokens, 1) - 1 AS p
        FROM cases
    ),
    asked AS (
        SELECT a.hay_doc, a.context_len, a.depth, a.p AS qp, k.p // {s} AS i, a.needle_span, a.needle_spans, a.n_spans,
            CASE WHEN k.token = a.token THEN 1 + coalesce(w, 0) ELSE 1 END AS m
        FROM ctx a LEFT JOIN idf ON idf.token = a.token
        JOIN ctx k ON a.hay_doc = k.hay_doc AND a.context_len = k.context_len AND a.depth = k.depth AND k.p <= a.p
        WHERE a.p >= a.context_len - {s}
    ),
    z AS (SELECT hay_doc, context_len, depth, qp, sum(m) AS z FROM asked GROUP BY ALL),
    looks AS (
        SELECT hay_doc, context_len, depth, i, any_value(needle_span) AS a, any_value(needle_spans) AS k, any_value(n_spans) AS n, round(sum(m / z), 6) AS f
        FROM asked JOIN z USING (hay_doc, context_len, depth, qp) GROUP BY ALL
    ),
    hits AS (
        SELECT hay_doc, context_len, depth, CASE WHEN best >= a AND best < a + k THEN 1 ELSE 0 END AS hit FROM (
            SELECT hay_doc, context_len, depth, any_value(a) AS a, any_value(k) AS k,
                arg_min(i, (-f, i)) FILTER (i >= {m} AND i < n - 1 - {n}) AS best
            FROM looks GROUP BY ALL
        )
    )"""
