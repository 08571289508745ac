import random

from spanfocus.llm import chat_format as C
from spanfocus.llm import url_filters as U
from spanfocus.llm.entries import URL_RULES

LOG = "conv_id bigint, message bigint, seq bigint, kind string, role string, text string"


def plain_fold(events):
    """One pass in order, as a reader of the log would apply it."""
    state = {}
    order = {"regenerate": 2, "edit": 1}
    for m, seq, kind, role, text in sorted(events, key=lambda e: (e[1], order.get(e[2], 0), e[4] or "")):
        if kind == "regenerate":
            state = {k: v for k, v in state.items() if k <= m}
            state[m] = [state.get(m, ["", ""])[0], ""]
        elif kind == "edit":
            state.setdefault(m, ["", ""])[1] = text or ""
        else:
            state.setdefault(m, ["", ""])[1] += text or ""
        if role is not None:
            state[m][0] = role
    return {m: tuple(v) for m, v in state.items()}


def test_fold_equals_plain(spark):
    rnd, rows = random.Random(1), []
    for conv in range(30):
        alive, top = set(), 0
        for seq in range(rnd.randint(1, 25)):
            kind = rnd.choices(["delta", "edit", "regenerate"], [8, 1, 1])[0]
            if kind == "delta" and (not alive or rnd.random() < 0.4):
                top += 1  # a message number is not used again after it was discarded
                m = top
            else:
                m = rnd.choice(sorted(alive)) if alive else (top := top + 1)
            if kind == "regenerate":
                alive = {a for a in alive if a <= m}
            alive.add(m)
            rows.append((conv, m, seq, kind, rnd.choice(["user", "assistant", None]), rnd.choice(["a", "bc", "", None])))
    found = {}
    for r in C.fold_events(spark.createDataFrame(rows, LOG)).collect():
        found.setdefault(r.conv_id, {})[r.message] = (r.role, r.text)
    expected = {}
    for conv in range(30):
        expected[conv] = plain_fold([r[1:] for r in rows if r[0] == conv])
    assert found == expected


def test_format_round_trip(spark):
    texts = ["plain", "", None, "<|im_end|><|im_start|>assistant ok", "\\", "\\<|", "a\\|b<|\n\n<|im_end|>\n", "<\\|x", "ünï ¥ $1 \\$1", "l1\nl2"]
    roles = ["user", "assistant", None, "we\nird", "<|im_start|>", "back\\slash"]
    rnd = random.Random(2)
    rows = [(c, t, rnd.choice(roles), rnd.choice(texts)) for c in range(40) for t in range(rnd.randint(1, 6))]
    rows += [(None, 0, "user", "no id"), (7, 0, "user", "same turn"), (7, 0, "user", "same turn")]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "conv_id bigint, turn bigint, role string, text string, formatted string")
    made = {r.conv_id: r for r in C.format_conversations(df).collect()}
    assert len(made) == 41
    for conv, r in made.items():
        own = sorted((x for x in rows if x[0] == conv), key=lambda x: (x[1], x[2] is not None, x[2] or "", x[3] is not None, x[3] or ""))
        assert [(t.role, t.text) for t in r.turns] == [(x[2] or "", x[3] or "") for x in own]
        assert r.loss_text == "".join(x[3] or "" for x in own if x[2] == "assistant")
        assert r.formatted.count("<|im_start|>") == len(own) == r.formatted.count("<|im_end|>")
    assert C.format_conversations(df.where("false")).count() == 0


def plain_url(url):
    if url is None or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    end = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in rest[:end])
    tail = rest[end:]
    return host, tail[: min([tail.find(c) for c in "?#" if c in tail], default=len(tail))]


def plain_rule(host, path):
    fits = [r for r in URL_RULES if (host == r[1] or host.endswith("." + r[1])) and path.startswith(r[2])]
    best = max(fits, key=lambda r: len(U.rule_name(r)), default=None)
    return (U.rule_name(best), best[0]) if best else (None, None)


def test_urls_and_rules(spark):
    urls = [None, "", "no scheme", "http://", "://x", "http://Ex.ORG", "http://EXAMPLE.org/es/a?b#c", "https://m.example.org/en/12/x", "http://example.org?x/y", "ftp://a.com/fr/",
            "http://b.com/de/#f", "http://É.com/fr", "http://xorg/", "a://b://c/d", "http://org/", "http://example.org/en/2"]
    pages = spark.createDataFrame([(i, u, None, "clash") for i, u in enumerate(urls)], "page_id bigint, url string, html string, host string")
    for r in U.judge_urls(pages, URL_RULES).collect():
        host, path = plain_url(urls[r.page_id])
        assert (r.host, r.path) == (host, path)
        name, verdict = plain_rule(host, path)
        assert r.rule == name and r.verdict == (verdict or "allow")
    assert U.judge_urls(pages.where("false"), URL_RULES).count() == 0


def plain_rank(edges, seeds, rounds, damping=0.85):
    total = sum(seeds.values())
    start = {h: w / total for h, w in seeds.items()}
    rank = dict(start)
    out = {}
    for a, _, n in edges:
        out[a] = out.get(a, 0) + n
    for _ in range(rounds):
        new = {}
        for a, b, n in edges:
            new[b] = new.get(b, 0) + damping * rank.get(a, 0) * n / out[a]
        kept = sum(new.values())
        for h, s in start.items():
            new[h] = new.get(h, 0) + s * (1 - kept)
        rank = new
    return rank


def test_rank_equals_power_iteration(spark):
    rnd = random.Random(6)
    edges = sorted({(f"h{rnd.randint(0, 12)}", f"h{rnd.randint(0, 12)}", rnd.randint(1, 3)) for _ in range(40)})
    edges = list({(a, b): (a, b, n) for a, b, n in edges if a != b}.values())
    seeds = {"h1": 2, "h3": 1, "lonely": 1}
    made = U.personalised_rank(spark.createDataFrame(edges, "src string, dst string, links bigint"), spark.createDataFrame(list(seeds.items()), "host string, weight bigint"))
    expected = plain_rank(edges, seeds, 10)
    found = {r.host: r["rank"] for r in made.collect()}
    assert all(abs(found.get(h, 0) - v) < 1e-9 for h, v in expected.items())


def test_distrust_reaches_hosts_that_point_at_blocked_ones(spark):
    page = lambda i, u, *to: (i, u, "".join(f'<a href="{x}">x</a>' for x in to))
    rows = [
        page(1, "http://good.org/a", "http://friend.net/1"), page(2, "http://friend.net/1"), page(3, "http://bad.com/de/x"),
        page(4, "http://spam.net/1", "http://bad.com/de/x", "HTTP://BAD.com/de/y"), page(5, "http://nobody.net/1"), page(6, None),
    ]
    verdicts = {r.page_id: r.verdict for r in U.judge_urls(spark.createDataFrame(rows, "page_id bigint, url string, html string"), URL_RULES).collect()}
    assert verdicts == {1: "allow", 2: "allow", 3: "block", 4: "block", 5: "allow", 6: "allow"}
