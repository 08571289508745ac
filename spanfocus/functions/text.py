"""Column functions on text and tokens."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

# Both patterns mean the same in Spark and in DuckDB.
SPACE, WORD = r"[^ \t\n\r]+", r"[\p{L}\p{N}]+"


def tokens_of(text: Column | str, mode: str | Callable[[Column], Column] = "space") -> Column:
    """Array of tokens: maximal runs without blanks (``space``), of letters and digits (``word``), or what a
    callable makes of the text's column."""
    if callable(mode):
        return mode(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")))
    if mode not in ("space", "word"):
        raise ValueError("mode must be 'space' or 'word'")
    pattern = SPACE if mode == "space" else WORD
    return F.regexp_extract_all(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")), F.lit(pattern), 0)


def token_hashes(tokens: Column | str) -> Column:
    """64-bit hash of every token, in order."""
    return F.transform(tokens, lambda t: F.xxhash64(t))


def at_least_chars(n_tokens: int) -> int:
    """Characters that a text of so many tokens has at the least: one each and the gaps."""
    return max(0, 2 * n_tokens - 1)


def random_order(key: Column | str, seed: int) -> Column:
    """Reproducible order of rows: the md5 of seed and key; the same in any engine."""
    return F.md5(F.concat_ws(":", F.lit(str(seed)), (F.col(key) if isinstance(key, str) else key).cast("string")))


def is_heldout(text: Column | str) -> Column:
    """Whether a text belongs to the held-out sixteenth; copies of a text stay on one side."""
    return F.substring(F.md5(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))), 1, 1) == "0"


def span_index(pos: Column | str, span: int) -> Column:
    return F.floor((F.col(pos) if isinstance(pos, str) else pos) / span).cast("int")


def page_text(html: Column | str) -> Column:
    """Readable text of a page: scripts, styles, comments and tags out, five entities back, blanks single."""
    out = F.col(html) if isinstance(html, str) else html
    for pattern, to in (
        (r"(?is)<script[^>]*>.*?</script>", " "), (r"(?is)<style[^>]*>.*?</style>", " "), (r"(?s)<!--.*?-->", " "),
        (r"(?s)<[^>]*>", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&"), (r"[ \t\r\n]+", " "),
    ):
        out = F.regexp_replace(out, pattern, to)
    return F.trim(out)
