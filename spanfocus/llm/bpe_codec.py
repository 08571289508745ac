"""Word-level BPE as a bounded-lookahead streaming transducer, and an incremental decoder.

How far to the right of a token a text can still change that token depends on the merge list alone: a
merge (u, v) is undone only if v's right end had merged earlier with something further right, and so on
through merges of falling rank. The longest such chain that begins on a token's right edge is that token's
lookahead; the longest of all is the list's sufficient lookahead. The encoder reads a word's symbols a few
at a time, merges what it holds, and emits each token as soon as its own lookahead has been read. It holds
at most one token, the sufficient lookahead and one reading, whatever the length of the word. The ids of a
short word are remembered; every word goes through the transducer when it is first met. The decoder is a
state machine from ids to bytes to text.
"""

from __future__ import annotations

import codecs
import hashlib
import json
import unicodedata
from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache
from heapq import heapify, heappop, heappush
from itertools import islice

import regex
from pyspark.sql import DataFrame

from spanfocus.llm.arrow_rows import map_texts
from spanfocus.llm.token_counts import byte_alphabet

# The published pre-token pattern of this kind of vocabulary.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\p{White_Space}\p{L}\p{N}]+"

#: Distinct words a worker remembers, and words held at once of a long text.
REMEMBERED, HELD = 500_000, 200_000
#: Symbols that the transducer reads at once, and characters of a word that are expanded at once.
READING, _CHARS = 32, 4096
_SPACES = regex.compile(r"\p{White_Space}+")
_NONE = 1 << 40


def lookaheads(merges: list[tuple[str, str]], length: dict[str, int]) -> Callable[[str, str], int]:
    """For a token and the character that follows it (empty: any), the symbols past its end that can still change it.

    Walks the merges by rank. ``reach`` of u is the furthest right that a merge with left part u, of lower
    rank than the one looked at, depends on; the right spine of a token names the parts that stood at its
    right end before it was whole. A merge (u, v) only matters where v's first character follows.
    """
    parts: dict[str, tuple[str, str]] = {}
    reach: dict[tuple[str, str], int] = {}

    def beyond(token: str, following: str = "") -> int:
        most = 0
        while True:
            most = max(most, reach.get((token, following), 0))
            if token not in parts:
                return most
            token = parts[token][1]

    for u, v in merges:
        far = length[v] + beyond(v)
        for following in ("", v[0]):
            reach[u, following] = max(reach.get((u, following), 0), far)
        parts.setdefault(u + v, (u, v))
    return beyond


class Codec:
    """A vocabulary file: encoder and decoder."""

    def __init__(self, path: str, reading: int = READING) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.end = model["end_of_word_suffix"] or ""
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.rank = {p: r for r, p in enumerate(pairs)}
        self.bytes = byte_alphabet()
        self.byte_of = {c: b for b, c in self.bytes.items()}
        length = {t: len(t.removesuffix(self.end) if self.end else t) for t in self.vocab}
        self.lookahead_of = lookaheads(pairs, length)
        self.lookahead = max(map(self.lookahead_of, self.vocab), default=0)
        self.longest = max(length.values(), default=1)
        self.reading = reading
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.special_pattern = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))))
        self.string_of = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.special.items()}
        self.piece_of = {i: self._piece(t) for t, i in self.vocab.items()} | {i: t.encode() for t, i in self.special.items()}
        self.words = regex.compile(PATTERN)
        self.known: dict[str, list[int]] = {}

    def _piece(self, token: str) -> bytes:
        """Bytes of a token; its end mark is a blank."""
        closed = bool(self.end) and token.endswith(self.end)
        body = token.removesuffix(self.end) if closed else token
        return bytes(self.byte_of[c] for c in body if c in self.byte_of) + (b" " if closed else b"")

    def merged(self, symbols: list[str]) -> list[str]:
        """Symbols after all merges, lowest rank first and left to right."""
        if len(symbols) > 32:
            return self._merged_long(symbols)
        rank, symbols = self.rank.get, list(symbols)
        ranks = [rank(p, _NONE) for p in zip(symbols, symbols[1:], strict=False)]
        while ranks and (best := min(ranks)) != _NONE:
            i = ranks.index(best)
            symbols[i] += symbols.pop(i + 1)
            # Only the pairs on either side of the new token change.
            del ranks[i]
            if i:
                ranks[i - 1] = rank((symbols[i - 1], symbols[i]), _NONE)
            if i < len(ranks):
                ranks[i] = rank((symbols[i], symbols[i + 1]), _NONE)
        return symbols

    def _merged_long(self, symbols: list[str]) -> list[str]:
        """The same for many symbols: a heap of candidate merges over a linked list."""
        n, rank, text = len(symbols), self.rank.get, list(symbols)
        after, before = [*range(1, n), -1], list(range(-1, n - 1))
        heap = [(r, i, text[i], text[i + 1]) for i in range(n - 1) if (r := rank((text[i], text[i + 1]))) is not None]
        heapify(heap)
        while heap:
            _, i, a, b = heappop(heap)
            j = after[i]
            if text[i] != a or j < 0 or text[j] != b:
                continue  # one of the two has merged meanwhile
            text[i], text[j] = a + b, ""
            after[i] = after[j]
            if after[j] >= 0:
                before[after[j]] = i
            for left, right in ((before[i], i), (i, after[i])):
                if left >= 0 and right >= 0 and (r := rank((text[left], text[right]))) is not None:
                    heappush(heap, (r, left, text[left], text[right]))
        return [t for t in text if t]

    def stream(self, symbols: Iterable[str]) -> Iterator[str]:
        """Tokens of one word's symbols (the last one bears the end mark), each emitted once it is stable.

        Holds at most ``longest + lookahead + reading`` symbols.
        """
        source, held = iter(symbols), []
        while more := list(islice(source, self.reading)):
            held += more
            tokens, used = self.merged(held), 0
            if len(more) < self.reading:
                yield from tokens
                return
            for t, following in zip(tokens, [*(t[0] for t in tokens[1:]), ""], strict=True):
                size = 1 if t in self.byte_of else len(t)
                if len(held) - used - size < self.lookahead_of(t, following):
                    break
                used += size
                yield t
            del held[:used]
        yield from self.merged(held)

    def symbols(self, word: str) -> Iterator[str]:
        """Byte symbols of a word one by one, the end mark on the last."""
        before = None
        for a in range(0, len(word), _CHARS):
            for b in word[a : a + _CHARS].encode():
                if before is not None:
                    yield before
                before = self.bytes[b]
        if before is not None:
            yield before + self.end

    def word_ids(self, word: str) -> list[int]:
        """Ids of one pre-token by the transducer; those of short words are remembered, up to a bound."""
        ids = self.known.get(word)
        if ids is None:
            ids = [self.vocab[t] for t in self.stream(self.symbols(word))]
            if len(word) < 64:
                if len(self.known) >= REMEMBERED:
                    self.known.clear()
                self.known[word] = ids
        return ids

    @staticmethod
    def normal(text: str) -> str:
        """Composed form, single blanks, lower case by character (no final-sigma rule)."""
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
            text = _SPACES.sub(" ", text)
            return "".join(c.lower() for c in text) if "Σ" in text else text.lower()
        return text.lower()

    def encode(self, text: str) -> Iterator[list[int]]:
        """Ids of a whole text, a list for each stretch of bounded length; special strings are their own id."""
        at = 0
        for m in self.special_pattern.finditer(text) if "<|" in text else ():
            yield from self._plain(text[at : m.start()])
            yield [self.special[m.group()]]
            at = m.end()
        yield from self._plain(text[at:] if at else text)

    def _plain(self, text: str) -> Iterator[list[int]]:
        known, word_ids, line = self.known, self.word_ids, self.normal(text)
        found = (m.group() for m in self.words.finditer(line)) if len(line) > HELD else iter(self.words.findall(line))
        while words := list(islice(found, HELD)):
            ids: list[int] = []
            for w in words:
                ids += known.get(w) or word_ids(w)
            yield ids


class Decoder:
    """Ids to text, a piece at a time: feed ids, get the text that is certain, then ``finish``.

    ``plain`` False gives what the library's decode gives for a vocabulary without decoder: the tokens'
    own strings with one blank between. True gives readable text: byte symbols become bytes, bytes become
    text as soon as a UTF-8 sequence is whole (a broken one becomes U+FFFD), end marks become blanks.
    """

    def __init__(self, codec: Codec, plain: bool = False) -> None:
        self.codec, self.plain = codec, plain
        self.utf8 = codecs.getincrementaldecoder("utf-8")("replace")
        self.begun = False

    def feed(self, ids: Iterable[int]) -> str:
        if self.plain:
            return self.utf8.decode(b"".join(map(self.codec.piece_of.__getitem__, ids)))
        out = " ".join(map(self.codec.string_of.__getitem__, ids))
        lead = " " if self.begun and out else ""
        self.begun = self.begun or bool(out)
        return lead + out

    def finish(self) -> str:
        return self.utf8.decode(b"", True) if self.plain else ""


@lru_cache(maxsize=2)
def codec(path: str) -> Codec:
    return Codec(path)


def encode_documents(df: DataFrame, vocabulary: str, key: str = "doc_id", text: str = "text", keep_ids: bool = True) -> DataFrame:
    """(key, n_tokens, ids_sha256, decoded_sha256, readable_sha256[, ids]) of every row's whole text.

    Null and empty texts have no ids. The digests are of the decimal ids joined by one blank, of the decoded
    text in UTF-8 as the library gives it, and of the readable text; all are fed stretch by stretch. Repeated rows stay; other columns are not read.
    """

    def run(texts: list[str]) -> dict[str, list]:
        c = codec(vocabulary)
        out: dict[str, list] = {"n_tokens": [], "ids_sha256": [], "decoded_sha256": [], "readable_sha256": [], "ids": []}
        for t in texts:
            n, all_ids, decoder, reader = 0, [], Decoder(c), Decoder(c, plain=True)
            by_id, by_text, by_reading = hashlib.sha256(), hashlib.sha256(), hashlib.sha256()
            for ids in c.encode(t):
                if ids:
                    by_id.update(((" " if n else "") + " ".join(map(str, ids))).encode())
                    by_text.update(decoder.feed(ids).encode())
                    by_reading.update(reader.feed(ids).encode())
                    n += len(ids)
                    if keep_ids:
                        all_ids += ids
            by_text.update(decoder.finish().encode())
            by_reading.update(reader.finish().encode())
            made = (n, by_id.hexdigest(), by_text.hexdigest(), by_reading.hexdigest(), all_ids)
            for column, value in zip(out.values(), made, strict=True):
                column.append(value)
        return out

    schema = "n_tokens bigint, ids_sha256 string, decoded_sha256 string, readable_sha256 string" + (", ids array<int>" if keep_ids else "")
    return map_texts(df, [key], text, schema, run)
