"""Token counts of byte-level BPE by rank-synchronous merging of ragged numpy arrays.

All pre-tokens of a block lie end to end in one array. Each round finds every sequence's pair of lowest
rank, replaces all its occurrences in all sequences at once, and drops the sequences that are done; what
is left of a sequence is its number of tokens. A bounded table remembers pre-tokens already counted.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from functools import lru_cache
from itertools import islice

import numpy as np
import regex
from pyspark.sql import DataFrame

from spanfocus.llm.arrow_rows import map_texts

# The published pre-token pattern of byte-level BPE.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"""

#: Pre-tokens whose counts a worker remembers, and pre-tokens held at once of a long text.
REMEMBERED, HELD = 300_000, 200_000
_NO_RANK = np.iinfo(np.int32).max


def byte_alphabet() -> dict[int, str]:
    """Byte to the printable character that stands for it in byte-level vocabularies."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table = {b: chr(b) for b in shown}
    table |= {b: chr(256 + i) for i, b in enumerate(b for b in range(256) if b not in table)}
    return table


class MergeTable:
    """Merge ranks of a vocabulary file as sorted arrays, and the rank-synchronous counter."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab = spec["model"]["vocab"]
        pairs = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        self.of_byte = np.array([vocab[c] for _, c in sorted(byte_alphabet().items())], np.int64)
        keys = np.array([vocab[a] << 32 | vocab[b] for a, b in pairs], np.int64)
        order = np.argsort(keys)
        self.keys, self.rank = keys[order], order.astype(np.int32)
        self.made = np.array([vocab[a + b] for a, b in pairs], np.int64)
        special = [t["content"] for t in spec["added_tokens"]]
        self.special = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None
        self.words = regex.compile(PATTERN)
        self.known: dict[str, int] = {}

    def _ranks(self, ids: np.ndarray, seq: np.ndarray) -> np.ndarray:
        """Rank of the pair that starts at each place; _NO_RANK at the last place of a sequence."""
        rank = np.full(ids.size, _NO_RANK, np.int32)
        key = ids[:-1] << 32 | ids[1:]
        at = np.minimum(np.searchsorted(self.keys, key), self.keys.size - 1)
        hit = (self.keys[at] == key) & (seq[:-1] == seq[1:])
        rank[:-1][hit] = self.rank[at[hit]]
        return rank

    def counts(self, words: list[bytes]) -> np.ndarray:
        """Tokens of each byte string when its merges are applied to the end."""
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        out = sizes.copy()
        ids = self.of_byte[np.frombuffer(b"".join(words), np.uint8)]
        seq = np.repeat(np.arange(len(words)), sizes)
        while ids.size:
            rank = self._ranks(ids, seq)
            starts = np.flatnonzero(np.diff(seq, prepend=-1))
            best = np.minimum.reduceat(rank, starts)
            length = np.diff(starts, append=ids.size)
            done = best == _NO_RANK
            out[seq[starts[done]]] = length[done]
            at = np.flatnonzero((rank == np.repeat(best, length)) & (rank != _NO_RANK))
            if not at.size:
                break
            # In a run of overlapping occurrences (a a a) the first, third, ... are replaced.
            run = np.maximum.accumulate(np.where(np.diff(at, prepend=-2) > 1, np.arange(at.size), 0))
            at = at[(at - at[run]) % 2 == 0]
            ids[at] = self.made[rank[at]]
            keep = np.repeat(~done, length)
            keep[at + 1] = False
            ids, seq = ids[keep], seq[keep]
        return out

    def pieces(self, text: str) -> Iterator[list[str]]:
        """The pre-tokens of a text without special strings, in lists of bounded length."""
        if len(text) < HELD:
            yield self.words.findall(text)
            return
        found = (m.group() for m in self.words.finditer(text))
        while some := list(islice(found, HELD)):
            yield some

    def learn(self, words: list[str]) -> None:
        """Count pre-tokens not yet known."""
        new = list({*words} - self.known.keys())
        if len(self.known) + len(new) > REMEMBERED:
            self.known.clear()
            new = list({*words})
        if new:
            self.known.update(zip(new, self.counts([w.encode() for w in new]).tolist(), strict=True))

    def count_texts(self, texts: list[str]) -> list[int]:
        """Tokens of whole texts; special strings inside a text are one token each."""
        totals, waiting, held = [0] * len(texts), [], 0

        def settle() -> None:
            self.learn([w for _, ws in waiting for w in ws])
            for i, ws in waiting:
                totals[i] += sum(map(self.known.__getitem__, ws))
            waiting.clear()

        for i, text in enumerate(texts):
            parts = [text]
            if self.special is not None and "<|" in text:
                parts = self.special.split(text)
                totals[i] += len(parts) - 1
            for part in parts:
                for some in self.pieces(part):
                    waiting.append((i, some))
                    held += len(some)
                    if held >= HELD:
                        settle()
                        held = 0
        settle()
        return totals


@lru_cache(maxsize=2)
def merge_table(path: str) -> MergeTable:
    return MergeTable(path)


def count_tokens(df: DataFrame, vocabulary: str, limit: int = 512, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_bytes, n_tokens, over_limit) of every row, by the vocabulary file at ``vocabulary``.

    Null and empty texts have no tokens. Repeated rows stay; other columns are not read; a long text is
    taken whole, a bounded number of its pre-tokens at a time. ``over_limit``: more than ``limit`` tokens.
    """

    def run(texts: list[str]) -> dict[str, list]:
        n = merge_table(vocabulary).count_texts(texts)
        return {"n_bytes": [len(t.encode()) for t in texts], "n_tokens": n, "over_limit": [x > limit for x in n]}

    return map_texts(df, [key], text, "n_bytes bigint, n_tokens bigint, over_limit boolean", run)
