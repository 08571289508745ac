"""Exact top-k inner products over bit-sliced indexes.

Rows are indexed in blocks. An index holds, for every vector component, its quantised value as bit
slices: one bitmap per binary digit, a bit per row. A batch of queries multiplies by adding shifted slices with
bitmap arithmetic (carry-save adders), which leaves the scores themselves as bit slices. The upper slices and the
upper digits of the weights come first: what they leave out is bounded, so the bit slices of these scores,
compared from the most significant downward, tell which rows can be among the best. Those few are compared by
exact scores, and rows that tie at the boundary are resolved by id.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spanfocus.session import cut, ship_package

#: Rows of an index block and queries of a query block.
BLOCK_ROWS, BLOCK_QUERIES = 8_192, 256
#: Weights of the queries that are added up together; slices of a component and digits of a weight that the first pass
#: adds; share of a block's rows beyond which a first pass is followed by one over all slices.
BATCH_WEIGHTS, UPPER_SLICES, UPPER_DIGITS, MANY = 1_024, 7, 6, 0.1


def _packed(bits: np.ndarray) -> np.ndarray:
    """Boolean rows to words of 64 bits, little end first."""
    by_byte = np.packbits(bits, axis=-1, bitorder="little")
    short = -by_byte.shape[-1] % 8
    return np.ascontiguousarray(np.pad(by_byte, [(0, 0)] * (bits.ndim - 1) + [(0, short)])).view(np.uint64)


def _positions(words: np.ndarray) -> np.ndarray:
    """The rows whose bit is set."""
    return np.flatnonzero(np.unpackbits(words.view(np.uint8), bitorder="little"))


class BitSlices:
    """Index of one block: ``ids`` ascending, ``slices[c, b]`` is bit b of component c plus ``offset``."""

    def __init__(self, ids: np.ndarray, values: np.ndarray) -> None:
        order = np.argsort(ids, kind="stable")
        self.ids, values = ids[order], values[order]
        low, high = (int(values.min()), int(values.max())) if values.size else (0, 0)
        self.offset, self.bits = -low, max(1, (high - low).bit_length())
        shifted = (values + self.offset).T
        self.slices = _packed(np.stack([(shifted >> b) & 1 == 1 for b in range(self.bits)], axis=1))
        self.all = _packed(np.ones((1, len(ids)), bool))[0]

    @classmethod
    def stored(cls, n_rows: int, bits: int, offset: int, ids: bytes, slices: bytes) -> BitSlices:
        """The index of a written block."""
        index = cls.__new__(cls)
        index.ids, index.offset, index.bits = np.frombuffer(ids, np.int64), offset, bits
        index.all = _packed(np.ones((1, n_rows), bool))[0]
        index.slices = np.frombuffer(slices, np.uint64).reshape(-1, bits, index.all.size)
        return index

    @cached_property
    def values(self) -> np.ndarray:
        """The rows' components, read back from the slices."""
        spelled = np.zeros((len(self.slices), len(self.ids)), np.uint64)
        for b in range(self.bits):
            bits = np.unpackbits(self.slices[:, b].view(np.uint8), axis=1, count=len(self.ids), bitorder="little")
            spelled |= bits.astype(np.uint64) << np.uint64(b)
        return np.ascontiguousarray((spelled.view(np.int64) - self.offset).T)

    @cached_property
    def longest(self) -> float:
        """The largest length of a row."""
        return float(np.sqrt(np.square(self.values.astype(float)).sum(1)).max(initial=0.0))

    @cached_property
    def _sources(self) -> dict[int, tuple[np.ndarray, float]]:
        return {}

    def _source(self, drop: int) -> tuple[np.ndarray, float]:
        """All slices without the ``drop`` lowest, then their complements, then an empty one; and the length of what
        the slices left out can add to a row, counted from its middle."""
        if drop not in self._sources:
            kept = self.slices[:, drop:].reshape(-1, self.all.size)
            mask = (1 << drop) - 1
            twice = 2 * (self.values + self.offset & mask) - mask
            rest = float(np.sqrt(np.square(twice.astype(float)).sum(1)).max(initial=0.0)) / 2
            self._sources[drop] = np.concatenate([kept, ~kept & self.all, np.zeros((1, self.all.size), np.uint64)]), rest
        return self._sources[drop]

    def _added(self, weights: np.ndarray, drop: int) -> tuple[np.ndarray, np.ndarray]:
        """Bit slices (place, query, word) of every row's score by the slices from ``drop`` on, for a batch of queries;
        and what each query's numbers are too large by.

        A weight is written with digits 1, 0 and -1, no two neighbours other than 0. A digit -1 uses the
        complement of the component's slices, so all terms add up.
        """
        source, _ = self._source(drop)
        n, bits = len(weights), self.bits - drop
        size = np.abs(weights).astype(np.uint64)
        half = size >> np.uint64(1)
        sums = size + half
        plus, minus = sums & (half ^ sums), half & (half ^ sums)
        plus, minus = np.where(weights < 0, minus, plus), np.where(weights < 0, plus, minus)
        terms, excess = [], np.zeros(n, object)
        for shift in range(int(max(plus.max(initial=0), minus.max(initial=0))).bit_length()):
            for digits, first in ((plus, 0), (minus, weights.shape[1])):
                query, component = np.nonzero(digits >> np.uint64(shift) & np.uint64(1))
                terms.append((query, (component + first) * bits, np.full(len(query), shift)))
                if first:
                    excess += np.bincount(query, minlength=n).astype(object) * ((1 << bits) - 1 << shift)
        query, base, shift = (np.concatenate([np.zeros(0, np.int64), *x]) for x in (zip(*terms, strict=True) if terms else ((),) * 3))
        wanted, heights, place = [], [], 0
        while place < bits + int(shift.max(initial=-1)) or heights and heights[-1] > 1:
            here = np.flatnonzero((shift <= place) & (place < shift + bits))
            here = here[np.argsort(query[here], kind="stable")]
            count = np.bincount(query[here], minlength=n)
            at = np.full((int(count.max(initial=0)), n), len(source) - 1)
            at[np.arange(len(here)) - np.repeat(np.cumsum(count) - count, count), query[here]] = base[here] + place - shift[here]
            wanted.append(at)
            heights.append(len(at) + (heights[-1] // 2 if heights else 0))
            place += 1
        out = np.zeros((place, n, self.all.size), np.uint64)
        columns, following, spare = (np.empty((max(heights, default=0) // x + 1, n, self.all.size), np.uint64) for x in (1, 1, 3))
        for place, at in enumerate(wanted):
            np.take(source, at, axis=0, out=columns[: len(at)], mode="clip")
            left, carries = heights[place], following[len(wanted[place + 1]) if place + 1 < len(wanted) else 0 :]
            while left > 1:
                # Full adders take three bitmaps of one place to one of it and one of the next.
                m = left // 3
                if m:
                    a, b, c, half, carry = columns[:m], columns[m : 2 * m], columns[2 * m : 3 * m], spare[:m], carries[:m]
                    np.bitwise_xor(a, b, out=half)
                    np.bitwise_and(a, b, out=carry)
                    np.bitwise_xor(half, c, out=a)
                    half &= c
                    carry |= half
                    columns[m : left - 2 * m] = columns[3 * m : left]
                    left, carries = left - 2 * m, carries[m:]
                else:
                    np.bitwise_and(columns[0], columns[1], out=carries[0])
                    columns[0] ^= columns[1]
                    left = 1
            if left:
                out[place] = columns[0]
            columns, following = following, columns
        return out, excess

    @staticmethod
    def _first(slices: np.ndarray, rows: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Of the bitmap ``rows`` of each query, those sure to be among the ``k`` largest numbers, and those tied for the rest."""
        sure, tied = np.zeros_like(rows), rows.copy()
        for s in slices[::-1]:
            with_one = tied & s
            grown = sure | with_one
            over = (np.bitwise_count(grown).sum(1, dtype=np.int64) > k)[:, None]
            tied = np.where(over, with_one, tied & ~s)
            sure = np.where(over, sure, grown)
        return sure, tied

    @staticmethod
    def _at_least(slices: np.ndarray, rows: np.ndarray, least: list[int]) -> np.ndarray:
        """Of the bitmap ``rows`` of each query, those whose number is no less than the query's own bound."""
        above, equal = np.zeros_like(rows), rows.copy()
        for place in reversed(range(len(slices))):
            one = np.array([[x >> place & 1] for x in least], bool)
            above |= np.where(one, np.uint64(0), equal & slices[place])
            equal &= np.where(one, slices[place], ~slices[place])
        return above | equal

    def _exact(self, rows: np.ndarray, query: np.ndarray) -> np.ndarray:
        """Inner products of some rows, in numbers that hold them."""
        bound = self.longest * float(np.sqrt(np.square(query.astype(float)).sum()))
        kind = np.int64 if bound < 2.0**61 else object
        return self.values[rows].astype(kind, copy=False) @ query.astype(kind, copy=False)

    def _near_top(self, queries: np.ndarray, k: int, rows: np.ndarray, drop: int, weight_bits: int) -> np.ndarray:
        """Of the bitmap ``rows`` of each query, at least those that no ``k`` others beat, ties included.

        Slices below ``drop`` are not added, and a weight keeps ``weight_bits`` digits. What is left out of a score is
        bounded by lengths (Cauchy-Schwarz), so no row is lost whose exact score may reach the k-th.
        """
        _, rest = self._source(drop)
        cuts = [max(0, int(x).bit_length() - weight_bits) for x in np.abs(queries).astype(np.uint64).max(1, initial=0)]
        cut_at = np.array(cuts)[:, None]
        weights = (queries >> cut_at) + np.where(cut_at > 0, queries >> np.maximum(cut_at - 1, 0) & 1, 0)
        slices, excess = self._added(weights, drop)
        sure, tied = self._first(slices, rows, k)
        length = np.sqrt(np.square(queries.astype(float)).sum(1))
        length_cut = np.sqrt(np.square((queries - (weights << cut_at)).astype(float)).sum(1))
        least = []
        for i, query in enumerate(queries):
            best = _positions(sure[i])
            seeds = np.concatenate([best, _positions(tied[i])[: k - len(best)]])
            if len(seeds) < k:
                least.append(0)
                continue
            error = int((length[i] * rest + length_cut[i] * (self.longest + rest)) * (1 + 1e-9)) + 1
            # Twice the numbers: a row counts from the middle of what its lowest slices spell.
            middle = ((1 << drop) - 1 - 2 * self.offset) * int(weights[i].astype(object).sum()) << cuts[i]
            low = 2 * (int(self._exact(seeds, query).min()) - error) - middle
            least.append(max(0, -(-low >> cuts[i] + drop + 1) + excess[i]))
        return self._at_least(slices, rows, least)

    def top_many(self, queries: np.ndarray, k: int, own: np.ndarray | None = None) -> list[list[tuple[int, int]]]:
        """Each query's ``k`` best (id, score), ties to the smaller id; rows with its id in ``own`` take no part.

        The upper slices alone leave few rows that can be among the best; where they leave many, all slices
        are added. The rows left are compared by their exact scores.
        """
        if not len(self.ids):
            return [[] for _ in queries]
        out: list[list[tuple[int, int]]] = []
        together = max(1, BATCH_WEIGHTS // max(1, queries.shape[1]))
        for start in range(0, len(queries), together):
            batch = queries[start : start + together]
            rows = np.repeat(self.all[None], len(batch), 0)
            if own is not None:
                first, last = (np.searchsorted(self.ids, own[start : start + together], side) for side in ("left", "right"))
                for i in np.flatnonzero(first < last):
                    mask = np.zeros(len(self.ids), bool)
                    mask[first[i] : last[i]] = True
                    rows[i] &= ~_packed(mask[None])[0]
            near = self._near_top(batch, k, rows, max(0, self.bits - UPPER_SLICES), UPPER_DIGITS)
            many = np.flatnonzero(np.bitwise_count(near).sum(1, dtype=np.int64) > max(4 * k, len(self.ids) * MANY))
            if len(many):
                near[many] = self._near_top(batch[many], k, near[many], 0, 64)
            for query, bitmap in zip(batch, near, strict=True):
                left = _positions(bitmap)
                score = self._exact(left, query)
                order = np.argsort(-score, kind="stable")[:k]
                out.append(list(zip(self.ids[left[order]].tolist(), score[order].tolist(), strict=True)))
        return out

    def top(self, query: np.ndarray, k: int, own: int | None = None) -> list[tuple[int, int]]:
        """:meth:`top_many` of one query."""
        return self.top_many(query[None], k, None if own is None else np.array([own]))[0]


def quantised(vectors: DataFrame, key: str = "vec_id", vector: str = "embedding", scale: int = 256) -> DataFrame:
    """(key, q): floor(scale * x) of every component as a double; rows that cannot take part are left out.

    Those are rows with a null id, a null or empty vector, or a null or non-finite component.
    """
    v = F.col(vector).cast("array<double>")
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    rows = vectors.where(F.col(key).isNotNull() & v.isNotNull() & (F.size(v) > 0) & ~bad)
    return rows.select(key, F.transform(v, lambda x: F.floor(x * F.lit(float(scale))).cast("bigint")).alias("q"))


def _matrix(column: list[list[int]]) -> np.ndarray:
    """Rows of numbers as a matrix; a shorter row is filled with zeros."""
    width = max(map(len, column), default=0)
    if all(len(r) == width for r in column):
        return np.array(column, np.int64).reshape(len(column), width)
    return np.array([[*r, *[0] * (width - len(r))] for r in column], np.int64)


def index_blocks(vectors: DataFrame, key: str = "vec_id", block_rows: int = BLOCK_ROWS, copies: int = 5) -> DataFrame:
    """Stored form of the index: (g, n_rows, bits, offset, ids, slices), a row per block of (key, q).

    Rows are dealt to even blocks by the hash of their content, so a task that runs again deals them the same
    way. Rows equal in id and vector count up to ``copies`` times; a block that chance makes larger than
    ``block_rows`` becomes several.
    """
    ship_package(vectors.sparkSession)
    once = vectors.groupBy(key, "q").agg(F.count("*").alias("n"))
    groups = max(1, -(-vectors.count() // block_rows))
    rows = once.select(key, "q", F.explode(F.sequence(F.lit(1), F.least("n", F.lit(copies)).cast("int"))).alias("copy"))
    rows = rows.select(F.pmod(F.xxhash64(key, "q", "copy"), F.lit(groups)).cast("int").alias("g"), key, "q")

    def build(frame: pd.DataFrame) -> pd.DataFrame:
        ids, values, out = frame[key].to_numpy(np.int64), _matrix(frame["q"].tolist()), []
        for a in range(0, len(ids), block_rows):
            index = BitSlices(ids[a : a + block_rows], values[a : a + block_rows])
            out.append((int(frame["g"].iloc[0]), len(index.ids), index.bits, index.offset, index.ids.tobytes(), index.slices.tobytes()))
        return pd.DataFrame(out, columns=["g", "n_rows", "bits", "offset", "ids", "slices"])

    return rows.groupBy("g").applyInPandas(build, "g int, n_rows bigint, bits int, offset bigint, ids binary, slices binary")


def query_blocks(queries: DataFrame, key: str = "vec_id", block_queries: int = BLOCK_QUERIES) -> DataFrame:
    """(h, asked, weights): ids and vectors of even blocks of queries; an id with several vectors asks with the least."""
    ask = queries.groupBy(key).agg(F.min("q").alias("q"))
    groups = max(1, -(-ask.count() // block_queries))

    def pack(frame: pd.DataFrame) -> pd.DataFrame:
        weights = _matrix(frame["q"].tolist())
        return pd.DataFrame({"h": [int(frame["h"].iloc[0])], "asked": [frame[key].to_numpy(np.int64).tobytes()], "weights": [weights.tobytes()]})

    rows = ask.select(F.pmod(F.xxhash64(key), F.lit(groups)).cast("int").alias("h"), key, "q")
    return rows.groupBy("h").applyInPandas(pack, "h int, asked binary, weights binary")


def top_k(
    candidates: DataFrame, queries: DataFrame, k: int = 5, key: str = "vec_id", block_rows: int = BLOCK_ROWS, block_queries: int = BLOCK_QUERIES
) -> DataFrame:
    """(query_id, rank, <key>, score): each query's ``k`` best candidates by inner product, exactly.

    Both inputs have (key, q) as from :func:`quantised`. A candidate with the query's id is the query's own
    and takes no part. Ties go to the smaller id; fewer candidates give fewer rows; repeated candidates
    each count; repeated queries count once (the least vector, if one id has several). A shorter vector is
    filled with zeros. The index is built and written once; its blocks meet blocks of queries, each pair
    once, and a task holds one such pair.
    """
    spark = candidates.sparkSession
    ship_package(spark)
    index, asked = cut(index_blocks(candidates, key, block_rows, k)), cut(query_blocks(queries, key, block_queries))
    row_groups, query_groups = ((d.agg(F.max(c)).first()[0] or 0) + 1 for d, c in ((index, "g"), (asked, "h")))
    parts = max(1, min(row_groups * query_groups, 8 * spark.sparkContext.defaultParallelism))
    for_all = lambda name, n: F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias(name)
    left = index.select("*", for_all("h", query_groups)).repartition(parts, "g", "h")
    pairs = left.join(asked.select("*", for_all("g", row_groups)).repartition(parts, "g", "h"), ["g", "h"])

    def search(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for r in frame.itertuples(index=False):
                block, out = BitSlices.stored(r.n_rows, r.bits, r.offset, r.ids, r.slices), []
                own = np.frombuffer(r.asked, np.int64)
                weights = np.frombuffer(r.weights, np.int64).reshape(len(own), -1)
                # Components beyond the shorter of the two are zero.
                weights = np.pad(weights, [(0, 0), (0, max(0, len(block.slices) - weights.shape[1]))])[:, : len(block.slices)]
                for one, best in zip(own.tolist(), block.top_many(weights, k, own), strict=True):
                    out += [(one, i, s) for i, s in best]
                yield pd.DataFrame(out, columns=["query_id", key, "score"])

    found = pairs.mapInPandas(search, f"query_id bigint, {key} bigint, score bigint")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), key)
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", key, "score")


def every_nth(vectors: DataFrame, n: int, key: str = "vec_id") -> DataFrame:
    """The rows whose id is divisible by ``n``."""
    return vectors.where(F.pmod(F.col(key), F.lit(n)) == 0)
