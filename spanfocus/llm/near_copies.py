"""SimHash near-duplicates by anchor-point covering.

Two 64-bit fingerprints that differ in at most three bits differ in at most one bit in one of their
halves. Each half is covered by anchors: the codewords of the Hamming code of length 31 (covering radius
1), times the free top bit. A fingerprint is at home at the anchor nearest to its half and is replicated
to every anchor within covering radius plus one; so any two linked fingerprints meet at a home anchor.
Members of an anchor are compared in blocks of bounded size, and only a spanning forest of the links
leaves a block. Components come from alternating star contraction over those links.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from spanfocus.llm.arrow_rows import map_texts
from spanfocus.session import cut, ship_package

THRESHOLD = 3
#: Members of one anchor that one task compares at once.
BLOCK = 2048
_HASHES = 65_536


def shingle_hashes(text: str, words: int = 3, seed: int = 42) -> np.ndarray:
    """XXH64 of every word shingle of a whole text, repeats included; a shorter text is one shingle, one without words none."""
    parts = text.encode().lower().split()
    if not parts:
        return np.zeros(0, np.uint64)
    ends, at = [], -1
    for p in parts:
        at += len(p) + 1
        ends.append(at)
    line, n, digest = b" ".join(parts), max(1, len(parts) - words + 1), xxhash.xxh64_intdigest
    if len(parts) <= words:
        return np.array([digest(line, seed)], np.uint64)
    starts = [0, *(e + 1 for e in ends[: n - 1])]
    return np.fromiter((digest(line[s:e], seed) for s, e in zip(starts, ends[words - 1 :], strict=True)), np.uint64, n)


def majority_bits(h: np.ndarray) -> int:
    """The number whose bits are those set in over half of the hashes; zero for none."""
    set_bits = np.zeros(64, np.int64)
    for a in range(0, h.size, _HASHES):
        some = h[a : a + _HASHES].astype(">u8")
        set_bits += np.unpackbits(some.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * set_bits > h.size).tobytes(), "big")


def fingerprint(text: str, words: int = 3, seed: int = 42) -> int:
    """SimHash of a whole text over its word shingles, repeats included; zero for a text without words."""
    return majority_bits(shingle_hashes(text, words, seed))


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, fp): the fingerprint of every row as a signed 64-bit number. Null text counts as empty."""

    def run(texts: list[str]) -> dict[str, list]:
        fps = [fingerprint(t) for t in texts]
        return {"fp": np.array(fps, np.uint64).view(np.int64)}

    return map_texts(docs, [key], text, "fp bigint", run)


def _syndromes(half: np.ndarray) -> np.ndarray:
    """For each 31-bit word the xor of the 1-based places of its set bits: 0 for a codeword."""
    s = np.zeros(half.shape, np.uint32)
    for place in range(31):
        s ^= np.where(half >> np.uint32(place) & np.uint32(1), np.uint32(place + 1), np.uint32(0))
    return s


def _flip(places: np.ndarray) -> np.ndarray:
    """The one-bit mask of a 1-based place; 0 for place 0."""
    return np.where(places > 0, np.uint32(1) << (np.maximum(places, 1) - 1).astype(np.uint32), np.uint32(0)).astype(np.uint32)


def anchors_of(half: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Home anchor of each 32-bit half, and a matrix of all other anchors within covering radius plus one.

    The columns are the homes of the half after each single flip (31 code bits in the lower part and the
    free bit). Columns that repeat the home or another column hold the home itself and are to be skipped.
    """
    low, free = half & np.uint32(0x7FFFFFFF), half & np.uint32(0x80000000)
    s = _syndromes(low)
    home = low ^ _flip(s) | free
    near = np.repeat(home[:, None], 32, axis=1)
    for place in range(1, 32):
        partner = s ^ np.uint32(place)
        other = low ^ _flip(np.full(s.shape, place, np.uint32)) ^ _flip(partner) | free
        # The flips (place, partner) and (partner, place) lead to one codeword: keep the smaller place.
        once = (partner == 0) | (np.uint32(place) <= partner)
        near[:, place - 1] = np.where(once, other, home)
    near[:, 31] = home ^ np.uint32(0x80000000)
    return home, near


def place_at_anchors(fps: DataFrame) -> DataFrame:
    """(cell, is_home, fp): each distinct fingerprint at its home and near anchors, for both halves.

    A cell is an anchor of 32 bits; those of the upper half lie above the others.
    """
    schema = StructType.fromDDL("cell bigint, is_home boolean, fp bigint")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for a in range(0, len(frame), 4096):
                fp = frame["fp"].to_numpy(np.int64)[a : a + 4096]
                for half in (0, 1):
                    word = (fp.view(np.uint64) >> np.uint64(32 * half) & np.uint64(0xFFFFFFFF)).astype(np.uint32)
                    home, near = anchors_of(word)
                    row, col = np.nonzero(near != home[:, None])
                    yield pd.DataFrame(
                        {
                            "cell": np.concatenate([home, near[row, col]]).astype(np.int64) | half << 32,
                            "is_home": np.arange(len(fp) + len(row)) < len(fp),
                            "fp": np.concatenate([fp, fp[row]]),
                        }
                    )

    ship_package(fps.sparkSession)
    return fps.select("fp").mapInPandas(run, schema)


class Forest:
    """Union-find over the members of a cell: keeps the links that join something."""

    def __init__(self, n: int) -> None:
        self.parent = list(range(n))

    def root(self, i: int) -> int:
        parent = self.parent
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    def join(self, i: int, j: int) -> None:
        a, b = self.root(i), self.root(j)
        if a != b:
            self.parent[max(a, b)] = min(a, b)

    def links(self) -> tuple[np.ndarray, np.ndarray]:
        """Places of the joined members and of their roots."""
        joined = [(i, r) for i in range(len(self.parent)) if (r := self.root(i)) != i]
        pairs = np.array(joined, np.int64).reshape(-1, 2)
        return pairs[:, 0], pairs[:, 1]


#: Which of many members (columns of arrays) are linked to one of them.
Linked = Callable[[list[np.ndarray], list], np.ndarray]


def _cell_links(columns: list[np.ndarray], is_home: np.ndarray, linked: Linked) -> tuple[np.ndarray, np.ndarray]:
    """Links between members at home and all members, reduced to a spanning forest, as values of the first column.

    A component grows from a member at home; those it has reached are compared only with members that none has
    reached, so a cell full of copies costs little more than one pass over it.
    """
    left, reached, us, vs = np.arange(len(is_home)), np.zeros(len(is_home), bool), [columns[0][:0]], [columns[0][:0]]
    rest, homes = columns, is_home
    for first in np.flatnonzero(is_home).tolist():
        if reached[first]:
            continue
        other, waiting = left != first, [first]
        left, rest, homes = left[other], [c[other] for c in rest], homes[other]
        while waiting and left.size:
            i = waiting.pop()
            hit = linked(rest, [c[i] for c in columns])
            if not is_home[i]:
                hit &= homes
            if hit.any():
                found, other = left[hit], ~hit
                reached[found] = True
                us.append(columns[0][found])
                vs.append(np.full(found.size, columns[0][first]))
                waiting.extend(found.tolist())
                left, rest, homes = left[other], [c[other] for c in rest], homes[other]
    return np.concatenate(us), np.concatenate(vs)


def differing_bits(fps: np.ndarray, fp: int) -> np.ndarray:
    return np.bitwise_count((fps ^ fp).view(np.uint64))


def links_in_cells(at: DataFrame, linked: Linked, block: int = BLOCK) -> DataFrame:
    """(u, v): links between members of the same cell, reduced per block to a spanning forest.

    ``at`` has (cell, is_home, node, further columns): members at home are compared with all. Cells of more
    than ``block`` members are dealt out as block pairs, every home block against every block, so no task
    holds more than two blocks. Repeated rows change nothing.
    """
    payload = [c for c in at.columns if c not in ("cell", "is_home")]
    sizes = at.groupBy("cell").agg(F.count("*").alias("n_"), F.sum(F.col("is_home").cast("int")).alias("homes_"))
    # A cell without a home, or with nothing beside one, has nothing to compare.
    parts = F.ceil(F.col("n_") / block).cast("int")
    sizes = sizes.where((F.col("homes_") > 0) & (F.col("n_") > 1)).select("cell", parts.alias("parts_"))
    own = F.pmod(F.xxhash64(payload[0]), F.col("parts_")).cast("int")
    all_parts = F.sequence(F.lit(0), F.col("parts_") - 1)
    single = F.array(F.struct(F.lit(0).alias("i"), F.lit(0).alias("j"), F.col("is_home").alias("as_home")))
    as_home = F.transform(all_parts, lambda j: F.struct(own.alias("i"), j.alias("j"), F.lit(True).alias("as_home")))
    as_other = F.transform(all_parts, lambda i: F.struct(i.alias("i"), own.alias("j"), F.lit(False).alias("as_home")))
    many = F.when(F.col("is_home"), F.concat(as_home, as_other)).otherwise(as_other)
    dealt = (
        at.join(sizes.hint("merge"), "cell")
        .select("cell", *payload, F.explode(F.when(F.col("parts_") == 1, single).otherwise(many)).alias("d"))
        .select(F.xxhash64("cell", "d.i", "d.j").alias("pair"), "cell", "d.i", "d.j", "d.as_home", *payload)
    )

    def compare(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        """Cells arrive sorted, rows of a cell together; a cell may span two Arrow batches."""
        held: list[pd.DataFrame] = []
        names = ["pair", "cell", "i", "j"]

        def settled(frame: pd.DataFrame) -> pd.DataFrame:
            cols = [frame[n].to_numpy() for n in names]
            new = np.ones(len(frame), bool)
            new[1:] = np.any([c[1:] != c[:-1] for c in cols], axis=0)
            starts = [*np.flatnonzero(new).tolist(), len(frame)]
            data, is_home, us, vs = [frame[n].to_numpy() for n in payload], frame["as_home"].to_numpy(bool), [], []
            for a, b in zip(starts, starts[1:], strict=False):
                if b - a > 1 and is_home[a:b].any():
                    u, v = _cell_links([c[a:b] for c in data], is_home[a:b], linked)
                    us.append(u)
                    vs.append(v)
            return pd.DataFrame({"u": np.concatenate([np.zeros(0, np.int64), *us]), "v": np.concatenate([np.zeros(0, np.int64), *vs])})

        for frame in frames:
            if not len(frame):
                continue
            last = frame[names].iloc[-1]
            tail = (frame[names] == last).all(axis=1).to_numpy()
            cut_at = len(frame) - int(tail[::-1].argmin() if not tail.all() else len(frame))
            if cut_at or (held and tuple(held[-1][names].iloc[-1]) != tuple(last)):
                yield settled(pd.concat([*held, frame.iloc[:cut_at]]))
                held = []
            held.append(frame.iloc[cut_at:])
        if held:
            yield settled(pd.concat(held))

    ship_package(at.sparkSession)
    cols = ["pair", "cell", "i", "j"]
    return dealt.repartition("pair").sortWithinPartitions(*cols).mapInPandas(compare, "u bigint, v bigint").distinct()


def links(fps: DataFrame, threshold: int = THRESHOLD, block: int = BLOCK) -> DataFrame:
    """(u, v): links between distinct fingerprints that differ in ``threshold`` bits or fewer, as forests.

    ``fps`` has one row for each distinct fingerprint.
    """
    if threshold > 3:
        raise ValueError("the halves' anchors cover thresholds up to 3")

    def linked(columns: list[np.ndarray], one: list) -> np.ndarray:
        return differing_bits(columns[0], one[0]) <= threshold

    return links_in_cells(place_at_anchors(fps), linked, block)  # cheap to place twice, large to keep


def components(edges: DataFrame, rounds: int = 50) -> DataFrame:
    """(node, root): the least node of each component, for the nodes of ``edges`` (columns u, v).

    Alternates two steps until nothing changes: every node points its larger neighbours, then its smaller
    ones, at its least neighbour. Each step is an aggregate and a join; lineage is cut after each round.
    """

    def pointed(pairs: DataFrame) -> DataFrame:
        least = pairs.groupBy("a").agg(F.min("b").alias("m"))
        # Both sides lie dealt by ``a``: a broadcast would only send them through the driver, round after round.
        return pairs.join(least.select(F.col("a"), F.least("a", "m").alias("m")).hint("merge"), "a")

    def stamp(df: DataFrame) -> tuple:
        row = df.agg(F.count("*"), F.bit_xor(F.xxhash64("a", "b"))).first()
        return tuple(row)

    now = cut(edges.where("u <> v").select(F.greatest("u", "v").alias("a"), F.least("u", "v").alias("b")).distinct())
    seen = stamp(now)
    for _ in range(rounds):
        if not seen[0]:
            break
        both = now.union(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        large = pointed(both).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")
        # Dealt by their larger node once, these rows are aggregated and joined where they are.
        small = pointed(large.repartition("a"))  # here every row has b < a
        now = cut(
            small.select("a", F.col("m").alias("b"))
            .union(small.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")))
            .distinct()
        )
        found = stamp(now)
        if found == seen:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root"))
        seen = found
    if seen[0]:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return now.select(F.col("a").alias("node"), F.col("b").alias("root"))


def hex_fingerprint(fp: str | Column = "fp") -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def near_duplicate_groups(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, fp, component_id): the smallest id reachable over links of at most three differing bits.

    Copies collapse to their fingerprint before anything is compared. Null and empty texts share
    fingerprint zero and link like any other. A null id keeps its row; it is no component's smallest id.
    Repeated rows stay. An empty table gives an empty result.
    """
    rows = cut(fingerprints(docs, key, text))
    classes = rows.groupBy("fp").agg(F.min(key).alias("first_id"))
    classes = cut(classes)
    roots = components(links(classes.select("fp")))
    rooted = classes.join(roots.withColumnRenamed("node", "fp").hint("merge"), "fp", "left").select(
        "fp", "first_id", F.coalesce("root", "fp").alias("root")
    )
    least = rooted.groupBy("root").agg(F.min("first_id").alias("component_id"))
    of_class = rooted.join(least, "root").select("fp", "component_id")
    return rows.join(of_class, "fp").select(key, "fp", "component_id")
