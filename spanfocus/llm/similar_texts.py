"""Groups of texts whose five-word shingles are alike: SimHash finds the neighbourhoods, exact Jaccard decides.

Three bits of 64 catch few of the pairs with a similarity of 0.8 (there, about ten bits differ), and no
covering code over 64 bits reaches that far. So texts also meet at cells taken from their shingles: pairs of
shingles that come first in two random orders. One common line is not enough to share such a pair, so cells
stay small however many texts hold the line. At a cell sketches of the whole sets are compared, one bit for
each of 256 orders: they tell a similarity of 0.8 from one of 0.5, so no chain of chance neighbours runs
through unrelated texts. A spanning forest of the links leaves the cell; the components, with the links of
the covering code, are neighbourhoods. Inside each, whole shingle sets are compared block by block, exactly,
and again only a forest of the links leaves a block.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spanfocus.llm.arrow_rows import map_texts
from spanfocus.llm.near_copies import Forest, components, differing_bits, links, links_in_cells, majority_bits, shingle_hashes
from spanfocus.session import cut, release

#: Fingerprints and whole sets of one block.
BLOCK_PRINTS, BLOCK_SETS = 16_384, 512
#: Cells of a text, each of two orders' first shingles. Two texts of similarity 0.8 share none with probability
#: (1 - 0.8 ** 2) ** CELLS, which is 6e-7.
CELLS = 14
#: Differing bits of 256 up to which sketches are neighbours. At similarity 0.8 the mean is 25.6, the deviation 4.8.
NEAR_BITS = 50
#: Columns of the sketch, 64 orders each.
SKETCH = ("b0", "b1", "b2", "b3")
_ORDERS = np.random.default_rng(11).integers(0, 1 << 32, 64 * len(SKETCH), np.uint32) | np.uint32(1)
_COLUMNS, _SHINGLES = 4096, 256


def shingle_set(h: np.ndarray) -> np.ndarray:
    """Distinct shingle hashes, ascending; a text without words has the one shingle of an empty text."""
    return np.unique(h if h.size else np.array([xxhash.xxh64_intdigest(b"")], np.uint64)).view(np.int64)


def text_digest(text: str = "text") -> Column:
    return F.unhex(F.md5(F.coalesce(F.col(text), F.lit(""))))


def first_shingles(s: np.ndarray) -> np.ndarray:
    """For each order the place in it of the shingle that comes first; equal for two sets as often as they are similar."""
    x, first = (s.view(np.uint64) >> np.uint64(32)).astype(np.uint32), np.full(_ORDERS.size, 0xFFFFFFFF, np.uint32)
    for a in range(0, x.size, _SHINGLES):
        np.minimum(first, (_ORDERS[:, None] * x[None, a : a + _SHINGLES]).min(axis=1), out=first)
    return first


def sketch(first: np.ndarray) -> np.ndarray:
    """One bit for each order, packed."""
    return np.packbits((first * np.uint32(0x9E3779B1) >> np.uint32(31)).astype(np.uint8)).view(np.int64)


def cells_of(first: np.ndarray) -> np.ndarray:
    """The cells of a text: two orders' first shingles and the number of the pair, mixed into one number."""
    one, two = first[: 2 * CELLS].astype(np.uint64).reshape(-1, 2).T
    return ((one << np.uint64(32) | two) ^ np.arange(CELLS, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)).view(np.int64)


def neighbours(classes: DataFrame, least: float) -> DataFrame:
    """(u, v): forest of links between distinct fingerprints that meet at an anchor, or whose sketches meet at a cell."""
    fps = classes.select("fp").distinct()
    prints = classes.select("fp", "n", *SKETCH, "cells").dropDuplicates(["fp", "n", *SKETCH])
    cells = prints.select(F.explode("cells").alias("cell"), F.lit(True).alias("is_home"), "fp", "n", *SKETCH)

    def linked(columns: list[np.ndarray], one: list) -> np.ndarray:
        (_, n, *bits), (_, size, *own) = columns, one
        near = np.minimum(n, size) >= least * np.maximum(n, size) - 1e-9
        return near & (sum(differing_bits(b, o).astype(np.int32) for b, o in zip(bits, own, strict=True)) <= NEAR_BITS)

    return links(fps).unionByName(links_in_cells(cells, linked, BLOCK_PRINTS))


def shared_counts(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of the pairwise intersections of sets, by products of their indicator matrices, some columns at a time."""
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, column, uses = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    place = np.cumsum(uses > 1) - 1
    shared = uses[column] > 1
    owner, column = owner[shared], place[column[shared]]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    out = np.zeros((len(sets), len(sets)), np.float32)
    width = int(column[-1]) + 1 if column.size else 0
    for a in range(0, width, _COLUMNS):
        x, y = np.searchsorted(column, [a, a + _COLUMNS])
        held = np.zeros((len(sets), min(_COLUMNS, width - a)), np.float32)
        held[owner[x:y], column[x:y] - a] = 1
        out += held @ held.T
    out[np.diag_indices(len(sets))] = [len(s) for s in sets]
    return out


def _alike(cids: np.ndarray, sets: list[np.ndarray], least: float) -> tuple[np.ndarray, np.ndarray]:
    """Forest of the pairs of sets whose Jaccard similarity is at least ``least``, as (cid, cid)."""
    sizes = np.array([len(s) for s in sets], np.float64)
    both = shared_counts(sets)
    alike = both >= least * (sizes[:, None] + sizes[None, :] - both) - 1e-9
    forest = Forest(len(cids))
    for i, j in zip(*(x.tolist() for x in np.nonzero(np.triu(alike, 1))), strict=True):
        forest.join(i, j)
    u, v = forest.links()
    return cids[u], cids[v]


def _verified(dealt: DataFrame, least: float) -> DataFrame:
    """(u, v) of rows (pair, cluster, i, j, cid, s): all sets with equal first columns are compared."""
    keys = ["pair", "cluster", "i", "j"]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        now, cids, sets = None, [], []

        def settled() -> pd.DataFrame:
            u, v = _alike(np.array(cids, np.int64), sets, least)
            return pd.DataFrame({"u": u, "v": v})

        for frame in frames:
            for *at, cid, s in zip(*(frame[k].tolist() for k in keys), frame["cid"].tolist(), frame["s"], strict=True):
                if at != now:
                    if len(cids) > 1:
                        yield settled()
                    now, cids, sets = at, [], []
                cids.append(cid)
                sets.append(np.asarray(s, np.int64))
        if len(cids) > 1:
            yield settled()

    return dealt.repartition("pair").sortWithinPartitions(*keys).mapInPandas(run, "u bigint, v bigint").distinct()


def similar_text_groups(docs: DataFrame, words: int = 5, least: float = 0.8, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(digest, first_id, root): every distinct text with its smallest id and its component.

    Links are pairs of distinct texts with a Jaccard similarity of at least ``least``, compared in full where
    they are neighbours; components are closed over them. Null and empty texts are alike.
    ``first_id`` is null where no row of the text has an id. An empty table gives an empty result.
    """
    docs = docs.select(key, text, text_digest(text).alias("digest"))

    def sketched(texts: list[str]) -> dict[str, list]:
        out: dict[str, list] = {c: [] for c in ("fp", "n", "cells", *SKETCH)}
        for t in texts:
            h = shingle_hashes(t, words)
            s = shingle_set(h)
            out["fp"].append(majority_bits(h))
            out["n"].append(len(s))
            first = first_shingles(s)
            out["cells"].append(cells_of(first))
            for c, bits in zip(SKETCH, sketch(first).tolist(), strict=True):
                out[c].append(bits)
        return out | {"fp": np.array(out["fp"], np.uint64).view(np.int64)}

    schema = f"fp bigint, n int, cells array<bigint>, {', '.join(f'{c} bigint' for c in SKETCH)}"
    rows = map_texts(docs, [key, "digest"], text, schema, sketched)
    classes = rows.groupBy("digest").agg(F.min(key).alias("first_id"), *(F.first(c).alias(c) for c in ("fp", "n", "cells", *SKETCH)))
    classes = cut(classes.withColumn("cid", F.monotonically_increasing_id()))
    near = components(neighbours(classes, least)).withColumnsRenamed({"node": "fp", "root": "cluster"})
    # Whatever Spark takes their sizes for, these tables grow with the input: no join sends one through the driver.
    held = classes.drop("cells", *SKETCH).join(near.hint("merge"), "fp", "left").withColumn("cluster", F.coalesce("cluster", "fp"))
    sizes = held.groupBy("cluster").agg(F.ceil(F.count("*") / BLOCK_SETS).cast("int").alias("parts"), F.count("*").alias("of"))
    members = cut(held.join(sizes.where("of > 1").drop("of").hint("merge"), "cluster"))
    release(docs.sparkSession)
    same = F.col("digest").eqNullSafe(F.col("_digest")) & F.col(key).eqNullSafe(F.col("_id"))
    asked = members.select("cid", "cluster", "parts", F.col("digest").alias("_digest"), F.col("first_id").alias("_id"))
    found = docs.join(asked.hint("merge"), same).select("cid", "cluster", "parts", text)
    sets = map_texts(
        found, ["cid", "cluster", "parts"], text, "s array<bigint>", lambda texts: {"s": [shingle_set(shingle_hashes(t, words)) for t in texts]}
    )
    own = F.pmod(F.xxhash64("cid"), F.col("parts")).cast("int")
    blocks = F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda k: F.struct(F.least(own, k).alias("i"), F.greatest(own, k).alias("j")))
    dealt = sets.select("cluster", "cid", "s", F.explode(blocks).alias("b")).select(
        F.xxhash64("cluster", "b.i", "b.j").alias("pair"), "cluster", "b.i", "b.j", "cid", "s"
    )
    roots = components(_verified(dealt, least))
    return classes.select("digest", "first_id", "cid").join(roots.withColumnRenamed("node", "cid").hint("merge"), "cid", "left").select(
        "digest", "first_id", F.coalesce("root", "cid").alias("root")
    )
