"""Lexical attention calculator: exact softmax attention over one-hot token states.

A query token matches an equal key token with logit g = beta * idf and any other key with logit 0. Then a
row's softmax denominator is the number of keys plus (exp(g) - 1) for every equal one, and the mass on a
span is a dense part, the same for all spans, plus a sparse part where the spans share tokens. Two forms:
Catalyst long form, and an Arrow kernel that scores whole documents in one pass without a shuffle.
It sees verbatim repetition only; for semantic dependency use the trained or an external calculator.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from spanfocus.functions.text import token_hashes, tokens_of
from spanfocus.geometry import Geometry, cost_of
from spanfocus.operators.focus import VARIANTS, fold_matrix
from spanfocus.session import cut, ship_package
from spanfocus.sources.tables import require

#: Largest vocabulary whose weights are broadcast; those of a larger one are joined to the rows that hold them.
MAX_EXACT = 2_000_000


def document_frequency(df: DataFrame, text: str = "text", mode: str = "space") -> DataFrame:
    """(token, df): in how many documents a token occurs, over all documents."""
    distinct = F.array_distinct(tokens_of(text, mode))
    return require(df, text).select(F.explode(distinct).alias("token")).groupBy("token").agg(F.count("*").alias("df"))


def token_weights(df: DataFrame, beta: float = 1.0, text: str = "text", mode: str = "space") -> DataFrame:
    """(token, weight): exp(beta * idf) - 1 with idf = ln((1 + documents) / (1 + df))."""
    gain = F.lit(float(beta)) * F.log(F.lit(1.0 + df.count()) / (1 + F.col("df")))
    return document_frequency(df, text, mode).select("token", (F.exp(gain) - 1).alias("weight"))


def pair_focus(samples: DataFrame, weights: DataFrame, geometry: Geometry, causal: bool = True, all_pairs: bool = False) -> DataFrame:
    """(doc_id, j, i, pair_focus) in long form, by Catalyst operators.

    ``causal`` False lets a row see its whole own span, as the block formula literally says. ``all_pairs``
    gives every i <= j instead of the geometry's rows and columns (then a row sums to the span length).
    """
    span, g = geometry.span, geometry
    base = samples.select("doc_id", F.posexplode("tokens").alias("pos", "token")).withColumn("s", F.floor(F.col("pos") / span).cast("int"))
    counts = base.groupBy("doc_id", "token", "s").agg(F.count("*").alias("c"))
    rows = base
    if causal:
        seen = F.row_number().over(Window.partitionBy("doc_id", "token").orderBy("pos"))
        rows = rows.withColumn("seen", seen).withColumn("keys", F.col("pos") + 1)
    else:
        upto = Window.partitionBy("doc_id", "token").orderBy("s").rangeBetween(Window.unboundedPreceding, 0)
        rows = rows.withColumn("seen", F.count("*").over(upto)).withColumn("keys", (F.col("s") + 1) * span)
    if not all_pairs:
        first = g.first_row + g.col_phase
        rows = rows.where((F.col("s") >= first) & ((F.col("s") - first) % g.col_stride == 0))
    rows = rows.join(weights, "token", "left").withColumn("weight", F.coalesce("weight", F.lit(0.0)))
    rows = rows.withColumn("inv", 1 / (F.col("keys") + F.col("seen") * F.col("weight")))
    own = None
    if all_pairs and causal:
        # Of its own span a row sees the keys up to itself, and the equal ones among them.
        same = F.row_number().over(Window.partitionBy("doc_id", "token", "s").orderBy("pos"))
        mine = rows.withColumn("same", same).withColumn("visible", F.col("pos") - F.col("s") * span + 1)
        own = mine.groupBy("doc_id", F.col("s").alias("j")).agg(
            F.sum((F.col("visible") + F.col("same") * F.col("weight")) * F.col("inv")).alias("pair_focus")
        )
    rows = rows.select("doc_id", "token", F.col("s").alias("j"), "inv", "weight")
    low = g.skip_first + g.row_phase
    if all_pairs:
        wanted = F.col("i") < F.col("j") if causal else F.col("i") <= F.col("j")
        cols = F.sequence(F.lit(0), F.col("j"))
    else:
        last = F.col("j") - g.skip_near - 1
        wanted = (F.col("i") >= low) & (F.col("i") <= last) & ((F.col("i") - low) % g.row_stride == 0)
        cols = F.when(last >= low, F.sequence(F.lit(low), last, F.lit(g.row_stride))).otherwise(F.array().cast("array<int>"))
    dense = rows.groupBy("doc_id", "j").agg((F.sum("inv") * span).alias("dense"))
    grid = dense.withColumn("i", F.explode(cols))
    if own is not None:
        grid = grid.where("i < j")
    shared = rows.join(counts.withColumnRenamed("s", "i"), ["doc_id", "token"]).where(wanted)
    sparse = shared.groupBy("doc_id", "j", "i").agg(F.sum(F.col("c") * F.col("weight") * F.col("inv")).alias("sparse"))
    joined = grid.join(sparse, ["doc_id", "j", "i"], "left")
    out = joined.select("doc_id", "j", "i", (F.col("dense") + F.coalesce("sparse", F.lit(0.0))).alias("pair_focus"))
    return out if own is None else out.unionByName(own.select("doc_id", "j", F.col("j").alias("i"), "pair_focus"))


@dataclass
class WeightTable:
    """Token weights for the kernel: sorted 64-bit hashes with weights, or a fixed number of slots."""

    hashes: np.ndarray
    weights: np.ndarray
    slots: int = 0

    def of(self, h: np.ndarray) -> np.ndarray:
        if self.slots:
            return self.weights[h.view(np.uint64) % np.uint64(self.slots)]
        if not self.hashes.size:
            return np.zeros(h.shape)
        at = np.minimum(np.searchsorted(self.hashes, h), self.hashes.size - 1)
        return np.where(self.hashes[at] == h, self.weights[at], 0.0)


@dataclass
class WeightRows:
    """Token weights (h, weight) that stay a table, for any vocabulary."""

    rows: DataFrame

    def gathered(self) -> WeightTable:
        """The same as one table, 16 bytes a token: for rows that cannot be joined twice, as a stream's."""
        return WeightTable(*_sorted(self.rows.toArrow()))


def _sorted(made: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    h = made["h"].to_numpy().astype(np.int64)
    order = np.argsort(h)
    return h[order], made["weight"].to_numpy().astype(np.float64)[order]


Weights = WeightTable | WeightRows


def gathered(table: Weights) -> WeightTable:
    return table.gathered() if isinstance(table, WeightRows) else table


def weight_table(df: DataFrame, beta: float = 1.0, text: str = "text", mode: str = "space", max_exact: int = MAX_EXACT, slots: int = 0) -> Weights:
    """The kernel's weights: broadcast up to ``max_exact`` tokens, beyond that a table to be joined.

    With ``slots`` a larger vocabulary is folded into so many numbers instead. In a slot the document
    frequencies of its tokens add up, which lowers their weights a little.
    """
    hashed = F.array_distinct(token_hashes(tokens_of(text, mode)))
    counts = df.select(F.explode(hashed).alias("h")).groupBy("h").agg(F.count("*").alias("df")).persist()
    try:
        n_docs = df.count()
        large = counts.count() > max_exact
        if large and not slots:
            w = F.exp(F.lit(float(beta)) * F.log(F.lit(1.0 + n_docs) / (1 + F.least("df", F.lit(n_docs))))) - 1
            return WeightRows(cut(counts.select("h", w.alias("weight"))))
        if large:
            # Signed hashes shifted to unsigned order modulo a power of two keep their low bits.
            counts_by_slot = counts.groupBy(F.pmod("h", F.lit(slots)).alias("h")).agg(F.sum("df").alias("df"))
            rows = counts_by_slot.toArrow()
        else:
            rows = counts.toArrow()
    finally:
        counts.unpersist()
    h, n = rows["h"].to_numpy().astype(np.int64), np.minimum(rows["df"].to_numpy().astype(np.float64), n_docs)
    w = np.exp(beta * np.log((1 + n_docs) / (1 + n))) - 1
    if large:
        table = np.zeros(slots)
        table[h] = w
        return WeightTable(np.zeros(0, np.int64), table, slots)
    order = np.argsort(h)
    return WeightTable(h[order], w[order])


#: The weights of the k-th row of a batch with the hashes ``h``.
Lookup = Callable[[pa.RecordBatch, int, np.ndarray], np.ndarray]


def with_weights(rows: DataFrame, table: Weights) -> tuple[DataFrame, Lookup]:
    """``rows`` (with token hashes ``h``) and what gives their weights inside a task.

    A broadcast table leaves the rows as they are. Joined weights come as two more columns, the hashes of the
    row and their weights. Rows meet them by a digest of their hashes, so ids may be null or repeat.
    """
    spark = rows.sparkSession
    ship_package(spark)
    if isinstance(table, WeightRows) and rows.isStreaming:
        table = table.gathered()
    if isinstance(table, WeightTable):
        shared = spark.sparkContext.broadcast(table)
        return rows, lambda batch, k, h: shared.value.of(h)
    keyed = rows.withColumn("row_", F.unhex(F.md5(F.array_join(F.col("h").cast("array<string>"), ","))))
    held = keyed.select("row_", F.array_distinct("h").alias("h")).dropDuplicates(["row_"]).select("row_", F.explode("h").alias("h"))
    own = held.join(table.rows, "h").groupBy("row_").agg(F.sort_array(F.collect_list(F.struct("h", "weight"))).alias("own_"))
    made = keyed.join(own, "row_", "left").withColumns({"own_h_": F.col("own_.h"), "own_weight_": F.col("own_.weight")})

    def look(batch: pa.RecordBatch, k: int, h: np.ndarray) -> np.ndarray:
        own_h, own_weight = (batch.column(c)[k].values for c in ("own_h_", "own_weight_"))
        if own_h is None:
            return np.zeros(h.shape)
        return WeightTable(own_h.to_numpy(zero_copy_only=False), own_weight.to_numpy(zero_copy_only=False)).of(h)

    return made.drop("row_", "own_"), look


def focus_matrix(h: np.ndarray, e: np.ndarray, geometry: Geometry, rows: Sequence[int], causal: bool = True) -> np.ndarray:
    """Mass of each query row j in ``rows`` on every span: (spans, rows). ``h`` and ``e``: hash and weight by position."""
    span, n = geometry.span, geometry.n_spans
    codes = np.unique(h, return_inverse=True)[1]
    of_span = np.repeat(np.arange(n), span)
    counts = np.bincount(of_span * (codes.max() + 1) + codes, minlength=n * (codes.max() + 1)).reshape(n, -1)
    at = (np.asarray(rows)[:, None] * span + np.arange(span)).ravel()
    if causal:
        order = np.argsort(codes, kind="stable")
        first = np.searchsorted(codes[order], codes[order])
        seen = np.empty(len(codes), np.int64)
        seen[order] = np.arange(len(codes)) - first + 1
        seen, keys = seen[at], at + 1
    else:
        seen = np.cumsum(counts, axis=0)[of_span[at], codes[at]]
        keys = (of_span[at] + 1) * span
    inv = 1 / (keys + seen * e[at])
    by_row = (counts[:, codes[at]] * (e[at] * inv)).reshape(n, len(rows), span).sum(axis=2)
    mass = by_row + span * inv.reshape(len(rows), span).sum(axis=1)
    for k, j in enumerate(rows):
        mass[j + 1 :, k] = 0.0
        if causal:
            mass[j, k] = span - mass[:j, k].sum()  # a row sums to the span length; of its own span it sees a part
    return mass


def score_documents(
    samples: DataFrame, table: Weights, geometry: Geometry, variants: Sequence[str] = ("full",),
    strides: Sequence[tuple[int, int]] | None = None, causal: bool = True, ddof: int = 0, sigma_over: str = "used",
) -> DataFrame:
    """One pass from tokens to scores: (doc_id, domain, n_tokens, a column per variant and stride, counters).

    Columns are named ``<variant>_<row stride>_<column stride>``; the geometry's own strides give the plain
    variant's name as well. ``samples`` is (doc_id, domain, n_tokens, tokens) cut to the geometry's length.
    No shuffle, unless the weights are joined: tokens are hashed in the JVM and travel to the kernel as numbers.
    """
    unknown = [v for v in variants if v not in VARIANTS]
    if unknown:
        raise ValueError(f"unknown variants {unknown}; known: {', '.join(VARIANTS)}")
    settings = list(strides or [(geometry.row_stride, geometry.col_stride)])
    geometries = [geometry.with_strides(*s) for s in settings]
    names = [f"{v}_{a}_{b}" for a, b in settings for v in variants]
    rows = sorted({j for g in geometries for j in g.rows()})
    cost = cost_of(geometries[0])
    schema = StructType(samples.select("doc_id", "domain", "n_tokens").schema.fields)
    for n in names:
        schema = schema.add(n, "double")
    for n in ("rows_used", "pairs_used", "logits"):
        schema = schema.add(n, "long")
    weighted, weights_of = with_weights(samples.select("doc_id", "domain", "n_tokens", token_hashes("tokens").alias("h")), table)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = [[] for _ in names]
            hashes = batch.column(3)
            for k in range(batch.num_rows):
                h = hashes[k].values.to_numpy(zero_copy_only=False)
                mass = focus_matrix(h, weights_of(batch, k, h), geometry, rows, causal) if rows else np.zeros((geometry.n_spans, 0))
                made = [fold_matrix(mass, rows, g, v, ddof, sigma_over) for g in geometries for v in variants]
                for column, x in zip(values, made, strict=True):
                    column.append(x)
            counters = [pa.array([cost[n]] * batch.num_rows, pa.int64()) for n in ("rows", "pairs", "logits")]
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:3], *(pa.array(v, pa.float64()) for v in values), *counters], names=schema.fieldNames()
            )

    return weighted.mapInArrow(run, schema)


def pair_focus_kernel(samples: DataFrame, table: Weights, geometry: Geometry, causal: bool = True) -> DataFrame:
    """(doc_id, j, i, pair_focus) by the kernel: the same values as :func:`pair_focus`."""
    weighted, weights_of = with_weights(samples.select("doc_id", token_hashes("tokens").alias("h")), table)
    rows = geometry.rows()
    js = np.array([j for j in rows for _ in geometry.cols(j)], np.int32)
    at = np.array([k for k, j in enumerate(rows) for _ in geometry.cols(j)], np.int64)
    cols = np.array([i for j in rows for i in geometry.cols(j)], np.int32)
    schema = StructType([samples.schema["doc_id"]]).add("j", "integer").add("i", "integer").add("pair_focus", "double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                h = batch.column(1)[k].values.to_numpy(zero_copy_only=False)
                mass = focus_matrix(h, weights_of(batch, k, h), geometry, rows, causal)
                yield pa.RecordBatch.from_arrays(
                    [pa.repeat(batch.column(0)[k], len(js)), pa.array(js), pa.array(cols), pa.array(mass[cols, at])], names=schema.fieldNames()
                )

    return weighted.mapInArrow(run, schema)
