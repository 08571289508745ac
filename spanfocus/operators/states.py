"""Attention calculators over explicit query and key states: given ones, or those of an external model."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from spanfocus.geometry import Geometry
from spanfocus.operators.focus import fold_matrix
from spanfocus.session import ship_package

#: tokens to query and key states, each (heads, length, dim); layers come as more heads.
StateModel = Callable[[list[str]], tuple[np.ndarray, np.ndarray]]


def state_focus(q: np.ndarray, k: np.ndarray, geometry: Geometry, rows: Sequence[int], causal: bool = True, scale: float | None = None) -> np.ndarray:
    """Attention mass of each row span on every span, (spans, rows), by a dense softmax row block by row block.

    ``q`` and ``k`` are (length, dim). Memory is one block of span x keys, never length x length.
    """
    span, n = geometry.span, geometry.n_spans
    scale = q.shape[-1] ** -0.5 if scale is None else scale
    out = np.zeros((n, len(rows)))
    for at, j in enumerate(rows):
        a, b = j * span, (j + 1) * span
        logits = (q[a:b] @ k[:b].T).astype(np.float64) * scale
        if causal:
            logits[:, a:][np.triu_indices(span, 1)] = -np.inf
        mass = np.exp(logits - logits.max(axis=1, keepdims=True))
        mass /= mass.sum(axis=1, keepdims=True)
        out[: j + 1, at] = mass.reshape(span, j + 1, span).sum(axis=(0, 2))
    return out


def merge_heads(q: np.ndarray, k: np.ndarray, geometry: Geometry, rows: Sequence[int], causal: bool = True, heads: str | Sequence[int] = "mean") -> np.ndarray:
    """One mass matrix from (heads, length, dim) states: mean or max over heads, the last, or listed ones averaged."""
    chosen = range(len(q)) if heads in ("mean", "max") else [len(q) - 1] if heads == "last" else list(heads)
    each = np.array([state_focus(q[h], k[h], geometry, rows, causal) for h in chosen])
    return each.max(axis=0) if heads == "max" else each.mean(axis=0)


def label_samples(vectors: DataFrame, geometry: Geometry, group: str = "label", key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(group, states): the first vectors of each group by id, as one sample; short groups are dropped.

    The length limit is the sample's; ids are cut to it before the vectors are gathered.
    """
    from pyspark.sql import Window

    place = F.row_number().over(Window.partitionBy(group).orderBy(key))
    firsts = vectors.where(F.col(vector).isNotNull()).withColumn("place", place).where(F.col("place") <= geometry.length)
    rows = firsts.groupBy(group).agg(F.sort_array(F.collect_list(F.struct("place", F.col(vector).alias("v")))).alias("s"))
    return rows.where(F.size("s") == geometry.length).select(group, F.transform("s", lambda x: x["v"]).alias("states"))


def _matrix(value: pa.Scalar) -> np.ndarray:
    inner = value.values
    return inner.flatten().to_numpy(zero_copy_only=False).reshape(len(inner), -1)


def pair_focus_states(samples: DataFrame, geometry: Geometry, key: str = "label", states: str = "states", causal: bool = True) -> DataFrame:
    """(key, j, i, pair_focus) where query and key states are the given vectors themselves."""
    ship_package(samples.sparkSession)
    rows = geometry.rows()
    pairs = [(j, at, i) for at, j in enumerate(rows) for i in geometry.cols(j)]
    js, at, cols = (np.array([p[c] for p in pairs], np.int32) for c in range(3))
    schema = StructType([samples.schema[key], *StructType.fromDDL("j int, i int, pair_focus double").fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                x = _matrix(batch.column(1)[k])
                mass = state_focus(x, x, geometry, rows, causal)
                yield pa.RecordBatch.from_arrays(
                    [pa.repeat(batch.column(0)[k], len(js)), pa.array(js), pa.array(cols), pa.array(mass[cols, at])], names=schema.fieldNames()
                )

    return samples.select(key, states).mapInArrow(run, schema)


def score_with_model(
    samples: DataFrame, model: StateModel, geometry: Geometry, variants: Sequence[str] = ("full",), causal: bool = True, heads: str | Sequence[int] = "mean"
) -> DataFrame:
    """(doc_id, domain, n_tokens, a column per variant) by any model of query and key states.

    This is the hook for an external model; the callable is sent to the workers as it is.
    """
    ship_package(samples.sparkSession)
    rows = geometry.rows()
    schema = StructType(samples.select("doc_id", "domain", "n_tokens").schema.fields)
    for v in variants:
        schema = schema.add(v, "double")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            made: list[list[float]] = [[] for _ in variants]
            for tokens in batch.column(3).to_pylist():
                mass = merge_heads(*model(tokens), geometry, rows, causal, heads)
                for column, v in zip(made, variants, strict=True):
                    column.append(fold_matrix(mass, rows, geometry, v))
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], *(pa.array(m, pa.float64()) for m in made)], names=schema.fieldNames())

    return samples.select("doc_id", "domain", "n_tokens", "tokens").mapInArrow(run, schema)


def focus_with_model(samples: DataFrame, model: StateModel, geometry: Geometry, key: str = "doc_id", causal: bool = True, heads: str | Sequence[int] = "mean") -> DataFrame:
    """(key, j, i, pair_focus) by any model of query and key states."""
    ship_package(samples.sparkSession)
    rows = geometry.rows()
    pairs = [(j, at, i) for at, j in enumerate(rows) for i in geometry.cols(j)]
    js, at, cols = (np.array([p[c] for p in pairs], np.int32) for c in range(3))
    schema = StructType([samples.schema[key], *StructType.fromDDL("j int, i int, pair_focus double").fields])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k, tokens in enumerate(batch.column(1).to_pylist()):
                mass = merge_heads(*model(tokens), geometry, rows, causal, heads)
                yield pa.RecordBatch.from_arrays(
                    [pa.repeat(batch.column(0)[k], len(js)), pa.array(js), pa.array(cols), pa.array(mass[cols, at])], names=schema.fieldNames()
                )

    return samples.select(key, "tokens").mapInArrow(run, schema)
