"""Arrow plumbing shared by the operators that run Python on executors."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.types import StructType

from spanfocus.session import ship_package

#: Characters of text that one working block holds; a longer single text makes a block of its own.
BLOCK_CHARS = 2_000_000


def text_blocks(batches: Iterable[pa.RecordBatch], text: str = "text") -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """Slices of the batches with about ``BLOCK_CHARS`` of text each; a null text reads as empty."""
    for batch in batches:
        column = batch.column(batch.schema.get_field_index(text))
        start = held = 0
        texts: list[str] = []
        for i in range(batch.num_rows):
            value = column[i].as_py() or ""
            if texts and held + len(value) > BLOCK_CHARS:
                yield batch.slice(start, len(texts)), texts
                start, held, texts = i, 0, []
            texts.append(value)
            held += len(value)
        if texts:
            yield batch.slice(start, len(texts)), texts


def map_texts(
    df: DataFrame, keys: list[str], text: str, schema: str | StructType, fn: Callable[[list[str]], dict[str, list]]
) -> DataFrame:
    """Rows (keys, text) to (keys, new columns); ``fn`` gets the texts of a block and returns its columns.

    The keys, of which the text may be one, keep their values and types; other columns are not read.
    """
    keys = list(dict.fromkeys(keys))
    made = StructType.fromDDL(schema) if isinstance(schema, str) else schema
    out = StructType([df.schema[k] for k in keys] + list(made.fields))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_type

        types = {f.name: to_arrow_type(f.dataType, prefers_large_types=False) for f in made.fields}
        for block, texts in text_blocks(batches, text):
            columns = fn(texts)
            arrays = [block.column(block.schema.get_field_index(k)) for k in keys]
            arrays += [pa.array(columns[n], type=t) for n, t in types.items()]
            yield pa.RecordBatch.from_arrays(arrays, names=[*keys, *types])
            pa.default_memory_pool().release_unused()

    ship_package(df.sparkSession)
    return df.select(*dict.fromkeys([*keys, text])).mapInArrow(run, out)
